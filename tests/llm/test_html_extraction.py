import random
import time

import pytest
from pyspark.sql import functions as F

from topfd.llm import html_extraction as H

ARTICLE = "<article><h1>Title &amp; more</h1><p><b>One\n two.<br><p>Three&nbsp;four &lt;x&gt; &#233;</p></article>"
WANT = "Title & more\nOne two.\nThree four <x> é"
CASES = {
    "plain": (ARTICLE, WANT),
    "around": (f"<html><head><title>no</title><style>p{{}}</style></head><body><header>Site</header><nav><ul><li>a<li>b</ul></nav><div class='ad'>Buy</div>{ARTICLE}<aside>side</aside><footer>&copy; x</footer>", WANT),
    "script": (f"<script>var t='</p><article>no';</script>{ARTICLE}<script>if (a<b) {{}}", WANT),
    "comment": (f"<!-- <p>no</p> -->{ARTICLE}<!-- open", WANT),
    "form inside": ("<article><p>a</p><form><p>mail</p><input><button>go</button></form><p>b</p></article>", "a\nb"),
    "reader comments": ("<article><p>" + "text " * 30 + "</p></article><section class='comments'><article><p>nice " + "very " * 40 + "</p></article></section>", ("text " * 30).strip()),
    "comments inside": ("<article><p>a</p><div id='comments'><p>b</p></div><p>c</p></article>", "a\nc"),
    "own header": ("<article><header><h1>T</h1></header><p>a</p></article>", "T\na"),
    "main": ("<nav>n</nav><main><p>a</p><p>b</p></main><div class='footer'>after</div>", "a\nb"),
    "bare": ("<p>a</p><p hidden>h</p><p style='display: none'>i</p><p>b", "a\nb"),
    "after main": ("<nav>n</nav><main><p>a</p></main><p>after</p>", "a\nafter"),
    "above": ("<h1>Headline</h1><article><p>a</p></article><section><p>unshared</p></section>", "Headline\na\nunshared"),
    "two articles": ("<article><p>" + "long " * 50 + "</p></article><article><p>short</p></article>", ("long " * 50).strip() + "\nshort"),
    "classes inside": ("<article><p class='share-prices'>a</p><p id='alert'>b</p><div class='related'>c</div><div class='comments'>no</div><ul class='social work'><li>d</ul></article>", "a\nb\nc\nd"),
    "formula": ("<article><p>x <math><mi>y</mi></math> <object>z</object><noscript>w</noscript></article>", "x y zw"),
    "slash closes no script": ("<script src='a.js'/>code</script><p>a</p>", "a"),
    "open quote": ("<p title=\"x>a</p><p>b</p>", "a\nb"),
    "no end": ("<p>a</p><a x <b y", "a\n<a x <b y"),
    "notice": ("<article><p>a</p><div class='cookie-notice'>we use</div></article>", "a"),
    "unclosed": ("<article><p>a<p>b<div>c<p>d</article><footer>f", "a\nb\nc\nd"),
    "void and case": ("<ARTICLE><P>a<IMG SRC='x>y'>b<HR>c</P></ARTICLE>", "ab\nc"),
    "less than": ("<article><p>1 < 2 and a<b c>d</p></article>", "1 < 2 and ad"),
    "list": ("<article><ul><li>x<li>y</ul><table><tr><td>1<td>2</table></article>", "x\ny\n1\n2"),
    "text only": ("just text\n here", "just text here"),
    "empty": ("", ""),
    "null": (None, ""),
}


@pytest.mark.parametrize("name", CASES)
def test_main_text(name):
    page, want = CASES[name]
    assert H.main_text(H.lines_of(page), None)[0] == want


def test_shared_lines_are_a_longest_common_subsequence():
    rng = random.Random(1)
    for _ in range(400):
        a, b = ([rng.choice("abcde") for _ in range(rng.randint(0, 14))] for _ in range(2))
        table = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                table[i + 1][j + 1] = table[i][j] + 1 if x == y else max(table[i][j + 1], table[i + 1][j])
        found = H.shared_lines(a, b)
        assert len(found) == table[-1][-1]
        rest = iter(b)
        assert all(a[i] in rest for i in sorted(found))


@pytest.mark.parametrize("unit", ["<a x ", "<a x='", '<a x="<b>"', "<b>", "<p><b>", "</i>", "<script>", "</script ", "<!-- ", "<hr", "<a xxxx", "<p a", "<td><b>", "<li>", "<a b=c ", "<x", "<a '\"", "&", "<p><td><b><hr>"])
def test_a_long_page_is_read_in_linear_time(unit):
    for page in (unit * (1_000_000 // len(unit)), "<p>" + "<a " + "y" * 1_000_000 + ">", "<b>" * 150_000 + "<hr>" * 150_000 + "</u>" * 50_000):
        began = time.perf_counter()
        H.lines_of(page)
        assert time.perf_counter() - began < 5


def test_halved_alignments_are_as_long(monkeypatch):
    rng = random.Random(3)
    for _ in range(300):
        a, b = ([rng.choice("abcd") for _ in range(rng.randint(0, 20))] for _ in range(2))
        monkeypatch.setattr(H, "CELLS", 1 << 28)
        whole = H.shared_lines(a, b)
        monkeypatch.setattr(H, "CELLS", 3)
        halved = H.shared_lines(a, b)
        assert len(halved) == len(whole)
        rest = iter(b)
        assert all(a[i] in rest for i in sorted(halved))


def _by_definition(rows):
    """The whole query over a list of pages: a quadratic search for the partner and a table for the alignment."""
    from urllib.parse import urlsplit

    def parts(url):
        if not url or "://" not in url:
            return "", ""
        u = urlsplit(url)
        return u.netloc.lower(), u.path

    lines = {k: H.lines_of(page) for k, (_, _, page) in enumerate(rows)}
    order = sorted(range(len(rows)), key=lambda k: (*parts(rows[k][1]), rows[k][0]))
    out = {}
    for place, k in enumerate(order):
        host, path = parts(rows[k][1])
        near = []
        for side in (order[:place][::-1], order[place + 1 :]):
            for q in side:
                if parts(rows[q][1])[0] != host:
                    break
                if [t for t, _ in lines[q]] != [t for t, _ in lines[k]]:
                    near.append(q)
                    break
        alike = lambda q: next((i for i, (x, y) in enumerate(zip(path, parts(rows[q][1])[1], strict=False)) if x != y), min(len(path), len(parts(rows[q][1])[1])))
        gone = 0
        if near:
            a, b = ([t for t, _ in lines[x]] for x in (k, max(near, key=alike)))
            gone = H.shared_lines(a, b)
        out[rows[k][0]] = "\n".join(t for i, (t, w) in enumerate(lines[k]) if w == H.ARTICLE or (w == H.PLAIN and (not near or i not in gone)))
    return out


def test_whole_query_equals_the_definition(spark, monkeypatch):
    rng = random.Random(9)
    word = lambda: rng.choice(["alpha", "beta", "gamma", "delta", "epsilon"])
    rows = []
    for i in range(120):
        around = [f"<p>{rng.choice(['Site', 'Top', 'News'])}</p>", f"<nav><a>{word()}</a></nav>"]
        body = "".join(f"<p>{word()} {word()}</p>" for _ in range(rng.randint(0, 4)))
        body = f"<article>{body}</article>" if rng.random() < 0.5 else body
        rows.append((i, f"http://h{rng.randrange(4)}.org/{rng.randrange(5)}/{rng.randrange(60):02}x{i}", "".join(around) + body + "<p>All rights</p>"))
    want = _by_definition(rows)
    df = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(4)
    for pages in (400, 20):
        monkeypatch.setattr(H, "PARTITION_PAGES", pages)
        got = H.extract(df).collect()
        assert {r["page_id"]: r["text"] for r in got} == want
        assert sum(r["n_shared"] for r in got) > 100


def test_nearest_pages_lose_what_they_share(spark):
    page = lambda body: f"<div><p>Our site</p><p>Follow us</p>{body}<p>All rights</p></div>"
    rows = [
        (1, "http://a.org/x/1", page("<p>first text</p>")),
        (2, "http://a.org/x/2", page("<p>second text</p><p>more</p>")),
        (3, "http://a.org/y/9", page("<p>third</p>")),
        (4, "http://b.org/x/1", page("<p>alone</p>")),
        (5, "http://c.org/1", page("<p>copy</p>")),
        (6, "http://c.org/2", page("<p>copy</p>")),
        (7, None, None),
        (8, "http://d.org/", ARTICLE),
        (8, "http://d.org/", ARTICLE),
    ]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("host", F.lit("clash")).withColumn("text", F.lit(1)).repartition(3)
    got = sorted((r["page_id"], r["url"], r["text"], r["n_chars"]) for r in H.extract(df.coalesce(1)).collect())
    by = {i: t for i, _, t, _ in got}
    whole = "Our site\nFollow us\n{}\nAll rights"
    assert by[1] == "first text" and by[2] == "second text\nmore" and by[3] == "third"
    assert by[4] == whole.format("alone") and by[5] == by[6] == whole.format("copy")
    assert by[7] == "" and by[8] == WANT and len(got) == 9
    assert all(n == len(t) for _, _, t, n in got)


def _site(n_copies):
    page = lambda body: f"<div><p>Our site</p><p>Follow us</p>{body}<p>All rights</p></div>"
    rows = [(1, "http://a.org/a", page("<p>first</p>"))]
    rows += [(10 + i, f"http://a.org/c/{i:03}", page("<p>copy</p>")) for i in range(n_copies)]
    rows += [(900, "http://a.org/z", page("<p>last</p>"))] * 3 + [(None, "http://b.org/1", page("<p>b</p>")), (901, "http://b.org/2", page("<p>c</p>"))]
    return rows, {1: "first", 900: "last", None: "b", 901: "c"}


def test_copies_are_differenced_against_the_nearest_other_page(spark, monkeypatch):
    """Runs of copies in one range, and over several whole ranges; hosts that a cut divides."""
    rows, want = _site(40)
    df = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    for pages in (400, 10, 3):
        monkeypatch.setattr(H, "PARTITION_PAGES", pages)
        got = [(r["page_id"], r["text"]) for r in H.extract(df).collect()]
        assert len(got) == len(rows)
        assert {t for i, t in got if i not in want} == {"copy"}, pages
        assert all(t == want[i] for i, t in got if i in want), pages


def test_every_number_of_ranges_gives_the_same_texts(spark, monkeypatch):
    rng = random.Random(5)
    body = lambda: "".join(f"<p>{rng.choice('abcdef')}</p>" for _ in range(rng.randint(0, 3)))
    rows = [(i // 2, f"http://h{rng.randrange(3)}.org/{rng.randrange(4)}/{rng.randrange(30)}", f"<p>top</p>{body()}<p>end</p>") for i in range(150)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    found = []
    for pages, cuts in ((400, 128), (12, 128), (9, 3)):
        monkeypatch.setattr(H, "PARTITION_PAGES", pages)
        monkeypatch.setattr(H, "CUTS", cuts)
        found.append(sorted(map(tuple, H.extract(df).collect()), key=str))
    assert len(found[0]) == 150 and found[0] == found[1] == found[2]


def test_empty_table(spark):
    assert H.extract(spark.createDataFrame([], "page_id long, url string, html string")).collect() == []
