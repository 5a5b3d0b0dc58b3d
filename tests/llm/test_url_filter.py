import re

import pytest
from pyspark.sql import functions as F

from topfd.llm import url_filter as U

URLS = [
    ("http://a.net", "a.net", "", None, "allow"),
    ("http://a.net/", "a.net", "/", "net/", "block"),
    ("HTTP://WWW.Example.NET/en/1?x#y", "www.example.net", "/en/1", "example.net/en/", "allow"),
    ("https://example.net/EN/1", "example.net", "/EN/1", "net/", "block"),
    ("https://myexample.com/de/1", "myexample.com", "/de/1", None, "allow"),
    ("https://x.example.com/de/1", "x.example.com", "/de/1", "example.com/de/", "block"),
    ("https://x.org/fr/1#a?b", "x.org", "/fr/1", "org/fr/", "allow"),
    ("https://cheap-pills.example.org/fr/1", "cheap-pills.example.org", "/fr/1", "org/fr/", "allow"),
    ("https://m.cheap-pills.example.org/en/1", "m.cheap-pills.example.org", "/en/1", None, "block"),
    ("https://cheap-pills2.example.org/en/1", "cheap-pills2.example.org", "/en/1", None, "allow"),
    ("https://ok.example.org/cheap-pills.html", "ok.example.org", "/cheap-pills.html", None, "allow"),
    ("no scheme.net/en/", "", "", None, "allow"),
    ("a://b://c.net/x", "b:", "//c.net/x", None, "allow"),
    ("https://ÄB.net/ä", "Äb.net", "/ä", "net/", "block"),
    ("https://x.net\n/a", "x.net\n", "/a", None, "allow"),
    ("https://foo\nbar.net/a", "foo\nbar.net", "/a", "net/", "block"),
    ("https://foo\ncheap-pills.org/a", "foo\ncheap-pills.org", "/a", None, "allow"),
    ("https://foo\nx.cheap-pills.org/a", "foo\nx.cheap-pills.org", "/a", None, "block"),
    ("https://", "", "", None, "allow"),
    ("", "", "", None, "allow"),
    (None, "", "", None, "allow"),
]


def test_rules_and_parts(spark):
    df = spark.createDataFrame([(i, u[0], "<p>") for i, u in enumerate(URLS)], "page_id long, url string, html string").withColumn("host", F.lit(1)).withColumn("rule", F.lit("x"))
    got = {r["page_id"]: r for r in U.judge(df).collect()}
    for i, (u, *want) in enumerate(URLS):
        assert [got[i][c] for c in ("host", "path", "rule", "verdict")] == want, u


LINES = ["! a comment", "", "||ads.example.com^", "||q.org/en/", "@@||q.org/en/good", "/banner/*/img", "|b.example.net", "track1|", "*free*", "||uk^", "x-y"]


@pytest.mark.parametrize("literal", [2000, 0])
def test_index_gives_the_verdict_of_all_rules(spark, monkeypatch, literal):
    """Each rule's regular expression on every URL, without the index; as a literal and as a join."""
    monkeypatch.setattr(U, "LITERAL_RULES", literal)
    rules = U.default_rules() + [U.Rule("block", "^[^#]*#/en/.*\\bthe\\b", ("the",)), U.Rule("block", r"track\d+$", ())] + [r for x in LINES if (r := U.parse_rule(x))]
    urls = [f"https://{h}/{p}" for h in ("a.net", "b.example.net", "free-bets.example.com", "q.org", "ads.example.com", "bbc.co.uk", "sx-y.de") for p in ("en/the/1", "en/there", "de/2", "fr/the", "x?track1", "a/track1", "en/good/1", "banner/7/img", "carefree")]
    df = spark.createDataFrame([(i, u) for i, u in enumerate(urls + urls[:5] + [None])], "page_id long, url string").repartition(2)
    got = U.judge(df, rules).collect()
    assert len(got) == len(urls) + 6
    some = 0
    for r in got:
        key = f"{r['host']}#{r['path']}"
        fits = [x for x in rules if re.search(x.pattern, key)]
        assert all(set(x.tokens) <= set(re.split("[^a-z0-9]+", key.lower())) for x in fits), (key, fits)
        named = max((x for x in fits if x.label), key=lambda x: len(x.label), default=None)
        want = named.verdict if named else "block" if {x.verdict for x in fits} == {"block"} else "allow"
        assert (r["rule"], r["verdict"]) == (named and named.label, want), key
        assert r["n_candidates"] < len(rules)
        some += bool(fits) and not named
    assert some > 10


def test_filter_list_lines(spark, tmp_path):
    (tmp_path / "rules.txt").write_text("\n".join(LINES))
    rules = U.read_rules(spark, str(tmp_path / "rules.txt"))
    assert len(rules) == len(LINES) - 2
    by = dict(zip(LINES[2:], rules, strict=True))
    assert by["||ads.example.com^"].tokens == ("ads", "example", "com") and by["track1|"].tokens == () and by["*free*"].tokens == () and by["/banner/*/img"].tokens == ("banner",)
    assert by["@@||q.org/en/good"].verdict == "allow" and re.search(by["||q.org/en/"].pattern, "www.q.org#/EN/1") and not re.search(by["||q.org/en/"].pattern, "aq.org#/en/1")
    with pytest.raises(ValueError):
        U.parse_rule("||a.de^$third-party")
    assert U.judge(spark.createDataFrame([(1, "http://a.de")], "page_id long, url string"), []).first()["verdict"] == "allow"


def test_empty_table(spark):
    assert U.judge(spark.createDataFrame([], "page_id long, url string")).collect() == []
