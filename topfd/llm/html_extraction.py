"""Main text of web pages by differencing each page against the page with the nearest URL of its host.

1. A page becomes lines, one a block, in page order, menus, adverts and all else included; only what no browser shows (scripts, styles, comments) gives none.
   A line knows where it stands: in a page's article (or main) element, in an element that can't be part of one, or in neither.
2. Pages are sorted by host, path and id across ranges, so that a host of any size is spread over many tasks. On both sides the nearest page
   of the host whose lines differ is looked for, past copies and past the ends of a range, and the one whose path has the longer common
   start is the partner.
3. Every page is differenced: a longest common subsequence aligns the lines of the two pages, and a shared line is deleted unless it stands in the page's own
   article. On the given pages articles share passages that belong to them, so there the text of an article is safe from its neighbour.
4. Of the lines that the partner doesn't share, those in an element that can't be part of an article (a menu, footer, form, aside, advert, notice or
   reader comment, by element, role or class) are deleted too: the given menus, adverts and footers are different on every page, and
   differencing alone would keep them. All other lines stay. ``n_shared`` and ``n_marked`` say how many lines each of the two rules deleted.

Inside an article only containers are judged by their class, and only by words that name nothing else; paragraphs, headings and list items never are.

Character references are decoded; white space inside a block becomes one space; blocks are joined by one line break. Null and empty
pages, and pages without any such line, give the empty text. Null URLs count as an empty host and path. Pages with equal lines are
never each other's partner, so copies don't erase each other. Repeated rows give equal texts. A page of any length is read in time that grows
with its length, unfinished tags included. An empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import hashlib
import html as entities
import re
from collections.abc import Iterator
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..ship import ship
from .common import arrow_map, table, written
from .url_filter import host_and_path

#: Elements by their part in a page. Fixed values of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Their content is no mark-up and is not shown as text.
RAW = frozenset("script style textarea title iframe template select xmp noembed noframes".split())
NEVER = frozenset("nav footer aside form button dialog menu head label fieldset".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
#: Start tags that end an open paragraph.
ENDS_P = BLOCK - {"body", "html", "caption", "tbody", "td", "tfoot", "th", "thead", "tr", "option", "legend"}
#: Elements that hold others, whose class may name them inside an article too.
CONTAINERS = frozenset("div section ul ol dl table span ins center details figure".split())
#: Words in class or id, and roles, of what isn't article text: outside an article; and, as whole class names, inside of one.
MARKS = frozenset("ad ads adv advert adverts advertisement advertising banner sponsor sponsored promo promotion cookie cookies consent gdpr notice notices alert newsletter subscribe subscription signup login paywall sidebar sidebars menu menus nav navbar navigation breadcrumb breadcrumbs pagination pager comment comments replies reply disqus respond share sharing social related recommended recommendations popup modal overlay toolbar footer masthead topbar widget widgets skip".split())
MARKS_INSIDE = frozenset("ad ads advert adverts advertisement advertising sponsored cookie-notice cookie-banner cookies consent newsletter newsletter-signup paywall sidebar navbar breadcrumb breadcrumbs pagination pager comments comment-list disqus disqus_thread respond".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
#: What a line is part of.
PLAIN, ARTICLE, MARKED = 0, 1, 2

_NAME = re.compile(r"/?[a-zA-Z][^\s/>]*+")
_UNQUOTED = re.compile(r"[^\"'>]*+")
#: A name and perhaps a value; every match goes on where the last one ended, so a tag of any length is read once.
_ATTR = re.compile(r"([^\s=/\"'>]++)(?:\s*+=\s*+(?:\"([^\"]*+)\"|'([^']*+)'|([^\s\"'>]++)))?")
_ENDS = {name: re.compile(rf"</{name}(?=[\s/>])", re.I) for name in RAW}
_SPLIT = re.compile(r"[^a-z0-9]+")
_CLASSES = re.compile(r"[^a-z0-9_-]+")
#: Pages of a range, at least.
PARTITION_PAGES = 400
#: What pages are sorted by; mark keeps equal pages together.
KEY = ("host", "path", "place", "mark")
#: Cuts between ranges are searched in blocks of so many.
CUTS = 128
#: Cells of an alignment whose rows are held at once; larger ones are halved.
CELLS = 1 << 28


def _unwanted(name: str, attributes: str, inside: bool) -> bool:
    """inside: of an article, whose header is its own."""
    if name in NEVER or (name == "header" and not inside):
        return True
    if not attributes or name in ("body", "html", "article", "main"):
        return False
    for m in _ATTR.finditer(attributes):
        key, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
        if key in ("class", "id"):
            if inside:
                if name in CONTAINERS and not MARKS_INSIDE.isdisjoint(_CLASSES.split(value)):
                    return True
                continue
            words = _SPLIT.split(value)
            if not MARKS.isdisjoint(words) or ("header" in words and name == "div"):
                return True
        elif key == "hidden" or (key == "role" and value in ROLES) or (key == "aria-hidden" and value == "true") or (key == "style" and "display:none" in value.replace(" ", "")):
            return True
    return False


class _Tags:
    """The tags of a page from left to right. A tag whose quotes never end is read as ending at the next '>'; from then on all are, so no page is read more than twice."""

    def __init__(self, page: str):
        self.page, self.end = page, len(page)
        self.last = {c: page.rfind(c) for c in "\"'>"}
        self.quotes = True

    def next(self, at: int) -> tuple[int, int, str, str] | None:
        """(start, end, name with a leading / of an end tag, attributes) of the first tag from `at` on; the name is empty for a comment or declaration."""
        page = self.page
        while True:
            start = page.find("<", at)
            if start < 0:
                return None
            if page.startswith("<!--", start):
                end = page.find("-->", start + 4)
                return start, (end + 3 if end >= 0 else self.end), "", ""
            if page[start + 1 : start + 2] in ("!", "?"):
                end = page.find(">", start)
                return start, (end + 1 if end >= 0 else self.end), "", ""
            if start > self.last[">"]:
                return None
            name = _NAME.match(page, start + 1)
            if not name:
                at = start + 1
                continue
            end = self._end(name.end())
            return start, end + 1, name[0].lower(), page[name.end() : end]

    def _end(self, begun: int) -> int:
        at = begun
        while self.quotes:
            at = _UNQUOTED.match(self.page, at).end()
            if at >= self.end:
                self.quotes = False
            elif self.page[at] == ">":
                return at
            elif at >= self.last[self.page[at]]:
                self.quotes = False
            else:
                at = self.page.find(self.page[at], at + 1) + 1
        return self.page.find(">", begun)


class _Open:
    """The open elements. Where the last of each name stands is known, so nothing is searched for."""

    def __init__(self) -> None:
        self.names: list[str] = []
        self.unwanted: list[bool] = []
        self.at: dict[str, list[int]] = {}
        self.skipping = 0

    def push(self, name: str, unwanted: bool) -> None:
        self.at.setdefault(name, []).append(len(self.names))
        self.names.append(name)
        self.unwanted.append(unwanted)
        self.skipping += unwanted

    def last(self, *names: str) -> int:
        return max((self.at[n][-1] for n in names if self.at.get(n)), default=-1)

    def close(self, upto: int) -> None:
        while len(self.names) > upto:
            self.at[self.names.pop()].pop()
            self.skipping -= self.unwanted.pop()

    def holds(self, name: str) -> bool:
        return bool(self.at.get(name))


_P_WALLS = ("article", "main", "section", "div", "td", "li", "blockquote")


def lines_of(page: str | None) -> list[tuple[str, int]]:
    """(text, place) of each block; place: ARTICLE in an article element (a main element if the page has no article), MARKED in an element that can't be part of one, else PLAIN."""
    if not page:
        return []
    out: list[tuple[str, bool, bool, bool]] = []
    elements, tags, parts = _Open(), _Tags(page), []

    def end_block() -> None:
        if parts:
            text = " ".join(entities.unescape("".join(parts)).split())
            if text:
                out.append((text, elements.skipping > 0, elements.holds("article"), elements.holds("main")))
            parts.clear()

    def close(upto: int) -> None:
        # text of an unwanted element doesn't run on into what follows
        if any(elements.unwanted[upto:]) or any(n in ("article", "main") for n in elements.names[upto:]):
            end_block()
        elements.close(upto)

    at = 0
    while True:
        tag = tags.next(at)
        if tag is None:
            parts.append(page[at:])
            break
        start, end, name, attributes = tag
        if start > at:
            parts.append(page[at:start])
        at = end
        if not name:
            continue
        if name[0] == "/":
            name = name[1:]
            if name in BLOCK:
                end_block()
            if (last := elements.last(name)) >= 0:
                close(last)
            continue
        if name in RAW:
            # a slash at its end doesn't close it
            found = _ENDS[name].search(page, at)
            if not found:
                break
            at = page.find(">", found.end())
            if at < 0:
                break
            at += 1
            continue
        if name == "br":
            parts.append(" ")
        if name in BLOCK:
            end_block()
        if name in VOID:
            continue
        if name in ENDS_P and elements.last("p") > elements.last(*_P_WALLS):
            close(elements.last("p"))
        if name == "li" and elements.last("li") > elements.last("ul", "ol"):
            close(elements.last("li"))
        unwanted = _unwanted(name, attributes, elements.holds("article") and not elements.skipping)
        if unwanted:
            end_block()
        elements.push(name, unwanted)
    end_block()
    articles = any(article and not marked for _, marked, article, _ in out)
    return [(text, MARKED if marked else ARTICLE if (article if articles else main) else PLAIN) for text, marked, article, main in out]


def _rows(xs: list[int], x: list[str], ys: list[str], keep: bool) -> tuple[list[int], int]:
    """Bit-parallel alignment of x[xs] and ys: row i has a 0 at j where the common length of x[..i] and ys[..j] exceeds that of ys[..j-1]. (rows if kept, the last)."""
    places: dict[str, int] = {}
    for j, t in enumerate(ys):
        places[t] = places.get(t, 0) | 1 << j
    full = (1 << len(ys)) - 1
    rows, v = [], full
    for i in xs:
        hit = v & places.get(x[i], 0)
        v = ((v + hit) | (v - hit)) & full
        if keep:
            rows.append(v)
    return rows, v


def _aligned(xs: list[int], x: list[str], ys: list[str]) -> list[int]:
    """Those of xs that are in a longest common subsequence of x[xs] and ys."""
    if not xs or not ys:
        return []
    if len(xs) * len(ys) > CELLS and len(xs) > 1:
        half = len(xs) // 2
        _, front = _rows(xs[:half], x, ys, False)
        _, back = _rows(xs[half:][::-1], x, ys[::-1], False)
        n = len(ys)
        front_upto = [0, *accumulate(1 - (front >> j & 1) for j in range(n))]
        back_upto = [0, *accumulate(1 - (back >> j & 1) for j in range(n))]
        cut = max(range(n + 1), key=lambda j: front_upto[j] + back_upto[n - j])
        return _aligned(xs[:half], x, ys[:cut]) + _aligned(xs[half:], x, ys[cut:])
    rows, _ = _rows(xs, x, ys, True)
    found = []
    i, j = len(xs) - 1, len(ys) - 1
    length = lambda i, j: (~rows[i] & ((1 << (j + 1)) - 1)).bit_count() if i >= 0 and j >= 0 else 0
    while i >= 0 and j >= 0:
        here = length(i, j)
        if not here:
            break
        if x[xs[i]] == ys[j] and length(i - 1, j - 1) == here - 1:
            found.append(xs[i])
            i, j = i - 1, j - 1
        elif length(i - 1, j) == here:
            i -= 1
        else:
            j -= 1
    return found


def shared_lines(a: list[str], b: list[str]) -> set[int]:
    """Positions in a of a longest common subsequence of a and b. Equal starts and ends are taken first."""
    top = 0
    while top < min(len(a), len(b)) and a[top] == b[top]:
        top += 1
    tail = 0
    while tail < min(len(a), len(b)) - top and a[-1 - tail] == b[-1 - tail]:
        tail += 1
    found = {*range(top), *range(len(a) - tail, len(a))}
    x, y = a[top : len(a) - tail], b[top : len(b) - tail]
    common = set(x) & set(y)
    return found | {top + i for i in _aligned([i for i, t in enumerate(x) if t in common], x, [t for t in y if t in common])}


def main_text(lines: list[tuple[str, int]], partner: list[tuple[str, int]] | None) -> tuple[str, int, int]:
    """(text, lines deleted as shared with the partner, further lines deleted as marked)."""
    gone = shared_lines([t for t, _ in lines], [t for t, _ in partner]) if partner else set()
    shared = {i for i in gone if lines[i][1] != ARTICLE}
    marked = {i for i, (_, place) in enumerate(lines) if place == MARKED} - shared
    return "\n".join(t for i, (t, _) in enumerate(lines) if i not in shared and i not in marked), len(shared), len(marked)


def _alike(a: str, b: str) -> int:
    n = 0
    for x, y in zip(a, b, strict=False):
        if x != y:
            break
        n += 1
    return n


def _differenced(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pages in order of range, side and key. A run of pages with equal lines waits for the next page that differs; the page before the run is held too.
    Rows whose side isn't 0 are the neighbours of the range: partners alone."""
    before = now = None
    run: list[tuple] = []
    done: list[tuple] = []
    size = 0

    def out() -> pa.RecordBatch:
        kinds = (pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int32(), pa.int32())
        batch = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*done, strict=True), kinds, strict=True)], ["page_id", "url", "text", "n_chars", "n_shared", "n_marked"])
        done.clear()
        return batch

    def settled(after) -> Iterator[pa.RecordBatch]:
        nonlocal size
        near, texts = [p for p in (before, after) if p], {}
        for page_id, url, path, side, inside in run:
            if side:
                continue
            k = max(range(len(near)), key=lambda k: _alike(near[k][0], path), default=None)
            if (k, inside) not in texts:
                texts[k, inside] = main_text([(t, a) for (t, _), a in zip(now[1], inside, strict=True)], None if k is None else near[k][1])
            text, n_shared, n_marked = texts[k, inside]
            done.append((page_id, url, text, len(text), n_shared, n_marked))
            size += len(text)
            if size > 4_000_000:
                yield out()
                size = 0

    for batch in batches:
        for page_id, url, path, side, part, host, page in zip(*(batch.column(k).to_pylist() for k in range(6)), batch.column(6), strict=True):
            lines = lines_of(page.as_py())
            same_host = now and now[0] == (part, host)
            if not (same_host and [t for t, _ in lines] == [t for t, _ in now[1]]):
                if now:
                    yield from settled((path, lines) if same_host else None)
                before, now = (run[-1][2], now[1]) if same_host else None, ((part, host), lines)
                run.clear()
            # copies may differ in what an article element holds, so a line's place stays with its page
            run.append((page_id, url, path, side, tuple(a for _, a in lines)))
    if now:
        yield from settled(None)
    if done:
        yield out()
    pa.default_memory_pool().release_unused()


def _ends(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Keys and line hashes in order -> at most four of a range: the first page and the first of its host that differs from it; the last and the last that differs."""
    first = first_other = last = last_other = None
    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if first is None:
                first = row
            elif first_other is None and row[0] == first[0] and row[4] != first[4]:
                first_other = row
            if last and row[0] != last[0]:
                last_other = None
            elif last and row[4] != last[4]:
                last_other = last
            last = row
    found = [(k, first[:4], *row) for k, row in enumerate((first, first_other, last, last_other)) if row] if first else []
    kinds = (pa.int32(), None, pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64())
    if found:
        start = pa.StructArray.from_arrays([pa.array(c, k) for c, k in zip(zip(*(f[1] for f in found), strict=True), kinds[2:6], strict=True)], list(KEY))
        rest = [pa.array(c, k) for c, k in zip(zip(*(f[2:] for f in found), strict=True), kinds[2:], strict=True)]
        yield pa.RecordBatch.from_arrays([pa.array([f[0] for f in found], pa.int32()), start, *rest], ["kind", "start", *KEY, "lines"])


def neighbours(ranges: list[dict[int, tuple]]) -> list[tuple[int, int, tuple]]:
    """ranges: in order, what _ends found, each (host, path, place, mark, lines) -> (range, side, key) of the last page before it (side -1) that
    has the host and not the lines of its first page, and of the first page after it (side 1) against its last page."""
    out = []
    for side, near, near_other, far in ((-1, 2, 3, 0), (1, 0, 1, 2)):
        held = None
        order = range(len(ranges)) if side < 0 else range(len(ranges) - 1, -1, -1)
        previous = None
        for q in order:
            page = ranges[q][far]
            if previous is not None:
                p = ranges[previous]
                if p[near][0] != page[0]:
                    held = None
                elif p[near][4] != page[4]:
                    held = p[near]
                elif near_other in p:
                    held = p[near_other]
                elif p[far][0] != page[0]:
                    held = None
                # else the range before is one run with these lines: its own neighbour is this one's too
                if held:
                    out.append((q, side, held[:4]))
            previous = q
    return out


def _line_hashes(keyed: DataFrame) -> DataFrame:
    def make():
        def each(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            marks = [int.from_bytes(hashlib.blake2b("\n".join(t for t, _ in lines_of(x.as_py())).encode(errors="surrogatepass"), digest_size=8).digest(), "little", signed=True) for x in batch.column(4)]
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(4)), pa.array(marks, pa.int64())], [*KEY, "lines"])

        return each

    return arrow_map(keyed, [*KEY, "html"], "host string, path string, place long, mark long, lines long", make)


def _ranged(keyed: DataFrame, parts: int) -> DataFrame:
    """The pages with their range (part) and side 0, and each range's neighbours with their side."""
    spark, fields = keyed.sparkSession, "host string, path string, place long, mark long"
    narrow = written(_line_hashes(keyed)).repartitionByRange(parts, *KEY).sortWithinPartitions(*KEY)
    by_start: dict[tuple, dict[int, tuple]] = {}
    for r in narrow.mapInArrow(_ends, f"kind int, start struct<{fields.replace(' ', ':')}>, {fields}, lines long".replace(",:", ", ")).collect():
        by_start.setdefault(tuple(r["start"]), {})[r["kind"]] = (*(r[k] for k in KEY), r["lines"])
    starts = sorted(by_start)
    blocks = [starts[k : k + CUTS] for k in range(0, len(starts), CUTS)]
    cut = "array<struct<host:string,path:string,place:bigint,mark:bigint>>"
    cuts = spark.createDataFrame([([x[0] for x in blocks], blocks)], f"firsts {cut}, blocks array<{cut}>")
    reached = lambda cuts: F.size(F.filter(cuts, lambda c: c <= F.struct(*KEY)))
    placed = keyed.crossJoin(F.broadcast(cuts)).withColumn("_block", F.greatest(reached(F.col("firsts")), F.lit(1)))
    part = (F.col("_block") - 1) * CUTS + reached(F.element_at("blocks", F.col("_block"))) - 1
    own = placed.select("*", part.cast("int").alias("part"), F.lit(0).alias("side")).drop("firsts", "blocks", "_block")
    ends = spark.createDataFrame([(*key, q, side) for q, side, key in neighbours([by_start[s] for s in starts])], f"{fields}, part int, side int")
    guests = keyed.join(F.broadcast(ends), list(KEY)).dropDuplicates(["part", "side"]).select(own.columns)
    return own.unionByName(guests).repartitionById(len(starts), "part")


def extract(pages: DataFrame) -> DataFrame:
    """pages(page_id, url, html) -> page_id, url, text, n_chars, n_shared, n_marked."""
    ship(pages.sparkSession)
    host, path = host_and_path(F.col("url"))
    keyed = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", host.alias("host"), path.alias("path"), "html")
    keyed = keyed.select("*", F.coalesce("page_id", F.lit(-(2**63))).alias("place"), F.xxhash64("html").alias("mark"))
    # up to four times the usual number of ranges, as pages are long rows of which a task holds a batch on either side of Arrow
    parts = max(1, min(4 * int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions")), pages.count() // PARTITION_PAGES))
    ranged = _ranged(keyed, parts) if parts > 1 else keyed.select("*", F.lit(0).alias("part"), F.lit(0).alias("side")).repartitionByRange(1, *KEY)
    near = ranged.sortWithinPartitions("part", "side", *KEY).select("page_id", "url", "path", "side", "part", "host", "html")
    return near.mapInArrow(_differenced, "page_id long, url string, text string, n_chars long, n_shared int, n_marked int")


def op9_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
