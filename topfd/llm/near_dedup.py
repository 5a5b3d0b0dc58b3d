"""Near-duplicate groups: SuperMinHash signatures, banding, verification on full shingle sets, and union-find.

* Sets: distinct hashes of word shingles of whole lower-cased texts. Documents with equal sets are one class from here on.
* Signature: every element draws a random permutation of the slots and one random number for each step; slot p keeps the least
  step + number of those elements whose permutation reaches p. Steps run for all documents of a chunk together, and a
  document leaves as soon as every slot is filled, as later steps can't lower a slot.
* Banding: a bucket is a band's hash. Every class is paired with its bucket's least class, pairs whose sizes already rule
  them out are dropped, and the rest are verified on full sets.
* Buckets whose classes are still in different components are searched further: what is outside a bucket's largest component meets all of it, in blocks of
  bounded size. Signatures are compared in bulk, and pairs across components that may reach the threshold are confirmed on their full sets on the
  spot. So no link depends on who leads a bucket, and no group's pairs are emitted. A pair at the threshold is missed by all bands with a
  probability of MISS, and by the estimate with one of ESTIMATE_MISS; the latter's margin is derived from slots and threshold.

Null and empty texts have an empty set and link with nothing. Texts of fewer words than a shingle have their whole sequence as one
element. Rows that share a doc_id are judged each by its own text. A null doc_id counts as the largest; its component is null if
no row of its group has an id. An empty table gives an empty result. Only doc_id and text are read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, table, written
from .graph import components
from .words import chunks, mix, words

#: Probabilities that a pair at the threshold shares no band, and that its signatures agree in fewer slots than are asked for in the second search.
MISS, ESTIMATE_MISS = 1e-5, 1e-6


def banding(percent: int, miss: float = MISS) -> tuple[int, int]:
    """(bands, rows) that miss a pair at the threshold with at most about this probability."""
    rows = 5 if percent >= 85 else 4
    return int(np.ceil(np.log(miss) / np.log(1 - (percent / 100) ** rows))), rows


def least_agreement(percent: int, slots: int, miss: float = ESTIMATE_MISS) -> int:
    """The most slots that may be asked for if a pair at the threshold is to fall below with at most this probability. Slots count as independent draws, which
    SuperMinHash's are better than."""
    t, below = percent / 100, 0.0
    for k in range(slots + 1):
        below += math.comb(slots, k) * t**k * (1 - t) ** (slots - k)
        if below > miss:
            return k
    return slots


#: Documents of a block, and elements of their sets.
BLOCK, BLOCK_ELEMENTS = 512, 4_000_000
_LAST = np.iinfo(np.int64).max
_UNSET = np.uint64(2**64 - 1)
_STEP_BITS = np.uint64(56)


def shingle_sets(data: np.ndarray, bounds: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, first): the distinct shingle hashes of each document of a chunk, ascending; first has one entry more than documents."""
    w = words(data, bounds, lower=True)
    n = np.diff(w.first)
    h, at = w.windows(width)
    doc = np.searchsorted(w.first, at, "right") - 1
    parts, docs = [h], [doc]
    for short in range(1, width):
        if len(few := np.flatnonzero(n == short)):
            hs, ats = w.windows(short)
            parts.append(hs[np.searchsorted(ats, w.first[few])])
            docs.append(few)
    h, doc = np.concatenate(parts), np.concatenate(docs)
    order = np.lexsort((h, doc))
    h, doc = h[order], doc[order]
    if len(h):
        new = np.concatenate(([True], (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])))
        h, doc = h[new], doc[new]
    return h, np.searchsorted(doc, np.arange(len(n) + 1))


def _nth(k: int) -> np.uint64:
    return np.uint64(k * 0x9E3779B97F4A7C15 % 2**64)


def signatures(h: np.ndarray, first: np.ndarray, slots: int) -> np.ndarray:
    """SuperMinHash of each document: uint64[documents, slots], the step in the top 8 bits and the random number below; _UNSET throughout for an empty set."""
    if slots > 256:
        raise ValueError("at most 256 slots: a step has eight bits")
    n = len(first) - 1
    sig = np.full(n * slots, _UNSET, np.uint64)
    doc = np.repeat(np.arange(n), np.diff(first))
    m = np.uint64(slots)
    draw = mix(h + _nth(1))
    swap = (draw % m).astype(np.int64)
    np.minimum.at(sig, doc * slots + swap, mix(draw) >> np.uint64(8))
    open_docs = (sig.reshape(n, slots) == _UNSET).any(axis=1) & (np.diff(first) > 0)
    active = np.flatnonzero(open_docs[doc])
    if not len(active):
        return sig.reshape(n, slots)
    h, doc, swap = h[active], doc[active], swap[active]
    order = np.tile(np.arange(slots, dtype=np.uint8), (len(h), 1))
    rows = np.arange(len(h))
    order[rows, swap], order[:, 0] = order[rows, 0], swap
    for step in range(1, slots):
        draw = mix(h + _nth(step + 1))
        swap = step + (draw % np.uint64(slots - step)).astype(np.int64)
        rows = np.arange(len(h))
        place = order[rows, swap].astype(np.int64)
        order[rows, swap] = order[:, step]
        order[:, step] = place
        np.minimum.at(sig, doc * slots + place, (np.uint64(step) << _STEP_BITS) | (mix(draw) >> np.uint64(8)))
        still = (sig.reshape(n, slots)[doc] == _UNSET).any(axis=1) if step % 4 == 0 or step < 4 else np.ones(len(h), bool)
        if not still.all():
            h, doc, order = h[still], doc[still], order[still]
            if not len(h):
                break
    return sig.reshape(n, slots)


def band_hashes(sig: np.ndarray, bands: int) -> np.ndarray:
    """int64[documents, bands]."""
    parts = sig.reshape(len(sig), bands, -1)
    out = np.broadcast_to(np.arange(bands, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93), parts.shape[:2]).copy()
    for k in range(parts.shape[2]):
        out = mix(out * np.uint64(0x9FB21C651E98DF25) + parts[:, :, k])
    return out.view(np.int64)


def _key(df: DataFrame) -> DataFrame:
    return df.select(_did().alias("did"), "text")


def _did() -> Column:
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(int(_LAST)))


def _text_keys() -> list[Column]:
    """128 bits of the text itself: with the id, the key of a row up to rows that repeat both."""
    return [F.xxhash64("text").alias("text_1"), F.xxhash64(F.lit(1), "text").alias("text_2")]


def _set_hashes(h: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    sizes = np.diff(first).astype(np.uint64)
    out = []
    for salt in (1, 2):
        total = np.concatenate((np.zeros(1, np.uint64), np.cumsum(mix(h ^ mix(np.array([salt], np.uint64))))))
        out.append(mix(total[first[1:]] - total[first[:-1]] + sizes).view(np.int64))
    return out[0], out[1]


def facts(docs: DataFrame, width: int, percent: int) -> DataFrame:
    """did, text_1 and text_2 (128 bits of the text), n_shingles, node and node2 (128 bits of the set), bands (null for an empty set)."""
    n_bands, rows = banding(percent)

    def make():
        def each(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for lo, hi, data, bounds in chunks(batch.column(3)):
                h, first = shingle_sets(data, bounds, width)
                n = np.diff(first)
                a, b = _set_hashes(h, first)
                bands = pa.FixedSizeListArray.from_arrays(pa.array(band_hashes(signatures(h, first, n_bands * rows), n_bands).ravel()), n_bands).cast(pa.list_(pa.int64()))
                bands = pa.compute.if_else(pa.array(n > 0), bands, pa.nulls(len(n), bands.type))
                keys = [batch.column(k)[lo:hi] for k in range(3)]
                yield pa.RecordBatch.from_arrays([*keys, pa.array(n, pa.int64()), pa.array(a), pa.array(b), bands], ["did", "text_1", "text_2", "n_shingles", "node", "node2", "bands"])

        return each

    return arrow_map(_key(docs), ["did", *_text_keys(), "text"], "did long, text_1 long, text_2 long, n_shingles long, node long, node2 long, bands array<long>", make)


def _linked(pairs: DataFrame, docs: DataFrame, reps: DataFrame, width: int, percent: int) -> DataFrame:
    """pairs(a, b) of nodes -> those that reach the threshold on the full sets of whole texts. reps(node, did): one document of each."""
    nodes = pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct()
    wanted = reps.join(nodes, "node").select("node", F.col("did").alias("rep_did"))
    texts = _key(docs).join(wanted, F.col("did") == F.col("rep_did")).select("node", "text")
    left, right = (texts.select(F.col("node").alias(k), F.col("text").alias(f"text_{k}")) for k in "ab")
    both = pairs.select("a", "b").join(left, "a").join(right, "b").select("a", "b", "text_a", "text_b")

    def make():
        def each(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for lo, hi, data, bounds in chunks(batch.column(2)):
                data2, bounds2 = _whole(batch.column(3)[lo:hi])
                (h, f), (h2, f2) = shingle_sets(data, bounds, width), shingle_sets(data2, bounds2, width)
                here = [x[0].view(np.uint64) ^ np.uint64(0) for x in (_set_hashes(h, f), _set_hashes(h2, f2))]
                ids = [batch.column(k)[lo:hi].to_numpy().view(np.uint64) for k in (0, 1)]
                n, n2 = np.diff(f), np.diff(f2)
                pair, pair2 = np.repeat(np.arange(hi - lo, dtype=np.uint64), n), np.repeat(np.arange(hi - lo, dtype=np.uint64), n2)
                # elements that both documents of a pair have stand twice in the merged order
                order = np.lexsort((np.concatenate((h, h2)), np.concatenate((pair, pair2))))
                hs, ps = np.concatenate((h, h2))[order], np.concatenate((pair, pair2))[order]
                same = (hs[1:] == hs[:-1]) & (ps[1:] == ps[:-1])
                common = np.bincount(ps[1:][same].astype(np.int64), minlength=hi - lo)
                good = (100 * common >= percent * (n + n2 - common)) & (here[0] == ids[0]) & (here[1] == ids[1])
                yield pa.RecordBatch.from_arrays([batch.column(k)[lo:hi].filter(pa.array(good)) for k in (0, 1)], ["a", "b"])

        return each

    return arrow_map(both, ["a", "b", "text_a", "text_b"], "a long, b long", make)


def _whole(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    _, _, data, bounds = next(chunks(column, 1 << 62))
    return data, bounds


def _sizes_allow(a: Column, b: Column, percent: int) -> Column:
    return F.least(a, b) * 100 >= F.greatest(a, b) * percent


def _block_links(percent: int):
    """Links between the left rows of a block (side 0) and its right ones (side 1) in other components: candidates by estimate, confirmed on the full sets, best estimates first.
    Two components that a link has joined are not compared again, so what a block returns is a forest, at most one row for each of its documents."""
    n_bands, per_band = banding(percent)
    least = least_agreement(percent, n_bands * per_band)

    def of(rows: pa.Table) -> pa.Table:
        node, comp, n, side = (rows.column(c).to_numpy() for c in ("node", "component", "n_shingles", "side"))
        h = np.frombuffer(b"".join(rows.column("elements").to_pylist()), np.uint64)
        first = np.concatenate((np.zeros(1, np.int64), np.cumsum(n)))
        sig = signatures(h, first, n_bands * per_band)
        bands, band = band_hashes(sig, n_bands), rows.column("band")[0].as_py()
        part = np.unique(comp, return_inverse=True)[1]
        right = np.flatnonzero(side == 1)
        out: list[tuple[int, int]] = []
        for i in np.flatnonzero(side == 0).tolist():
            j = right[part[right] != part[i]]
            j = j[np.minimum(n[j], n[i]) * 100 >= np.maximum(n[j], n[i]) * percent]
            if not len(j):
                continue
            alike = (sig[j] == sig[i]).sum(axis=1)
            j, alike = j[alike >= least], alike[alike >= least]
            # buckets of other bands hold the pair too; the first of them looks at it
            mine = (bands[j] == bands[i]).argmax(axis=1) == band if len(j) else np.zeros(0, bool)
            j = j[mine][np.argsort(-alike[mine], kind="stable")]
            own = h[first[i] : first[i + 1]]
            for a in range(0, len(j), 64):
                some = j[a : a + 64]
                some = some[part[some] != part[i]]
                if not len(some):
                    continue
                elements = np.concatenate([h[first[x] : first[x + 1]] for x in some.tolist()])
                hit = own[np.minimum(np.searchsorted(own, elements), len(own) - 1)] == elements
                common = np.add.reduceat(hit, np.concatenate((np.zeros(1, np.int64), np.cumsum(n[some])[:-1])), dtype=np.int64)
                for x in some[100 * common >= percent * (n[i] + n[some] - common)].tolist():
                    if part[x] != part[i]:
                        out.append((int(node[i]), int(node[x])))
                        part[part == part[x]] = part[i]
        a, b = zip(*out, strict=True) if out else ((), ())
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return of


def _sets(docs: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """wanted(node, did) -> node, elements: the full set, ascending, as bytes."""

    def make():
        def each(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for lo, hi, data, bounds in chunks(batch.column(1)):
                h, first = shingle_sets(data, bounds, width)
                sets = [h[a:b].tobytes() for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True)]
                good = _set_hashes(h, first)[0] == batch.column(0)[lo:hi].to_numpy()
                yield pa.RecordBatch.from_arrays([batch.column(0)[lo:hi], pa.array(sets, pa.binary())], ["node", "elements"]).filter(pa.array(good))

        return each

    texts = _key(docs).join(wanted.select("node", F.col("did").alias("rep_did")), F.col("did") == F.col("rep_did"))
    return arrow_map(texts, ["node", "text"], "node long, elements binary", make).dropDuplicates(["node"])


def _one_name_a_set(known: DataFrame) -> DataFrame:
    """facts() in which `node` alone names a set: where two sets of different second halves share a first half, both get a name of all 128 bits."""
    classes = known.where(F.col("n_shingles") > 0).groupBy("node").agg(F.min("node2").alias("low"), F.max("node2").alias("high"))
    shared = classes.where(F.col("low") != F.col("high")).select("node")
    if not shared.limit(1).count():
        return known
    again = known.join(shared.withColumn("clash", F.lit(True)), "node", "left")
    node = F.when(F.col("clash"), F.xxhash64("node", "node2", F.lit(7))).otherwise(F.col("node"))
    return written(again.withColumn("node", node).select(known.columns))


def _met(rest: DataFrame, sets: DataFrame) -> DataFrame:
    """rest(bucket, band, node, n_shingles, component, main) -> blocks: every row outside its bucket's main component (side 0) with every row of the bucket (side 1), their sets included."""
    outside = F.col("component") != F.col("main")
    count = lambda x, to: F.greatest(F.lit(1), F.ceil(F.sum(x) / F.lit(to))).cast("int")
    sizes = rest.groupBy("bucket").agg(
        F.greatest(count(outside.cast("int"), BLOCK), count(F.when(outside, F.col("n_shingles")).otherwise(0), BLOCK_ELEMENTS)).alias("lefts"),
        F.greatest(count(F.lit(1), BLOCK), count(F.col("n_shingles"), BLOCK_ELEMENTS)).alias("rights"),
    )
    placed = rest.join(written(sizes), "bucket").join(sets, "node")
    kept = ["bucket", "band", "node", "n_shingles", "component", "elements"]
    own = lambda name: F.pmod(F.xxhash64("node"), F.col(name)).cast("int")
    every = lambda name: F.explode(F.sequence(F.lit(0), F.col(name) - 1))
    left = placed.where(outside).select(*kept, F.lit(0).alias("side"), own("lefts").alias("b0"), every("rights").alias("b1"))
    right = placed.select(*kept, F.lit(1).alias("side"), own("rights").alias("b1"), every("lefts").alias("b0"))
    return left.unionByName(right)


def _named(docs: DataFrame, width: int, percent: int) -> DataFrame:
    """facts() with the group of each row; null for an empty set, which is in no group."""
    known = _one_name_a_set(written(facts(docs, width, percent)))
    reps = written(known.where(F.col("n_shingles") > 0).groupBy("node").agg(F.min("did").alias("did"), F.min("n_shingles").alias("n_shingles")))
    banded = known.where(F.col("n_shingles") > 0).dropDuplicates(["node"]).select("node", "n_shingles", F.posexplode("bands").alias("band", "bucket"))
    sizes = banded.groupBy("bucket").agg(F.min(F.struct("node", "n_shingles")).alias("lead"), F.count(F.lit(1)).alias("held")).where(F.col("held") > 1)
    members = written(banded.join(sizes, "bucket").select("bucket", "band", "node", "n_shingles", "held", "lead"))
    stars = members.where((F.col("node") != F.col("lead.node")) & _sizes_allow(F.col("n_shingles"), F.col("lead.n_shingles"), percent))
    stars = stars.select(F.col("lead.node").alias("a"), F.col("node").alias("b")).distinct()
    links = written(_linked(stars, docs, reps, width, percent))
    parts = components(links)
    open_members = members.where(F.col("held") > 2).join(parts, "node", "left").withColumn("component", F.coalesce("root", "node"))
    shares = open_members.groupBy("bucket", "component").agg(F.count(F.lit(1)).alias("n"))
    mixed = shares.groupBy("bucket").agg(F.max_by("component", F.struct("n", "component")).alias("main"), F.count(F.lit(1)).alias("n_parts")).where(F.col("n_parts") > 1)
    # stored, so that adaptive execution can split the join at a hot bucket
    mixed = written(mixed.select("bucket", "main"))
    rest = written(open_members.join(mixed, "bucket").select("bucket", "band", "node", "n_shingles", "component", "main"))
    if rest.limit(1).count():
        sets = _sets(docs, reps.join(rest.select("node").distinct(), "node"), width)
        more = written(_met(rest, sets).groupBy("bucket", "b0", "b1").applyInArrow(_block_links(percent), "a long, b long"))
        if more.limit(1).count():
            parts = components(links.unionByName(more))
    return known.join(parts, "node", "left").withColumn("group", F.when(F.col("n_shingles") > 0, F.coalesce("root", "node")))


def groups(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_shingles, component_id, kept."""
    named = _named(docs, width, percent)
    # stored, and only of groups with more than one id: so the join has two plain shuffles, which adaptive execution can split at a hot group
    least = named.where(F.col("group").isNotNull()).groupBy("group").agg(F.min("did").alias("least"), F.max("did").alias("most"))
    least = written(least.where(F.col("least") < F.col("most")).select("group", "least"))
    out = named.join(least, "group", "left").withColumn("component", F.coalesce("least", "did"))
    real = lambda c: F.when(F.col(c) < F.lit(int(_LAST)), F.col(c))
    return out.select(real("did").alias("doc_id"), "n_shingles", real("component").alias("component_id"), (F.col("did") == F.col("component")).alias("kept"))


def one_of_each(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """One document of each group, with all its columns: of those with the group's smallest id (null is the largest) the one with the least hash
    of the text. Documents in no group stay. Rows come back by id and text, never by the id alone; of rows that repeat both, one stays."""
    row = F.struct("did", "text_1", "text_2")
    named = _named(docs, width, percent).select("group", row.alias("row"))
    grouped = F.col("group").isNotNull()
    first = named.where(grouped).groupBy("group").agg(F.min("row").alias("row"))
    chosen = written(first.select("row").unionByName(named.where(~grouped).select("row")))
    one, two = _text_keys()
    # the documents' own columns stay in a struct, so that none can clash
    own = docs.select(F.struct(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(docs.columns)]).alias("own"), _did().alias("did"), one, two)
    keys = chosen.select("row.did", "row.text_1", "row.text_2").distinct()
    kept = own.join(keys, ["did", "text_1", "text_2"], "left_semi")
    # rows that repeat id and text; told from the narrow facts, so that texts are shuffled only where there are any
    if named.groupBy("row").count().where(F.col("count") > 1).limit(1).count():
        kept = kept.dropDuplicates(["did", "text_1", "text_2"])
    return kept.select(*[F.col(f"own.c{i}").alias(c) for i, c in enumerate(docs.columns)])


def op7_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return groups(table(spark, sf_dir, "documents"), width=3, percent=85)


#: All pairs by definition: quick enough on the correctness tables, where shared shingles give the pairs.
ORACLE = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+'), []::VARCHAR[]) AS w FROM documents),
s AS (
  SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN []::VARCHAR[] WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
         ELSE list_transform(range(1, len(w) - 1), lambda i: array_to_string(w[i : i + 2], ' ')) END) AS sh FROM d),
items AS (SELECT doc_id, unnest(sh) AS x FROM s),
pairs AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS common FROM items a JOIN items b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY ALL),
links AS (
  SELECT a, b FROM pairs JOIN s p ON p.doc_id = a JOIN s q ON q.doc_id = b WHERE 100 * common >= 85 * (len(p.sh) + len(q.sh) - common)),
both_ways AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach AS (SELECT doc_id, doc_id AS c FROM s UNION SELECT e.b, r.c FROM reach r JOIN both_ways e ON e.a = r.doc_id),
least AS (SELECT doc_id, min(c) AS component_id FROM reach GROUP BY doc_id)
SELECT doc_id, CAST(len(sh) AS BIGINT) AS n_shingles, component_id, doc_id = component_id AS kept FROM s JOIN least USING (doc_id)
"""
