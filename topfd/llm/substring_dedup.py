"""Removal of word passages that stand earlier in the corpus, by level-wise doubling.

Windows of `size` words that repeat can only hold shorter windows that repeat. So windows of a short length are counted first,
and only what repeats there is extended to twice that length, level by level (5, 10, 20 words), until nothing is left or `size` is reached:

* At a short length, each `size`-window is stood for by the least hash among its short windows. Equal windows share it, so
  a window whose least short window stands nowhere else can't repeat. That is about one short window in eight.
* Each task first combines what it has read: a hash that it met in two documents is known to repeat without being sent for
  every document. One row a task and hash is shuffled, so a passage that a third of all documents share is as cheap as any other.
* At the last length all candidate windows get 128-bit hashes, and the least document id of each decides which occurrences are first.

Documents whose whole word sequence stands in a document with a smaller id are settled by a hash of that sequence and never extended.

Order: doc_id, null last. Rows that share a doc_id are not earlier than each other, so repeated rows are judged alike. Null texts
and texts of fewer than `size` words lose nothing. Removing everything leaves an empty text. An empty table gives an empty result.
Only doc_id and text are read. Hashes have 128 bits where documents meet at the last length, and 48 before (where a collision costs time, not
correctness); a document finds its own windows again by 64 of them. A row is named by 64 bits of its id and text, so rows of one id, or of none, keep their
windows apart. Any size from 1 on will do; sizes that are no double of a shorter one are reached in a shorter step.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import arrow_map, table, written
from .words import Words, chunks, mix, sums, words

SIZE, SHORTEST = 20, 5
_LAST = np.iinfo(np.int64).max
#: Rows that a task holds before it combines and sends them.
_HELD = 1_000_000
_SEQUENCE = (0xC2B2AE3D27D4EB4F, 0x9FB21C651E98DF25)
_LOW48 = np.uint64(2**48 - 1)


def lengths(size: int = SIZE, shortest: int = SHORTEST) -> list[int]:
    """size, halved (and rounded up) as long as it is at least `shortest`, in ascending order."""
    out = [size]
    while -(-out[0] // 2) >= shortest and out[0] > 1:
        out.insert(0, -(-out[0] // 2))
    return out


def _key(df: DataFrame, *more: str) -> DataFrame:
    """did (null: the largest), row (the name of a row), text."""
    did = F.coalesce(F.col("doc_id").cast("long"), F.lit(int(_LAST)))
    return df.select(did.alias("did"), F.xxhash64(did, F.col("text")).alias("row"), "text", *more)


def _docs_of(w: Words, at: np.ndarray) -> np.ndarray:
    return np.searchsorted(w.first, at, "right") - 1


def _least(values: np.ndarray, width: int) -> np.ndarray:
    """Sliding minimum; one entry for each full range."""
    step, out = 1, values
    while 2 * step <= width:
        out = np.minimum(out[:-step], out[step:])
        step *= 2
    return np.minimum(out[: len(values) - width + 1], out[width - step : width - step + len(values) - width + 1]) if width > step else out


def _anchors(w: Words, short: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """For every window of `size` words: its least short-window hash (48 bits), and its document in the chunk."""
    values, at = w.windows(short)
    span = size - short + 1
    if len(values) < span:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    least, docs = _least(values, span), _docs_of(w, at)
    inside = docs[: len(least)] == docs[span - 1 :]
    return least[inside] & _LOW48, docs[: len(least)][inside]


def _unique_pairs(doc: np.ndarray, values: np.ndarray, *more: np.ndarray) -> tuple[np.ndarray, ...]:
    """One row for each document and value."""
    if len(doc):
        changed = np.concatenate(([True], (values[1:] != values[:-1]) | (doc[1:] != doc[:-1])))
        doc, values, *more = (x[changed] for x in (doc, values, *more))
        order = np.lexsort((values, doc))
        doc, values, *more = (x[order] for x in (doc, values, *more))
        new = np.concatenate(([True], (values[1:] != values[:-1]) | (doc[1:] != doc[:-1])))
        doc, values, *more = (x[new] for x in (doc, values, *more))
    return doc, values, *more


def _sequence_hash(w: Words, base: int) -> np.ndarray:
    """Of each document's whole word sequence."""
    total, down = sums(w.hashes, base)
    low = w.first[:-1]
    return mix((total[w.first[1:]] - total[low]) * down[low] + np.diff(w.first).astype(np.uint64)).view(np.int64)


def facts(keyed: DataFrame, size: int = SIZE) -> DataFrame:
    """did, row, n_words, h1, h2 (128 bits of the word sequence), repeats_itself, sha (of the words joined by a space)."""

    def make():
        def each(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for lo, hi, data, bounds in chunks(batch.column(2)):
                w = words(data, bounds)
                n = np.diff(w.first)
                seq = [_sequence_hash(w, base) for base in _SEQUENCE]
                h, at = w.windows(size)
                doc = _docs_of(w, at)
                keyed = np.sort(h ^ mix(doc.astype(np.uint64)))
                itself = np.zeros(hi - lo, bool)
                if len(again := keyed[1:][keyed[1:] == keyed[:-1]]):
                    itself[doc[np.isin(h ^ mix(doc.astype(np.uint64)), again)]] = True
                raw = data.tobytes()
                sha = [hashlib.sha256(b" ".join(raw[a:b].split())).digest() for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
                keys = [batch.column(k)[lo:hi] for k in (0, 1)]
                yield pa.RecordBatch.from_arrays([*keys, pa.array(n, pa.int64()), pa.array(seq[0]), pa.array(seq[1]), pa.array(itself), pa.array(sha, pa.binary())], ["did", "row", "n_words", "h1", "h2", "repeats_itself", "sha"])

        return each

    return arrow_map(keyed, ["did", "row", "text"], "did long, row long, n_words long, h1 long, h2 long, repeats_itself boolean, sha binary", make)


def _sent(held: list[tuple[np.ndarray, ...]], last: bool) -> Iterator[pa.RecordBatch]:
    """What a task sends of the (row, hash, second hash, id) that it holds: one row a hash that has to meet other tasks' rows (key is the hash), and rows
    that are settled here (own key). hash is null where it is the key. known: settled or repeated here. Before the last length, the id is the row's name,
    as it only matters whether a hash stands in two rows; at the last, the least id comes first."""
    if not held:
        return
    row, h, h2, did = (np.concatenate(x) for x in zip(*held, strict=True))
    held.clear()
    order = np.lexsort((row, did, h2, h))
    row, h, h2, did = row[order], h[order], h2[order], did[order]
    if last and len(h):
        # repeated rows say the same
        new = np.concatenate(([True], (h[1:] != h[:-1]) | (h2[1:] != h2[:-1]) | (row[1:] != row[:-1])))
        row, h, h2, did = row[new], h[new], h2[new], did[new]
    starts = np.flatnonzero(np.concatenate(([True], (h[1:] != h[:-1]) | (h2[1:] != h2[:-1])))) if len(h) else np.zeros(0, np.int64)
    count = np.diff(np.append(starts, len(h)))
    first = np.repeat(did[starts], count) if len(h) else did
    lead = np.zeros(len(h), bool)
    lead[starts] = True
    if last:
        # rows of the least id are all sent to meet others; any further id's are known to come later
        rest = did != first
        lead = ~rest
        known = rest
    else:
        rest = ~lead
        known = np.repeat(count > 1, count)
    sent = lead | rest
    key = np.where(rest, mix(h ^ mix(row.view(np.uint64))), h).view(np.int64)[sent]
    own = rest[sent]
    body = [pa.array(key), pa.array(h2.view(np.int64)[sent]), pa.array(h.view(np.int64)[sent], mask=~own), pa.array(row[sent]), pa.array(known[sent])]
    names = ["key", "key2", "hash", "row", "known"]
    if last:
        body, names = [*body, pa.array(did[sent])], [*names, "did"]
    for a in range(0, len(key), 20_000):
        yield pa.RecordBatch.from_arrays([c[a : a + 20_000] for c in body], names)


_SENT = "key long, key2 long, hash long, row long, known boolean"


def _level(keyed: DataFrame, alive: DataFrame | None, short: int, longer: int, size: int) -> DataFrame:
    """Rows as of _sent, of the windows of `longer` words. alive: row, hashes of the short windows that repeat; only what holds one is extended. None: all, whatever `short`.
    Below `size`, a window of `size` words is stood for by its least window of `longer` words. All levels, and what removes the words in the end, join the same
    columns of the same rows by the same key, so that Spark shuffles the texts once and reads that shuffle again."""
    last, filtered, hashes_at = longer == size, alive is not None, len(keyed.columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in batches:
            ids, names = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            for lo, hi, data, bounds in chunks(batch.column(2)):
                w = words(data, bounds)
                if last:
                    (values, at), (second, _) = w.windows(size), w.windows(size, _SEQUENCE[0])
                    doc = _docs_of(w, at)
                else:
                    values, doc = _anchors(w, longer, size)
                    second = np.zeros(len(values), np.uint64)
                if filtered:
                    some = batch.column(hashes_at)[lo:hi]
                    least, doc = _anchors(w, short, size)
                    wanted = mix(np.repeat(np.arange(hi - lo, dtype=np.uint64), np.diff(some.offsets.to_numpy()))) ^ some.flatten().to_numpy().view(np.uint64)
                    hit = np.isin(mix(doc.astype(np.uint64)) ^ least, wanted)
                    doc, values, second = doc[hit], values[hit], second[hit]
                doc, values, second = _unique_pairs(doc, values, second)
                held.append((names[lo:hi][doc], values, second, ids[lo:hi][doc] if last else np.zeros(len(doc), np.int64)))
                n += len(doc)
                if n > _HELD:
                    yield from _sent(held, last)
                    n = 0
        yield from _sent(held, last)

    rows = keyed.select("did", "row", "text") if alive is None else keyed.join(alive, "row").select(*keyed.columns, "hashes")
    return rows.mapInArrow(run, f"{_SENT}, did long" if last else _SENT)


def _lists(rows: DataFrame) -> DataFrame:
    return rows.groupBy("row").agg(F.collect_set(F.coalesce("hash", "key")).alias("hashes"))


def repeated(keyed: DataFrame, leaders: DataFrame, size: int = SIZE, shortest: int = SHORTEST) -> DataFrame:
    """row, hashes: of each row, the windows that also stand in a document with a smaller id. leaders(row): those whose whole sequence stands in no earlier document."""
    steps = lengths(size, shortest)
    meet = Window.partitionBy("key", "key2")
    alive = None
    for short, longer in zip([0, *steps[:-1]], steps, strict=True):
        rows = _level(keyed, alive, short, longer, size)
        if longer < size:
            n = F.sum(F.when(F.col("known"), 2).otherwise(1)).over(meet)
            alive = _lists(rows.withColumn("n", n).where(F.col("n") > 1)).join(leaders, "row", "left_semi")
    return _lists(rows.withColumn("least", F.min("did").over(meet)).where(F.col("known") | (F.col("did") > F.col("least"))))


def _cut(column: pa.Array, lists: pa.Array, size: int) -> Iterator[tuple]:
    """(rows, h1, n_removed, kept) of runs of documents, given the hashes of the windows that stand earlier (null: none)."""
    for lo, hi, data, bounds in chunks(column):
        w = words(data, bounds)
        some = lists[lo:hi]
        h, at = w.windows(size)
        keyed = h ^ mix(_docs_of(w, at).astype(np.uint64))
        flat, sizes = some.flatten().to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64), some.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
        gone = np.isin(keyed, mix(np.repeat(np.arange(hi - lo, dtype=np.uint64), sizes)) ^ flat)
        order = np.argsort(keyed, kind="stable")
        keyed = keyed[order]
        gone[order[1:][keyed[1:] == keyed[:-1]]] = True
        cover = np.zeros(len(w.hashes) + 1, np.int64)
        np.add.at(cover, at[gone], 1)
        np.add.at(cover, at[gone] + size, -1)
        kept = np.cumsum(cover)[:-1] == 0
        n = np.diff(w.first)
        kept_upto = np.concatenate(([0], np.cumsum(kept)))
        left = kept_upto[w.first[1:]] - kept_upto[w.first[:-1]]
        raw, starts, ends = data.tobytes(), w.starts[kept].tolist(), w.ends[kept].tolist()
        texts, a = [], 0
        for k in left.tolist():
            texts.append(b" ".join([raw[s:e] for s, e in zip(starts[a : a + k], ends[a : a + k], strict=True)]).decode("utf-8", "replace"))
            a += k
        yield (lo, hi), _sequence_hash(w, _SEQUENCE[0]).tolist(), (n - left).tolist(), texts


def _apply(keyed: DataFrame, lists: DataFrame, size: int) -> DataFrame:
    """row, n_removed, kept: of the documents that lists (row, hashes) names; null hashes: only repeats inside the document count."""
    hashes_at = len(keyed.columns)

    def make():
        def each(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for (lo, hi), _, lost, texts in _cut(batch.column(2), batch.column(hashes_at), size):
                yield pa.RecordBatch.from_arrays([batch.column(1)[lo:hi], pa.array(lost, pa.int64()), pa.array(texts, pa.string())], ["row", "n_removed", "kept"])

        return each

    return arrow_map(keyed.join(lists, "row"), [*keyed.columns, "hashes"], "row long, n_removed long, kept string", make)


def _judged(keyed: DataFrame, size: int, shortest: int) -> tuple[DataFrame, DataFrame]:
    """(facts of each row with `copy`: its whole sequence stands in a document with a smaller id; lists: row, hashes of the rows that lose words otherwise)."""
    known = written(facts(keyed, size))
    # stored, and only of sequences that stand more than once: so the join has two plain shuffles, which adaptive execution can split at a hot sequence
    firsts = known.where(F.col("n_words") >= size).groupBy("h1", "h2", "n_words").agg(F.min("did").alias("first"), F.max("did").alias("final"))
    firsts = written(firsts.where(F.col("first") < F.col("final")).drop("final"))
    judged = written(known.join(firsts, ["h1", "h2", "n_words"], "left").withColumn("copy", F.coalesce(F.col("did") > F.col("first"), F.lit(False))).drop("first"))
    own = judged.where(~F.col("copy"))
    leaders = own.where(F.col("n_words") >= size).select("row").distinct()
    itself = own.where("repeats_itself").select("row").distinct()
    return judged, repeated(keyed, leaders, size, shortest).join(itself, "row", "full_outer").select("row", "hashes")


def digests(docs: DataFrame, size: int = SIZE, shortest: int = SHORTEST) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_words, n_removed, kept_sha256, one row a document."""
    keyed = _key(docs)
    judged, lists = _judged(keyed, size, shortest)
    changed = _apply(keyed, lists, size).select("row", F.col("n_removed").alias("lost"), F.sha2("kept", 256).alias("kept_sha")).dropDuplicates(["row"])
    out = judged.join(changed, "row", "left")
    return out.select(
        F.when(F.col("did") < F.lit(int(_LAST)), F.col("did")).alias("doc_id"),
        "n_words",
        F.when(F.col("copy"), F.col("n_words")).otherwise(F.coalesce("lost", F.lit(0))).cast("long").alias("n_removed"),
        F.when(F.col("copy"), F.sha2(F.lit(""), 256)).otherwise(F.coalesce("kept_sha", F.lower(F.hex("sha")))).alias("kept_sha256"),
    )


def deduplicated(docs: DataFrame, size: int = SIZE, shortest: int = SHORTEST) -> DataFrame:
    """The documents with their texts after removal (kept words joined by a space) and all other columns as they are. Texts that lose nothing stay unchanged."""
    names = docs.columns
    # other columns go by place, so that no name can clash; a text alone is a struct too
    rest = F.struct(F.lit(0).alias("none"), *[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names) if c != "text"])
    keyed = _key(docs.select("doc_id", "text", rest.alias("rest")), "rest")
    judged, lists = _judged(keyed, size, shortest)
    fate = lists.withColumn("listed", F.lit(True)).join(judged.where("copy").select("row").distinct().withColumn("copy", F.lit(True)), "row", "full_outer")
    rows = keyed.join(fate, "row", "left").select(*keyed.columns, "hashes", "listed", "copy")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            _, _, whole, rest, hashes, listed, copied = batch.columns
            texts, copies = whole.to_pylist(), copied.to_pylist()
            at = [i for i, (named, copy) in enumerate(zip(listed.to_pylist(), copies, strict=True)) if named and not copy]
            if at:
                places = pa.array(at)
                done = [x for part in _cut(whole.take(places), hashes.take(places), size) for x in zip(*part[2:], strict=True)]
                for i, (n_removed, kept) in zip(at, done, strict=True):
                    if n_removed:
                        texts[i] = kept
            texts = ["" if copy else t for t, copy in zip(texts, copies, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(texts, pa.string()), rest], ["text", "rest"])

    out = rows.mapInArrow(run, f"text string, rest {rows.schema['rest'].dataType.simpleString()}")
    return out.select(*[F.col("text") if c == "text" else F.col(f"rest.c{i}").alias(c) for i, c in enumerate(names)])


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents"))


#: SQL of the definition itself; quick enough on the correctness tables.
ORACLE = r"""
WITH d AS (SELECT doc_id, coalesce(regexp_extract_all(text, '[^\x20\x09-\x0D]+'), []::VARCHAR[]) AS w FROM documents),
win AS (
  SELECT doc_id, s, list_aggregate(w[s : s + 19], 'string_agg', ' ') AS seq
  FROM (SELECT doc_id, w, unnest(range(1, len(w) - 18)) AS s FROM d WHERE len(w) >= 20)),
ranked AS (SELECT doc_id, s, row_number() OVER (PARTITION BY seq ORDER BY doc_id, s) AS rn FROM win),
gone AS (SELECT DISTINCT doc_id, s + k AS i FROM (SELECT doc_id, s, unnest(range(0, 20)) AS k FROM ranked WHERE rn > 1)),
lists AS (SELECT doc_id, list(i) AS gone FROM gone GROUP BY doc_id),
kept AS (
  SELECT d.doc_id, len(w) AS n, coalesce(len(gone), 0) AS g,
         CASE WHEN gone IS NULL THEN w ELSE list_filter(w, lambda x, i: NOT list_contains(gone, i)) END AS k
  FROM d LEFT JOIN lists USING (doc_id))
SELECT doc_id, CAST(n AS BIGINT) AS n_words, CAST(g AS BIGINT) AS n_removed,
       sha256(coalesce(list_aggregate(k, 'string_agg', ' '), '')) AS kept_sha256
FROM kept
"""
