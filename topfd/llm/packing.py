"""Best-fit packing of token sequences, certified by lower bounds and repacked across partitions.

1. Every document is encoded whole and ends with id 0. Longer ones are cut into full pieces; only the first may be shorter.
   What moves from here on is one narrow row a piece, which carries a checksum of its ids instead of the ids.
2. Full pieces are sequences of their own. The others are dealt to groups of bounded size by a hash of their row id, and
   each group runs best-fit decreasing over free-space stacks (a bit mask finds the tightest bin at once).
3. Each group's number of bins is held against a lower bound from dual-feasible functions. A group that meets its bound is certified: all its bins but
   the emptiest are settled. Other groups settle the bins without a gap. The open bins are exchanged, whole, between groups and packed anew.
4. That ends when the whole number of bins meets the bound of all pieces together, which comes from the histogram of their lengths, or when a round saves no
   bin. A group keeps its old bins where the new ones aren't fewer. `certificates` lists bins, bound and gap of every group, `certificate` those of the whole.

Null texts count as empty, so they are one piece of one token. Repeated rows are packed each for itself. An empty table gives an
empty result. A text of any length is encoded whole, one at a time. Other columns are not read. sequence_id values are unique but not consecutive.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, table, written
from .tokens import encoder

CAPACITY, END_ID = 2048, 0
#: Pieces of a group; a group's task holds so many narrow rows and no more than about twice.
GROUP_ROWS = 20_000
#: Bins with more free space than this share have a gap.
GAP = 0.002
#: Rounds of exchange at most; it ends before where the bound is met or nothing is saved.
ROUNDS = 8
PIECE = "rid long, doc_id long, piece int, start long, length long, ids_crc32 long"
PLACED = f"{PIECE}, sequence_id long, offset long, used long, bound long, bins long, grp long, open boolean"


def cut(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens, n at least 1."""
    first = n % capacity or capacity
    return [(0, first), *((s, capacity) for s in range(first, n, capacity))]


def pieces(docs: DataFrame, capacity: int = CAPACITY, json_path: str | None = None, ranks_path: str | None = None) -> DataFrame:
    """docs(doc_id, text) -> one row a piece; rid is unique where the rows are written once."""

    def make():
        encode = encoder(json_path, ranks_path)
        task, serial = TaskContext.get().partitionId() << 36, iter(range(1 << 36))

        def each(batch: pa.RecordBatch):
            rows: list[list] = [[] for _ in range(6)]
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = np.append(encode(text.as_py() or ""), END_ID).astype("<u4")
                for k, (s, n) in enumerate(cut(len(ids), capacity)):
                    for column, value in zip(rows, (task | next(serial), doc_id, k, s, n, zlib.crc32(ids[s : s + n].tobytes())), strict=True):
                        column.append(value)
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(rows, kinds, strict=True)], ["rid", "doc_id", "piece", "start", "length", "ids_crc32"])

        return each

    return arrow_map(docs, [F.col("doc_id").cast("long"), "text"], PIECE, make)


def best_fit_decreasing(lengths: np.ndarray, capacity: int) -> np.ndarray:
    """The bin of each item: longest first, each into the bin that it leaves the least space in."""
    stacks: list[list[int]] = [[] for _ in range(capacity + 1)]
    mask, made, out = 0, 0, np.zeros(len(lengths), np.int64)
    for i in np.argsort(-lengths, kind="stable").tolist():
        size = int(lengths[i])
        fitting = mask >> size
        if fitting:
            space = size + (fitting & -fitting).bit_length() - 1
            b = stacks[space].pop()
            if not stacks[space]:
                mask ^= 1 << space
        else:
            space, b, made = capacity, made, made + 1
        out[i] = b
        if space > size:
            stacks[space - size].append(b)
            mask |= 1 << (space - size)
    return out


def lower_bound(lengths: np.ndarray, capacity: int) -> int:
    """No packing has fewer bins: the largest of several dual-feasible functions' sums."""
    return bound_of_counts(np.bincount(lengths, minlength=capacity + 1)[: capacity + 1], capacity) if len(lengths) else 0


def bound_of_counts(counts: np.ndarray, capacity: int) -> int:
    """The same from the number of pieces of each length, 0 to capacity."""
    sizes = np.arange(capacity + 1)
    mass = counts * sizes
    upto, many = np.cumsum(mass), np.cumsum(counts)
    small = np.arange(1, capacity // 2 + 1)
    # items above capacity - a fill a bin each, those below a count nothing
    by_size = (many[-1] - many[capacity - small]) * capacity + upto[capacity - small] - upto[small - 1]
    best = max(-(-int(mass.sum()) // capacity), -(-int(by_size.max(initial=0)) // capacity))
    for k in range(1, 21):
        scaled = (k + 1) * sizes
        # in units of 1 / (k * capacity)
        value = np.where(scaled % capacity == 0, sizes * k, scaled // capacity * capacity)
        best = max(best, -(-int((counts * value).sum()) // (k * capacity)))
    return best


def _offsets(bins: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    order = np.argsort(bins, kind="stable")
    before = np.cumsum(lengths[order]) - lengths[order]
    new = np.flatnonzero(np.diff(bins[order], prepend=-1))
    out = np.empty(len(bins), np.int64)
    out[order] = before - np.repeat(before[new], np.diff(np.append(new, len(bins))))
    return out


def _packer(step: int, capacity: int):
    return lambda rows: _pack_group(rows, step, capacity)


def _pack_group(rows: pa.Table, step: int, capacity: int) -> pa.Table:
    lengths = rows.column("length").to_numpy()
    group = (np.int64(step) << 34) | np.int64(rows.column("grp")[0].as_py())
    bins, bound = best_fit_decreasing(lengths, capacity), lower_bound(lengths, capacity)
    made = int(bins.max()) + 1
    sequence, offset, used = (group << 24) | bins, _offsets(bins, lengths), np.bincount(bins, lengths).astype(np.int64)[bins]
    if "sequence_id" in rows.column_names:
        old = rows.column("sequence_id").to_numpy()
        had = len(np.unique(old))
        if made >= had:
            sequence, offset, used, made = old, rows.column("offset").to_numpy(), rows.column("used").to_numpy(), had
    if made == bound:
        emptiest = sequence[np.lexsort((sequence, used))[0]]
        still_open = (sequence == emptiest) & (used < capacity)
    else:
        still_open = used < int(capacity * (1 - GAP))
    n = len(rows)
    kept = rows.select([c.split()[0] for c in PIECE.split(", ")])
    for name, values in (("sequence_id", sequence), ("offset", offset), ("used", used), ("bound", np.full(n, bound)), ("bins", np.full(n, made)), ("grp", np.full(n, group))):
        kept = kept.append_column(name, pa.array(values, pa.int64()))
    return kept.append_column("open", pa.array(still_open))


def _n_bins(placed: DataFrame) -> int:
    """Every bin has one piece at its start."""
    return placed.where(F.col("offset") == 0).count()


def assign(cuts: DataFrame, capacity: int = CAPACITY, group_rows: int = GROUP_ROWS, rounds: int = ROUNDS) -> DataFrame:
    """Written pieces -> the same with sequence_id, offset, used (tokens of its sequence), and grp, bins, bound of the group that placed it last."""
    one = F.lit(1).cast("long")
    full = cuts.where(F.col("length") == capacity)
    full = full.select("*", (-F.col("rid") - 1).alias("sequence_id"), F.lit(0).cast("long").alias("offset"), F.col("length").alias("used"), one.alias("bound"), one.alias("bins"), F.lit(-1).cast("long").alias("grp"), F.lit(False).alias("open"))
    done, pool = [full], cuts.where(F.col("length") < capacity)
    counts = np.zeros(capacity + 1, np.int64)
    for r in pool.groupBy("length").count().collect():  # at most one number a length
        counts[r["length"]] = r["count"]
    best, settled, before = bound_of_counts(counts, capacity) if counts.sum() else 0, 0, None
    for step in range(1, rounds + 1):
        groups = max(1, -(-pool.count() // group_rows))
        dealt = pool.withColumn("grp", F.pmod(F.xxhash64("rid" if step == 1 else "sequence_id", F.lit(step)), F.lit(groups)))
        placed = written(dealt.groupBy("grp").applyInArrow(_packer(step, capacity), PLACED))
        made = settled + _n_bins(placed)
        if groups == 1 or step == rounds or made <= best or (before is not None and made >= before):
            done.append(placed)
            break
        before = made
        finished = placed.where(~F.col("open"))
        settled += _n_bins(finished)
        done.append(finished)
        pool = placed.where("open")
    out = done[0]
    for more in done[1:]:
        out = out.unionByName(more)
    return out


def certificates(assigned: DataFrame) -> DataFrame:
    """grp, pieces, bins, bound, gap of each group as it was packed last. A gap of 0 proves that its pieces need that many bins."""
    packed = assigned.where(F.col("grp") >= 0).groupBy("grp").agg(F.count(F.lit(1)).alias("pieces"), F.max("bins").alias("bins"), F.max("bound").alias("bound"))
    return packed.withColumn("gap", F.col("bins") - F.col("bound"))


def certificate(assigned: DataFrame, capacity: int = CAPACITY) -> dict[str, int]:
    """sequences, bound and gap of a whole plan; the bound is that of all its pieces together."""
    counts = np.zeros(capacity + 1, np.int64)
    for r in assigned.groupBy("length").count().collect():
        counts[r["length"]] = r["count"]
    made, bound = _n_bins(assigned), bound_of_counts(counts, capacity) if counts.sum() else 0
    return {"sequences": made, "bound": bound, "gap": made - bound}


def pack(docs: DataFrame, capacity: int = CAPACITY, group_rows: int = GROUP_ROWS, json_path: str | None = None, ranks_path: str | None = None) -> DataFrame:
    """docs(doc_id, text) -> doc_id, piece, start, length, ids_crc32, sequence_id, offset, and grp, group_bins, group_bound of the group that packed it."""
    plan = assign(written(pieces(docs, capacity, json_path, ranks_path)), capacity, group_rows)
    return plan.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", "grp", F.col("bins").alias("group_bins"), F.col("bound").alias("group_bound"))


def sequences(docs: DataFrame, plan: DataFrame, capacity: int = CAPACITY, json_path: str | None = None, ranks_path: str | None = None) -> DataFrame:
    """The packed sequences themselves: sequence_id, ids. Encodes again, so that ids travel once only. Pieces are found by id, place and checksum, so ids
    may repeat, with the same text or others."""

    def make():
        encode = encoder(json_path, ranks_path)

        def each(batch: pa.RecordBatch):
            out: list[tuple] = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = np.append(encode(text.as_py() or ""), END_ID).astype("<u4")
                out += [(doc_id, k, s, n, zlib.crc32(ids[s : s + n].tobytes()), ids[s : s + n].tolist()) for k, (s, n) in enumerate(cut(len(ids), capacity))]
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()))
            columns = zip(*out, strict=True) if out else [()] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], [*(f"{x}_" for x in key), "ids"])

        return each

    key = ("doc_id", "piece", "start", "length", "ids_crc32")
    texts = arrow_map(docs, [F.col("doc_id").cast("long"), "text"], "doc_id_ long, piece_ int, start_ long, length_ long, ids_crc32_ long, ids array<long>", make)
    texts = texts.dropDuplicates([f"{x}_" for x in key])
    same = F.lit(True)
    for x in key:
        same = same & (F.col(x).eqNullSafe(F.col(f"{x}_")) if x == "doc_id" else F.col(x) == F.col(f"{x}_"))
    placed = plan.join(texts, same)
    return placed.groupBy("sequence_id").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("offset", "ids"))), lambda x: x["ids"])).alias("ids"))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
