"""Difference sets: the attributes on which two rows disagree, as bitmasks.

Rows are compared by a 64-bit fingerprint of each value. Only a bounded number of pairs is ever compared, so a collision is as good as impossible.
"""

from __future__ import annotations

from collections.abc import Iterable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import Relation, bits

#: Sampled rows of an attribute's slice of classes, at most, and cells of all slices; sort orders that an attribute leads.
SLICE_ROWS, SLICE_CELLS, SORTS = 25_000, 12_000_000, 4
#: Threads of the driver that sort a sample.
SORTERS = 8
#: Rows and cells that are drawn evenly, for lower bounds of class counts.
COUNT_ROWS, COUNT_CELLS = 200_000, 3_000_000
#: Up to so many rows their classes are counted by sorting, beyond by a bit table of so many slots.
SORTED_ROWS, COUNT_SLOTS = 20_000, 1 << 23
#: Different rows up to which all pairs may be compared; for relations of few of them.
ALL_PAIRS_ROWS = 2_000
WORD_BITS = 62


def codes(rel: Relation) -> Column:
    """Codes of all attributes of a row of the coded relation, in order."""
    return F.array(*[F.col(f"_1_{i}") for i in range(rel.m)])


def mask_between(a: list[int], b: list[int]) -> int:
    return sum(1 << i for i, (x, y) in enumerate(zip(a, b, strict=True)) if x != y)


def difference_words(rel: Relation, left: str, right: str) -> Column:
    """The difference set of two rows of a join as words of 62 bits, in DataFrame functions; null equals null."""
    flags = [F.when(F.col(f"{left}.`{c}`").eqNullSafe(F.col(f"{right}.`{c}`")), F.lit(0)).otherwise(F.lit(1)).cast("long") for c in rel.columns]
    words = [flags[i : i + WORD_BITS] for i in range(0, len(flags), WORD_BITS)]
    return F.array(*[reduce(lambda x, y: x.bitwiseOR(y), [F.shiftleft(f, k) for k, f in enumerate(w)]) for w in words])


def all_difference_sets(rel: Relation, most_rows: int = ALL_PAIRS_ROWS) -> DataFrame:
    """words, support: of every pair of rows, exactly. Equal rows are combined first, so a pair of different rows stands for as many pairs as it repeats; quadratic
    in the different rows, so refused beyond most_rows of these."""
    classes = rel.df.groupBy(*[rel.col(i) for i in range(rel.m)]).agg(F.count(F.lit(1)).alias("_n"))
    if classes.limit(most_rows + 1).count() > most_rows:
        raise ValueError(f"more than {most_rows} different rows")
    pairs = classes.alias("l").crossJoin(classes.alias("r")).select(difference_words(rel, "l", "r").alias("words"), F.col("l._n").alias("a"), F.col("r._n").alias("b"))
    # each pair is met in both orders, and so are the pairs of equal rows
    met = F.sum(F.when(F.forall("words", lambda w: w == 0), F.col("a") * (F.col("a") - 1)).otherwise(F.col("a") * F.col("b")))
    return pairs.groupBy("words").agg(met.alias("met")).where("met > 0").select("words", F.expr("met div 2").alias("support"))


def mask_of_words(words: list[int]) -> int:
    return sum(w << (WORD_BITS * k) for k, w in enumerate(words))


@dataclass
class Sample:
    """Rows on the driver, as small integers for each attribute's values, and for each attribute the rows of its slice of classes. whole: each different row of the relation."""

    rows: np.ndarray
    slices: list[np.ndarray]
    whole: bool = False

    @classmethod
    def of(cls, rows: np.ndarray) -> Sample:
        return cls(rows, [np.arange(len(rows))] * rows.shape[1])

    def __len__(self) -> int:
        return len(self.rows)


def _draw(seed: int, *columns: str) -> Column:
    return F.pmod(F.xxhash64(*[F.col(c) for c in columns], F.lit(seed)), F.lit(1 << 30)) / float(1 << 30)


def take_sample(rel: Relation, n: int, cards: list[int], slice_rows: int = SLICE_ROWS, seed: int = 20) -> Sample:
    """A bounded number of rows, the same in every run.

    Of each attribute, a slice of its *classes* is taken whole, and where that slice holds more than its share of rows (few or large classes), a hash
    sample of it; so near-keys and two-valued columns both give pairs that agree. Some more rows are drawn evenly, for counts. A first narrow
    pass counts what the slices hold, so that a class with a third of all rows can't flood the driver; repeated rows are combined before they are sent."""
    m = rel.m
    if n < 2 or not m:
        return Sample.of(np.zeros((0, m), np.int32))
    if rel.held is not None:
        return rel.held.sample(slice_rows, seed)
    each = max(64, min(slice_rows, SLICE_CELLS // (m * m)))
    own = [F.pmod(F.xxhash64(F.col(f"_2_{i}"), F.lit(5)), F.lit(max(1, min(max(1, cards[i] // 4), n // each)))) == 0 for i in range(m)]
    held = rel.coded.agg(*[F.coalesce(F.sum(own[i].cast("long")), F.lit(0)).alias(f"n{i}") for i in range(m)]).first()
    row = _draw(seed, *[f"_1_{i}" for i in range(m)])
    taken = [own[i] & (F.col("draw") < each / max(1, held[f"n{i}"])) for i in range(m)]
    words = [reduce(lambda x, y: x.bitwiseOR(y), [F.when(taken[i], F.lit(1 << (i % WORD_BITS))).otherwise(F.lit(0)).cast("long") for i in range(w, min(w + WORD_BITS, m))]) for w in range(0, m, WORD_BITS)]
    counted = min(COUNT_ROWS, COUNT_CELLS // m)
    some = rel.coded.withColumn("draw", row).select(codes(rel).alias("codes"), F.array(*words).alias("of"), "draw")
    some = some.where(reduce(lambda x, y: x | y, [F.col("of")[i] != 0 for i in range(len(words))], F.col("draw") < counted / n)).select("codes", "of").distinct()
    picked = some.toArrow()
    flat, flags = (picked.column(c).combine_chunks().flatten().to_numpy().reshape(picked.num_rows, -1) for c in ("codes", "of"))
    order = np.lexsort(flat.T[::-1]) if len(flat) else np.zeros(0, np.int64)
    dense = np.stack([np.unique(flat[order, i], return_inverse=True)[1].astype(np.int32) for i in range(m)], axis=1)
    # of so few rows every slice is everything
    return Sample(dense, [np.flatnonzero(flags[order, i // WORD_BITS] >> np.int64(i % WORD_BITS) & 1) for i in range(m)], n <= each)


def _class_keys(rows: np.ndarray, lhs: int) -> np.ndarray:
    key = np.zeros(len(rows), np.uint64)
    for i in bits(lhs):
        key = (key ^ rows[:, i].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(29)
    return key


def distinct_in_sample(rows: np.ndarray, lhs: int) -> int:
    """At least so many classes of the sampled rows, and never more than the relation has: a safe lower bound. Keys that share a slot only lower it."""
    keys = _class_keys(rows, lhs)
    if len(keys) <= SORTED_ROWS:
        return len(np.unique(keys))
    seen = np.zeros(COUNT_SLOTS, bool)
    seen[keys & np.uint64(COUNT_SLOTS - 1)] = True
    return int(np.count_nonzero(seen))


def _masks(differ: np.ndarray) -> set[int]:
    if not len(differ):
        return set()
    packed = np.packbits(differ, axis=1, bitorder="little")
    if packed.shape[1] <= 8:
        # one word a row sorts as numbers
        return set(np.unique(np.pad(packed, ((0, 0), (0, 8 - packed.shape[1]))).view("<u8")).tolist()) - {0}
    return {int.from_bytes(b.tobytes(), "little") for b in np.unique(packed, axis=0)} - {0}


def edges_of_sample(sample: Sample, sorts: int = SORTS, seed: int = 20) -> set[int]:
    """Difference sets of neighbours in sort orders that each attribute leads in turn, over its slice: they agree on long prefixes, so their difference sets are small and say most.
    sorts=0: neighbours in one class order of each attribute alone, as little evidence as a sampling phase may give."""
    rng, found = np.random.default_rng(seed), set()
    m = sample.rows.shape[1]
    if not sorts:
        for i in range(m):
            rows = sample.rows[sample.slices[i]]
            at = rows[np.argsort(rows[:, i], kind="stable")]
            found |= _masks(at[1:] != at[:-1])
        return found
    some = sample.rows[:: max(1, len(sample) // SLICE_ROWS)]
    orders = []
    for lead in [*range(m), *[None] * sorts]:
        for _ in range(sorts if lead is not None else 1):
            order = rng.permutation(m).tolist()
            orders.append((lead, order if lead is None else [lead, *[x for x in order if x != lead]]))

    def neighbours(lead: int | None, order: list[int]) -> set[int]:
        rows = some if lead is None else sample.rows[sample.slices[lead]]
        at = rows[np.lexsort([rows[:, x] for x in reversed(order[:8])])]
        return _masks(at[1:] != at[:-1]) | _masks(at[2:] != at[:-2])

    # sorting leaves the interpreter's lock
    with ThreadPoolExecutor(SORTERS) as pool:
        return found.union(*pool.map(neighbours, *zip(*orders, strict=True)))


def refute_on_sample(sample: Sample, cards: list[int], lhs: int, rhs: int, most: int = 16) -> set[int]:
    """Difference sets of sampled rows that agree on lhs and differ on rhs, of the slice of lhs's attribute with most classes: whole classes of it are there, hence
    of lhs too. Neighbours when sorted by class, then rhs. Empty if the sample doesn't refute."""
    if lhs:
        lead = max(bits(lhs), key=lambda i: cards[i])
        rows = sample.rows[sample.slices[lead]]
    else:
        rows = sample.rows
    left = list(bits(lhs))
    at = rows[np.lexsort((rows[:, rhs], _class_keys(rows, lhs)))]
    differ = at[1:] != at[:-1]
    differ = differ[differ[:, rhs] & ~differ[:, left].any(axis=1)]
    return _masks(differ[np.argsort(differ.sum(axis=1), kind="stable")[:most]])


def refute_on_sample_all(sample: Sample, cards: list[int], candidates: list[tuple[int, int]]) -> list[set[int]]:
    """The same for many (lhs, rhs)."""
    if len(candidates) < 2:
        return [refute_on_sample(sample, cards, lhs, a) for lhs, a in candidates]
    with ThreadPoolExecutor(SORTERS) as pool:
        return list(pool.map(lambda c: refute_on_sample(sample, cards, *c), candidates))


def check_on_sample(sample: Sample, lhs: int, rhs: int, most: int = 16) -> tuple[int, set[int]]:
    """(classes of lhs, difference sets that break lhs -> rhs) in a sample that is the whole relation; no such set if the dependency holds."""
    left = list(bits(lhs))
    at = sample.rows[np.lexsort([sample.rows[:, i] for i in (rhs, *left)])]
    differ = at[1:] != at[:-1]
    same = ~differ[:, left].any(axis=1)
    broken = differ[same & differ[:, rhs]]
    return len(at) - int(same.sum()), _masks(broken[np.argsort(broken.sum(axis=1), kind="stable")[:most]])


def sample_difference_sets(rel: Relation, n: int, cards: list[int], slice_rows: int = SLICE_ROWS, sorts: int = SORTS, seed: int = 20) -> set[int]:
    """Difference sets of sampled row pairs that agree on some attributes."""
    sample = take_sample(rel, n, cards, slice_rows, seed)
    return edges_of_sample(sample, sorts, seed) if len(sample) else set()


def violating_edges(rel: Relation, broken: Iterable[tuple[int, int, tuple[int, int]]]) -> dict[tuple[int, int], int]:
    """For refuted candidates (lhs, attribute, fingerprints of a class that breaks it): the difference set of two rows of that class that differ on the
    attribute. One scan for all of them, with two conditional aggregates each and no shuffle but that of the aggregates."""
    broken = list(broken)
    if not broken:
        return {}
    aggs, anywhere = [], F.lit(False)
    for k, (lhs, a, (x1, x2)) in enumerate(broken):
        key = rel.key(lhs)
        here = (key[0] == F.lit(x1)) & (key[1] == F.lit(x2))
        anywhere = anywhere | here
        order = F.when(here, F.struct(F.col(f"_1_{a}").alias("v"), F.col("_codes").alias("c")))
        aggs += [F.min(order).alias(f"lo{k}"), F.max(order).alias(f"hi{k}")]
    row = rel.coded.where(anywhere).withColumn("_codes", codes(rel)).agg(*aggs).first()
    found = {}
    for k, (lhs, a, _) in enumerate(broken):
        edge = mask_between(row[f"lo{k}"]["c"], row[f"hi{k}"]["c"])
        if edge & lhs or not edge >> a & 1:
            raise RuntimeError("a refuted candidate gave no pair of rows that refutes it")
        found[lhs, a] = edge
    return found


def lag_pairs(df: DataFrame, within: list[str], order_by: list[str], columns: list[str], lag: int = 1) -> DataFrame:
    """attrs (names of columns that differ, comma-separated, sorted), support: over pairs of rows `lag` places apart in their class of `within`. Each class is sorted in
    one task, so `within` has to be of many classes; order_by has to be unique in a class for reruns to agree."""
    window = Window.partitionBy(*[F.col(f"`{c}`") for c in within]).orderBy(*[F.col(f"`{c}`") for c in order_by])
    row = F.struct(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(columns)])
    pairs = df.select(row.alias("own"), F.lag(row, lag).over(window).alias("other")).where("other IS NOT NULL")
    differ = [F.when(~F.col(f"own.c{i}").eqNullSafe(F.col(f"other.c{i}")), F.lit(c)) for c, i in sorted((c, i) for i, c in enumerate(columns))]
    return pairs.groupBy(F.concat_ws(",", *differ).alias("attrs")).agg(F.count(F.lit(1)).alias("support"))


def induce(edges: Iterable[int], rhs: int) -> set[int]:
    """Edges with the attribute, without it: what a left-hand side has to hit. An empty one means that nothing determines the attribute."""
    return {e & ~(1 << rhs) for e in edges if e >> rhs & 1}


def minimise(edges: Iterable[int]) -> list[int]:
    """Inclusion-minimal edges, smallest first: hitting these hits all."""
    left = sorted(set(edges), key=lambda e: (e.bit_count(), e))
    if not left or left[0] == 0:
        return left[:1]
    words = words_of(left)
    kept: list[int] = []
    at = np.arange(len(left))
    while len(at):
        kept.append(left[at[0]])
        first = words[at[0]]
        at = at[((words[at] & first) != first).any(axis=1)]
    return kept


def words_of(masks: list[int]) -> np.ndarray:
    """uint64[masks, words], 62 bits a word."""
    n = max(1, -(-max((x.bit_length() for x in masks), default=1) // WORD_BITS))
    low = (1 << WORD_BITS) - 1
    return np.array([[x >> (WORD_BITS * k) & low for k in range(n)] for x in masks], np.uint64).reshape(len(masks), n)


def edge_frame(rel: Relation, edges: Iterable[int], rhs: int | None = None) -> DataFrame:
    """attrs (sorted names joined by commas), size, and the right-hand side if given."""
    rows = [(rel.lhs_text(e), e.bit_count(), None if rhs is None else rel.columns[rhs]) for e in sorted(edges)]
    return rel.df.sparkSession.createDataFrame(rows, "attrs string, size int, rhs string")


def snapshot(rel: Relation) -> str:
    """Names the rows of a relation, whatever their order: their number, attributes, and a sum of row hashes, in one narrow pass."""
    total = rel.coded.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64(*[F.col(f"_{s}_{i}") for i in range(rel.m) for s in (1, 2)]).cast("decimal(38,0)")).alias("h")).first()
    return f"{total['n']}:{','.join(rel.columns)}:{total['h'] or 0}"


def save_evidence(rel: Relation, edges: Iterable[int], path: str) -> None:
    """With the snapshot of the rows that they were found in: an edge is a fact about two of them."""
    mark = snapshot(rel)
    rows = [(mark, [rel.columns[i] for i in bits(e)]) for e in sorted(edges)]
    rel.df.sparkSession.createDataFrame(rows or [(mark, None)], "snapshot string, attrs array<string>").write.mode("overwrite").parquet(path)


def load_evidence(rel: Relation, path: str) -> set[int]:
    """Stored edges over this relation's columns; an error if the rows aren't those that they were found in."""
    at = {c: i for i, c in enumerate(rel.columns)}
    rows = rel.df.sparkSession.read.parquet(path).collect()
    if {r["snapshot"] for r in rows} != {snapshot(rel)}:
        raise ValueError("stored evidence belongs to other rows")
    return {sum(1 << at[c] for c in r["attrs"]) for r in rows if r["attrs"] is not None}
