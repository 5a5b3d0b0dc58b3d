"""Candidates checked where their classes lie together: rows are dealt out by some attributes that several left-hand sides share, so that every class of these is in one
task, which sorts 128-bit keys. One shuffle of narrow rows serves all left-hand sides that hold these attributes, and only counts and a few pairs leave a task."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa

from ..model import Relation, bits
from ..ship import ship

#: Rows of a task, about, and those beyond which it leaves its left-hand sides to the hash aggregation (a class with a large part of all rows).
TASK_ROWS, MOST_TASK_ROWS = 250_000, 4_000_000
#: Classes that the attributes by which rows are dealt should have for each task, so that tasks are of one size.
CLASSES_A_TASK = 64
#: Attributes up to which rows are sent whole, so that a task gives difference sets too; and classes of a refuted candidate that give one.
WHOLE_ROWS, EXAMPLES = 16, 8

Entry = tuple[int, list[int]]
VERDICTS = "s int, i int, card long, keys array<long>, edges array<binary>, codes array<long>"


def deal(entries: Iterable[Entry], cards: list[int], tasks: int) -> tuple[dict[int, list[int]], list[int]]:
    """(attributes to deal rows by -> places of entries, places of the entries that have too few classes for that)."""
    entries = list(entries)
    own: list[int | None] = []
    for lhs, _ in entries:
        by, classes = 0, 1
        for a in sorted(bits(lhs), key=lambda a: (-cards[a], a)):
            if classes >= CLASSES_A_TASK * tasks:
                break
            by, classes = by | 1 << a, classes * cards[a]
        own.append(by if by and classes >= CLASSES_A_TASK * tasks else None)
    left, groups = {k for k, by in enumerate(own) if by is not None}, {}
    while left:
        # the one that serves most of what is left
        fits = {by: [k for k in sorted(left) if entries[k][0] & by == by] for by in {own[k] for k in left}}
        by = min(fits, key=lambda x: (-len(fits[x]), x))
        groups[by] = fits[by]
        left -= set(fits[by])
    return groups, [k for k, by in enumerate(own) if by is None]


def _mixed(codes: Iterable[np.ndarray], n: int) -> np.ndarray:
    key = np.zeros(n, np.uint64)
    for c in codes:
        key = (key ^ c.view(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(29)
    return key


def judge(first: dict[int, np.ndarray], second: dict[int, np.ndarray], n: int, entries: Iterable[tuple[int, int, list[int]]], m: int | None) -> Iterator[tuple]:
    """Rows of VERDICTS for (place, lhs, right-hand sides) over one task's rows: codes by attribute. m: rows are whole, so a refuted candidate gets the difference sets of
    the pairs with the least and the greatest right-hand value in its first classes; else the codes of its first class."""
    for s, lhs, rhs in entries:
        left = list(bits(lhs))
        one, two = (_mixed([codes[i] for i in left], n) for codes in (first, second))
        order = np.argsort(one, kind="stable")
        a, b = one[order], two[order]
        same, agree = a[1:] == a[:-1], b[1:] == b[:-1]
        if (same & ~agree).any():
            order = np.lexsort((two, one))
            a, b = one[order], two[order]
            same = (a[1:] == a[:-1]) & (b[1:] == b[:-1])
        # the class of each place, so that a place's class is a range
        starts = np.flatnonzero(np.concatenate([[True], ~same]))
        for i, x in enumerate(rhs):
            v = first[x][order]
            at = np.flatnonzero(same & (v[1:] != v[:-1]))
            keys, edges, codes = [], [], []
            if len(at):
                broken = np.unique(np.searchsorted(starts, at, side="right") - 1)[: EXAMPLES if m else 1]
                for c in broken.tolist():
                    keys.append(int(a[starts[c]].view(np.int64)))
                    rows = order[starts[c] : starts[c + 1] if c + 1 < len(starts) else n]
                    if m:
                        by = [x, *(j for j in range(m) if j != x)]
                        sorted_rows = rows[np.lexsort([first[j][rows] for j in reversed(by)])]
                        lo, hi = sorted_rows[0], sorted_rows[-1]
                        edges.append(sum(1 << j for j in range(m) if first[j][lo] != first[j][hi]).to_bytes(-(-m // 8), "little"))
                    else:
                        codes = [int(c[j][rows[0]]) for c in (first, second) for j in left]
            yield s, i, len(starts), keys, edges, codes


def verdict_rows(rel: Relation, entries: list[Entry], n: int, cards: list[int]) -> tuple[dict[tuple[int, int], tuple], list[int]]:
    """((place of an entry, place of its right-hand side) -> (classes, difference sets, codes of a class that breaks it), places of the entries that are left to others)."""
    spark = rel.df.sparkSession
    ship(spark)
    tasks = max(spark.sparkContext.defaultParallelism, -(-n // TASK_ROWS))
    groups, rest = deal(entries, cards, tasks)
    m = rel.m if rel.m <= WHOLE_ROWS else None
    frames = []
    for by, places in groups.items():
        lhs_all, all_ = 0, 0
        for k in places:
            lhs_all |= entries[k][0]
            all_ |= entries[k][0] | sum(1 << a for a in entries[k][1])
        one, two = list(range(rel.m)) if m else list(bits(all_)), list(bits(lhs_all))
        asked = [(k, *entries[k]) for k in places]
        dealt = rel.coded.select(*[f"_1_{i}" for i in one], *[f"_2_{i}" for i in two]).repartition(tasks, *[f"_2_{i}" for i in bits(by)])
        frames.append(dealt.mapInArrow(_task(one, two, asked, m), VERDICTS))
    found: dict[tuple[int, int], list] = {}
    if frames:
        whole = frames[0]
        for f in frames[1:]:
            whole = whole.unionAll(f)
        for r in whole.collect():
            if r["card"] < 0:
                rest.append(r["s"])
                continue
            x = found.setdefault((r["s"], r["i"]), [0, [], None])
            x[0] += r["card"]
            x[1] += zip(r["keys"], map(bytes, r["edges"]), strict=False)
            if r["codes"]:
                # of the class with the least key, however rows were dealt out
                x[2] = min((y for y in (x[2], (r["keys"][0], r["codes"])) if y is not None), key=lambda y: y[0])
    left = set(rest)
    out = {}
    for (s, i), (card, pairs, codes) in found.items():
        if s not in left:
            out[s, i] = (card, tuple(dict.fromkeys(int.from_bytes(e, "little") for _, e in sorted(pairs)[:EXAMPLES])), codes and codes[1])
    # an entry without rows in any task has no class
    for k, (_, rhs) in enumerate(entries):
        if k not in left:
            for i in range(len(rhs)):
                out.setdefault((k, i), (0, (), None))
    return out, sorted(left)


def _task(one: list[int], two: list[int], asked: list[tuple[int, int, list[int]]], m: int | None):
    names = [f"_1_{i}" for i in one] + [f"_2_{i}" for i in two]

    def each(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for part in parts:
            n += part.num_rows
            if n <= MOST_TASK_ROWS:
                held.append(part)
            else:
                held.clear()
        if not n:
            return
        if n > MOST_TASK_ROWS:
            rows = [(s, 0, -1, [], [], []) for s, _, _ in asked]
        else:
            table = pa.Table.from_batches(held)
            columns = [table.column(k).to_numpy() for k in range(len(names))]
            held.clear()
            rows = judge(dict(zip(one, columns, strict=False)), dict(zip(two, columns[len(one) :], strict=True)), n, asked, m)
        types = [pa.int32(), pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.binary()), pa.list_(pa.int64())]
        yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), types, strict=True)], ["s", "i", "card", "keys", "edges", "codes"])

    return each
