"""Antichains on the executors: one task a right-hand side multiplies the edges in and sends its best candidates."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa

from ..operators.evidence import induce
from ..ship import ship
from .transversal import Antichain, Counters


def spread_candidates(run, rank: list[int], max_lhs: int | None, empty_lhs: bool, most: int) -> list[tuple[int, int, int, int, int]]:
    """(-bound, rank, size, lhs, rhs) of the best candidates of all right-hand sides, best first. What a task needs (edges, counts, threshold, sampled rows) is broadcast and
    bounded, whatever the number of rows; nothing is kept between rounds, so a lost executor costs one task."""
    spark, rel = run.rel.df.sparkSession, run.rel
    ship(spark)
    top = run.top
    state = spark.sparkContext.broadcast((run.edges, run.matrix, run.known, top.tau, top.any and top.k is not None and len(top.best) == top.k, top.k is None))
    m, batch = rel.m, run.batch

    def each(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        edges, matrix, known, tau, at_tau, everything = state.value

        def below(bound: int) -> bool:
            return not everything and (bound < tau or (at_tau and bound <= tau))

        for part in parts:
            for a in part.column(0).to_pylist():
                chain = Antichain(a, m, induce(edges, a), rank, matrix, Counters(), max_lhs, empty_lhs, below, most)
                if chain.overgrown:
                    raise MemoryError("an antichain outgrew its share of memory; use the trees")
                chain.settled |= {lhs for lhs, b in known if b == a}
                best = sorted(chain.candidates(below), key=lambda c: (-c[0], c[1].bit_count(), c[1]))[:batch]
                yield pa.RecordBatch.from_arrays([pa.array([a] * len(best), pa.int32()), pa.array([hex(x) for _, x in best], pa.string()), pa.array([b for b, _ in best], pa.int64())], ["rhs", "lhs", "bound"])

    rows = spark.range(m).selectExpr("int(id) AS rhs").repartition(m, "rhs").mapInArrow(each, "rhs int, lhs string, bound long").collect()
    state.destroy()
    found = [(-r["bound"], rank[r["rhs"]], int(r["lhs"], 16).bit_count(), int(r["lhs"], 16), r["rhs"]) for r in rows]
    return sorted(found)
