"""Exact top-k search by pivot tables.

Inner products become distances: with M the largest norm, a candidate x gets one more coordinate sqrt(M^2 - |x|^2) and a
query q gets 0, so that |q'-x'|^2 = |q|^2 + M^2 - 2 q.x. Every candidate's distances to some pivots are computed once and stored with
it. |d(q',p) - d(x',p)| bounds d(q',x') from below for each pivot p; the largest of these bounds bounds the score from above.

1. Candidates are dealt to cells by their nearest pivot, and by their second nearest where the table is large. A cell keeps the interval of its rows' distances to each
   pivot, which bounds the score of all its rows at once; there are at most PIVOTS squared cells, however many rows.
2. Each query is sent to its most promising cell and comes back with its k-th best score there.
3. It is then sent to those other cells alone whose bound reaches that score. Cells beyond CANDIDATE_BLOCK rows are dealt to several tasks.

In a task, a query's candidates are evaluated in order of their own bound until the k-th best score exceeds every bound that is left. Queries move, not
the table: a candidate is copied only where more than QUERY_BLOCK queries want its cell. A task's memory doesn't depend on the input, and tasks
return k rows a query, which are merged. All components are floor(256 * x) and scores are exact integers.

Vectors that are null, empty or hold a null or non-finite component take no part, nor do those whose length as integers is 2^31 or more, as their scores need not fit a
long. Vectors of different length are compared as if the shorter ended in zeros. Copies are one candidate with its smallest ids. Repeated rows with
one id are one row; an id with several vectors counts by its best score. Fewer than k candidates give fewer rows; an empty table gives none.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table, written
from .vectors import finite, matrix, smallest_ids

PIVOTS, QUERY_BLOCK, CANDIDATE_BLOCK, STEP = 32, 8192, 16_384, 64
#: Squared length of integer vectors from which on a score need not fit a long.
LONGEST = float(2**62)


def integers(rows: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """vec_id, vec: floor(256 * x) of each component, of the vectors that take part."""
    floors = F.transform(embedding, lambda x: F.floor(F.least(F.greatest(x.cast("double") * 256, F.lit(-4e18)), F.lit(4e18))).cast("double"))
    short = F.aggregate(floors, F.lit(0.0), lambda s, x: s + x * x) < LONGEST
    return rows.where(finite(embedding) & F.col(vec_id).isNotNull() & short).select(F.col(vec_id).cast("long").alias("vec_id"), F.transform(floors, lambda x: x.cast("long")).alias("vec"))


def choose_pivots(candidates: DataFrame, n: int) -> list[list[int]]:
    """n candidates far apart: the greedy farthest-first choice among a bounded sample of 32 n, taken by hash."""
    sample = [r["vec"] for r in candidates.orderBy(F.xxhash64("vec"), "vec").select("vec").limit(32 * n).collect()]
    if not sample:
        return []
    width = max(map(len, sample))
    m = np.array([v + [0] * (width - len(v)) for v in sample], float)
    picked, far = [0], np.linalg.norm(m - m[0], axis=1)
    while len(picked) < min(n, len(m)) and far.max() > 0:
        picked.append(int(far.argmax()))
        far = np.minimum(far, np.linalg.norm(m - m[picked[-1]], axis=1))
    return [sample[i] for i in picked]


def pivot_table(candidates: DataFrame, pivots: list[list[int]], top: float, pairs: bool = False) -> DataFrame:
    """candidates(vec, ids) with to_pivots: distances, in the space with one more coordinate, to the pivots (as points of that space); and the
    cell: the nearest pivot, or with `pairs` the two nearest."""
    p, lift_p = _points(pivots, top)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch.column(0))
                d = _distances(x, np.sqrt(np.maximum(0, top - (x * x).sum(axis=1))), p, lift_p)
                order = np.argsort(d, axis=1, kind="stable")
                cell = order[:, 0] * len(p) + order[:, 1] if pairs and len(p) > 1 else order[:, 0]
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.FixedSizeListArray.from_arrays(pa.array(d.ravel()), len(p)).cast(pa.list_(pa.float64())), pa.array(cell.astype(np.int32))], ["vec", "ids", "to_pivots", "cell"])

    return candidates.select("vec", "ids").mapInArrow(run, "vec array<long>, ids array<long>, to_pivots array<double>, cell int")


def _points(pivots: list[list[int]], top: float) -> tuple[np.ndarray, np.ndarray]:
    """The pivots and their further coordinate."""
    width = max(map(len, pivots), default=0)
    p = np.array([v + [0] * (width - len(v)) for v in pivots], float).reshape(len(pivots), width)
    return p, np.sqrt(np.maximum(0, top - (p * p).sum(axis=1)))


def _upper(gap: np.ndarray, norm: np.ndarray | float, top: float) -> np.ndarray:
    """No score is larger, given the distance that is certain; rounding of the distances never hides a candidate."""
    return (norm + top - gap * gap) / 2 + 1e-9 * (norm + top) + 0.5


def _ranked_cells(queries: DataFrame, pivots: list[list[int]], top: float, cells: list[tuple]) -> DataFrame:
    """queries(query_id, vec) with the cells in order of their bounds, best first, and these bounds. cells: (cell, least distances, largest distances), of a bounded number."""
    p, lift_p = _points(pivots, top)
    names = np.array([c[0] for c in cells], np.int32)
    low, high = (np.array([c[k] for c in cells], float) for k in (1, 2))

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                q = matrix(batch.column(1))
                near = _distances(q, np.zeros(len(q)), p, lift_p)
                gap = np.stack([np.maximum(0, np.maximum(low - row, row - high)).max(axis=1) for row in near])
                bound = _upper(gap, (q * q).sum(axis=1)[:, None], top)
                order = np.argsort(-bound, axis=1, kind="stable")
                lists = [pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), len(names)).cast(pa.list_(kind)) for x, kind in ((names[order], pa.int32()), (np.take_along_axis(bound, order, 1), pa.float64()))]
                yield pa.RecordBatch.from_arrays([*batch.columns, *lists], ["query_id", "vec", "cells", "bounds"])

    return queries.select("query_id", "vec").mapInArrow(run, "query_id long, vec array<long>, cells array<int>, bounds array<double>")


def _same_width(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    width = max(a.shape[1], b.shape[1])
    return tuple(x if x.shape[1] == width else np.pad(x, ((0, 0), (0, width - x.shape[1]))) for x in (a, b))


def _distances(x: np.ndarray, lift: np.ndarray, p: np.ndarray, lift_p: np.ndarray) -> np.ndarray:
    x, p = _same_width(x, p)
    return np.sqrt(np.stack([((x - row) ** 2).sum(axis=1) + (lift - up) ** 2 for row, up in zip(p, lift_p, strict=True)], axis=1))


def search_block(k: int, pivots: list[list[int]], top: float) -> Callable[[pa.Table, pa.Table], pa.Table]:
    """Queries (query_id, vec, least: the score that they have already, or null) and candidates of one task -> each query's k best among them that reach it."""
    p, lift_p = _points(pivots, top)

    def of(queries: pa.Table, candidates: pa.Table) -> pa.Table:
        out: list[tuple[int, int, int]] = []
        seen = 0
        if len(queries) and len(candidates):
            q, x = _same_width(matrix(queries.column("vec"), np.int64), matrix(candidates.column("vec"), np.int64))
            big = float(np.abs(x).max(initial=0)) * float(np.abs(q).max(initial=0)) * x.shape[1] >= 2**53
            xf = x.astype(object) if big else x.astype(float)
            to_pivots = matrix(candidates.column("to_pivots"))
            near = _distances(q.astype(float), np.zeros(len(q)), p, lift_p)
            ids = candidates.column("ids").to_pylist()
            for i, (own, least) in enumerate(zip(queries.column("query_id").to_pylist(), queries.column("least").to_pylist(), strict=True)):
                gap = np.abs(to_pivots - near[i]).max(axis=1)
                bound = _upper(gap, float((q[i].astype(float) ** 2).sum()), top)
                order = np.argsort(-bound, kind="stable")
                qi = q[i].astype(object) if big else q[i].astype(float)
                best: list[tuple[int, int]] = []
                a, step = 0, STEP
                while a < len(order):
                    if least is not None and bound[order[a]] < least:
                        break
                    some = order[a : a + step]
                    a, step = a + step, min(2 * step, 2048)
                    seen += len(some)
                    scores = xf[some] @ qi
                    if least is not None:
                        good = np.flatnonzero(scores >= least)
                        scores, some = scores[good], some[good]
                    best += [(-int(s), v) for s, c in zip(scores.tolist(), some.tolist(), strict=True) for v in ids[c] if v != own]
                    best = _first_of_each(sorted(best), k)
                    if len(best) == k:
                        least = -best[-1][0] if least is None else max(least, -best[-1][0])
                out += [(own, v, -s) for s, v in best]
        cols = list(zip(*out, strict=True)) if out else [(), (), ()]
        return pa.table({"query_id": pa.array(cols[0], pa.int64()), "vec_id": pa.array(cols[1], pa.int64()), "score": pa.array(cols[2], pa.int64()), "evaluated": pa.array([seen] * len(cols[0]), pa.int64())})

    return of


def _first_of_each(best: list[tuple[int, int]], k: int) -> list[tuple[int, int]]:
    """The k best of different ids."""
    kept: dict[int, int] = {}
    for s, v in best:
        if v not in kept:
            kept[v] = s
            if len(kept) == k:
                break
    return [(s, v) for v, s in kept.items()]


def top_k(rows: DataFrame, is_query: Column, k: int, pivots: int = PIVOTS, query_block: int = QUERY_BLOCK, candidate_block: int = CANDIDATE_BLOCK) -> DataFrame:
    """rows(vec_id, vec of integers) -> query_id, rank, vec_id, score, evaluated (by the task that found it, over its queries)."""
    queries = written(rows.where(is_query).select(F.col("vec_id").alias("query_id"), "vec").distinct())
    distinct = written(smallest_ids(rows, k))
    facts = distinct.agg(F.count(F.lit(1)).alias("n"), F.max(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))).alias("top")).first()
    schema = "query_id long, vec_id long, score long, evaluated long"
    chosen = choose_pivots(distinct, pivots)
    if not chosen:
        empty = rows.sparkSession.createDataFrame([], schema)
        return empty.select("query_id", F.lit(1).alias("rank"), "vec_id", "score", "evaluated")
    top = float(facts["top"])
    stored = written(pivot_table(distinct, chosen, top, facts["n"] > len(chosen) * candidate_block))
    ends = [f(F.element_at("to_pivots", i + 1)).alias(f"{name}{i}") for i in range(len(chosen)) for name, f in (("low", F.min), ("high", F.max))]
    cells = stored.groupBy("cell").agg(F.count(F.lit(1)).alias("n"), *ends).collect()  # at most the square of the pivots' number
    parts = {r["cell"]: -(-r["n"] // candidate_block) for r in cells}
    n_parts = F.element_at(F.create_map(*[F.lit(int(x)) for kv in parts.items() for x in kv]), F.col("cell"))
    ranked = written(_ranked_cells(queries, chosen, top, [(r["cell"], [r[f"low{i}"] for i in range(len(chosen))], [r[f"high{i}"] for i in range(len(chosen))]) for r in cells]))
    candidates = stored.withColumn("part", F.pmod(F.xxhash64("vec"), n_parts).cast("int"))

    def searched(wanted: DataFrame) -> DataFrame:
        """wanted(query_id, vec, least, cell): every query against all rows of its cell. Cells that many queries want hold their rows once for each block of queries."""
        many = wanted.groupBy("cell").agg(F.ceil(F.count(F.lit(1)) / F.lit(query_block)).cast("int").alias("blocks")).where(F.col("blocks") > 1).collect()
        blocks = F.coalesce(F.try_element_at(F.create_map(*[F.lit(int(r[c])) for r in many for c in ("cell", "blocks")]), F.col("cell")), F.lit(1)) if many else F.lit(1)
        q = wanted.withColumn("part", F.explode(F.sequence(F.lit(0), n_parts.cast("int") - 1))).withColumn("block", F.pmod(F.xxhash64("query_id"), blocks).cast("int"))
        c = candidates.withColumn("block", F.explode(F.sequence(F.lit(0), blocks - 1)))
        return q.groupBy("cell", "part", "block").cogroup(c.groupBy("cell", "part", "block")).applyInArrow(search_block(k, chosen, top), schema)

    best = lambda found: found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"), F.max("evaluated").alias("evaluated"))
    home = written(searched(ranked.select("query_id", "vec", F.lit(None).cast("long").alias("least"), F.element_at("cells", 1).alias("cell"))))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    least = best(home).withColumn("rank", rank).where(F.col("rank") == k).select(F.col("query_id").alias("of"), F.col("score").alias("least"))
    rest = ranked.join(least, F.col("query_id") == F.col("of"), "left").select("query_id", "vec", "least", F.posexplode(F.arrays_zip("cells", "bounds")).alias("place", "at"))
    rest = rest.where((F.col("place") > 0) & (F.col("least").isNull() | (F.col("at.bounds") >= F.col("least")))).select("query_id", "vec", "least", F.col("at.cells").alias("cell"))
    found = best(home.unionByName(searched(rest)))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", "evaluated")


def op1_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = integers(table(spark, sf_dir, "embeddings"))
    return top_k(rows, F.col("vec_id") % 50 == 0, 5).select("query_id", "rank", "vec_id", "score")


ORACLE = r"""
WITH v AS (
  SELECT DISTINCT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS e
  FROM embeddings WHERE len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda z: z[1] * z[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id),
ranked AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM scored)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 5
"""
