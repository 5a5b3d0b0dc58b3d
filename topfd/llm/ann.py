"""Approximate nearest neighbours by inner product: a forest of random-projection trees under one priority queue.

* Inner products become angles, as in the exact search: candidates are lifted to the norm of the longest one.
* Each tree splits a bounded sample at the median of a random projection until a leaf holds LEAF of its points. Every row of the table is filed in
  a leaf of each tree. Subtrees of bounded size, in rows, are boughs: what a task holds. Leaves beyond that size are dealt to several tasks.
* A query walks all trees at once: one queue holds the open branches of all of them, keyed by the smallest margin met on the way, and the
  best branch is opened next, until the leaves reached hold the wanted share of all (tree, row) entries. That share falls as the table grows, by
  SHARE * (SHARE_ROWS / rows) ** FALL, so the work of a query grows more slowly than the table.
* A bough scores its rows, leaf by leaf, for the queries that came there, on the original vectors in double precision. Its queries are dealt to several
  tasks where they are many. A query's home boughs, those of its first leaf in each tree, send their best k on; the k-th best of these is what rows of
  its other boughs have to reach to be sent at all. Merging all, without repeats from other trees, is the exact rerank of all candidates.

Vectors that are null, empty, zero or hold a null or non-finite component take no part. Copies are one candidate with its k + 1 smallest
ids, which loses no result. Vectors of different length are compared as if the shorter ended in zeros. Ties go to the smaller id.
If a query reaches fewer than k candidates, its queue opens further leaves, so small tables are searched whole. An empty table gives no row.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table, written
from .vectors import finite, matrix, smallest_ids

#: Sample rows, trees, sample points in a leaf.
SAMPLE, TREES, LEAF = 32_768, 8, 32
#: Share of all (tree, row) entries that a query's leaves have to hold: at so many rows, and the power by which it falls with more.
SHARE, SHARE_ROWS, FALL = 0.16, 2_000, 0.2
#: Rows of a bough, and queries that one task takes.
BOUGH_ROWS, QUERY_ROWS = 16_384, 16_384


def share_at(rows: int) -> float:
    """SHARE at SHARE_ROWS rows; more for smaller tables, less for larger ones."""
    return min(1.0, SHARE * (SHARE_ROWS / max(1, rows)) ** FALL)


@dataclass
class Forest:
    """Trees as flat arrays: node i splits by `normals[i]` at `cuts[i]`, its children are `below[i]` and `above[i]`; a negative child ~leaf is a leaf."""

    roots: list[int]
    normals: np.ndarray
    cuts: np.ndarray
    below: np.ndarray
    above: np.ndarray
    held: np.ndarray  # sample points of each leaf
    top: float

    def boughs(self, most: float) -> np.ndarray:
        """The bough of each leaf: largest subtrees of no more than `most` sample points, or single leaves."""
        out, n = np.zeros(len(self.held), np.int64), 0
        below_of: dict[int, list[int]] = {}

        def leaves(node: int) -> list[int]:
            if node < 0:
                return [~node]
            if node not in below_of:
                below_of[node] = leaves(int(self.below[node])) + leaves(int(self.above[node]))
            return below_of[node]

        queue = list(self.roots)
        while queue:
            node = queue.pop()
            some = leaves(node)
            if node < 0 or self.held[some].sum() <= most:
                out[some] = n
                n += 1
            else:
                queue += [int(self.below[node]), int(self.above[node])]
        return out

    def lift(self, x: np.ndarray) -> np.ndarray:
        """Candidates with the coordinate that makes all norms equal; queries get 0 there."""
        return np.sqrt(np.maximum(0, self.top - (x * x).sum(axis=1)))[:, None]

    def _fit(self, x: np.ndarray) -> np.ndarray:
        width = self.normals.shape[1]
        return x if x.shape[1] == width else np.pad(x[:, :width], ((0, 0), (0, max(0, width - x.shape[1]))))

    def leaves(self, x: np.ndarray) -> np.ndarray:
        """leaf of each row in each tree."""
        y = self._fit(np.hstack((x, self.lift(x))) if x.shape[1] + 1 == self.normals.shape[1] else np.hstack((np.pad(x, ((0, 0), (0, max(0, self.normals.shape[1] - 1 - x.shape[1]))))[:, : self.normals.shape[1] - 1], self.lift(x))))
        out = np.empty((len(x), len(self.roots)), np.int64)
        for t, root in enumerate(self.roots):
            node = np.full(len(x), root)
            while (inner := np.flatnonzero(node >= 0)).size:
                at = node[inner]
                side = np.einsum("ij,ij->i", y[inner], self.normals[at]) > self.cuts[at]
                node[inner] = np.where(side, self.above[at], self.below[at])
            out[:, t] = ~node
        return out

    def visits(self, q: np.ndarray, wanted: float) -> list[int]:
        """Leaves of all trees for one query, best margins first, until they hold `wanted` sample points."""
        width = self.normals.shape[1]
        y = np.zeros(width)
        y[: min(len(q), width - 1)] = q[: width - 1]
        margins = self.normals @ y - self.cuts
        queue = [(-np.inf, r) for r in self.roots]
        heapq.heapify(queue)
        found, held = [], 0
        while queue and held < wanted:
            cost, node = heapq.heappop(queue)
            while node >= 0:
                m = margins[node]
                near, far = (self.above[node], self.below[node]) if m > 0 else (self.below[node], self.above[node])
                heapq.heappush(queue, (max(cost, abs(m)), int(far)))
                node = int(near)
            found.append(~node)
            held += self.held[~node]
        return found


def plant(sample: np.ndarray, top: float, trees: int = TREES, leaf: int = LEAF, seed: int = 20) -> Forest:
    rng = np.random.default_rng(seed)
    lifted = np.hstack((sample, np.sqrt(np.maximum(0, top - (sample * sample).sum(axis=1)))[:, None]))
    normals, cuts, below, above, held, roots = [], [], [], [], [], []

    def grow(points: np.ndarray) -> int:
        if len(points) > leaf:
            for _ in range(3):
                a, b = lifted[rng.choice(points, 2, replace=False)]
                normal = a - b
                size = np.linalg.norm(normal)
                if not size:
                    continue
                normal = normal / size
                along = lifted[points] @ normal
                cut = float(np.median(along))
                low, high = points[along <= cut], points[along > cut]
                if len(low) and len(high):
                    at = len(normals)
                    normals.append(normal), cuts.append(cut), below.append(0), above.append(0)
                    below[at], above[at] = grow(low), grow(high)
                    return at
        held.append(len(points))
        return ~(len(held) - 1)

    for _ in range(trees):
        roots.append(grow(np.arange(len(lifted))))
    width = lifted.shape[1]
    return Forest(roots, np.array(normals).reshape(-1, width), np.array(cuts), np.array(below, int), np.array(above, int), np.array(held), top)


def _filed(distinct: DataFrame, forest, boughs) -> DataFrame:
    """vec, ids, leaf, bough: one row for each tree."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                leaves = forest.value.leaves(matrix(batch.column(0)))
                lists = [pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), leaves.shape[1]).cast(pa.list_(pa.int64())) for x in (leaves, boughs.value[leaves])]
                yield pa.RecordBatch.from_arrays([*batch.columns, *lists], ["vec", "ids", "leaves", "boughs"])

    filed = distinct.select("vec", "ids").mapInArrow(run, f"vec {distinct.schema['vec'].dataType.simpleString()}, ids array<long>, leaves array<long>, boughs array<long>")
    return filed.select("vec", "ids", F.explode(F.arrays_zip("leaves", "boughs")).alias("at")).select("vec", "ids", F.col("at.leaves").alias("leaf"), F.col("at.boughs").alias("bough"))


def _routed(queries: DataFrame, forest, boughs, wanted: float) -> DataFrame:
    """query_id, mark, bough, home, leaves: what a query visits of each bough. The vector itself isn't repeated here."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                rows: list[tuple] = []
                for q, own, mark in zip(matrix(batch.column(1)), batch.column(0).to_pylist(), batch.column(2).to_pylist(), strict=True):
                    found = np.array(forest.value.visits(q, wanted), np.int64)
                    at = boughs.value[found]
                    order = np.argsort(at, kind="stable")
                    cuts = np.flatnonzero(np.diff(at[order])) + 1
                    # the queue opens every root first, so the first leaves are one of each tree
                    homes = set(at[: len(forest.value.roots)].tolist())
                    rows += [(own, mark, int(at[part[0]]), int(at[part[0]]) in homes, found[part]) for part in np.split(order, cuts) if len(part)]
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], ["query_id", "mark", "bough", "home", "leaves"])

    return queries.select("query_id", "vec", "mark").mapInArrow(run, "query_id long, mark long, bough long, home boolean, leaves array<long>")


def _bough_search(k: int):
    """Best k of each query among the rows of its leaves in one bough that reach its `least` score (null: any); scored counts the rows."""

    def of(queries: pa.Table, candidates: pa.Table) -> pa.Table:
        out_q, out_v, out_s, out_n = [], [], [], []
        if len(queries) and len(candidates):
            q, x = matrix(queries.column("vec")), matrix(candidates.column("vec"))
            width = max(q.shape[1], x.shape[1])
            q, x = (np.pad(m, ((0, 0), (0, width - m.shape[1]))) for m in (q, x))
            ids, leaf = candidates.column("ids").to_pylist(), candidates.column("leaf").to_numpy()
            names, place = np.unique(leaf, return_inverse=True)
            members = np.split(np.argsort(place, kind="stable"), np.cumsum(np.bincount(place))[:-1])
            visits = queries.column("leaves").combine_chunks()
            visitor = np.repeat(np.arange(len(q)), visits.value_lengths().to_numpy())
            seen = np.searchsorted(names, visits.flatten().to_numpy())
            own_ids, least = queries.column("query_id").to_pylist(), queries.column("least").to_pylist()
            for a in range(0, len(q), 256):
                scores = np.full((min(256, len(q) - a), len(x)), -np.inf)
                here = (visitor >= a) & (visitor < a + 256) & (seen < len(names))
                # leaves without a row in this task have no place among the names
                here[here] = names[seen[here]] == visits.flatten().to_numpy()[here]
                order = np.argsort(seen[here], kind="stable")
                who, what = visitor[here][order] - a, seen[here][order]
                for part in np.split(np.arange(len(what)), np.flatnonzero(np.diff(what)) + 1):
                    if len(part):
                        rows = members[what[part[0]]]
                        scores[np.ix_(who[part], rows)] = q[a + who[part]] @ x[rows].T
                for i in range(len(scores)):
                    s = scores[i]
                    n = int((s > -np.inf).sum())
                    if not n:
                        continue
                    wanted = least[a + i]
                    if wanted is not None:
                        # sums in another order may differ in their last digits
                        s = np.where(s >= wanted - 1e-9 * max(1.0, abs(wanted)), s, -np.inf)
                        n = int((s > -np.inf).sum())
                        if not n:
                            continue
                    # ties beyond the (k+1)-th best score may not be cut by position: all rows at its score stay
                    some = np.flatnonzero(s >= np.partition(s, -k - 1)[-k - 1] - 1e-9 * abs(s[s > -np.inf]).max()) if n > k + 1 else np.flatnonzero(s > -np.inf)
                    own = own_ids[a + i]
                    # the sum in a fixed order, so that every copy and tree gives the same double
                    exact = np.cumsum(q[a + i] * x[some], axis=1)[:, -1]
                    pairs = sorted((-e, v) for e, c in zip(exact.tolist(), some.tolist(), strict=True) for v in ids[c] if v != own and (wanted is None or e >= wanted))[:k]
                    out_q += [own] * len(pairs)
                    out_v += [v for _, v in pairs]
                    out_s += [-e for e, _ in pairs]
                    out_n += [n] * len(pairs)
        return pa.table({"query_id": pa.array(out_q, pa.int64()), "vec_id": pa.array(out_v, pa.int64()), "score": pa.array(out_s, pa.float64()), "scored": pa.array(out_n, pa.int64())})

    return of


def _parts(rows: DataFrame, most: int) -> Column:
    """How many parts a bough's rows are dealt to. At most one number a leaf of the bounded trees is collected."""
    sizes = rows.groupBy("bough").agg(F.ceil(F.count(F.lit(1)) / F.lit(most)).alias("parts")).where(F.col("parts") > 1).collect()
    if not sizes:
        return F.lit(1)
    return F.coalesce(F.try_element_at(F.create_map(*[F.lit(int(r[c])) for r in sizes for c in ("bough", "parts")]), F.col("bough").cast("int")), F.lit(1))


def search(rows: DataFrame, is_query: Column, k: int, share: float | None = None, trees: int = TREES, leaf: int = LEAF, sample: int = SAMPLE) -> DataFrame:
    """rows(vec_id, vec of doubles) -> query_id, rank, vec_id, score. share: of the (tree, row) entries, in place of share_at."""
    mark = F.xxhash64("vec")
    queries = written(rows.where(is_query).select(F.col("vec_id").alias("query_id"), "vec", mark.alias("mark")).distinct())
    distinct = written(smallest_ids(rows, k))
    single = F.bool_and(F.forall("vec", lambda x: x.cast("float").cast("double") == x))
    facts = distinct.agg(F.count(F.lit(1)).alias("n"), F.max(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x * x)).alias("top"), single.alias("single")).first()
    spark, schema = rows.sparkSession, "query_id long, vec_id long, score double, scored long"
    if not facts["n"]:
        return spark.createDataFrame([], schema).select("query_id", F.lit(1).alias("rank"), "vec_id", "score")
    drawn = matrix(pa.array([r["vec"] for r in distinct.orderBy(F.xxhash64("vec"), "vec").limit(sample).select("vec").collect()], pa.list_(pa.float64())))
    forest = plant(drawn, float(facts["top"]), trees, leaf)
    shared, boughs = spark.sparkContext.broadcast(forest), spark.sparkContext.broadcast(forest.boughs(BOUGH_ROWS * len(drawn) / facts["n"]))
    # a share of the sample's entries, but never so few that k rows of a small table could be missed
    wanted = max((share_at(facts["n"]) if share is None else share) * len(drawn) * trees, 4.0 * (k + 1) * trees * len(drawn) / facts["n"])
    # components that single precision holds exactly move as such, half as wide
    sent = distinct.withColumn("vec", F.col("vec").cast("array<float>")) if facts["single"] else distinct
    filed = _filed(sent, shared, boughs)
    routed = written(_routed(queries, shared, boughs, wanted))
    n_rows, n_queries = _parts(filed.select("bough"), BOUGH_ROWS), _parts(routed, QUERY_ROWS)
    deal = lambda n: F.explode(F.sequence(F.lit(0), n - 1))
    candidates = filed.withColumn("part", F.pmod(F.xxhash64("vec"), n_rows).cast("int")).withColumn("side", deal(n_queries))

    def searched(some: DataFrame) -> DataFrame:
        """some(query_id, mark, bough, leaves, least) -> query_id, vec_id, score. A vec_id with several vectors counts by its best."""
        q = some.withColumn("side", F.pmod(F.xxhash64("query_id"), n_queries).cast("int")).join(queries.select("query_id", "mark", "vec"), ["query_id", "mark"]).withColumn("part", deal(n_rows))
        found = q.groupBy("bough", "part", "side").cogroup(candidates.groupBy("bough", "part", "side")).applyInArrow(_bough_search(k), schema)
        return found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))

    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    home = written(searched(routed.where("home").withColumn("least", F.lit(None).cast("double"))))
    least = home.withColumn("rank", rank).where(F.col("rank") == k).select(F.col("query_id").alias("of"), F.col("score").alias("least"))
    rest = routed.where(~F.col("home")).join(least, F.col("query_id") == F.col("of"), "left").drop("of")
    found = home.unionByName(searched(rest)).groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def doubles(rows: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    usable = rows.where(finite(embedding) & F.col(vec_id).isNotNull() & F.exists(embedding, lambda x: x != 0))
    return usable.select(F.col(vec_id).cast("long").alias("vec_id"), F.transform(embedding, lambda x: x.cast("double")).alias("vec"))


def op10_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(doubles(table(spark, sf_dir, "embeddings")), F.col("vec_id") % 20 == 0, 20)
