import numpy as np
import pytest
from pyspark.sql import functions as F

from topfd.llm import ann, exact_search as X

SCHEMA = "vec_id long, embedding array<float>, label int"


def vectors(seed, n=400, d=12):
    rng = np.random.default_rng(seed)
    centres = rng.normal(size=(6, d))
    v = centres[rng.integers(0, 6, n)] + 0.4 * rng.normal(size=(n, d))
    rows = [(i, [float(np.float32(x)) for x in row], 0) for i, row in enumerate(v)]
    rows += [(10_000 + i, rows[7][1], 0) for i in range(30)]  # copies: ties that the smaller id wins
    rows += [(20_000, None, 0), (20_001, [1.0, None], 0), (20_002, [float("nan")] * d, 0), (20_003, [float("inf")] * d, 0), (20_004, [0.0] * d, 0), (20_005, [], 0), (None, rows[3][1], 0)]
    rows += [rows[9], (20_050, rows[5][1][:5], 0)]  # a repeated row; a shorter vector
    return rows


def usable(rows, zero):
    out = {}
    for i, v, _ in rows:
        if i is not None and v and all(x is not None and np.isfinite(x) for x in v) and (zero or any(v)):
            out[i] = np.pad(np.array(v, float), (0, 12 - len(v)))
    return out


def frame(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).withColumn("score", F.lit("x")).withColumn("vec", F.lit(1)).withColumn("ids", F.lit(1)).repartition(3)


@pytest.mark.parametrize("block", [16, 64, 4096])
def test_exact_search_is_brute_force(spark, block):
    rows = vectors(1)
    v = {i: np.floor(256 * x).astype(np.int64) for i, x in usable(rows, True).items()}
    want = []
    for q in sorted(v):
        if q % 50 == 0:
            best = sorted((-int(v[q] @ v[c]), c) for c in v if c != q)[:5]
            want += [(q, r, c, -s) for r, (s, c) in enumerate(best, 1)]
    got = X.top_k(X.integers(frame(spark, rows)), F.col("vec_id") % 50 == 0, 5, pivots=8, query_block=block // 8, candidate_block=block)
    assert sorted(map(tuple, got.select("query_id", "rank", "vec_id", "score").collect())) == want


def test_bounds_stop_the_exact_search_early(spark):
    rows = [(i, [float(x) for x in np.eye(40)[i % 40] * (1 + i / 1000)], 0) for i in range(2000)]
    got = X.top_k(X.integers(spark.createDataFrame(rows, SCHEMA)), F.col("vec_id") % 400 == 0, 5, pivots=40).agg(F.max("evaluated").alias("n")).first()
    assert got["n"] < 2000 * 5 / 2


def test_exact_search_of_few_or_no_rows(spark):
    few = spark.createDataFrame([(0, [1.0, 2.0], 0), (50, [1.0, 1.0], 0), (1, [0.0, 0.0], 0)], SCHEMA)
    got = X.top_k(X.integers(few), F.col("vec_id") % 50 == 0, 5).collect()
    assert sorted((r["query_id"], r["rank"]) for r in got) == [(0, 1), (0, 2), (50, 1), (50, 2)]
    assert X.top_k(X.integers(few.limit(0)), F.col("vec_id") % 50 == 0, 5).collect() == []


def test_ids_with_several_vectors_and_huge_components(spark):
    rows = [(0, [1.0, 0.0], 0), (0, [0.0, 1.0], 0), (1, [2.0, 0.0], 0), (1, [3.0, 0.0], 0), (2, [0.0, 5.0], 0), (3, [1e300, 0.0], 0), (4, [-1e18, 1.0], 0), (5, [1e6, 1e6], 0)]
    got = X.top_k(X.integers(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")), F.col("vec_id") == 0, 5).collect()
    assert sorted((r["rank"], r["vec_id"], r["score"]) for r in got) == [(1, 5, 256 * 256_000_000), (2, 2, 256 * 1280), (3, 1, 256 * 768)]
    found = ann.search(ann.doubles(spark.createDataFrame(rows[:5], "vec_id long, embedding array<double>, label int")), F.col("vec_id") == 0, 5).collect()
    assert sorted((r["rank"], r["vec_id"], r["score"]) for r in found) == [(1, 2, 5.0), (2, 1, 3.0)]


@pytest.mark.parametrize("rows_of_task", [50, 16_384])
def test_boughs_and_blocks_of_any_size_give_the_same_result(spark, monkeypatch, rows_of_task):
    rows = vectors(4, 600)
    monkeypatch.setattr(ann, "BOUGH_ROWS", rows_of_task)
    monkeypatch.setattr(ann, "QUERY_ROWS", 7 if rows_of_task == 50 else 16_384)
    got = sorted(map(tuple, ann.search(ann.doubles(frame(spark, rows)), F.col("vec_id") % 20 == 0, 5, share=1.0).collect()))
    v = usable(rows, False)
    want = [(q, r, c) for q in sorted(v) if q % 20 == 0 for r, (_, c) in enumerate(sorted((-float(np.cumsum(v[q] * v[c])[-1]), c) for c in v if c != q)[:5], 1)]
    assert [x[:3] for x in got] == want


def test_visits_fall_behind_the_table(spark):
    shares = [ann.share_at(n) for n in (500, 2_000, 10_000, 50_000, 1_000_000)]
    assert shares == sorted(shares, reverse=True) and shares[1] == ann.SHARE and shares[-1] < shares[1] / 3


def test_forest_recall_scores_and_order(spark):
    rows = vectors(2, 3000)
    v = usable(rows, False)
    got: dict[int, list] = {}
    for r in ann.search(ann.doubles(frame(spark, rows)), F.col("vec_id") % 20 == 0, 20).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    assert set(got) == {i for i in v if i % 20 == 0}
    ids = np.array(sorted(v))
    m = np.array([v[i] for i in ids])
    hits = 0
    for q, found in got.items():
        found.sort()
        assert [r for r, *_ in found] == list(range(1, 21)) and q not in {c for _, c, _ in found} and len({c for _, c, _ in found}) == 20
        assert all(s == pytest.approx(float(v[q] @ v[c]), rel=1e-12, abs=1e-12) for _, c, s in found)
        assert found == sorted(found, key=lambda x: (-x[2], x[1]))
        exact = sorted(zip(-(m @ v[q]), ids, strict=True))
        hits += len({c for _, c, _ in found} & {int(c) for _, c in exact if c != q and True} & {int(c) for _, c in [x for x in exact if x[1] != q][:20]})
    assert hits / (20 * len(got)) >= 0.9


def test_forest_of_few_or_no_rows(spark):
    few = spark.createDataFrame([(0, [1.0, 2.0], 0), (20, [1.0, 1.0], 0), (1, [3.0], 0), (2, [0.0, 0.0], 0)], SCHEMA)
    got = ann.search(ann.doubles(few), F.col("vec_id") % 20 == 0, 20).collect()
    assert sorted((r["query_id"], r["rank"], r["vec_id"]) for r in got) == [(0, 1, 1), (0, 2, 20), (20, 1, 0), (20, 2, 1)]
    assert ann.search(ann.doubles(few.limit(0)), F.col("vec_id") % 20 == 0, 20).collect() == []


def test_all_rows_alike(spark):
    same = spark.createDataFrame([(i, [1.0, 2.0, 3.0], 0) for i in range(500)], SCHEMA)
    for got in (ann.search(ann.doubles(same), F.col("vec_id") % 20 == 0, 20), X.top_k(X.integers(same), F.col("vec_id") % 20 == 0, 20)):
        rows = got.collect()
        assert len(rows) == 25 * 20
        assert sorted(r["vec_id"] for r in rows if r["query_id"] == 20) == [x for x in range(21) if x != 20]
