"""Row kernels on Spark: counts, checks, evidence; nulls, floats, odd types, degenerate relations."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from tests.memory_kernel import MemoryRelation, brute_force, listed
from topfd.model import Limits, Relation, bits, mask_of
from topfd.operators import cardinality as C
from topfd.operators import definitions as D
from topfd.operators import evidence as E
from topfd.operators import local_classes
from topfd.plans.baseline import brute_force as spark_brute_force
from topfd.plans.baseline import closure, discover_all, implied, simplify_group_by
from topfd.plans.metrics import kinds, lift, ratios
from topfd.plans.search import VARIANTS, discover
from topfd.sources.views import TOY, flight_toy


def rel_of(spark, rows, schema, **options):
    return Relation.bind(spark.createDataFrame(rows, schema).coalesce(2), **options)


def test_toy_has_nine_dependencies(spark):
    rel = Relation.bind(flight_toy(spark))
    found = discover_all(rel)
    assert listed(found) == brute_force([tuple(r) for r in TOY], rel.columns)
    assert [f.redundancy for f in found.fds] == [3] * 6 + [0] * 3
    assert [(rel.lhs_text(f.lhs), rel.columns[f.rhs]) for f in discover(rel, 3).fds] == [("Dest", "FlightNo"), ("Dest", "Origin"), ("FlightNo", "Dest")]
    assert [round(lift(found.result, k).first()["lift"], 9) for k in (1, 3)] == [1.6, 2.0]
    assert lift(found.result, 6).first()["lift"] == float("inf")
    assert lift(found.result, 9, rest="positive").first()["lift"] is None
    assert lift(found.result, 12, divisor="k").first()["mean_top"] == 18 / 12


def test_random_relations_on_spark(spark):
    rng = random.Random(6)
    for trial in range(8):
        m, n = rng.randint(2, 5), rng.randint(1, 14)
        rows = [tuple(rng.choice([None, 0, 1, 2]) for _ in range(m)) for _ in range(n)]
        columns = [f"c{i}" for i in range(m)]
        want = brute_force(rows, columns)
        rel = rel_of(spark, rows, ", ".join(f"{c} int" for c in columns))
        option = {"variant": rng.choice(list(VARIANTS)), "kernel": rng.choice(["tree", "antichain"]), "batch": rng.choice([1, 24])}
        assert listed(discover(rel, 4, **option)) == [x for x in want if x[0] < 0][:4]
        assert sorted(listed(discover(rel, None, **option))) == want


def test_counts_by_all_kernels_agree(spark):
    rng = random.Random(7)
    rows = [tuple(rng.choice([None, "a", "b", "", "c"]) for _ in range(5)) for _ in range(60)]
    rel = rel_of(spark, rows, "a string, b string, c string, d string, e string")
    memory = MemoryRelation(rows, rel.columns)
    sets = [s for s in range(1, 32)]
    want = {s: memory.card(s) for s in sets}
    assert C.set_cardinalities(rel, sets, expand=7) == want
    assert C.exploded_cardinalities(rel, sets) == want
    got = C.check_batch(rel, [(s, a) for s in sets for a in range(5) if not s >> a & 1])
    assert all(v.n_classes == want[s] and v.valid == (want[s] == want[s | 1 << a]) for (s, a), v in got.items())
    edges = E.violating_edges(rel, [(s, a, v.example) for (s, a), v in got.items() if not v.valid])
    pairs = {sum(1 << i for i in range(5) if r[i] != s[i]) for r in rows for s in rows}
    assert all(e in pairs and not e & s and e >> a & 1 for (s, a), e in edges.items())
    assert set(C.refute_on_slice(rel, list(got), 1)) == {k for k, v in got.items() if not v.valid}
    assert set(C.refute_on_slice(rel, list(got), 3)) <= {k for k, v in got.items() if not v.valid}
    n, cards = C.profile(rel)
    assert E.sample_difference_sets(rel, n, cards) <= pairs - {0}
    assert {E.mask_of_words(r["words"]) for r in E.all_difference_sets(rel).collect()} - {0} == pairs - {0}


def test_nulls_equal_each_other(spark):
    rel = rel_of(spark, [(None, 1), (None, 1), (1, None)], "a int, b int")
    assert C.set_cardinalities(rel, [1, 3]) == {1: 2, 3: 2}
    assert C.check_batch(rel, [(1, 1)])[1, 1].valid
    assert not D.fd_holds(spark.createDataFrame([(None, 1), (None, 2)], "a int, b int"), ["a"], "b")
    assert not D.fd_holds(spark.createDataFrame([(1, None), (1, 2)], "a int, b int"), ["a"], "b")


def test_nulls_apart(spark):
    rows = [(None, 1), (None, 2), (1, 5), (1, 5)]
    rel = rel_of(spark, rows, "a int, b int", nulls="neq")
    assert C.set_cardinalities(rel, [1, 2]) == {1: 3, 2: 3}
    got = C.check_batch(rel, [(1, 1), (2, 0)])
    assert got[1, 1].valid and got[1, 1].n_classes == 3 and got[2, 0].valid
    assert not C.check_batch(rel_of(spark, [(1, None), (1, None)], "a int, b int", nulls="neq"), [(1, 1)])[1, 1].valid
    assert [(f.lhs, f.rhs, f.redundancy) for f in discover(rel, 5, empty_lhs=False).fds] == [(1, 1, 1), (2, 0, 1)]


def test_floats_and_odd_types(spark):
    nan = float("nan")
    rel = rel_of(spark, [(nan,), (nan,), (0.0,), (-0.0,)], "x double")
    assert C.set_cardinalities(rel, [1]) == {1: 2} and C.exploded_cardinalities(rel, [1]) == {1: 2}
    df = spark.sql("SELECT map('a', 1, 'b', 2) AS m, array(1, 2) AS a, struct(1 AS x) AS s, binary('q') AS b, date'2020-01-01' AS d, 1.5BD AS e UNION ALL SELECT map('b', 2, 'a', 1), array(1, 2), struct(1), binary('q'), date'2020-01-01', 1.5BD UNION ALL SELECT map('c', 1), array(3), struct(2), binary('r'), date'2021-01-01', 2.5BD")
    rel = Relation.bind(df)
    assert C.set_cardinalities(rel, [1 << i for i in range(6)]) == {1 << i: 2 for i in range(6)}
    assert len(discover(rel, 100).fds) == 30 and all(f.redundancy == 1 for f in discover(rel, 100).fds)


def test_degenerate_relations(spark):
    const = rel_of(spark, [(1, 7), (2, 7), (3, 7), (4, 7)], "a int, c int")
    assert listed(discover(const, 10)) == [(-3, 0, "", "c")]
    assert listed(discover(const, 10, empty_lhs=False)) == []
    assert listed(discover(rel_of(spark, [(1, 2)] * 3, "a int, b int"), 10)) == [(-2, 0, "", "a"), (-2, 0, "", "b")]
    for rows in ([(1, 2)], []):
        found = discover(rel_of(spark, rows, "a int, b int"), 10)
        assert found.fds == [] and found.result.columns[0] == "rank" and found.result.count() == 0
    assert discover(rel_of(spark, [(1,), (2,)], "a int"), 10).fds == []
    for k in (0, -1):
        with pytest.raises(ValueError):
            discover(const, k)
    with pytest.raises(ValueError):
        Relation.bind(spark.range(1), ["nope"])


def test_redundancy_as_sum_and_difference(spark):
    rel = Relation.bind(flight_toy(spark))
    for attrs in (["ID"], ["FlightNo"], ["Origin", "Dest"]):
        r = D.redundancy_sum(rel, attrs).first()
        assert r["redundancy"] == D.redundancy(r["n_rows"], r["n_classes"]) == 5 - C.set_cardinalities(rel, [mask_of(attrs, rel.columns)])[mask_of(attrs, rel.columns)]
    assert sorted(r["ID"] for r in D.redundant_rows(rel, ["FlightNo"], "Origin", ["ID"]).collect()) == [2, 3, 5]


def test_canonical_cut_of_ties(spark):
    want = [("Dest", "FlightNo"), ("Dest", "Origin")]
    for variant in VARIANTS:
        for batch in (1, 8):
            found = discover(flight_toy(spark), 2, variant, batch=batch)
            assert [(found.rel.lhs_text(f.lhs), found.rel.columns[f.rhs]) for f in found.fds] == want


def test_brute_force_and_recheck(spark):
    rel = Relation.bind(flight_toy(spark))
    fds = spark_brute_force(rel, 3)
    assert fds == discover_all(rel).fds
    assert C.recheck(rel, [(f.lhs, f.rhs, f.n_classes) for f in fds]) == []
    assert C.recheck(rel, [(1 << 1, 0, 2)]) == [(2, 0, 2)]


def test_closure_implication_grouping_and_kinds(spark):
    rel = Relation.bind(flight_toy(spark))
    fds = discover_all(rel).fds
    at = rel.columns.index
    assert closure(fds, 1 << at("Dest")) == mask_of(["Dest", "Origin", "FlightNo"], rel.columns)
    assert len(implied(fds)) == len(fds)
    assert simplify_group_by(rel, ["ID", "Origin", "Dest"], fds) == ["ID"]
    assert set(kinds(rel, [f for f in fds if f.redundancy]).values()) == {"synonym"}
    a, b = discover(rel, 3), discover_all(rel)
    assert 0 <= ratios(a, b)["search_pruning"] < 1


def test_wide_relations_split_jobs(spark):
    m = 70
    rows = [tuple((r * (i + 1)) % 5 for i in range(m)) for r in range(12)]
    rel = rel_of(spark, rows, ", ".join(f"c{i} int" for i in range(m)))
    memory = MemoryRelation(rows, rel.columns)
    wide = (1 << m) - 1
    assert C.set_cardinalities(rel, [1 << i for i in range(m)]) == {1 << i: memory.card(1 << i) for i in range(m)}
    assert C.exploded_cardinalities(rel, [wide]) == {wide: memory.card(wide)}
    assert {E.mask_of_words(r["words"]) for r in E.all_difference_sets(rel).collect()} == {sum(1 << i for i in range(m) if a[i] != b[i]) for k, a in enumerate(rows) for b in rows[:k]}
    found = discover(rel, 3, max_lhs=1)
    assert [x[0] for x in listed(found)] == [x[0] for x in sorted((memory.card(1 << i) - 12, a) for i in range(m) for a in range(m) if a != i and memory.card(1 << i) == memory.card(1 << i | 1 << a))[:3]]


def test_plan_of_the_check_stays_in_hash_aggregation(spark):
    rel = rel_of(spark, [("a", 1.0, "x")], "s string, d double, t string")
    plan = C.check_frame(rel, [(1, [1, 2]), (5, [1])])._jdf.queryExecution().executedPlan().toString()
    assert "SortAggregate" not in plan and "ObjectHash" not in plan and "Cartesian" not in plan
    plan = C.grouping_frame(rel, [1, 3])._jdf.queryExecution().executedPlan().toString()
    assert "SortAggregate" not in plan and plan.count("Exchange hashpartitioning") <= 2


def test_only_needed_columns_are_read(spark, tmp_path):
    spark.range(10).select("id", (F.col("id") % 2).alias("p"), F.lit("x").alias("unused")).write.parquet(f"{tmp_path}/t")
    rel = Relation.bind(spark.read.parquet(f"{tmp_path}/t"))
    plan = C.check_frame(rel, [(1, [1])])._jdf.queryExecution().executedPlan().toString()
    assert "unused" not in plan.split("ReadSchema")[1]


def test_slices_change_no_answer(spark, monkeypatch):
    from topfd.plans import search

    rng = random.Random(8)
    rows = [tuple(rng.randrange(k) for k in (3, 4, 5, 30)) + (0,) for _ in range(80)]
    rows = [(a, b, c, d, (a * 7 + b) % 5) for a, b, c, d, _ in rows]
    monkeypatch.setattr(search, "SLICE_ROWS", 10)
    want = [x for x in brute_force(rows, list("abcde")) if x[0] < 0]
    for kernel in ("tree", "antichain"):
        found = discover(rel_of(spark, rows, "a int, b int, c int, d int, e int"), 6, kernel=kernel, sample=False)
        assert listed(found) == want[:6] and found.stats["slice_refuted"] > 0


def test_bits():
    assert list(bits(0b1011)) == [0, 1, 3] and list(bits(0)) == []


def _mixed(n=400):
    rng = random.Random(11)
    rows = [tuple(rng.randrange(k) for k in (3, 4, 5, 40)) for _ in range(n)]
    return [(a, b, c, d, (a * 7 + b) % 5, a * 10, None if d % 7 else d) for a, b, c, d in rows], "a int, b int, c int, d int, e int, f int, g int"


def test_spread_kernels_lower_profile_and_warm_start_change_no_answer(spark):
    rows, schema = _mixed()
    want = [x for x in brute_force(rows, list("abcdefg")) if x[0] < 0][:8]
    for options in ({}, {"spread": True}, {"spread": True, "warm_start": False, "sample": False}, {"warm_start": False}, {"persist": True}, {"kernel": "tree", "warm_start": True}):
        found = discover(rel_of(spark, rows, schema), 8, **options)
        assert listed(found) == want and found.stats["exact"], options
    lower = discover(rel_of(spark, rows, schema), 8, profile="lower")
    assert listed(lower) == want and not lower.stats["exact"]
    n, cards = C.lower_profile(rel_of(spark, rows, schema))
    assert n == 400 and all(x <= len({r[i] for r in rows}) for i, x in enumerate(cards))


def test_an_antichain_that_outgrows_its_share_leaves_the_rest_to_the_trees(spark, monkeypatch):
    from topfd.plans import search

    rows, schema = _mixed()
    want = [x for x in brute_force(rows, list("abcdefg")) if x[0] < 0][:8]
    monkeypatch.setattr(search, "MOST_SETS", 2)
    assert listed(discover(rel_of(spark, rows, schema), 8, warm_start=False)) == want


def test_a_run_goes_on_from_its_folder(spark, tmp_path):
    rows, schema = _mixed()
    want = [x for x in brute_force(rows, list("abcdefg")) if x[0] < 0][:8]
    folder = f"{tmp_path}/progress"
    cut = discover(rel_of(spark, rows, schema), 8, batch=2, warm_start=False, limits=Limits(max_validations=6), resume=folder)
    assert cut.status == "over_budget"
    again = discover(rel_of(spark, rows, schema), 8, batch=2, warm_start=False, resume=folder)
    whole = discover(rel_of(spark, rows, schema), 8, batch=2, warm_start=False)
    assert listed(again) == listed(whole) == want and again.stats["validations"] < whole.stats["validations"]
    other = discover(rel_of(spark, rows[:-1], schema), 8, resume=folder)
    assert listed(other) == [x for x in brute_force(rows[:-1], list("abcdefg")) if x[0] < 0][:8]


def test_stored_evidence_is_for_its_rows_alone(spark, tmp_path):
    rows, schema = _mixed(50)
    rel = rel_of(spark, rows, schema)
    edges = E.sample_difference_sets(rel, *C.profile(rel))
    E.save_evidence(rel, edges, f"{tmp_path}/e")
    assert E.load_evidence(rel_of(spark, rows[::-1], schema), f"{tmp_path}/e") == edges
    with pytest.raises(ValueError):
        E.load_evidence(rel_of(spark, rows[1:], schema), f"{tmp_path}/e")


def test_sampled_edges_are_difference_sets_of_rows_and_the_sample_repeats(spark):
    rows, schema = _mixed(300)
    rel = rel_of(spark, rows + [rows[0]] * 200, schema)
    n, cards = C.profile(rel)
    a, b = (E.take_sample(rel, n, cards, 500) for _ in range(2))
    assert (a.rows == b.rows).all() and all((x == y).all() for x, y in zip(a.slices, b.slices, strict=True)) and len(a) <= 300
    pairs = {sum(1 << i for i in range(7) if r[i] != s[i]) for r in rows for s in rows}
    assert E.edges_of_sample(a) <= pairs


def test_measures_are_of_one_run(spark):
    small, large = rel_of(spark, [(1, 2), (1, 2)], "a int, b int"), Relation.bind(spark.range(400_000).selectExpr("id AS a", "id % 1000 AS b", "id % 1000 * 2 AS c", "uuid() AS d"))
    peaks = [discover(r, 3).stats for r in (large, small)]
    assert peaks[1]["peak_heap_mb"] < peaks[0]["peak_heap_mb"]
    assert peaks[1]["shuffle_mb"] < peaks[0]["shuffle_mb"] and peaks[0]["stages"] > 0 and peaks[0]["rows_read"] >= 0


def test_a_wrong_answer_would_be_an_error(spark, monkeypatch):
    rows, schema = _mixed(50)
    monkeypatch.setattr(C, "recheck", lambda rel, fds: list(fds)[:1])
    with pytest.raises(RuntimeError):
        discover(rel_of(spark, rows, schema), 3)
    assert discover(rel_of(spark, rows, schema), 3, recheck=False).fds


def test_neighbours_in_a_window_give_their_difference_sets(spark):
    rows = [(1, 1, "a", None), (1, 2, "a", None), (1, 3, "b", 4), (2, 1, "a", 1), (2, 2, "b", 1), (3, 1, "c", 2)]
    df = spark.createDataFrame(rows, "g long, `at.x` long, p string, q long")
    got = {r["attrs"]: r["support"] for r in E.lag_pairs(df, ["g"], ["at.x"], ["q", "p"]).collect()}
    assert got == {"": 1, "p,q": 1, "p": 1}
    assert {r["attrs"]: r["support"] for r in E.lag_pairs(df, ["g"], ["at.x"], ["q", "p"], lag=2).collect()} == {"p,q": 1}
    assert E.lag_pairs(df.limit(0), ["g"], ["at.x"], ["p"]).count() == 0


def test_an_anti_join_leaves_minimal_masks(spark):
    # of the sets over bits 1, 2, 4: 1 gives 2, so {1, 4} gives 2 too but isn't minimal
    cards = spark.createDataFrame([(0, 1), (1, 3), (2, 2), (4, 2), (3, 3), (5, 4), (6, 4), (7, 4)], "mask long, card long")
    found = D.minimal_masks(cards, spark.createDataFrame([(1,), (2,), (4,)], "bit long"))
    assert {tuple(r) for r in found.collect()} == {(1, 2, 3), (6, 1, 4)}


def test_kept_codes_of_one_file_are_dealt_out(spark, tmp_path):
    spark.range(200_000).selectExpr("id", "xxhash64(id) AS h", "id % 7 AS a", "id % 7 % 3 AS b").coalesce(1).write.parquet(f"{tmp_path}/t")
    df = spark.read.parquet(f"{tmp_path}/t")
    kept, plain = Relation.bind(df, persist=True), Relation.bind(df)
    tasks = [r.coded.groupBy(F.spark_partition_id()).count().count() for r in (kept, plain)]
    assert tasks[0] > 1 == tasks[1]
    assert discover(kept, 5).fds == discover(plain, 5).fds
    kept.release()
    # a table of a few rows stays in one task
    spark.range(20).coalesce(1).write.parquet(f"{tmp_path}/s")
    assert Relation.bind(spark.read.parquet(f"{tmp_path}/s"), persist=True).coded.rdd.getNumPartitions() == 1


def test_difference_sets_of_many_rows_and_few_classes(spark):
    df = spark.range(5_000).selectExpr("id % 3 AS a", "IF(id % 3 = 0, NULL, 'x') AS b", "id % 2 AS c")
    rel = Relation.bind(df)
    got = {rel.lhs_text(E.mask_of_words(r["words"])): r["support"] for r in E.all_difference_sets(rel).collect()}
    classes = {}
    for r in df.collect():
        classes[tuple(r)] = classes.get(tuple(r), 0) + 1
    want = {}
    for x, n in classes.items():
        for y, m in classes.items():
            text = ",".join(name for name, u, v in zip("abc", x, y, strict=True) if u != v)
            want[text] = want.get(text, 0) + (n * (n - 1) if x == y else n * m)
    assert got == {t: n // 2 for t, n in want.items()} and sum(got.values()) == 5_000 * 4_999 // 2
    with pytest.raises(ValueError):
        E.all_difference_sets(Relation.bind(spark.range(2_001)))


def _orders(spark, tmp_path):
    """Eight orders of two years; the quarter follows from the month alone."""
    days = ("2023-01-05", "2023-02-05", "2023-04-05", "2023-04-06", "2024-01-05", "2024-05-05", "2024-05-05", "2024-12-31")
    rows = [(i, i % 3, "FOP"[i % 3], 1.0, d, "1-URGENT") for i, d in enumerate(days)]
    df = spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate string, o_orderpriority string")
    df.withColumn("o_orderdate", F.to_date("o_orderdate")).write.parquet(f"{tmp_path}/orders.parquet")
    return str(tmp_path), [(r[2], int(r[4][:4]), (int(r[4][5:7]) + 2) // 3, int(r[4][5:7])) for r in rows]


def test_induced_edges_are_those_of_the_orders_given(spark, tmp_path):
    from topfd.registry import QUERIES
    from topfd.sources.views import COLUMNS

    folder, rows = _orders(spark, tmp_path)
    names = COLUMNS["order_months"]
    sets = [{c for c, x, y in zip(names, a, b, strict=True) if x != y} for i, a in enumerate(rows) for b in rows[:i]]
    want = {",".join(sorted(e - {"o_quarter"})) for e in sets if "o_quarter" in e}
    assert {r["attrs"] for r in QUERIES["induced_edges"](spark, folder).collect()} == want


def test_minimal_edges_are_those_of_the_orders_given(spark, tmp_path):
    from topfd.registry import QUERIES

    folder, rows = _orders(spark, tmp_path)
    induced = [frozenset(c for c, x, y in zip("sym", (a[0], a[1], a[3]), (b[0], b[1], b[3]), strict=True) if x != y) for i, a in enumerate(rows) for b in rows[:i] if a[2] != b[2]]
    least = {e for e in induced if not any(x < e for x in induced)}
    text = {"s": "o_orderstatus", "y": "o_year", "m": "o_month"}
    assert {r["attrs"] for r in QUERIES["minimal_edges"](spark, folder).collect()} == {",".join(sorted(text[c] for c in e)) for e in least}


def test_mask_names_are_of_the_orders_given(spark, tmp_path):
    from topfd.registry import QUERIES

    spark.range(20).select(F.col("id").alias("o_orderkey")).write.parquet(f"{tmp_path}/orders.parquet")
    got = {r["mask"]: (r["names"], r["n"]) for r in QUERIES["fn_mask_names"](spark, str(tmp_path)).collect()}
    assert len(got) == 8 and got[0] == ("", 3) and got[3] == ("n_name,n_nationkey", 3) and got[7] == ("n_name,n_nationkey,n_regionkey", 2)


def test_classes_are_checked_where_they_lie_together(spark, monkeypatch):
    """Many left-hand sides in one pass over dealt rows: the same classes and verdicts as by hash aggregation, and difference sets of given pairs of rows."""
    monkeypatch.setattr(local_classes, "CLASSES_A_TASK", 1)
    rng = np.random.default_rng(3)
    rows = [tuple(int(x) or None for x in r) for r in np.stack([rng.integers(0, c, 600) for c in (500, 90, 40, 6, 3)], 1).tolist()]
    rel = Relation.bind(spark.createDataFrame(rows, "a int, b int, c int, d int, e int"))
    candidates = [(s, a) for s in range(1, 32) for a in range(5) if not s >> a & 1]
    slow = C.check_batch(rel, candidates)
    pairs = {E.mask_between(x, y) for i, x in enumerate(rows) for y in rows[:i]}
    rel.counted = C.profile(rel)
    for whole, most in ((16, 4_000_000), (2, 4_000_000), (16, 100)):
        # rows sent whole; narrow rows; tasks that hold too much and leave some sets to the hash aggregation
        monkeypatch.setattr(local_classes, "WHOLE_ROWS", whole)
        monkeypatch.setattr(local_classes, "MOST_TASK_ROWS", most)
        fast = C.check_batch(rel, candidates)
        assert {c: (v.valid, v.n_classes) for c, v in fast.items()} == {c: (v.valid, v.n_classes) for c, v in slow.items()}
        assert all(set(v.edges) <= pairs and all(e >> a & 1 and not e & s for e in v.edges) for (s, a), v in fast.items())
        assert any(v.edges for v in fast.values()) == (whole == 16 and most > 100)
        unseen = E.violating_edges(rel, [(s, a, v.example) for (s, a), v in fast.items() if not v.valid and not v.edges])
        assert set(unseen.values()) <= pairs and (unseen or most > 100)
    assert not any(local_classes.deal([(3, [2]), (1, [2]), (8, [0])], [1000, 1000, 9, 2], 4)[0].keys() - {1}) and local_classes.deal([(8, [0])], [1, 1, 1, 2], 4) == ({}, [0])


def test_a_sample_that_is_the_whole_relation_decides(spark):
    rel = Relation.bind(spark.createDataFrame([(1, 1, 1), (1, 1, 2), (2, 1, 3), (3, None, 3), (3, None, 3)], "a int, b int, c int"))
    n, cards = C.profile(rel)
    sample = E.take_sample(rel, n, cards)
    assert sample.whole and not E.take_sample(Relation.bind(spark.range(70).toDF("a")), 70, [70], 10).whole
    for (lhs, a), v in C.check_batch(rel, [(s, a) for s in range(8) for a in range(3) if not s >> a & 1]).items():
        card, edges = E.check_on_sample(sample, lhs, a)
        assert (card, not edges) == (v.n_classes, v.valid) and all(e >> a & 1 and not e & lhs for e in edges)


def test_masks_of_any_width():
    for m in (1, 9, 64, 70):
        differ = np.random.default_rng(m).random((50, m)) < 0.3
        assert E._masks(differ) == {sum(1 << i for i in range(m) if r[i]) for r in differ} - {0}


@pytest.mark.parametrize("nulls", ["eq", "neq"])
def test_kept_rows_are_narrow_and_give_the_same_codes(spark, nulls):
    df = spark.sql("SELECT IF(id % 3 = 0, NULL, id) AS a, CAST(id % 5 AS INT) AS b, IF(id % 4 = 0, double('nan'), -0.0D * id) AS c, concat('x', id % 2) AS d, date_add(DATE'2020-01-01', int(id % 9)) AS e, timestamp_micros(id % 7) AS f, id % 2 = 0 AS g FROM range(300)")
    kept, plain = Relation.bind(df, nulls=nulls, persist=True), Relation.bind(df, nulls=nulls)
    if nulls == "eq":
        # values where they are no larger than a code, two codes of text
        assert kept.stored.columns == ["_0_0", "_0_1", "_0_2", "_1_3", "_2_3", "_0_4", "_0_5", "_0_6"]
        assert sorted(map(tuple, kept.coded.collect())) == sorted(map(tuple, plain.coded.collect()))
    assert kept.coded.columns == plain.coded.columns and kept.coded.distinct().count() == plain.coded.distinct().count() == 300
    assert kept.stored.storageLevel.useMemory
    kept.release()
    assert not kept.stored.storageLevel.useMemory
