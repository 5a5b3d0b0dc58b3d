from topfd import registry, workloads
from topfd.model import Limits
from topfd.sources.views import COLUMNS, VIEWS


def _tables(spark, tmp_path):
    spark.range(60).selectExpr("id AS a", "id % 7 AS b", "id % 7 * 2 AS c", "id % 5 AS d").write.parquet(f"{tmp_path}/t.parquet")
    return lambda spark, sf_dir: spark.read.parquet(f"{sf_dir}/t.parquet")


def test_limits_bind_the_exhaustive_run_alone(spark, tmp_path, monkeypatch):
    monkeypatch.setitem(VIEWS, "small", _tables(spark, tmp_path))
    monkeypatch.setitem(COLUMNS, "small", ("a", "b", "c", "d"))
    none = Limits(max_validations=0, max_nodes=0)
    rows = workloads.attribute_scaling(spark, str(tmp_path), "small", sizes=(3, 4), limits=none).collect()
    assert {(r["setting"], r["method"], r["status"]) for r in rows} == {(m, *x) for m in ("3", "4") for x in (("pruned", "complete"), ("exhaustive", "over_budget"))}
    over = workloads.overall(spark, str(tmp_path), ("small",), limits=none).first()
    assert over["status"] == "over_budget" and over["pruned_s"] > 0 and over["n_fds"] is over["same_answer"] is over["lift"] is None
    done = workloads.overall(spark, str(tmp_path), ("small",)).first()
    assert done["status"] == "complete" and done["same_answer"] and done["n_fds"] > 0


def test_registered_workloads_are_whole(spark, monkeypatch):
    """What the queries ask of the workloads; nothing runs."""
    bound, runs = [], []

    class Rel:
        release = staticmethod(lambda: None)

    monkeypatch.setattr(workloads, "bound_view", lambda spark, sf, view, columns=None: bound.append((view, len(columns or COLUMNS[view]))) or Rel())
    monkeypatch.setattr(workloads, "discover", lambda rel, k, *a, **b: runs.append((bound[-1][0], k, b.get("limits"))))
    monkeypatch.setattr(workloads, "row", lambda *a: a)
    monkeypatch.setattr(workloads, "compared", lambda rel, v, k, limits: ())
    monkeypatch.setattr(workloads, "rows_frame", lambda spark, rows: spark.range(len(rows)))
    monkeypatch.setattr(workloads, "COMPARE_SCHEMA", "a int")
    frame = spark.range(0)
    monkeypatch.setattr(type(spark), "createDataFrame", lambda self, *a, **b: frame)
    ask = lambda name: (bound.clear(), runs.clear(), registry.QUERIES[name](spark, ""))
    ask("w1_overall")
    assert {"order_lines", "priced_lines", "events_calendar", "orders", "documents", "lineitem", "embedding_bins", "wide_star"} <= {v for v, _ in bound} and len(bound) == 23
    ask("w3_attributes")
    assert [m for _, m in bound] == [8, 16, 24, 32, 40] and all(x[2] is None for x in runs if x[1])
    ask("w4_k")
    assert {(v, k) for v, k, _ in runs if k} == {(v, k) for v in ("order_lines", "embedding_bins") for k in workloads.KS}
    ask("w5_ablation")
    assert [v for v, _ in bound] == ["order_lines", "doc_labels"]
    ask("w9_limits")
    assert bound == [("wide_star", 40)] and [x[2] is None for x in runs] == [True, False]


def test_runs_of_a_workload_prepare_a_relation_once(spark, tmp_path, monkeypatch):
    monkeypatch.setitem(VIEWS, "small", _tables(spark, tmp_path))
    monkeypatch.setitem(COLUMNS, "small", ("a", "b", "c", "d"))
    taken, take = [], workloads.discover.__globals__["evidence"].take_sample
    monkeypatch.setattr(workloads.discover.__globals__["evidence"], "take_sample", lambda *a: taken.append(1) or take(*a))
    rows = workloads.k_sweep(spark, str(tmp_path), "small", ks=(1, 2, 3)).collect()
    # one for the run that warms up
    assert len(taken) == 2 and len(rows) == 4
    prepared = workloads.discover(workloads.sharing(workloads.bound_view(spark, str(tmp_path), "small")), 3)
    alone = workloads.discover(workloads.bound_view(spark, str(tmp_path), "small"), 3)
    assert prepared.fds == alone.fds and prepared.stats["wall_s"] > 0 and prepared.stats["peak_heap_mb"] > 0
