"""The experiments: overall comparison, scaling in rows and attributes, k, ablation, threshold traces, cases, overhead, limits. One row a run."""

from __future__ import annotations

from statistics import median

from pyspark.sql import DataFrame, SparkSession

from .model import Limits, Relation
from .operators import held
from .plans.metrics import kinds, lift, ratios
from .plans.search import VARIANTS, Discovery, discover
from .sources.views import COLUMNS, VIEWS, embedding_bins, prefix

#: Runs of each method in a comparison.
RUNS = 3
#: The published search, one candidate at a time: evidence from few sampled rows, every candidate validated on all rows, no bound but the published ones.
PUBLISHED = {"batch": 1, "sample_bound": False, "early": False, "slice_rows": 100}
KS = (1, 10, 50, 100, 500)
SHARES = (0.2, 0.4, 0.6, 0.8, 1.0)
#: What the exhaustive run may take, in counts, so that no result depends on a machine's speed; the pruned one has no limits. The second is for wide relations.
EXHAUSTIVE, EXHAUSTIVE_WIDE = Limits(max_validations=300, max_nodes=50_000), Limits(max_validations=100, max_nodes=50_000)
OVERALL = ("cust_geo", "orders_calendar", "priced_lines", "order_lines", "doc_labels", "events_calendar", "event_props", "page_facts", "talk_facts", "bench_facts", "region", "nation", "customer", "supplier", "part", "orders", "events", "documents", "labels", "conversations", "lineitem", "embedding_bins", "wide_star")
RUN_SCHEMA = (
    "workload string, relation string, setting string, method string, k int, n_rows long, n_attributes int, status string, wall_s double, peak_heap_mb double, "
    "nodes long, nodes_visited long, validations long, valid_found long, valid_until_last_change long, spark_jobs long, answers int, top_redundancy long, tau long"
)
COMPARE_SCHEMA = "relation string, n_rows long, n_attributes int, n_fds long, n_positive long, base_s double, base_heap_mb double, pruned_s double, pruned_heap_mb double, speedup double, search_pruning double, candidate_pruning double, lift double, same_answer boolean, status string"


def bound_view(spark: SparkSession, sf_dir: str, view: str, columns: tuple[str, ...] | None = None) -> Relation:
    return Relation.bind(VIEWS[view](spark, sf_dir), list(columns or COLUMNS[view]), persist=True)


def holding(rel: Relation) -> Relation:
    """From here on, runs over this relation hold its rows on the driver if they are few enough."""
    rel.hold = True
    return rel


def sharing(rel: Relation) -> Relation:
    """From here on, runs over this relation prepare its profile and evidence once; each counts the seconds as its own."""
    rel.shared = {}
    return rel


def row(workload: str, relation: str, setting: str, method: str, found: Discovery) -> tuple:
    s = found.stats
    positive = [f for f in found.fds if f.redundancy > 0]
    return (
        workload, relation, setting, method, s["k"], s["n_rows"], s["n_attributes"], found.status, s["wall_s"], s["peak_heap_mb"], s["nodes_generated"], s["nodes_visited"], s["validations"],
        s["valid_found"], s["valid_until_last_change"], s["spark_jobs"], len(positive), positive[0].redundancy if positive else 0, found.trace[-1][3],
    )


def rows_frame(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, RUN_SCHEMA)


def compared(rel: Relation, name: str, k: int = 10, max_lhs: int | None = None, limits: Limits | None = None) -> tuple:
    """One row of the overall comparison. limits: of the exhaustive run; where it exceeds them, what its answer would say is null.

    A run of its own warms the relation and the code up and isn't measured. Then both methods take turns; seconds and peaks are medians of their runs. An
    exhaustive run that exceeds its limits is not repeated."""
    discover(holding(rel), 1, max_lhs=1)
    sharing(rel)
    runs: list[tuple[Discovery, Discovery]] = []
    while len(runs) < RUNS:
        runs.append((discover(rel, k, max_lhs=max_lhs), discover(rel, None, "core", max_lhs=max_lhs, limits=limits)))
        if runs[-1][1].status != "complete":
            break
    for measure in ("wall_s", "peak_heap_mb"):
        for side in (0, 1):
            middle = median(r[side].stats[measure] for r in runs)
            runs[-1][side].stats[measure] = middle
    pruned, base = runs[-1]
    r = ratios(pruned, base)
    m = lift(rel.frame(base.fds), k).first()
    best = [f for f in base.fds if f.redundancy > 0][:k]
    if base.status != "complete":
        return (
            name, base.stats["n_rows"], rel.m, None, None, base.stats["wall_s"], base.stats["peak_heap_mb"], pruned.stats["wall_s"], pruned.stats["peak_heap_mb"],
            None, None, None, None, None, base.status,
        )
    return (
        name, base.stats["n_rows"], rel.m, m["n_fds"], m["n_positive"], base.stats["wall_s"], base.stats["peak_heap_mb"], pruned.stats["wall_s"], pruned.stats["peak_heap_mb"],
        r["speedup"], r["search_pruning"], r["candidate_pruning"], m["lift"], best == pruned.fds, base.status,
    )


def overall(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = OVERALL, k: int = 10, limits: Limits | None = EXHAUSTIVE) -> DataFrame:
    out = []
    for v in views:
        rel = bound_view(spark, sf_dir, v)
        try:
            out.append(compared(rel, v, k, limits=limits))
        finally:
            rel.release()
    return spark.createDataFrame(out, COMPARE_SCHEMA)


def tuple_scaling(spark: SparkSession, sf_dir: str, view: str = "order_lines", key: str = "l_orderkey", k: int = 10, baseline: bool = True, max_lhs: int | None = None, limits: Limits | None = None) -> DataFrame:
    """Prefixes by key quantile. limits: of the exhaustive run."""
    out = []
    for share in SHARES:
        rel = Relation.bind(prefix(VIEWS[view](spark, sf_dir), key, share), list(COLUMNS[view]), persist=True)
        sharing(holding(rel))
        out.append(row("tuples", view, f"{share:.0%}", "pruned", discover(rel, k, max_lhs=max_lhs)))
        if baseline:
            out.append(row("tuples", view, f"{share:.0%}", "exhaustive", discover(rel, None, "core", max_lhs=max_lhs, limits=limits)))
        rel.release()
    return rows_frame(spark, out)


def attribute_scaling(spark: SparkSession, sf_dir: str, view: str = "wide_star", sizes: tuple[int, ...] = (8, 16, 24, 32, 40), k: int = 10, limits: Limits | None = None, max_lhs: int | None = None) -> DataFrame:
    # ties="any", as published: with synonyms in the relation, many dependencies tie at the threshold, and the canonical order has to look at all of them
    # limits: of the exhaustive run alone
    limits = limits or EXHAUSTIVE_WIDE
    out = []
    rels = [Relation.bind(embedding_bins(m - 1)(spark, sf_dir), persist=True) if view == "embedding_bins" else bound_view(spark, sf_dir, view, COLUMNS[view][:m]) for m in sizes]
    # the widest relation has the others' attributes: its rows are read once, where they are few enough to hold; a run counts the seconds that its own attributes took
    wide = rels[sizes.index(max(sizes))]
    shared = held.Columns(wide)
    for m, rel in zip(sizes, rels, strict=True):
        sharing(holding(rel))
        rel.columns_held = shared
        out.append(row("attributes", view, str(m), "pruned", discover(rel, k, max_lhs=max_lhs, ties="any")))
        out.append(row("attributes", view, str(m), "exhaustive", discover(rel, None, "core", max_lhs=max_lhs, limits=limits)))
        if rel is not wide:
            rel.release()
    wide.release()
    return rows_frame(spark, out)


def k_sweep(spark: SparkSession, sf_dir: str, view: str = "order_lines", ks: tuple[int, ...] = KS, max_lhs: int | None = None, baseline: bool = True, limits: Limits | None = EXHAUSTIVE) -> DataFrame:
    rel = bound_view(spark, sf_dir, view)
    discover(holding(rel), 1, max_lhs=1)
    sharing(rel)
    out = [row("k", view, str(k), "pruned", discover(rel, k, max_lhs=max_lhs)) for k in ks]
    if baseline:
        out.append(row("k", view, "any", "exhaustive", discover(rel, None, "core", max_lhs=max_lhs, limits=limits)))
    rel.release()
    return rows_frame(spark, out)


def ablation(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = ("order_lines", "doc_labels"), k: int = 10, max_lhs: int | None = None) -> DataFrame:
    """One candidate at a time, so that nodes and validations are those of the method."""
    out = []
    for v in views:
        rel = bound_view(spark, sf_dir, v)
        discover(holding(rel), 1, max_lhs=1)
        sharing(holding(rel))
        out += [row("ablation", v, "one by one", x, discover(rel, k, x, max_lhs=max_lhs, **PUBLISHED)) for x in VARIANTS]
        rel.release()
    return rows_frame(spark, out)


def traces(spark: SparkSession, sf_dir: str, view: str = "order_lines", k: int = 10) -> DataFrame:
    """variant, seq, elapsed_s, validations, tau."""
    rel = bound_view(spark, sf_dir, view)
    out = [(v, *t) for v in VARIANTS for t in discover(rel, k, v, **PUBLISHED).trace]
    rel.release()
    return spark.createDataFrame(out, "variant string, seq long, elapsed_s double, validations long, tau long")


CASES = ("orders_calendar", "cust_geo", "priced_lines", "order_lines", "doc_labels")


def cases(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = CASES, k: int = 3, limits: Limits | None = EXHAUSTIVE) -> DataFrame:
    """The first k of each view, with what they mean, and LIFT_k against all others (null where the exhaustive run exceeds its limits)."""
    out = []
    for v in views:
        rel = sharing(holding(bound_view(spark, sf_dir, v)))
        found = discover(rel, 10)
        label = kinds(rel, found.fds)
        base = discover(rel, None, "core", limits=limits)
        value = lift(rel.frame(base.fds), k).first()["lift"] if base.status == "complete" else None
        out += [(v, i, rel.lhs_text(f.lhs), rel.columns[f.rhs], f.redundancy, f.n_rows, f.n_classes, label[f], value) for i, f in enumerate(found.fds[:k], 1)]
        rel.release()
    return spark.createDataFrame(out, "relation string, rank int, lhs_text string, rhs string, redundancy long, n_rows long, n_classes long, kind string, lift double")


def overhead(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = ("region", "nation", "labels", "benchmark")) -> DataFrame:
    """Share of a small run's time that pairs and queue take, by the published scheduler, beside an exhaustive run of the same relation. Both warm, medians."""
    out = []
    for v in views:
        rel = bound_view(spark, sf_dir, v)
        discover(rel, 1, max_lhs=1)
        runs = [(discover(rel, 10, kernel="tree", warm_start=False, recheck=False).stats, discover(rel, None, "core").stats) for _ in range(RUNS)]
        s, base = sorted(runs, key=lambda r: r[0]["wall_s"])[RUNS // 2][0], median(b["wall_s"] for _, b in runs)
        out.append((v, s["n_rows"], s["n_attributes"], s["wall_s"], s["pairs_s"], s["queue_s"], (s["pairs_s"] + s["queue_s"]) / s["wall_s"], base, s["wall_s"] / base))
        rel.release()
    return spark.createDataFrame(out, "relation string, n_rows long, n_attributes int, wall_s double, pairs_s double, queue_s double, share double, base_s double, overhead double")


def limited(spark: SparkSession, sf_dir: str, d: int = 40, limits: Limits | None = None) -> DataFrame:
    """A wide relation under a budget of nodes and validations that the exhaustive run exceeds; the pruned one has no limits and finishes."""
    limits = limits or EXHAUSTIVE_WIDE
    rel = bound_view(spark, sf_dir, "wide_star", COLUMNS["wide_star"][:d])
    sharing(holding(rel))
    out = [row("limits", "wide_star", f"{d} attributes", "pruned", discover(rel, 10, ties="any")), row("limits", "wide_star", f"{d} attributes", "exhaustive", discover(rel, None, "core", limits=limits))]
    rel.release()
    return rows_frame(spark, out)
