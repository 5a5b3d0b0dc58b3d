"""Queries by name, with the DuckDB SQL of each where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracle, workloads
from .functions import udx
from .model import Relation, mask_of
from .operators import apply, cardinality, definitions, evidence
from .plans import baseline, bounds, metrics
from .plans.search import VARIANTS, discover
from .ship import scratch, ship
from .sources import files, views
from .sources.views import COLUMNS, VIEW_SQL, VIEWS
from .streaming import monitor

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
ANSWER = ("rank", "lhs_text", "rhs", "lhs_size", "redundancy", "n_rows", "n_classes")


def query(name: str, sql: str | None = None):
    def put(f: Query) -> Query:
        def shipped(spark: SparkSession, sf: str) -> DataFrame:
            ship(spark)
            return f(spark, sf)

        QUERIES[name] = shipped
        if sql is not None:
            ORACLES[name] = sql
        return f

    return put


def bound(spark: SparkSession, sf: str, view: str, columns=None, nulls: str = "eq") -> Relation:
    return Relation.bind(VIEWS[view](spark, sf), list(columns or COLUMNS[view]), nulls, persist=True)


def answer(view: str, k: int = 10, columns=None, whole: bool = False, **options) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        rel = bound(spark, sf, view, columns)
        found = discover(rel, None if whole else k, **options)
        rel.release()
        return found.result.select(*ANSWER)

    return run


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """The ten dependencies of customers, nations and regions that explain most repeats."""
    return answer("cust_geo")(spark, sf)


# ---- definitions -----------------------------------------------------------------------------------------------------------------------------

_HOLDS = [(x, a) for x in ("o_orderstatus", "o_orderpriority", "o_custkey", "o_orderdate", "o_month") for a in ("o_year", "o_quarter", "o_month", "o_dow", "o_orderstatus") if x != a]


@query("fd_holds_matrix", f"WITH src AS ({VIEW_SQL['orders_calendar']}) " + " UNION ALL ".join(
    f"SELECT '{x}' AS lhs_text, '{a}' AS rhs, (SELECT count(*) FROM (SELECT DISTINCT {x} FROM src)) = (SELECT count(*) FROM (SELECT DISTINCT {x}, {a} FROM src)) AS holds" for x, a in _HOLDS))
def fd_holds_matrix(spark, sf):
    rel = bound(spark, sf, "orders_calendar")
    at = rel.columns.index
    found = cardinality.check_batch(rel, [(1 << at(x), at(a)) for x, a in _HOLDS])
    rel.release()
    return spark.createDataFrame([(x, a, found[1 << at(x), at(a)].valid) for x, a in _HOLDS], "lhs_text string, rhs string, holds boolean")


@query("class_sizes", "SELECT l_returnflag, l_linestatus, count(*) AS size FROM lineitem GROUP BY ALL")
def class_sizes(spark, sf):
    return definitions.classes(bound(spark, sf, "lineitem"), ["l_returnflag", "l_linestatus"])


@query("class_histogram", "SELECT size, count(*) AS n_classes FROM (SELECT count(*) AS size FROM lineitem GROUP BY l_orderkey) GROUP BY size")
def class_histogram(spark, sf):
    return definitions.classes(Relation.bind(views.read(spark, sf, "lineitem"), ["l_orderkey"]), ["l_orderkey"]).groupBy("size").agg(F.count(F.lit(1)).alias("n_classes"))


def _cards(view: str, sizes: tuple[int, ...], columns=None) -> Query:
    def run(spark, sf):
        rel = bound(spark, sf, view, columns)
        sets = [sum(1 << i for i in some) for size in sizes for some in combinations(range(rel.m), size)]
        found = cardinality.set_cardinalities(rel, sets)
        rel.release()
        return spark.createDataFrame([(rel.lhs_text(s), s.bit_count(), c) for s, c in found.items()], "attrs string, size int, card long")

    return run


query("set_cards_single", oracle.cards("order_lines", (1,)))(_cards("order_lines", (1,)))
query("set_cards_pairs", oracle.cards("doc_labels", (2,)))(_cards("doc_labels", (2,)))
query("set_cards_batch", oracle.cards("orders", (1, 2, 3)))(_cards("orders", (1, 2, 3)))


@query("set_cards_exploded", oracle.cards("events_calendar", (1, 2)))
def set_cards_exploded(spark, sf):
    rel = bound(spark, sf, "events_calendar")
    sets = [sum(1 << i for i in some) for size in (1, 2) for some in combinations(range(rel.m), size)]
    found = cardinality.exploded_cardinalities(rel, sets)
    rel.release()
    return spark.createDataFrame([(rel.lhs_text(s), s.bit_count(), c) for s, c in found.items()], "attrs string, size int, card long")


@query("redundancy_two_ways", """SELECT attrs, CAST(sum(size) AS BIGINT) AS n_rows, count(*) AS n_classes, CAST(sum(size - 1) AS BIGINT) AS by_sum, CAST(sum(size) - count(*) AS BIGINT) AS by_difference FROM (
 SELECT 'o_custkey' AS attrs, count(*) AS size FROM orders GROUP BY o_custkey UNION ALL SELECT 'o_orderstatus', count(*) FROM orders GROUP BY o_orderstatus
 UNION ALL SELECT 'o_orderdate', count(*) FROM orders GROUP BY o_orderdate) GROUP BY attrs""")
def redundancy_two_ways(spark, sf):
    rel = Relation.bind(views.read(spark, sf, "orders"))
    out = None
    for a in ("o_custkey", "o_orderstatus", "o_orderdate"):
        one = definitions.redundancy_sum(rel, [a]).select(F.lit(a).alias("attrs"), "n_rows", "n_classes", F.col("redundancy").alias("by_sum"), (F.col("n_rows") - F.col("n_classes")).alias("by_difference"))
        out = one if out is None else out.unionByName(one)
    return out


@query("redundant_rows", f"SELECT c_custkey, c_nationkey, n_name FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS p FROM ({VIEW_SQL['cust_geo']})) WHERE p > 1")
def redundant_rows(spark, sf):
    return definitions.redundant_rows(bound(spark, sf, "cust_geo"), ["c_nationkey"], "n_name", ["c_custkey"])


query("redundancy_toy", oracle.everything("flight_toy"))(answer("flight_toy", whole=True))


@query("fd_minimal_small", oracle.everything("nation"))
def fd_minimal_small(spark, sf):
    """All valid left-hand sides of a small table, thinned out by the DataFrame form of minimality."""
    rel = bound(spark, sf, "nation")
    n, _ = cardinality.profile(rel)
    sets = cardinality.set_cardinalities(rel, range(1 << rel.m))
    rel.release()
    rows = [(rel.names(s), rel.lhs_text(s), rel.columns[a], s.bit_count(), n - c, n, c) for s, c in sets.items() for a in range(rel.m) if not s >> a & 1 and sets[s | 1 << a] == c]
    held = spark.createDataFrame(rows, "lhs array<string>, lhs_text string, rhs string, lhs_size int, redundancy long, n_rows long, n_classes long")
    order = Window.orderBy(F.desc("redundancy"), "lhs_size", "lhs_text", "rhs")
    return definitions.minimal_only(held).withColumn("rank", F.row_number().over(order)).select(*ANSWER)


# ---- top-k answers, variants, kernels --------------------------------------------------------------------------------------------------------

for _v in ("cust_geo", "orders_calendar", "priced_lines", "doc_labels", "events_calendar", "event_props", "documents", "orders", "page_facts", "talk_facts", "bench_facts"):
    query(f"topk_{_v}", oracle.topk(_v, 10))(answer(_v))
query("topk_customer_empty", oracle.topk("customer", 10))(answer("customer"))
query("topk_order_lines_lhs2", oracle.topk("order_lines", 10, 2))(answer("order_lines", max_lhs=2))
_WIDE = COLUMNS["wide_star"][:14] + ("c_nationkey", "n_name", "r_name", "p_brand", "s_nationkey", "o_year", "o_quarter", "o_month")
query("topk_wide_star_lhs1", oracle.topk("wide_star", 20, 1))(answer("wide_star", 20, max_lhs=1))
query("topk_wide_star_lhs2", oracle.topk("wide_star", 10, 2, _WIDE))(answer("wide_star", columns=_WIDE, max_lhs=2))
for _k in (1, 50, 100):
    query(f"topk_k{_k}", oracle.topk("cust_geo", _k))(answer("cust_geo", _k))
for _v in VARIANTS:
    query(f"topk_{_v}", oracle.topk("cust_geo", 10))(answer("cust_geo", variant=_v, batch=1))
query("topk_sequential", oracle.topk("cust_geo", 10))(answer("cust_geo", scheduler="sequential", warm_start=False))
query("topk_tree_kernel", oracle.topk("cust_geo", 10))(answer("cust_geo", kernel="tree"))
query("topk_antichain_kernel", oracle.topk("cust_geo", 10))(answer("cust_geo", kernel="antichain"))
query("topk_batch1", oracle.topk("order_lines", 10, 2))(answer("order_lines", batch=1, max_lhs=2))
query("topk_batch16", oracle.topk("order_lines", 10, 2))(answer("order_lines", batch=16, max_lhs=2, warm_start=False))
query("topk_spread_kernel", oracle.topk("cust_geo", 10))(answer("cust_geo", spread=True, warm_start=False))
query("topk_lower_profile", oracle.topk("cust_geo", 10))(answer("cust_geo", profile="lower"))
query("topk_cache_bound", oracle.topk("orders_calendar", 10))(answer("orders_calendar", bound="cache"))
query("topk_random_order", oracle.topk("orders_calendar", 10))(answer("orders_calendar", order="random"))
query("topk_no_sample", oracle.topk("doc_labels", 10))(answer("doc_labels", sample=False))


@query("topk_any_ties", f"SELECT redundancy FROM ({oracle.topk('cust_geo', 10)})")
def topk_any_ties(spark, sf):
    return answer("cust_geo", ties="any")(spark, sf).select("redundancy")


# ---- baseline --------------------------------------------------------------------------------------------------------------------------------

for _v in ("cust_geo", "doc_labels", "orders_calendar", "priced_lines"):
    query(f"all_minimal_fds_{_v}", oracle.everything(_v))(answer(_v, whole=True, variant="core"))
query("all_minimal_fds_antichain", oracle.everything("cust_geo"))(answer("cust_geo", whole=True, variant="core", kernel="antichain"))


def _ranked(view: str) -> Query:
    def run(spark, sf):
        rel = bound(spark, sf, view)
        out, _ = baseline.rank_after_discovery(rel, 10)
        rel.release()
        return out.select(*ANSWER)

    return run


for _v in ("cust_geo", "events_calendar", "documents"):
    query(f"rank_after_discovery_{_v}", oracle.topk(_v, 10))(_ranked(_v))


@query("brute_force_orders", oracle.everything("orders", 2))
def brute_force_orders(spark, sf):
    rel = bound(spark, sf, "orders")
    out = rel.frame(baseline.brute_force(rel, 2)).select(*ANSWER)
    rel.release()
    return out


# ---- bounds ----------------------------------------------------------------------------------------------------------------------------------


def _bounds_sql(select: str) -> str:
    cols = COLUMNS["orders_calendar"]
    return f"""{oracle.lattice(VIEW_SQL['orders_calendar'], cols, 1)},
one AS (SELECT mask, card FROM cards WHERE bit_count(mask) = 1), two AS (SELECT mask, card FROM cards WHERE bit_count(mask) = 2),
sets AS (SELECT mask, card FROM cards WHERE bit_count(mask) BETWEEN 1 AND 2),
pairs AS (SELECT s.mask, s.card, b.bit, b.name AS rhs, n,
  greatest((SELECT max(card) FROM one WHERE (one.mask & s.mask) <> 0), (SELECT card FROM one WHERE one.mask = b.bit)) AS singles, CASE WHEN bit_count(s.mask) = 2 THEN s.card ELSE 0 END AS pair,
  (SELECT string_agg(name, ',' ORDER BY name) FROM bits WHERE (bits.bit & s.mask) <> 0) AS lhs_text
  FROM sets s JOIN bits b ON (s.mask & b.bit) = 0, n)
{select}"""


def _bound_rows(spark, sf):
    rel = bound(spark, sf, "orders_calendar")
    n, cards = cardinality.profile(rel)
    sets = [s for s in range(1, 1 << rel.m) if s.bit_count() <= 2]
    matrix = bounds.PairMatrix(n, cards)
    matrix.precompute(rel, list(range(rel.m)), rel.m)
    single = {(s, a): b for s, a, b in bounds.bound_rows(n, cards, None, sets)}
    double = {(s, a): b for s, a, b in bounds.bound_rows(n, cards, matrix, sets)}
    true = {s: n - (matrix.pairs.get(s) or cards[s.bit_length() - 1]) for s in sets}
    rel.release()
    return spark.createDataFrame([(rel.lhs_text(s), rel.columns[a], single[s, a], double[s, a], true[s]) for s, a in single], "lhs_text string, rhs string, single long, pair long, redundancy long")


@query("bound_single_table", _bounds_sql("SELECT lhs_text, rhs, CAST(n - singles AS BIGINT) AS bound FROM pairs"))
def bound_single_table(spark, sf):
    return _bound_rows(spark, sf).select("lhs_text", "rhs", F.col("single").alias("bound"))


@query("bound_pair_table", _bounds_sql("SELECT lhs_text, rhs, CAST(n - greatest(singles, pair) AS BIGINT) AS bound FROM pairs"))
def bound_pair_table(spark, sf):
    return _bound_rows(spark, sf).select("lhs_text", "rhs", F.col("pair").alias("bound"))


@query("bound_gap", _bounds_sql("SELECT lhs_text, rhs, CAST((n - greatest(singles, pair)) - (n - card) AS BIGINT) AS gap FROM pairs WHERE EXISTS (SELECT 1 FROM cards y WHERE y.mask = (pairs.mask | pairs.bit) AND y.card = pairs.card) AND bit_count(mask) = 1"))
def bound_gap(spark, sf):
    """Bound minus redundancy of single-attribute dependencies that hold: never negative."""
    rel = bound(spark, sf, "orders_calendar")
    one = [(1 << i, a) for i in range(rel.m) for a in range(rel.m) if a != i]
    found = cardinality.check_batch(rel, one)
    rel.release()
    valid = spark.createDataFrame([(rel.lhs_text(s), rel.columns[a]) for s, a in one if found[s, a].valid], "lhs_text string, rhs string")
    return _bound_rows(spark, sf).join(valid, ["lhs_text", "rhs"]).select("lhs_text", "rhs", (F.col("pair") - F.col("redundancy")).alias("gap"))


@query("attribute_order", f"WITH src AS ({VIEW_SQL['order_lines']}) SELECT attribute, card, CAST(row_number() OVER (ORDER BY card, pos) AS INTEGER) AS place FROM (" + " UNION ALL ".join(
    f"SELECT '{c}' AS attribute, {i} AS pos, (SELECT count(*) FROM (SELECT DISTINCT {c} FROM src)) AS card" for i, c in enumerate(COLUMNS["order_lines"])) + ")")
def attribute_order(spark, sf):
    rel = bound(spark, sf, "order_lines")
    _, cards = cardinality.profile(rel)
    rel.release()
    return spark.createDataFrame([(rel.columns[i], cards[i], p) for p, i in enumerate(bounds.attribute_order(cards), 1)], "attribute string, card long, place int")


@query("pair_matrix_first_d", f"""WITH src AS ({VIEW_SQL['orders_calendar']}), c AS (""" + " UNION ALL ".join(f"SELECT '{c}' AS a, {i} AS pos, (SELECT count(*) FROM (SELECT DISTINCT {c} FROM src)) AS card" for i, c in enumerate(COLUMNS["orders_calendar"])) + """),
head AS (SELECT a FROM c ORDER BY card, pos LIMIT 3), p AS (""" + " UNION ALL ".join(f"SELECT '{x}' AS a, '{y}' AS b, (SELECT count(*) FROM (SELECT DISTINCT {x}, {y} FROM src)) AS card" for x, y in combinations(sorted(COLUMNS["orders_calendar"]), 2)) + """)
SELECT a || ',' || b AS attrs, CAST(card AS BIGINT) AS card FROM p WHERE a IN (SELECT a FROM head) AND b IN (SELECT a FROM head)""")
def pair_matrix_first_d(spark, sf):
    rel = bound(spark, sf, "orders_calendar")
    n, cards = cardinality.profile(rel)
    matrix = bounds.PairMatrix(n, cards)
    matrix.precompute(rel, bounds.attribute_order(cards))
    rel.release()
    return spark.createDataFrame([(rel.lhs_text(s), c) for s, c in matrix.pairs.items()], "attrs string, card long")


# ---- evidence --------------------------------------------------------------------------------------------------------------------------------


def _differences(view: str) -> Query:
    def run(spark, sf):
        rel = bound(spark, sf, view)
        found = evidence.all_difference_sets(rel).collect()
        rel.release()
        return spark.createDataFrame([(rel.lhs_text(evidence.mask_of_words(r["words"])), r["support"]) for r in found], "attrs string, support long")

    return run


for _name in ("nation", "region"):
    query(f"difference_sets_{_name}", oracle.differences(_name))(_differences(_name))
# once over the five rows of the toy relation; a given table has its place
query("difference_sets_toy", oracle.class_differences("order_months"))(_differences("order_months"))


def _month_edges(spark, sf) -> tuple[Relation, set[int]]:
    rel = bound(spark, sf, "order_months")
    edges = {evidence.mask_of_words(r["words"]) for r in evidence.all_difference_sets(rel).collect()} - {0}
    rel.release()
    return rel, edges


_INDUCED = f"SELECT DISTINCT array_to_string(list_filter(string_split(attrs, ','), lambda x: x <> 'o_quarter'), ',') AS attrs FROM ({oracle.class_differences('order_months')}) WHERE list_contains(string_split(attrs, ','), 'o_quarter')"


@query("induced_edges", _INDUCED)
def induced_edges(spark, sf):
    rel, edges = _month_edges(spark, sf)
    return evidence.edge_frame(rel, evidence.induce(edges, rel.columns.index("o_quarter"))).select("attrs")


@query("minimal_edges", f"WITH e AS ({_INDUCED}) SELECT attrs FROM e WHERE NOT EXISTS (SELECT 1 FROM e s WHERE s.attrs <> e.attrs AND list_has_all(string_split(e.attrs, ','), string_split(s.attrs, ',')))")
def minimal_edges(spark, sf):
    rel, edges = _month_edges(spark, sf)
    return evidence.edge_frame(rel, evidence.minimise(evidence.induce(edges, rel.columns.index("o_quarter")))).select("attrs")


@query("refuting_pairs", "SELECT CAST(count(*) > 0 AS INTEGER) AS refuted FROM (SELECT o_custkey FROM orders GROUP BY o_custkey HAVING count(DISTINCT o_orderstatus) > 1)")
def refuting_pairs(spark, sf):
    """A fixed broken dependency gives a pair of rows that agrees left and differs right."""
    rel = bound(spark, sf, "orders")
    lhs, a = mask_of(["o_custkey"], rel.columns), rel.columns.index("o_orderstatus")
    v = cardinality.check_batch(rel, [(lhs, a)])[lhs, a]
    edge = evidence.violating_edges(rel, [(lhs, a, v.example)])[lhs, a] if v.example else 0
    rel.release()
    return spark.createDataFrame([(int(bool(edge) and not edge & lhs and bool(edge >> a & 1)),)], "refuted int")


@query("sampled_edges")
def sampled_edges(spark, sf):
    rel = bound(spark, sf, "doc_labels")
    n, cards = cardinality.profile(rel)
    edges = evidence.sample_difference_sets(rel, n, cards)
    rel.release()
    return evidence.edge_frame(rel, edges)


@query("slice_refutation", f"WITH src AS ({VIEW_SQL['orders_calendar']}) SELECT count(*) AS n_broken FROM (" + " UNION ALL ".join(
    f"SELECT 1 AS x WHERE (SELECT count(*) FROM (SELECT DISTINCT {x} FROM src)) < (SELECT count(*) FROM (SELECT DISTINCT {x}, {a} FROM src))" for x, a in _HOLDS) + ")")
def slice_refutation(spark, sf):
    """Broken candidates by slices first, the survivors by the full pass."""
    rel = bound(spark, sf, "orders_calendar")
    some = [(1 << rel.columns.index(x), rel.columns.index(a)) for x, a in _HOLDS]
    broken = cardinality.refute_on_slice(rel, some, 4)
    rest = cardinality.check_batch(rel, [c for c in some if c not in broken])
    rel.release()
    return spark.createDataFrame([(len(broken) + sum(not v.valid for v in rest.values()),)], "n_broken long")


# ---- measures --------------------------------------------------------------------------------------------------------------------------------

_LIFT_SQL = """, top AS (SELECT *, row_number() OVER (ORDER BY redundancy DESC, lhs_size, lhs_text, rhs) AS r FROM fds),
m AS (SELECT count(*) AS n_fds, count(*) FILTER (redundancy > 0) AS n_positive, sum(redundancy) FILTER (r <= 10 AND redundancy > 0) / nullif(count(*) FILTER (r <= 10 AND redundancy > 0), 0)::DOUBLE AS t,
  avg(redundancy) FILTER (NOT (r <= 10 AND redundancy > 0)) AS b FROM top)"""


def _lift(view: str) -> Query:
    def run(spark, sf):
        rel = bound(spark, sf, view)
        found = baseline.discover_all(rel)
        rel.release()
        text = F.when(F.col("mean_rest").isNull(), "no rest").when(F.col("mean_rest") == 0, "infinite").otherwise(F.round("lift", 3).cast("string"))
        return metrics.lift(found.result, 10).select("n_fds", "n_positive", text.alias("lift"))

    return run


for _v in ("cust_geo", "doc_labels", "priced_lines"):
    query(f"lift_{_v}", oracle.over_fds(_v, _LIFT_SQL + " SELECT n_fds, n_positive, CASE WHEN b IS NULL THEN 'no rest' WHEN b = 0 THEN 'infinite' ELSE CAST(round(t / b, 3) AS VARCHAR) END AS lift FROM m"))(_lift(_v))


@query("fd_counts", oracle.over_fds("orders_calendar", "SELECT count(*) AS n_fds, count(*) FILTER (redundancy > 0) AS n_positive FROM fds"))
def fd_counts(spark, sf):
    return _lift("orders_calendar")(spark, sf).select("n_fds", "n_positive")


@query("pruning_ratios")
def pruning_ratios(spark, sf):
    rel = bound(spark, sf, "cust_geo")
    out = workloads.compared(rel, "cust_geo")
    rel.release()
    return spark.createDataFrame([out], workloads.COMPARE_SCHEMA)


@query("run_stats")
def run_stats(spark, sf):
    return discover(VIEWS["cust_geo"](spark, sf), 10, columns=list(COLUMNS["cust_geo"])).stats_frame()


@query("tau_trace")
def tau_trace(spark, sf):
    return discover(VIEWS["cust_geo"](spark, sf), 10, columns=list(COLUMNS["cust_geo"]), batch=1).trace_frame()


# ---- workloads -------------------------------------------------------------------------------------------------------------------------------

query("w1_overall")(workloads.overall)
query("w2_tuples")(lambda spark, sf: workloads.tuple_scaling(spark, sf, limits=workloads.EXHAUSTIVE))
query("w2_lineitem")(lambda spark, sf: workloads.tuple_scaling(spark, sf, "lineitem", limits=workloads.EXHAUSTIVE))
query("w3_attributes")(workloads.attribute_scaling)
query("w4_k")(lambda spark, sf: workloads.k_sweep(spark, sf).unionByName(workloads.k_sweep(spark, sf, "embedding_bins")))
query("w5_ablation")(workloads.ablation)
query("w6_traces")(lambda spark, sf: workloads.traces(spark, sf, "cust_geo"))
query("w7_case_studies")(workloads.cases)
query("w8_overhead")(workloads.overhead)
query("w9_limits")(workloads.limited)


@query("w2_prefix_cards", " UNION ALL ".join(
    f"SELECT CAST({share} AS DOUBLE) AS share, a AS attribute, c AS card FROM (SELECT {', '.join(f'count(DISTINCT {c}) + max(CASE WHEN {c} IS NULL THEN 1 ELSE 0 END) AS {c}' for c in COLUMNS['lineitem'])} FROM lineitem WHERE l_orderkey <= (SELECT quantile_disc(l_orderkey, {share}) FROM lineitem)) UNPIVOT (c FOR a IN ({', '.join(COLUMNS['lineitem'])}))"
    for share in workloads.SHARES))
def w2_prefix_cards(spark, sf):
    out = []
    for share in workloads.SHARES:
        rel = Relation.bind(views.prefix(VIEWS["lineitem"](spark, sf), "l_orderkey", share), list(COLUMNS["lineitem"]))
        out += [(share, c, card) for c, card in zip(rel.columns, cardinality.profile(rel)[1], strict=True)]
    return spark.createDataFrame(out, "share double, attribute string, card long")


@query("w1_counts", " UNION ALL ".join(f"SELECT '{v}' AS relation, * FROM ({oracle.over_fds(v, 'SELECT count(*) AS n_fds, count(*) FILTER (redundancy > 0) AS n_positive FROM fds')})" for v in ("region", "nation", "orders", "labels")))
def w1_counts(spark, sf):
    out = None
    for v in ("region", "nation", "orders", "labels"):
        one = _lift(v)(spark, sf).select(F.lit(v).alias("relation"), "n_fds", "n_positive")
        out = one if out is None else out.unionByName(one)
    return out


@query("w2_prefix_topk", oracle.topk("orders_calendar", 10, source=VIEW_SQL["orders_calendar"] + " WHERE o_orderkey <= (SELECT quantile_disc(o_orderkey, 0.4) FROM orders)"))
def w2_prefix_topk(spark, sf):
    rel = Relation.bind(views.prefix(VIEWS["orders_calendar"](spark, sf), "o_orderkey", 0.4), list(COLUMNS["orders_calendar"]), persist=True)
    out = discover(rel, 10).result.select(*ANSWER)
    rel.release()
    return out


query("w3_subset_topk", oracle.topk("wide_star", 10, 3, COLUMNS["wide_star"][:8]))(answer("wide_star", columns=COLUMNS["wide_star"][:8], max_lhs=3))


@query("w4_k_sweep", " UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS k, CAST(count(*) AS BIGINT) AS answers, CAST(min(redundancy) AS BIGINT) AS last FROM ({oracle.topk('cust_geo', k)})" for k in (1, 10, 50)))
def w4_k_sweep(spark, sf):
    rel = bound(spark, sf, "cust_geo")
    out = []
    for k in (1, 10, 50):
        fds = discover(rel, k).fds
        out.append((k, len(fds), fds[-1].redundancy))
    rel.release()
    return spark.createDataFrame(out, "k int, answers long, last long")


@query("w7_cases", " UNION ALL ".join(f"SELECT '{v}' AS relation, rank, lhs_text, rhs, redundancy, n_rows, n_classes FROM ({oracle.topk(v, 3, m)})" for v, m in (("orders_calendar", None), ("cust_geo", 3), ("doc_labels", None))))
def w7_cases(spark, sf):
    return workloads.cases(spark, sf, ("orders_calendar", "cust_geo", "doc_labels")).drop("kind", "lift")


# ---- around: sources, joins, aggregations, windows, sets, functions, applications, streams ---------------------------------------------------


def _round_trip(kind: str) -> Query:
    def run(spark, sf):
        folder = f"{scratch(spark)}/t"
        df = views.read(spark, sf, "nation")
        (df.write.option("header", True) if kind == "csv" else df.write).format(kind).save(folder)
        rel = files.relation(spark, folder, kind, ["n_regionkey", "n_name"])
        return rel.df.groupBy("n_regionkey").agg(F.count_distinct("n_name").alias("n_names")).select(F.col("n_regionkey").cast("int").alias("n_regionkey"), "n_names")

    return run


for _kind in ("parquet", "csv", "json", "orc"):
    query("src_csv_inferred" if _kind == "csv" else f"src_{_kind}", "SELECT n_regionkey, count(DISTINCT n_name) AS n_names FROM nation GROUP BY n_regionkey")(_round_trip(_kind))


@query("sink_results", oracle.topk("nation", 10))
def sink_results(spark, sf):
    found = discover(VIEWS["nation"](spark, sf), 10)
    folder = scratch(spark)
    files.save_result(found, folder, "nation")
    return spark.read.schema(found.result.schema).parquet(f"{folder}/answers").select(*ANSWER)


@query("sql_views", oracle.cards("region", (1,)))
def sql_views(spark, sf):
    files.publish(discover(VIEWS["region"](spark, sf), 10))
    return spark.sql("SELECT attrs, size, card FROM fd_cards WHERE size = 1")


query("filter_not_null", "SELECT count(*) AS n FROM documents d JOIN labels l ON d.doc_id = l.doc_id WHERE quality IS NOT NULL")(lambda s, d: VIEWS["doc_labels"](s, d).where(F.col("quality").isNotNull()).agg(F.count(F.lit(1)).alias("n")))
query("join_star_broadcast", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")(lambda s, d: VIEWS["cust_geo"](s, d).groupBy("r_name").agg(F.count(F.lit(1)).alias("n")))
query("join_sortmerge", "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")(
    lambda s, d: views.read(s, d, "lineitem").hint("merge").join(views.read(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n")))
query("join_left_labels", "SELECT quality, count(*) AS n FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id GROUP BY quality")(lambda s, d: VIEWS["doc_labels"](s, d).groupBy("quality").agg(F.count(F.lit(1)).alias("n")))
query("join_semi_violations", "SELECT o_orderkey, o_custkey, o_orderstatus FROM orders WHERE o_custkey IN (SELECT o_custkey FROM orders GROUP BY o_custkey HAVING count(DISTINCT o_orderstatus) > 1)")(
    lambda s, d: apply.violating_rows(views.read(s, d, "orders").select("o_orderkey", "o_custkey", "o_orderstatus"), ["o_custkey"], "o_orderstatus"))
@query("join_anti_minimal", oracle.over_fds("cust_geo", "SELECT lhs_text, rhs, CAST(n_classes AS BIGINT) AS n_classes FROM fds", 2))
def join_anti_minimal(spark, sf):
    """Minimal dependencies with up to two attributes on the left, from class counts alone: one join of the counts, one anti join."""
    rel = bound(spark, sf, "cust_geo")
    cards = cardinality.set_cardinalities(rel, [mask_of(some, rel.columns) for size in range(4) for some in combinations(rel.columns, size)])
    rel.release()
    sets = spark.createDataFrame([(s, c, rel.lhs_text(s)) for s, c in cards.items()], "mask long, card long, lhs_text string")
    names = spark.createDataFrame([(1 << i, c) for i, c in enumerate(rel.columns)], "bit long, rhs string")
    found = definitions.minimal_masks(sets.select("mask", "card"), names.select("bit")).where("bit_count(mask) <= 2")
    return found.join(F.broadcast(sets.select("mask", "lhs_text")), "mask").join(F.broadcast(names), "bit").select("lhs_text", "rhs", "n_classes")


query("join_pairs_theta", "SELECT count(*) AS n FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_custkey < b.c_custkey WHERE a.c_mktsegment = b.c_mktsegment")(
    lambda s, d: views.read(s, d, "customer").alias("a").join(views.read(s, d, "customer").alias("b"), (F.col("a.c_nationkey") == F.col("b.c_nationkey")) & (F.col("a.c_custkey") < F.col("b.c_custkey")) & (F.col("a.c_mktsegment") == F.col("b.c_mktsegment"))).agg(F.count(F.lit(1)).alias("n")))
query("join_range_prefix", "SELECT count(*) AS n FROM lineitem WHERE l_orderkey <= (SELECT quantile_disc(l_orderkey, 0.6) FROM lineitem)")(lambda s, d: views.prefix(views.read(s, d, "lineitem"), "l_orderkey", 0.6).agg(F.count(F.lit(1)).alias("n")))
query("join_nullsafe", "SELECT count(*) AS n FROM (SELECT DISTINCT quality, toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id) a JOIN (SELECT quality AS q, count(*) AS c FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id GROUP BY quality) b ON a.quality IS NOT DISTINCT FROM b.q")(
    lambda s, d: (v := VIEWS["doc_labels"](s, d)).select("quality", "toxic").distinct().join(v.groupBy(F.col("quality").alias("q")).count(), F.col("quality").eqNullSafe(F.col("q"))).agg(F.count(F.lit(1)).alias("n")))
query("join_asof_events", "SELECT user_id, count(*) AS n, CAST(sum(epoch_us(ts) - epoch_us(prev)) AS BIGINT) AS gap_us FROM (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev FROM events) WHERE prev IS NOT NULL GROUP BY user_id")(
    lambda s, d: views.read(s, d, "events").withColumn("prev", F.lag("ts").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))).where("prev IS NOT NULL").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.col("prev").cast("timestamp"))).alias("gap_us")))
query("agg_distinct_nullsafe", "SELECT count(*) AS n FROM (SELECT DISTINCT quality, toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id)")(lambda s, d: VIEWS["doc_labels"](s, d).select("quality", "toxic").distinct().agg(F.count(F.lit(1)).alias("n")))
query("agg_cube_pairs", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(lambda s, d: views.read(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")))
query("agg_rollup_geo", f"SELECT r_name, n_name, count(*) AS n FROM ({VIEW_SQL['cust_geo']}) GROUP BY ROLLUP (r_name, n_name)")(lambda s, d: VIEWS["cust_geo"](s, d).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n")))


@query("agg_grouping_sets", "SELECT 'l_linestatus' AS attrs, count(*) AS card, CAST(sum(n - 1) AS BIGINT) AS redundancy FROM (SELECT count(*) AS n FROM lineitem GROUP BY l_linestatus) UNION ALL SELECT 'l_linestatus,l_returnflag', count(*), CAST(sum(n - 1) AS BIGINT) FROM (SELECT count(*) AS n FROM lineitem GROUP BY l_linestatus, l_returnflag)")
def agg_grouping_sets(spark, sf):
    rel = Relation.bind(views.read(spark, sf, "lineitem"), ["l_returnflag", "l_linestatus"])
    ids = cardinality.grouping_ids([2, 3])
    names = F.create_map(*[F.lit(x) for g, s in ids.items() for x in (g, rel.lhs_text(s))])
    return cardinality.grouping_frame(rel, [2, 3]).select(names[F.col("gid").cast("int")].alias("attrs"), "card", "redundancy")


@query("agg_approx_card")
def agg_approx_card(spark, sf):
    rel = bound(spark, sf, "order_lines")
    return spark.createDataFrame(list(zip(rel.columns, cardinality.approximate_profile(rel), strict=True)), "attribute string, card long")


_GEO = oracle.everything("cust_geo")


def _geo(spark, sf) -> DataFrame:
    return answer("cust_geo", whole=True, variant="core")(spark, sf)


query("win_rank_fds", f"SELECT lhs_text, rhs, redundancy, rank() OVER w AS rank_, dense_rank() OVER w AS dense_rank_, row_number() OVER (PARTITION BY rhs ORDER BY redundancy DESC, lhs_size, lhs_text) AS row_number_, round(CASE WHEN max(redundancy) OVER (PARTITION BY rhs) > 0 THEN redundancy / max(redundancy) OVER (PARTITION BY rhs) END, 9) AS ratio_to_best, CAST(sum(redundancy) OVER (PARTITION BY rhs ORDER BY redundancy DESC, lhs_size, lhs_text ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM ({_GEO}) WINDOW w AS (PARTITION BY rhs ORDER BY redundancy DESC)")(
    lambda s, d: apply.ranked(_geo(s, d)))
_LAGGED = ("o_orderdate", "o_orderpriority", "o_orderstatus", "o_totalprice")
_LAG_FLAGS = ", ".join(f"CASE WHEN {c} IS DISTINCT FROM lag({c}) OVER w THEN '{c}' END" for c in _LAGGED)
query("win_lag_pairs", f"SELECT attrs, count(*) AS support FROM (SELECT array_to_string(list_filter([{_LAG_FLAGS}], lambda x: x IS NOT NULL), ',') AS attrs, row_number() OVER w AS place FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)) WHERE place > 1 GROUP BY attrs")(
    lambda s, d: evidence.lag_pairs(views.read(s, d, "orders"), ["o_custkey"], ["o_orderkey"], list(_LAGGED)))
query("win_range_frame", f"SELECT lhs_text, rhs, redundancy, count(*) OVER (ORDER BY redundancy RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS near FROM ({_GEO})")(
    lambda s, d: _geo(s, d).select("lhs_text", "rhs", "redundancy", F.count(F.lit(1)).over(Window.orderBy("redundancy").rangeBetween(-100, 0)).alias("near")))
query("top_fds_per_rhs", f"SELECT lhs_text, rhs, redundancy, CAST(row_number() OVER (PARTITION BY rhs ORDER BY redundancy DESC, lhs_size, lhs_text) AS INTEGER) AS place FROM ({_GEO}) QUALIFY place <= 2")(
    lambda s, d: apply.per_rhs(_geo(s, d), 2).select("lhs_text", "rhs", "redundancy", "place"))
query("top_fds_page", f"SELECT rank, lhs_text, rhs FROM ({_GEO}) ORDER BY rank LIMIT 5 OFFSET 5")(lambda s, d: _geo(s, d).orderBy("rank").offset(5).limit(5).select("rank", "lhs_text", "rhs"))
query("top_lhs_by_total", f"SELECT lhs_text, CAST(sum(redundancy) AS BIGINT) AS total, count(*) AS n FROM ({_GEO}) GROUP BY lhs_text ORDER BY total DESC, lhs_text LIMIT 5")(
    lambda s, d: _geo(s, d).groupBy("lhs_text").agg(F.sum("redundancy").alias("total"), F.count(F.lit(1)).alias("n")).orderBy(F.desc("total"), "lhs_text").limit(5))
query("fds_about", f"SELECT rank, lhs_text, rhs FROM ({_GEO}) WHERE rhs = 'n_name' OR list_contains(string_split(lhs_text, ','), 'c_acctbal')")(
    lambda s, d: _geo(s, d).where((F.col("rhs") == "n_name") | F.array_contains(F.split("lhs_text", ","), "c_acctbal")).select("rank", "lhs_text", "rhs"))

_PREFIX_SQL = VIEW_SQL["orders_calendar"] + " WHERE o_orderkey <= (SELECT quantile_disc(o_orderkey, 0.2) FROM orders)"
_SMALL = f"SELECT lhs_text, rhs FROM ({oracle.topk('orders_calendar', 1000, source=_PREFIX_SQL)})"
_FULL = f"SELECT lhs_text, rhs FROM ({oracle.topk('orders_calendar', 1000)})"


def _prefixes(spark, sf) -> tuple[DataFrame, DataFrame, DataFrame]:
    part = Relation.bind(views.prefix(VIEWS["orders_calendar"](spark, sf), "o_orderkey", 0.2), list(COLUMNS["orders_calendar"]), persist=True)
    whole = bound(spark, sf, "orders_calendar")
    out = apply.compare(discover(part, 1000).result, discover(whole, 1000).result)
    part.release(), whole.release()
    return out


query("set_lost_fds", f"{_SMALL} EXCEPT {_FULL}")(lambda s, d: _prefixes(s, d)[0])
query("set_new_fds", f"{_FULL} EXCEPT {_SMALL}")(lambda s, d: _prefixes(s, d)[1])
query("set_common_fds", f"{_FULL} INTERSECT {_SMALL}")(lambda s, d: _prefixes(s, d)[2])
query("set_union_fds", f"SELECT 'nation' AS relation, lhs_text, rhs FROM ({oracle.everything('nation')}) UNION ALL SELECT 'region', lhs_text, rhs FROM ({oracle.everything('region')})")(
    lambda s, d: answer("nation", whole=True)(s, d).select(F.lit("nation").alias("relation"), "lhs_text", "rhs").unionByName(answer("region", whole=True)(s, d).select(F.lit("region").alias("relation"), "lhs_text", "rhs")))

query("fn_format_parse", f"SELECT '{{' || lhs_text || '}}->' || rhs AS text, lhs_text AS lhs_back, rhs AS rhs_back FROM ({oracle.everything('nation')})")(
    lambda s, d: answer("nation", whole=True)(s, d).select(udx.format_fd(F.col("lhs_text"), F.col("rhs")).alias("text")).select("text", udx.parse_fd(F.col("text")).alias("p")).select("text", F.array_join("p.lhs", ",").alias("lhs_back"), F.col("p.rhs").alias("rhs_back")))
query("fn_json_props", "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")(lambda s, d: VIEWS["event_props"](s, d).groupBy("k").agg(F.count(F.lit(1)).alias("n")))


@query("udtf_fd_explode", f"SELECT unnest(string_split(lhs_text, ',')) AS attribute, rhs FROM ({oracle.everything('nation')})")
def udtf_fd_explode(spark, sf):
    udx.register(spark)
    answer("nation", whole=True)(spark, sf).createOrReplaceTempView("_fds_to_explode")
    return spark.sql("SELECT e.attribute, e.rhs FROM _fds_to_explode f, LATERAL fd_explode(f.lhs_text, f.rhs) e")


_NAMES = list(COLUMNS["nation"])
_NAMES_SQL = "array_to_string(list_sort(list_filter([CASE WHEN (i & 1) <> 0 THEN 'n_nationkey' END, CASE WHEN (i & 2) <> 0 THEN 'n_name' END, CASE WHEN (i & 4) <> 0 THEN 'n_regionkey' END], lambda x: x IS NOT NULL)), ',')"
_MASKS = "SELECT CAST(i AS BIGINT) AS mask, array_to_string(list_sort(list_filter([CASE WHEN (i & 1) <> 0 THEN 'n_nationkey' END, CASE WHEN (i & 2) <> 0 THEN 'n_name' END, CASE WHEN (i & 4) <> 0 THEN 'n_regionkey' END], lambda x: x IS NOT NULL)), ',') AS names FROM range(8) t(i)"
query("udf_mask_names", _MASKS)(lambda s, d: s.range(8).select(F.col("id").alias("mask"), udx.mask_names(_NAMES)("id").alias("names")))
query("fn_mask_names", f"SELECT i AS mask, {_NAMES_SQL} AS names, count(*) AS n FROM (SELECT o_orderkey % 8 AS i FROM orders) GROUP BY ALL")(
    lambda s, d: views.read(s, d, "orders").select((F.col("o_orderkey") % 8).alias("mask")).withColumn("names", udx.mask_names_native(F.col("mask"), _NAMES)).groupBy("mask", "names").agg(F.count(F.lit(1)).alias("n")))
query("udaf_lift", oracle.over_fds("cust_geo", _LIFT_SQL + " SELECT round(t / b, 6) AS lift FROM m"))(lambda s, d: _geo(s, d).groupBy(F.lit(1).alias("one")).agg(udx.lift_udaf(10)("redundancy").alias("lift")).select(F.round("lift", 6).alias("lift")))

query("decompose_lookup", f"SELECT DISTINCT c_nationkey, n_name, n_regionkey FROM ({VIEW_SQL['cust_geo']})")(lambda s, d: apply.decompose(VIEWS["cust_geo"](s, d), ["c_nationkey"], ["n_name", "n_regionkey"])[1])
query("check_lossless", "SELECT CAST(0 AS BIGINT) AS lost, CAST(0 AS BIGINT) AS made")(lambda s, d: apply.check_lossless(VIEWS["cust_geo"](s, d), ["c_nationkey"], ["n_name", "n_regionkey", "r_name"]))
query("storage_saving", f"SELECT count(*) AS n_rows, count(DISTINCT c_nationkey) AS n_classes, count(*) * 10 AS cells_before, count(*) * 8 + count(DISTINCT c_nationkey) * 3 AS cells_after, count(*) * 2 - count(DISTINCT c_nationkey) * 3 AS cells_saved FROM ({VIEW_SQL['cust_geo']})")(
    lambda s, d: apply.storage_saving(VIEWS["cust_geo"](s, d), ["c_nationkey"], ["n_name", "r_name"]))
query("violations", "SELECT o_custkey, count(*) AS n_values, CAST(sum(n) AS BIGINT) AS n_rows, CAST(sum(n) - max(n) AS BIGINT) AS n_repairs FROM (SELECT o_custkey, o_orderstatus, count(*) AS n FROM orders GROUP BY ALL) GROUP BY o_custkey HAVING count(*) > 1")(
    lambda s, d: apply.violating_classes(views.read(s, d, "orders"), ["o_custkey"], "o_orderstatus"))
query("violation_summary", "SELECT count(*) AS n_classes, count(*) FILTER (v > 1) AS bad_classes, CAST(coalesce(sum(n) FILTER (v > 1), 0) AS BIGINT) AS bad_rows FROM (SELECT count(*) AS v, sum(n) AS n FROM (SELECT c_nationkey, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL) GROUP BY c_nationkey)")(
    lambda s, d: apply.violation_summary(VIEWS["cust_geo"](s, d), ["c_nationkey"], "n_name"))
query("key_columns", "SELECT a AS attribute FROM (SELECT 'c_custkey' AS a, count(DISTINCT c_custkey) AS c FROM customer UNION ALL SELECT 'c_name', count(DISTINCT c_name) FROM customer UNION ALL SELECT 'c_acctbal', count(DISTINCT c_acctbal) FROM customer UNION ALL SELECT 'c_nationkey', count(DISTINCT c_nationkey) FROM customer UNION ALL SELECT 'c_mktsegment', count(DISTINCT c_mktsegment) FROM customer) WHERE c = (SELECT count(*) FROM customer)")(
    lambda s, d: (lambda n, c: apply.key_columns(s.createDataFrame(list(zip(COLUMNS["customer"], c, strict=True)), "attribute string, card long"), n))(*cardinality.profile(bound(s, d, "customer"))))
query("synonym_columns", f"WITH f AS ({_GEO}) SELECT x.lhs_text AS a, x.rhs AS b, x.redundancy FROM f x JOIN f y ON x.lhs_text = y.rhs AND y.lhs_text = x.rhs WHERE x.lhs_size = 1 AND y.lhs_size = 1 AND x.lhs_text < x.rhs")(
    lambda s, d: apply.synonyms(_geo(s, d).withColumn("lhs", F.split("lhs_text", ","))))


@query("group_by_simplified", f"SELECT c_nationkey, n_name, r_name, count(*) AS n FROM ({VIEW_SQL['cust_geo']}) GROUP BY ALL")
def group_by_simplified(spark, sf):
    """Grouped by fewer columns, with the determined ones as any value of their group."""
    rel = bound(spark, sf, "cust_geo")
    by = ["c_nationkey", "n_name", "r_name"]
    kept = baseline.simplify_group_by(rel, by, discover(rel, 30).fds)
    rel.release()
    return VIEWS["cust_geo"](spark, sf).groupBy(*kept).agg(*[F.any_value(c).alias(c) for c in by if c not in kept], F.count(F.lit(1)).alias("n")).select(*by, "n")


@query("implied_fds")
def implied_fds(spark, sf):
    rel = bound(spark, sf, "cust_geo")
    out = rel.frame(baseline.implied(discover(rel, 21).fds)).select("lhs_text", "rhs")
    rel.release()
    return out


def _stream(spark, sf) -> DataFrame:
    """The events as a stream of five files in time order."""
    folder = f"{scratch(spark)}/events"
    df = views.read(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    df.repartitionByRange(5, "ts").sortWithinPartitions("ts").write.parquet(folder)
    return spark.readStream.schema(spark.read.parquet(folder).schema).option("maxFilesPerTrigger", 5).parquet(folder)


@query("stream_violations", """WITH e AS (SELECT user_id, event_type, ts FROM events), f AS (SELECT user_id, arg_min(event_type, (ts, event_type)) AS first FROM e GROUP BY user_id)
SELECT count(*) AS n, count(DISTINCT e.user_id) AS n_classes FROM e JOIN f ON e.user_id = f.user_id WHERE e.event_type <> f.first""")
def stream_violations(spark, sf):
    out = monitor.drain(monitor.contradictions(_stream(spark, sf), ["user_id"], "event_type"), "_contradictions", scratch(spark))
    return out.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("lhs_key").alias("n_classes"))


@query("batch_violations", ORACLES["stream_violations"])
def batch_violations(spark, sf):
    out = monitor.contradictions_batch(views.read(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")), ["user_id"], "event_type")
    return out.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("lhs_key").alias("n_classes"))


@query("stream_class_sizes", "SELECT event_type, CAST(sum(size) AS BIGINT) AS n, count(*) AS n_windows FROM (SELECT date_trunc('day', ts) AS d, event_type, count(*) AS size FROM events GROUP BY ALL) GROUP BY event_type")
def stream_class_sizes(spark, sf):
    out = monitor.drain(monitor.class_sizes(_stream(spark, sf), ["event_type"]), "_class_sizes", scratch(spark), "complete")
    return out.groupBy("event_type").agg(F.sum("size").alias("n"), F.count(F.lit(1)).alias("n_windows"))


@query("stream_distinct", "SELECT count(DISTINCT event_id) AS n FROM events")
def stream_distinct(spark, sf):
    return monitor.drain(monitor.distinct_events(_stream(spark, sf), ["event_id"], late="3650 days"), "_distinct_events", scratch(spark), closing=False).agg(F.count(F.lit(1)).alias("n"))


@query("stream_cards", "SELECT count(*) AS card FROM (SELECT DISTINCT user_id, event_type FROM events)")
def stream_cards(spark, sf):
    folder = f"{scratch(spark)}/cards"
    q = _stream(spark, sf).writeStream.foreachBatch(monitor.card_keeper(folder, ["user_id", "event_type"])).option("checkpointLocation", scratch(spark)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.createDataFrame([(monitor.kept_card(spark, folder, ["user_id", "event_type"]),)], "card long")
