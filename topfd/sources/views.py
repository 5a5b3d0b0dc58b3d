"""De-normalised views of the given tables, on which dependencies of known kinds hold. Small dimensions are joined without hints: Spark broadcasts what is small."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of the toy relation: number, flight, origin, destination. Fixed values.
TOY = ((1, "UA57", "SFO", "JFK"), (2, "UA57", "SFO", "JFK"), (3, "UA57", "SFO", "JFK"), (4, "AA20", "LAX", "ORD"), (5, "AA20", "LAX", "ORD"))
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
EMBEDDING_SIZE = 64


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def flight_toy(spark: SparkSession, sf_dir: str = "") -> DataFrame:
    return spark.createDataFrame(TOY, "ID int, FlightNo string, Origin string, Dest string")


def cust_geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, n, r = (read(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    return c.join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)


def _calendar(c: str, prefix: str) -> list:
    return [F.year(c).alias(f"{prefix}_year"), F.quarter(c).alias(f"{prefix}_quarter"), F.month(c).alias(f"{prefix}_month")]


def orders_calendar(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority", "o_orderdate", *_calendar("o_orderdate", "o"), (F.dayofweek("o_orderdate") - 1).alias("o_dow"))


def order_months(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many rows, few different ones."""
    return orders_calendar(spark, sf_dir).select("o_orderstatus", "o_year", "o_quarter", "o_month")


def priced_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    net = F.round(F.col("l_quantity") * (1 - F.col("l_discount")) * 100).cast("long").alias("net_cents")
    pct = F.round(100 * F.col("l_discount") + 100 * F.col("l_tax")).cast("long").alias("adj_pct")
    return read(spark, sf_dir, "lineitem").select("l_linenumber", "l_quantity", "l_discount", "l_tax", "l_returnflag", "l_linestatus", net, pct)


def order_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines, o, c, n = (read(spark, sf_dir, t) for t in ("lineitem", "orders", "customer", "nation"))
    joined = lines.join(o, lines.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey)
    return joined.select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_returnflag", "l_linestatus", "o_custkey", "o_orderstatus", "o_orderpriority", "c_mktsegment", "c_nationkey", "n_regionkey")


def doc_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, marks = read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")
    return d.join(marks, "doc_id", "left").select("doc_id", "text", "lang", "source", "n_chars", "quality", "toxic")


def events_calendar(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "props", F.to_date("ts").alias("d"), F.hour("ts").alias("h"), (F.dayofweek("ts") - 1).alias("dow"), "value")


def event_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "value", F.to_date("ts").alias("d"), F.from_json("props", "k long").getField("k").alias("k"))


def embedding_bins(d: int, q: int = 10) -> Callable[[SparkSession, str], DataFrame]:
    """label and the first d components, each cut to 1/q, cast to double first."""

    def view(spark: SparkSession, sf_dir: str) -> DataFrame:
        bins = [F.floor(F.col("embedding")[i].cast("double") * q).cast("int").alias(f"e{i}") for i in range(d)]
        return read(spark, sf_dir, "embeddings").select("label", *bins)

    return view


def wide_star(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines, o, c, n, r, p, s = (read(spark, sf_dir, t) for t in ("lineitem", "orders", "customer", "nation", "region", "part", "supplier"))
    joined = lines.join(o, lines.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey)
    joined = joined.join(r, n.n_regionkey == r.r_regionkey).join(p, lines.l_partkey == p.p_partkey).join(s, lines.l_suppkey == s.s_suppkey)
    return joined.select("*", *_calendar("o_orderdate", "o"))


def page_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    rest = F.substring_index(F.col("url"), "://", -1)
    return read(spark, sf_dir, "pages").select("page_id", F.substring_index(rest, "/", 1).alias("host"), (F.size(F.split(rest, "/")) - 1).alias("depth"), F.length("html").alias("html_length"), F.substring_index("url", "://", 1).alias("scheme"))


def talk_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.length("text").alias("text_length"))


def bench_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "benchmark").select("item_id", "text", F.length("text").alias("text_length"), F.size(F.split("text", " ")).alias("n_words"))


def table(name: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: read(spark, sf_dir, name)


def prefix(df: DataFrame, key: str, share: float) -> DataFrame:
    """Rows up to the quantile of a key, ties included: a filter that reaches the scan of a sorted table."""
    if share >= 1:
        return df
    cut = df.stat.approxQuantile(key, [share], 0.0)
    return df.where(F.col(key) <= cut[0]) if cut else df


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "flight_toy": flight_toy, "cust_geo": cust_geo, "orders_calendar": orders_calendar, "priced_lines": priced_lines, "order_lines": order_lines, "doc_labels": doc_labels,
    "events_calendar": events_calendar, "event_props": event_props, "embedding_bins": embedding_bins(12), "wide_star": wide_star, "page_facts": page_facts, "talk_facts": talk_facts,
    "bench_facts": bench_facts, "order_months": order_months, **{t: table(t) for t in TABLES},
}

_CAL = "CAST(year({c}) AS INTEGER) AS {p}_year, CAST(quarter({c}) AS INTEGER) AS {p}_quarter, CAST(month({c}) AS INTEGER) AS {p}_month"
#: The same views in DuckDB SQL.
VIEW_SQL: dict[str, str] = {
    "flight_toy": "SELECT * FROM (VALUES " + ", ".join(str(r) for r in TOY) + ') AS t("ID", "FlightNo", "Origin", "Dest")',
    "cust_geo": "SELECT * FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
    "orders_calendar": f"SELECT o_orderkey, o_custkey, o_orderstatus, o_orderpriority, o_orderdate, {_CAL.format(c='o_orderdate', p='o')}, CAST(dayofweek(o_orderdate) AS INTEGER) AS o_dow FROM orders",
    "priced_lines": "SELECT l_linenumber, l_quantity, l_discount, l_tax, l_returnflag, l_linestatus, CAST(round(l_quantity * (1 - l_discount) * 100) AS BIGINT) AS net_cents, CAST(round(100 * l_discount + 100 * l_tax) AS BIGINT) AS adj_pct FROM lineitem",
    "order_lines": "SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_returnflag, l_linestatus, o_custkey, o_orderstatus, o_orderpriority, c_mktsegment, c_nationkey, n_regionkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey",
    "doc_labels": "SELECT d.doc_id, text, lang, source, n_chars, quality, toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id",
    "events_calendar": "SELECT event_id, user_id, event_type, props, CAST(ts AS DATE) AS d, CAST(hour(ts) AS INTEGER) AS h, CAST(dayofweek(ts) AS INTEGER) AS dow, value FROM events",
    "event_props": "SELECT event_id, user_id, event_type, value, CAST(ts AS DATE) AS d, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events",
    "embedding_bins": "SELECT label, " + ", ".join(f"CAST(floor(CAST(embedding[{i + 1}] AS DOUBLE) * 10) AS INTEGER) AS e{i}" for i in range(12)) + " FROM embeddings",
    "wide_star": f"SELECT lineitem.*, orders.*, customer.*, nation.*, region.*, part.*, supplier.*, {_CAL.format(c='o_orderdate', p='o')} FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey",
    "page_facts": "SELECT page_id, split_part(rest, '/', 1) AS host, CAST(len(string_split(rest, '/')) - 1 AS INTEGER) AS depth, CAST(length(html) AS INTEGER) AS html_length, split_part(url, '://', 1) AS scheme FROM (SELECT *, list_last(string_split(url, '://')) AS rest FROM pages)",
    "talk_facts": "SELECT conv_id, turn, role, CAST(length(text) AS INTEGER) AS text_length FROM conversations",
    "bench_facts": "SELECT item_id, text, CAST(length(text) AS INTEGER) AS text_length, CAST(len(string_split(text, ' ')) AS INTEGER) AS n_words FROM benchmark",
    "order_months": f"SELECT o_orderstatus, {_CAL.format(c='o_orderdate', p='o')} FROM orders",
    **{t: f"SELECT * FROM {t}" for t in TABLES},
}

COLUMNS: dict[str, tuple[str, ...]] = {
    "flight_toy": ("ID", "FlightNo", "Origin", "Dest"),
    "cust_geo": ("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment", "n_nationkey", "n_name", "n_regionkey", "r_regionkey", "r_name"),
    "orders_calendar": ("o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority", "o_orderdate", "o_year", "o_quarter", "o_month", "o_dow"),
    "priced_lines": ("l_linenumber", "l_quantity", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "net_cents", "adj_pct"),
    "order_lines": ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_returnflag", "l_linestatus", "o_custkey", "o_orderstatus", "o_orderpriority", "c_mktsegment", "c_nationkey", "n_regionkey"),
    "doc_labels": ("doc_id", "text", "lang", "source", "n_chars", "quality", "toxic"),
    "events_calendar": ("event_id", "user_id", "event_type", "props", "d", "h", "dow", "value"),
    "event_props": ("event_id", "user_id", "event_type", "value", "d", "k"),
    "embedding_bins": ("label", *(f"e{i}" for i in range(12))),
    "page_facts": ("page_id", "host", "depth", "html_length", "scheme"),
    "talk_facts": ("conv_id", "turn", "role", "text_length"),
    "bench_facts": ("item_id", "text", "text_length", "n_words"),
    "order_months": ("o_orderstatus", "o_year", "o_quarter", "o_month"),
    "region": ("r_regionkey", "r_name"),
    "nation": ("n_nationkey", "n_name", "n_regionkey"),
    "customer": ("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"),
    "supplier": ("s_suppkey", "s_name", "s_nationkey", "s_acctbal"),
    "part": ("p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"),
    "orders": ("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"),
    "lineitem": ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"),
    "events": ("event_id", "ts", "user_id", "event_type", "value", "props"),
    "documents": ("doc_id", "text", "lang", "source", "n_chars"),
    "labels": ("doc_id", "quality", "toxic"),
    "pages": ("page_id", "url", "html"),
    "benchmark": ("item_id", "text"),
    "conversations": ("conv_id", "turn", "role", "text"),
    "embeddings": ("vec_id", "embedding", "label"),
}
COLUMNS["wide_star"] = (
    *COLUMNS["lineitem"], *COLUMNS["orders"], *COLUMNS["customer"], *COLUMNS["nation"], *COLUMNS["region"], *COLUMNS["part"], *COLUMNS["supplier"], "o_year", "o_quarter", "o_month",
)
