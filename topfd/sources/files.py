"""Relations from files and databases, and stored results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..model import Relation

FORMATS = ("parquet", "orc", "json", "csv", "avro")


def relation(spark: SparkSession, path: str, kind: str = "parquet", columns: list[str] | None = None, nulls: str = "eq", schema=None, **options) -> Relation:
    """A relation over files. Columns are pruned in the scan. Without a schema, csv and json are inferred, which reads them once more."""
    if kind not in FORMATS:
        raise ValueError(f"unknown format {kind}")
    if kind == "csv":
        options = {"header": True} | ({} if schema else {"inferSchema": True}) | options
    reader = spark.read.options(**options)
    return Relation.bind((reader.schema(schema) if schema else reader).format(kind).load(path), columns, nulls)


def jdbc_relation(spark: SparkSession, url: str, table: str, columns: list[str] | None = None, partition: tuple[str, int, int, int] | None = None, **options) -> Relation:
    """A relation over a database table. partition: (column, lower, upper, parts) reads it in parallel."""
    if partition:
        options |= dict(zip(("partitionColumn", "lowerBound", "upperBound", "numPartitions"), map(str, partition), strict=True))
    return Relation.bind(spark.read.format("jdbc").options(url=url, dbtable=table, **options).load(), columns)


def save_result(found, path: str, table: str, kind: str = "parquet") -> None:
    """Answer, counters and threshold trace of a run under path/answers, path/stats and path/trace, partitioned by the relation's name."""
    from pyspark.sql import functions as F

    for name, df in (("answers", found.result), ("stats", found.stats_frame()), ("trace", found.trace_frame())):
        df.withColumn("relation", F.lit(table)).write.mode("append").partitionBy("relation").format(kind).save(f"{path}/{name}")


def publish(found, answers: str = "fd_result", cards: str = "fd_cards") -> tuple[DataFrame, DataFrame]:
    """Temporary views for SQL: the answer, and every number of classes that the run knows."""
    spark, rel = found.rel.df.sparkSession, found.rel
    known = [(c, 1, n, "profile") for c, n in zip(rel.columns, found.cards, strict=True)]
    known += [(rel.lhs_text(m), 2, n, found.matrix.origin.get(m, "validated")) for m, n in sorted(found.matrix.pairs.items())]
    out = found.result, spark.createDataFrame(known, "attrs string, size int, card long, origin string")
    out[0].createOrReplaceTempView(answers)
    out[1].createOrReplaceTempView(cards)
    return out
