"""Token counts from an exact histogram of encoded lengths.

Documents are encoded whole; each batch sends only (length, documents) pairs on, so what is shuffled is bounded by the
number of different lengths. Suffix sums over the histogram then answer, for every context limit L that is some document's
length: how many documents are at least as long, all tokens, and the tokens left if each document is cut at L. Sums run inside
blocks of lengths and over the blocks, so that no task needs the whole histogram.

Null and empty texts have length 0 and are counted there; a text of any length is encoded whole, one at a time. Repeated rows count as often as they appear. An empty table gives an
empty result. Other columns are not read.
"""

from __future__ import annotations

from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import arrow_map, table, written
from .tokens import encoder

BLOCK = 1024


def histogram(docs: DataFrame, json_path: str | None = None, ranks_path: str | None = None) -> DataFrame:
    """docs(text) -> length, n_docs."""

    def make():
        encode = encoder(json_path, ranks_path)

        def each(batch: pa.RecordBatch):
            found = Counter(len(encode(t.as_py())) if t.is_valid else 0 for t in batch.column(0))
            yield pa.RecordBatch.from_arrays([pa.array(found.keys(), pa.int64()), pa.array(found.values(), pa.int64())], ["length", "n"])

        return each

    return arrow_map(docs, ["text"], "length long, n long", make).groupBy("length").agg(F.sum("n").alias("n_docs"))


def totals(hist: DataFrame) -> DataFrame:
    """length, n_docs -> with docs_from (as long or longer), docs_upto, tokens_upto, total_docs, total_tokens, truncated_tokens (every document cut at length), quantile (share of documents up to length)."""
    tokens = F.col("length") * F.col("n_docs")
    blocks = hist.groupBy(F.floor(F.col("length") / BLOCK).alias("block")).agg(F.sum("n_docs").alias("d"), F.sum(tokens).alias("t"))
    earlier = Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    blocks = blocks.select(F.col("block").alias("of_block"), F.coalesce(F.sum("d").over(earlier), F.lit(0)).alias("d0"), F.coalesce(F.sum("t").over(earlier), F.lit(0)).alias("t0"), F.sum("d").over(every).alias("total_docs"), F.sum("t").over(every).alias("total_tokens"))
    inside = Window.partitionBy("block").orderBy("length")
    run = hist.withColumn("block", F.floor(F.col("length") / BLOCK)).select("*", F.sum("n_docs").over(inside).alias("d1"), F.sum(tokens).over(inside).alias("t1"))
    upto, tokens_upto = F.col("d0") + F.col("d1"), F.col("t0") + F.col("t1")
    return run.join(blocks, F.col("block") == F.col("of_block")).select(
        "length",
        "n_docs",
        (F.col("total_docs") - upto + F.col("n_docs")).alias("docs_from"),
        upto.alias("docs_upto"),
        tokens_upto.alias("tokens_upto"),
        "total_docs",
        "total_tokens",
        (tokens_upto + F.col("length") * (F.col("total_docs") - upto)).alias("truncated_tokens"),
        (upto / F.col("total_docs")).alias("quantile"),
    )


def at_limits(hist: DataFrame, limits: list[int]) -> DataFrame:
    """context, tokens: the tokens kept for any given context limits, also those that are no document's length. The limits are expressions of one aggregation over the histogram."""
    held = [F.sum(F.least(F.col("length"), F.lit(int(x))) * F.col("n_docs")).alias("tokens") for x in limits]
    one = hist.agg(F.array(*held).alias("tokens"))
    return one.select(F.posexplode("tokens").alias("i", "tokens")).select(F.element_at(F.array(*map(F.lit, limits)), F.col("i") + 1).cast("long").alias("context"), F.coalesce("tokens", F.lit(0)).alias("tokens"))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    # stored, as the sums read it twice: every text is encoded once
    return totals(written(histogram(table(spark, sf_dir, "documents"))))
