"""Mixing sources to target weights by capped water-filling, in DataFrame functions alone.

The budget is the corpus' own number of words. Each source asks for its weight's share; a source stops at ``max_epochs``
times its size, and what it can't use is dealt to the others by weight. All sources that stop do so in ascending order of
size / weight, so one pass over the *sources* (not the rows) finds the level: of the prefixes of that order, the first
whose next source isn't full at the level that remains.

A source then takes each document floor(target / size) times, and a seeded part of its documents once more: documents are
dealt to 4,096 buckets by a hash of seed and id; buckets below the cut are taken whole, the cut bucket's documents each
for the same fraction of their words. So no source is sorted, whatever its size; only (source, bucket) sums are shuffled.

Rows with a null source form a source of their own, the last. Null texts have size 0 and are kept with 0 taken. Repeated
rows are drawn alike, as their hash is the same. Source names that appear once or an empty table need no special case:
an empty table gives an empty result. Columns of other names are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table, word_count, written

#: Weights dealt to sources in code-point order, in turn. Fixed values.
WEIGHTS = (5.0, 2.0, 1.0)
BUCKET_DIGITS = 3
#: Up to so many sources their table is broadcast; with more, Spark joins by shuffle.
BROADCAST_SOURCES = 50_000


def bucket(doc_id: Column, seed: int) -> Column:
    """0 to 16**BUCKET_DIGITS - 1, alike in every engine: the first hexadecimal digits of an MD5."""
    key = F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.lit("")))
    return F.conv(F.substring(F.md5(key), 1, BUCKET_DIGITS), 16, 10).cast("int")


def targets(sources: DataFrame, max_epochs: float = 3.0, weights: tuple[float, ...] = WEIGHTS, total: Column | None = None) -> DataFrame:
    """sources(source, source_size) with weight and target. One row a source, so its windows hold the catalogue of sources, not rows."""
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    place = (F.row_number().over(by_name) - 1) % len(weights)
    weight = F.element_at(F.array(*map(F.lit, weights)), (place + 1).cast("int"))
    weighed = sources.select("source", "source_size", weight.alias("weight"))
    cap = F.col("source_size") * F.lit(float(max_epochs))
    everything = Window.partitionBy()
    filling = Window.orderBy(cap / F.col("weight"), F.col("source").asc_nulls_last())
    before = filling.rowsBetween(Window.unboundedPreceding, -1)
    levels = weighed.select(
        "*",
        cap.alias("cap"),
        F.sum("source_size").over(everything).cast("double").alias("budget"),
        F.coalesce(F.sum(cap).over(before), F.lit(0.0)).alias("full"),
        (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))).alias("open_weight"),
    )
    level = (F.col("budget") - F.col("full")) / F.col("open_weight")
    open_here = F.col("cap") >= level * F.col("weight")
    chosen = levels.withColumn("level", F.min_by(F.when(open_here, F.struct("budget", "full", "open_weight")), F.when(open_here, F.struct(cap / F.col("weight"), F.col("full")))).over(everything))
    share = (F.col("level.budget") - F.col("level.full")) * F.col("weight") / F.col("level.open_weight")
    return chosen.select("source", "source_size", "weight", F.when(F.col("level").isNull() | (F.col("cap") < share), F.col("cap")).otherwise(share).alias("target"))


def mix(docs: DataFrame, max_epochs: float = 3.0, weights: tuple[float, ...] = WEIGHTS, seed: int = 20, carry: tuple[str, ...] = ()) -> DataFrame:
    """docs(doc_id, text, source) -> doc_id, source, size, source_size, weight, target, taken: how many of its words the mix takes, repeats counted.
    carried: a struct of the columns of `carry` by place (c0, c1, ...), so that no name can clash."""
    facts = ("doc_id", "source", word_count(F.col("text")).alias("size"), bucket(F.col("doc_id"), seed).alias("bucket"))
    if carry:
        sized = docs.select(*facts, F.struct(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(carry)]).alias("carried"))
    else:
        # narrow rows, stored once: no text is read or counted twice
        sized = written(docs.select(*facts)).withColumn("carried", F.lit(None).cast("int"))
    per_bucket = written(sized.groupBy("source", "bucket").agg(F.sum("size").alias("bucket_size"), F.count(F.lit(1)).alias("n")))
    goal = targets(per_bucket.groupBy("source").agg(F.sum("bucket_size").alias("source_size")), max_epochs, weights)
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0))
    rest = F.col("target") - F.col("whole") * F.col("source_size")
    running = Window.partitionBy("source").orderBy("bucket")
    cut = (
        per_bucket.withColumn("upto", F.sum("bucket_size").over(running))
        .join(goal.withColumn("whole", whole).withColumn("rest", rest).withColumnRenamed("source", "goal_source"), F.col("source").eqNullSafe(F.col("goal_source")))
        .groupBy("source", "source_size", "weight", "target", "whole")
        .agg(
            F.max(F.when(F.col("upto") <= F.col("rest"), F.col("bucket"))).alias("last_full"),
            F.min_by(F.struct((F.col("rest") - F.col("upto") + F.col("bucket_size")).alias("missing"), F.col("bucket_size").alias("of")), F.when(F.col("upto") > F.col("rest"), F.col("bucket"))).alias("cut"),
            F.min(F.when(F.col("upto") > F.col("rest"), F.col("bucket"))).alias("cut_bucket"),
        )
        .select(F.col("source").alias("mix_source"), "source_size", "weight", "target", "whole", "cut_bucket", F.col("cut.missing").alias("missing"), F.col("cut.of").alias("of"))
    )
    cut = written(cut)
    if cut.count() <= BROADCAST_SOURCES:
        cut = F.broadcast(cut)
    part = F.when(F.col("cut_bucket").isNull() | (F.col("bucket") < F.col("cut_bucket")), F.col("size")).when(F.col("bucket") == F.col("cut_bucket"), F.floor(F.col("size") * F.col("missing") / F.col("of"))).otherwise(F.lit(0))
    part = F.when(F.col("target") > F.col("whole") * F.col("source_size"), part).otherwise(F.lit(0))
    return sized.join(cut, F.col("source").eqNullSafe(F.col("mix_source"))).select(
        "doc_id", "source", "size", "source_size", "weight", "target", (F.col("whole") * F.col("size") + part).cast("long").alias("taken"), "carried"
    )


def sample(docs: DataFrame, max_epochs: float = 3.0, weights: tuple[float, ...] = WEIGHTS, seed: int = 20) -> DataFrame:
    """The mix itself, with the columns of docs: each document as often as it is taken whole, and once more with its first words where a part is taken."""
    names = docs.columns
    at = names.index("text")
    mixed = mix(docs, max_epochs, weights, seed, tuple(names)).where(F.col("taken") > 0)
    times = F.explode(F.sequence(F.lit(1), F.ceil(F.col("taken") / F.col("size")).cast("int"))).alias("time")
    rows = mixed.select("size", "taken", "carried", times)
    left = F.col("taken") - (F.col("time") - 1) * F.col("size")
    all_words = F.filter(F.split(F.col(f"carried.c{at}"), r"[\x20\x09-\x0D]+"), lambda w: w != "")
    text = F.when(left >= F.col("size"), F.col(f"carried.c{at}")).otherwise(F.array_join(F.slice(all_words, 1, left.cast("int")), " "))
    return rows.select(*[text.alias(c) if i == at else F.col(f"carried.c{i}").alias(c) for i, c in enumerate(names)])


def op4_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


ORACLE = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
         CAST('0x' || substr(md5('20:' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 3) AS INTEGER) AS bucket
  FROM documents),
per_bucket AS (SELECT source, bucket, CAST(sum(size) AS BIGINT) AS bucket_size FROM sized GROUP BY ALL),
weighed AS (
  SELECT source, CAST(sum(bucket_size) AS BIGINT) AS source_size,
         [5.0::DOUBLE, 2.0::DOUBLE, 1.0::DOUBLE][CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS INTEGER)] AS weight
  FROM per_bucket GROUP BY source),
levels AS (
  SELECT *, source_size * 3.0::DOUBLE AS cap, CAST(sum(source_size) OVER () AS DOUBLE) AS budget,
         coalesce(sum(source_size * 3.0::DOUBLE) OVER (ORDER BY source_size * 3.0::DOUBLE / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS filled,
         sum(weight) OVER () - coalesce(sum(weight) OVER (ORDER BY source_size * 3.0::DOUBLE / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS open_weight
  FROM weighed),
level AS (
  SELECT arg_min(budget, ord) AS budget, arg_min(filled, ord) AS filled, arg_min(open_weight, ord) AS open_weight
  FROM (SELECT *, {'a': cap / weight, 'b': filled} AS ord FROM levels) WHERE cap >= (budget - filled) / open_weight * weight),
goal AS (
  SELECT source, source_size, least(cap, (level.budget - level.filled) * weight / level.open_weight) AS target
  FROM levels, level),
parts AS (
  SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS whole FROM goal),
running AS (
  SELECT b.source, bucket, bucket_size, target - whole * source_size AS rest,
         CAST(sum(bucket_size) OVER (PARTITION BY b.source ORDER BY bucket) AS BIGINT) AS upto
  FROM per_bucket b JOIN parts p ON b.source IS NOT DISTINCT FROM p.source),
cut AS (
  SELECT source, min(bucket) AS cut_bucket, arg_min(rest - upto + bucket_size, bucket) AS missing, arg_min(bucket_size, bucket) AS total
  FROM running WHERE upto > rest GROUP BY source)
SELECT doc_id, size, source_size, target,
       CAST(whole * size + CASE WHEN NOT target > whole * source_size THEN 0
            WHEN cut_bucket IS NULL OR bucket < cut_bucket THEN size
            WHEN bucket = cut_bucket THEN CAST(floor(size * missing / total) AS BIGINT) ELSE 0 END AS BIGINT) AS taken
FROM sized s JOIN parts p ON s.source IS NOT DISTINCT FROM p.source LEFT JOIN cut c ON s.source IS NOT DISTINCT FROM c.source
"""
