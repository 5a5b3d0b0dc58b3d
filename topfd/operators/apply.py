"""What one does with a dependency: split tables, list what contradicts it, find synonyms and keys, compare answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _cols(names):
    return [F.col(f"`{c}`") for c in names]


def decompose(df: DataFrame, lhs: list[str], rhs: list[str]) -> tuple[DataFrame, DataFrame]:
    """(the table without rhs, the table of lhs and rhs once a class). Lossless if lhs determines rhs."""
    return df.select(*_cols([c for c in df.columns if c not in rhs])), df.select(*_cols([*lhs, *rhs])).distinct()


def recompose(main: DataFrame, looked_up: DataFrame, lhs: list[str], columns: list[str]) -> DataFrame:
    """The join back, null equal to null."""
    right = looked_up.select(*[F.col(f"`{c}`").alias(f"_r_{c}") for c in looked_up.columns])
    on = F.lit(True)
    for c in lhs:
        on = on & F.col(f"`{c}`").eqNullSafe(F.col(f"`_r_{c}`"))
    return main.join(right, on).select(*[F.col(f"`_r_{c}`").alias(c) if c not in main.columns else F.col(f"`{c}`") for c in columns])


def check_lossless(df: DataFrame, lhs: list[str], rhs: list[str]) -> DataFrame:
    """One row: rows lost and rows made up by splitting and joining back, bags compared."""
    back = recompose(*decompose(df, lhs, rhs), lhs, df.columns)
    lost = df.exceptAll(back).agg(F.count(F.lit(1)).alias("lost"))
    made = back.exceptAll(df).agg(F.count(F.lit(1)).alias("made"))
    return lost.withColumn("one", F.lit(1)).join(made.withColumn("one", F.lit(1)), "one").drop("one")


def storage_saving(df: DataFrame, lhs: list[str], rhs: list[str]) -> DataFrame:
    """One row: cells before and after the split, and the cells saved."""
    n, width = F.count(F.lit(1)), len(df.columns)
    cards = df.groupBy(*_cols(lhs)).agg(n.alias("size")).agg(F.coalesce(F.sum("size"), F.lit(0)).alias("n_rows"), F.count(F.lit(1)).alias("n_classes"))
    before, after = F.col("n_rows") * width, F.col("n_rows") * (width - len(rhs)) + F.col("n_classes") * (len(lhs) + len(rhs))
    return cards.select("n_rows", "n_classes", before.alias("cells_before"), after.alias("cells_after"), (before - after).alias("cells_saved"))


def violating_classes(df: DataFrame, lhs: list[str], rhs: str) -> DataFrame:
    """Classes of lhs that hold more than one value of rhs: how many values, how many rows, and the fewest rows to change to repair the class."""
    values = df.groupBy(*_cols([*lhs, rhs])).agg(F.count(F.lit(1)).alias("n"))
    found = values.groupBy(*_cols(lhs)).agg(F.count(F.lit(1)).alias("n_values"), F.sum("n").alias("n_rows"), (F.sum("n") - F.max("n")).alias("n_repairs"))
    return found.where(F.col("n_values") > 1)


def violating_rows(df: DataFrame, lhs: list[str], rhs: str) -> DataFrame:
    """All rows of those classes; a null-safe semi join, which adaptive execution splits for large classes."""
    bad = violating_classes(df, lhs, rhs).select(*[F.col(f"`{c}`").alias(f"_b_{c}") for c in lhs])
    on = F.lit(True)
    for c in lhs:
        on = on & F.col(f"`{c}`").eqNullSafe(F.col(f"`_b_{c}`"))
    return df.join(bad, on, "left_semi")


def violation_summary(df: DataFrame, lhs: list[str], rhs: str) -> DataFrame:
    """One row: n_classes, violating classes and rows; the two last are 0 for a dependency that holds, whatever its number of classes."""
    per_class = df.groupBy(*_cols([*lhs, rhs])).agg(F.count(F.lit(1)).alias("n")).groupBy(*_cols(lhs)).agg(F.count(F.lit(1)).alias("v"), F.sum("n").alias("n"))
    bad = F.col("v") > 1
    return per_class.agg(F.count(F.lit(1)).alias("n_classes"), F.coalesce(F.sum(bad.cast("int")), F.lit(0)).cast("long").alias("bad_classes"), F.coalesce(F.sum(F.when(bad, F.col("n"))), F.lit(0)).alias("bad_rows"))


def synonyms(fds: DataFrame) -> DataFrame:
    """Pairs of single attributes that determine each other: a, b with a < b, and their redundancy."""
    one = fds.where(F.col("lhs_size") == 1).select(F.col("lhs")[0].alias("a"), F.col("rhs").alias("b"), "redundancy")
    back = one.select(F.col("b").alias("a"), F.col("a").alias("b"))
    return one.join(back, ["a", "b"], "left_semi").where(F.col("a") < F.col("b"))


def key_columns(cards: DataFrame, n_rows: int) -> DataFrame:
    """Single attributes with as many classes as rows. cards(attribute, card)."""
    return cards.where(F.col("card") == n_rows).select("attribute")


def per_rhs(fds: DataFrame, k: int) -> DataFrame:
    """The k best of each right-hand side, with their place in it."""
    by = Window.partitionBy("rhs").orderBy(F.desc("redundancy"), "lhs_size", "lhs_text")
    return fds.withColumn("place", F.row_number().over(by)).where(F.col("place") <= k)


def ranked(fds: DataFrame) -> DataFrame:
    """Places by redundancy in each right-hand side in the three usual ways, and the ratio to the best one."""
    by = Window.partitionBy("rhs").orderBy(F.desc("redundancy"))
    total = Window.partitionBy("rhs").orderBy(F.desc("redundancy"), "lhs_size", "lhs_text")
    best = F.max("redundancy").over(Window.partitionBy("rhs"))
    return fds.select(
        "lhs_text", "rhs", "redundancy", F.rank().over(by).alias("rank_"), F.dense_rank().over(by).alias("dense_rank_"), F.row_number().over(total).alias("row_number_"),
        F.round(F.when(best > 0, F.col("redundancy") / best), 9).alias("ratio_to_best"), F.sum("redundancy").over(total.rowsBetween(Window.unboundedPreceding, 0)).alias("running"),
    )


def compare(before: DataFrame, after: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(lost, new, common) dependencies of two answers, as (lhs_text, rhs)."""
    a, b = (x.select("lhs_text", "rhs") for x in (before, after))
    return a.exceptAll(b), b.exceptAll(a), a.intersect(b)
