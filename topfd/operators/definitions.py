"""What a dependency, its minimality and its redundancy are, each as a DataFrame expression of its definition."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import Relation, mask_of


def classes(rel: Relation, attrs: list[str]) -> DataFrame:
    """The partition by attrs as its classes' sizes."""
    return rel.df.groupBy(*[F.col(f"`{a}`") for a in attrs]).agg(F.count(F.lit(1)).alias("size"))


def redundancy_sum(rel: Relation, attrs: list[str]) -> DataFrame:
    """One row: n_rows, n_classes and redundancy as the sum of class size - 1."""
    return classes(rel, attrs).agg(
        F.coalesce(F.sum("size"), F.lit(0)).alias("n_rows"), F.count(F.lit(1)).alias("n_classes"), F.coalesce(F.sum(F.col("size") - 1), F.lit(0)).alias("redundancy")
    )


def redundancy(n_rows: int, n_classes: int) -> int:
    return n_rows - n_classes


def minimal_only(fds: DataFrame) -> DataFrame:
    """fds(lhs array, rhs, ...) without those whose left-hand side contains another's for the same right-hand side, and without trivial ones."""
    own = fds.where(~F.array_contains("lhs", F.col("rhs")))
    small = own.select(F.col("lhs").alias("less"), F.col("rhs").alias("of"))
    inside = (F.col("rhs") == F.col("of")) & (F.size("less") < F.size("lhs")) & (F.size(F.array_except("less", "lhs")) == 0)
    return own.join(small, inside, "left_anti")


def minimal_masks(cards: DataFrame, attributes: DataFrame) -> DataFrame:
    """mask, bit, n_classes of the minimal dependencies among cards(mask, card), which holds all sets up to some size, and attributes(bit). Counts of a set with and without an
    attribute meet by the set's mask, and an anti join by right-hand side leaves out what contains a smaller left-hand side."""
    left = cards.select("mask", F.col("card").alias("n_classes")).join(F.broadcast(attributes), F.col("mask").bitwiseAND(F.col("bit")) == 0)
    held = left.join(cards.select(F.col("mask").alias("whole"), "card"), (F.col("whole") == F.col("mask").bitwiseOR(F.col("bit"))) & (F.col("card") == F.col("n_classes")))
    held = held.select("mask", "bit", "n_classes")
    less = held.select(F.col("mask").alias("less"), F.col("bit").alias("of"))
    inside = (F.col("bit") == F.col("of")) & (F.col("less") != F.col("mask")) & (F.col("less").bitwiseAND(F.col("mask")) == F.col("less"))
    return held.join(less, inside, "left_anti")


def rank_topk(fds: DataFrame, k: int) -> DataFrame:
    """The k best with positive redundancy in canonical order, ranked from 1."""
    best = fds.where(F.col("redundancy") > 0).orderBy(F.desc("redundancy"), "lhs_size", "lhs_text", "rhs").limit(k)
    return best.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("redundancy"), "lhs_size", "lhs_text", "rhs")))


def redundant_rows(rel: Relation, lhs: list[str], rhs: str, order_by: list[str]) -> DataFrame:
    """The rows whose right-hand value repeats what an earlier row of their class says. Equal rows are counted, and a class' first row is a minimum: both combine before
    the shuffle, so no class is sorted or held in one task, however large."""
    named = [*order_by, *[c for c in (*lhs, rhs) if c not in order_by]]
    quoted = lambda names: [F.col(f"`{c}`") for c in names]
    place = F.struct(*quoted(order_by))
    counted = rel.df.groupBy(*quoted(named)).agg(F.count(F.lit(1)).alias("copies"))
    first = rel.df.groupBy(*[c.alias(f"class{i}") for i, c in enumerate(quoted(lhs))]).agg(F.min(place).alias("first"))
    same = F.lit(True)
    for i, c in enumerate(quoted(lhs)):
        same = same & c.eqNullSafe(F.col(f"class{i}"))
    left = F.col("copies") - F.when(place.eqNullSafe(F.col("first")), 1).otherwise(0)
    return counted.join(first, same).select(*quoted(named), F.explode(F.array_repeat(F.lit(1), left.cast("int"))).alias("copy")).drop("copy")


def fd_holds(df: DataFrame, lhs: list[str], rhs: str, nulls: str = "eq") -> bool:
    from .cardinality import check_batch

    rel = Relation.bind(df, list(dict.fromkeys([*lhs, rhs])), nulls)
    pair = mask_of(lhs, rel.columns), rel.columns.index(rhs)
    return check_batch(rel, [pair])[pair].valid
