"""Functions for SQL and DataFrame users over dependencies. The native forms are the ones to use over many rows; the Python forms are their twins."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf


@udtf(returnType="attribute string, rhs string")
class FdExplode:
    """One row for each left-hand attribute of a dependency; for the empty set, one with null."""

    def eval(self, lhs_text: str, rhs: str) -> Iterator[tuple]:
        for name in (lhs_text or "").split(",") if lhs_text else [None]:
            yield name, rhs


def mask_names(names: list[str]):
    """A vectorised function: bitmask -> sorted names joined by commas."""

    @pandas_udf("string")
    def of(mask: pd.Series) -> pd.Series:
        return mask.map(lambda m: ",".join(sorted(n for i, n in enumerate(names) if int(m) >> i & 1)))

    return of


def mask_names_native(mask: Column, names: list[str]) -> Column:
    flags = [F.when(mask.bitwiseAND(F.lit(1 << i)) != 0, F.lit(n)) for i, n in enumerate(names)]
    return F.array_join(F.array_sort(F.filter(F.array(*flags), lambda x: x.isNotNull())), ",")


def lift_udaf(k: int):
    """A grouped aggregate over the redundancies of one answer: mean of the k largest positive ones by mean of the others; NaN without others."""

    @pandas_udf("double")
    def of(redundancy: pd.Series) -> float:
        values = redundancy.sort_values(ascending=False).reset_index(drop=True)
        top = values[(values.index < k) & (values > 0)]
        rest = values[len(top) :]
        if not len(rest) or not len(top):
            return float("nan")
        return float("inf") if rest.mean() == 0 else float(top.mean() / rest.mean())

    return of


def format_fd(lhs_text: Column, rhs: Column) -> Column:
    """{a,b}->c"""
    return F.concat(F.lit("{"), lhs_text, F.lit("}->"), rhs)


def parse_fd(text: Column) -> Column:
    """The reverse, as a struct of lhs (array) and rhs."""
    inner = F.regexp_extract(text, r"^\{(.*)\}->(.*)$", 1)
    return F.struct(F.when(inner == "", F.array().cast("array<string>")).otherwise(F.split(inner, ",")).alias("lhs"), F.regexp_extract(text, r"^\{(.*)\}->(.*)$", 2).alias("rhs"))


def register(spark: SparkSession) -> None:
    """fd_explode(lhs_text, rhs) as a table function in SQL."""
    spark.udtf.register("fd_explode", FdExplode)
