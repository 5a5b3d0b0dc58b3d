"""Measures over runs and answers: speedup, pruning ratios, utility, counts, kinds of dependency."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import FD, Relation
from .search import Discovery


def lift(fds: DataFrame, k: int = 10, rest: str = "all", divisor: str = "answer") -> DataFrame:
    """One row: mean redundancy of the k best with any, of the rest, and their ratio. rest: all other minimal dependencies or only `positive` ones;
    divisor: the answer's size or k. The ratio is null without a rest, and infinite if the rest's mean is 0."""
    if rest not in ("all", "positive") or divisor not in ("answer", "k"):
        raise ValueError("rest is all or positive, divisor answer or k")
    top = (F.col("rank") <= k) & (F.col("redundancy") > 0)
    other = ~top & (F.col("redundancy") > 0) if rest == "positive" else ~top
    size = F.lit(float(k)) if divisor == "k" else F.sum(top.cast("int")).cast("double")
    a = F.sum(F.when(top, F.col("redundancy")).otherwise(0)) / F.nullif(size, F.lit(0.0))
    b = F.avg(F.when(other, F.col("redundancy")))
    one = fds.agg(F.count(F.lit(1)).alias("n_fds"), F.coalesce(F.sum((F.col("redundancy") > 0).cast("int")), F.lit(0)).cast("long").alias("n_positive"), a.alias("mean_top"), b.alias("mean_rest"))
    ratio = F.when(F.col("mean_rest") == 0, F.when(F.col("mean_top") > 0, F.lit(float("inf")))).otherwise(F.try_divide("mean_top", "mean_rest"))
    return one.withColumn("lift", ratio)


def ratios(pruned: Discovery, exhaustive: Discovery) -> dict[str, float | None]:
    """Speedup, and the shares of nodes and of candidates that the exhaustive run looked at and the pruned one didn't."""
    a, b = pruned.stats, exhaustive.stats
    part = lambda x, y: 1 - x / y if y else None
    return {"speedup": b["wall_s"] / a["wall_s"] if a["wall_s"] else None, "search_pruning": part(a["nodes_visited"], b["nodes_visited"]), "candidate_pruning": part(a["validations"], b["validations"])}


def kinds(rel: Relation, fds: list[FD]) -> dict[FD, str]:
    """synonym: both directions hold; hierarchy: other single-attribute ones; invariant: any of a set of three or more attributes follows from the others;
    constant: the empty set determines it; composite: the rest."""
    single = {(f.lhs, 1 << f.rhs) for f in fds if f.lhs.bit_count() == 1}
    whole: dict[int, int] = {}
    for f in fds:
        whole[f.lhs | 1 << f.rhs] = whole.get(f.lhs | 1 << f.rhs, 0) + 1
    out = {}
    for f in fds:
        together = f.lhs | 1 << f.rhs
        if f.lhs.bit_count() == 1:
            out[f] = "synonym" if (1 << f.rhs, f.lhs) in single else "hierarchy"
        elif f.lhs and whole[together] == together.bit_count():
            out[f] = "invariant"
        else:
            out[f] = "composite" if f.lhs else "constant"
    return out
