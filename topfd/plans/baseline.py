"""Rank-after-discovery, the exhaustive baseline, and a levelwise brute force."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..model import FD, Relation
from ..operators.cardinality import profile, set_cardinalities
from ..operators.definitions import rank_topk
from .search import Discovery, discover


def discover_all(source: DataFrame | Relation, **options) -> Discovery:
    """All minimal dependencies, those without redundancy included: the same kernel in schema order, right-hand side by right-hand side, nothing pruned."""
    return discover(source, None, options.pop("variant", "core"), **options)


def rank_after_discovery(source: DataFrame | Relation, k: int = 10, **options) -> tuple[DataFrame, Discovery]:
    """(the k best of all, the exhaustive run). A run over its limits gives what it had found and says over_budget."""
    if k < 1:
        raise ValueError("k is 1 or more")
    found = discover_all(source, **options)
    return rank_topk(found.result, k), found


def brute_force(rel: Relation, max_lhs: int) -> list[FD]:
    """Levelwise over all sets up to max_lhs attributes and one more; a reference for small relations."""
    n, _ = profile(rel)
    sets = [s for s in range(1 << rel.m) if s.bit_count() <= max_lhs + 1]
    card = set_cardinalities(rel, sets)
    out: list[FD] = []
    for a in range(rel.m):
        minimal: list[int] = []
        for s in sorted(sets, key=lambda s: (s.bit_count(), s)):
            if s.bit_count() > max_lhs or s >> a & 1 or any(x & s == x for x in minimal):
                continue
            if card[s] == card[s | 1 << a]:
                minimal.append(s)
        out += [FD(s, a, card[s], n) for s in minimal if n]
    return sorted(out, key=rel.sort_key)


def closure(fds: list[FD], attributes: int) -> int:
    """All attributes that the given ones determine through these dependencies."""
    known = attributes
    while True:
        more = known
        for f in fds:
            if f.lhs & more == f.lhs:
                more |= 1 << f.rhs
        if more == known:
            return known
        known = more


def implied(fds: list[FD]) -> list[FD]:
    """Those that follow from the others."""
    return [f for i, f in enumerate(fds) if closure(fds[:i] + fds[i + 1 :], f.lhs) >> f.rhs & 1]


def simplify_group_by(rel: Relation, by: list[str], fds: list[FD]) -> list[str]:
    """Grouping columns that suffice: a column that the remaining ones determine forms no further groups."""
    kept = list(by)
    for c in reversed(by):
        rest = sum(1 << rel.columns.index(x) for x in kept if x != c)
        if closure(fds, rest) >> rel.columns.index(c) & 1:
            kept.remove(c)
    return kept


__all__ = ["brute_force", "closure", "discover_all", "implied", "rank_after_discovery", "simplify_group_by"]
