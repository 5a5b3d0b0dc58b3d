"""Upper bounds of redundancy, attribute orders, and the matrix of pair cardinalities.

A class count never falls when attributes are added, and a valid X -> A has at least as many classes in X as in A. So n minus the largest known count
among A, the attributes of X and the pairs inside X bounds the redundancy of X -> A and of every extension of X.
"""

from __future__ import annotations

import math
import random
from collections.abc import Iterable

from ..model import Relation, bits
from ..operators.cardinality import coded_cardinalities
from ..operators.evidence import distinct_in_sample


def attribute_order(cards: list[int], how: str = "ascending", seed: int = 20) -> list[int]:
    """Attributes in the order of access: ascending (default) or descending number of classes, as in the schema, or shuffled by a seed. Ties keep schema order."""
    at = list(range(len(cards)))
    if how == "schema":
        return at
    if how == "random":
        random.Random(seed).shuffle(at)
        return at
    if how not in ("ascending", "descending"):
        raise ValueError(f"unknown order {how}")
    return sorted(at, key=lambda i: (cards[i] if how == "ascending" else -cards[i], i))


def bound_single(n: int, cards: list[int], lhs: int, rhs: int) -> int:
    return n - max([cards[rhs], *(cards[i] for i in bits(lhs))])


class PairMatrix:
    """Known class counts of attribute pairs. `mode`: "single" knows none, "pairs" those of pairs, "cache" any counted set that a left-hand side contains."""

    def __init__(self, n: int, cards: list[int], mode: str = "pairs"):
        if mode not in ("single", "pairs", "cache"):
            raise ValueError(f"unknown bound {mode}")
        self.n, self.cards, self.mode = n, cards, mode
        self.pairs: dict[int, int] = {}
        self.origin: dict[int, str] = {}
        self.larger: dict[int, int] = {}
        self.sample = None
        self._sampled: dict[int, int] = {}

    def sampled(self, lhs: int) -> int:
        """Classes of lhs among the sampled rows; 0 without a sample. Counted once for each set."""
        if self.sample is None:
            return 0
        if lhs not in self._sampled:
            self._sampled[lhs] = distinct_in_sample(self.sample, lhs)
        return self._sampled[lhs]

    def precompute(self, rel: Relation, order: list[int], d: int | None = None) -> None:
        """Pairs among the first d attributes of the order, the rounded-up root of their number by default: about half as many sets as attributes, one job."""
        d = math.ceil(math.sqrt(len(order))) if d is None else d
        head = order[:d]
        wanted = [1 << a | 1 << b for k, a in enumerate(head) for b in head[k + 1 :]]
        if wanted:
            for mask, card in coded_cardinalities(rel, wanted).items():
                self.learn(mask, card, "first")

    def learn(self, mask: int, card: int, origin: str = "validated") -> None:
        """A set that was counted on the way."""
        if mask.bit_count() == 2:
            self.pairs[mask] = card
            self.origin.setdefault(mask, origin)
        elif self.mode == "cache" and mask.bit_count() > 2:
            self.larger[mask] = card
        if self.sample is not None:
            # what a set has among all rows takes the place of what it has among the sampled ones, whatever its next right-hand side
            self._sampled[mask] = card

    def get(self, a: int, b: int) -> int:
        """0 where unknown, which is a safe lower bound."""
        return self.pairs.get(1 << a | 1 << b, 0)

    def extend(self, parent_max: int, lhs: int, new: int) -> int:
        """Largest known count inside lhs with `new` added, given that of lhs: linear in the size of lhs."""
        best = max(parent_max, self.cards[new])
        if self.mode != "single" and self.pairs:
            for b in bits(lhs):
                best = max(best, self.pairs.get(1 << b | 1 << new, 0))
        return best

    def largest(self, lhs: int) -> int:
        """The same from nothing, with all that is known by now."""
        at = list(bits(lhs))
        best = max((self.cards[i] for i in at), default=min(1, self.n))
        if self.mode != "single" and self.pairs:
            for k, a in enumerate(at):
                for b in at[k + 1 :]:
                    best = max(best, self.pairs.get(1 << a | 1 << b, 0))
        if self.mode == "cache":
            best = max([best, *(c for m, c in self.larger.items() if m & lhs == m)])
        return best

    def bound(self, largest: int, rhs: int) -> int:
        return self.n - max(largest, self.cards[rhs])


def bound_rows(n: int, cards: list[int], pairs: PairMatrix | None, sets: Iterable[int]) -> list[tuple[int, int, int]]:
    """(lhs, rhs, bound) of every set and every attribute outside it."""
    return [
        (s, a, bound_single(n, cards, s, a) if pairs is None else pairs.bound(pairs.largest(s), a))
        for s in sets
        for a in range(len(cards))
        if not s >> a & 1
    ]
