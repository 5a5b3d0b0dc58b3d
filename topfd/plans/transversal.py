"""Candidate left-hand sides as hitting sets of difference sets, for one right-hand side each.

Two kernels give the same candidates. The tree kernel keeps a stack of nodes and branches on an unhit edge with the fewest usable attributes. The
antichain kernel keeps all minimal hitting sets and multiplies each new edge in. Both drop what is bounded below the threshold, and both take
edges that arrive at any time: a tree child may only use the attributes of those siblings that are popped before it, so no
hitting set of a later edge is lost. While candidates wait for their validation, nodes that only look redundant wait with them.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass

import numpy as np

from ..model import bits
from ..operators.evidence import WORD_BITS, minimise, words_of

_LOW = (1 << WORD_BITS) - 1
#: Edges from which on arrays are quicker than a loop.
ARRAY_EDGES = 24


def hits(lhs: int, edges: list[int]) -> bool:
    return all(lhs & e for e in edges)


def is_minimal(lhs: int, edges: list[int]) -> bool:
    """Every attribute has an edge that it alone hits."""
    need = lhs
    for e in edges:
        one = e & lhs
        if one and one & (one - 1) == 0:
            need &= ~one
            if not need:
                return True
    return not need


class Edges:
    """Inclusion-minimal edges with their words, so that thousands are tested at once."""

    def __init__(self, edges: Iterable[int], m: int):
        self.n_words = -(-m // WORD_BITS)
        self._set(minimise(edges))

    def _set(self, masks: list[int]) -> None:
        self.masks = masks
        words = words_of(masks) if masks else np.zeros((0, 1), np.uint64)
        self.words = self._room = np.pad(words, ((0, 0), (0, self.n_words - words.shape[1]))) if words.shape[1] < self.n_words else words

    def _word(self, mask: int) -> np.ndarray:
        return np.array([mask >> (WORD_BITS * k) & _LOW for k in range(self.n_words)], np.uint64)

    @property
    def closed(self) -> bool:
        """An empty edge: no left-hand side at all."""
        return bool(self.masks) and self.masks[0] == 0

    def covered(self, edge: int) -> bool:
        """Whether an edge here lies inside this one."""
        if len(self.masks) < ARRAY_EDGES:
            return any(k & edge == k for k in self.masks)
        return bool(((self.words & ~self._word(edge)) == 0).all(axis=1).any())

    def append(self, edge: int) -> None:
        """One that isn't covered. Larger edges that it covers stay: they change neither what is hit nor what is minimal."""
        n = len(self.masks)
        if n + 1 > len(self._room):
            self._room = np.zeros((2 * n + 16, self.n_words), np.uint64)
            self._room[:n] = self.words
        self._room[n] = self._word(edge)
        self.masks.append(edge)
        self.words = self._room[: n + 1]

    def add(self, edges: Iterable[int]) -> list[int]:
        """The edges that were new."""
        fresh = [e for e in edges if not self.covered(e)]
        if fresh:
            self._set(minimise([*self.masks, *fresh]))
        return fresh

    def unhit(self, lhs: int) -> list[int]:
        if len(self.masks) < ARRAY_EDGES:
            return [e for e in self.masks if not e & lhs]
        return [self.masks[i] for i in np.flatnonzero(~(self.words & self._word(lhs)).any(axis=1)).tolist()]

    def minimal(self, lhs: int) -> bool:
        """Every attribute of lhs has an edge that it alone hits."""
        if len(self.masks) < ARRAY_EDGES:
            return is_minimal(lhs, self.masks)
        own = self.words & self._word(lhs)
        alone = own[np.bitwise_count(own).sum(axis=1) == 1]
        return bool((np.bitwise_or.reduce(alone, axis=0) == self._word(lhs)).all()) if len(alone) else not lhs


@dataclass
class Counters:
    generated: int = 0
    visited: int = 0
    pruned_expand: int = 0
    pruned_validate: int = 0
    pruned_pop: int = 0
    refuted: int = 0


@dataclass
class Node:
    lhs: int
    usable: int
    largest: int


class Tree:
    """The search tree of one right-hand side. rank: place of each attribute in the order of access."""

    def __init__(self, rhs: int, m: int, edges: set[int] | Callable[[], set[int]], rank: list[int], matrix, counters: Counters, max_lhs: int | None, empty_lhs: bool = True):
        """edges: the difference sets, or what gives all that are known when the tree first needs them."""
        self.rhs, self.rank, self.matrix, self.counters, self.max_lhs, self.empty_lhs = rhs, rank, matrix, counters, max_lhs, empty_lhs
        self.everything = ((1 << m) - 1) & ~(1 << rhs)
        self._source, self._edges = edges if callable(edges) else lambda: edges, None if callable(edges) else Edges(edges, m)
        self.m = m
        self.stack = [Node(0, self.everything, min(1, matrix.n))]
        self.held: list[Node] = []
        counters.generated += 1
        self.recheck = True

    def add_edges(self, edges: set[int]) -> None:
        """New difference sets without the right-hand side; one that is empty leaves no candidate at all."""
        if self._edges is not None:
            self._edges.add(edges)

    @property
    def edges(self) -> Edges:
        if self._edges is None:
            self._edges = Edges(self._source(), self.m)
        return self._edges

    @property
    def closed(self) -> bool:
        return self.edges.closed

    def top_bound(self) -> int | None:
        """Bound of the node on top of the stack; None if the tree is done."""
        if self.closed:
            self.stack.clear()
        return self.matrix.bound(self.stack[-1].largest, self.rhs) if self.stack else None

    def step(self, below: Callable[[int], bool]) -> int | None:
        """Pops one node and expands it, or returns its left-hand side as a candidate. below(bound): whether that is under the threshold."""
        node = self.stack.pop()
        self.counters.visited += 1
        if self.recheck:
            node.largest = max(node.largest, self.matrix.largest(node.lhs))
            if node.lhs.bit_count() > 2 and not below(self.matrix.bound(node.largest, self.rhs)):
                node.largest = max(node.largest, self.matrix.sampled(node.lhs))
        bound = self.matrix.bound(node.largest, self.rhs)
        unhit = self.edges.unhit(node.lhs)
        if not unhit and (node.lhs or self.empty_lhs):
            if not self.edges.minimal(node.lhs) and (self.empty_lhs or node.lhs.bit_count() > 1):
                if self.held:
                    # what is being validated may bring the edge that makes this one minimal
                    self.held.append(node)
                return None
            if below(bound):
                self.counters.pruned_validate += 1
                return None
            self.held.append(node)
            return node.lhs
        if self.recheck and below(bound):
            self.counters.pruned_pop += 1
            return None
        self.expand(node, unhit, below)
        return None

    def expand(self, node: Node, unhit: list[int], below: Callable[[int], bool]) -> None:
        if self.max_lhs is not None and node.lhs.bit_count() >= self.max_lhs:
            return
        # without an unhit edge, only the empty set that isn't wanted gets here: every single attribute is next
        edge = min((e & node.usable for e in unhit), key=lambda e: (e.bit_count(), e)) if unhit else node.usable
        usable = node.usable & ~edge
        children = []
        for b in sorted(bits(edge), key=lambda i: self.rank[i]):
            largest = self.matrix.extend(node.largest, node.lhs, b)
            if below(self.matrix.bound(largest, self.rhs)):
                self.counters.pruned_expand += 1
                continue
            children.append(Node(node.lhs | 1 << b, usable, largest))
            usable |= 1 << b
        self.counters.generated += len(children)
        self.stack += reversed(children)

    def resume(self, valid: set[int]) -> None:
        """After a validation: all that was held back goes on the stack as it was popped, but for what turned out valid."""
        self.stack += [n for n in reversed(self.held) if n.lhs not in valid]
        self.held.clear()


class Antichain:
    """All minimal hitting sets of the edges so far whose bound may still matter."""

    def __init__(
        self, rhs: int, m: int, edges: set[int], rank: list[int], matrix, counters: Counters, max_lhs: int | None, empty_lhs: bool = True, below: Callable[[int], bool] = lambda b: False, most: int | None = None
    ):
        self.rhs, self.rank, self.matrix, self.counters, self.max_lhs, self.most = rhs, rank, matrix, counters, max_lhs, most
        self.everything = ((1 << m) - 1) & ~(1 << rhs)
        self.sets: set[int] = {0} if empty_lhs else {1 << i for i in bits(self.everything)}
        self.edges = Edges((), m)
        self.settled: set[int] = set()
        self.closed = self.overgrown = False
        counters.generated += 1
        if below(matrix.bound(min(1, matrix.n), rhs)):
            self.sets = set()
        self.add_edges(edges, below)

    def _hopeless(self, lhs: int, below: Callable[[int], bool]) -> bool:
        return below(self.matrix.bound(self.matrix.largest(lhs), self.rhs)) or (lhs.bit_count() > 1 and below(self.matrix.bound(self.matrix.sampled(lhs), self.rhs)))

    def add_edges(self, edges: Iterable[int], below: Callable[[int], bool] = lambda b: False) -> None:
        """Sets that hit a new edge stay; the others are extended by each of its attributes, and what is hopeless or not minimal is dropped. Where no set is left, none can come back."""
        if not self.sets or self.closed or self.overgrown:
            return
        for e in minimise(edges):
            if not self.sets or self.overgrown:
                return
            if self.edges.covered(e):
                continue
            if e == 0:
                self.closed, self.sets = True, set()
                return
            self.edges.append(e)
            lost = [s for s in self.sets if not s & e]
            if not lost:
                continue
            good = self.sets.difference(lost)
            grown: set[int] = set()
            for s in lost:
                if self.max_lhs is not None and s.bit_count() >= self.max_lhs:
                    continue
                for b in bits(e):
                    t = s | 1 << b
                    if t in grown:
                        continue
                    # a minimal hitting set of all edges: each attribute has an edge of its own
                    if not self.edges.minimal(t):
                        continue
                    if self._hopeless(t, below):
                        self.counters.pruned_expand += 1
                    else:
                        grown.add(t)
            self.counters.generated += len(grown)
            self.sets = good | grown
            if self.most is not None and len(self.sets) > self.most:
                self.overgrown = True

    def candidates(self, below: Callable[[int], bool]) -> list[tuple[int, int]]:
        """(bound, lhs) of what is still to be validated."""
        out = []
        for s in sorted(self.sets - self.settled, key=lambda s: tuple(sorted(self.rank[i] for i in bits(s)))):
            bound = self.matrix.bound(max(self.matrix.largest(s), self.matrix.sampled(s) if s.bit_count() > 1 else 0), self.rhs)
            if below(bound):
                self.counters.pruned_validate += 1
                self.sets.discard(s)
            else:
                out.append((bound, s))
        return out
