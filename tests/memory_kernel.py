"""The search's row kernels over Python tuples, so that its logic can be tried on thousands of relations; and brute force."""

from __future__ import annotations

import random

import numpy as np

from topfd.model import bits
from topfd.operators.cardinality import Verdict
from topfd.operators.evidence import Sample


class MemoryRelation:
    """Looks like a Relation to the search. Difference sets of refutations are drawn at random among all that refute."""

    class _Frame:
        def __init__(self, n):
            self.n = n
            self.sparkSession = None

        def count(self):
            return self.n

    def __init__(self, rows, columns, seed=0):
        self.rows, self.columns, self.df, self.rng = rows, columns, self._Frame(len(rows)), random.Random(seed)

    @property
    def m(self):
        return len(self.columns)

    def names(self, mask):
        return sorted(self.columns[i] for i in bits(mask))

    def lhs_text(self, mask):
        return ",".join(self.names(mask))

    def sort_key(self, fd):
        return (-fd.redundancy, fd.lhs.bit_count(), self.lhs_text(fd.lhs).encode(), self.columns[fd.rhs].encode())

    def card(self, mask):
        return len({tuple(r[i] for i in bits(mask)) for r in self.rows})


def install(monkeypatch):
    from topfd.plans import bounds, search

    def check(rel, candidates, rows=None):
        return {(x, a): Verdict(rel.card(x) == rel.card(x | 1 << a), rel.card(x), None if rel.card(x) == rel.card(x | 1 << a) else (x, a)) for x, a in candidates}

    def edges(rel, broken):
        found = {}
        for x, a, _ in broken:
            pairs = [(r, s) for r in rel.rows for s in rel.rows if all(r[i] == s[i] for i in bits(x)) and r[a] != s[a]]
            r, s = rel.rng.choice(pairs)
            found[x, a] = sum(1 << i for i in range(rel.m) if r[i] != s[i])
        return found

    def sample(rel, n, cards, slice_rows=0, seed=20):
        rows = [rel.rows[i] for i in sorted(rel.rng.sample(range(n), rel.rng.randint(0, n)))] if n > 1 else []
        codes = [{v: k for k, v in enumerate(dict.fromkeys(r[i] for r in rows))} for i in range(rel.m)]
        rows = np.array([[codes[i][r[i]] for i in range(rel.m)] for r in rows], np.int64).reshape(len(rows), rel.m)
        return Sample.of(rows)

    monkeypatch.setattr(search.cardinality, "check_batch", check)
    monkeypatch.setattr(search.cardinality, "profile", lambda rel: (len(rel.rows), [rel.card(1 << i) for i in range(rel.m)]))
    monkeypatch.setattr(search.evidence, "violating_edges", edges)
    monkeypatch.setattr(search.evidence, "take_sample", sample)
    monkeypatch.setattr(bounds, "coded_cardinalities", lambda rel, sets: {s: rel.card(s) for s in sets})
    monkeypatch.setattr(search.Relation, "release", lambda self: None)


def brute_force(rows, columns, max_lhs=None):
    """(-redundancy, lhs size, names, rhs) of all minimal dependencies, in canonical order."""
    rel = MemoryRelation(rows, columns)
    m = len(columns)
    card = {x: rel.card(x) for x in range(1 << m)}
    out = []
    for a in range(m):
        holds = [x for x in card if not x >> a & 1 and card[x] == card[x | 1 << a]]
        out += [(card[x] - len(rows), x.bit_count(), rel.lhs_text(x), columns[a]) for x in holds if not any(y != x and y & x == y for y in holds)]
    return sorted(x for x in out if max_lhs is None or x[1] <= max_lhs)


def listed(found):
    return [(-f.redundancy, f.lhs.bit_count(), found.rel.lhs_text(f.lhs), found.rel.columns[f.rhs]) for f in found.fds]
