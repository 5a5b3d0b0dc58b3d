"""The search on thousands of random relations against brute force: variants, kernels, batches, orders, ties, caps."""

import random

import pytest

from tests.memory_kernel import MemoryRelation, brute_force, install, listed
from topfd.model import Limits, bits
from topfd.plans import bounds
from topfd.plans.search import VARIANTS, discover


@pytest.fixture
def memory(monkeypatch):
    install(monkeypatch)


def relation(rng):
    m, n, d = rng.randint(1, 6), rng.randint(0, 14), rng.choice([1, 2, 3, 4])
    return [tuple(rng.choice([None, *range(d)]) for _ in range(m)) for _ in range(n)], [f"c{i}" for i in range(m)]


@pytest.mark.parametrize("kernel", ["tree", "antichain"])
def test_every_variant_gives_the_exact_answer(memory, kernel):
    rng = random.Random(1)
    for trial in range(1500):
        rows, columns = relation(rng)
        want = brute_force(rows, columns)
        k, batch = rng.choice([1, 2, 5, 10]), rng.choice([1, 2, 7, 16])
        options = {"variant": rng.choice(list(VARIANTS)), "kernel": kernel, "batch": batch, "sample": rng.random() < 0.5, "order": rng.choice([None, "random", "descending"]), "bound": rng.choice([None, "cache"])}
        options["strict_counts"] = rng.random() < 0.3
        rel = MemoryRelation(rows, columns, trial)
        positive = [x for x in want if x[0] < 0]
        assert listed(discover(rel, k, **options)) == positive[:k], (rows, k, options)
        loose = discover(MemoryRelation(rows, columns, trial), k, ties="any", **options)
        assert [x[0] for x in listed(loose)] == [x[0] for x in positive[:k]], (rows, k, options)


@pytest.mark.parametrize("kernel", ["tree", "antichain"])
def test_without_k_everything_is_found(memory, kernel):
    rng = random.Random(2)
    for trial in range(1000):
        rows, columns = relation(rng)
        most = rng.choice([None, None, 1, 2])
        options = {"variant": rng.choice(list(VARIANTS)), "kernel": kernel, "batch": rng.choice([1, 3, 16]), "max_lhs": most}
        found = discover(MemoryRelation(rows, columns, trial), None, **options)
        assert sorted(listed(found)) == (brute_force(rows, columns, most) if rows else []), (rows, options)


def test_trace_rises_and_counts_agree(memory):
    rng = random.Random(3)
    for trial in range(200):
        rows, columns = relation(rng)
        found = discover(MemoryRelation(rows, columns, trial), 3, batch=4)
        taus = [t for *_, t in found.trace]
        assert taus == sorted(taus)
        assert found.stats["valid_until_last_change"] <= found.stats["valid_found"] <= found.stats["validations"]
        assert found.status == "complete"


def test_bounds_are_safe_monotone_and_tighter_with_pairs(memory):
    rng = random.Random(4)
    for trial in range(200):
        rows, columns = relation(rng)
        rel = MemoryRelation(rows, columns, trial)
        n, cards = len(rows), [rel.card(1 << i) for i in range(rel.m)]
        pairs = bounds.PairMatrix(n, cards)
        pairs.precompute(rel, bounds.attribute_order(cards))
        for x in range(1 << rel.m):
            for a in range(rel.m):
                if x >> a & 1:
                    continue
                single, double = bounds.bound_single(n, cards, x, a), pairs.bound(pairs.largest(x), a)
                assert double <= single
                if rel.card(x) == rel.card(x | 1 << a):
                    assert n - rel.card(x) <= double
                for b in bits(((1 << rel.m) - 1) & ~x & ~(1 << a)):
                    assert pairs.bound(pairs.largest(x | 1 << b), a) <= double
                    assert pairs.extend(pairs.largest(x), x, b) == pairs.largest(x | 1 << b)


def test_an_edge_that_arrives_late_loses_no_hitting_set(memory):
    """Three rows pairs whose difference sets appear one after another, each after a refutation: {a, b} hits all."""
    rows = [(0, 0, 0, 0), (1, 1, 0, 1), (0, 0, 0, 0), (1, 0, 1, 2), (0, 1, 1, 3)]
    columns = ["a", "b", "c", "y"]
    want = brute_force(rows, columns)
    for seed in range(50):
        for batch in (1, 2, 5):
            assert sorted(listed(discover(MemoryRelation(rows, columns, seed), None, batch=batch, sample=False))) == want


def test_limits_end_a_run(memory):
    rng = random.Random(5)
    rows = [tuple(rng.randrange(3) for _ in range(6)) for _ in range(30)]
    found = discover(MemoryRelation(rows, list("abcdef")), None, batch=1, sample=False, limits=Limits(max_validations=3))
    assert found.status == "over_budget"
    assert found.stats["validations"] <= 3


def test_k_below_one_is_an_error(memory):
    with pytest.raises(ValueError):
        discover(MemoryRelation([(1,)], ["a"]), 0)


def test_empty_lhs_can_be_left_out(memory):
    rows = [(1, 1, 7), (1, 2, 7), (2, 2, 7)]
    with_it = listed(discover(MemoryRelation(rows, ["a", "b", "c"]), None))
    without = listed(discover(MemoryRelation(rows, ["a", "b", "c"]), None, empty_lhs=False))
    assert (-2, 0, "", "c") in with_it and not any(x[3] == "c" and x[1] for x in with_it)
    assert {x[2] for x in without if x[3] == "c"} == {"a", "b"}
