import random

import pytest
from pyspark.sql import functions as F

from tests.llm.tables import docs
from topfd.llm import mixing as M


def filled(sizes, weights, epochs=3.0):
    """Targets by repeated clamping, as the definition tells it."""
    budget, stopped = float(sum(sizes)), {}
    while True:
        left = budget - sum(stopped.values())
        open_ = [i for i in range(len(sizes)) if i not in stopped]
        total = sum(weights[i] for i in open_)
        share = {i: left * weights[i] / total for i in open_}
        over = [i for i in open_ if share[i] > epochs * sizes[i]]
        if not over:
            return [stopped.get(i, share.get(i)) for i in range(len(sizes))]
        stopped |= {i: epochs * sizes[i] for i in over}


@pytest.mark.parametrize("seed", range(4))
def test_targets_are_those_of_repeated_clamping(spark, seed):
    rng = random.Random(seed)
    sizes = [rng.choice([0, 1, 10, 500, 10_000, 200_000]) for _ in range(rng.randint(1, 12))]
    if not sum(sizes):
        sizes[0] = 5
    names = [f"n{i:02}" for i in range(len(sizes) - 1)] + [None]
    got = {r["source"]: r["target"] for r in M.targets(spark.createDataFrame(list(zip(names, sizes, strict=True)), "source string, source_size long")).collect()}
    want = filled(sizes, [M.WEIGHTS[i % 3] for i in range(len(sizes))])
    assert [got[n] for n in names] == pytest.approx(want, rel=1e-9)


def rows(rng, n=300):
    out = [(i, " ".join(["w"] * rng.randint(0, 40)), "en", rng.choice(["big", "big", "big", "mid", "tiny", None]) if i > 3 else "tiny") for i in range(n)]
    return [*out, (n, None, "en", "big"), (None, "a b c", "en", "mid"), out[5]]


def test_sources_meet_their_targets(spark):
    df = docs(spark, rows(random.Random(1)), extra=True)
    got = M.mix(df).collect()
    by = {}
    for r in got:
        assert 0 <= r["taken"] <= 3 * r["size"]
        x = by.setdefault(r["source"], [0, r["target"], r["source_size"], 0])
        x[0] += r["taken"]
        x[3] += r["size"]
    for taken, target, size, total in by.values():
        assert size == total and abs(taken - target) <= 4
    assert sum(x[1] for x in by.values()) == pytest.approx(sum(r["size"] for r in got))
    again = M.mix(df.repartition(7)).collect()
    assert sorted(map(str, again)) == sorted(map(str, got))


def test_sample_takes_what_the_mix_says(spark):
    df = docs(spark, rows(random.Random(2)), extra=True)
    out = M.sample(df)
    assert out.columns == df.columns
    words = {(r["doc_id"], r["source"]): r["n"] for r in out.groupBy("doc_id", "source").agg(F.sum(F.size(F.split("text", " "))).alias("n")).collect()}
    want = {}
    for r in M.mix(df).collect():
        if r["taken"]:
            want[r["doc_id"], r["source"]] = want.get((r["doc_id"], r["source"]), 0) + r["taken"]
    assert words == want


def test_empty_and_wordless_tables(spark):
    assert M.mix(docs(spark, [(1, "a")]).limit(0)).collect() == []
    got = M.mix(docs(spark, [(1, None), (2, "  ")])).collect()
    assert [r["taken"] for r in got] == [0, 0]
    assert M.sample(docs(spark, [(1, None)])).collect() == []
