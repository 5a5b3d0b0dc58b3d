import math
import random

import numpy as np
import pyarrow as pa
import pytest

from tests.llm.tables import awkward, docs
from topfd.llm import graph, near_dedup as N
from topfd.llm.words import chunks

_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def sets(rows, width):
    out = []
    for _, text, *_ in rows:
        w = (text or "").translate(_LOWER).encode().split()
        out.append({tuple(w)} if 0 < len(w) < width else {tuple(w[i : i + width]) for i in range(len(w) - width + 1)})
    return out


def brute(rows, width, percent):
    """(doc_id, n_shingles, component_id, kept) by all pairs."""
    s, root = sets(rows, width), list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            both = len(s[i] & s[j])
            if both and 100 * both >= percent * (len(s[i]) + len(s[j]) - both):
                root[find(i)] = find(j)
    last = float("inf")
    ids = [last if r[0] is None else r[0] for r in rows]
    least: dict[int, float] = {}
    for i in range(len(rows)):
        least[find(i)] = min(least.get(find(i), last), ids[i])
    real = lambda x: None if x == last else x
    return sorted(((real(ids[i]), len(s[i]), real(least[find(i)]), ids[i] == least[find(i)]) for i in range(len(rows))), key=str)


def listed(df):
    return sorted(map(tuple, df.select("doc_id", "n_shingles", "component_id", "kept").collect()), key=str)


def near_copies(rng, base, n, edits):
    out = []
    for _ in range(n):
        w = list(base)
        for _ in range(rng.randint(0, edits)):
            w[rng.randrange(len(w))] = f"e{rng.randrange(10**6)}"
        out.append(" ".join(w))
    return out


def test_against_all_pairs(spark):
    rng = random.Random(1)
    rows = awkward(rng, 80, longest=60, words=[f"w{i}" for i in range(40)])
    base = [f"b{i}" for i in range(120)]
    rows += [(1000 + i, t) for i, t in enumerate(near_copies(rng, base, 60, 4))]
    rows += [(2000, "one"), (2001, "ONE"), (2002, "two words"), (2003, "two\twords"), (2004, "Élan vital ici"), (2005, "élan vital ici")]
    assert listed(N.groups(docs(spark, rows, extra=True).repartition(3), 3, 85)) == brute(rows, 3, 85)


def test_blocks_link_what_stars_miss(spark, monkeypatch):
    """Chains whose ends are far apart: no member is like all others. Small blocks make members meet across blocks."""
    monkeypatch.setattr(N, "BLOCK", 8)
    rng = random.Random(2)
    rows, w = [], [f"c{i}" for i in range(150)]
    for i in range(60):
        rows.append((i, " ".join(w)))
        w[rng.randrange(len(w))] = f"n{i}"
    rng.shuffle(rows)
    assert listed(N.groups(docs(spark, rows).repartition(2), 3, 85)) == brute(rows, 3, 85)


def test_signature_agreement_estimates_similarity():
    rng = random.Random(3)
    for n in (2, 8, 60, 400):
        off = []
        for trial in range(40):
            a = [f"x{trial}_{i}" for i in range(n)]
            b = a[: n * 3 // 4] + [f"y{trial}_{i}" for i in range(n // 4)]
            _, _, data, bounds = next(chunks(pa.array([" ".join(a), " ".join(b)])))
            h, first = N.shingle_sets(data, bounds, 1)
            sig = N.signatures(h, first, 250)
            assert (sig != N._UNSET).all()
            sa, sb = (set(h[first[k] : first[k + 1]].tolist()) for k in (0, 1))
            off.append((sig[0] == sig[1]).mean() - len(sa & sb) / len(sa | sb))
        assert abs(np.mean(off)) < 0.02, n
    h, first = np.zeros(0, np.uint64), np.zeros(2, np.int64)
    assert (N.signatures(h, first, 100) == N._UNSET).all()
    del rng


def test_one_of_each_keeps_columns_and_one_row(spark):
    rows = [(1, "a b c d e f"), (1, "a b c d e f"), (2, "A b c d e f"), (3, None), (4, ""), (5, "q r s t u v")]
    df = docs(spark, rows, extra=True)
    out = N.one_of_each(df)
    assert out.columns == df.columns
    assert sorted(r["doc_id"] for r in out.collect()) == [1, 3, 4, 5]


def test_one_of_each_brings_rows_back_by_id_and_text(spark):
    """Several null ids, one id on different texts, ids that a kept and a removed row share."""
    long = [" ".join(f"{c}{i}" for i in range(40)) for c in "abcdefg"]
    near = [t + " more" for t in long]
    rows = [
        (None, long[0]), (None, long[1]), (None, None), (None, ""), (None, near[1]),  # one of the two that are alike
        (7, long[2]), (7, long[3]),
        (1, long[4]), (9, near[4]), (9, long[5]),  # of id 9, only the second
        (2, long[6]), (None, near[6]),  # this null id goes, the others stay
        (7, long[2]),
    ]
    got = sorted(((r["doc_id"], r["text"]) for r in N.one_of_each(docs(spark, rows, extra=True).repartition(3)).collect()), key=str)
    alike = [r for r in got if r[1] in (long[1], near[1])]
    assert len(alike) == 1
    want = [(None, long[0]), (None, None), (None, ""), (7, long[2]), (7, long[3]), (1, long[4]), (9, long[5]), (2, long[6])]
    assert sorted((r for r in got if r not in alike), key=str) == sorted(want, key=str)


def test_empty_table(spark):
    assert N.groups(docs(spark, [(1, "a")]).limit(0)).collect() == []


def test_components(spark):
    rng = random.Random(4)
    edges = [(i, i + 1) for i in range(0, 200)] + [(1000, 1000 + i) for i in range(1, 300)] + [(rng.randrange(5000, 9000), rng.randrange(5000, 9000)) for _ in range(2000)] + [(7, 7)]
    got = {r["node"]: r["root"] for r in graph.components(spark.createDataFrame(edges, "a long, b long").repartition(6)).collect()}
    root: dict[int, int] = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    want = {x: find(x) for x in root}
    lonely = {x for x in want if want[x] == x and sum(v == x for v in want.values()) == 1}
    assert got == {x: r for x, r in want.items() if x not in lonely}


def test_banding_misses_few():
    for percent in (80, 85, 90):
        bands, rows = N.banding(percent)
        assert (1 - (percent / 100) ** rows) ** bands <= 1e-5


@pytest.mark.parametrize("block", [1, 3])
def test_blocks_of_any_size_find_every_link(spark, monkeypatch, block):
    monkeypatch.setattr(N, "BLOCK", block)
    monkeypatch.setattr(N, "BLOCK_ELEMENTS", 40 * block)
    rng = random.Random(21)
    base = [[rng.choice("abcdefghij") + str(rng.randrange(30)) for _ in range(60)] for _ in range(3)]
    rows = []
    for i in range(90):
        w = list(base[i % 3])
        for _ in range(rng.randrange(6)):
            w[rng.randrange(len(w))] = f"x{rng.randrange(5)}"
        rows.append((i, " ".join(w)))
    got = sorted((r["doc_id"], r["component_id"]) for r in N.groups(docs(spark, rows).repartition(3), 3, 70).collect())
    assert got == sorted((x[0], x[2]) for x in brute(rows, 3, 70))


def test_sets_that_share_half_a_name_stay_apart(spark):
    rows = [(1, 0, 0, 3, 77, 1, None), (2, 0, 0, 3, 77, 1, None), (3, 0, 0, 4, 77, 2, None), (4, 0, 0, 5, 78, 3, None), (5, 0, 0, 0, 77, 9, None)]
    known = spark.createDataFrame(rows, "did long, text_1 long, text_2 long, n_shingles long, node long, node2 long, bands array<long>")
    got = {r["did"]: r["node"] for r in N._one_name_a_set(known).collect()}
    assert got[1] == got[2] != got[3] and len({got[1], got[3], got[4]}) == 3 and got[4] == 78
    assert N._one_name_a_set(known.where("did <> 3 AND did <> 5")).count() == 3


def test_margins_follow_slots_and_threshold():
    for percent in (80, 85):
        bands, rows = N.banding(percent)
        slots = bands * rows
        least = N.least_agreement(percent, slots)
        below = sum(math.comb(slots, k) * (percent / 100) ** k * (1 - percent / 100) ** (slots - k) for k in range(least))
        assert below <= N.ESTIMATE_MISS and 0.5 * slots < least < percent / 100 * slots
        assert (1 - (percent / 100) ** rows) ** bands <= N.MISS
