import hashlib
import random

import pytest
from pyspark.sql import functions as F

from tests.llm.tables import awkward, docs
from topfd.llm import substring_dedup as S


def brute(rows, size):
    """By definition; rows that share an id are judged each against smaller ids and itself."""
    last = float("inf")
    key = lambda i: last if i is None else i
    first: dict[tuple, float] = {}
    words = [((r[1] or "").encode().split()) for r in rows]
    for (i, *_), w in zip(rows, words, strict=True):
        for s in range(len(w) - size + 1):
            t = tuple(w[s : s + size])
            first[t] = min(first.get(t, last), key(i))
    out = []
    for (i, *_), w in zip(rows, words, strict=True):
        gone, own = set(), set()
        for s in range(len(w) - size + 1):
            t = tuple(w[s : s + size])
            if first[t] < key(i) or t in own:
                gone |= set(range(s, s + size))
            own.add(t)
        kept = b" ".join(x for k, x in enumerate(w) if k not in gone)
        out.append((i, len(w), len(gone), hashlib.sha256(kept).hexdigest(), kept.decode(), w))
    return out


@pytest.mark.parametrize(("size", "shortest"), [(4, 2), (8, 2), (20, 10), (20, 5), (7, 2), (5, 5), (1, 1), (13, 3)])
def test_against_brute_force(spark, size, shortest):
    rng = random.Random(size)
    rows = awkward(rng, 60, longest=3 * size)
    df = docs(spark, rows, extra=True).repartition(3)
    got = sorted(map(tuple, S.digests(df, size, shortest).select("doc_id", "n_words", "n_removed", "kept_sha256").collect()), key=str)
    assert got == sorted((x[:4] for x in brute(rows, size)), key=str)


def test_texts_keep_their_columns(spark):
    rng = random.Random(5)
    rows = awkward(rng, 40, longest=16)
    df = docs(spark, rows, extra=True)
    out = S.deduplicated(df, 4, 2)
    assert out.columns == df.columns
    want = sorted((str(i), (r[1] if not lost else kept)) for (i, _, lost, _, kept, _), r in zip(brute(rows, 4), rows, strict=True) if r[1] is not None)
    assert sorted((str(r["doc_id"]), r["text"]) for r in out.collect() if r["text"] is not None) == want


def test_rows_without_an_id_of_their_own(spark):
    """Many null ids, and one id on different texts: none is earlier than another of the same id."""
    rng = random.Random(6)
    body = [" ".join(rng.choice("abc") for _ in range(12)) for _ in range(60)]
    rows = [(rng.choice([None, None, 5, 7]), t) for t in body] + [(None, body[0])] * 5 + [(5, body[1])] * 5
    got = sorted(map(tuple, S.digests(docs(spark, rows).repartition(4), 4, 2).collect()), key=str)
    assert got == sorted((x[:4] for x in brute(rows, 4)), key=str)


def test_clashing_names(spark):
    df = docs(spark, [(1, "a b c d e"), (2, "x a b c d e")]).withColumn("none", F.lit(1)).withColumn("a.b", F.lit(2)).withColumn("row", F.lit(3)).withColumn("copy", F.lit(4))
    got = S.deduplicated(df, 4, 2)
    assert got.columns == df.columns and sorted((r["text"], r["a.b"], r["row"], r["copy"], r["none"]) for r in got.collect()) == [("a b c d e", 2, 3, 4, 1), ("x", 2, 3, 4, 1)]


def test_a_passage_that_all_share_and_a_very_long_text(spark):
    passage = " ".join(f"p{i}" for i in range(25))
    rows = [(i, f"u{i} {passage} v{i}") for i in range(300)] + [(300, "w " * 200_000)]
    got = {r["doc_id"]: r["n_removed"] for r in S.digests(docs(spark, rows).repartition(5)).collect()}
    assert got[0] == 0 and all(got[i] == 25 for i in range(1, 300))
    assert got[300] == 199_999  # the first window stays but for what later ones cover


def test_empty_table(spark):
    assert S.digests(docs(spark, [(1, "a")]).limit(0)).collect() == []
    assert S.deduplicated(docs(spark, [(1, "a")]).limit(0)).collect() == []


def test_lengths():
    assert S.lengths(20, 10) == [10, 20] and S.lengths(40, 10) == [10, 20, 40] and S.lengths(20, 5) == [5, 10, 20] and S.lengths(21, 5) == [6, 11, 21] and S.lengths(3, 5) == [3]
