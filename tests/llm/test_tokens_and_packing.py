import random
import zlib
from collections import Counter

import numpy as np
import pyarrow.parquet as pq
import pytest

from tests.llm.tables import awkward, docs
from topfd.llm import packing as P
from topfd.llm import token_counts as C
from topfd.llm import tokens as T


@pytest.fixture(scope="module")
def reference():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(T.public_path(T.JSON_FILE))
    return lambda text: t.encode(text, add_special_tokens=False).ids


def test_fast_ids_are_the_reference_ids(reference):
    encode = T.encoder()
    chars = [chr(c) for c in range(0x3000) if not T._OTHER.search(chr(c))]
    assert len(chars) > 500
    for c in chars:
        for text in (c, f"a{c}b", f" {c} ", f"{c}{c}", f"1{c}.", f"\n{c}\t"):
            assert encode(text).tolist() == reference(text), repr(text)
    rng = random.Random(1)
    for _ in range(3000):
        text = "".join(rng.choice([rng.choice(chars), " ", "the", "'s", "\n", "9"]) for _ in range(rng.randint(0, 40)))
        assert encode(text).tolist() == reference(text), repr(text)


def test_ids_of_whole_documents_are_the_reference_ids(reference):
    texts = pq.read_table("/root/testdata/sf0.01/documents.parquet", columns=["text"]).column("text").to_pylist()
    encode = T.encoder()
    assert len(texts) >= 1000
    for text in texts:
        assert encode(text or "").tolist() == reference(text or "")


def test_other_texts_take_the_reference(reference):
    encode = T.encoder()
    for text in ("漢字 кириллица", "a<|endoftext|>b", "x\x1cy\x85z", "e\u0301", "\u00a0 \u2003x", "😀 ok", ""):
        assert encode(text).tolist() == reference(text)


def test_histogram_and_totals(spark, reference):
    rows = awkward(random.Random(2), 60)
    lengths = [len(reference(t)) if t else 0 for _, t in rows]
    got = {r["length"]: r for r in C.totals(C.histogram(docs(spark, rows, extra=True).repartition(3))).collect()}
    want = Counter(lengths)
    assert {k: r["n_docs"] for k, r in got.items()} == want
    for limit, r in got.items():
        assert r["docs_from"] == sum(n >= limit for n in lengths) and r["docs_upto"] == sum(n <= limit for n in lengths)
        assert r["total_tokens"] == sum(lengths) and r["tokens_upto"] == sum(n for n in lengths if n <= limit)
        assert r["truncated_tokens"] == sum(min(n, limit) for n in lengths)
    limits = [0, 3, 17, 10_000]
    held = {r["context"]: r["tokens"] for r in C.at_limits(C.histogram(docs(spark, rows)), limits).collect()}
    assert held == {x: sum(min(n, x) for n in lengths) for x in limits}
    assert C.totals(C.histogram(docs(spark, rows).limit(0))).collect() == []


def test_bounds_hold_and_packings_are_packings():
    rng = np.random.default_rng(3)
    for trial in range(300):
        cap = int(rng.integers(5, 60))
        lengths = rng.integers(1, cap + 1, rng.integers(1, 60))
        bins = P.best_fit_decreasing(lengths, cap)
        assert np.bincount(bins, lengths).max() <= cap
        assert P.lower_bound(lengths, cap) <= bins.max() + 1
        offsets = P._offsets(bins, lengths)
        for b in range(bins.max() + 1):
            spans = sorted((o, o + n) for o, n in zip(offsets[bins == b], lengths[bins == b], strict=True))
            assert spans[0][0] == 0 and all(x[1] == y[0] for x, y in zip(spans, spans[1:], strict=False))
    # an item above half a bin each: the bound sees that they can't share
    assert P.lower_bound(np.array([6] * 7), 10) == 7
    assert P.lower_bound(np.array([4] * 7), 10) == 4
    assert P.lower_bound(np.zeros(0, int), 10) == 0


def _optimum(lengths, cap):
    """Fewest bins, by trying every place of every item."""
    best = len(lengths)

    def place(i, bins):
        nonlocal best
        if len(bins) >= best:
            return
        if i == len(lengths):
            best = len(bins)
            return
        for k in range(len(bins)):
            if bins[k] + lengths[i] <= cap and bins[k] not in bins[:k]:
                bins[k] += lengths[i]
                place(i + 1, bins)
                bins[k] -= lengths[i]
        place(i + 1, [*bins, lengths[i]])

    place(0, [])
    return best


def test_bounds_and_certificates_against_the_optimum():
    rng = np.random.default_rng(6)
    certified = 0
    for _ in range(300):
        cap = int(rng.integers(6, 25))
        lengths = np.sort(rng.integers(1, cap, rng.integers(1, 9)))[::-1]
        best = _optimum(lengths.tolist(), cap)
        made, bound = P.best_fit_decreasing(lengths, cap).max() + 1, P.lower_bound(lengths, cap)
        assert bound <= best <= made
        certified += made == bound
    assert certified > 200


def test_exchange_ends_by_the_certificate(spark):
    """Groups of 20 pieces: exchange brings the whole near its bound, and certified groups keep their bins."""
    rng = np.random.default_rng(8)
    rows = [(i, i, 0, 0, int(n), 0) for i, n in enumerate(rng.integers(1, 100, 600))] + [(1000 + i, i, 0, 0, 100, 0) for i in range(5)]
    cuts = P.written(spark.createDataFrame(rows, P.PIECE))
    once, done = (P.assign(cuts, 100, 20, rounds) for rounds in (1, 8))
    first, last = P.certificate(once, 100), P.certificate(done, 100)
    assert last["bound"] == first["bound"] <= last["sequences"] < first["sequences"] and last["gap"] == last["sequences"] - last["bound"]
    assert done.count() == 605 and done.groupBy("sequence_id").agg({"length": "sum"}).agg({"sum(length)": "max"}).first()[0] <= 100
    listed = P.certificates(once).collect()
    assert sum(r["bins"] for r in listed) == first["sequences"] - 5 and all(r["gap"] >= 0 for r in listed)
    # bins that met their bound at once aren't packed again, but for the emptiest
    kept = {r["grp"] for r in listed if not r["gap"]} & {r["grp"] for r in done.select("grp").distinct().collect()}
    assert kept


def test_cut():
    assert P.cut(1) == [(0, 1)] and P.cut(2048) == [(0, 2048)]
    assert P.cut(2049) == [(0, 1), (1, 2048)] and P.cut(4096) == [(0, 2048), (2048, 2048)]
    assert P.cut(5000, 2048) == [(0, 904), (904, 2048), (2952, 2048)]


def test_pack(spark, reference):
    rng = random.Random(4)
    rows = [*awkward(rng, 120), (500, "long text " * 700), (501, "word " * 300)]
    df = docs(spark, rows, extra=True).repartition(4)
    got = P.pack(df, 256, group_rows=40).collect()
    ids = {}
    for i, t in rows:
        ids.setdefault(i, set()).add(tuple(reference(t or "")) + (0,))
    seen: dict[int, list] = {}
    for r in got:
        whole = [x for x in ids[r["doc_id"]] if zlib.crc32(np.array(x[r["start"] : r["start"] + r["length"]], "<u4").tobytes()) == r["ids_crc32"]]
        assert whole
        seen.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for spans in seen.values():
        spans.sort()
        assert spans[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(spans, spans[1:], strict=False)) and sum(n for _, n in spans) <= 256
    total = sum(len(reference(t or "")) + 1 for _, t in rows)
    assert sum(r["length"] for r in got) == total
    assert len(seen) <= -(-total // 256) * 1.02 + 1
    assert P.pack(df.limit(0)).collect() == []


def test_sequences_hold_the_ids(spark, reference):
    rows = [(i, "some words here " * (i + 1)) for i in range(20)]
    df = docs(spark, rows)
    plan = P.pack(df, 64)
    got = [x for r in P.sequences(df, plan, 64).collect() for x in r["ids"]]
    want = [x for _, t in rows for x in [*reference(t), 0]]
    assert sorted(got) == sorted(want)


def test_sequences_of_repeated_ids(spark, reference):
    rows = [(1, "one text " * 9), (1, "one text " * 9), (1, "another"), (None, "third text"), (None, None)]
    df = docs(spark, rows)
    plan = P.pack(df, 16)
    got = [x for r in P.sequences(df, plan, 16).collect() for x in r["ids"]]
    assert sorted(got) == sorted(x for _, t in rows for x in [*reference(t or ""), 0])
