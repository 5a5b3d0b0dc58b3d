import random
import zlib
from collections import Counter

import numpy as np

from tests.llm import test_mixing, test_near_dedup, test_substring_dedup
from tests.llm.tables import docs
from tests.llm.test_language_id import text


def corpus(rng):
    rows = [(i, text(rng, lang, rng.randint(30, 80)), lang, f"s{i % 4}") for i, lang in enumerate(rng.choice(["aa", "bb", "cc"]) for _ in range(160))]
    passage = text(rng, "aa", 30)
    rows += [(200 + i, f"{text(rng, 'aa', 40)} {passage} {text(rng, 'aa', 40)}", "aa", "hot") for i in range(40)]
    rows += [(300 + i, rows[i][1] + (" zusatz" if i % 2 else ""), "bb", "hot") for i in range(30)]
    rows += [(400, None, "aa", "s1"), (401, "12 34 !!", "aa", "s1"), (402, "", None, None), (403, text(rng, "bb", 60), None, None), (None, text(rng, "cc", 50), "cc", "s2"), rows[3]]
    return rows


def test_stages_against_their_brute_force(spark, tmp_path):
    import corpus_pipeline as C

    rows = corpus(random.Random(7))
    d = docs(spark, rows, extra=True).repartition(4)
    names = d.columns
    (_, identify), (_, distinct), (_, passages), (_, mix), (_, pack) = C.STAGES
    keep = lambda df, name: (df.write.parquet(f"{tmp_path}/{name}"), spark.read.parquet(f"{tmp_path}/{name}"))[1]
    as_rows = lambda df: [(r["doc_id"], r["text"], r["lang"], r["source"]) for r in df.collect()]

    one = keep(identify(spark, d, ""), "one")
    assert one.columns == names
    dropped = {r[0] for r in rows} - {r[0] for r in as_rows(one)}
    assert {400, 401, 402} <= dropped and len(dropped) <= 5
    assert all(r["lang"] is not None for r in one.collect())

    two = keep(distinct(spark, one, ""), "two")
    assert two.columns == names
    want = {x[0] for x in test_near_dedup.brute(as_rows(one), 5, 80) if x[3]}
    assert Counter(r[0] for r in as_rows(two)) == Counter(want)

    three = keep(passages(spark, two, ""), "three")
    assert three.columns == names
    before = as_rows(two)
    want = {b[0]: (b[4] if b[2] else r[1]) for b, r in zip(test_substring_dedup.brute(before, 20), before, strict=True)}
    assert {r[0]: r[1] for r in as_rows(three)} == {i: t for i, t in want.items() if t}
    assert all(r["n_chars"] == len(r["text"]) for r in three.collect())

    four = keep(mix(spark, three, ""), "four")
    assert four.columns == names
    size, got = Counter(), Counter()
    for _, t, _, s in as_rows(three):
        size[s] += len(t.split())
    for _, t, _, s in as_rows(four):
        got[s] += len(t.split())
    order = sorted(size, key=lambda s: (s is None, s or ""))
    target = dict(zip(order, test_mixing.filled([size[s] for s in order], [(5.0, 2.0, 1.0)[i % 3] for i in range(len(order))]), strict=True))
    assert all(abs(got[s] - target[s]) <= 5 for s in order)

    five = pack(spark, four, "").collect()
    from topfd.llm.tokens import encoder

    encode = encoder()
    pieces = Counter()
    for i, t, *_ in as_rows(four):
        ids = np.append(encode(t), 0).astype("<u4")
        pieces[i, zlib.crc32(ids.tobytes()), len(ids)] += 1
    assert Counter((r["doc_id"], r["ids_crc32"], r["length"]) for r in five) == pieces
    total = sum(r["length"] for r in five)
    assert len({r["sequence_id"] for r in five}) <= -(-total // 2048) + 1


def test_run_of_an_empty_table(spark, tmp_path):
    import corpus_pipeline as C

    docs(spark, [(1, "a")]).limit(0).write.parquet(f"{tmp_path}/documents.parquet")
    assert C.run(spark, str(tmp_path)).collect() == []


def test_odd_columns_and_ids_lose_no_document(spark, tmp_path):
    """Null ids, one id on several texts, repeated rows and names that clash with everything: each text comes through, the columns as they were."""
    import corpus_pipeline as C
    from pyspark.sql import functions as F

    rng = random.Random(11)
    texts = [text(rng, lang, 40) for lang in ("aa", "bb", "cc") for _ in range(30)]
    rows = [((None, 5, 5, i)[i % 4], t, ("aa", "bb", "cc")[i // 30], f"s{i % 2}") for i, t in enumerate(texts)]
    df = docs(spark, rows + rows[:7])
    for name in ("a.b", "_kept_did", "_kept_id", "__none", "did", "row", "own", "judged_lang0", "size", "taken", "copy", "bucket", "text_1", "score", "rest", "group"):
        df = df.withColumn(name, F.lit(name))
    names = df.columns
    (_, identify), (_, distinct), (_, passages), (_, mix), (_, pack) = C.STAGES
    now = df.repartition(3)
    for k, stage in enumerate((identify, distinct, passages)):
        out = stage(spark, now, "")
        assert out.columns == names
        out.write.parquet(f"{tmp_path}/{k}")
        now = spark.read.parquet(f"{tmp_path}/{k}")
        assert sorted(set(r["text"] for r in now.collect())) == sorted(texts)
    assert now.count() == len(rows) and all(r["a.b"] == "a.b" and r["own"] == "own" for r in now.collect())
    four = mix(spark, now, "")
    assert four.columns == names and all(r["a.b"] == "a.b" for r in four.collect())
    assert pack(spark, four, "").count() == four.count()


def test_run_leaves_only_its_result(spark, tmp_path):
    import os

    import corpus_pipeline as C
    from topfd.ship import shared_folder

    docs(spark, corpus(random.Random(12))).write.parquet(f"{tmp_path}/documents.parquet")
    folder = shared_folder(spark).removeprefix("file:")
    before = set(os.listdir(folder))
    out = C.run(spark, str(tmp_path))
    assert len(set(os.listdir(folder)) - before) == 1 and out.count() > 100
