import itertools
import random

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from tests.llm.tables import docs
from topfd.llm import language_id as L
from topfd.llm.words import chunks

_SYLLABLES = {"aa": ["the", "ing", "er", "on"], "bb": ["ße", "sch", "keit", "ung"], "cc": ["ción", "os", "ñe", "que"]}


def text(rng, lang, n=40):
    return " ".join("".join(rng.choice(_SYLLABLES[lang]) for _ in range(rng.randint(1, 3))) for _ in range(n))


def corpus(rng, n=300):
    return [(i, text(rng, lang), lang, "s") for i, lang in enumerate(rng.choice(list(_SYLLABLES)) for _ in range(n))]


def test_forward_backward_is_exact():
    rng = np.random.default_rng(1)
    sizes, k = [3, 1, 4, 0, 2], 3
    first = np.concatenate(([0], np.cumsum(sizes)))
    scores, trans, start = rng.normal(size=(first[-1], k)), rng.normal(size=(k, k)), rng.normal(size=k)
    pairs = np.zeros((k, k))
    got = L.forward_backward(scores, first, trans, start, pairs)
    want, want_pairs = np.zeros_like(scores), np.zeros((k, k))
    for a, n in zip(first[:-1], sizes, strict=True):
        if not n:
            continue
        paths = list(itertools.product(range(k), repeat=n))
        weights = np.array([np.exp(start[p[0]] + sum(scores[a + t, p[t]] for t in range(n)) + sum(trans[p[t], p[t + 1]] for t in range(n - 1))) for p in paths])
        weights /= weights.sum()
        for p, w in zip(paths, weights, strict=True):
            for t in range(n):
                want[a + t, p[t]] += w
                if t:
                    want_pairs[p[t - 1], p[t]] += w
    assert np.allclose(got, want) and np.allclose(pairs, want_pairs)


def test_blocks_give_the_same_probabilities():
    rng = np.random.default_rng(2)
    for trial in range(30):
        sizes, k = rng.integers(0, 40, rng.integers(1, 8)), int(rng.integers(1, 5))
        first = np.concatenate(([0], np.cumsum(sizes)))
        scores, trans, start = 3 * rng.normal(size=(first[-1], k)), rng.normal(size=(k, k)), rng.normal(size=k)
        assert np.allclose(L.probabilities(scores, first, trans, start, 4), L.forward_backward(scores, first, trans, start)), trial


def test_gradient_by_finite_differences():
    rng = np.random.default_rng(3)
    bounds, k = np.array([0, 4, 5, 9]), 3
    y = rng.integers(0, k, 9)
    scores, trans, start = rng.normal(size=(9, k)), rng.normal(size=(k, k)), rng.normal(size=k)

    def likelihood():
        total = 0.0
        for a, b in itertools.pairwise(bounds.tolist()):
            of = lambda p: start[p[0]] + sum(scores[a + t, p[t]] for t in range(b - a)) + sum(trans[p[t], p[t + 1]] for t in range(b - a - 1))  # noqa: B023, E731
            total += of(y[a:b]) - np.log(sum(np.exp(of(p)) for p in itertools.product(range(k), repeat=b - a)))
        return total

    for x, grad in zip((scores, trans, start), L.gradient(scores, y, bounds, trans, start), strict=True):
        for at in np.ndindex(x.shape):
            held = x[at]
            x[at] = held + 1e-5
            up = likelihood()
            x[at] = held - 1e-5
            assert abs((up - likelihood()) / 2e-5 - grad[at]) < 1e-5
            x[at] = held


def test_letters_and_characters():
    assert [L._has_letter(t) for t in ("²½ Ⅷ ① 12 _", "ª", "文", "", "é")] == [False, True, True, False, True]
    raw = np.frombuffer("aé文 😀b".encode(), np.uint8)
    points, sizes = L.characters(raw, np.array([0, 7]), np.array([6, 12]))
    assert [chr(p) for p in points] == ["a", "é", "文", "😀", "b"] and sizes.tolist() == [3, 2]


def test_words_of_mixed_texts_and_long_training_texts(spark):
    rng = random.Random(4)
    rows = [(i, text(rng, lang, 9000), lang, "s") for i, lang in enumerate(["aa", "bb", "cc"] * 4)]
    assert all(len(r[1]) > L.LONGEST for r in rows)
    field = L.train(docs(spark, rows))
    assert field.labels == ["aa", "bb", "cc"]
    again = L.train(docs(spark, rows).repartition(5))
    assert (field.weights == again.weights).all()
    mixed = f"{text(rng, 'aa', 15)}  {text(rng, 'bb', 15)}"
    got = {r["doc_id"]: r["words"] for r in L.label_words(docs(spark, [(1, mixed, None, None), (2, None, None, None), (3, "", None, None)], extra=True), field).collect()}
    assert [w["word"] for w in got[1]] == mixed.split() and got[2] == got[3] == []
    assert sum(w["lang"] == "aa" for w in got[1][:15]) > 12 and sum(w["lang"] == "bb" for w in got[1][15:]) > 12 and all(0 < w["probability"] <= 1 for w in got[1])
    assert L.label_words(docs(spark, [(1, mixed, None, None)]), None).first()["words"] == []


def test_features_are_those_of_the_word_alone():
    def of(t):
        _, _, data, bounds = next(chunks(pa.array([t])))
        w = L.words(data, bounds)
        buckets, first = L.ngram_features(w.data, w.starts, w.ends)
        return [sorted(buckets[a:b].tolist()) for a, b in zip(first[:-1], first[1:], strict=True)]

    alone = {w: of(w)[0] for w in ("a", "der", "schön", "ab")}
    assert of("a der schön ab") == [alone[w] for w in ("a", "der", "schön", "ab")]
    assert len(alone["der"]) == 5 + 4 + 3 + 2 and len({tuple(x) for x in alone.values()}) == 4


def test_held_out_accuracy_and_edges(spark):
    rng = random.Random(2)
    rows = corpus(rng)
    rows += [(900, None, "aa", "s"), (901, "123 ... !", "aa", "s"), (902, "", None, "s"), (903, text(rng, "bb", 20_000), None, "s"), (None, text(rng, "cc"), None, None), (904, "ß", None, "s"), rows[5]]
    df = docs(spark, rows, extra=True).repartition(3)
    got = L.predict(df, L.train(df), ["doc_id", "lang"]).withColumn("held", L.held_out(F.col("doc_id"))).collect()
    assert len(got) == len(rows)
    held = [r for r in got if r["held"] and r["doc_id"] < 900]
    assert len(held) > 30 and sum(r["lang"] == r["lang_pred"] for r in held) / len(held) > 0.97
    by = {r["doc_id"]: r for r in got}
    assert all((by[i]["lang_pred"], by[i]["score"]) == ("und", 0.0) for i in (900, 901, 902))
    assert by[903]["lang_pred"] == "bb" and by[None]["lang_pred"] == "cc" and by[904]["lang_pred"] in _SYLLABLES
    assert all(0 <= r["score"] <= 1 for r in got)


def test_code_switched_words_are_labelled_by_language():
    rng = random.Random(3)
    field = L.fit([text(rng, x, 60).encode() for x in _SYLLABLES for _ in range(40)], [x for x in _SYLLABLES for _ in range(40)])
    mixed = f"{text(rng, 'aa', 15)} {text(rng, 'bb', 15)}"
    _, _, data, bounds = next(chunks(pa.array([mixed])))
    w = L.words(data, bounds, lower=True)
    scores = L.word_scores(field.weights, field.lexicon, *L.ngram_features(w.data, w.starts, w.ends), w.hashes)
    best = L.forward_backward(scores, w.first, field.transitions, field.start).argmax(axis=1)
    assert (best[:15] == 0).mean() > 0.9 and (best[15:] == 1).mean() > 0.9
    assert all(field.transitions[i, i] == field.transitions[i].max() for i in range(3))
    lang, score = L._judge_batch(field, pa.array([mixed, text(rng, "aa")]))
    assert score[0] < 0.8 < score[1]


def test_nothing_to_learn_from(spark):
    df = docs(spark, [(1, "some text", None, "s"), (2, None, "aa", "s")])
    assert [r["lang_pred"] for r in L.predict(df, L.train(df), ["doc_id"]).collect()] == ["und", "und"]
    none = df.limit(0)
    assert L.predict(none, L.train(none), ["doc_id"]).collect() == []
