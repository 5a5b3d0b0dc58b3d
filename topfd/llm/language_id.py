"""Language of each word and text by a linear-chain conditional random field.

Every word gets one label; scores of a word are sums of learned weights of its hashed character n-grams (1 to 4 code points) with word-boundary marks
(so prefixes and suffixes are among them) and, for words of a learned lexicon, a weight of the word itself. Learned transition
weights tie neighbours together, and forward-backward over the whole text gives each word's label probabilities. `label_words` returns
these labels, which is what code-switched text is read by. A text's language is the label with the largest mean probability, its score that mean: it says how pure the text is.

Training labels are those of documents. Spans of documents are put in a seeded random order, so that sequences switch languages as
code-switched text does. The field is fitted by Adam on the exact likelihood of a bounded sample: about PER_LANG documents of each
language, chosen by a hash, and of a document longer than LONGEST characters a span of that length. At most MOST_LANGS languages are learned, those of most documents.
Prediction reads every text to its end; the blocks of a long text are stepped through side by side.

Null texts and texts without a letter (a character of Unicode's letter categories) are `und` with score 0, as is every text if nothing could be learned. A tie goes to the first
label in code-point order. Repeated rows are judged alike; an empty table gives an empty result; other columns are carried by `identify` only.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..ship import ship
from .common import table
from .words import chunks, mix, words

PER_LANG, LONGEST, MOST_LANGS = 150, 20_000, 500
FEATURE_BITS, LEXICON, LEXICON_LEAST = 16, 20_000, 3
SPAN, SEQUENCE, EPOCHS, RATE, DECAY = 24, 96, 30, 0.1, 1e-4
#: Words whose probabilities are held at once, and of a block that is stepped through by itself.
GROUP_WORDS, BLOCK_WORDS = 400_000, 1024
UNKNOWN = "und"
_EDGE = np.uint64(0x110000)  # beyond all code points
_ASCII_LETTER = np.zeros(256, bool)
_ASCII_LETTER[[*range(65, 91), *range(97, 123)]] = True


@dataclass
class Field:
    labels: list[str]
    weights: np.ndarray  # n-gram buckets and then lexicon words, each by label
    lexicon: np.ndarray  # sorted word hashes
    transitions: np.ndarray
    start: np.ndarray


def characters(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(code points, sizes) of the given words, one after another."""
    sizes = ends - starts
    at = np.concatenate((np.zeros(1, np.int64), np.cumsum(sizes)))
    raw = data[np.repeat(starts - at[:-1], sizes) + np.arange(at[-1])]
    if len(raw) and raw.max() < 128:
        return raw.astype(np.uint64), sizes
    points = np.frombuffer(raw.tobytes().decode("utf-8", "replace").encode("utf-32-le", "replace"), np.uint32).astype(np.uint64)
    # a code point begins at every byte that isn't a continuation
    begins = np.concatenate((np.zeros(1, np.int64), np.cumsum((raw & 0xC0) != 0x80)))
    return points, begins[at[1:]] - begins[at[:-1]]


def ngram_features(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(buckets, first): of each word, the buckets of its 1- to 4-grams of characters, boundary marks included, and where each word's begin."""
    points, sizes = characters(data, starts, ends)
    sizes = sizes + 2
    at = np.concatenate((np.zeros(1, np.int64), np.cumsum(sizes)))
    text = np.zeros(at[-1] + 3, np.uint64)
    edge = np.zeros(at[-1] + 3, bool)
    edge[at[:-1]] = edge[at[1:] - 1] = True
    text[: at[-1]][~edge[: at[-1]]] = points
    text[edge] = _EDGE
    word_end = np.repeat(at[1:], sizes)
    place = np.arange(at[-1])
    grams = []
    rolled = np.zeros(at[-1], np.uint64)
    for k in range(4):
        rolled = rolled * np.uint64(0x110003) + text[k : k + at[-1]] + np.uint64(1)
        g = (mix(rolled + np.uint64(k << 56)) >> np.uint64(64 - FEATURE_BITS)).astype(np.int64)
        grams.append(np.where(place + k < word_end, g, -1))
    table_ = np.stack(grams, axis=1)
    good = table_ >= 0
    return table_[good], np.concatenate((np.zeros(1, np.int64), np.cumsum(good.sum(axis=1))))[at]


def word_scores(field_weights: np.ndarray, lexicon: np.ndarray, buckets: np.ndarray, first: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    if not len(hashes):
        return np.zeros((0, field_weights.shape[1]), np.float32)
    total = np.add.reduceat(field_weights[buckets], first[:-1], axis=0)
    if len(lexicon):
        where = np.minimum(np.searchsorted(lexicon, hashes), len(lexicon) - 1)
        known = lexicon[where] == hashes
        total[known] += field_weights[(1 << FEATURE_BITS) + where[known]]
    return total


def forward_backward(
    scores: np.ndarray, first: np.ndarray, transitions: np.ndarray, start: np.ndarray, pairs: np.ndarray | None = None, enter: np.ndarray | None = None, leave: np.ndarray | None = None
) -> np.ndarray:
    """Label probabilities of each word. scores: words by label, sequences one after another; first: where each begins. All sequences step together, longest first.
    pairs: gets the sum of the probabilities of neighbouring label pairs. enter, leave: of each sequence, the message that comes in before its first word (instead of start) and after its last."""
    sizes = np.diff(first)
    order = np.argsort(-sizes, kind="stable")
    begin, sizes = first[:-1][order], sizes[order]
    longest = int(sizes[0]) if len(sizes) else 0
    alive = len(sizes) - np.searchsorted(sizes[::-1], np.arange(longest), "right")
    push = np.exp(scores - scores.max(axis=1, keepdims=True)) if len(scores) else scores
    step, pull = np.exp(transitions).astype(scores.dtype), np.exp(transitions.T).astype(scores.dtype)
    alpha = np.empty_like(push)
    n = int(alive[0]) if longest else 0
    now = np.exp(start).astype(scores.dtype)[None, :] * np.ones((n, 1), scores.dtype) if enter is None else enter[order[:n]]
    for t in range(longest):
        at = begin[: alive[t]] + t
        if t:
            now = now[: alive[t]] @ step
        now = now * push[at]
        now /= now.sum(axis=1, keepdims=True)
        alpha[at] = now
    ends = np.ones((n, push.shape[1]), scores.dtype) if leave is None else leave[order[:n]]
    later = ends[:0]
    for t in range(longest - 1, -1, -1):
        at = begin[: alive[t]] + t
        if len(later) < len(at):
            later = np.concatenate((later, ends[len(later) : len(at)]))
        both = alpha[at] * later
        emitted = later * push[at]
        if pairs is not None and t:
            pair = alpha[at - 1][:, :, None] * step[None] * emitted[:, None, :]
            pairs += (pair / pair.sum(axis=(1, 2), keepdims=True)).sum(axis=0)
        alpha[at] = both / both.sum(axis=1, keepdims=True)
        later = emitted @ pull
        later /= later.sum(axis=1, keepdims=True)
    return alpha


def probabilities(scores: np.ndarray, first: np.ndarray, transitions: np.ndarray, start: np.ndarray, block: int = BLOCK_WORDS) -> np.ndarray:
    """forward_backward in steps that follow the block, not the longest text: a block's product of step matrices carries messages over it, so the blocks of a text first exchange
    messages, one step a block, and are then all stepped through together."""
    sizes = np.diff(first)
    if not len(sizes) or sizes.max() <= 2 * block:
        return forward_backward(scores, first, transitions, start)
    n_blocks = np.maximum(1, -(-sizes // block))
    of = np.repeat(np.arange(len(sizes)), n_blocks)
    place = np.arange(len(of)) - np.repeat(np.cumsum(n_blocks) - n_blocks, n_blocks)
    begin = first[:-1][of] + place * block
    cuts = np.append(begin, first[-1])
    lengths = np.diff(cuts)
    push = np.exp(scores.astype(np.float64) - scores.max(axis=1, keepdims=True))
    step = np.exp(transitions.astype(np.float64))
    n_labels = scores.shape[1]
    over = np.broadcast_to(np.eye(n_labels), (len(of), n_labels, n_labels)).copy()
    for t in range(int(lengths.max())):
        here = np.flatnonzero(lengths > t)
        moved = over[here] @ step if t else over[here]
        moved = moved * push[begin[here] + t][:, None, :]
        over[here] = moved / moved.sum(axis=(1, 2), keepdims=True)
    enter, leave = np.empty((len(of), n_labels)), np.ones((len(of), n_labels))
    steps = range(int(n_blocks.max()))
    for t in steps:
        here = np.flatnonzero((place == t) & (lengths > 0))
        if t == 0:
            enter[here] = np.exp(start.astype(np.float64))
            enter[place == 0] = np.exp(start.astype(np.float64))
        else:
            gone = (enter[here - 1][:, None, :] @ over[here - 1])[:, 0, :]
            gone = gone / gone.sum(axis=1, keepdims=True)
            enter[here] = gone @ step
    last = np.cumsum(n_blocks) - 1
    for t in steps:
        # from the last block of each text backwards
        here = last[n_blocks > t + 1] - t - 1
        come = (over[here + 1] @ leave[here + 1][:, :, None])[:, :, 0] @ step.T
        leave[here] = come / come.sum(axis=1, keepdims=True)
    return forward_backward(scores, cuts, transitions, start, None, enter.astype(scores.dtype), leave.astype(scores.dtype))


def fit(texts: list[bytes], langs: list[str], seed: int = 20) -> Field | None:
    """None if there is no word to learn from."""
    labels = sorted(set(langs))
    column = pa.array(texts, pa.large_binary())
    parts = []
    for lo, hi, data, bounds in chunks(column, 1 << 62):
        w = words(data, bounds, lower=True)
        doc_label = np.array([labels.index(x) for x in langs[lo:hi]], np.int64)
        parts.append((w, np.repeat(doc_label, np.diff(w.first))))
    if not parts or not len(parts[0][0].hashes):
        return None
    w, y = parts[0]
    n_labels, rng = len(labels), np.random.default_rng(seed)
    uniq, index, inverse, counts = np.unique(w.hashes, return_index=True, return_inverse=True, return_counts=True)
    frequent = np.flatnonzero(counts >= LEXICON_LEAST)
    lexicon = np.sort(uniq[frequent[np.argsort(-counts[frequent], kind="stable")[:LEXICON]]])
    buckets, first = ngram_features(w.data, w.starts[index], w.ends[index])
    # spans of documents in random order, cut into sequences of one length
    span = np.arange(len(y)) // SPAN
    shuffled = np.argsort(rng.permutation(span[-1] + 1)[span], kind="stable")
    words_of, y = inverse[shuffled], y[shuffled]
    bounds = np.append(np.arange(0, len(y), SEQUENCE), len(y))
    weights = np.zeros(((1 << FEATURE_BITS) + len(lexicon), n_labels))
    transitions, start = np.zeros((n_labels, n_labels)), np.zeros(n_labels)
    model = [weights, transitions, start]
    moments = [(np.zeros_like(x), np.zeros_like(x)) for x in model]
    lex_at = np.minimum(np.searchsorted(lexicon, uniq), max(0, len(lexicon) - 1))
    in_lex = lexicon[lex_at] == uniq if len(lexicon) else np.zeros(len(uniq), bool)
    per_word = np.diff(first)
    scale = [100 / len(y), 1 / len(y), 1 / (len(bounds) - 1)]
    for epoch in range(1, EPOCHS + 1):
        scores = word_scores(weights, lexicon, buckets, first, uniq)[words_of]
        off, pairs, begun = gradient(scores, y, bounds, transitions, start)
        by_word = np.stack([np.bincount(words_of, off[:, k], len(uniq)) for k in range(n_labels)], axis=1)
        g = np.stack([np.bincount(buckets, np.repeat(by_word[:, k], per_word), len(weights)) for k in range(n_labels)], axis=1)
        g[(1 << FEATURE_BITS) + lex_at[in_lex]] += by_word[in_lex]
        for x, grad, by, (m, v) in zip(model, (g, pairs, begun), scale, moments, strict=True):
            grad = grad * by - DECAY * x
            m += 0.1 * (grad - m)
            v += 0.01 * (grad * grad - v)
            x += RATE * (m / (1 - 0.9**epoch)) / (np.sqrt(v / (1 - 0.99**epoch)) + 1e-8)
    return Field(labels, weights.astype(np.float32), lexicon, transitions.astype(np.float32), start.astype(np.float32))


def gradient(scores: np.ndarray, y: np.ndarray, bounds: np.ndarray, transitions: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of the log-likelihood of labels y: by word scores, by transitions, by start."""
    expected, gold_pairs = np.zeros_like(transitions), np.zeros_like(transitions)
    off = np.eye(scores.shape[1])[y] - forward_backward(scores, bounds, transitions, start, expected)
    inside = np.ones(len(y), bool)
    inside[bounds[1:] - 1] = False
    np.add.at(gold_pairs, (y[:-1][inside[:-1]], y[1:][inside[:-1]]), 1)
    return off, gold_pairs - expected, off[bounds[:-1]].sum(axis=0)


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def train(docs: DataFrame, per_lang: int = PER_LANG, longest: int = LONGEST) -> Field | None:
    """docs(doc_id, text, lang): learns from rows that aren't held out. The sample has about per_lang rows a language, chosen by a hash of id and text: the same in every run."""
    usable = docs.where(F.col("lang").isNotNull() & ~held_out(F.col("doc_id")) & (F.length("text") > 0)).select("doc_id", "lang", "text")
    most = usable.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(MOST_LANGS)
    counts = {r["lang"]: r["count"] for r in most.collect()}
    if not counts:
        return None
    share = F.create_map(*[F.lit(x) for lang, n in counts.items() for x in (lang, min(1.0, per_lang / n))])
    mark = F.xxhash64("doc_id", "text", F.lit(3))
    drawn = usable.withColumn("draw", F.pmod(mark, F.lit(1 << 40)) / float(1 << 40)).where(F.col("draw") < F.try_element_at(share, F.col("lang")))
    # of a long text the span from a drawn place on
    begin = F.when(F.length("text") > longest, F.pmod(mark, F.length("text") - longest) + 1).otherwise(F.lit(1)).cast("int")
    spans = drawn.select("lang", F.substring("text", begin, F.lit(longest)).alias("text"), "doc_id", "draw").distinct()
    rows = spans.orderBy(F.col("draw") / F.try_element_at(share, F.col("lang")), "lang", "doc_id", "text").limit(2 * per_lang * len(counts)).collect()
    rows.sort(key=lambda r: (r["lang"], r["doc_id"] is None, r["doc_id"] or 0, r["text"]))
    return fit([r["text"].encode() for r in rows], [r["lang"] for r in rows])


def _has_letter(text: str) -> bool:
    return any(map(str.isalpha, text))


def _judge_batch(field: Field | None, column: pa.Array) -> tuple[list[str], list[float]]:
    n_rows = len(column)
    if field is None:
        return [UNKNOWN] * n_rows, [0.0] * n_rows
    n_labels = len(field.labels)
    scores, sizes, letters = [], [], []
    mean = np.zeros((n_rows, n_labels))
    pending, begun = 0, 0

    def flush(upto: int) -> None:
        nonlocal scores, pending, begun
        n = np.concatenate(sizes[begun:] or [np.zeros(0, np.int64)])
        rows = np.arange(flushed[0], upto)
        filled = n > 0
        first = np.concatenate((np.zeros(1, np.int64), np.cumsum(n[filled])))
        if first[-1]:
            prob = probabilities(np.concatenate(scores), first, field.transitions, field.start)
            mean[rows[filled]] = np.add.reduceat(prob, first[:-1], axis=0, dtype=np.float64) / n[filled][:, None]
        scores, pending, begun, flushed[0] = [], 0, len(sizes), upto

    flushed = [0]
    for lo, hi, data, bounds in chunks(column):
        w = words(data, bounds, lower=True)
        uniq, index, inverse = np.unique(w.hashes, return_index=True, return_inverse=True)
        buckets, first = ngram_features(w.data, w.starts[index], w.ends[index])
        scores.append(word_scores(field.weights, field.lexicon, buckets, first, uniq)[inverse])
        sizes.append(np.diff(w.first))
        seen = np.concatenate(([0], np.cumsum(_ASCII_LETTER[data])))
        has = seen[bounds[1:]] > seen[bounds[:-1]]
        raw = data.tobytes()
        for i in np.flatnonzero(~has).tolist():
            has[i] = _has_letter(raw[bounds[i] : bounds[i + 1]].decode("utf-8", "replace"))
        letters.append(has)
        pending += len(w.hashes)
        if pending >= GROUP_WORDS:
            flush(hi)
    flush(n_rows)
    has = np.concatenate(letters) if letters else np.zeros(0, bool)
    best = mean.argmax(axis=1)
    return [field.labels[b] if ok else UNKNOWN for b, ok in zip(best.tolist(), has.tolist(), strict=True)], np.where(has, np.clip(mean[np.arange(n_rows), best], 0, 1), 0.0).tolist()


def predict(docs: DataFrame, field: Field | None, keep: list[str], names: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """docs with text -> the columns of `keep`, lang_pred, score (or other names). Only the text is looked at, and it is sent once if it is kept too."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(field)
    # by place, as no name may hold a dot on its way to a worker
    kept = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(keep)], *([] if "text" in keep else [F.col("text").alias("text")]))
    at = keep.index("text") if "text" in keep else len(keep)
    kinds = dict(kept.dtypes)
    places = [f"c{i}" for i in range(len(keep))]
    schema = ", ".join([*(f"{c} {kinds[c]}" for c in places), "lang_pred string", "score double"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                lang, score = _judge_batch(shared.value, batch.column(at))
                yield pa.RecordBatch.from_arrays([*batch.columns[: len(places)], pa.array(lang, pa.string()), pa.array(score, pa.float64())], [*places, "lang_pred", "score"])
        pa.default_memory_pool().release_unused()

    judged = kept.mapInArrow(run, schema)
    return judged.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(keep)], F.col("lang_pred").alias(names[0]), F.col("score").alias(names[1]))


def label_words(docs: DataFrame, field: Field | None) -> DataFrame:
    """docs(doc_id, text) -> doc_id, words (array of word, lang, probability), of every word of the text in order; empty for a null text or if nothing was learned."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(field)
    kind = pa.list_(pa.struct([("word", pa.string()), ("lang", pa.string()), ("probability", pa.float64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            f, lists = shared.value, []
            for _, _, data, bounds in chunks(batch.column(1)):
                w = words(data, bounds, lower=True)
                if f is None:
                    lists += [[]] * (len(bounds) - 1)
                    continue
                uniq, index, inverse = np.unique(w.hashes, return_index=True, return_inverse=True)
                buckets, first = ngram_features(w.data, w.starts[index], w.ends[index])
                prob = probabilities(word_scores(f.weights, f.lexicon, buckets, first, uniq)[inverse], w.first, f.transitions, f.start)
                best, raw = prob.argmax(axis=1), data.tobytes()
                rows = [
                    {"word": raw[a:b].decode("utf-8", "replace"), "lang": f.labels[k], "probability": p}
                    for a, b, k, p in zip(w.starts.tolist(), w.ends.tolist(), best.tolist(), prob.max(axis=1, initial=0).tolist(), strict=True)
                ]
                lists += [rows[a:b] for a, b in zip(w.first[:-1].tolist(), w.first[1:].tolist(), strict=True)]
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(lists, kind)], ["doc_id", "words"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, words array<struct<word:string,lang:string,probability:double>>")


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    judged = predict(docs, train(docs), ["doc_id"])
    return judged.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
