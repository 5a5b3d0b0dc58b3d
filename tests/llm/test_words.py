import random

import numpy as np
import pyarrow as pa

from topfd.llm import words as W


def test_words_match_the_definition():
    rng = random.Random(1)
    alphabet = "ab é漢\t\n\x0b\x0c\r \x1c\x85\xa0"
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 60))) for _ in range(200)] + [None, "", "  "]
    seen: dict[bytes, int] = {}
    for lo, hi, data, bounds in W.chunks(pa.array(texts), 300):
        w = W.words(data, bounds)
        for k in range(lo, hi):
            mine = [bytes(w.data[s:e]) for s, e in zip(w.starts[w.first[k - lo] : w.first[k - lo + 1]], w.ends[w.first[k - lo] : w.first[k - lo + 1]], strict=True)]
            assert mine == (texts[k] or "").encode().split()
        for s, e, h in zip(w.starts, w.ends, w.hashes, strict=True):
            assert seen.setdefault(bytes(w.data[s:e]), int(h)) == int(h)
    assert len(set(seen.values())) == len(seen)


def test_windows_are_equal_iff_their_words_are():
    rng = random.Random(2)
    texts = [" ".join(rng.choice("abc") for _ in range(rng.randint(0, 30))) for _ in range(60)]
    seen = {}
    for limit in (64, 1 << 20):
        for lo, hi, data, bounds in W.chunks(pa.array(texts), limit):
            w = W.words(data, bounds)
            h, at = w.windows(4)
            doc = np.searchsorted(w.first, at, "right") - 1
            for x, a, d in zip(h, at, doc, strict=True):
                tokens = tuple(texts[lo + d].split()[a - w.first[d] : a - w.first[d] + 4])
                assert len(tokens) == 4
                assert seen.setdefault(tokens, int(x)) == int(x)
    assert len(set(seen.values())) == len(seen)


def test_upper_case_letters_of_ascii_alone_are_lowered():
    _, _, data, bounds = next(W.chunks(pa.array(["ABC abc ÄÖ äö"])))
    h = W.words(data, bounds, lower=True).hashes
    assert h[0] == h[1] and h[2] != h[3]
