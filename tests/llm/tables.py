"""Small awkward tables: nulls, empty and very long texts, ties, repeated rows, extra columns with names that operators use inside."""

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
EXTRA = {"hashes": "1", "score": "'x'", "size": "2.5", "did": "null", "rest": "1", "node": "2", "copies": "'c'", "target": "1", "bucket": "3", "rank": "1", "key": "null", "taken": "9", "_": "0"}


def docs(spark, rows, extra=False):
    """rows: (doc_id, text) or (doc_id, text, lang, source)."""
    full = [(r[0], r[1], *(r[2:] or ("en", "s")), None if r[1] is None else len(r[1])) for r in rows]
    df = spark.createDataFrame(full, DOCS)
    return df.selectExpr("*", *[f"{v} AS `{k}`" for k, v in EXTRA.items()]) if extra else df


def awkward(rng, n=40, words="ab cd ef gh ij kl".split(), longest=40):
    """Random texts over few words, with copies, nulls, blanks, repeated ids."""
    out = []
    for i in range(n):
        kind = rng.random()
        if kind < 0.05:
            text = None
        elif kind < 0.1:
            text = rng.choice(["", "  \t\n", "x"])
        elif kind < 0.35 and out:
            base = rng.choice(out)[1] or ""
            text = base if rng.random() < 0.5 else f"{base} {rng.choice(words)}"
        else:
            text = rng.choice([" ", "\n", "  "]).join(rng.choice(words) for _ in range(rng.randint(1, longest)))
        out.append((i, text))
    out.append(out[3])
    out.append((None, out[4][1]))
    out.append((None, "a text of a row without an id"))
    rng.shuffle(out)
    return out
