"""Small corpora with copies, near copies, shared passages, nulls, ties and repeated rows."""

import random

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def corpus(seed=1, n=120, vocabulary=60):
    r = random.Random(seed)
    word = lambda: r.choice(["a", "Of", "thé", "xyz", "q1", "lorem", "ipsum", "ÄÖ"]) if r.random() < 0.2 else "w%d" % r.randrange(vocabulary * 20)
    text = lambda k: "".join(word() + r.choice([" ", " ", " ", "\n", "\t ", "  "]) for _ in range(k))
    passages = [text(k) for k in (14, 25, 40, 13, 60)]
    rows = []
    for i in range(n):
        kind = r.random()
        if kind < 0.25 and rows:
            t = r.choice(rows)[1] or ""
            if kind < 0.18 and t:
                w = t.split(" ")
                for _ in range(r.randrange(1, 4)):
                    w[r.randrange(len(w))] = word()
                t = " ".join(w)
        elif kind < 0.6:
            t = text(r.randrange(0, 60)) + r.choice(passages) + text(r.randrange(0, 40)) + (r.choice(passages) if kind < 0.4 else "")
        elif kind < 0.66:
            t = r.choice(["", None, " ", "one", "One two", "ab" * 150, "x" * 230, "\n\t"])
        else:
            t = text(r.randrange(1, 120))
        rows.append((i * 3 + 1, t))
    r.shuffle(rows)
    return rows


def odd():
    """Nulls, ties, repeated rows and a long text."""
    t = "these are some words that stand here twice and go on until thirteen and more of them are here"
    long = " ".join("v%d" % (i % 997) for i in range(30_000))
    return [(None, t), (3, t), (3, t), (5, None), (None, None), (7, ""), (8, long), (9, long[1000:150_000]), (10, "x")]


def frame(spark, rows, clash=()):
    """documents with further columns of the names in clash."""
    names = "doc_id long, text string, lang string, source string, n_chars long" + "".join(f", `{c}` string" for c in clash)
    return spark.createDataFrame([(d, t, None if i % 7 == 0 else "en", None if i % 11 == 0 else f"s{i % 3}", len(t) if t is not None else None, *["?"] * len(clash)) for i, (d, t) in enumerate(rows)], names)
