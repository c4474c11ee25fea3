"""Small tables with every odd case."""

import re

WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, digest string, n long, size long, comp string"


def docs(spark, texts, sources=None, ids=None):
    """Documents with extra columns whose names operators use themselves; texts may be null."""
    ids = ids or list(range(len(texts)))
    sources = sources or ["a"] * len(texts)
    rows = [(i, t, None, s, len(t) if t else None, "x", 7, 8, None) for i, t, s in zip(ids, texts, sources)]
    return spark.createDataFrame(rows, DOCS)


def random_texts(rng, n, words=40, vocabulary=60):
    base = [" ".join(f"w{rng.randrange(vocabulary)}" for _ in range(rng.randrange(1, words))) for _ in range(n // 2)]
    out = list(base)
    while len(out) < n:
        t = rng.choice(base).split()
        for _ in range(rng.randrange(0, 3)):
            t[rng.randrange(len(t))] = f"w{rng.randrange(vocabulary)}"
        out.append(" ".join(t))
    return out
