"""Quality by a factorisation machine over hashed words, structure statistics and metadata.

A score is the logistic of  b + w.x + 1/2 (|Vx|^2 - sum of (V_j x_j)^2), so pairs of features cost no more than
the features themselves. The model is fitted on the driver from a bounded, seeded sample of labelled rows
(SAMPLE); its size is fixed by BUCKETS and RANK, whatever the data. Scoring reads whole texts and shuffles nothing.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from biclique_spark.llm.common import give_back, parts

#: Labelled rows used for fitting at most; hashed words; columns of V.
SAMPLE, BUCKETS, RANK = 8_000, 1 << 14, 4
#: Words whose bucket a Python worker remembers, for a batch at most: the worker lives on into later stages.
KEPT = 1 << 18
#: Names of the structure and metadata features; each also falls into one of BINS bins that are features of their own.
STATS = ("chars", "words", "word_chars", "distinct", "top_word", "repeats", "upper", "digits", "marks", "wide", "line_words", "same_lines", "n_chars")
BINS = 8
WIDTH = BUCKETS + len(STATS) * BINS
_words: dict[str, int] = {}


def statistics(text: str, words: list[str], counts: Counter, n_chars: int | None) -> list[float]:
    raw = np.frombuffer(text.encode("utf-8", "replace"), np.uint8)
    n, m = max(1, len(raw)), max(1, len(words))
    kinds = np.bincount(raw, minlength=256)
    letters = kinds[65:91].sum() + kinds[97:123].sum()
    marks = kinds[33:48].sum() + kinds[58:65].sum() + kinds[91:97].sum() + kinds[123:127].sum()
    lines = [x for x in text.split("\n") if x]
    return [
        np.log1p(len(raw)),
        np.log1p(len(words)),
        np.log1p(len(raw) / m),
        len(counts) / m,
        max(counts.values(), default=0) / m,
        sum(map(eq, words, words[1:])) / m,
        kinds[65:91].sum() / max(1, letters),
        kinds[48:58].sum() / n,
        marks / n,
        kinds[128:].sum() / n,
        np.log1p(len(words) / max(1, len(lines))),
        1 - len(set(lines)) / max(1, len(lines)),
        np.log1p(max(0, n_chars)) if n_chars is not None else -1.0,
    ]


def features(texts: list[str], n_chars: list[int | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Buckets of words, their values, how many each text has; and the statistics, a row a text."""
    if len(_words) > KEPT:
        _words.clear()
    index, value, sizes, stats = [], [], [], []
    for text, n in zip(texts, n_chars, strict=True):
        words = text.split()
        counts = Counter(words)
        for w in [w for w in counts if w not in _words]:
            _words[w] = zlib.crc32(w.encode("utf-8", "replace")) % BUCKETS
        index.append(np.fromiter(map(_words.__getitem__, counts), np.int32, len(counts)))
        value.append(np.sqrt(np.fromiter(counts.values(), np.float32, len(counts)) / max(1, len(words))))
        sizes.append(len(counts))
        stats.append(statistics(text, words, counts, n))
    join = lambda x, kind: np.concatenate(x).astype(kind) if x else np.zeros(0, kind)
    return join(index, np.int32), join(value, np.float32), np.array(sizes, np.int64), np.array(stats, np.float32).reshape(-1, len(STATS))


class FactorisationMachine:
    """Fitted by AdaGrad on small batches, in a fixed order; the same rows give the same model."""

    def __init__(self, edges: np.ndarray, seed: int = 5):
        self.edges = edges  # of the bins, a row a statistic
        self.bias = np.float32(0)
        self.w = np.zeros(WIDTH, np.float32)
        self.v = np.random.default_rng(seed).normal(0, 0.05, (WIDTH, RANK)).astype(np.float32)

    def rows(self, index, value, sizes, stats):
        """Sparse rows with the bins put in front of each row's words."""
        k, n = len(STATS), len(sizes)
        bins = np.stack([np.searchsorted(self.edges[j], stats[:, j]) for j in range(k)], axis=1) if n else np.zeros((0, k), int)
        bins = (BUCKETS + np.arange(k) * BINS + bins).astype(np.int32)
        starts = np.concatenate([[0], np.cumsum(sizes)])[:-1]
        at = np.repeat(starts, k)
        return np.insert(index, at, bins.ravel()), np.insert(value, at, np.full(n * k, 0.5, np.float32)), sizes + k

    def sums(self, index, value, starts):
        x = value[:, None] * self.v[index]
        s = np.add.reduceat(x, starts, axis=0)
        pairs = 0.5 * ((s**2).sum(1) - np.add.reduceat((x**2).sum(1), starts))
        return self.bias + np.add.reduceat(value * self.w[index], starts) + pairs, s

    def score(self, index, value, sizes, stats) -> np.ndarray:
        if not len(sizes):
            return np.zeros(0)
        index, value, sizes = self.rows(index, value, sizes, stats)
        z, _ = self.sums(index, value, np.concatenate([[0], np.cumsum(sizes)])[:-1])
        return 1 / (1 + np.exp(-np.clip(z.astype(np.float64), -30, 30)))

    def fit(self, index, value, sizes, stats, y, epochs: int = 8, batch: int = 64, rate: float = 0.1, decay: float = 1e-5, seed: int = 5):
        index, value, sizes = self.rows(index, value, sizes, stats)
        ends = np.cumsum(sizes)
        order, g0, gw, gv = np.random.default_rng(seed), 1e-6, np.full(WIDTH, 1e-6, np.float32), np.full((WIDTH, RANK), 1e-6, np.float32)
        for _ in range(epochs):
            shuffled = order.permutation(len(sizes))
            for at in range(0, len(shuffled), batch):
                own = shuffled[at : at + batch]
                take = np.concatenate([np.arange(ends[i] - sizes[i], ends[i]) for i in own])
                i, x, n = index[take], value[take], sizes[own]
                z, s = self.sums(i, x, np.concatenate([[0], np.cumsum(n)])[:-1])
                d = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y[own]).astype(np.float32) / len(own)
                row = np.repeat(np.arange(len(own)), n)
                used, back = np.unique(i, return_inverse=True)
                dw = np.bincount(back, d[row] * x, len(used)).astype(np.float32) + decay * self.w[used]
                each = d[row, None] * x[:, None] * (s[row] - self.v[i] * x[:, None])
                dv = np.stack([np.bincount(back, each[:, k], len(used)) for k in range(RANK)], axis=1).astype(np.float32) + decay * self.v[used]
                g0, gw[used], gv[used] = g0 + d.sum() ** 2, gw[used] + dw**2, gv[used] + dv**2
                self.bias -= np.float32(rate * d.sum() / np.sqrt(g0))
                self.w[used] -= rate * dw / np.sqrt(gw[used])
                self.v[used] -= rate * dv / np.sqrt(gv[used])
        return self


def _prepared(docs: DataFrame, id_col: str, text_col: str, chars_col: str | None) -> DataFrame:
    chars = F.col(chars_col).cast("long") if chars_col else F.lit(None).cast("long")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), chars.alias("n_chars"))


def remainder(doc_id: Column, n: int) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % n


def fit(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, chars_col: str | None, label_col: str) -> FactorisationMachine:
    """From at most SAMPLE rows of labels, those with the smallest digests of their ids."""
    rows = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("y"))
    rows = rows.orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id", "y").limit(SAMPLE)

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in source:
            index, value, sizes, stats = features(b.column(1).to_pylist(), b.column(2).to_pylist())
            ends = pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32))
            columns = [b.column(0), b.column(3), pa.ListArray.from_arrays(ends, pa.array(index)), pa.ListArray.from_arrays(ends, pa.array(value)), pa.array(stats.tolist(), pa.list_(pa.float32()))]
            yield pa.record_batch(columns, ["doc_id", "y", "i", "x", "stats"])

    some = _prepared(docs, id_col, text_col, chars_col).join(F.broadcast(rows), "doc_id").select("doc_id", "text", "n_chars", "y")
    t = some.mapInArrow(run, "doc_id long, y int, i array<int>, x array<float>, stats array<float>").toArrow().combine_chunks()
    t = t.sort_by("doc_id")
    if not t.num_rows:
        return FactorisationMachine(np.zeros((len(STATS), BINS - 1), np.float32))
    flat = lambda c: t[c].combine_chunks().flatten().to_numpy(zero_copy_only=False)
    sizes = np.array([len(x) for x in t["i"]], np.int64)
    stats = flat("stats").reshape(-1, len(STATS))
    edges = np.quantile(stats, np.linspace(0, 1, BINS + 1)[1:-1], axis=0).T.astype(np.float32)
    for j in range(len(STATS)):  # the outer bins are for what few rows have
        edges[j, 0], edges[j, -1] = np.quantile(stats[:, j], [0.02, 0.98])
    edges.sort(axis=1)
    return FactorisationMachine(edges).fit(flat("i"), flat("x"), sizes, stats, t["y"].to_numpy().astype(np.float32))


def scores(model: FactorisationMachine, texts: pa.Array, n_chars: pa.Array) -> pa.Array:
    """What words a worker remembered goes with the batch."""
    try:
        found = [model.score(*features(t.to_pylist(), n.to_pylist())) for t, n in zip(parts(texts), parts(n_chars), strict=True)]
        return pa.array(np.concatenate(found) if found else np.zeros(0))
    finally:
        _words.clear()
        give_back()


def quality(
    docs: DataFrame,
    labels: DataFrame,
    folds: int = 5,
    held: int = 0,
    threshold: float = 0.3,
    id_col: str = "doc_id",
    text_col: str = "text",
    chars_col: str | None = "n_chars",
    label_col: str = "quality",
) -> DataFrame:
    """doc_id, held_out, score, predicted for each row of docs.

    Labels are learned only from ids whose crc32 modulo ``folds`` is not ``held``. Null texts count as empty
    and get a score; null labels are not used; rows with a null id are scored and not held out; repeated rows
    get the same score; without usable labels all scores are 0.5. An empty table gives an empty result; only
    text and n_chars (it may be null) enter a score, and no column but those named is read.
    """
    model = fit(docs, labels.where(remainder(F.col(id_col), folds) != held), id_col, text_col, chars_col, label_col)

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in source:
            yield pa.record_batch([b.column(0), scores(model, b.column(1), b.column(2))], ["doc_id", "score"])

    scored = _prepared(docs, id_col, text_col, chars_col).mapInArrow(run, "doc_id long, score double")
    return scored.select(
        "doc_id",
        F.coalesce(remainder(F.col("doc_id"), folds) == held, F.lit(False)).alias("held_out"),
        "score",
        (F.col("score") >= threshold).cast("int").alias("predicted"),
    )


def keep(
    docs: DataFrame,
    labels: DataFrame,
    folds: int = 5,
    held: int = 0,
    threshold: float = 0.3,
    id_col: str = "doc_id",
    text_col: str = "text",
    chars_col: str | None = "n_chars",
    label_col: str = "quality",
) -> DataFrame:
    """The rows of docs, with all their columns, whose score is at least the threshold; see quality(). Rows are scored
    where they are read, so nothing is shuffled, and only texts and n_chars go through Python. Rows with null ids are
    scored like others, repeated rows stay or go together, null texts are empty ones, an empty table gives an empty
    result; columns may have any other names."""
    model = fit(docs, labels.where(remainder(F.col(id_col), folds) != held), id_col, text_col, chars_col, label_col)

    def run(text: pa.Array, n_chars: pa.Array) -> pa.Array:
        return scores(model, text, n_chars)

    run.__annotations__ = {"text": pa.Array, "n_chars": pa.Array, "return": pa.Array}  # read by Spark, as types
    chars = F.col(chars_col).cast("long") if chars_col else F.lit(None).cast("long")
    score = F.arrow_udf(run, "double")(F.coalesce(F.col(text_col), F.lit("")), chars)
    return docs.where(score >= threshold)
