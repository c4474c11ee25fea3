import random

import numpy as np
from pyspark.sql import functions as F

from biclique_spark.llm import ann, mixing
from tests.llm.helpers import WORD, docs


def water(sizes, weights):
    """Targets by resharing the excess until no source is above three times its size."""
    total, target, full = sum(sizes), [0.0] * len(sizes), set()
    while True:
        open_ = [i for i in range(len(sizes)) if i not in full]
        left = total - sum(target[i] for i in full)
        for i in open_:
            target[i] = left * weights[i] / sum(weights[j] for j in open_)
        over = [i for i in open_ if target[i] > 3 * sizes[i] + 1e-9]
        if not over:
            return target
        for i in over:
            target[i] = 3.0 * sizes[i]
            full.add(i)


def test_mix(spark):
    rng = random.Random(8)
    texts, sources = [], []
    for s, n in (("b", 600), ("a", 60), (None, 100), ("é", 40), ("Z", 5)):
        for _ in range(n):
            texts.append(rng.choice([None, "", " \t"]) if rng.random() < 0.05 else "w " * rng.randrange(1, 200))
            sources.append(s)
    texts.append("long " * 20_000)
    sources.append("a")
    d = docs(spark, texts, sources)
    got = mixing.taken(d).collect()
    assert len(got) == len(texts)
    order = sorted({s for s in sources if s is not None}) + [None]
    size = {s: sum(len(WORD.findall(t or "")) for t, x in zip(texts, sources) if x == s) for s in order}
    target = dict(zip(order, water([size[s] for s in order], [1, 2, 3, 1, 2])))
    used = dict.fromkeys(order, 0)
    for r in got:
        s = sources[r.doc_id]
        assert r.size == len(WORD.findall(texts[r.doc_id] or "")) and r.source_size == size[s]
        assert abs(r.target - target[s]) < 1e-3 and 0 <= r.taken <= 3 * r.size
        used[s] += r.taken
    for s in order:
        assert abs(used[s] - target[s]) <= max(0.02 * target[s], 200), (s, used[s], target[s])
    again = {r.doc_id: r.taken for r in mixing.taken(d.repartition(7)).collect()}
    assert again == {r.doc_id: r.taken for r in got}


def test_mix_plan(spark):
    d = docs(spark, ["x " * 300, "y " * 500, "z " * 40, "v"], ["a", "b", "b", "c"])
    m = mixing.mix(d, length=16, shard_slots=8)
    counts = m.shard_counts.groupBy("shard").agg(F.sum("n_slots").alias("n")).orderBy("shard").collect()
    assert all(r.n <= 8 for r in counts) and sum(r.n for r in counts) >= 8 * (len(counts) - 1) - 2  # a capped source's slots end
    held = {(r.shard, r.source_key): r["count"] for r in m.slots.groupBy("shard", "source_key").count().collect()}
    assert held == {(r.shard, r.source_key): r.n_slots for r in m.shard_counts.collect()}
    assert sum(n for (_, s), n in held.items() if s == "=c") <= 3
    for s in ("=a", "=b"):
        blocks = [r.block for r in m.slots.where(F.col("source_key") == s).orderBy("rank").collect()]
        n = -(-{"=a": 300, "=b": 540}[s] // 16)
        for k in range(0, len(blocks), n):
            assert len(set(blocks[k : k + n])) == len(blocks[k : k + n]) and max(blocks) < n
    words = {(r.source_key, r.block): len(r.text.split()) for r in mixing.block_texts(d, m).collect()}
    assert sum(words.values()) == 841 and max(words.values()) == 16
    assert mixing.mixed_texts(d, length=16, shard_slots=8).count() == m.slots.count()
    plan = mixing.taken(d)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_mix_edges(spark):
    assert not mixing.taken(docs(spark, ["a"]).limit(0)).collect()
    rows = mixing.taken(docs(spark, [None, "", "a b"], [None, "q", "q"], ids=[None, 1, None])).collect()
    assert sorted((r.size, r.source_size) for r in rows) == [(0, 0), (0, 2), (2, 2)]
    twice = mixing.taken(docs(spark, ["a b", "a b"], ids=[1, 1])).collect()
    assert len(twice) == 2 and all(r.size == 2 for r in twice)
    mixed = mixing.mixed_documents(docs(spark, ["a b c d"] * 50, ["s"] * 50))
    assert mixed.columns == docs(spark, ["a"]).columns and mixed.count() == 50


def test_hilbert_visits_neighbours():
    side = 8
    points = np.array([(x, y, z) for x in range(side) for y in range(side) for z in range(side)])
    place = ann.hilbert(points, 3)
    assert sorted(place) == list(range(side**3))
    path = points[np.argsort(place)]
    assert (np.abs(np.diff(path, axis=0)).sum(1) == 1).all()


VECTORS = "vec_id long, embedding array<float>, label int, point long, window int"


def table(spark, vectors, ids=None):
    rows = [(i, v, 0, 1, 2) for i, v in zip(ids or range(len(vectors)), vectors)]
    return spark.createDataFrame(rows, VECTORS)


def test_search_against_brute_force(spark):
    rng = np.random.default_rng(9)
    v = np.vstack([rng.normal(size=(600, 12)) * rng.uniform(0.5, 2, (600, 1)), np.tile(6 * rng.normal(size=12), (200, 1))]).astype(np.float32)
    got = ann.search(table(spark, v.tolist()), F.col("vec_id") % 20 == 0, k=10, window=64).collect()
    want = ann.brute_force(v.astype(float), np.arange(800), np.arange(0, 800, 20), 10)
    lists = {}
    for r in sorted(got, key=lambda r: (r.query_id, r["rank"])):
        lists.setdefault(r.query_id, []).append(r.vec_id)
        assert abs(r.score - float(v[r.query_id].astype(float) @ v[r.vec_id].astype(float))) < 1e-9
    assert set(lists) == set(want) and all(len(x) == 10 for x in lists.values())
    recall = np.mean([len(set(lists[q]) & set(want[q])) / 10 for q in want])
    assert recall >= 0.9, recall
    same = [q for q in want if q >= 600]
    assert all(lists[q] == [i for i in range(600, 612) if i != q][:10] for q in same)


def test_search_edges(spark):
    nan, inf = float("nan"), float("inf")
    rows = [[1.0, 0.0], None, [], [0.0, 0.0], [nan, 1.0], [inf, 1.0], [None, 1.0], [0.5, 0.5], [1.0, 2.0, 3.0], [2.0, 0.0], [2.0, 0.0]]
    got = ann.search(table(spark, rows), F.lit(True), k=20).collect()
    pairs = {(r.query_id, r.vec_id) for r in got}
    assert pairs == {(a, b) for a in (0, 7, 9, 10) for b in (0, 7, 9, 10) if a != b}
    assert [r.vec_id for r in sorted(got, key=lambda r: r["rank"]) if r.query_id == 0] == [9, 10, 7]
    assert not ann.search(table(spark, rows).limit(0), F.lit(True)).collect()
    twice = ann.search(table(spark, [[1.0, 0.0], [1.0, 0.0], [3.0, 1.0]], [1, 1, 2]), F.col("vec_id") == 1).collect()
    assert [(r.query_id, r.vec_id, r.score) for r in twice] == [(1, 2, 3.0)]


def test_search_adds_curves_for_isolated_vectors(spark):
    v = np.random.default_rng(3).normal(size=(6000, 32))
    v = (v / np.linalg.norm(v, axis=1, keepdims=True)).astype(np.float32)
    want = ann.brute_force(v.astype(float), np.arange(6000), np.arange(0, 6000, 20))
    wanted = spark.createDataFrame([(q, i) for q, ids in want.items() for i in ids], "query_id long, vec_id long")
    for window in (64, 256):
        got = ann.search(table(spark, v.tolist()), F.col("vec_id") % 20 == 0, curves=2, window=window)
        share, _ = ann.recall(got, wanted)
        assert share >= 0.9, (window, share)
