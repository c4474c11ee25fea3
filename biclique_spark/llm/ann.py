"""Nearest neighbours by shifted space-filling curves.

Each of CURVES orderings projects the vectors onto a few random orthogonal directions, shifts them and sorts
them along a Hilbert curve; Spark sorts by range partitions. Along a curve the rows are cut into windows of
WINDOW rows; a query meets the rows of its own window and of the two beside it, and is reranked there by the
exact inner product. The best of all curves are merged. Larger inner products become smaller distances by one
more coordinate, which lifts every vector to the largest norm.

Equal vectors are one point of a curve: it stands for the smallest identifiers of its vectors, as many as a
result can need, so a vector that a third of all rows share costs no more than another. Work and shuffle grow in
proportion to the rows and the curves.

With WINDOW and CURVES fixed, recall falls as isolated vectors get further apart in rank. So the exact answers of
SAMPLE queries are taken from all rows, and curves are added until recall() of these queries, less two standard
errors, is RECALL. Where so many curves would compare as much as all rows hold, queries meet all rows, in blocks.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from biclique_spark.llm.common import written

#: CURVES is where a search begins.
CURVES, WINDOW, AXES, BITS = 8, 4096, 6, 8
#: What a search must find; the queries that measure it; points and queries of a block where all are compared.
RECALL, SAMPLE, BLOCK, ASKED = 0.9, 200, 16_384, 4_096


def hilbert(points: np.ndarray, bits: int) -> np.ndarray:
    """The place along the Hilbert curve of whole-number points (rows) with ``bits`` bits an axis.

    Works from the highest bit down on all rows at once: each bit plane either swaps low bits with the first
    axis or flips them there; a Gray code over the axes and the interleaved bits then give the place.
    """
    x = points.astype(np.uint64).T.copy()
    axes, one = len(x), np.uint64(1)
    for level in range(bits - 1, 0, -1):
        bit, low = one << np.uint64(level), (one << np.uint64(level)) - one
        for i in range(axes):
            flip = (x[i] & bit) != 0
            swap = np.where(flip, np.uint64(0), (x[0] ^ x[i]) & low)
            x[0] ^= np.where(flip, low, swap)
            x[i] ^= swap
    for i in range(1, axes):
        x[i] ^= x[i - 1]
    turn = np.zeros_like(x[0])
    for level in range(bits - 1, 0, -1):
        turn ^= np.where((x[-1] >> np.uint64(level)) & one, (one << np.uint64(level)) - one, np.uint64(0))
    x ^= turn
    place = np.zeros_like(x[0])
    for level in range(bits - 1, -1, -1):
        for i in range(axes):
            place = (place << one) | ((x[i] >> np.uint64(level)) & one)
    return place.astype(np.int64)


def usable(vector: Column) -> Column:
    """No null, no component that is null or not finite, and some component other than 0."""
    fine = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return vector.isNotNull() & (F.size(vector) > 0) & F.coalesce(fine, F.lit(False)) & F.coalesce(F.exists(vector, lambda x: x != 0), F.lit(False))


def keys(points: DataFrame, dim: int, largest: float, spread: float, curves: range, seed: int) -> DataFrame:
    """(curve, place, id) of each point on the curves of these numbers: thin rows."""

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        axes = min(AXES, dim + 1)
        plans = []
        for c in curves:
            rng = np.random.default_rng([seed, c])
            plans.append((np.linalg.qr(rng.normal(size=(dim + 1, dim + 1)))[0][:, :axes], rng.uniform(-0.25, 0.25, axes)))
        for b in source:
            if not b.num_rows:
                continue
            v = b.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)
            v = np.hstack([v, np.sqrt(np.maximum(0, largest**2 - (v**2).sum(1)))[:, None]])
            for c, (directions, shift) in zip(curves, plans, strict=True):
                grid = np.floor(((v @ directions / spread + shift) / 6 + 0.5) * (1 << BITS))
                place = hilbert(np.clip(grid, 0, (1 << BITS) - 1), BITS)
                yield pa.record_batch([pa.array(np.full(len(v), c, np.int32)), pa.array(place), b.column(0)], ["curve", "place", "id"])

    return points.select("id", "vec").mapInArrow(run, "curve int, place long, id long")


def windows(placed: DataFrame, rows: int, window: int) -> DataFrame:
    """(curve, id, window): the rows of each curve in order, cut into windows. Ranks come from positions in the
    range partitions and the numbers of rows in those before (a row a partition and curve)."""
    parts = max(1, -(-rows // (8 * window)))
    ordered = placed.repartitionByRange(parts, "curve", "place", "id").sortWithinPartitions("curve", "place", "id")
    at = F.monotonically_increasing_id()
    at = ordered.select("curve", "id", F.shiftright(at, 33).alias("part"), at.bitwiseAND((1 << 33) - 1).alias("at"))
    ordered = written(at, "ann-order")
    counts = ordered.groupBy("curve", "part").agg(F.count(F.lit(1)).alias("n"), F.min("at").alias("first"))
    before = Window.partitionBy("curve").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("curve", "part", (F.coalesce(F.sum("n").over(before), F.lit(0)) - F.col("first")).alias("base"))
    return ordered.join(base, ["curve", "part"]).select("curve", "id", F.floor((F.col("base") + F.col("at")) / window).alias("window"))


def nearest(asking: np.ndarray, asked: np.ndarray, ids: np.ndarray, vectors: np.ndarray, most: int) -> pd.DataFrame:
    """point, near, score: for each of ``asking`` (with vectors ``asked``) the ``most`` best of ``ids``, which are sorted."""
    if not len(asking) or not len(ids):
        return pd.DataFrame({"point": np.empty(0, np.int64), "near": np.empty(0, np.int64), "score": np.empty(0)})
    points, near, scores = [], [], []
    for at in range(0, len(asking), 256):
        score = asked[at : at + 256] @ vectors.T
        if most < len(ids):  # ties at the last place: all of them, so that the smaller id can win
            top = np.argpartition(-score, most - 1, axis=1)[:, :most]
            where = np.nonzero(score >= np.take_along_axis(score, top, 1).min(1)[:, None])
        else:
            where = np.nonzero(np.ones_like(score, bool))
        points.append(asking[at + where[0]])
        near.append(ids[where[1]])
        scores.append(score[where])
    return foremost(pd.DataFrame({"point": np.concatenate(points), "near": np.concatenate(near), "score": np.concatenate(scores)}), most)


def foremost(found: pd.DataFrame, most: int) -> pd.DataFrame:
    return found.sort_values(["point", "score", "near"], ascending=[True, False, True]).groupby("point").head(most)


def best_of(found: DataFrame, most: int) -> DataFrame:
    """The ``most`` best (point, near, score) of each point."""
    order = Window.partitionBy("point").orderBy(F.desc("score"), "near")
    best = found.groupBy("point", "near").agg(F.max("score").alias("score"))
    return best.withColumn("nth", F.row_number().over(order)).where(F.col("nth") <= most).drop("nth")


def exact(points: DataFrame, dim: int, asking: DataFrame, most: int) -> DataFrame:
    """The best of all points for a few of them, ``asking``, which go to every task; a task keeps its best only."""
    few = asking.select("id", "vec").collect()
    ids, vectors = np.array([r.id for r in few], np.int64), np.array([r.vec for r in few]).reshape(len(few), dim)

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = nearest(ids, vectors, ids[:0], vectors[:0], most)
        for b in source:
            if not b.num_rows:
                continue
            at, v = b.column(0).to_numpy(), b.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)
            order = np.argsort(at)
            kept = foremost(pd.concat([kept, nearest(ids, vectors, at[order], v[order], most)]), most)
        yield pa.RecordBatch.from_pandas(kept, pa.schema([("point", pa.int64()), ("near", pa.int64()), ("score", pa.float64())]), preserve_index=False)

    return best_of(points.select("id", "vec").mapInArrow(run, "point long, near long, score double"), most)


def recall(got: DataFrame, want: DataFrame) -> tuple[float, float]:
    """The share of wanted (query_id, vec_id) that were got, as a mean of the queries, and its standard error."""
    hits = want.select("query_id", "vec_id").join(got.select("query_id", "vec_id", F.lit(1.0).alias("hit")), ["query_id", "vec_id"], "left")
    shares = hits.groupBy("query_id").agg(F.avg(F.coalesce("hit", F.lit(0.0))).alias("share"))
    mean, error = shares.agg(F.avg("share"), F.stddev_samp("share") / F.sqrt(F.count(F.lit(1)))).first()
    return (1.0, 0.0) if mean is None else (mean, error or 0.0)


def search(
    vectors: DataFrame,
    is_query: Column,
    k: int = 20,
    curves: int = CURVES,
    window: int = WINDOW,
    seed: int = 29,
    id_col: str = "vec_id",
    vec_col: str = "embedding",
    least: float = RECALL,
) -> DataFrame:
    """query_id, rank, vec_id, score: for each query row its k nearest found, by inner product in double precision.

    ``is_query`` is a condition on the identifier column. A query's own row is no candidate. Ties go to the
    smaller id. Vectors null, zero or holding null or non-finite components take no part, nor do rows without
    an id; vectors of different lengths are searched apart. Repeated rows (same id and vector) are one row. With
    fewer than k candidates all are returned; an empty table gives an empty result; other columns are not read.
    ``curves`` is the number to begin with: more are added until a sample of queries finds ``least`` of its neighbours.
    """
    spark = vectors.sparkSession
    rows = vectors.where(F.col(id_col).isNotNull() & usable(F.col(vec_col))).select(
        F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("vec"), is_query.alias("asks")
    )
    rows = written(rows.dropDuplicates(["id", "vec"]), "ann-rows")
    out = None
    for dim, largest, n in rows.groupBy(F.size("vec").alias("dim")).agg(
        F.max(_norm2()), F.count(F.lit(1))
    ).collect():  # a row for each length of vectors
        found = _search(rows.where(F.size("vec") == dim), dim, float(largest) ** 0.5, (float(largest) / (dim + 1)) ** 0.5, n, k, curves, window, seed, least)
        out = found if out is None else out.unionByName(found)
    return out if out is not None else spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")


def _norm2() -> Column:
    return F.aggregate("vec", F.lit(0.0), lambda a, x: a + x * x)


def _search(rows: DataFrame, dim: int, largest: float, spread: float, n: int, k: int, curves: int, window: int, seed: int, least: float) -> DataFrame:
    # The k + 1 smallest ids of each vector: one may be the query's own. Spark limits the window's groups before it shuffles.
    nth = F.row_number().over(Window.partitionBy("vec").orderBy("id"))
    first = rows.withColumn("nth", nth).where(F.col("nth") <= k + 1)
    named = first.groupBy("vec").agg(F.min("id").alias("id"), F.sort_array(F.collect_list("id")).alias("ids"))
    points = written(named, "ann-points")
    asked = written(
        rows.where("asks").select(F.col("id").alias("query_id"), "vec").join(points.select("vec", F.col("id").alias("point")), "vec").select("query_id", "point"),
        "ann-queries",
    )
    # A point is asked once for all queries with its vector.
    asking = points.join(asked.select(F.col("point").alias("id")).distinct(), "id", "left_semi")
    held, queries = points.count(), asked.count()
    measured = held > window  # else one window holds all
    if measured:
        sample = written(asked.orderBy(F.md5(F.col("query_id").cast("string")), "query_id", "point").limit(SAMPLE), "ann-sample")
        few = points.join(sample.select(F.col("point").alias("id")).distinct(), "id", "left_semi")
        want = written(_answers(exact(points, dim, few, k + 1), points, sample, k), "ann-exact")

    def rerank(group: pd.DataFrame) -> pd.DataFrame:
        q, c = group[group.asks], group[~group.asks].sort_values("id")
        if not len(q) or not len(c):
            return pd.DataFrame({"point": [], "near": [], "score": []})
        return nearest(q.id.to_numpy(), np.stack(q.vec.to_numpy()), c.id.to_numpy(), np.stack(c.vec.to_numpy()), k + 1)

    def along(numbers: range) -> DataFrame:
        cut = written(windows(keys(points, dim, largest, spread, numbers, seed), n * len(numbers), window), "ann-windows")
        near = lambda of, offsets: (
            of.select("id", "vec").join(cut, "id").withColumn("window", F.explode(F.array(*[F.col("window") + o for o in offsets])))
        )
        both = near(points, (0,)).withColumn("asks", F.lit(False)).unionByName(near(asking, (-1, 0, 1)).withColumn("asks", F.lit(True)))
        return both.groupBy("curve", "window").applyInPandas(rerank, "point long, near long, score double")

    def throughout() -> DataFrame:
        blocks = {"held": -(-held // BLOCK), "asked": -(-queries // ASKED)}
        dealt = lambda of, mine, other: (
            of.select("id", "vec", F.pmod(F.xxhash64("id"), F.lit(blocks[mine])).alias(mine), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks[other] - 1).cast("long"))).alias(other))
        )
        both = dealt(points, "held", "asked").withColumn("asks", F.lit(False)).unionByName(dealt(asking, "asked", "held").withColumn("asks", F.lit(True)))
        return both.groupBy("asked", "held").applyInPandas(rerank, "point long, near long, score double")

    best, done = written(best_of(along(range(curves)), k + 1), "ann-best"), curves
    while measured:
        share, error = recall(_answers(best, points, sample, k), want)
        error = 2 * error if queries > SAMPLE else 0.0
        if share - error >= least:
            break
        # Curves miss a neighbour independently of each other, more or less.
        goal, share = min(0.99, least + error + 0.01), min(max(share, 0.01), 0.98)
        need = max(done + -(-done // 4), math.ceil(done * math.log(1 - goal) / math.log(1 - share)))
        measured = need * 3 * window < held
        more = along(range(done, need)) if measured else throughout()
        best, done = written(best_of(best.unionByName(more), k + 1), "ann-best"), need
    return _answers(best, points, asked, k)


def _answers(best: DataFrame, points: DataFrame, asked: DataFrame, k: int) -> DataFrame:
    members = best.join(points.select(F.col("id").alias("near"), "ids"), "near").select("point", "score", F.explode("ids").alias("vec_id"))
    order = Window.partitionBy("point").orderBy(F.desc("score"), "vec_id")
    members = members.withColumn("nth", F.row_number().over(order)).where(F.col("nth") <= k + 1)
    answers = asked.join(members, "point").where("query_id != vec_id")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = answers.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def brute_force(vectors: np.ndarray, ids: np.ndarray, queries: np.ndarray, k: int = 20) -> dict[int, list[int]]:
    """The exact answer for a small table: a list of ids for each query id."""
    place = {int(i): j for j, i in enumerate(ids)}
    out = {}
    for q in queries:
        score = vectors @ vectors[place[int(q)]]
        order = [int(ids[j]) for j in np.lexsort((ids, -score)) if ids[j] != q]
        out[int(q)] = order[:k]
    return out
