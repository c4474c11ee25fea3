"""The hybrid baseline: left anchors of low degree exactly by pivots, the dense rest by zigzags."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biclique_spark.functions.scalar import DRAW_BITS, EXACT, draw
from biclique_spark.operators import sampler, zigzag
from biclique_spark.operators.exact import count_edge_pivot
from biclique_spark.operators.graph import anchor_ranks, core_reduce
from biclique_spark.operators.index import broom_total, stored
from biclique_spark.plans import planner
from biclique_spark.sources.io import written


def split_dense_sparse(edges: DataFrame, cut: float = 0.5) -> tuple[DataFrame, DataFrame]:
    """(sparse, dense): left vertices (u) up to and above the degree at share ``cut`` of the left side. Each biclique
    belongs to its first left vertex in degree order, so the parts' counts add up to the whole."""
    d = anchor_ranks(edges).select("u", F.col("r.d").alias("d"))
    at = d.agg(F.percentile_approx("d", cut).alias("at")).first()["at"] or 0
    return d.where(F.col("d") <= at).select("u"), d.where(F.col("d") > at).select("u")


def dense_edges(edges: DataFrame, dense: DataFrame) -> DataFrame:
    """Edges of dense left vertices: later ones in degree order are dense too, so they hold all bicliques of dense anchors."""
    return edges.join(dense, "u", "left_semi")


def exact_parts(edges: DataFrame, p: int, q: int, cut: float = 0.5) -> DataFrame:
    """part, bicliques: both parts counted exactly; their sum is the whole."""
    core = core_reduce(edges, p, q)
    sparse, dense = split_dense_sparse(core, cut)
    one = count_edge_pivot(core, p, q, sparse, reduce=False).select(F.lit("sparse").alias("part"), "bicliques")
    two = count_edge_pivot(dense_edges(core, dense), p, q, reduce=False).select(F.lit("dense").alias("part"), "bicliques")
    return one.unionByName(two)


def estimate_hybrid(edges: DataFrame, p: int, q: int, t: int, cut: float = 0.5, seed: int = 1, basic: bool = False, weight: str = "double") -> DataFrame:
    """One row: sparse (exact), dense (estimated), estimate. ``basic``: the earlier form, whose samples are shared out
    among the paths' end edges by weight instead of being drawn from all paths at once."""
    core = core_reduce(edges, p, q)
    sparse, dense = split_dense_sparse(core, cut)
    exact = count_edge_pivot(core, p, q, sparse, reduce=False).select(F.col("bicliques").alias("sparse"))
    rest = written(dense_edges(core, dense), "dense")
    if basic:
        sampled = _stratified(rest, p, q, t, seed).select(F.col("estimate").alias("dense"))
    else:
        engine = planner.choose(planner.statistics(rest), min(p, q), min(p, q)).engine
        sampled = zigzag.estimate_zigzag(rest, p, q, t, seed, weight, reduce=False, engine=engine).select(F.col("estimate").alias("dense"))
    return exact.crossJoin(sampled).select(F.col("sparse").cast(EXACT), "dense", (F.col("sparse").cast("double") + F.col("dense")).alias("estimate"))


def _stratified(edges: DataFrame, p: int, q: int, t: int, seed: int) -> DataFrame:
    """Each end edge gets its share of the samples, rounded up or down by a draw, so there are about t whatever the
    number of edges; every sample stands for zigzags / t paths."""
    h = min(p, q)
    index = stored(zigzag.zigzag_index(edges, h))
    last = f"w{2 * h - 1}"
    total = broom_total(index, h, h)
    shares = index.where(F.col(last) > 0).crossJoin(total).select("u", "v", "cu", "cv", F.col(last).alias("w"), "brooms", (F.col(last) / F.col("brooms") * t).alias("due"))
    up = draw(seed, F.col("u"), F.col("v")) < (F.col("due") - F.floor("due")) * float(1 << DRAW_BITS)
    shares = shares.withColumn("n", F.floor("due") + up.cast("long")).where("n > 0")
    each = shares.withColumn("k", F.explode(F.sequence(F.lit(1).cast("long"), F.col("n"))))
    named = written(each.withColumn("sample_id", F.xxhash64("u", "v", "k")), "strata")
    walks = sampler.start(named)
    from biclique_spark.functions.pattern import broom_steps

    for layer in range(2 * h - 2, 0, -1):
        walks = sampler.walk_step(walks, index, edges, broom_steps(h, h)[layer - 1], layer, seed, free=True)
    walks = written(walks, "zigzags")
    x = zigzag.contributions(walks, edges, p, q).agg(F.coalesce(F.sum("x"), F.lit(0.0)).alias("x"))
    return x.crossJoin(total).select((F.col("x") * F.col("brooms") / t).alias("estimate"))  # one row each
