"""The zigzag estimator: paths that alternate sides, by key order; a path's vertices must induce a complete graph."""

from __future__ import annotations

from math import comb

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biclique_spark.functions.scalar import binomial
from biclique_spark.operators import sampler, twins
from biclique_spark.operators.graph import core_reduce
from biclique_spark.operators.index import broom_index, broom_total, colored_by_key, stored
from biclique_spark.sources.io import written


def zigzag_index(edges: DataFrame, h: int, weight: str = "double") -> DataFrame:
    """Paths of 2h - 1 edges with growing keys on both sides: the (h,h)-brooms under key ranks."""
    return broom_index(colored_by_key(edges), h, h, weight)


def zigzag_total(edges: DataFrame, h: int, weight: str = "double") -> DataFrame:
    return broom_total(zigzag_index(edges, h, weight), h, h).select(F.col("brooms").alias("zigzags"))


def contributions(walks: DataFrame, edges: DataFrame, p: int, q: int) -> DataFrame:
    """sample_id, x: what a complete path adds. Its h vertices on the smaller side have n common neighbours, h of them
    on the path; the other side is filled up from the rest, and each biclique holds comb(max, h) paths."""
    h = min(p, q)
    full = walks.join(sampler.complete(walks, edges), "sample_id", "left_semi")
    chosen, side = ("us", "u") if p <= q else ("vs", "v")
    other = "v" if side == "u" else "u"
    members = full.select("sample_id", F.explode(chosen).alias(side)).join(edges.select("u", "v"), side)
    n = members.groupBy("sample_id", other).agg(F.count(F.lit(1)).alias("m")).where(F.col("m") == h).groupBy("sample_id").agg(F.count(F.lit(1)).alias("n"))
    most = max(p, q)
    return n.select("sample_id", (binomial(F.col("n") - h, most - h) / F.lit(float(comb(most, h)))).alias("x"))


def estimate_zigzag(edges: DataFrame, p: int, q: int, t: int, seed: int = 1, weight: str = "double", reduce: bool = True, engine: str = "join", first: int = 0) -> DataFrame:
    """One row: zigzags, t, hits, largest, estimate, std_error."""
    h = min(p, q)
    edges = core_reduce(edges, p, q) if reduce else edges
    index = stored(zigzag_index(edges, h, weight))
    walks = written(sampler.sample_walks(index, edges, h, h, t, seed, free=True, engine=engine, first=first), "zigzags")
    x = contributions(walks, edges, p, q)
    sums = x.agg(F.count(F.lit(1)).alias("hits"), F.coalesce(F.sum("x"), F.lit(0.0)).alias("s"), F.coalesce(F.sum(F.col("x") ** 2), F.lit(0.0)).alias("s2"), F.coalesce(F.max("x"), F.lit(0.0)).alias("largest"))
    z = broom_total(index, h, h).select(F.col("brooms").alias("zigzags"))
    mean = F.col("s") / t
    spread = F.sqrt(F.greatest(F.lit(0.0), F.col("s2") / t - mean * mean) / t)
    zd = F.col("zigzags").cast("double")
    return z.crossJoin(sums).select("zigzags", F.lit(t).cast("long").alias("t"), "hits", "largest", (zd * mean).alias("estimate"), (zd * spread).alias("std_error"))


def enumerate_zigzags(edges: DataFrame, p: int, q: int) -> DataFrame:
    """The largest contribution of one path over all paths (for tiny graphs): h vertices of the smaller side."""
    h = min(p, q)
    t = twins.twins(edges)
    tuples = twins.class_tuples(t if p <= q else t.turned(), h, max(p, q)).where(twins.ways(F.col("us"), h) > 0)
    return tuples.agg(F.coalesce(F.max(binomial(F.col("w") - h, max(p, q) - h)), F.lit(0.0)).alias("largest")).select((F.col("largest") / F.lit(float(comb(max(p, q), h)))).alias("largest"))
