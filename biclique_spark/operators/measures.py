"""Measures of accuracy, cost and structure."""

from __future__ import annotations

import time
from collections.abc import Callable
from math import comb

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biclique_spark.functions.scalar import EXACT, binomial, relative_error
from biclique_spark.operators import coloring, exact, hybrid, twins, zigzag
from biclique_spark.operators.graph import core_reduce, split_by_anchor
from biclique_spark.operators.index import broom_index, broom_total, colored_by_key
from biclique_spark.plans import planner
from biclique_spark.sources.io import written


def mean_error(runs: DataFrame, truth: float | None = None) -> DataFrame:
    """One row: runs, truth, mean_error, spread. Without an exact count the runs' mean stands for it."""
    of = runs.agg(F.avg("estimate").alias("mean"))
    known = runs.crossJoin(of).withColumn("truth", F.lit(truth) if truth is not None else F.col("mean"))
    return known.agg(F.count(F.lit(1)).alias("runs"), F.first("truth").alias("truth"), F.avg(relative_error(F.col("estimate"), F.col("truth"))).alias("mean_error"), F.stddev_samp("estimate").alias("spread"))


def heat_map(grid: DataFrame, value: str) -> DataFrame:
    """p down, q across."""
    return grid.groupBy("p").pivot("q").agg(F.first(value)).orderBy("p")


def margins(grid: DataFrame, value: str, how: str = "cube") -> DataFrame:
    """Means of a grid's cells over all of p, of q and of both; null stands for all."""
    return getattr(grid, how)("p", "q").agg(F.avg(value).alias(value), F.count(F.lit(1)).alias("cells"))


def stage_times(stages: list[tuple[str, Callable[[], object]]]) -> list[tuple[str, float]]:
    """Seconds of each stage, in order."""
    out = []
    for name, run in stages:
        began = time.time()
        run()
        out.append((name, time.time() - began))
    return out


def sample_ratio_broom(brooms: float, count: float) -> float | None:
    return (brooms / count) ** 2 if count else None


def sample_ratio_zigzag(zigzags: float, count: float, largest: float, p: int, q: int, rho: str = "range") -> float | None:
    """Z^2 / rho^2. rho: the count over the largest contribution of one path ('range': then the sample bound has the
    same form as for brooms), or the number of complete paths ('paths')."""
    if not count:
        return None
    r = count / largest if rho == "range" else count * comb(max(p, q), min(p, q))
    return (zigzags / r) ** 2


def colored(edges: DataFrame, p: int, q: int, strategy: str | None, seed: int = 1) -> DataFrame:
    """Colored edges by a strategy of coloring, 'none' for key order, None for the planner's choice by size."""
    strategy = strategy or planner.choose(planner.statistics(edges), p, q).strategy
    return colored_by_key(edges) if strategy == "none" else coloring.color_graph(edges, p, q, "random", seed, strategy)


def sample_ratios(edges: DataFrame, sizes: list[tuple[int, int]], strategy: str | None = None) -> DataFrame:
    """p, q, bicliques, brooms, zigzags, largest, kappa, broom_ratio, zigzag_ratio: brooms of the colored graph,
    zigzags in key order, as the baseline has them."""
    rows = []
    for p, q in sizes:
        core = core_reduce(edges, p, q)
        c = float(exact.count_vertex_expand(core, p, q, reduce=False).first()[0])
        tinted = written(colored(core, p, q, strategy), "colored")
        b = float(broom_total(broom_index(tinted, p, q), p, q).first()[0])
        z = float(zigzag.zigzag_total(core, min(p, q)).first()[0])
        m = float(zigzag.enumerate_zigzags(core, p, q).first()[0])
        rows.append((p, q, c, b, z, m, coloring.color_count(tinted).first()["kappa"], sample_ratio_broom(b, c), sample_ratio_zigzag(z, c, m, p, q)))
    return edges.sparkSession.createDataFrame(rows, "p int, q int, bicliques double, brooms double, zigzags double, largest double, kappa long, broom_ratio double, zigzag_ratio double")


def color_counts(edges: DataFrame, sizes: list[tuple[int, int]], strategy: str | None = None) -> DataFrame:
    """p, q, kappa: colors of the larger side for each size."""
    rows = []
    for p, q in sizes:
        rows.append((p, q, coloring.color_count(colored(core_reduce(edges, p, q), p, q, strategy)).first()["kappa"]))
    return edges.sparkSession.createDataFrame(rows, "p int, q int, kappa long")


def held_bytes(df: DataFrame) -> tuple[int, int]:
    """Rows of a table, and the bytes that its blocks take in the executors' storage once it is cached."""
    df = df.cache()
    try:
        rows = df.count()
        return rows, int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    finally:
        df.unpersist(blocking=True)


def memory_profile(edges: DataFrame, p: int, q: int, methods: tuple[str, ...] = ("vertex_expand", "edge_pivot", "hybrid", "broom"), strategy: str | None = None) -> DataFrame:
    """method, held, rows, bytes: the largest tables that each method keeps in the executors: the broom's index, the
    hybrid's path index and sparse parts, the pivot's anchor parts (wedges), the expansion's last but one tuples."""
    core = core_reduce(edges, p, q)
    h = min(p, q)
    tables = {
        "broom": ("index", lambda: [broom_index(colored(core, p, q, strategy), p, q)]),
        "hybrid": ("path index, sparse parts", lambda: [zigzag.zigzag_index(core, h), split_by_anchor(core, p, q, anchors=hybrid.split_dense_sparse(core)[0])]),
        "edge_pivot": ("parts", lambda: [split_by_anchor(core, p, q)]),
        "vertex_expand": ("tuples", lambda: [exact.grow_left(core, max(1, p - 1), q)]),
    }
    rows = []
    for m in methods:
        held, of = tables[m]
        found = [held_bytes(t) for t in of()]
        rows.append((m, held, sum(n for n, _ in found), sum(b for _, b in found)))
    return edges.sparkSession.createDataFrame(rows, "method string, held string, rows long, bytes long")


def speedup(times: DataFrame, base: str) -> DataFrame:
    """graph, method, factor: seconds of every other method over those of ``base``; times(graph, method, seconds)."""
    b = times.where(F.col("method") == base).select("graph", F.col("seconds").alias("own"))
    return times.where(F.col("method") != base).join(b, "graph").select("graph", "method", (F.col("seconds") / F.col("own")).alias("factor"))


def error_reduction(errors: DataFrame, base: str) -> DataFrame:
    """graph, method, factor: the mean error of every other method over that of ``base``, null where that is 0;
    errors(graph, method, mean_error)."""
    return speedup(errors.withColumn("seconds", F.when((F.col("method") != base) | (F.col("mean_error") > 0), F.col("mean_error"))), base)


def samples_to_error(history: DataFrame, target: float) -> DataFrame:
    """method, t: the fewest samples whose mean error is within the target; history(method, t, mean_error)."""
    return history.where(F.col("mean_error") <= target).groupBy("method").agg(F.min("t").alias("t"))


def success_rate(walks: DataFrame, t: int) -> DataFrame:
    return walks.agg((F.count(F.lit(1)) / t).alias("success_rate"))


def clustering_coefficient(edges: DataFrame, p: int, q: int) -> DataFrame:
    """One row: bicliques, wedges, coefficient. A wedge is a (p-1,q)-biclique with one more edge from one of its right
    vertices to a left vertex outside; each (p,q)-biclique holds p q of them."""
    n = exact.count_vertex_expand(edges, p, q)
    degree = edges.groupBy("v").agg(F.count(F.lit(1)).alias("d"))
    if p == 2:
        stars = edges.groupBy("u").agg(F.count(F.lit(1)).alias("k"))
        # A right vertex of a (1,q)-star: in comb(k-1, q-1) of them.
        wide = edges.join(stars, "u").join(degree, "v").select((binomial(F.col("k") - 1, q - 1) * (F.col("d") - 1)).alias("w"))
    else:
        t = exact.grow_left(edges, p - 1, q).select("us", F.size("vs").alias("k"), F.explode("vs").alias("v")).join(degree, "v")
        wide = t.select((binomial(F.col("k") - 1, q - 1) * (F.col("d") - p + 1)).alias("w"))
    w = wide.agg(F.coalesce(F.sum("w"), F.lit(0.0)).alias("wedges"))
    return n.crossJoin(w).select("bicliques", "wedges", F.when(F.col("wedges") > 0, p * q * F.col("bicliques").cast("double") / F.col("wedges")).otherwise(0.0).alias("coefficient"))


def motif_profile(edges: DataFrame, sizes: list[tuple[int, int]], estimates: DataFrame | None = None) -> DataFrame:
    """p, q, value: log(1 + count) of each size, exact, or from estimates(p, q, estimate)."""
    if estimates is not None:
        return estimates.select("p", "q", F.log1p("estimate").alias("value"))
    out = None
    for p, q in sizes:
        one = exact.count_vertex_expand(edges, p, q).select(F.lit(p).alias("p"), F.lit(q).alias("q"), F.log1p(F.col("bicliques").cast("double")).alias("value"))
        out = one if out is None else out.unionByName(one)
    return out


def motif_kernel(profiles: DataFrame) -> DataFrame:
    """a, b, similarity: cosine of the profiles of graphs; profiles(graph, p, q, value)."""
    a = profiles.select(F.col("graph").alias("a"), "p", "q", F.col("value").alias("x"))
    b = profiles.select(F.col("graph").alias("b"), "p", "q", F.col("value").alias("y"))
    dots = a.join(b, ["p", "q"]).where("a <= b").groupBy("a", "b").agg(F.sum(F.col("x") * F.col("y")).alias("xy"))
    norm = dots.where("a = b").select(F.col("a").alias("g"), F.sqrt("xy").alias("n"))
    out = dots.join(norm.select(F.col("g").alias("a"), F.col("n").alias("na")), "a").join(norm.select(F.col("g").alias("b"), F.col("n").alias("nb")), "b")
    return out.select("a", "b", F.when(F.col("na") * F.col("nb") > 0, F.col("xy") / (F.col("na") * F.col("nb"))).otherwise(0.0).alias("similarity"))


def biclique_density(edges: DataFrame, p: int, q: int) -> DataFrame:
    """One row: bicliques, vertices, density."""
    n = edges.agg((F.count_distinct("u") + F.count_distinct("v")).alias("vertices"))
    return exact.count_vertex_expand(edges, p, q).crossJoin(n).select("bicliques", "vertices", F.when(F.col("vertices") > 0, F.col("bicliques").cast("double") / F.col("vertices")).otherwise(0.0).alias("density"))


def participation(edges: DataFrame, p: int, q: int, side: str = "u") -> DataFrame:
    """(vertex, bicliques): in how many each vertex of a side is."""
    return twins.participation(core_reduce(edges, p, q), p, q, side)


def estimated_participation(walks: DataFrame, total: float, t: int, side: str = "u") -> DataFrame:
    """(vertex, bicliques) from walk members: each finished walk stands for brooms * ratio / t bicliques."""
    rows = walks.select(F.explode("us" if side == "u" else "vs").alias("vertex"), "ratio")
    return rows.groupBy("vertex").agg((F.sum("ratio") * total / t).alias("bicliques"))
