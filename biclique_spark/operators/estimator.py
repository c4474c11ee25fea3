"""The broom estimator from edges to an estimate, and its variants."""

from __future__ import annotations

import time
from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biclique_spark.functions.pattern import broom_steps
from biclique_spark.operators import coloring, sampler
from biclique_spark.operators.graph import core_reduce, split_by_anchor, transpose
from biclique_spark.operators.index import broom_index, broom_total, colored_by_key, stored
from biclique_spark.operators.twins import growth
from biclique_spark.plans import planner
from biclique_spark.sources.io import released, written

DEFAULT_T = 100_000


def summarize(walks: DataFrame, total: DataFrame, p: int, q: int, t: int) -> DataFrame:
    """One row: p, q, t, brooms, hits, mean_ratio, estimate, std_error, ci_low, ci_high. Walks that ended early are
    samples of 0; with no brooms the estimate is 0."""
    sums = walks.agg(F.count(F.lit(1)).alias("hits"), F.coalesce(F.sum("ratio"), F.lit(0.0)).alias("s"), F.coalesce(F.sum(F.col("ratio") ** 2), F.lit(0.0)).alias("s2"))
    b = F.col("brooms").cast("double")
    mean = F.col("s") / t
    deviation = F.sqrt(F.greatest(F.lit(0.0), F.col("s2") / t - mean * mean) / t)
    rows = total.crossJoin(sums)  # one row each
    return rows.select(
        F.lit(p).alias("p"), F.lit(q).alias("q"), F.lit(t).cast("long").alias("t"), "brooms", "hits", mean.alias("mean_ratio"),
        (b * mean).alias("estimate"), (b * deviation).alias("std_error"),
        F.greatest(F.lit(0.0), b * (mean - 1.96 * deviation)).alias("ci_low"), (b * (mean + 1.96 * deviation)).alias("ci_high"),
    )


def prepared(edges: DataFrame, p: int, q: int, reduce: str = "core", strategy: str | None = None, order: str = "random", seed: int = 1, weight: str = "double", relabel: int = 1):
    """(edges after reduction, index, choice): everything that samples share."""
    if reduce in ("core", "both"):
        edges = core_reduce(edges, p, q)
    choice = planner.choose(planner.statistics(edges), p, q, weight=weight)
    strategy = strategy or choice.strategy
    if strategy == "none":
        colored = colored_by_key(edges)
    else:
        colored = coloring.color_graph(edges, p, q, order, seed, strategy, relabel)
    return edges, stored(broom_index(colored, p, q, weight, choice.blocks)), choice


def estimate(
    edges: DataFrame, p: int, q: int, t: int = DEFAULT_T, seed: int = 1, order: str = "random", strategy: str | None = None,
    reduce: str = "core", weight: str = "double", engine: str | None = None, contain: str | None = None, relabel: int = 1,
) -> DataFrame:
    """One row, see summarize(), with kappa_u and kappa_v.

    strategy: None (by size), 'none', 'greedy', 'rounds' or 'conflict'. reduce: 'core', 'none', 'split' (the query
    becomes (p-1,q) on each left vertex's part) or 'both'.
    """
    if reduce in ("split", "both") and p > 2:
        return estimate_split(core_reduce(edges, p, q) if reduce == "both" else edges, p, q, t, seed, strategy or "none")
    reduced, index, choice = prepared(edges, p, q, reduce, strategy, order, seed, weight, relabel)
    walks = sampler.sample_walks(index, reduced, p, q, t, seed, contain or choice.contain, engine or choice.engine, meet=choice.meet)
    kappa = index.agg(F.count_distinct("cu").alias("kappa_u"), F.count_distinct("cv").alias("kappa_v"))
    return summarize(walks, broom_total(index, p, q), p, q, t).crossJoin(kappa)


def estimate_split(edges: DataFrame, p: int, q: int, t: int, seed: int = 1, strategy: str = "none") -> DataFrame:
    """Through the parts of left anchors: vertices of all parts are named (anchor, vertex), so that one index counts
    the (p-1,q)-brooms of all of them. Where right vertices have fewer wedges, they are the anchors."""
    left, right = growth(edges, 2, 2)
    turned = q > 2 and right < left
    a, b = (q, p) if turned else (p, q)
    parts = split_by_anchor(transpose(edges) if turned else edges, a, b)
    one = parts.select(F.struct("anchor", "u").alias("u"), F.struct("anchor", "v").alias("v"))
    out = estimate(one, a - 1, b, t, seed, strategy=strategy, engine="join")
    if turned:
        out = out.withColumns({"kappa_u": F.col("kappa_v"), "kappa_v": F.col("kappa_u")})
    return out.withColumns({"p": F.lit(p), "q": F.lit(q)})


def estimate_auto(edges: DataFrame, p: int, q: int, t: int = DEFAULT_T, seed: int = 1) -> DataFrame:
    """estimate() in the orientation with fewer shuffles."""
    edges = written(edges, "graph")
    released(edges.sparkSession)
    if planner.fewer_turned(p, q):
        return estimate(transpose(edges), q, p, t, seed).withColumns({"p": F.lit(p), "q": F.lit(q)})
    return estimate(edges, p, q, t, seed)


def estimate_repeated(edges: DataFrame, p: int, q: int, t: int, runs: int = 10, seed: int = 1, **options) -> DataFrame:
    """run, t, estimate: independent runs on one index. All walks are drawn in one job; a run is a range of samples."""
    reduced, index, choice = prepared(edges, p, q, seed=seed, **options)
    walks = sampler.sample_walks(index, reduced, p, q, t * runs, seed, choice.contain, choice.engine, meet=choice.meet)
    per = walks.groupBy(F.floor(F.col("sample_id") / t).cast("int").alias("run")).agg(F.sum("ratio").alias("s"), F.count(F.lit(1)).alias("hits"))
    every = edges.sparkSession.range(runs).select(F.col("id").cast("int").alias("run"))
    out = every.join(per, "run", "left").crossJoin(broom_total(index, p, q))
    return out.select("run", F.lit(t).cast("long").alias("t"), F.coalesce("hits", F.lit(0)).alias("hits"), (F.col("brooms").cast("double") * F.coalesce("s", F.lit(0.0)) / t).alias("estimate"))


def estimate_independent(edges: DataFrame, p: int, q: int, t: int, runs: int = 10, seed: int = 1, **options) -> DataFrame:
    """run, t, hits, estimate: runs that share nothing, each with a coloring, an index and walks of its own seed."""
    out = None
    for run in range(runs):
        row = estimate(edges, p, q, t, seed + run, **options).select(F.lit(run).alias("run"), "t", "hits", F.col("estimate").cast("double").alias("estimate"))
        out = row if out is None else out.unionByName(row)
    return out


def estimate_progressive(edges: DataFrame, p: int, q: int, t0: int = 1000, growth: int = 4, tol: float = 0.05, max_t: int = DEFAULT_T, seed: int = 1, **options) -> DataFrame:
    """t, estimate, change: samples are added until two estimates in a row differ by less than tol. Samples are kept."""
    reduced, index, choice = prepared(edges, p, q, seed=seed, **options)
    brooms = float(broom_total(index, p, q).first()[0])
    t, done, s, last, history = t0, 0, 0.0, None, []
    while True:
        walks = sampler.sample_walks(index, reduced, p, q, t - done, seed, choice.contain, choice.engine, first=done, meet=choice.meet)
        s += walks.agg(F.sum("ratio")).first()[0] or 0.0
        now, done = brooms * s / t, t
        change = None if last is None else abs(now - last) / max(abs(now), 1e-300)
        history.append((t, now, change))
        if t >= max_t or (change is not None and change < tol):
            break
        last, t = now, min(max_t, t * growth)
    return edges.sparkSession.createDataFrame(history, "t long, estimate double, change double")


def estimate_grid(edges: DataFrame, ps: Iterable[int], qs: Iterable[int], t: int, seed: int = 1, **options) -> DataFrame:
    """estimate() for each p and q, with the seconds of initialisation and sampling. The loop is over a few sizes."""
    rows = []
    for p in ps:
        for q in qs:
            began = time.time()
            reduced, index, choice = prepared(edges, p, q, seed=seed, **options)
            ready = time.time()
            walks = sampler.sample_walks(index, reduced, p, q, t, seed, choice.contain, choice.engine, meet=choice.meet)
            r = summarize(walks, broom_total(index, p, q), p, q, t).first()
            rows.append((p, q, t, float(r["brooms"]), r["hits"], float(r["estimate"]), float(r["std_error"]), ready - began, time.time() - ready))
    return edges.sparkSession.createDataFrame(rows, "p int, q int, t long, brooms double, hits long, estimate double, std_error double, init_s double, sample_s double")


def expected_ratio(colored: DataFrame, edges: DataFrame, p: int, q: int) -> DataFrame:
    """One row: brooms, survivors, expectation, estimate. Every walk that can finish is followed with its probability
    (chance) and product of shares (ratio); their products sum up to C / B. For tiny graphs."""
    index = broom_index(colored, p, q)
    last = p + q - 1
    total = broom_total(index, p, q)
    w = index.where(F.col(f"w{last}") > 0).crossJoin(total)
    walks = w.select("u", "v", "cu", "cv", F.col(f"w{last}").alias("w"), F.array("u").alias("us"), F.array("v").alias("vs"), F.lit(1.0).alias("ratio"), (F.col(f"w{last}") / F.col("brooms")).alias("chance"))
    walks = walks.withColumn("walk", F.monotonically_increasing_id())
    from pyspark.sql import Window

    from biclique_spark.operators.graph import adjacency
    from biclique_spark.sources.io import written

    near = {s: adjacency(edges, s) for s in ("u", "v")}
    for layer in range(last - 1, 0, -1):
        step = broom_steps(p, q)[layer - 1]
        shared, other, color, chosen = ("u", "v", "cv", "us") if step == "U" else ("v", "u", "cu", "vs")
        walks = written(walks, "expectation")
        i = index.where(F.col(f"w{layer}") > 0).select(F.col(shared).alias("s"), F.col(other).alias("x"), F.col("cu").alias("ncu"), F.col("cv").alias("ncv"), F.col(f"w{layer}").alias("nw"))
        c = walks.join(i, walks[shared] == i.s).where(F.col(f"n{color}") < F.col(color)).join(near[other].select(F.col("id").alias("x"), "nbrs"), "x")
        c = c.where(F.size(F.array_except(chosen, "nbrs")) == 0).withColumn("total", F.sum("nw").over(Window.partitionBy("walk")))
        grown = "vs" if step == "U" else "us"
        walks = c.select(
            *[F.col("x").alias(k) if k == other else F.col(k) for k in ("u", "v")], F.col("ncu").alias("cu"), F.col("ncv").alias("cv"), F.col("nw").alias("w"),
            *[F.concat(F.array("x"), k).alias(k) if k == grown else F.col(k) for k in ("us", "vs")],
            (F.col("ratio") * F.col("total") / F.col("w")).alias("ratio"), (F.col("chance") * F.col("nw") / F.col("total")).alias("chance"),
            F.monotonically_increasing_id().alias("walk"),
        )
    sums = walks.agg(F.count(F.lit(1)).alias("survivors"), F.coalesce(F.sum(F.col("ratio") * F.col("chance")), F.lit(0.0)).alias("expectation"))
    return total.crossJoin(sums).select("brooms", "survivors", "expectation", (F.col("brooms") * F.col("expectation")).alias("estimate"))
