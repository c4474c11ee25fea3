"""The experiments on the given tables, each (spark, sf_dir, **sizes) -> DataFrame.

Defaults are the published ones: nine graphs, all sizes from 3 to 9, 100,000 samples, ten runs and every method.
Registered queries pass smaller sizes in plain sight. Exact methods may be given a limit in seconds; a cell that
takes longer has a null, as do counts that only they could give.
"""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable, Iterable
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from biclique_spark.operators import coloring, estimator, exact, hybrid, measures, sampler
from biclique_spark.operators.graph import core_reduce, edges_from, sample_vertices
from biclique_spark.operators.index import broom_index, broom_total, stored
from biclique_spark.plans import planner
from biclique_spark.sources.catalog import graph
from biclique_spark.sources.io import written

NINE = ("customer_part", "supplier_part", "customer_supplier", "user_k", "user_hour", "doc_line", "conv_token", "page_href", "vec_topdim")
VARIANTS = {"none": ("none", "random"), "random": ("greedy", "random"), "asc": ("greedy", "asc"), "desc": ("greedy", "desc")}
GRID, T, RUNS, LIMIT = tuple(product(range(3, 10), repeat=2)), 100_000, 10, 100_000.0
POWERS = tuple(10**k for k in range(1, 7))
#: name: (edges, p, q, samples, seed) -> count; the first two are exact.
METHODS: dict[str, Callable[..., float]] = {
    "vertex_expand": lambda e, p, q, t, s: exact.count_vertex_expand(e, p, q).first()[0],
    "edge_pivot": lambda e, p, q, t, s: exact.count_edge_pivot(e, p, q).first()[0],
    "hybrid_basic": lambda e, p, q, t, s: hybrid.estimate_hybrid(e, p, q, t, seed=s, basic=True).first()["estimate"],
    "hybrid": lambda e, p, q, t, s: hybrid.estimate_hybrid(e, p, q, t, seed=s).first()["estimate"],
    "broom": lambda e, p, q, t, s: estimator.estimate(e, p, q, t, s).first()["estimate"],
}
FOUR = ("vertex_expand", "edge_pivot", "hybrid", "broom")
ESTIMATORS = ("hybrid", "broom")


def within(spark: SparkSession, seconds: float, run: Callable[[], object]) -> tuple[float | None, float]:
    """What run() returns and the seconds it took; None where its Spark jobs were cancelled after ``seconds``."""
    sc, group, late = spark.sparkContext, uuid.uuid4().hex, threading.Event()

    def stop() -> None:
        late.set()
        sc.cancelJobGroup(group)

    timer = threading.Timer(seconds, stop)
    sc.setJobGroup(group, "timed", True)
    timer.start()
    began = time.time()
    try:
        value = run()
        return None if value is None else float(value), time.time() - began
    except Exception:
        if not late.is_set():
            raise
        return None, time.time() - began
    finally:
        timer.cancel()
        sc.setLocalProperty("spark.jobGroup.id", None)


def truth_of(e: DataFrame, p: int, q: int, limit: float) -> float | None:
    return within(e.sparkSession, limit, lambda: exact.count_vertex_expand(e, p, q).first()[0])[0]


def mean_error(values: list[float], truth: float | None) -> float | None:
    """Over runs; their mean stands for a count that is not known. Null where that is 0."""
    of = truth if truth is not None else sum(values) / len(values)
    return sum(abs(x - of) for x in values) / len(values) / of if of else None


def runtimes(spark: SparkSession, sf: str, graphs: Iterable[str] = NINE, sizes=GRID, t: int = T, methods=FOUR, limit: float = LIMIT) -> DataFrame:
    """graph, p, q, method, seconds, count: total time of each method."""
    rows = []
    for g in graphs:
        e = written(graph(spark, sf, g), "graph")
        for (p, q), m in product(sizes, methods):
            count, seconds = within(spark, limit, lambda: METHODS[m](e, p, q, t, 1))  # noqa: B023
            rows.append((g, p, q, m, seconds, count))
    return spark.createDataFrame(rows, "graph string, p int, q int, method string, seconds double, count double")


def errors(spark: SparkSession, sf: str, graphs: Iterable[str] = NINE, sizes=GRID, t: int = T, runs: int = RUNS, methods=ESTIMATORS, limit: float = LIMIT) -> DataFrame:
    """graph, p, q, method, runs, truth, mean_error, seconds: runs share nothing, colorings neither."""
    rows = []
    for g in graphs:
        e = written(graph(spark, sf, g), "graph")
        for p, q in sizes:
            truth = truth_of(e, p, q, limit)
            for m in methods:
                began = time.time()
                values = [float(METHODS[m](e, p, q, t, seed)) for seed in range(1, runs + 1)]
                rows.append((g, p, q, m, runs, truth, mean_error(values, truth), (time.time() - began) / runs))
    return spark.createDataFrame(rows, "graph string, p int, q int, method string, runs int, truth double, mean_error double, seconds double")


def grids(spark: SparkSession, sf: str, graphs: Iterable[str] = NINE, sizes=GRID, t: int = T, runs: int = RUNS, methods=ESTIMATORS, limit: float = LIMIT) -> DataFrame:
    """graph, p, q, method, mean_error, seconds, truth and the mean estimate: cells of the time and error maps. Cells
    without a truth stay, by a full outer join."""
    found = errors(spark, sf, graphs, sizes, t, runs, methods, limit)
    known = found.where("truth is not null").select("graph", "p", "q", "truth").distinct()
    return found.drop("truth").join(known, ["graph", "p", "q"], "full")


def against_samples(spark: SparkSession, sf: str, graphs: Iterable[str] = ("customer_part", "doc_line", "supplier_part"), sizes=((3, 3),), ts=POWERS, runs: int = RUNS, methods=ESTIMATORS, limit: float = LIMIT) -> DataFrame:
    """graph, p, q, t, method, mean_error, seconds: error and time against the number of samples."""
    out = None
    for t in ts:
        one = errors(spark, sf, graphs, sizes, t, runs, methods, limit).withColumn("t", F.lit(t).cast("long"))
        out = one if out is None else out.unionByName(one)
    return out.select("graph", "p", "q", "t", "method", "mean_error", "seconds")


def raise_samples(spark: SparkSession, sf: str, g: str = "user_hour", p: int = 3, q: int = 3, ts=(100_000, 500_000, 1_000_000, 7_000_000), runs: int = RUNS, rival: str = "hybrid", limit: float = LIMIT) -> DataFrame:
    """t, mean_error, rival_error, wins: samples are added for the broom until its error is below that of the rival with
    the first number of samples."""
    e = written(graph(spark, sf, g), "graph")
    truth = truth_of(e, p, q, limit)
    of = lambda m, t: mean_error([float(METHODS[m](e, p, q, t, seed)) for seed in range(1, runs + 1)], truth)
    other, rows = of(rival, ts[0]), []
    for t in ts:
        own = of("broom", t)
        rows.append((t, own, other, own is not None and other is not None and own < other))
        if rows[-1][-1]:
            break
    return spark.createDataFrame(rows, "t long, mean_error double, rival_error double, wins boolean")


def coloring_ablation(spark: SparkSession, sf: str, graphs: Iterable[str] = ("customer_part", "doc_line", "supplier_part"), sizes=((3, 3),), ts=POWERS, runs: int = RUNS, limit: float = LIMIT) -> DataFrame:
    """graph, p, q, variant, t, kappa, brooms, mean_error, init_s, sample_s for no coloring and the three orders. Walks
    of one variant are drawn once, for the largest t; smaller ones take their first samples."""
    rows = []
    for g, (p, q) in product(graphs, sizes):
        e = core_reduce(graph(spark, sf, g), p, q)
        truth, engine = truth_of(e, p, q, limit), planner.choose(planner.statistics(e), p, q).engine
        for name, (strategy, order) in VARIANTS.items():
            began = time.time()
            colored = written(coloring.color_graph(e, p, q, order, 1, strategy), "colored")
            index = stored(broom_index(colored, p, q))
            brooms, kappa = float(broom_total(index, p, q).first()[0]), coloring.color_count(colored).first()["kappa"]
            init = time.time() - began
            for t in ts:
                began = time.time()
                walks = sampler.sample_walks(index, e, p, q, t * runs, engine=engine)
                sums = {r["run"]: r["s"] for r in walks.groupBy(F.floor(F.col("sample_id") / t).alias("run")).agg(F.sum("ratio").alias("s")).collect()}  # a row a run
                error = mean_error([brooms * sums.get(i, 0.0) / t for i in range(runs)], truth)
                rows.append((g, p, q, name, t, int(kappa), brooms, error, init, (time.time() - began) / runs))
    return spark.createDataFrame(rows, "graph string, p int, q int, variant string, t long, kappa int, brooms double, mean_error double, init_s double, sample_s double")


def stage_split(spark: SparkSession, sf: str, graphs: Iterable[str] = NINE, sizes=((3, 3),), t: int = T, methods=ESTIMATORS) -> DataFrame:
    """graph, p, q, method, init_s, sample_s, estimate: coloring and index apart from walks, for the broom; for the
    hybrid the exact sparse part and the path index apart from its walks."""
    rows = []
    for g, (p, q) in product(graphs, sizes):
        e = written(graph(spark, sf, g), "graph")
        if "broom" in methods:
            r = estimator.estimate_grid(e, [p], [q], t).first()
            rows.append((g, p, q, "broom", r["init_s"], r["sample_s"], r["estimate"]))
        if "hybrid" not in methods:
            continue
        began = time.time()
        hybrid.estimate_hybrid(e, p, q, 1).first()
        init = time.time() - began
        began = time.time()
        value = hybrid.estimate_hybrid(e, p, q, t).first()["estimate"]
        rows.append((g, p, q, "hybrid", init, max(0.0, time.time() - began - init), float(value)))
    return spark.createDataFrame(rows, "graph string, p int, q int, method string, init_s double, sample_s double, estimate double")


def ratio_table(spark: SparkSession, sf: str, graphs: Iterable[str] = ("page_href", "doc_line"), sizes=tuple(product(range(2, 6), repeat=2)), strategy: str | None = None) -> DataFrame:
    """B^2/C^2 of the colored broom against Z^2/rho^2 of the zigzag, by graph and size."""
    out = None
    for g in graphs:
        one = measures.sample_ratios(graph(spark, sf, g), list(sizes), strategy).withColumn("graph", F.lit(g))
        out = one if out is None else out.unionByName(one)
    return out


def memory(spark: SparkSession, sf: str, graphs: Iterable[str] = NINE, sizes=((3, 3),), methods=FOUR, strategy: str | None = None) -> DataFrame:
    """graph, p, q, method, held, rows, bytes."""
    out = None
    for g, (p, q) in product(graphs, sizes):
        one = measures.memory_profile(graph(spark, sf, g), p, q, methods, strategy)
        one = one.select(F.lit(g).alias("graph"), F.lit(p).alias("p"), F.lit(q).alias("q"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def scalability(spark: SparkSession, sf: str, graphs: Iterable[str] = ("supplier_part", "doc_line"), sizes=((6, 8), (3, 4)), t: int = T, shares=(0.6, 0.8, 1.0), runs: int = RUNS, limit: float = LIMIT, strategy: str | None = None) -> DataFrame:
    """graph, p, q, share, edges, init_s, sample_s, truth, mean_error on induced subgraphs of shares of the vertices."""
    rows = []
    for g, (p, q), share in product(graphs, sizes, shares):
        e = graph(spark, sf, g)
        e = written(sample_vertices(e, share) if share < 1 else e, "graph")
        truth = truth_of(e, p, q, limit)
        cells = [estimator.estimate_grid(e, [p], [q], t, seed, strategy=strategy).first() for seed in range(1, runs + 1)]
        mean = lambda c: sum(r[c] for r in cells) / runs  # noqa: B023, E731
        rows.append((g, p, q, share, e.count(), mean("init_s"), mean("sample_s"), truth, mean_error([r["estimate"] for r in cells], truth)))
    return spark.createDataFrame(rows, "graph string, p int, q int, share double, edges long, init_s double, sample_s double, truth double, mean_error double")


def small_sizes(spark: SparkSession, sf: str, graphs: Iterable[str] = NINE, sizes=tuple(product(range(3, 6), repeat=2)), t: int = T, limit: float = LIMIT) -> DataFrame:
    """graph, p, q, edge_pivot_s, broom_s, exact, estimate, error."""
    both = runtimes(spark, sf, graphs, sizes, t, ("edge_pivot", "broom"), limit)
    of = lambda m, count, seconds: both.where(F.col("method") == m).select("graph", "p", "q", F.col("seconds").alias(seconds), F.col("count").alias(count))
    out = of("edge_pivot", "exact", "edge_pivot_s").join(of("broom", "estimate", "broom_s"), ["graph", "p", "q"], "full")
    return out.withColumn("error", F.when(F.col("exact") > 0, F.abs(F.col("estimate") - F.col("exact")) / F.col("exact")))


def dataset_statistics(spark: SparkSession, sf: str, graphs: Iterable[str] = NINE) -> DataFrame:
    """graph, n_left, n_right, n_edges of each graph."""
    out = None
    for g in graphs:
        e = graph(spark, sf, g)
        row = e.agg(F.count_distinct("u").alias("n_left"), F.count_distinct("v").alias("n_right"), F.count(F.lit(1)).alias("n_edges")).select(F.lit(g).alias("graph"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def most_colors(spark: SparkSession, sf: str, graphs: Iterable[str] = NINE, sizes=GRID, strategy: str | None = None) -> DataFrame:
    """graph, kappa: the most colors of a side over all sizes."""
    out = None
    for g in graphs:
        row = measures.color_counts(graph(spark, sf, g), list(sizes), strategy).agg(F.max("kappa").alias("kappa")).select(F.lit(g).alias("graph"), "kappa")
        out = row if out is None else out.unionByName(row)
    return out


def region_profiles(spark: SparkSession, sf: str, sizes=((2, 2),)) -> DataFrame:
    """graph (region), p, q, value: motif profiles of what each region's customers buy."""
    t = lambda n: spark.read.parquet(f"{sf}/{n}.parquet")
    rows = t("orders").join(t("lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).join(t("customer"), F.col("c_custkey") == F.col("o_custkey"))
    rows = rows.join(t("nation"), F.col("n_nationkey") == F.col("c_nationkey")).join(t("region"), F.col("r_regionkey") == F.col("n_regionkey"))
    # One graph whose left vertices know their region: pairs never cross regions.
    e = edges_from(rows, F.struct("r_name", F.col("o_custkey").alias("c")), F.struct("r_name", F.col("l_partkey").alias("k")))
    out = None
    for p, q in sizes:
        tuples = exact.grow_left(e, p, q)
        n = tuples.groupBy(F.get("us", F.lit(0))["r_name"].alias("graph")).agg(F.sum(exact.binomial(F.size("vs"), q)).alias("n"))
        row = n.select("graph", F.lit(p).alias("p"), F.lit(q).alias("q"), F.log1p("n").alias("value"))
        out = row if out is None else out.unionByName(row)
    return out
