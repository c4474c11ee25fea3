"""Bipartite graphs as edges(u, v): building, reducing, splitting and sampling them."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType, StringType

from biclique_spark.functions.scalar import DRAW_BITS, draw
from biclique_spark.sources.io import discard, written

#: Edges of two short columns that one task may hold.
CORE_EDGES = 1_000_000
#: Vertices that a step of core_by_peeling() takes away at most.
PEELED = 100_000


def edges_from(df: DataFrame, u: Column | str, v: Column | str) -> DataFrame:
    """Distinct pairs of two keys without nulls."""
    of = lambda x: F.col(x) if isinstance(x, str) else x
    return df.select(of(u).alias("u"), of(v).alias("v")).dropna().distinct()


def transpose(edges: DataFrame) -> DataFrame:
    """Sides exchanged: (p,q) becomes (q,p)."""
    out = edges.select(F.col("v").alias("u"), F.col("u").alias("v"))
    if hasattr(edges, "table_path"):
        out.table_path = edges.table_path
    return out


def encode_vertices(edges: DataFrame, parts: int | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Edges with whole-number ids from 0, dense within range partitions of keys, and both dictionaries.

    Ids are positions in range partitions plus the vertices in partitions before, so no task sorts a whole side.
    """
    spark = edges.sparkSession

    def dictionary(side: str) -> DataFrame:
        n = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
        at = F.monotonically_increasing_id()
        keys = edges.select(F.col(side).alias("key")).distinct().repartitionByRange(n, "key").sortWithinPartitions("key")
        placed = written(keys.select("key", F.shiftright(at, 33).alias("part"), at.bitwiseAND((1 << 33) - 1).alias("at")), "vertex-order")
        sizes = placed.groupBy("part").count().orderBy("part").collect()  # a row a partition
        offset, rows = 0, []
        for r in sizes:
            rows.append((r["part"], offset))
            offset += r["count"]
        base = spark.createDataFrame(rows, "part long, base long")
        return placed.join(F.broadcast(base), "part").select("key", (F.col("base") + F.col("at")).alias("id"))

    du, dv = dictionary("u"), dictionary("v")
    coded = edges.join(du.select(F.col("key").alias("u"), F.col("id").alias("iu")), "u").join(dv.select(F.col("key").alias("v"), F.col("id").alias("iv")), "v")
    return coded.select(F.col("iu").alias("u"), F.col("iv").alias("v")), du, dv


def degrees(edges: DataFrame) -> DataFrame:
    """(side, id, degree); ids as strings, as sides may have different types."""
    one = lambda s: edges.groupBy(F.col(s).cast("string").alias("id")).agg(F.count(F.lit(1)).alias("degree")).withColumn("side", F.lit(s))
    return one("u").unionByName(one("v")).select("side", "id", "degree")


def adjacency(edges: DataFrame, side: str) -> DataFrame:
    """(id, nbrs): sorted neighbours of each vertex of a side."""
    other = "v" if side == "u" else "u"
    return edges.groupBy(F.col(side).alias("id")).agg(F.sort_array(F.collect_set(other)).alias("nbrs"))


def core_round(edges: DataFrame, p: int, q: int) -> DataFrame:
    """One round: left vertices with q neighbours stay, then right vertices with p of those."""
    left = edges.groupBy("u").agg(F.count(F.lit(1)).alias("d")).where(F.col("d") >= q).select("u")
    edges = edges.join(left, "u", "left_semi")
    right = edges.groupBy("v").agg(F.count(F.lit(1)).alias("d")).where(F.col("d") >= p).select("v")
    return edges.join(right, "v", "left_semi")


def core_in_one_task(edges: DataFrame, p: int, q: int) -> DataFrame:
    """The fixpoint of core_round() in one task, for edges that fit there."""

    def peel(group: pd.DataFrame) -> pd.DataFrame:
        u, v = pd.factorize(group["u"])[0], pd.factorize(group["v"])[0]
        at = np.arange(len(group))
        while True:
            keep = (np.bincount(u)[u] >= q) & (np.bincount(v)[v] >= p)
            if keep.all():
                return group.iloc[at]
            u, v, at = u[keep], v[keep], at[keep]
            if not len(at):
                return group.iloc[at]

    return edges.groupBy(F.lit(0).alias("one")).applyInPandas(lambda g: peel(g), edges.schema)


def core_by_peeling(edges: DataFrame, p: int, q: int) -> DataFrame | None:
    """The fixpoint of core_round(), where few vertices go at once; None where more than PEELED do. Degrees are counted once;
    then each step takes away the vertices of a side with too few neighbours, and off the degrees what they were in."""
    least = {"u": q, "v": p}
    degree = {s: written(edges.groupBy(s).agg(F.count(F.lit(1)).alias("d")), "degrees") for s in ("u", "v")}
    gone: dict[str, DataFrame] = {}
    idle, s, o = 0, "u", "v"
    while idle < 2:
        low = written(degree[s].where(F.col("d") < least[s]).select(s), "peeled")
        n = low.count()
        if n > PEELED:
            return None
        if n:
            lost = edges.join(F.broadcast(low), s, "left_semi")
            if o in gone:
                lost = lost.join(F.broadcast(gone[o]), o, "left_anti")
            lost = lost.groupBy(o).agg(F.count(F.lit(1)).alias("lost"))
            left = F.col("d") - F.coalesce("lost", F.lit(0))
            degree[o] = written(degree[o].join(lost, o, "left").select(o, left.alias("d")), "degrees")
            degree[s] = degree[s].where(F.col("d") >= least[s])
            gone[s] = gone[s].unionByName(low) if s in gone else low
        idle, s, o = 0 if n else idle + 1, o, s
    if not gone:
        return edges
    out = edges
    for s, vertices in gone.items():
        out = out.join(F.broadcast(vertices), s, "left_anti")
    return written(out.select("u", "v"), "core")


def core_reduce(edges: DataFrame, p: int, q: int, max_rounds: int | None = None, least_gain: float = 0.0, one_task: int = CORE_EDGES) -> DataFrame:
    """Edges that can be in a (p,q)-biclique by their degrees, to the fixpoint; or until a round takes away a share
    of ``least_gain`` or less, as every result on the way has all bicliques. Once no more than ``one_task`` edges are
    left, the rest of the way to the fixpoint is one task's: rounds of few edges cost their scheduling only."""
    given = hasattr(edges, "table_path")  # a stored table need not be stored again, and is not ours to delete
    edges = edges if given else written(edges, "core")
    size, rounds = edges.count(), 0
    plain = edges.columns == ["u", "v"] and all(isinstance(f.dataType, IntegralType | StringType) for f in edges.schema)
    while size and (max_rounds is None or rounds < max_rounds):
        fits = plain and max_rounds is None and not least_gain and size <= one_task
        if not fits and max_rounds is None and not least_gain and (core := core_by_peeling(edges, p, q)) is not None:
            if core is not edges and not given:
                discard(edges)
            return core
        smaller = written(core_in_one_task(edges, p, q) if fits else core_round(edges, p, q), "core")
        if not given:
            discard(edges)
        given = False
        if fits:
            return smaller
        left = smaller.count()
        edges, gone, size, rounds = smaller, size - left, left, rounds + 1
        if gone <= least_gain * (left + gone):
            break
    return edges


def common_neighbors(edges: DataFrame, side: str, at_least: int = 1) -> DataFrame:
    """(a, b, n): pairs of one side, a < b, with at least so many shared neighbours."""
    other = "v" if side == "u" else "u"
    a = edges.select(F.col(side).alias("a"), F.col(other).alias("w"))
    b = edges.select(F.col(side).alias("b"), F.col(other).alias("w"))
    pairs = a.join(b, "w").where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))
    return pairs.where(F.col("n") >= at_least)


def anchor_ranks(edges: DataFrame, rank: str = "degree") -> DataFrame:
    """(u, r): a total order of the left side, as a sortable struct."""
    d = edges.groupBy("u").agg(F.count(F.lit(1)).alias("d"))
    return d.select("u", (F.struct("d", "u") if rank == "degree" else F.struct(F.lit(0).cast("long").alias("d"), "u")).alias("r"))


def wedges_of(edges: DataFrame, rank: str = "degree", anchors: DataFrame | None = None) -> DataFrame:
    """(anchor, u, v): paths from a left vertex over a right one to a later left vertex; with ``anchors`` (u) only
    those that begin there, which is settled before vertices meet."""
    ranked = edges.join(anchor_ranks(edges, rank), "u")
    first = ranked if anchors is None else ranked.join(anchors.select("u"), "u", "left_semi")
    a = first.select(F.col("u").alias("anchor"), F.col("r").alias("ra"), "v")
    return a.join(ranked, "v").where("r > ra").select("anchor", "u", "v")


def split_by_anchor(edges: DataFrame, p: int, q: int, rank: str = "degree", anchors: DataFrame | None = None) -> DataFrame:
    """(anchor, u, v): for each left vertex the edges of later ones that share q neighbours with it, to its own
    neighbours. The (p-1,q)-bicliques of all these graphs are the (p,q)-bicliques of the whole. Wedges are stored, as
    they are counted and then read again."""
    wedges = written(wedges_of(edges, rank, anchors), "wedges")
    enough = wedges.groupBy("anchor", "u").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= q).select("anchor", "u")
    return wedges.join(enough, ["anchor", "u"], "left_semi")


def _kept(column: str, side: str, share: float, seed: int) -> Column:
    return draw(seed, side, F.col(column)) < int(share * (1 << DRAW_BITS))


def sample_vertices(edges: DataFrame, share: float, seed: int = 1) -> DataFrame:
    """A share of both vertex sets and what they induce."""
    return edges.where(_kept("u", "u", share, seed) & _kept("v", "v", share, seed))


def sample_edges(edges: DataFrame, share: float, seed: int = 1) -> DataFrame:
    return edges.where(draw(seed, F.col("u"), F.col("v")) < int(share * (1 << DRAW_BITS)))


def complete_graph(spark: SparkSession, m: int, n: int) -> DataFrame:
    """All pairs of 1..m and 1..n."""
    rows = spark.range(m * n)
    return rows.select((F.floor(F.col("id") / n) + 1).alias("u"), (F.col("id") % n + 1).alias("v"))


def worked_example(spark: SparkSession) -> DataFrame:
    """A graph of ten edges with two (3,2)-bicliques, {1,3,4} x {1,2} and {3,4,5} x {2,3}."""
    pairs = {(u, v) for us, vs in (((1, 3, 4), (1, 2)), ((3, 4, 5), (2, 3))) for u in us for v in vs}
    return spark.createDataFrame(sorted(pairs), "u long, v long")
