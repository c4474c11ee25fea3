"""Counting brooms: prefix sums over edges in color order, a layer for each edge of the broom.

``colored`` is edges(u, v) with colors cu and cv from 1. The weight of an edge in layer t is the number of partial
brooms whose t-th edge it is: colors grow along the staircase on both sides. Layers are columns w1..wL of one row
an edge; steps that share a side share its partitioning and sort, so there is one exchange for each run of the
broom's steps, not for each layer.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from biclique_spark.functions.pattern import broom_steps
from biclique_spark.functions.scalar import EXACT
from biclique_spark.operators.graph import encode_vertices
from biclique_spark.sources.io import discard, released, written


#: Vertices of a side that one task may rank.
RANKED = 2_000_000


def layers(p: int, q: int) -> int:
    return p + q - 1


def _kind(weight: str) -> str:
    return EXACT if weight == "decimal" else "double"


def colored_by_key(edges: DataFrame) -> DataFrame:
    """Every vertex its own color: its rank among the side's keys. A side of up to RANKED vertices is ranked in one
    task; larger ones by range partitions and the numbers of vertices before them, see encode_vertices()."""
    if edges.agg(F.greatest(F.approx_count_distinct("u"), F.approx_count_distinct("v"))).first()[0] > RANKED:
        _, du, dv = encode_vertices(edges)
        of = lambda d, s: d.select(F.col("key").alias(s), (F.col("id") + 1).alias(f"c{s}"))
        return edges.join(of(du, "u"), "u").join(of(dv, "v"), "v").select("u", "v", "cu", "cv")
    rank = lambda s: edges.select(s).distinct().select(s, F.row_number().over(Window.orderBy(s)).alias(f"c{s}"))
    return edges.join(rank("u"), "u").join(rank("v"), "v").select("u", "v", "cu", "cv")


def broom_index(colored: DataFrame, p: int, q: int, weight: str = "double", blocks: int | None = None, cut: bool = False) -> DataFrame:
    """u, v, cu, cv, w1..wL. weight: 'double', or 'decimal' for exact counts up to 38 digits.

    With ``blocks`` (colors a block) prefix sums are skew-safe: see skewsafe_prefix(). With ``cut`` the layers of each run
    are stored, so that the shuffle files of one run only are there at a time.
    """
    kind = _kind(weight)
    out = colored.withColumn("w1", F.lit(1).cast(kind))
    if cut:
        out_table = out = written(out, "broom-layers")
    steps = broom_steps(p, q)
    for t, step in enumerate(steps, 1):
        key, color = ("u", "cv") if step == "U" else ("v", "cu")
        if cut and t > 1 and step != steps[t - 2]:
            last, out = out_table, written(out, "broom-layers")
            out_table = out
            discard(last)
            released(out.sparkSession)
        if blocks:
            # Each step reads the last one twice, so it is stored: plans would double with every step.
            out = written(skewsafe_prefix(out, key, color, f"w{t}", f"w{t + 1}", kind, blocks), "broom-layer")
        else:
            before = Window.partitionBy(key).orderBy(color).rangeBetween(Window.unboundedPreceding, -1)
            out = out.withColumn(f"w{t + 1}", F.coalesce(F.sum(f"w{t}").over(before).cast(kind), F.lit(0).cast(kind)))
    return out


def skewsafe_prefix(df: DataFrame, key: str, color: str, w: str, name: str, kind: str, block: int) -> DataFrame:
    """The sum of w over rows of the same key with a smaller color, for keys with any number of rows.

    Rows are summed by key and color first (a partial sum in each task), then colors are cut into blocks: sums of
    blocks before, and a window within each block. No task needs all rows of a key.
    """
    sums = df.groupBy(key, color).agg(F.sum(w).alias("s")).withColumn("block", F.floor(F.col(color) / block))
    whole = sums.groupBy(key, "block").agg(F.sum("s").alias("b"))
    earlier = Window.partitionBy(key).orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    whole = whole.select(key, "block", F.coalesce(F.sum("b").over(earlier), F.lit(0)).alias("base"))
    inside = Window.partitionBy(key, "block").orderBy(color).rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("inside", F.coalesce(F.sum("s").over(inside), F.lit(0))).join(whole, [key, "block"])
    sums = sums.select(key, color, (F.col("base") + F.col("inside")).cast(kind).alias(name))
    return df.join(sums, [key, color]).select(*df.columns, name)


def broom_total(index: DataFrame, p: int, q: int) -> DataFrame:
    """One row: brooms, 0 for an empty graph."""
    last = f"w{layers(p, q)}"
    kind = dict(index.dtypes)[last]
    return index.agg(F.coalesce(F.sum(last).cast(kind), F.lit(0).cast(kind)).alias("brooms"))


def long_index(index: DataFrame, p: int, q: int) -> DataFrame:
    """layer, u, v, cu, cv, w: a row for each layer and edge, without zero weights."""
    entries = F.array(*[F.struct(F.lit(t).alias("layer"), F.col(f"w{t}").alias("w")) for t in range(1, layers(p, q) + 1)])
    rows = index.select("u", "v", "cu", "cv", F.explode(entries).alias("e"))
    return rows.select("e.layer", "u", "v", "cu", "cv", "e.w").where("w > 0")


def array_index(index: DataFrame, p: int, q: int) -> DataFrame:
    """u, v, cu, cv, ws: all layers of an edge packed into an array."""
    return index.select("u", "v", "cu", "cv", F.array(*[f"w{t}" for t in range(1, layers(p, q) + 1)]).alias("ws"))


def layer_sums(index: DataFrame, p: int, q: int) -> DataFrame:
    """layer, edges with weight, sum of weights."""
    return long_index(index, p, q).groupBy("layer").agg(F.count(F.lit(1)).alias("edges"), F.sum("w").alias("weight"))


def broom_list(colored: DataFrame, p: int, q: int) -> DataFrame:
    """us, vs of every broom: by joins along the staircase; for tiny graphs."""
    e = colored.select("u", "v", "cu", "cv")
    out = e.select(F.array("u").alias("us"), F.array("v").alias("vs"), "u", "v", "cu", "cv")
    for step in broom_steps(p, q):
        n = e.select(*[F.col(c).alias(f"n_{c}") for c in e.columns])
        if step == "U":
            out = out.join(n, (F.col("u") == F.col("n_u")) & (F.col("cv") < F.col("n_cv")))
            out = out.withColumn("vs", F.concat("vs", F.array("n_v")))
        else:
            out = out.join(n, (F.col("v") == F.col("n_v")) & (F.col("cu") < F.col("n_cu")))
            out = out.withColumn("us", F.concat("us", F.array("n_u")))
        out = out.select("us", "vs", F.col("n_u").alias("u"), F.col("n_v").alias("v"), F.col("n_cu").alias("cu"), F.col("n_cv").alias("cv"))
    return out.select("us", "vs")


def stored(index: DataFrame) -> DataFrame:
    """The index as a table, since walks read it many times."""
    return written(index, "broom-index")


def sql_layers(edges_sql: str, p: int, q: int) -> str:
    """CTEs e, c1..cL in DuckDB's SQL: colors by key rank, then a prefix sum a step. To be put behind ``with``."""
    out = [
        f"g as materialized ({edges_sql})",
        "c1 as materialized (select u, v, cu, cv, 1::hugeint as w1 from g join (select u, row_number() over (order by u) as cu from (select distinct u from g)) using (u)"
        " join (select v, row_number() over (order by v) as cv from (select distinct v from g)) using (v))",
    ]
    for t, step in enumerate(broom_steps(p, q), 1):
        key, color = ("u", "cv") if step == "U" else ("v", "cu")
        out.append(
            f"c{t + 1} as materialized (select *, coalesce(sum(w{t}) over (partition by {key} order by {color} range between unbounded preceding and 1 preceding), 0)::hugeint as w{t + 1} from c{t})"
        )
    return ",\n".join(out)
