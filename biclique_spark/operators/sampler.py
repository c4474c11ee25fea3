"""Walks back through the layers of the index.

A walk draws its last edge by the last layer's weights and goes back a layer a step, among edges that keep the shared
endpoint, have a smaller color on the other side and are adjacent to everything chosen there. The share of weight
that is left at each step is multiplied up; times the number of brooms it is an unbiased estimate.

Two engines give the same walks for the same seed: joins (any size) and a kernel with the index in each worker's
memory (for an index of a checked size). Draws are digests of (seed, sample, step).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from biclique_spark.functions.pattern import broom_steps
from biclique_spark.functions.scalar import DRAW_BITS, EXACT, draw, draw_sql
from biclique_spark.operators.graph import adjacency
from biclique_spark.sources.io import written

ONE = 1 << DRAW_BITS
#: Buckets of left vertices, by digest: with colors and keys behind them, the order of cumulative weights. A fixed number,
#: so that a draw stands for the same edge on a graph of any size and in sql_walks().
BUCKETS = 64
#: Edges of a vertex beyond which the kernel looks at them as arrays.
HUB = 128


def _samples(df: DataFrame, first: int, t: int) -> DataFrame:
    return df.sparkSession.range(first, first + t).select(F.col("id").alias("sample_id"))


def _bucket(buckets: int) -> Column:
    return F.conv(F.substring(F.md5(F.col("u").cast("string")), 1, 8), 16, 10).cast("long") % buckets


def _group(buckets: int, wide_u: int, wide_v: int) -> Column:
    """Bucket, left and right range of colors, as a struct that sorts like them."""
    return F.struct(_bucket(buckets).alias("b"), F.floor((F.col("cu") - 1) / wide_u).alias("i"), F.floor((F.col("cv") - 1) / wide_v).alias("j"))


def group_widths(edges: int, most_u: int, most_v: int, buckets: int = BUCKETS) -> tuple[int, int]:
    """Colors of either side that a group of the two-level lookup spans: a bucket is cut by left colors, and where these
    are few by right ones too, into about the square root of the edges in all, so that draws meet as many sums as edges."""
    cuts = max(1, (1 << (edges.bit_length() // 2)) // buckets)
    wide_u = -(-most_u // cuts) or 1
    cuts_v = max(1, cuts // max(1, most_u)) if wide_u == 1 else 1
    return wide_u, (-(-most_v // cuts_v) or 1)


def sample_last_edges(index: DataFrame, p: int, q: int, t: int, seed: int = 1, first: int = 0, buckets: int = BUCKETS) -> DataFrame:
    """sample_id, u, v, cu, cv, w: t draws with replacement, by weight.

    Cumulative weights go by bucket, colors and keys, and have two levels: groups (a bucket's edges of a range of colors;
    their sums are a small table) and edges in a group, so no task sorts all edges; draws find their group among the sums
    and then join only its edges. Groups are runs of that order, so their number does not change what is drawn.
    """
    last = f"w{p + q - 1}"
    size = index.agg(F.count(F.lit(1)), F.coalesce(F.max("cu"), F.lit(0)), F.coalesce(F.max("cv"), F.lit(0))).first()
    wide_u, wide_v = group_widths(*size, buckets)
    exact = dict(index.dtypes)[last] != "double"
    wide = lambda c: c.cast(EXACT) if exact else c
    live = index.where(F.col(last) > 0).select("u", "v", "cu", "cv", F.col(last).alias("w"), _group(buckets, wide_u, wide_v).alias("group"))
    sums = live.groupBy("group").agg(wide(F.sum("w")).alias("own"))
    order = Window.orderBy("group")
    sums = sums.select("group", (wide(F.sum("own").over(order)) - F.col("own")).alias("low"), wide(F.sum("own").over(order)).alias("high"), wide(F.sum("own").over(Window.partitionBy())).alias("total"))
    draws = _samples(index, first, t).withColumn("r", draw(seed, F.col("sample_id"), 0))
    one = F.lit(ONE).cast(EXACT) if exact else F.lit(float(ONE))
    r = F.col("r").cast("decimal(18,0)") if exact else F.col("r").cast("double")
    placed = draws.join(F.broadcast(sums), (wide(F.col("low")) * one <= r * F.col("total")) & (r * F.col("total") < F.col("high") * one))
    inside = Window.partitionBy("group").orderBy("cu", "cv", "u", "v").rowsBetween(Window.unboundedPreceding, 0)
    edges = live.withColumn("upto", wide(F.sum("w").over(inside)))
    here = F.col("low") + F.col("upto")
    drawn = placed.join(edges, "group").where((r * F.col("total") < here * one) & ((here - F.col("w")) * one <= r * F.col("total")))
    return drawn.select("sample_id", "u", "v", "cu", "cv", "w")


def degree(edges: DataFrame, side: str) -> DataFrame:
    """(id, d) of a side's vertices."""
    return edges.groupBy(F.col(side).alias("id")).agg(F.count(F.lit(1)).alias("d"))


def start(last: DataFrame) -> DataFrame:
    """Walks at their last edge: chosen vertices of both sides, and the product of shares so far."""
    return last.select("sample_id", "u", "v", "cu", "cv", "w", F.array("u").alias("us"), F.array("v").alias("vs"), F.lit(1.0).alias("ratio"))


def walk_step(walks: DataFrame, index: DataFrame, edges: DataFrame, step: str, layer: int, seed: int, contain: str = "array", free: bool = False, near: dict[str, DataFrame] | None = None, meet: str = "shared", sizes: dict[str, DataFrame] | None = None) -> DataFrame:
    """One step back, to ``layer``. Walks without candidates end and are not returned.

    meet: candidates are found among the index edges of the endpoint that is kept ('shared'), or among the neighbours
    of the chosen vertex of that side with fewest ('least'), which spares walks at a hub the hub's edges: they only look
    the candidates' edges up by both ends. sizes: degrees (id, d) of both sides, where stored.

    contain: 'array' looks candidates up in the neighbour array of the vertex, 'join' counts joined edges.
    free: without the test of adjacency (plain brooms, shares stay 1). near: adjacency of both sides, where stored.
    """
    exact = dict(index.dtypes)[f"w{layer}"] != "double"
    shared, other, color = ("u", "v", "cv") if step == "U" else ("v", "u", "cu")
    chosen = "us" if step == "U" else "vs"  # the side that a candidate must be adjacent to
    i = index.where(F.col(f"w{layer}") > 0).select(F.col(shared).alias("s"), F.col(other).alias("x"), F.col("cu").alias("ncu"), F.col("cv").alias("ncv"), F.col(f"w{layer}").alias("nw"))
    if meet == "least" and not free:
        d = sizes[shared] if sizes else degree(edges, shared)
        picked = walks.select("sample_id", F.explode(chosen).alias("id")).join(d, "id")
        picked = picked.groupBy("sample_id").agg(F.min(F.struct("d", "id")).getField("id").alias("m"))
        around = edges.select(F.col(shared).alias("m"), F.col(other).alias("x"))
        c = walks.join(picked, "sample_id").join(around, "m").drop("m").withColumn("s", F.col(shared)).join(i, ["s", "x"])
    else:
        c = walks.join(i, walks[shared] == i.s)
    c = c.where(F.col(f"n{color}") < F.col(color))
    if not free:
        if contain == "array":
            of = near[other] if near else adjacency(edges, other)
            c = c.join(of.select(F.col("id").alias("x"), "nbrs"), "x").where(F.size(F.array_except(chosen, "nbrs")) == 0).drop("nbrs")
        else:
            pairs = c.select("sample_id", "x", F.explode(chosen).alias("m"))
            e = edges.select(F.col(other).alias("x"), F.col(shared).alias("m"))
            full = pairs.join(e, ["x", "m"]).groupBy("sample_id", "x").agg(F.count(F.lit(1)).alias("n"))
            c = c.join(full, ["sample_id", "x"]).where(F.col("n") == F.size(chosen)).drop("n")
    whole = Window.partitionBy("sample_id")
    upto = whole.orderBy(f"n{color}", "x").rowsBetween(Window.unboundedPreceding, 0)
    kind = EXACT if exact else "double"
    c = c.withColumn("total", F.sum("nw").over(whole).cast(kind)).withColumn("high", F.sum("nw").over(upto).cast(kind))
    c = c.withColumn("r", draw(seed, F.col("sample_id"), layer))
    one = F.lit(ONE).cast(EXACT) if exact else F.lit(float(ONE))
    r = F.col("r").cast("decimal(18,0)") if exact else F.col("r").cast("double")
    c = c.where((r * F.col("total") < F.col("high") * one) & ((F.col("high") - F.col("nw")) * one <= r * F.col("total")))
    share = F.col("ratio") * (F.col("total").cast("double") / F.col("w").cast("double"))
    grown = "vs" if step == "U" else "us"
    return c.select(
        "sample_id",
        *[F.col("x").alias(k) if k == other else F.col(k) for k in ("u", "v")],
        F.col("ncu").alias("cu"), F.col("ncv").alias("cv"), F.col("nw").alias("w"),
        *[F.concat(F.array("x"), k).alias(k) if k == grown else F.col(k) for k in ("us", "vs")],
        share.alias("ratio"),
    )


def sample_walks(index: DataFrame, edges: DataFrame, p: int, q: int, t: int, seed: int = 1, contain: str = "array", engine: str = "join", first: int = 0, free: bool = False, cut: int = 3, meet: str = "shared") -> DataFrame:
    """sample_id, us, vs, ratio of the walks that finish; the others count as 0. The joins write a table every
    ``cut`` steps, so that plans stay short and lost executors cost little. meet: see walk_step(); walks are the same."""
    if engine == "local":
        return _local_walks(index, p, q, t, seed, first, free)
    walks = written(start(sample_last_edges(index, p, q, t, seed, first)), "walks")
    steps = broom_steps(p, q)
    near = None if free or contain != "array" else {s: written(adjacency(edges, s), "adjacency") for s in ("u", "v")}
    sizes = {s: written(degree(edges, s), "degrees") for s in ("u", "v")} if meet == "least" and not free else None
    for done, layer in enumerate(range(p + q - 2, 0, -1), 1):
        walks = walk_step(walks, index, edges, steps[layer - 1], layer, seed, contain, free, near, meet, sizes)
        if done % cut == 0:
            walks = written(walks, "walks")
    return walks.select("sample_id", "us", "vs", "ratio")


def _number(seed: int, sample: int, step: int) -> int:
    return int(hashlib.md5(f"{seed}:{sample}:{step}".encode()).hexdigest()[:13], 16)


def _local_walks(index: DataFrame, p: int, q: int, t: int, seed: int, first: int, free: bool) -> DataFrame:
    """Walks with the whole index in each worker; see planner.choose() for the size up to which it is used.

    Vertices are numbered in the order (color, key), so a vertex's edges lie in color order and a set of
    vertices is a whole number with a bit for each."""
    spark = index.sparkSession
    last = p + q - 1
    ku, kv = dict(index.dtypes)["u"], dict(index.dtypes)["v"]
    exact = dict(index.dtypes)["w1"] != "double"
    f = index.withColumn("bucket", _bucket(BUCKETS)).toPandas()
    us = f[["cu", "u"]].drop_duplicates().sort_values(["cu", "u"], ignore_index=True)
    vs = f[["cv", "v"]].drop_duplicates().sort_values(["cv", "v"], ignore_index=True)
    f["iu"] = f["u"].map({k: i for i, k in enumerate(us["u"])})
    f["iv"] = f["v"].map({k: i for i, k in enumerate(vs["v"])})
    f = f.sort_values(["iu", "iv"], ignore_index=True)
    as_numbers = lambda c: [int(x) for x in f[c]] if exact else f[c].astype(float).tolist()
    data = {
        "u": f["iu"].to_numpy(), "v": f["iv"].to_numpy(), "w": [as_numbers(f"w{k}") for k in range(1, last + 1)], "us": us, "vs": vs,
        "by_bucket": f.sort_values(["bucket", "cu", "cv", "u", "v"], kind="stable").index.to_numpy(),
    }
    shared = spark.sparkContext.broadcast(data)
    steps = broom_steps(p, q)
    parts = spark.sparkContext.defaultParallelism

    def run(source: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        d = shared.value
        u, v, w = d["u"], d["v"], d["w"]
        colors = {"U": d["vs"]["cv"].to_numpy(), "V": d["us"]["cu"].to_numpy()}
        limit = {"U": d["vs"]["cv"].to_numpy(), "V": d["us"]["cu"].to_numpy()}
        ws_of = [np.array(x, dtype=object if exact else float) for x in w]
        hubs: dict[tuple[str, int], tuple[np.ndarray, np.ndarray]] = {}

        def among_hub(step: str, vertex: int, edges_: list[int], near: int, at: int, layer: int) -> tuple[np.ndarray, np.ndarray]:
            """Candidates (edge, vertex) of a hub and sums of their weights, as arrays."""
            if (step, vertex) not in hubs:
                own = np.array(edges_)
                hubs[step, vertex] = own, (v if step == "U" else u)[own]
            own, xs = hubs[step, vertex]
            n = np.searchsorted(xs, np.searchsorted(limit[step], limit[step][at]))
            own, xs = own[:n], xs[:n]
            live = (ws_of[layer - 1][own] > 0).astype(bool)
            if not free:
                size = len(limit[step])
                bits = np.unpackbits(np.frombuffer(near.to_bytes(size // 8 + 1, "little"), np.uint8), bitorder="little")
                live &= bits[xs].astype(bool)
            own = own[live]
            return own, np.cumsum(ws_of[layer - 1][own])

        of_u: dict[int, list[int]] = {}
        of_v: dict[int, list[int]] = {}
        bits_u: dict[int, int] = {}
        bits_v: dict[int, int] = {}
        for e, (a, b) in enumerate(zip(u.tolist(), v.tolist(), strict=True)):
            of_u.setdefault(a, []).append(e)
            of_v.setdefault(b, []).append(e)
            bits_u[a] = bits_u.get(a, 0) | 1 << b
            bits_v[b] = bits_v.get(b, 0) | 1 << a
        order = d["by_bucket"].tolist()
        total, cumulated = 0, []
        for e in order:
            total += w[last - 1][e]
            cumulated.append(total)
        from bisect import bisect_right

        ends = [c * ONE for c in cumulated]
        for batch in source:
            out = []
            for sample in batch["id"].tolist():
                if not total:
                    continue
                e = order[min(bisect_right(ends, _number(seed, sample, 0) * total), len(order) - 1)]
                a, b = int(u[e]), int(v[e])
                left, right, ratio = [a], [b], 1.0
                common = {"U": bits_u[a], "V": bits_v[b]}  # vertices adjacent to all chosen on the opposite side
                for layer in range(last - 1, 0, -1):
                    step, ws = steps[layer - 1], w[layer - 1]
                    color, near = colors[step], common[step]
                    of, other, at = (of_u[a], v, b) if step == "U" else (of_v[b], u, a)
                    found, upto, sums = [], 0, []
                    if len(of) > HUB:
                        found, sums = among_hub(step, a if step == "U" else b, of, near, at, layer)
                        upto, of = sums[-1] if len(sums) else 0, []
                    for k in of:
                        x = int(other[k])
                        if color[x] >= color[at]:
                            break
                        if ws[k] and (free or near >> x & 1):
                            upto += ws[k]
                            found.append((k, x))
                            sums.append(upto)
                    if not upto:
                        break
                    ratio *= float(upto) / float(w[layer][e])
                    r = _number(seed, sample, layer) * upto
                    if isinstance(sums, np.ndarray):
                        k = int(found[min(int(np.searchsorted(sums * ONE, r, side="right")), len(found) - 1)])
                        x = int(other[k])
                    else:
                        k, x = found[min(bisect_right([s * ONE for s in sums], r), len(found) - 1)]
                    e = k
                    if step == "U":
                        b = x
                        right.insert(0, x)
                        common["V"] &= bits_v[x]
                    else:
                        a = x
                        left.insert(0, x)
                        common["U"] &= bits_u[x]
                else:
                    out.append((sample, d["us"]["u"].to_numpy()[left].tolist(), d["vs"]["v"].to_numpy()[right].tolist(), ratio))
            yield pd.DataFrame(out, columns=["sample_id", "us", "vs", "ratio"])

    return spark.range(first, first + t, 1, parts).mapInPandas(run, f"sample_id long, us array<{ku}>, vs array<{kv}>, ratio double")


def complete(walks: DataFrame, edges: DataFrame) -> DataFrame:
    """sample_id of walks whose vertices induce a complete subgraph: their pairs are counted among the edges."""
    pairs = walks.select("sample_id", "us", "vs", F.explode("us").alias("u")).select("sample_id", F.size("us").alias("p"), F.size("vs").alias("q"), "u", F.explode("vs").alias("v"))
    n = pairs.join(edges.select("u", "v"), ["u", "v"]).groupBy("sample_id", "p", "q").agg(F.count(F.lit(1)).alias("n"))
    return n.where("n = p * q").select("sample_id")


def naive_sample(index: DataFrame, edges: DataFrame, p: int, q: int, t: int, seed: int = 1, **options) -> DataFrame:
    """One row: t, hits, brooms, estimate. Whole brooms are drawn and tested."""
    walks = written(sample_walks(index, edges, p, q, t, seed, free=True, **options), "brooms")
    hits = complete(walks, edges).agg(F.count(F.lit(1)).alias("hits"))
    last = f"w{p + q - 1}"
    total = index.agg(F.coalesce(F.sum(last).cast("double"), F.lit(0.0)).alias("brooms"))
    return hits.join(total).select(F.lit(t).cast("long").alias("t"), "hits", "brooms", (F.col("brooms") * F.col("hits") / t).alias("estimate"))


def sql_walks(p: int, q: int, t: int, seed: int, free: bool = False, buckets: int = BUCKETS) -> str:
    """CTEs behind sql_layers(): s0 (last edges) and k1.. (walks after each step), in DuckDB's SQL."""
    last = p + q - 1
    steps = broom_steps(p, q)
    out = [
        f"le as materialized (select u, v, cu, cv, w{last} as w, ('0x' || substr(md5(u::varchar), 1, 8))::bigint % {buckets} as bucket from c{last} where w{last} > 0)",
        "lc as materialized (select *, sum(w) over (order by bucket, cu, cv, u, v rows unbounded preceding)::hugeint as high, sum(w) over ()::hugeint as total from le)",
        f"dr as materialized (select range as sample_id, {draw_sql(str(seed), 'range', '0')}::hugeint as r from range({t}))",
        f"k{last} as materialized (select sample_id, u, v, cu, cv, w, [u] as us, [v] as vs, 1.0::double as ratio from dr join lc on r * total < high * {ONE}::hugeint and (high - w) * {ONE}::hugeint <= r * total)",
    ]
    for layer in range(last - 1, 0, -1):
        step = steps[layer - 1]
        shared, other, color, chosen = ("u", "v", "cv", "us") if step == "U" else ("v", "u", "cu", "vs")
        near = "" if free else f"join (select {other}, list({shared}) as nb from g group by {other}) a on a.{other} = i.{other}"
        test = "" if free else f"and list_has_all(a.nb, k.{chosen})"
        us, vs = ("k.us", "list_prepend(i.v, k.vs)") if step == "U" else ("list_prepend(i.u, k.us)", "k.vs")
        out.append(
            f"m{layer} as materialized (select k.sample_id, i.u, i.v, i.cu, i.cv, i.w{layer} as w, k.w as pw, {us} as us, {vs} as vs, k.ratio, "
            f"sum(i.w{layer}) over (partition by k.sample_id)::hugeint as total, sum(i.w{layer}) over (partition by k.sample_id order by i.{color}, i.{other} rows unbounded preceding)::hugeint as high "
            f"from k{layer + 1} k join c{last} i on i.{shared} = k.{shared} and i.{color} < k.{color} and i.w{layer} > 0 {near} where true {test})"
        )
        r = draw_sql(str(seed), "sample_id", str(layer)) + "::hugeint"
        out.append(
            f"k{layer} as materialized (select sample_id, u, v, cu, cv, w, us, vs, ratio * (total::double / pw::double) as ratio from m{layer} "
            f"where {r} * total < high * {ONE}::hugeint and (high - w) * {ONE}::hugeint <= {r} * total)"
        )
    return ",\n".join(out)


