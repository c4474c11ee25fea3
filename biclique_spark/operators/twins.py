"""Counting on classes of twins: vertices of a side with the same neighbours.

Classes of both sides hold all that the graph does, as twins have all their edges alike: a class edge stands for every
pair of its classes' vertices. Copied pages and documents make classes few where pairs of vertices would be many. Counts
choose classes, and how many vertices of each.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DatetimeType, IntegralType, StringType

from biclique_spark.functions.scalar import EXACT, binomial
from biclique_spark.sources.io import released, written

#: Edges of a packed block of classes, about; meetings of edges at once.
BLOCK, MEETINGS = 1 << 21, 1 << 22
CLASS = "struct<n:bigint,a:bigint,b:bigint>"


@dataclass(frozen=True)
class Twins:
    """edges: (x, mx, y, my), classes and their numbers of vertices; left, right: (u, x) and (v, y), the members."""

    edges: DataFrame
    left: DataFrame
    right: DataFrame

    def turned(self) -> Twins:
        e = self.edges.select(F.col("y").alias("x"), F.col("my").alias("mx"), F.col("x").alias("y"), F.col("mx").alias("my"))
        return Twins(e, self.right.withColumnsRenamed({"v": "u", "y": "x"}), self.left.withColumnsRenamed({"u": "v", "x": "y"}))


def _fingerprint(n: Column, key: str) -> Column:
    """Number of neighbours and 128 bits of their set; the sums of hashes need no list of neighbours in one place."""
    return F.struct(n.cast("long").alias("n"), F.bit_xor(F.xxhash64(key, F.lit(1))).alias("a"), F.bit_xor(F.xxhash64(F.lit(2), key)).alias("b"))


def twins(edges: DataFrame) -> Twins:
    """The classes of edges(u, v) without repeated rows. That no two sets of neighbours have met in one fingerprint is
    checked by counting: class edges cover all edges, and more pairs than these only if sets differ within a class."""
    right = written(edges.groupBy("v").agg(_fingerprint(F.count(F.lit(1)), "u").alias("y")), "twins")
    wide = written(edges.join(right, "v").groupBy("u", "y").agg(F.count(F.lit(1)).alias("n")), "twins")
    left = written(wide.groupBy("u").agg(_fingerprint(F.sum("n"), "y").alias("x")), "twins")
    size = lambda t, c, m: t.groupBy(c).agg(F.count(F.lit(1)).alias(m))
    classes = wide.join(left, "u").select("x", "y").distinct()
    out = written(classes.join(size(left, "x", "mx"), "x").join(size(right, "y", "my"), "y").select("x", "mx", "y", "my"), "twins")
    pairs = out.agg(F.sum(F.col("mx").cast(EXACT) * F.col("my").cast("decimal(18,0)")).cast(EXACT)).first()[0] or 0
    if pairs != edges.count():  # never seen; each vertex is a class then
        of = lambda t, k, c: t.select(k, F.struct(F.lit(1).cast("long").alias("n"), F.row_number().over(_by(k)).cast("long").alias("a"), F.lit(0).cast("long").alias("b")).alias(c))
        left, right = written(of(left, "u", "x"), "twins"), written(of(right, "v", "y"), "twins")
        out = written(edges.join(left, "u").join(right, "v").select("x", F.lit(1).cast("long").alias("mx"), "y", F.lit(1).cast("long").alias("my")), "twins")
    return Twins(out, left, right)


def representatives(edges: DataFrame) -> Twins:
    """The classes of twins(), each named by its first vertex (as JSON, where keys are no plain values). Sets of neighbours
    are told apart by the same fingerprints, of vertices instead of classes, and checked in the same way; where no vertex has
    a twin, class edges are the given edges, without a join."""
    plain = lambda k: isinstance(edges.schema[k].dataType, IntegralType | StringType | DatetimeType)
    name = lambda k: F.col(k) if plain(k) else F.to_json(F.struct(k))

    def side(key: str, other: str, c: str) -> DataFrame:
        own = written(edges.groupBy(key).agg(_fingerprint(F.count(F.lit(1)), other).alias("f")), "twins")
        first = own.groupBy("f").agg(F.min(name(key)).alias(c), F.count(F.lit(1)).alias(f"m{c}"))
        return written(own.join(first, "f").select(key, c, f"m{c}"), "twins")

    left, right = side("u", "v", "x"), side("v", "u", "y")
    named = edges.select(name("u").alias("x"), name("v").alias("y"))
    out = named.withColumns({"mx": F.lit(1).cast("long"), "my": F.lit(1).cast("long")})
    if left.where("mx > 1").limit(1).count() or right.where("my > 1").limit(1).count():
        out = named
        for t, c in ((left, "x"), (right, "y")):
            out = out.join(t.where(name(t.columns[0]) == F.col(c)).select(c, f"m{c}"), c)
        out = written(out.select("x", "mx", "y", "my"), "twins")
        pairs = out.agg(F.sum(F.col("mx").cast(EXACT) * F.col("my").cast("decimal(18,0)")).cast(EXACT)).first()[0] or 0
        if pairs != edges.count():  # never seen; each vertex is a class then
            one = F.lit(1).cast("long")
            left, right = (t.select(t.columns[0], name(t.columns[0]).alias(c)) for t, c in ((left, "x"), (right, "y")))
            out = named.withColumns({"mx": one, "my": one})
    return Twins(out.select("x", "mx", "y", "my"), left.select("u", "x"), right.select("v", "y"))


def _by(key: str):
    from pyspark.sql import Window

    return Window.orderBy(key)


def growth(edges: DataFrame, p: int, q: int) -> tuple[float, float]:
    """Rows that growing p left vertices, or q right ones, makes at most: tuples of each length around each vertex."""
    x, y = edges.columns[0], "y" if "y" in edges.columns else "v"

    def rows(center: str, size: int) -> float:
        d = edges.groupBy(center).agg(F.count(F.lit(1)).alias("d"))
        return d.agg(F.coalesce(F.sum(sum((binomial(F.col("d"), k) for k in range(2, size + 1)), F.lit(0.0))), F.lit(0.0))).first()[0]

    return rows(y, p), rows(x, q)


def class_tuples(t: Twins, p: int, q: int) -> DataFrame:
    """us, ys, w: every set of 1 to p left classes that together have q or more neighbours; us, ys: arrays of (c, m),
    class and size; w: neighbours in common. A set grows by later classes only, through the edges of its neighbours."""
    e = t.edges.select(F.struct(F.col("x.n").alias("n"), F.col("x").alias("c")).alias("r"), F.struct(F.col("x").alias("c"), F.col("mx").alias("m")).alias("u"), F.struct(F.col("y").alias("c"), F.col("my").alias("m")).alias("n"))
    level = e.groupBy("u", "r").agg(F.collect_list("n").alias("ys"), F.sum("n.m").alias("w")).where(F.col("w") >= q)
    level = written(level.select(F.array("u").alias("us"), F.col("r").alias("last"), "ys", "w"), "classes")
    out = level
    for _ in range(2, p + 1):
        wide = level.select("us", "last", F.explode("ys").alias("n"))
        grown = wide.join(e, "n").where("r > last").groupBy("us", "u", "r").agg(F.collect_list("n").alias("ys"), F.sum("n.m").alias("w")).where(F.col("w") >= q)
        level = written(grown.select(F.concat("us", F.array("u")).alias("us"), F.col("r").alias("last"), "ys", "w"), "classes")
        out = out.unionByName(level)
    return out.select("us", "ys", "w")


def ways(us: Column, p: int, own: Column | None = None) -> Column:
    """In how many ways p vertices are chosen that take at least one of each class. own: the class of one vertex that is
    chosen for sure."""
    zero, one = F.lit(0).cast(EXACT), F.lit(1).cast(EXACT)

    def merge(acc: Column, u: Column) -> Column:
        def choose(k: int) -> Column:
            plain = binomial(u["m"], k, EXACT)
            return plain if own is None else F.when(u["c"] == own, binomial(u["m"] - 1, k - 1, EXACT)).otherwise(plain)

        c = [choose(k) for k in range(1, p + 1)]
        term = lambda n: sum((F.get(acc, F.lit(n - k)) * c[k - 1] for k in range(1, n + 1)), zero).cast(EXACT)
        return F.array(zero, *[F.coalesce(term(n), zero) for n in range(1, p + 1)])

    return F.get(F.aggregate(us, F.array(one, *[zero] * p), merge), F.lit(p))


def oriented(t: Twins, p: int, q: int) -> tuple[Twins, int, int, bool]:
    """The side whose tuples make fewer rows as the left one: (classes, p, q, whether sides were exchanged)."""
    left, right = growth(t.edges, p, q)
    return (t.turned(), q, p, True) if right < left else (t, p, q, False)


def _blocks(t: Twins) -> DataFrame:
    """(block, m, xs, ys, w, by_x): the edges of each block of left classes in one row, sorted by y, as bytes: classes by place
    (32 bits), y as numbers and their sizes (64 bits; none where all are 1), the order by class; m: sizes of the classes."""
    e = t.edges
    if not isinstance(e.schema["y"].dataType, IntegralType):
        numbers = written(e.select("y").distinct().withColumn("n", F.monotonically_increasing_id()), "numbers")
        e = e.join(numbers, "y").withColumn("y", F.col("n"))

    def pack(key: tuple, tables: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = pa.Table.from_batches(list(tables)).combine_chunks()
        x, y, w = e["x"].chunk(0).dictionary_encode().indices.to_numpy(), e["y"].to_numpy(), e["my"].to_numpy()
        m = np.zeros(x.max() + 1, np.int64)
        m[x] = e["mx"].to_numpy()
        order = np.argsort(y, kind="stable")
        x, y, w = x[order].astype(np.uint32), y[order], w[order]
        row = (key[0].as_py(), m.tobytes(), x.tobytes(), y.tobytes(), b"" if (w == 1).all() else w.tobytes(), np.argsort(x, kind="stable").astype(np.uint32).tobytes())
        yield pa.record_batch([pa.array([c], pa.int32() if i == 0 else pa.binary()) for i, c in enumerate(row)], ["block", "m", "xs", "ys", "w", "by_x"])

    n = max(1, -(-e.count() // BLOCK))
    block = F.pmod(F.xxhash64("x"), F.lit(n)).cast("int").alias("block")
    rows = e.select(block, "x", F.col("mx").cast("long").alias("mx"), F.col("y").cast("long").alias("y"), F.col("my").cast("long").alias("my"))
    return rows.groupBy("block").applyInArrow(pack, "block int, m binary, xs binary, ys binary, w binary, by_x binary")


def _met(a: dict, b: dict, same: bool, o: int) -> int:
    """Bicliques with a vertex of one class of a, one of a class of b (of a later one, if these are the same) and o right ones."""
    of = lambda t, c, kind=np.int64: np.frombuffer(t[c].as_buffer(), kind)
    (xa, ya, ma), (xb, yb, mb) = ((of(t, "xs", np.uint32), of(t, "ys"), of(t, "m")) for t in (a, b))
    weighted = len(a["w"].as_buffer()) or len(b["w"].as_buffer())
    wa = of(a, "w") if len(a["w"].as_buffer()) else np.ones(len(xa) if weighted else 0, np.int64)
    by_x = of(a, "by_x", np.uint32)
    first, last = (np.searchsorted(yb, ya, side)[by_x] for side in ("left", "right"))
    x, size, count = xa[by_x].astype(np.int64), np.int64(len(mb)), last - first
    wa = wa[by_x] if weighted else wa
    starts = np.append(np.nonzero(np.diff(x, prepend=-1))[0], len(x))  # where each class's edges begin
    ends, n, at = np.append(0, np.cumsum(count)), 0, 0
    plain = (ma == 1).all() and (mb == 1).all()
    while at < len(starts) - 1:  # so many meetings at once, and one class's at least
        to = max(at + 1, int(np.searchsorted(ends[starts], ends[starts[at]] + MEETINGS, "right")) - 1)
        i, j = starts[at], starts[to]
        at, c = to, count[i:j]
        place = np.arange(c.sum()) + np.repeat(first[i:j] - np.cumsum(c) + c, c)
        code = np.repeat(x[i:j] * size, c) + xb[place]
        w = np.repeat(wa[i:j], c) if weighted else None
        if same:
            later = code % size > code // size
            code, w = code[later], w[later] if weighted else None
        if weighted:
            order = np.argsort(code)
            code, w = code[order], w[order]
        else:
            code.sort()
        if not len(code):
            continue
        runs = np.nonzero(np.diff(code, prepend=-1))[0]
        shared = np.add.reduceat(w, runs) if weighted else np.diff(runs, append=len(code))
        enough = shared >= o
        shared, code = shared[enough], code[runs][enough]
        values, at_value = np.unique(shared, return_inverse=True)
        if plain:
            pairs = np.bincount(at_value, minlength=len(values)).tolist()
        else:
            both = ma[code // size] * mb[code % size]
            halves = [np.zeros(len(values), np.int64) for _ in range(2)]
            np.add.at(halves[0], at_value, both >> 31)
            np.add.at(halves[1], at_value, both & ((1 << 31) - 1))
            pairs = [(h << 31) + low for h, low in zip(halves[0].tolist(), halves[1].tolist(), strict=True)]
        n += sum(k * comb(v, o) for k, v in zip(pairs, values.tolist(), strict=True))
    return n


def pair_count(t: Twins, o: int) -> DataFrame:
    """One row: bicliques of two left vertices and o right ones. Left classes are dealt out to blocks, a block's edges are
    one packed row, and each two blocks count their pairs in one place: neither meetings nor pairs are shuffled or stored."""
    packed = written(_blocks(t), "class-blocks")
    released(packed.sparkSession)
    side = lambda n: packed.select(*[F.col(c).alias(f"{c}_{n}") for c in packed.columns])

    def met(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in source:
            for i in range(batch.num_rows):
                a, b = ({c.removesuffix(end): batch.column(c)[i] for c in batch.schema.names if c.endswith(end)} for end in ("_a", "_b"))
                yield pa.record_batch([pa.array([str(_met(a, b, a["block"].as_py() == b["block"].as_py(), o))])], ["n"])

    across = side("a").crossJoin(side("b")).where("block_a <= block_b").mapInArrow(met, "n string")
    within = t.edges.groupBy("x", "mx").agg(F.sum("my").alias("w")).where("mx > 1")
    within = within.select((binomial(F.col("mx"), 2, EXACT) * binomial(F.col("w"), o, EXACT)).cast(EXACT).alias("n"))
    n = across.select(F.col("n").cast(EXACT).alias("n")).unionByName(within)
    return n.agg(F.coalesce(F.sum("n").cast(EXACT), F.lit(0).cast(EXACT)).alias("bicliques"))


def count(edges: DataFrame, p: int, q: int) -> DataFrame:
    """One row: bicliques."""
    if 2 in (p, q):
        r = representatives(edges)
        left, right = growth(r.edges, p, q)
        if (s := q if right < left else p) == 2:
            return pair_count(r.turned() if right < left else r, p + q - s)
    t, s, o, _ = oriented(twins(edges), p, q)
    n = class_tuples(t, s, o).select((ways(F.col("us"), s) * binomial(F.col("w"), o, EXACT)).cast(EXACT).alias("n"))
    return n.agg(F.coalesce(F.sum("n").cast(EXACT), F.lit(0).cast(EXACT)).alias("bicliques"))


def participation(edges: DataFrame, p: int, q: int, side: str = "u") -> DataFrame:
    """(vertex, bicliques): in how many each vertex of a side is, 0 left out; twins are in as many."""
    t, s, o, turned = oriented(twins(edges), p, q)
    tuples = class_tuples(t, s, o)
    if (side == "u") != turned:  # the side that grows
        rows = tuples.select(F.explode("us").alias("own"), "us", "w").select(F.col("own.c").alias("c"), (ways(F.col("us"), s, F.col("own.c")) * binomial(F.col("w"), o, EXACT)).cast(EXACT).alias("n"))
    else:
        rows = tuples.select(F.explode("ys").alias("own"), "us", "w").select(F.col("own.c").alias("c"), (ways(F.col("us"), s) * binomial(F.col("w") - 1, o - 1, EXACT)).cast(EXACT).alias("n"))
    members = (t.left if (side == "u") != turned else t.right).toDF("vertex", "c")
    return rows.groupBy("c").agg(F.sum("n").cast(EXACT).alias("bicliques")).where("bicliques > 0").join(members, "c").select("vertex", "bicliques")


def anchor_parts(t: Twins, q: int) -> DataFrame:
    """anchor, ma, w, u, mu, v, mv: for each left class with q or more neighbours (w) the edges of later ones that share q
    with it, to its own; one row with nulls where there are none."""
    e = t.edges.select(F.struct(F.col("x.n").alias("n"), F.col("x").alias("c")).alias("r"), "x", "mx", "y", "my")
    first = e.groupBy("x").agg(F.first("r").alias("ra"), F.first("mx").alias("ma"), F.sum("my").alias("w")).where(F.col("w") >= q)
    a = e.join(first.select("x", "ra", "ma", "w"), "x").select(F.col("x").alias("anchor"), "ra", "ma", "w", "y")
    later = e.select("r", F.col("x").alias("u"), F.col("mx").alias("mu"), "y", F.col("my").alias("mv"))
    wedges = written(a.join(later, "y").where("r > ra").select("anchor", "u", "mu", F.col("y").alias("v"), "mv"), "wedges")
    enough = wedges.groupBy("anchor", "u").agg(F.sum("mv").alias("n")).where(F.col("n") >= q).select("anchor", "u")
    parts = wedges.join(enough, ["anchor", "u"], "left_semi")
    return first.select(F.col("x").alias("anchor"), "ma", "w").join(parts, "anchor", "left")


def parts_oriented(t: Twins, p: int, q: int) -> tuple[Twins, int, int]:
    """The side whose pairs make fewer rows as the left one."""
    left, right = growth(t.edges, 2, 2)
    return (t.turned(), q, p) if q >= 2 and right < left else (t, p, q)
