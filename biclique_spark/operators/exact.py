"""Exact counters: growing left vertices one by one, and pivot edges closed with binomials."""

from __future__ import annotations

from collections.abc import Callable
from math import comb

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biclique_spark.functions.scalar import EXACT, binomial
from biclique_spark.operators import twins
from biclique_spark.operators.graph import anchor_ranks, common_neighbors, core_reduce, split_by_anchor
from biclique_spark.sources.io import written

#: Bicliques that a piece of a listing has, about.
PIECE = 1 << 22


def grow_left(edges: DataFrame, p: int, q: int) -> DataFrame:
    """us, vs: ordered left tuples of p vertices with their q or more common neighbours. A tuple grows by later
    vertices only, through the edges of its neighbours, and is dropped when it has fewer than q."""
    ranked = edges.join(anchor_ranks(edges), "u")
    out = ranked.groupBy("u", "r").agg(F.sort_array(F.collect_set("v")).alias("vs")).where(F.size("vs") >= q).select(F.array("u").alias("us"), F.col("r").alias("last"), "vs")
    for size in range(2, p + 1):
        out = written(out, "tuples") if size > 2 else out
        wide = out.select("us", "last", F.explode("vs").alias("v"))
        grown = wide.join(ranked, "v").where("r > last").groupBy("us", "u", "r").agg(F.sort_array(F.collect_list("v")).alias("vs"))
        out = grown.where(F.size("vs") >= q).select(F.concat("us", F.array("u")).alias("us"), F.col("r").alias("last"), "vs")
    return out.select("us", "vs")


def count_vertex_expand(edges: DataFrame, p: int, q: int, reduce: bool = True) -> DataFrame:
    """One row: bicliques. Vertices of the side that makes fewer rows grow one by one, as classes of twins."""
    return twins.count(core_reduce(edges, p, q) if reduce else edges, p, q)


def count_vertex_expand_kernel(edges: DataFrame, p: int, q: int) -> DataFrame:
    """The same count, by a kernel for each anchor's part, which holds the anchor's two-step neighbourhood. Anchors and
    what grows are classes of twins, of the side with fewer wedges."""
    if p < 2:
        raise ValueError("p must be at least 2")
    t, p, q = twins.parts_oriented(twins.twins(core_reduce(edges, p, q)), p, q)

    def tuples(left: dict[int, int], right: dict[int, int], wl: list[int], wr: list[int]) -> list[int]:
        """Bicliques with 1 to p - 1 left vertices of the part."""
        near, found = [left[i] for i in range(len(wl))], [0] * p

        def grow(start: int, mask: int, chosen: int, factor: int) -> None:
            for i in range(start, len(near)):
                both = mask & near[i]
                n = sum(wr[j] for j in bits(both))
                if n < q:
                    continue
                for k in range(1, min(wl[i], p - 1 - chosen) + 1):
                    more = factor * comb(wl[i], k)
                    found[chosen + k] += more * comb(n, q)
                    if chosen + k < p - 1:
                        grow(i + 1, both, chosen + k, more)

        grow(0, (1 << len(wr)) - 1, 0, 1)
        return found[1:]

    return _by_class_anchors(twins.anchor_parts(t, q), p, q, tuples)


def _by_class_anchors(parts: DataFrame, p: int, q: int, count: Callable[..., list[int]]) -> DataFrame:
    """One row: bicliques by their first left class, from k of its vertices and what ``count`` (neighbours as bits and
    sizes of the part's classes) finds with 1 to p - 1 later vertices."""

    def one(group: pd.DataFrame) -> pd.DataFrame:
        m, w = int(group["ma"].iloc[0]), int(group["w"].iloc[0])
        total = comb(m, p) * comb(w, q)
        if group["mu"].notna().any():
            key = lambda c: [tuple(x.values()) if isinstance(x, dict) else tuple(x) for x in group[c]]
            us, vs = key("u"), key("v")
            nu, nv = {u: i for i, u in enumerate(dict.fromkeys(us))}, {v: i for i, v in enumerate(dict.fromkeys(vs))}
            wl, wr = [0] * len(nu), [0] * len(nv)
            left, right = dict.fromkeys(range(len(nu)), 0), dict.fromkeys(range(len(nv)), 0)
            for u, v, mu, mv in zip(us, vs, group["mu"], group["mv"], strict=True):
                i, j = nu[u], nv[v]
                wl[i], wr[j] = int(mu), int(mv)
                left[i] |= 1 << j
                right[j] |= 1 << i
            if p > 1:
                total += sum(comb(m, p - k) * n for k, n in enumerate(count(left, right, wl, wr), 1))
        return pd.DataFrame({"n": [str(total)]})

    return _summed(parts.groupBy("anchor").applyInPandas(lambda g: one(g), "n string"))


def _summed(counts: DataFrame) -> DataFrame:
    return counts.agg(F.coalesce(F.sum(F.col("n").cast(EXACT)).cast(EXACT), F.lit(0).cast(EXACT)).alias("bicliques"))


def pieces(edges: DataFrame, p: int, q: int) -> tuple[DataFrame, int, bool]:
    """(k, ls, rs, piece, of), their number, whether sides were exchanged: sets of k left classes of twins that bicliques are
    of, with the members of these (ls: class, vertex) and their common neighbours (rs). A set with many bicliques is there
    several times, as a piece of so many."""
    t, s, o, turned = twins.oriented(twins.twins(core_reduce(edges, p, q)), p, q)
    n = (twins.ways(F.col("us"), s) * binomial(F.col("w"), o, EXACT)).cast("double")
    sets = twins.class_tuples(t, s, o).withColumn("n", n).where("n > 0").withColumn("id", F.monotonically_increasing_id())
    sets = written(sets.select("id", "us", "ys", F.ceil(F.col("n") / PIECE).alias("of")), "sets")
    of = lambda m, c: m.groupBy(F.col(m.columns[1]).alias("c")).agg(F.sort_array(F.collect_list(m.columns[0])).alias(c))
    ls = sets.select("id", F.posexplode("us").alias("at", "m")).select("id", "at", "m.c").join(of(t.left, "names"), "c")
    ls = ls.groupBy("id").agg(F.sort_array(F.flatten(F.collect_list(F.transform("names", lambda x: F.struct("at", x.alias("x")))))).alias("ls"))
    rs = sets.select("id", F.explode("ys.c").alias("c")).join(of(t.right, "names"), "c")
    rs = rs.groupBy("id").agg(F.sort_array(F.flatten(F.collect_list("names"))).alias("rs"))
    out = sets.select("id", F.size("us").alias("k"), "of").join(ls, "id").join(rs, "id")
    out = out.select("k", "ls", "rs", F.explode(F.sequence(F.lit(0).cast("long"), F.col("of") - 1)).alias("piece"), "of")
    return out, int(sets.agg(F.sum("of")).first()[0] or 0), turned


def list_bicliques(edges: DataFrame, p: int, q: int) -> DataFrame:
    """us, vs of every biclique, sorted by key; as many rows as there are bicliques. Only pieces of sets of classes are
    stored and dealt out; their bicliques are listed one by one as they are read."""
    rows, n, turned = pieces(edges, p, q)
    s, o = (q, p) if turned else (p, q)

    def pick(rows: DataFrame, of: str, name: str, at: str) -> DataFrame:
        """A row for each element, with those behind it; the last pick needs no more of them."""
        kept = [F.col(c) for c in rows.columns if c != of]
        return rows.select("*", F.posexplode(of).alias(at, name)).select(*kept, at, name, F.slice(of, F.col(at) + 2, F.size(of)).alias(of))

    rows = pick(rows.repartition(max(1, n // 4)).withColumn("n", F.size("rs")), "ls", "l1", "i").where(f"l1.at = 0 and k <= {s}")
    rows = pick(rows, "rs", "r1", "j").where("(i * n + j) % of = piece").select("k", "ls", "l1", "rs", "r1")
    # Left vertices come in order of classes: each is of the class before it or the next one, and none may be left out.
    for m in range(2, s + 1):
        rows = pick(rows, "ls", f"l{m}", "d").drop("d").where(f"l{m}.at <= l{m - 1}.at + 1 and k - 1 - l{m}.at <= {s - m}")
    rows = rows.where(f"l{s}.at = k - 1").select(F.sort_array(F.array(*[f"l{m}.x" for m in range(1, s + 1)])).alias("us"), "rs", "r1")
    for m in range(2, o):
        rows = pick(rows, "rs", f"r{m}", "d").drop("d")
    rows = rows.select("*", F.explode("rs").alias(f"r{o}")) if o > 1 else rows
    rows = rows.select("us", F.array(*[f"r{m}" for m in range(1, o + 1)]).alias("vs"))
    return rows.select(F.col("vs").alias("us"), F.col("us").alias("vs")) if turned else rows


def pivot_count(left: dict[int, int], right: dict[int, int], p: int, q: int, wl: list[int] | None = None, wr: list[int] | None = None) -> int:
    """Bicliques with p of the left and q of the right vertices of a small graph. left and right: neighbours of each
    vertex as bits. wl, wr: numbers of twins that each one stands for; twins become free together, and 1, 2, .. of
    them are held.

    A branch has candidates (bits a, b) and on each side vertices that are held (used for sure) and free (used or
    not), all adjacent to everything opposite. Without edges among the candidates at most one side's candidates can
    be used. Otherwise the edge with most neighbours among them is the pivot: its ends become free, for the bicliques
    among their neighbours; the others use some outsider, and the first one used is held.
    """

    def leaf(a: int, b: int, hl: int, fl: int, hr: int, fr: int) -> int:
        need_l, need_r = p - hl, q - hr
        if need_l < 0 or need_r < 0:
            return 0
        all_l, all_r = comb(fl + a, need_l) * comb(fr, need_r), comb(fl, need_l) * comb(fr + b, need_r)
        return all_l + all_r - comb(fl, need_l) * comb(fr, need_r)

    def size(x: int, w: list[int] | None) -> int:
        return x.bit_count() if w is None else sum(w[i] for i in bits(x))

    def branch(a: int, b: int, hl: int, fl: int, hr: int, fr: int) -> int:
        if hl > p or hr > q or hl + fl + size(a, wl) < p or hr + fr + size(b, wr) < q:
            return 0
        best, pivot = -1, None
        for u in bits(a):
            near = left[u] & b
            if near:
                v = max(bits(near), key=lambda v: (right[v] & a).bit_count())
                score = near.bit_count() + (right[v] & a).bit_count()
                if score > best:
                    best, pivot = score, (u, v)
        if pivot is None:
            return leaf(size(a, wl), size(b, wr), hl, fl, hr, fr)
        u, v = pivot
        in_a, in_b = right[v] & a & ~(1 << u), left[u] & b & ~(1 << v)
        total = branch(in_a, in_b, hl, fl + (wl[u] if wl else 1), hr, fr + (wr[v] if wr else 1))
        rest = a
        for x in bits(a & ~right[v]):
            rest &= ~(1 << x)
            for k in range(1, min(wl[x] if wl else 1, p - hl) + 1):
                total += (comb(wl[x], k) if wl else 1) * branch(rest, b & left[x], hl + k, fl, hr, fr)
        inside, rest = a & right[v], b
        for y in bits(b & ~left[u]):
            rest &= ~(1 << y)
            for k in range(1, min(wr[y] if wr else 1, q - hr) + 1):
                total += (comb(wr[y], k) if wr else 1) * branch(inside & right[y], rest, hl, fl, hr + k, fr)
        return total

    a = sum(1 << u for u in left)
    b = sum(1 << v for v in right)
    return branch(a, b, 0, 0, 0, 0)


def bits(x: int):
    while x:
        low = x & -x
        yield low.bit_length() - 1
        x ^= low


def count_edge_pivot(edges: DataFrame, p: int, q: int, anchors: DataFrame | None = None, reduce: bool = True) -> DataFrame:
    """One row: bicliques, by the pivot kernel on each left anchor's part. With ``anchors`` (u) only those whose first
    left vertex is among them. Anchors are classes of twins, of the side with fewer wedges; or of the left side, where
    ``anchors`` has all vertices of a degree or none; or else single vertices."""
    core = core_reduce(edges, p, q) if reduce else edges
    if p > 1:
        t = twins.twins(core)
        pivots = lambda p, q: lambda *part: [pivot_count(*part[:2], n, q, *part[2:]) for n in range(1, p)]
        if anchors is None:
            t, p, q = twins.parts_oriented(t, p, q)
            return _by_class_anchors(twins.anchor_parts(t, q), p, q, pivots(p, q))
        chosen = t.left.join(anchors.select("u", F.lit(1).alias("chosen")), "u", "left").groupBy("x").agg(F.count(F.lit(1)).alias("n"), F.count("chosen").alias("chosen"))
        mixed = chosen.groupBy("x.n").agg(F.sum("n").alias("all"), F.sum("chosen").alias("some")).where("0 < some and some < all")
        if not mixed.limit(1).count():
            parts = twins.anchor_parts(t, q).join(chosen.where("chosen > 0").select(F.col("x").alias("anchor")), "anchor", "left_semi")
            return _by_class_anchors(parts, p, q, pivots(p, q))
    parts = split_by_anchor(core, p, q, anchors=anchors)
    if p == 2:
        n = parts.groupBy("anchor", "u").agg(F.count(F.lit(1)).alias("n"))
        return n.agg(F.coalesce(F.sum(binomial(F.col("n"), q, EXACT)).cast(EXACT), F.lit(0).cast(EXACT)).alias("bicliques"))

    def count(group: pd.DataFrame) -> pd.DataFrame:
        us = {u: i for i, u in enumerate(group["u"].unique())}
        vs = {v: i for i, v in enumerate(group["v"].unique())}
        left, right = dict.fromkeys(range(len(us)), 0), dict.fromkeys(range(len(vs)), 0)
        for u, v in zip(group["u"], group["v"], strict=True):
            left[us[u]] |= 1 << vs[v]
            right[vs[v]] |= 1 << us[u]
        return pd.DataFrame({"n": [str(pivot_count(left, right, p - 1, q))]})

    return _summed(parts.groupBy("anchor").applyInPandas(lambda g: count(g), "n string"))


def count_pairs_closed_form(edges: DataFrame, q: int) -> DataFrame:
    """One row: (2,q)-bicliques, from the shared neighbours of left pairs."""
    n = common_neighbors(edges, "u", q)
    return n.agg(F.coalesce(F.sum(binomial(F.col("n"), q, EXACT)).cast(EXACT), F.lit(0).cast(EXACT)).alias("bicliques"))


def sql_core(edges_sql: str, p: int, q: int, rounds: int) -> str:
    """CTEs r0..r<rounds> in DuckDB's SQL: a fixed number of rounds of core reduction."""
    out = [f"r0 as materialized ({edges_sql})"]
    for i in range(rounds):
        out.append(
            f"x{i} as materialized (select u, v from r{i} where u in (select u from r{i} group by u having count(*) >= {q})), "
            f"r{i + 1} as materialized (select u, v from x{i} where v in (select v from x{i} group by v having count(*) >= {p}))"
        )
    return ",\n".join(out)


def sql_count(edges_sql: str, p: int, q: int, rounds: int = 3) -> str:
    """DuckDB SQL: bicliques by growing left tuples."""
    cols = ["u1"]
    ctes = [sql_core(edges_sql, p, q, rounds), f"g as materialized (select * from r{rounds})", "t1 as materialized (select u as u1, v from g)"]
    for i in range(2, p + 1):
        old = ", ".join(f"t.{c}" for c in cols)
        cols.append(f"u{i}")
        ctes.append(f"w{i} as materialized (select {old}, g.u as u{i}, t.v from t{i - 1} t join g on g.v = t.v and g.u > t.u{i - 1})")
        names = ", ".join(cols)
        ctes.append(f"t{i} as materialized (select * from w{i} semi join (select {names} from w{i} group by {names} having count(*) >= {q}) using ({names}))")
    names = ", ".join(cols)
    n_over = " * ".join(f"(n - {i})" for i in range(q))
    fact = 1
    for i in range(2, q + 1):
        fact *= i
    return f"with {', '.join(ctes)} select coalesce(sum({n_over} // {fact}), 0)::decimal(38,0) as bicliques from (select {names}, count(*)::hugeint as n from t{p} group by {names})"
