"""Every registered query, with DuckDB SQL where SQL can say the same."""

from __future__ import annotations

from collections.abc import Callable
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from biclique_spark.functions import pattern, scalar
from biclique_spark.operators import coloring, estimator, exact, graph as G, hybrid, measures, sampler, zigzag
from biclique_spark.operators.index import broom_index, broom_list, broom_total, colored_by_key, layer_sums, long_index, sql_layers, stored
from biclique_spark.plans import workloads
from biclique_spark.sources.catalog import SQL, graph
from biclique_spark.sources.io import released, written
from biclique_spark.streaming import edges as streaming

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

SEED, T = 7, 60


def put(name: str, sql: str | None = None):
    def register(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


def big(df: DataFrame, *names: str) -> DataFrame:
    """Exact counts as double, for comparison across engines."""
    return df.withColumns({n: F.col(n).cast("double") for n in names})


# --- Graphs ------------------------------------------------------------------------------------------------------

_STATS = ("customer_part", "supplier_part", "customer_supplier", "user_type", "user_k", "user_hour", "page_href", "doc_line", "conv_token", "vec_topdim")
put("graph_stats", " union all ".join(f"select '{g}' as graph, count(distinct u) as n_left, count(distinct v) as n_right, count(*) as n_edges from ({SQL[g]})" for g in _STATS))(
    lambda s, d: workloads.dataset_statistics(s, d, _STATS)
)
for _g in ("customer_part", "supplier_part", "order_part", "order_supplier", "customer_supplier", "nation_part", "customer_brand", "user_type", "user_k", "user_hour", "page_href", "doc_line", "doc_label", "vec_topdim"):
    put(f"edges_{_g}", SQL[_g])(lambda s, d, g=_g: graph(s, d, g))
for _g in ("doc_token", "conv_token", "item_token", "page_token"):
    put(f"edges_{_g}", SQL[_g])(lambda s, d, g=_g: graph(s, d, g))

put(
    "degree_histogram",
    f"with g as ({SQL['customer_part']}) select side, degree, count(*) as n from (select 'u' as side, count(*) as degree from g group by u union all select 'v', count(*) from g group by v) group by side, degree",
)(lambda s, d: G.degrees(graph(s, d, "customer_part")).groupBy("side", "degree").agg(F.count(F.lit(1)).alias("n")))
put("adjacency", f"select u as id, list_sort(list(v)) as nbrs from ({SQL['customer_supplier']}) group by u")(lambda s, d: G.adjacency(graph(s, d, "customer_supplier"), "u"))
put("transpose", f"select v as u, u as v from ({SQL['user_k']})")(lambda s, d: G.transpose(graph(s, d, "user_k")))
put("common_neighbor_pairs", f"with g as ({SQL['customer_part']}) select a.u as a, b.u as b, count(*) as n from g a join g b on a.v = b.v and a.u < b.u group by 1, 2 having count(*) >= 4")(
    lambda s, d: G.common_neighbors(graph(s, d, "customer_part"), "u", 4)
)
put("core_reduce_3_3", f"with {exact.sql_core(SQL['doc_line'], 3, 3, 12)} select u, v from r12")(lambda s, d: G.core_reduce(graph(s, d, "doc_line"), 3, 3))
put(
    "split_anchor_sizes",
    f"""with g as materialized ({SQL['page_href']}), k as (select u, count(*) as d from g group by u), w as materialized (
    select a.u as anchor, b.u as u, b.v from g a join g b on a.v = b.v join k x on x.u = a.u join k y on y.u = b.u where (y.d, b.u) > (x.d, a.u)),
    e as (select anchor, u from w group by 1, 2 having count(*) >= 3) select anchor, count(*) as n_edges from w semi join e using (anchor, u) group by anchor""",
)(lambda s, d: G.split_by_anchor(graph(s, d, "page_href"), 3, 3).groupBy("anchor").agg(F.count(F.lit(1)).alias("n_edges")))
_SHARE = int(0.6 * (1 << scalar.DRAW_BITS))
put(
    "vertex_sample_60",
    f"select u, v from ({SQL['customer_part']}) where {scalar.draw_sql('1', chr(39) + 'u' + chr(39), 'u')} < {_SHARE} and {scalar.draw_sql('1', chr(39) + 'v' + chr(39), 'v')} < {_SHARE}",
)(lambda s, d: G.sample_vertices(graph(s, d, "customer_part"), 0.6, 1))
put("edge_sample_80", f"select u, v from ({SQL['customer_part']}) where {scalar.draw_sql('1', 'u', 'v')} < {int(0.8 * (1 << scalar.DRAW_BITS))}")(
    lambda s, d: G.sample_edges(graph(s, d, "customer_part"), 0.8, 1)
)
put(
    "encoded_edges",
    f"select count(*) as n_edges, count(distinct u) as n_left, max(u) as max_u, count(distinct v) as n_right, max(v) as max_v from (select dense_rank() over (order by u) - 1 as u, dense_rank() over (order by v) - 1 as v from ({SQL['doc_line']}))",
)(lambda s, d: G.encode_vertices(graph(s, d, "doc_line"))[0].agg(F.count(F.lit(1)).alias("n_edges"), F.count_distinct("u").alias("n_left"), F.max("u").alias("max_u"), F.count_distinct("v").alias("n_right"), F.max("v").alias("max_v")))

# --- Pattern and index -------------------------------------------------------------------------------------------


def _sizes_sql(key: str, rows: str) -> str:
    """Numbers of parts and suppliers, 2 at least, that lines of one key have: p and q of the broom over all of them."""
    return f"select p, q from (select {key}, count(distinct l_partkey) as p, count(distinct l_suppkey) as q from {rows} group by {key}) where p >= 2 and q >= 2"


def _sizes(rows: DataFrame, key: str) -> DataFrame:
    return rows.groupBy(key).agg(F.count_distinct("l_partkey").alias("p"), F.count_distinct("l_suppkey").alias("q")).where("p >= 2 and q >= 2").select("p", "q")


@put(
    "broom_shape",
    f"with z as (select distinct p, q from ({_sizes_sql('l_orderkey', 'lineitem')})), e as (select p, q, i, (i - 1) * (q - 1) // (p - 1) + 1 as j from (select p, q, unnest(range(1, p + 1)) as i from z)"
    " union select p, q, ((j - 1) * (p - 1) + q - 2) // (q - 1) as i, j from (select p, q, unnest(range(2, q + 1)) as j from z))"
    " select p, q, (row_number() over w)::int as t, i::int as i, j::int as j, case when lead(i) over w = i then 'U' when lead(i) over w is not null then 'V' end as step from e window w as (partition by p, q order by i, j)",
)
def broom_shape(s: SparkSession, d: str) -> DataFrame:
    """The broom of each size that orders have."""
    scalar.register(s)
    _sizes(s.read.parquet(f"{d}/lineitem.parquet"), "l_orderkey").distinct().createOrReplaceTempView("broom_sizes")
    return s.sql("select z.p, z.q, b.t, b.i, b.j, b.step from broom_sizes z, lateral broom_steps(cast(z.p as int), cast(z.q as int)) b")


put(
    "broom_runs",
    f"select p, q, case when p <= q then 2 * p - 2 else 2 * q - 1 end as runs, count(*) as customers from ({_sizes_sql('o_custkey', 'orders join lineitem on o_orderkey = l_orderkey')}) group by p, q",
)(lambda s, d: _runs(s, d))


def _runs(s: SparkSession, d: str) -> DataFrame:
    """Runs of the broom of each size that customers' orders have."""
    t = lambda n: s.read.parquet(f"{d}/{n}.parquet")
    rows = t("orders").join(t("lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    runs = F.udf(lambda p, q: len(pattern.broom_runs(p, q)), "long")
    return _sizes(rows, "o_custkey").groupBy("p", "q").agg(F.count(F.lit(1)).alias("customers")).select("p", "q", runs("p", "q").alias("runs"), "customers")


def _keyed(s: SparkSession, d: str, g: str, p: int, q: int) -> DataFrame:
    return broom_index(colored_by_key(graph(s, d, g)), p, q, "decimal")


def _total_sql(g: str, p: int, q: int) -> str:
    return f"with {sql_layers(SQL[g], p, q)} select coalesce(sum(w{p + q - 1}), 0)::double as brooms from c{p + q - 1}"


for _p, _q in ((2, 2), (3, 2), (2, 3), (3, 3), (3, 4), (4, 3)):
    put(f"broom_total_{_p}_{_q}", _total_sql("customer_part", _p, _q))(lambda s, d, p=_p, q=_q: big(broom_total(_keyed(s, d, "customer_part", p, q), p, q), "brooms"))
put(
    "broom_layer_sums_3_3",
    f"with {sql_layers(SQL['supplier_part'], 3, 3)} select layer, count(*) as edges, sum(w)::double as weight from (" + " union all ".join(f"select {t} as layer, w{t} as w from c5" for t in range(1, 6)) + ") where w > 0 group by layer",
)(lambda s, d: big(layer_sums(_keyed(s, d, "supplier_part", 3, 3), 3, 3), "weight"))
put("broom_last_layer_topk", f"with {sql_layers(SQL['customer_part'], 3, 3)} select u, v, w5::double as w from c5 order by w5 desc, u, v limit 20")(
    lambda s, d: big(_keyed(s, d, "customer_part", 3, 3).select("u", "v", F.col("w5").alias("w")).orderBy(F.desc("w"), "u", "v").limit(20), "w")
)
put("broom_index_skewsafe", f"with {sql_layers(SQL['nation_part'], 3, 3)} select coalesce(sum(w5), 0)::double as brooms from c5")(
    lambda s, d: big(broom_total(broom_index(colored_by_key(graph(s, d, "nation_part")), 3, 3, "decimal", blocks=256), 3, 3), "brooms")
)
put("broom_index_long", f"with {sql_layers(SQL['page_href'], 3, 3)} select u, v, w5::double as w from c5 where w5 > 0")(
    lambda s, d: big(long_index(_keyed(s, d, "page_href", 3, 3), 3, 3).where("layer = 5").select("u", "v", "w"), "w")
)
put("brooms_listed", _total_sql("page_href", 3, 2))(lambda s, d: broom_list(colored_by_key(graph(s, d, "page_href")), 3, 2).agg(F.count(F.lit(1)).cast("double").alias("brooms")))

# --- Exact counters ----------------------------------------------------------------------------------------------


def _count(name: str, g: str, p: int, q: int, f) -> None:
    put(name, f"select bicliques::double as bicliques from ({exact.sql_count(SQL[g], p, q)})")(lambda s, d: big(f(graph(s, d, g)), "bicliques"))


_count("butterflies", "customer_part", 2, 2, lambda e: exact.count_pairs_closed_form(e, 2))
_count("exact_2_3", "customer_part", 2, 3, lambda e: exact.count_pairs_closed_form(e, 3))
_count("exact_3_2", "customer_part", 3, 2, lambda e: exact.count_vertex_expand(e, 3, 2))
_count("exact_3_3", "customer_part", 3, 3, lambda e: exact.count_vertex_expand(e, 3, 3))
_count("exact_vertex_expand", "doc_line", 3, 4, lambda e: exact.count_vertex_expand(e, 3, 4))
_count("exact_vertex_kernel", "page_href", 4, 3, lambda e: exact.count_vertex_expand_kernel(e, 4, 3))
_count("exact_edge_pivot", "page_href", 4, 4, lambda e: exact.count_edge_pivot(e, 4, 4))
_count("exact_edge_pivot_lines", "doc_line", 3, 3, lambda e: exact.count_edge_pivot(e, 3, 3))
_count("exact_transposed", "page_href", 3, 4, lambda e: exact.count_vertex_expand(G.transpose(e), 4, 3))
put(
    "list_bicliques",
    f"with g as materialized ({SQL['page_href']}), c as materialized (select u, v from g where u in (select u from g group by u having count(*) >= 3)), w as materialized (select a.u as u1, b.u as u2, c3.u as u3, a.v from c a join c b on a.v = b.v and a.u < b.u join c c3 on c3.v = a.v and b.u < c3.u)"
    " select [a.u1, a.u2, a.u3] as us, [a.v, b.v, c.v] as vs from w a join w b on (a.u1, a.u2, a.u3) = (b.u1, b.u2, b.u3) and a.v < b.v join w c on (a.u1, a.u2, a.u3) = (c.u1, c.u2, c.u3) and b.v < c.v",
)(lambda s, d: exact.list_bicliques(graph(s, d, "page_href"), 3, 3))
put(
    "complete_graph_closed_form",
    "select m * (m - 1) / 2 * (n * (n - 1) * (n - 2) / 6) as bicliques, m * (m - 1) / 2 * (n * (n - 1) * (n - 2) / 6) as brooms from (select count(distinct l_quantity)::double as m, count(distinct l_linenumber)::double as n from lineitem)",
)(lambda s, d: _complete(s.read.parquet(f"{d}/lineitem.parquet")))


def _complete(lines: DataFrame) -> DataFrame:
    """Every quantity with every line number: bicliques and brooms are as many as choices of both sides' vertices."""
    e = lines.select(F.col("l_quantity").cast("long").alias("u")).distinct().crossJoin(lines.select(F.col("l_linenumber").cast("long").alias("v")).distinct()).dropna()
    return big(exact.count_vertex_expand(e, 2, 3).crossJoin(broom_total(broom_index(colored_by_key(e), 2, 3, "decimal"), 2, 3)), "bicliques", "brooms")


put("complete_graph_events", "with u as (select count(distinct user_id)::double as m from events) select m * (m - 1) * (m - 2) / 6 * 10 as bicliques from u")(
    lambda s, d: big(exact.count_vertex_expand(graph(s, d, "user_type"), 3, 3), "bicliques")
)

# --- Sampling ----------------------------------------------------------------------------------------------------

_WALK = "page_href"


def _index(s: SparkSession, d: str, p: int, q: int, g: str = _WALK) -> tuple[DataFrame, DataFrame]:
    e = graph(s, d, g)
    return e, stored(broom_index(colored_by_key(e), p, q, "decimal"))


def _walk_sql(p: int, q: int, select: str, free: bool = False, g: str = _WALK) -> str:
    return f"with {sql_layers(SQL[g], p, q)},\n{sampler.sql_walks(p, q, T, SEED, free)} {select}"


_ESTIMATE = "select {p} as p, {q} as q, {t}::bigint as t, (select sum(w{n}) from c{n})::double as brooms, count(*) as hits, coalesce(sum(ratio), 0) / {t} as mean_ratio, (select sum(w{n}) from c{n})::double * coalesce(sum(ratio), 0) / {t} as estimate from k1"


def _estimate_sql(p: int, q: int) -> str:
    return _walk_sql(p, q, _ESTIMATE.format(p=p, q=q, t=T, n=p + q - 1))


@put("last_edge_draws", _walk_sql(3, 3, "select sample_id, u, v from k5"))
def last_edge_draws(s: SparkSession, d: str) -> DataFrame:
    _, index = _index(s, d, 3, 3)
    return sampler.sample_last_edges(index, 3, 3, T, SEED).select("sample_id", "u", "v")


@put("walk_states", _walk_sql(3, 3, "select sample_id, us, vs from k1"))
def walk_states(s: SparkSession, d: str) -> DataFrame:
    e, index = _index(s, d, 3, 3)
    return sampler.sample_walks(index, e, 3, 3, T, SEED).select("sample_id", "us", "vs")


@put("walk_ratios", _walk_sql(2, 3, "select sample_id, ratio from k1"))
def walk_ratios(s: SparkSession, d: str) -> DataFrame:
    e, index = _index(s, d, 2, 3)
    return sampler.sample_walks(index, e, 2, 3, T, SEED, contain="join").select("sample_id", "ratio")


@put("walks_local_engine", _walk_sql(3, 3, "select sample_id, us, vs from k1"))
def walks_local_engine(s: SparkSession, d: str) -> DataFrame:
    e, index = _index(s, d, 3, 3)
    return sampler.sample_walks(index, e, 3, 3, T, SEED, engine="local").select("sample_id", "us", "vs")


def _summary(s: SparkSession, d: str, p: int, q: int, engine: str) -> DataFrame:
    e, index = _index(s, d, p, q)
    walks = sampler.sample_walks(index, e, p, q, T, SEED, engine=engine)
    out = estimator.summarize(walks, broom_total(index, p, q), p, q, T)
    return big(out.select("p", "q", "t", "brooms", "hits", "mean_ratio", "estimate"), "brooms")


put("broom_estimate", _estimate_sql(3, 2))(lambda s, d: _summary(s, d, 3, 2, "join"))
put("broom_estimate_3_3", _estimate_sql(3, 3))(lambda s, d: _summary(s, d, 3, 3, "local"))
put("estimate_auto")(lambda s, d: estimator.estimate_auto(graph(s, d, "customer_part"), 3, 2, 5_000))
put("estimate_split")(lambda s, d: estimator.estimate(graph(s, d, "page_href"), 3, 3, 500, reduce="split", strategy="none"))


@put(
    "naive_estimate",
    _walk_sql(
        3, 2, f"select {T}::bigint as t, (select count(*) from k1 where (select count(*) from g where list_contains(k1.us, g.u) and list_contains(k1.vs, g.v)) = 6) as hits, (select sum(w4) from c4)::double as brooms,"
        f" (select sum(w4) from c4)::double * (select count(*) from k1 where (select count(*) from g where list_contains(k1.us, g.u) and list_contains(k1.vs, g.v)) = 6) / {T} as estimate", free=True,
    ),
)
def naive_estimate(s: SparkSession, d: str) -> DataFrame:
    e, index = _index(s, d, 3, 2)
    return sampler.naive_sample(index, e, 3, 2, T, SEED)




@put("expected_ratio_exact", f"select round(bicliques::double, 3) as estimate from ({exact.sql_count(SQL['page_href'], 3, 2)})")
def expected_ratio_exact(s: SparkSession, d: str) -> DataFrame:
    """The expectation of the estimate, followed over all walks, is the exact count."""
    e = graph(s, d, "page_href")
    return estimator.expected_ratio(colored_by_key(e), e, 3, 2).select(F.round("estimate", 3).alias("estimate"))


_BC = f"(select brooms::double as b from ({_total_sql('customer_part', 3, 2)})) x, (select bicliques::double as c from ({exact.sql_count(SQL['customer_part'], 3, 2)})) y"


def _bc(s: SparkSession, d: str) -> DataFrame:
    e = written(graph(s, d, "customer_part"), "graph")  # read by both sides; what made it is given up
    released(s)
    brooms = written(broom_total(broom_index(colored_by_key(e), 3, 2, "decimal", cut=True), 3, 2), "brooms")
    released(s)
    return brooms.crossJoin(exact.count_vertex_expand(e, 3, 2))


put("hoeffding_samples", f"select ceil(b * b / (c * c) / (2 * 0.1 * 0.1) * ln(2 / 0.05))::bigint as samples from {_BC}")(
    lambda s, d: _bc(s, d).select(scalar.required_samples(F.col("brooms"), F.col("bicliques"), 0.1, 0.05).cast("long").alias("samples"))
)
put("failure_bound", f"select least(1, 2 * exp(-2 * 0.01 * 1e9 / (b * b / (c * c)))) as bound, b / c * sqrt(ln(2 / 0.05) / (2 * 1e9)) as error from {_BC}")(
    lambda s, d: _bc(s, d).select(
        scalar.failure_bound(F.col("brooms"), F.col("bicliques"), 0.1, F.lit(1e9)).alias("bound"), scalar.error_at(F.col("brooms"), F.col("bicliques"), F.lit(1e9), 0.05).alias("error")
    )
)

# --- Zigzags and the hybrid --------------------------------------------------------------------------------------

put("zigzag_total", _total_sql("customer_part", 3, 3).replace("as brooms", "as zigzags"))(lambda s, d: big(zigzag.zigzag_total(graph(s, d, "customer_part"), 3, "decimal"), "zigzags"))
put(
    "zigzag_estimate",
    _walk_sql(
        2, 2,
        "select (select sum(w3) from c3)::double as zigzags, count(*) filter (where n >= 2) as hits, coalesce(sum(case when n >= 2 then (n - 2) / 3.0 end), 0) * (select sum(w3) from c3)::double / "
        f"{T} as estimate from (select us, vs, (select count(*) from (select v from g where list_contains(k1.us, u) group by v having count(*) = 2)) as n, "
        "(select count(*) from g where list_contains(k1.us, g.u) and list_contains(k1.vs, g.v)) as full_pairs from k1) where full_pairs = 4", free=True,
    ),
)(lambda s, d: big(zigzag.estimate_zigzag(graph(s, d, _WALK), 2, 3, T, SEED, "decimal", reduce=False).select("zigzags", "hits", "estimate"), "zigzags"))
put("hybrid_exact_parts", f"select bicliques::double as bicliques from ({exact.sql_count(SQL['doc_line'], 3, 3)})")(
    lambda s, d: hybrid.exact_parts(graph(s, d, "doc_line"), 3, 3).agg(F.sum(F.col("bicliques").cast("double")).alias("bicliques"))
)
put("hybrid_basic_estimate")(lambda s, d: hybrid.estimate_hybrid(graph(s, d, "doc_line"), 3, 3, 2_000, basic=True))

# --- Coloring ----------------------------------------------------------------------------------------------------


def _violations(strategy: str, g: str = "page_href", order: str = "random"):
    def run(s: SparkSession, d: str) -> DataFrame:
        e = G.core_reduce(graph(s, d, g), 3, 3)
        bad = None
        for side in ("u", "v"):
            colors = coloring.color_side(e, side, 3, order, 1, strategy)
            one = coloring.coloring_violations(e, colors, side, 3).select("n")
            bad = one if bad is None else bad.unionByName(one)
        return bad.agg(F.count(F.lit(1)).alias("violations"))

    return run


for _s in ("greedy", "rounds", "conflict", "none"):
    put(f"coloring_violations_{_s}", "select 0::bigint as violations")(_violations(_s))
for _o in ("asc", "desc"):
    put(f"coloring_violations_{_o}", "select 0::bigint as violations")(_violations("greedy", "doc_line", _o))
put("coloring_order_ablation")(lambda s, d: workloads.coloring_ablation(s, d, ("page_href",), ((3, 3),), (100, 1_000), 5))
put("color_counts")(lambda s, d: coloring.color_count(coloring.color_graph(G.core_reduce(graph(s, d, "page_href"), 3, 3), 3, 3)))


@put("colored_survivors", f"select bicliques::double as survivors from ({exact.sql_count(SQL['doc_line'], 3, 3)})")
def colored_survivors(s: SparkSession, d: str) -> DataFrame:
    """Under any legal coloring just one broom of each biclique completes."""
    e = G.core_reduce(graph(s, d, "doc_line"), 3, 3)
    colored = coloring.color_graph(e, 3, 3, relabel=2)
    return coloring.survivors(colored, e, 3, 3)


# --- Measures and workloads --------------------------------------------------------------------------------------



@put(
    "error_grid_rollup",
    "select p, q, avg(c) as bicliques, count(*) as cells from (" + " union all ".join(f"select {p} as p, {q} as q, bicliques::double as c from ({exact.sql_count(SQL['page_href'], p, q)})" for p in (2, 3) for q in (2, 3)) + ") group by rollup (p, q)",
)
def error_grid_rollup(s: SparkSession, d: str) -> DataFrame:
    e = graph(s, d, "page_href")
    cells = None
    for p, q in product((2, 3), repeat=2):
        one = exact.count_vertex_expand(e, p, q).select(F.lit(p).alias("p"), F.lit(q).alias("q"), F.col("bicliques").cast("double").alias("bicliques"))
        cells = one if cells is None else cells.unionByName(one)
    return measures.margins(cells, "bicliques", "rollup")


put("stage_times")(lambda s, d: workloads.stage_split(s, d, workloads.NINE, ((3, 3),), 1_000, ("broom",)))
put("memory_profile")(lambda s, d: workloads.memory(s, d, workloads.NINE, ((3, 3),), ("broom", "hybrid")))
put("time_and_error_grid")(lambda s, d: workloads.grids(s, d, ("page_href",), ((2, 2), (2, 3), (3, 2), (3, 3)), 1_000, 2))
put("errors_by_samples")(lambda s, d: workloads.against_samples(s, d, ("page_href",), ((3, 3),), (100, 1_000), 3))
put("raised_samples")(lambda s, d: workloads.raise_samples(s, d, "page_href", 2, 3, (100, 400, 1_600), 3))
put("most_colors")(lambda s, d: workloads.most_colors(s, d, ("page_href", "doc_line"), ((3, 3), (3, 4))))
put("colored_ratio_table")(lambda s, d: workloads.ratio_table(s, d, ("page_href",), ((2, 2), (2, 3), (3, 2), (3, 3))))
put("method_runtimes")(lambda s, d: workloads.runtimes(s, d, ("page_href", "doc_line"), ((3, 3),), 1_000))
put("method_errors")(lambda s, d: workloads.errors(s, d, ("page_href",), ((3, 3),), 1_000, 5))
put("vertex_scalability")(lambda s, d: workloads.scalability(s, d, ("supplier_part",), ((3, 3),), 1_000, (0.6, 0.8, 1.0), 2))
put("small_sizes")(lambda s, d: workloads.small_sizes(s, d, ("page_href",), ((3, 3), (3, 4)), 1_000))
put(
    "clustering_coefficient",
    f"""with g as materialized ({SQL['page_href']}), du as (select u, count(*) as k from g group by u), dv as (select v, count(*) as d from g group by v),
    w as (select sum((k - 1) * (d - 1))::double as wedges from g join du using (u) join dv using (v)), b as ({exact.sql_count(SQL['page_href'], 2, 2)})
    select bicliques::double as bicliques, wedges, 4 * bicliques::double / wedges as coefficient from b, w""",
)(lambda s, d: big(measures.clustering_coefficient(graph(s, d, "page_href"), 2, 2), "bicliques"))
put(
    "motif_profile_by_region",
    """with g as materialized (select distinct r_name as r, o_custkey as u, l_partkey as v from orders join lineitem on o_orderkey = l_orderkey join customer on c_custkey = o_custkey
    join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey),
    n as (select a.r, count(*) as n from g a join g b on a.r = b.r and a.v = b.v and a.u < b.u group by a.r, a.u, b.u having count(*) >= 2)
    select r as graph, 2 as p, 2 as q, ln(1 + sum(n * (n - 1) / 2)) as value from n group by r""",
)(lambda s, d: workloads.region_profiles(s, d))
put(
    "biclique_density",
    f"with g as ({SQL['doc_line']}) select bicliques::double as bicliques, n as vertices, bicliques::double / n as density from ({exact.sql_count(SQL['doc_line'], 3, 3)}), (select count(distinct u) + count(distinct v) as n from g)",
)(lambda s, d: big(measures.biclique_density(graph(s, d, "doc_line"), 3, 3), "bicliques"))
put(
    "participation_topk",
    f"""with g as materialized ({SQL['page_href']}), n as materialized (select a.u as a, b.u as b, count(*) as n from g a join g b on a.v = b.v and a.u < b.u group by 1, 2 having count(*) >= 2)
    select vertex, sum(n * (n - 1) / 2)::double as bicliques from (select a as vertex, n from n union all select b, n from n) group by vertex order by bicliques desc, vertex limit 20""",
)(lambda s, d: big(measures.participation(graph(s, d, "page_href"), 2, 2).orderBy(F.desc("bicliques"), "vertex").limit(20), "bicliques"))

# --- Streams and snapshots ---------------------------------------------------------------------------------------

put("windowed_graphs", "select date_trunc('day', ts) as window_start, user_id as u, event_type as v, count(*) as n from events where user_id is not null and event_type is not null group by 1, 2, 3")(
    lambda s, d: streaming.windowed_graphs(s.read.parquet(f"{d}/events.parquet"))
)


@put("streamed_edges_equal_batch", SQL["user_type"])
def streamed_edges(s: SparkSession, d: str) -> DataFrame:
    """The edges that a stream over slices of the events leaves in a store."""
    from biclique_spark.sources.io import shared_dir

    folder, store = shared_dir(s, "event-slices"), shared_dir(s, "graph-store")
    s.read.parquet(f"{d}/events.parquet").repartitionByRange(3, "ts").write.parquet(folder)
    stream = streaming.stream_edges(streaming.event_stream(s, folder), late="36500 days")
    streaming.maintain_graph(stream, store)
    return s.read.parquet(store).select("u", "v").distinct()


_HALF = "(select date_trunc('day', min(ts) + (max(ts) - min(ts)) / 2) from events)"
put(
    "snapshot_diff",
    f"select u, v, 'new' as change from (select user_id as u, props as v from events where ts >= {_HALF} except select user_id, props from events where ts < {_HALF})",
)(lambda s, d: _snapshot_diff(s, d))


def _snapshot_diff(s: SparkSession, d: str) -> DataFrame:
    e = s.read.parquet(f"{d}/events.parquet")
    r = e.agg(F.min("ts").alias("a"), F.max("ts").alias("b")).select(F.date_trunc("day", F.col("a") + (F.col("b") - F.col("a")) / 2).alias("at"))
    rows = e.crossJoin(F.broadcast(r))
    pairs = lambda c: rows.where(c).select(F.col("user_id").alias("u"), F.col("props").alias("v"))
    return pairs(F.col("ts") >= F.col("at")).subtract(pairs(F.col("ts") < F.col("at"))).withColumn("change", F.lit("new"))
