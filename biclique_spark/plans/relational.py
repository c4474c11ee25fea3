"""Relational operations around the graphs: filters before building, as-of and full outer joins, ranks, frames,
statistics, layouts and set operations; and the wrappers that put estimates into SQL. Each with DuckDB SQL."""

from __future__ import annotations

import math
from collections.abc import Callable
from itertools import product

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from biclique_spark.functions import scalar
from biclique_spark.operators import estimator, exact, graph as G, measures, sampler
from biclique_spark.operators.index import array_index, broom_index, broom_total, colored_by_key, sql_layers, stored
from biclique_spark.plans import workloads
from biclique_spark.plans.queries import SEED, T, big
from biclique_spark.sources import io
from biclique_spark.sources.catalog import SQL, graph

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def put(name: str, sql: str):
    def register(f: Query) -> Query:
        QUERIES[name], ORACLES[name] = f, sql
        return f

    return register


def _t(s: SparkSession, d: str, name: str) -> DataFrame:
    return s.read.parquet(f"{d}/{name}.parquet")


# --- Building and joining ----------------------------------------------------------------------------------------


@put("filtered_edges", "select distinct l_suppkey as u, l_partkey as v from lineitem where l_quantity >= 25 and l_discount > 0.02")
def filtered_edges(s: SparkSession, d: str) -> DataFrame:
    """Predicates before the graph is built: they reach the Parquet scan."""
    rows = _t(s, d, "lineitem").where((F.col("l_quantity") >= 25) & (F.col("l_discount") > 0.02))
    return G.edges_from(rows, "l_suppkey", "l_partkey")


@put(
    "asof_first_type",
    "with k as (select min(event_type) as first_type from events), e as (select user_id as u, event_type as v, floor(epoch(ts))::bigint as seconds from events where user_id is not null and event_type is not null)"
    " select u, v, seconds, max(case when v = first_type then seconds end) over (partition by u order by seconds range between unbounded preceding and current row) as seen, count(*) over (partition by u, v, seconds) as same from e, k",
)
def asof_first_type(s: SparkSession, d: str) -> DataFrame:
    """Each action with the latest action of the first type by the same user up to then: an as-of join of a table with a
    part of itself as one frame, without a join."""
    e = _t(s, d, "events").select(F.col("user_id").alias("u"), F.col("event_type").alias("v"), F.unix_timestamp("ts").alias("seconds")).dropna()
    rows = e.crossJoin(F.broadcast(e.agg(F.min("v").alias("first_type"))))  # one row
    upto = Window.partitionBy("u").orderBy("seconds").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    seen = F.max(F.when(F.col("v") == F.col("first_type"), F.col("seconds"))).over(upto)
    return rows.select("u", "v", "seconds", seen.alias("seen"), F.count(F.lit(1)).over(Window.partitionBy("u", "v", "seconds")).alias("same"))


_PAIRS = "select a.u as a, b.u as b, count(*) as n from g a join g b on a.v = b.v and a.u < b.u group by 1, 2 having count(*) >= 2"


@put(
    "participation_compared",
    f"""with {sql_layers(SQL['page_href'], 2, 2)}, {sampler.sql_walks(2, 2, T, SEED)}, n as materialized ({_PAIRS}),
    truth as (select vertex, sum(n * (n - 1) / 2)::double as bicliques from (select a as vertex, n from n union all select b, n from n) group by vertex),
    guess as (select vertex, sum(ratio) * (select sum(w3) from c3)::double / {T} as estimate from (select unnest(us) as vertex, ratio from k1) group by vertex)
    select coalesce(truth.vertex, guess.vertex) as vertex, bicliques, round(estimate, 6) as estimate from truth full join guess on truth.vertex = guess.vertex""",
)
def participation_compared(s: SparkSession, d: str) -> DataFrame:
    """Exact and estimated participation of each left vertex, side by side: a vertex may lack either."""
    e = graph(s, d, "page_href")
    index = stored(broom_index(colored_by_key(e), 2, 2, "decimal"))
    total = float(broom_total(index, 2, 2).first()[0])
    walks = sampler.sample_walks(index, e, 2, 2, T, SEED)
    guess = measures.estimated_participation(walks, total, T).select("vertex", F.round("bicliques", 6).alias("estimate"))
    return big(measures.participation(e, 2, 2), "bicliques").join(guess, "vertex", "full")


# --- Aggregates --------------------------------------------------------------------------------------------------


@put("approximate_sides", "select true as left_close, true as right_close")
def approximate_sides(s: SparkSession, d: str) -> DataFrame:
    """Sketched vertex counts against exact ones; plans use the sketches."""
    e = graph(s, d, "customer_part")
    near = lambda c: F.abs(F.approx_count_distinct(c, 0.02) / F.count_distinct(c) - 1) < 0.1
    return e.agg(near("u").alias("left_close"), near("v").alias("right_close"))


@put(
    "degree_products",
    f"with g as materialized ({SQL['user_k']}), k as (select v, count(*)::double as d from g group by v) select u, round(sum(ln(d)), 6) as log_product, true as agrees from g join k using (v) group by u",
)
def degree_products(s: SparkSession, d: str) -> DataFrame:
    """A product over neighbours as a sum of logarithms, and by multiplying one by one."""
    e = graph(s, d, "user_k")
    rows = e.join(e.groupBy("v").agg(F.count(F.lit(1)).cast("double").alias("d")), "v")
    out = rows.groupBy("u").agg(F.sum(F.ln("d")).alias("s"), F.collect_list("d").alias("ds"))
    # A product of many neighbours is beyond a double: it is kept as a fraction below 2 and a power of two.
    power = lambda x: F.floor(F.log2(x))
    grown = lambda m, e: F.struct((m / F.pow(F.lit(2.0), power(m))).alias("m"), (e + power(m)).alias("e"))
    product_ = F.aggregate("ds", F.struct(F.lit(1.0).alias("m"), F.lit(0).cast("long").alias("e")), lambda a, x: grown(a["m"] * x, a["e"]))
    agrees = F.abs(F.exp(F.col("s") - product_["e"] * F.lit(math.log(2))) / product_["m"] - 1) < 1e-9
    return out.select("u", F.round("s", 6).alias("log_product"), agrees.alias("agrees"))


@put(
    "filtered_aggregates",
    "select user_id as u, count_if(hour(ts) < 12) as mornings, count(distinct event_type) filter (where hour(ts) >= 12) as later_types, sum(case when hour(ts) >= 18 then 1 else 0 end)::bigint as evenings from events where user_id is not null group by user_id",
)
def filtered_aggregates(s: SparkSession, d: str) -> DataFrame:
    hour = F.hour("ts")
    rows = _t(s, d, "events").where("user_id is not null").groupBy(F.col("user_id").alias("u"))
    return rows.agg(F.count_if(hour < 12).alias("mornings"), F.count_distinct(F.when(hour >= 12, F.col("event_type"))).alias("later_types"), F.sum(F.when(hour >= 18, 1).otherwise(0)).cast("long").alias("evenings"))


@put(
    "degree_statistics",
    f"with k as (select u, count(*) as d from ({SQL['customer_part']}) group by u) select round(avg(d), 9) as mean, round(stddev_samp(d), 9) as spread, min(d) as least, max(d) as most, median(d) as middle from k",
)
def degree_statistics(s: SparkSession, d: str) -> DataFrame:
    k = graph(s, d, "customer_part").groupBy("u").agg(F.count(F.lit(1)).alias("d"))
    return k.agg(F.round(F.avg("d"), 9).alias("mean"), F.round(F.stddev_samp("d"), 9).alias("spread"), F.min("d").alias("least"), F.max("d").alias("most"), F.median("d").alias("middle"))


def _cells(s: SparkSession, d: str, sizes) -> DataFrame:
    e, out = graph(s, d, "page_href"), None
    for p, q in sizes:
        one = exact.count_vertex_expand(e, p, q).select(F.lit(p).alias("p"), F.lit(q).alias("q"), F.col("bicliques").cast("double").alias("bicliques"))
        out = one if out is None else out.unionByName(one)
    return out


def _cells_sql(sizes) -> str:
    return " union all ".join(f"select {p} as p, {q} as q, bicliques::double as bicliques from ({exact.sql_count(SQL['page_href'], p, q)})" for p, q in sizes)


_SMALL = tuple(product((2, 3), repeat=2))
put("count_heat_map", f"select p, max(case when q = 2 then bicliques end) as q2, max(case when q = 3 then bicliques end) as q3 from ({_cells_sql(_SMALL)}) group by p")(
    lambda s, d: measures.heat_map(_cells(s, d, _SMALL), "bicliques").select("p", F.col("2").alias("q2"), F.col("3").alias("q3"))
)
put("count_grid_cube", f"select p, q, avg(bicliques) as bicliques, count(*) as cells from ({_cells_sql(_SMALL)}) group by cube (p, q)")(lambda s, d: measures.margins(_cells(s, d, _SMALL), "bicliques"))
_BY_P = ((2, 2), (3, 2), (4, 2))
put(
    "count_deltas",
    f"select p, bicliques, bicliques - lag(bicliques) over (order by p) as change, lead(bicliques) over (order by p) as next from ({_cells_sql(_BY_P)})",
)(
    lambda s, d: _cells(s, d, _BY_P).select(
        "p", "bicliques", (F.col("bicliques") - F.lag("bicliques").over(Window.orderBy("p"))).alias("change"), F.lead("bicliques").over(Window.orderBy("p")).alias("next")
    )
)

# --- Windows, order and sets -------------------------------------------------------------------------------------


@put(
    "degree_ranks",
    f"with k as (select u, count(*) as d from ({SQL['user_k']}) group by u) select u, d, row_number() over (order by d desc, u) as place, rank() over (order by d desc) as ranked, dense_rank() over (order by d desc) as level,"
    " ntile(4) over (order by d desc, u) as quarter, round(percent_rank() over (order by d desc), 9) as share from k",
)
def degree_ranks(s: SparkSession, d: str) -> DataFrame:
    k = graph(s, d, "user_k").groupBy("u").agg(F.count(F.lit(1)).alias("d"))
    by, total = Window.orderBy(F.desc("d")), Window.orderBy(F.desc("d"), "u")
    return k.select(
        "u", "d", F.row_number().over(total).cast("long").alias("place"), F.rank().over(by).cast("long").alias("ranked"), F.dense_rank().over(by).cast("long").alias("level"),
        F.ntile(4).over(total).cast("long").alias("quarter"), F.round(F.percent_rank().over(by), 9).alias("share"),
    )


@put(
    "edge_freshness",
    "select user_id as u, event_type as v, floor(epoch(ts))::bigint as seconds, count(*) over (partition by user_id, event_type order by floor(epoch(ts))::bigint range between 21600 preceding and current row) as recent"
    " from events where user_id is not null and event_type is not null",
)
def edge_freshness(s: SparkSession, d: str) -> DataFrame:
    """How often each edge was seen in the six hours up to each action."""
    e = _t(s, d, "events").select(F.col("user_id").alias("u"), F.col("event_type").alias("v"), F.unix_timestamp("ts").alias("seconds")).dropna()
    return e.withColumn("recent", F.count(F.lit(1)).over(Window.partitionBy("u", "v").orderBy("seconds").rangeBetween(-21600, 0)))


@put(
    "edges_by_color",
    f"with {sql_layers(SQL['customer_supplier'], 2, 2)} select u, v, cu, cv, row_number() over (order by cu, cv) as place from c1 order by cu, cv limit 100",
)
def edges_by_color(s: SparkSession, d: str) -> DataFrame:
    """The first edges in the order in which prefix sums meet them, a top-k report."""
    first = colored_by_key(graph(s, d, "customer_supplier")).orderBy("cu", "cv").limit(100)
    return first.withColumn("place", F.row_number().over(Window.orderBy("cu", "cv")).cast("long"))


_PART = "select distinct l_suppkey as u, l_partkey as v from lineitem where l_linenumber {}"
put(
    "edge_sets",
    " union all ".join(
        f"select '{name}' as kind, count(*) as edges from ({_PART.format('<= 2')} {sql} {_PART.format('>= 2')})" for name, sql in (("either", "union"), ("both", "intersect"), ("first", "except"))
    )
    + f" union all select 'first_rows' as kind, count(*) as edges from (select l_suppkey, l_partkey from lineitem where l_linenumber <= 2 except all {_PART.format('>= 2').replace('distinct ', '')})",
)(lambda s, d: _edge_sets(_t(s, d, "lineitem")))


def _edge_sets(lines: DataFrame) -> DataFrame:
    of = lambda c: lines.where(c).select(F.col("l_suppkey").alias("u"), F.col("l_partkey").alias("v"))
    a, b = of("l_linenumber <= 2"), of("l_linenumber >= 2")
    out = None
    for name, rows in (("either", a.union(b).distinct()), ("both", a.intersect(b)), ("first", a.subtract(b)), ("first_rows", a.exceptAll(b))):
        one = rows.agg(F.count(F.lit(1)).alias("edges")).select(F.lit(name).alias("kind"), "edges")
        out = one if out is None else out.unionByName(one)
    return out


# --- Layouts, SQL surface and functions --------------------------------------------------------------------------

put("broom_index_array", f"with {sql_layers(SQL['page_href'], 2, 3)} select u, v, cu, cv, [w1::double, w2::double, w3::double, w4::double] as ws from c4")(
    lambda s, d: array_index(broom_index(colored_by_key(graph(s, d, "page_href")), 2, 3), 2, 3)
)
put(
    "encoded_vertices",
    f"select u as key, dense_rank() over (order by u) - 1 as id from (select distinct u from ({SQL['customer_supplier']}))",
)(lambda s, d: G.encode_vertices(graph(s, d, "customer_supplier"))[1].select("key", "id"))


@put("sql_views", f"with {sql_layers(SQL['page_href'], 2, 2)} select u, count(*) as edges, sum(w3)::double as brooms from c3 group by u")
def sql_views(s: SparkSession, d: str) -> DataFrame:
    """Edges, colors and index as SQL views."""
    e = graph(s, d, "page_href")
    colored = colored_by_key(e)
    io.views(e, colored, broom_index(colored, 2, 2))
    return s.sql("select u, count(*) as edges, sum(w3) as brooms from edges join broom_index using (u, v) group by u")


@put("binomials", "select n::bigint as n, k, case when n >= k then factorial(n::integer) / (factorial(k::integer) * factorial((n - k)::integer)) else 0 end::double as ways, factorial(n::integer)::bigint as orders, seen from (select l_linenumber as n, count(distinct l_orderkey) as seen from lineitem group by l_linenumber) cross join (select unnest([0, 1, 2, 5, 9]) as k)")
def binomials(s: SparkSession, d: str) -> DataFrame:
    """The SQL function for binomials, and factorials, of orders' line numbers, and in how many orders each is."""
    scalar.register(s)
    _t(s, d, "lineitem").groupBy(F.col("l_linenumber").alias("n")).agg(F.count_distinct("l_orderkey").alias("seen")).createOrReplaceTempView("line_numbers")
    return s.sql("select cast(n as bigint) as n, k, binomial(n, k) as ways, factorial(cast(n as int)) as orders, seen from line_numbers lateral view explode(array(0, 1, 2, 5, 9)) t as k")


def _walks_on(edges_sql: str, p: int, q: int, t: int, select: str) -> str:
    return f"with {sql_layers(edges_sql, p, q)},\n{sampler.sql_walks(p, q, t, SEED)} {select}"


def _core_sql(edges_sql: str, p: int, q: int) -> str:
    return f"with {exact.sql_core(edges_sql, p, q, 12)} select u, v from r12"


_ONE = "select {p} as p, {q} as q, {t}::bigint as t, (select coalesce(sum(w{n}), 0) from c{n})::double as brooms, count(*) as hits, (select coalesce(sum(w{n}), 0) from c{n})::double * coalesce(sum(ratio), 0) / {t} as estimate from k1"
_EXACTLY = {"seed": SEED, "strategy": "none", "weight": "decimal"}


def _one(p: int, q: int, t: int = T) -> str:
    return _ONE.format(p=p, q=q, t=t, n=p + q - 1)


def _thin(df: DataFrame) -> DataFrame:
    return big(df.select("p", "q", "t", "brooms", "hits", "estimate"), "brooms")


# estimate() itself: reduction, colors, index, choice of the engine, walks and summary.
put("estimate_end_to_end", _walks_on(_core_sql(SQL["doc_line"], 3, 3), 3, 3, 200, _one(3, 3, 200)))(lambda s, d: _thin(estimator.estimate(graph(s, d, "doc_line"), 3, 3, 200, **_EXACTLY)))
put("estimate_end_to_end_join", _walks_on(_core_sql(SQL["page_href"], 3, 4), 3, 4, T, _one(3, 4)))(
    lambda s, d: _thin(estimator.estimate(graph(s, d, "page_href"), 3, 4, T, engine="join", contain="join", **_EXACTLY))
)
_TURNED = f"select v as u, u as v from ({SQL['page_href']})"
put("estimate_transposed", _walks_on(_core_sql(_TURNED, 3, 4), 3, 4, T, _one(3, 4)))(lambda s, d: _thin(estimator.estimate(G.transpose(graph(s, d, "page_href")), 3, 4, T, **_EXACTLY)))


def _history_sql(ts: tuple[int, ...]) -> str:
    """Estimates from growing numbers of samples, and their changes."""
    core = _core_sql(SQL["doc_line"], 3, 3)
    b = "(select coalesce(sum(w5), 0) from c5)::double"
    rows = " union all ".join(f"select {t}::bigint as t, {b} * coalesce(sum(ratio) filter (where sample_id < {t}), 0) / {t} as estimate from k1" for t in ts)
    return _walks_on(core, 3, 3, ts[-1], f"select t, round(estimate, 4) as estimate, round(abs(estimate - lag(estimate) over (order by t)) / abs(estimate), 9) as change from ({rows})")


put("progressive_estimates", _history_sql((50, 200, 240)))(
    lambda s, d: estimator.estimate_progressive(graph(s, d, "doc_line"), 3, 3, 50, 4, 0.0, 240, **_EXACTLY).select("t", F.round("estimate", 4).alias("estimate"), F.round("change", 9).alias("change"))
)
_RUN_SQL = _walks_on(
    _core_sql(SQL["doc_line"], 3, 3), 3, 3, 250,
    ", r as (select sample_id // 50 as run, sum(ratio) / 50 * (select sum(w5) from c5)::double as estimate from k1 group by 1), f as (select range as run, coalesce(estimate, 0) as estimate from range(5) left join r on run = range),"
    f" c as (select bicliques::double as truth from ({exact.sql_count(SQL['doc_line'], 3, 3)})) select count(*) as runs, first(truth) as truth, round(avg(abs(estimate - truth) / truth), 9) as mean_error, round(stddev_samp(estimate), 3) as spread from f, c",
).replace("\n ,", "\n,").replace(")) ,", ")),")


@put("repeated_runs_error", _RUN_SQL)
def repeated_runs_error(s: SparkSession, d: str) -> DataFrame:
    e = graph(s, d, "doc_line")
    truth = float(exact.count_vertex_expand(e, 3, 3).first()[0])
    out = measures.mean_error(estimator.estimate_repeated(e, 3, 3, 50, 5, **_EXACTLY), truth)
    return out.select("runs", "truth", F.round("mean_error", 9).alias("mean_error"), F.round("spread", 3).alias("spread"))


put("success_rate", _walks_on(SQL["page_href"], 3, 3, T, f"select count(*) / {T} as success_rate from k1"))(
    lambda s, d: measures.success_rate(sampler.sample_walks(stored(broom_index(colored_by_key(graph(s, d, "page_href")), 3, 3, "decimal")), graph(s, d, "page_href"), 3, 3, T, SEED), T)
)


@put("mean_ratio_by_udaf", _walks_on(SQL["page_href"], 2, 3, T, "select sample_id % 4 as part, round(avg(ratio), 9) as mean_ratio from k1 group by 1"))
def mean_ratio_by_udaf(s: SparkSession, d: str) -> DataFrame:
    """The mean of walks' ratios by a grouped Pandas function; built-in aggregates are the way for more than a sample."""

    def mean(ratio: pd.Series) -> float:
        return float(ratio.mean())

    mean.__annotations__ = {"ratio": pd.Series, "return": float}  # Spark reads them as types
    e = graph(s, d, "page_href")
    walks = sampler.sample_walks(stored(broom_index(colored_by_key(e), 2, 3, "decimal")), e, 2, 3, T, SEED)
    return walks.groupBy((F.col("sample_id") % 4).alias("part")).agg(F.round(F.pandas_udf(mean, "double")("ratio"), 9).alias("mean_ratio"))


def biclique_estimate(spark: SparkSession, table: str, p: int, q: int, t: int, view: str = "biclique_estimate", **options) -> DataFrame:
    """The estimate for a table or view with columns u and v, put into a view for SQL."""
    out = estimator.estimate(spark.table(table).select("u", "v"), p, q, t, **options)
    out.createOrReplaceTempView(view)
    return out


@put("estimate_by_sql", _walks_on(_core_sql(SQL["page_href"], 2, 3), 2, 3, T, _one(2, 3)))
def estimate_by_sql(s: SparkSession, d: str) -> DataFrame:
    graph(s, d, "page_href").createOrReplaceTempView("edges")
    biclique_estimate(s, "edges", 2, 3, T, **_EXACTLY)
    return s.sql("select p, q, t, cast(brooms as double) as brooms, hits, estimate from biclique_estimate")


# --- Baselines and measures --------------------------------------------------------------------------------------

_DENSE = f"""with k as materialized ({_core_sql(SQL['page_href'], 2, 3)}), d as materialized (select u, count(*) as n from k group by u), x as materialized (select coalesce(quantile_disc(n, 0.5), 0) as cut from d)"""
_SPARSE_SQL = f"""{_DENSE}, w as (select a.u as a, b.u as b, count(*)::hugeint as n from k a join d da on da.u = a.u join x on da.n <= x.cut join k b on a.v = b.v join d db on db.u = b.u where (db.n, b.u) > (da.n, a.u) group by 1, 2)
 select coalesce(sum(n * (n - 1) * (n - 2) // 6), 0)::double as sparse from w where n >= 3"""
_DENSE_SQL = f"{_DENSE} select u, v from k where u in (select d.u from d, x where d.n > x.cut)"
_PATHS = (
    "select us, vs, (select count(*) from (select v from g where list_contains(k1.us, u) group by v having count(*) = 2)) as n, "
    "(select count(*) from g where list_contains(k1.us, g.u) and list_contains(k1.vs, g.v)) as pairs from k1"
)
put(
    "hybrid_estimate",
    f"with {sql_layers(_DENSE_SQL, 2, 2)},\n{sampler.sql_walks(2, 2, 200, SEED, True)}, s as ({_SPARSE_SQL}), y as (select coalesce(sum((n - 2) / 3.0), 0) * (select coalesce(sum(w3), 0) from c3)::double / 200 as dense from ({_PATHS}) where pairs = 4 and n >= 2)"
    " select sparse, dense, sparse + dense as estimate from s, y",
)(lambda s, d: _hybrid(s, d))


def _hybrid(s: SparkSession, d: str) -> DataFrame:
    from biclique_spark.operators.hybrid import estimate_hybrid

    return big(estimate_hybrid(graph(s, d, "page_href"), 2, 3, 200, seed=SEED, weight="decimal"), "sparse")


put(
    "motif_kernel_regions",
    """with g as materialized (select distinct r_name as r, o_custkey as u, l_partkey as v from orders join lineitem on o_orderkey = l_orderkey join customer on c_custkey = o_custkey
    join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey),
    n as materialized (select a.r, count(*) as n from g a join g b on a.r = b.r and a.v = b.v and a.u < b.u group by a.r, a.u, b.u),
    f as materialized (select r, 2 as q, ln(1 + sum(n * (n - 1) / 2)) as x from n where n >= 2 group by r union all select r, 3, ln(1 + sum(n * (n - 1) * (n - 2) / 6)) from n where n >= 3 group by r),
    m as materialized (select a.r as a, b.r as b, sum(a.x * b.x) as xy from f a join f b on a.q = b.q and a.r <= b.r group by 1, 2)
    select m.a, m.b, round(m.xy / sqrt(x.xy * y.xy), 9) as similarity from m join m x on x.a = m.a and x.b = m.a join m y on y.a = m.b and y.b = m.b""",
)(lambda s, d: measures.motif_kernel(workloads.region_profiles(s, d, ((2, 2), (2, 3)))).withColumn("similarity", F.round("similarity", 9)))
put(
    "coaction_edges",
    "select distinct a.user_id as u, b.user_id as v from events a join events b on a.event_type = b.event_type and a.user_id < b.user_id and b.ts between a.ts - interval 61 minute and a.ts + interval 61 minute and abs(floor(epoch(a.ts))::bigint - floor(epoch(b.ts))::bigint) <= 3600",
)(lambda s, d: _coaction(s, d))


def _coaction(s: SparkSession, d: str) -> DataFrame:
    from biclique_spark.streaming.edges import coaction_edges

    return coaction_edges(_t(s, d, "events"))


def _ratio_sql(p: int, q: int, g: str = "page_href") -> str:
    """Bicliques, brooms, zigzags and the largest part that one zigzag stands for, of one size on its core."""
    h, most, core = min(p, q), max(p, q), _core_sql(SQL[g], p, q)
    x, y = ("u", "v") if p <= q else ("v", "u")
    top = f"(select coalesce(max(case when {most - h} = 0 then 1 else n - {h} end), 0) / {[1, 1, 1, 3][most] if most != h else 1}.0 from (select count(*) as n from ({core}) a join ({core}) b on a.{y} = b.{y} and a.{x} < b.{x} group by a.{x}, b.{x} having count(*) >= {most}))"
    if h == 3:
        top = "case when c > 0 then 1.0 else 0.0 end"
    total = lambda i, j: f"(select coalesce(sum(w{i + j - 1}), 0)::double from (with {sql_layers(core, i, j)} select * from c{i + j - 1}))"
    return f"""select {p} as p, {q} as q, c as bicliques, {total(p, q)} as brooms, {total(h, h)} as zigzags, ({top})::double as largest from (select bicliques::double as c from ({exact.sql_count(SQL[g], p, q)})) b"""


put(
    "sample_ratio_table",
    "select *, case when bicliques > 0 then round(brooms * brooms / (bicliques * bicliques), 6) end as broom_ratio, case when bicliques > 0 then round((zigzags * largest / bicliques) * (zigzags * largest / bicliques), 6) end as zigzag_ratio from ("
    + " union all ".join(_ratio_sql(p, q) for p, q in _SMALL)
    + ")",
)(
    lambda s, d: measures.sample_ratios(graph(s, d, "page_href"), list(_SMALL), "none")
    .drop("kappa").withColumns({"broom_ratio": F.round("broom_ratio", 6), "zigzag_ratio": F.round("zigzag_ratio", 6)})
)
put(
    "uncolored_kappa",
    " union all ".join(f"select {p} as p, {q} as q, (select greatest(count(distinct u), count(distinct v)) from ({_core_sql(SQL['page_href'], p, q)})) as kappa" for p, q in _SMALL),
)(lambda s, d: measures.color_counts(graph(s, d, "page_href"), _SMALL, "none"))
