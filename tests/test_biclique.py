"""Worked examples, exact baselines, invariants and statistics of the biclique methods."""

import itertools
import math
import random

import pytest
from pyspark.sql import functions as F

from biclique_spark.functions import pattern, scalar
from biclique_spark.operators import coloring, estimator, exact, graph as G, hybrid, measures, sampler, zigzag
from biclique_spark.operators.index import broom_index, broom_list, broom_total, colored_by_key, long_index
from biclique_spark.plans import planner, queries, workloads
from biclique_spark.sources import io
from biclique_spark.sources.catalog import graph, words

SF = "/root/testdata/sf0.001"


def one(df):
    return df.first()[0]


def brute(edges, p, q):
    near = {}
    for u, v in edges:
        near.setdefault(u, set()).add(v)
    return sum(math.comb(len(set.intersection(*(near[u] for u in us))), q) for us in itertools.combinations(sorted(near), p))


def rows(df):
    return [(r.u, r.v) for r in df.collect()]


@pytest.fixture(scope="module")
def small(spark):
    rng = random.Random(1)
    pairs = sorted({(rng.randrange(12), rng.randrange(100, 111)) for _ in range(75)})
    return spark.createDataFrame(pairs, "u long, v long").cache()


def test_worked_example_by_every_method(spark):
    e = G.worked_example(spark)
    assert e.count() == 10
    for f in (exact.count_vertex_expand, exact.count_vertex_expand_kernel, exact.count_edge_pivot):
        assert one(f(e, 3, 2)) == 2
    assert {tuple(r.us) for r in exact.list_bicliques(e, 3, 2).collect()} == {(1, 3, 4), (3, 4, 5)}
    assert abs(estimator.estimate(e, 3, 2, 500).first()["estimate"] - 2) < 0.5
    assert abs(zigzag.estimate_zigzag(e, 3, 2, 500).first()["estimate"] - 2) < 1
    assert hybrid.exact_parts(e, 3, 2).agg(F.sum("bicliques")).first()[0] == 2


def test_staircase():
    assert pattern.broom_steps(6, 3) == "VVUVVUV"
    assert pattern.broom_steps(2, 2) == "UV" and pattern.broom_steps(3, 4) == "UVUUV"
    for p, q in itertools.product(range(2, 13), repeat=2):
        e = pattern.broom_edges(p, q)
        assert len(e) == p + q - 1 and e[0] == (1, 1) and e[-1] == (p, q)
        assert all((c - a) + (d - b) == 1 for (a, b), (c, d) in zip(e, e[1:]))
        assert len(pattern.broom_runs(p, q)) == (2 * p - 2 if p <= q else 2 * q - 1)
    with pytest.raises(ValueError):
        pattern.broom_edges(1, 3)


@pytest.mark.parametrize("p,q", [(2, 2), (3, 2), (2, 3), (3, 3), (4, 3), (3, 4)])
def test_exact_methods_agree(small, p, q):
    c = brute(rows(small), p, q)
    assert one(exact.count_vertex_expand(small, p, q)) == c
    assert one(exact.count_vertex_expand_kernel(small, p, q)) == c
    assert one(exact.count_edge_pivot(small, p, q)) == c
    assert one(exact.count_vertex_expand(G.transpose(small), q, p)) == c
    assert exact.list_bicliques(small, p, q).count() == c
    if p == 2:
        assert one(exact.count_pairs_closed_form(small, q)) == c


@pytest.mark.parametrize("p,q", [(2, 2), (3, 2), (2, 4), (3, 3)])
def test_index_is_the_number_of_listed_brooms(small, p, q):
    colored = colored_by_key(small)
    listed = broom_list(colored, p, q).count()
    for index in (broom_index(colored, p, q, "decimal"), broom_index(colored, p, q), broom_index(colored, p, q, "decimal", blocks=3)):
        assert one(broom_total(index, p, q)) == listed
    last = long_index(broom_index(colored, p, q, "decimal"), p, q).where(f"layer = {p + q - 1}").agg(F.sum("w")).first()[0]
    assert (last or 0) == listed


@pytest.mark.parametrize("strategy,order", [("none", "random"), ("greedy", "random"), ("greedy", "asc"), ("greedy", "desc"), ("conflict", "random"), ("rounds", "random")])
def test_colorings_are_legal_and_keep_one_broom_a_biclique(spark, small, strategy, order):
    p, q = 3, 3
    options = {"palette": 8, "offers": 4} if strategy == "rounds" else {}
    colored = coloring.color_graph(small, p, q, order, 1, strategy, **options)
    for side, threshold in (("u", q), ("v", p)):
        colors = colored.select(side, F.col(f"c{side}").alias("color")).distinct()
        assert colors.count() == small.select(side).distinct().count()
        assert coloring.coloring_violations(small, colors, side, threshold).count() == 0
    listed = broom_list(colored, p, q).withColumn("sample_id", F.monotonically_increasing_id()).cache()
    assert sampler.complete(listed, small).count() == brute(rows(small), p, q)
    kappa = coloring.color_count(colored).first()
    assert kappa["kappa"] == max(kappa["kappa_u"], kappa["kappa_v"])


def test_complete_graph(spark):
    e = G.complete_graph(spark, 6, 5)
    index = broom_index(colored_by_key(e), 3, 2, "decimal")
    assert one(broom_total(index, 3, 2)) == math.comb(6, 3) * math.comb(5, 2)
    walks = sampler.sample_walks(index, e, 3, 2, 50).collect()
    assert len(walks) == 50 and all(r.ratio == 1 for r in walks)


def test_expectation_is_exact(small):
    for p, q in ((2, 2), (3, 2)):
        r = estimator.expected_ratio(colored_by_key(small), small, p, q).first()
        assert abs(r["estimate"] - brute(rows(small), p, q)) < 1e-6 * r["brooms"]


def test_engines_and_forms_draw_the_same_walks(small):
    for weight in ("decimal", "double"):
        index = broom_index(colored_by_key(small), 3, 3, weight).cache()
        walk = lambda **k: sorted((r.sample_id, tuple(r.us), tuple(r.vs), round(r.ratio, 12)) for r in sampler.sample_walks(index, small, 3, 3, 80, 5, **k).collect())  # noqa: B023, E731
        a = walk()
        assert a and a == walk(contain="join") == walk(engine="local") == walk(meet="least", contain="join")


def test_draws_follow_their_sql_beyond_small_graphs(spark):
    """Over 8,192 edges: more groups than buckets, in the order of the SQL's 64 buckets (colors few on the left, or many)."""
    import duckdb

    from biclique_spark.operators.index import sql_layers

    for left, right in ((400, 50), (7, 3000)):
        e = spark.range(left * right).select((F.col("id") % left).alias("u"), F.floor(F.col("id") / left).alias("v")).where("(u * 31 + v * 17) % 5 <> 0")
        index = broom_index(colored_by_key(e), 2, 2, "decimal").cache()
        assert index.count() > 8192 and sampler.group_widths(index.count(), left, right) != (left, right)
        sql = f"select distinct i % {left} as u, i // {left} as v from range({left * right}) t(i) where (i % {left} * 31 + i // {left} * 17) % 5 <> 0"
        walks = f"with {sql_layers(sql, 2, 2)}, {sampler.sql_walks(2, 2, 40, 3)}"
        want = sorted(duckdb.sql(f"{walks} select sample_id, u, v from k3").fetchall())
        assert sorted(map(tuple, sampler.sample_last_edges(index, 2, 2, 40, 3).select("sample_id", "u", "v").collect())) == want
        for engine in ("join", "local"):
            got = sampler.sample_walks(index, e, 2, 2, 40, 3, engine=engine).select("sample_id", "us", "vs").collect()
            assert sorted((r.sample_id, list(r.us), list(r.vs)) for r in got) == sorted(duckdb.sql(f"{walks} select sample_id, us, vs from k1").fetchall())


def test_engines_agree_at_hubs(spark):
    """Left vertices with more edges than sampler.HUB: the kernel looks at them as arrays."""
    e = spark.range(3 * 300).select((F.col("id") % 3).alias("u"), F.floor(F.col("id") / 3).alias("v")).where("(u + v) % 7 != 0")
    for weight in ("decimal", "double"):
        index = broom_index(colored_by_key(e), 2, 3, weight).cache()
        walk = lambda **k: sorted((r.sample_id, tuple(r.us), tuple(r.vs), round(r.ratio, 12)) for r in sampler.sample_walks(index, e, 2, 3, 60, 5, **k).collect())  # noqa: B023, E731
        a = walk()
        assert a and a == walk(engine="local") == walk(meet="least")


def test_core_in_one_task_is_the_core(small):
    for p, q in ((2, 2), (3, 4), (9, 9)):
        assert set(rows(G.core_reduce(small, p, q).select("u", "v"))) == set(rows(G.core_reduce(small, p, q, one_task=0).select("u", "v")))


def test_first_fit_takes_the_smallest_legal_color():
    rng = random.Random(3)
    for case in range(60):
        n, m = rng.randint(1, 40), rng.randint(1, 150 if case % 2 else 10)
        near = {x: {y for y in range(m) if rng.random() < 0.5 * rng.random()} for x in range(n)}
        for threshold in (1, 2, 4):
            shared = lambda x, group: sum(any(y in near[z] for z in group if z != x) for y in near[x])  # noqa: B023, E731
            expected: dict[int, int] = {}
            for x in near:
                c = 1
                while any(shared(z, group) >= threshold for group in [[k for k, v in expected.items() if v == c] + [x]] for z in group):
                    c += 1
                expected[x] = c
            assert coloring.first_fit([(x, list(ys)) for x, ys in near.items()], threshold) == expected


def test_rounds_take_as_many_tints_as_rivals_need(spark, monkeypatch):
    """300 vertices that all share two neighbours need 300 colors, which few blocks of many tints give; hubs that all of
    a side share make no larger palettes where sharing them is legal."""
    edges = spark.createDataFrame([(u, v) for u in range(300) for v in (-1, -2, u)], "u long, v long")
    drawn, whole = [], coloring.written
    monkeypatch.setattr(coloring, "written", lambda df, name: drawn.append(name) or whole(df, name))
    colors = {r["u"]: r["color"] for r in coloring.rounds_side(edges, "u", 2).collect()}
    assert len(colors) == 300 and len(set(colors.values())) == 300
    assert drawn.count("color-settled") <= 8
    pairs = coloring._classes(edges, "u", "random", 1)[0]
    assert coloring.roomy_palette(pairs, 5) == coloring.PALETTE < coloring.roomy_palette(pairs, 2)


@pytest.mark.parametrize("strategy", ["conflict", "rounds"])
def test_twins_are_colored_together(spark, strategy, monkeypatch):
    """40 vertices with the same neighbours, 3 with some of them and 30 with too few: rounds by class, not by vertex."""
    pairs = [(u, v) for u in range(40) for v in range(3)] + [(u, v) for u in (50, 51, 52) for v in range(1, 5)] + [(u, 9) for u in range(60, 90)]
    e, tables = spark.createDataFrame(pairs, "u long, v long"), []
    kept = coloring.written
    monkeypatch.setattr(coloring, "written", lambda df, name: tables.append(name) or kept(df, name))
    colors = coloring.color_side(e, "u", 3, "random", 1, strategy).cache()
    assert colors.count() == colors.select("u").distinct().count() == 73 and len(tables) < 40
    assert coloring.coloring_violations(e, colors, "u", 3).count() == 0
    assert colors.where("u < 40").select("color").distinct().count() == 40


@pytest.mark.parametrize("strategy", ["greedy", None])
def test_survivors_of_legal_and_other_colorings(spark, small, strategy, monkeypatch):
    from biclique_spark.operators import index

    def refuse(*_):
        raise AssertionError("brooms of a legal coloring need not be listed")

    if strategy:
        monkeypatch.setattr(index, "broom_list", refuse)
        assert one(coloring.survivors(coloring.color_graph(small, 3, 3, "random", 1, strategy), small, 3, 3)) == brute(rows(small), 3, 3)
        return
    colored = small.withColumns({"cu": F.pmod(F.xxhash64("u"), F.lit(5)).cast("int") + 1, "cv": F.pmod(F.xxhash64("v"), F.lit(5)).cast("int") + 1})
    listed = broom_list(colored, 3, 3).withColumn("sample_id", F.monotonically_increasing_id())
    assert one(coloring.survivors(colored, small, 3, 3)) == sampler.complete(listed.cache(), small).count() < brute(rows(small), 3, 3)


def test_estimates_are_close(spark, small):
    c = brute(rows(small), 3, 3)
    for options in ({}, {"strategy": "none"}, {"reduce": "split", "strategy": "none"}, {"relabel": 3}):
        r = estimator.estimate(small, 3, 3, 3_000, **options).first()
        assert abs(r["estimate"] - c) <= 5 * r["std_error"] + 1e-9
    runs = estimator.estimate_repeated(small, 3, 3, 500, 8)
    assert runs.count() == 8 and measures.mean_error(runs, c).first()["mean_error"] < 0.3
    history = estimator.estimate_progressive(small, 3, 3, 100, max_t=1_600).collect()
    assert history[0].t == 100 and abs(history[-1].estimate - c) / c < 0.3
    n = sampler.naive_sample(broom_index(colored_by_key(small), 3, 3), small, 3, 3, 2_000, engine="local").first()
    assert abs(n["estimate"] - c) / c < 0.5
    assert abs(estimator.estimate_auto(small, 3, 3, 3_000).first()["estimate"] - c) / c < 0.3


def test_zigzag_and_hybrid(small):
    assert one(zigzag.zigzag_total(small, 3, "decimal")) == one(broom_total(broom_index(colored_by_key(small), 3, 3, "decimal"), 3, 3))
    for p, q in ((2, 3), (3, 2), (3, 3)):
        c = brute(rows(small), p, q)
        z = zigzag.estimate_zigzag(small, p, q, 4_000, engine="local").first()
        assert abs(z["estimate"] - c) <= 5 * z["std_error"]
        assert hybrid.exact_parts(small, p, q).agg(F.sum("bicliques")).first()[0] == c
    c = brute(rows(small), 3, 3)
    for basic in (False, True):
        assert abs(hybrid.estimate_hybrid(small, 3, 3, 2_000, basic=basic).first()["estimate"] - c) / c < 0.3


def test_degenerate_graphs(spark):
    empty = spark.createDataFrame([], "u long, v long")
    star = spark.createDataFrame([(1, k) for k in range(9)], "u long, v long")
    for e in (empty, star):
        assert one(exact.count_vertex_expand(e, 2, 2)) == 0
        assert one(exact.count_edge_pivot(e, 3, 2)) == 0
        assert estimator.estimate(e, 2, 2, 10, strategy="none").first()["estimate"] == 0
    odd = spark.createDataFrame([("a", "x"), ("a", "x"), (None, "x"), ("b", None), ("a", "y"), ("b", "x"), ("b", "y")], "l string, r string")
    e = G.edges_from(odd, "l", "r")
    assert e.count() == 4 and one(exact.count_vertex_expand(e, 2, 2)) == 1
    assert estimator.estimate(e, 2, 2, 20, engine="local").first()["estimate"] == 1


def test_reductions(small):
    core = G.core_reduce(small, 3, 3)
    assert one(exact.count_vertex_expand(core, 3, 3, reduce=False)) == brute(rows(small), 3, 3)
    assert min(r["count"] for r in core.groupBy("u").count().collect()) >= 3
    coded, du, dv = G.encode_vertices(small, 3)
    assert sorted(r.id for r in du.collect()) == list(range(du.count())) and coded.count() == small.count()
    assert [r.key for r in dv.orderBy("id").collect()] == sorted(r.v for r in small.select("v").distinct().collect())
    half = G.sample_vertices(small, 0.5)
    assert set(rows(half)) <= set(rows(small))


def test_bounds_and_measures(spark, small):
    r = spark.range(1).select(
        scalar.required_samples(F.lit(200.0), F.lit(10.0), 0.1, 0.05).alias("t"), scalar.binomial(F.lit(9), 4, scalar.EXACT).alias("b"), scalar.binomial(F.lit(3), 4).alias("z")
    ).first()
    assert r.t == math.ceil(400 / 0.02 * math.log(40)) and r.b == 126 and r.z == 0
    assert measures.sample_ratio_broom(20, 10) == 4
    p = measures.participation(small, 2, 2).agg(F.sum("bicliques")).first()[0]
    assert p == 2 * brute(rows(small), 2, 2)
    v = measures.participation(small, 2, 2, "v").agg(F.sum("bicliques")).first()[0]
    assert v == 2 * brute(rows(small), 2, 2)
    c = measures.clustering_coefficient(G.complete_graph(spark, 4, 4), 2, 2).first()
    assert c["coefficient"] == 1.0
    assert measures.clustering_coefficient(G.complete_graph(spark, 5, 4), 3, 2).first()["coefficient"] == 1.0
    ratios = measures.sample_ratios(small, [(2, 2), (3, 2)]).collect()
    assert all(x.broom_ratio >= 1 and x.zigzag_ratio is not None for x in ratios)


def test_large_sample_bounds_equal_their_sql(spark):
    """Rounded up from doubles: operations in another order, or 2 eps^2 off by a unit, are other whole numbers."""
    import duckdb

    pairs = [(float(10**12 + 7919 * i), float(1_000_003 + i)) for i in range(200)]
    df = spark.createDataFrame(pairs, "b double, c double")
    got = [r[0] for r in df.select("b", scalar.required_samples(F.col("b"), F.col("c"), 0.1, 0.05).cast("long").alias("n")).orderBy("b").select("n").collect()]
    want = duckdb.sql("select ceil(b * b / (c * c) / (2 * 0.1 * 0.1) * ln(2 / 0.05))::bigint from (select (1000000000000 + 7919 * i)::double as b, (1000003 + i)::double as c from range(200) t(i)) order by b").fetchall()
    assert got == [r[0] for r in want]


@pytest.mark.parametrize("name", ["broom_shape", "broom_runs", "complete_graph_closed_form", "binomials"])
def test_closed_forms_on_given_tables(spark, name):
    """Each reads a given table by Spark, and equals its SQL."""
    import duckdb

    from biclique_spark.plans import relational

    f, sql = {**queries.QUERIES, **relational.QUERIES}[name], {**queries.ORACLES, **relational.ORACLES}[name]
    df = f(spark, SF)
    assert df.inputFiles() and any("lineitem" in x for x in df.inputFiles())
    con = duckdb.connect()
    for t in ("lineitem", "orders"):
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    got, want = sorted(map(tuple, df.collect()), key=str), sorted(con.execute(sql).fetchall(), key=str)
    assert got == want and len(got) > (name != "complete_graph_closed_form")


def test_products_beyond_a_double(spark, tmp_path):
    """400 neighbours of degree 50: their product has 680 digits."""
    rows = spark.range(400 * 50).select((F.col("id") % 50).alias("user_id"), F.concat(F.lit('{"k": '), F.floor(F.col("id") / 50).cast("string"), F.lit("}")).alias("props"))
    rows.write.parquet(str(tmp_path / "events.parquet"))
    from biclique_spark.plans import relational

    out = relational.QUERIES["degree_products"](spark, str(tmp_path)).collect()
    assert len(out) == 50 and all(r.agrees and abs(r.log_product - 400 * math.log(50)) < 1e-5 for r in out)


def test_counts_on_twins(spark):
    """Twins on both sides and a right vertex of all: counts and participations as by brute force, few rows of tuples."""
    from biclique_spark.operators import twins

    near = {u: {0, *range(1 + u % 3, 4 + u % 3), 7 + u // 10} for u in range(30)}
    pairs = [(u, v) for u, vs in near.items() for v in vs]
    e = spark.createDataFrame(pairs, "u long, v long")
    t = twins.twins(e)
    assert t.edges.count() < len(pairs) / 3 and sum(r.mx * r.my for r in t.edges.collect()) == len(pairs)
    for p, q in ((2, 3), (4, 3)):
        n = brute(pairs, p, q)
        assert one(twins.count(e, p, q)) == n == one(exact.count_vertex_expand(G.transpose(e), q, p))
        assert one(exact.count_vertex_expand_kernel(e, p, q)) == n == one(exact.count_edge_pivot(e, p, q))
    halves = [exact.count_edge_pivot(e, 3, 2, part) for part in hybrid.split_dense_sparse(e)]
    assert one(halves[0]) + one(halves[1]) == brute(pairs, 3, 2) and one(halves[0])
    for p, q in ((3, 2),):
        for side, ends in (("u", pairs), ("v", [(v, u) for u, v in pairs])):
            s, o = (p, q) if side == "u" else (q, p)
            whole = brute(ends, s, o)
            want = {x: n for x in {a for a, _ in ends} if (n := whole - brute([e for e in ends if e[0] != x], s, o))}
            assert {r.vertex: int(r.bicliques) for r in measures.participation(e, p, q, side).collect()} == want


def test_more_samples_help(small):
    c = brute(rows(small), 3, 3)
    errors = [measures.mean_error(estimator.estimate_repeated(small, 3, 3, t, 10), c).first()["mean_error"] for t in (10, 1_000)]
    assert errors[1] < errors[0]


def test_known_counts(spark):
    assert one(exact.count_pairs_closed_form(graph(spark, SF, "customer_part"), 2)) == 273_554
    assert one(exact.count_vertex_expand(graph(spark, SF, "doc_line"), 3, 3)) == 1_541
    assert one(exact.count_vertex_expand(graph(spark, SF, "user_type"), 3, 3)) == 4_550
    assert one(broom_total(broom_index(colored_by_key(graph(spark, SF, "customer_part")), 3, 3, "decimal"), 3, 3)) == 155_621_306


def test_index_plan_has_an_exchange_for_each_run(spark, small):
    colored = io.written(colored_by_key(small), "colored")
    for p, q in ((3, 4), (5, 3), (3, 6)):
        plan = broom_index(colored, p, q)._jdf.queryExecution().executedPlan().toString()
        assert plan.count("Exchange hashpartitioning") == len(pattern.broom_runs(p, q))


def test_planner_and_sources(spark, small, tmp_path):
    c = planner.choose(planner.statistics(small), 3, 3)
    assert (c.engine, c.strategy) == ("local", "greedy")
    assert planner.choose({"edges": 10**10, "max_u": 10**8, "max_v": 5}, 3, 3).engine == "join"
    text = tmp_path / "edges.txt"
    text.write_text("% comment\n1 2 0.5\n1 3\n# x\n\n2 2\n")
    assert sorted(rows(io.read_edge_text(spark, str(text)))) == [(1, 2), (1, 3), (2, 2)]
    io.save_graph(small, str(tmp_path / "g"), 4)
    assert sorted(rows(io.load_graph(spark, str(tmp_path / "g"), "v"))) == sorted(rows(small))
    for form in ("orc", "json", "csv"):
        small.write.format(form).option("header", "true").save(str(tmp_path / form))
        assert io.read_edges(spark, str(tmp_path / form), form).count() == small.count()
    index = long_index(broom_index(colored_by_key(small), 2, 2), 2, 2)
    io.save_index(index, str(tmp_path / "i"))
    plan = io.load_layer(spark, str(tmp_path / "i"), 2)
    assert plan.count() == index.where("layer = 2").count() and "PartitionFilters: [isnotnull(layer" in plan._jdf.queryExecution().executedPlan().toString()
    scalar.register(spark)
    assert spark.sql("select count(*) from broom_steps(4, 3)").first()[0] == 6
    assert spark.sql("select relative_error(9, 10) as e").first()["e"] == pytest.approx(0.1)


def test_doc_token_holds_frequent_words(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").count()
    most = lambda g: one(graph(spark, SF, g).groupBy("v").count().agg(F.max("count")))
    assert most("doc_token") > docs / 2
    assert most("doc_token_to_5_percent") <= 0.05 * docs


def test_words_of_any_script(spark):
    df = spark.createDataFrame([(1, "Für café, für_3 naïve"), (2, "Привет-мир ñ7 日本"), (3, None), (None, "x")], "id long, text string")
    assert set(rows(words(df, "id", "text"))) == {(1, "für"), (1, "café"), (1, "naïve"), (2, "привет"), (2, "мир"), (2, "ñ"), (2, "日本")}
    assert graph(spark, SF, "doc_token").count() == 50_193 and graph(spark, SF, "page_token").count() == 13_012  # SURVEY 1.4
    assert G.core_reduce(graph(spark, SF, "conv_token"), 3, 3).count() == 1_265  # FIXTURES


def test_method_errors_runs_both_methods_as_often(spark, monkeypatch):
    seeds, real = [], hybrid.estimate_hybrid
    monkeypatch.setattr(hybrid, "estimate_hybrid", lambda *a, seed, **k: (seeds.append(seed), real(*a, seed=seed, **k))[1])
    got = workloads.errors(spark, SF, ("page_href",), ((2, 2),), 100, runs=5)
    assert sorted(r.method for r in got.collect()) == ["broom", "hybrid"] and seeds == [1, 2, 3, 4, 5]


def test_registered_experiments_cover_the_nine_graphs(monkeypatch):
    got = {}
    for name in ("dataset_statistics", "stage_split", "memory"):
        monkeypatch.setattr(workloads, name, lambda s, d, graphs, *a, n=name: got.__setitem__(n, set(graphs)))
    monkeypatch.setattr(workloads, "scalability", lambda s, d, g, sizes, t, shares, *a: got.__setitem__("shares", shares))
    for q in ("graph_stats", "stage_times", "memory_profile", "vertex_scalability"):
        queries.QUERIES[q](None, None)
    assert all(set(workloads.NINE) <= got[n] for n in ("dataset_statistics", "stage_split", "memory")) and got["shares"] == (0.6, 0.8, 1.0)


def test_edge_pivot_takes_anchors_before_vertices_meet(spark):
    """The semi-join with the anchors lies below the join that makes wedges."""
    e = spark.createDataFrame([(u, v) for u in range(6) for v in range(5)], "u long, v long")
    sparse, _ = hybrid.split_dense_sparse(e)
    tree = G.wedges_of(e, anchors=sparse)._jdf.queryExecution().optimizedPlan().toString().split("\n")
    joins = [(len(x) - len(x.lstrip(" :+-")), x) for x in tree if "Join" in x]
    wedge = next(i for i, (_, x) in enumerate(joins) if "Inner" in x and "<" in x or "Inner" in x and ">" in x)
    assert any("LeftSemi" in x and depth > joins[wedge][0] for depth, x in joins[wedge + 1 :])
    assert one(exact.count_edge_pivot(e, 3, 2, sparse, reduce=False)) <= one(exact.count_edge_pivot(e, 3, 2))


def test_history_measures(spark):
    history = spark.createDataFrame([("broom", 10, 0.5), ("broom", 100, 0.04), ("hybrid", 100, 0.2)], "method string, t long, mean_error double")
    assert [tuple(r) for r in measures.samples_to_error(history, 0.05).collect()] == [("broom", 100)]
    times = spark.createDataFrame([("g", "broom", 2.0, 0.1), ("g", "edge_pivot", 8.0, 0.3)], "graph string, method string, seconds double, mean_error double")
    assert [tuple(r) for r in measures.speedup(times, "broom").collect()] == [("g", "edge_pivot", 4.0)]
    assert [round(r.factor, 9) for r in measures.error_reduction(times.drop("seconds"), "broom").collect()] == [3.0]
    assert workloads.mean_error([9.0, 11.0], None) == 0.1 and workloads.mean_error([1.0], 0.0) is None


def test_a_limit_in_seconds_cancels_jobs(spark):
    slow = lambda: spark.range(1 << 40).selectExpr("sum(hash(id))").first()[0]
    value, seconds = workloads.within(spark, 1.0, slow)
    assert value is None and seconds < 30 and workloads.within(spark, 60, lambda: 3)[0] == 3.0


def test_large_sides_are_ranked_by_ranges(spark, monkeypatch):
    from biclique_spark.operators import index

    e = graph(spark, SF, "page_href")
    want = {tuple(r) for r in index.colored_by_key(e).collect()}
    monkeypatch.setattr(index, "RANKED", 10)
    assert {tuple(r) for r in index.colored_by_key(e).collect()} == want


def test_bucketed_table(spark):
    io.save_table(spark.createDataFrame([(1, 2), (1, 3)], "u long, v long"), "edges_by_u", buckets=2)
    try:
        assert spark.table("edges_by_u").count() == 2
    finally:
        spark.sql("drop table edges_by_u")


def test_listing_stores_no_table_longer_than_the_edges(spark, tmp_path, monkeypatch):
    """Of many twins there are more tuples than edges, and more bicliques still."""
    monkeypatch.setattr(exact, "PIECE", 1000)
    e = spark.createDataFrame([(u, f"v{v}") for u in range(40) for v in range(8) if (u % 2, v) != (1, 7)], "u long, v string")
    number = itertools.count()
    monkeypatch.setattr(io, "shared_dir", lambda s, name: f"file://{tmp_path}/{name}-{next(number)}")
    rows = exact.list_bicliques(e, 3, 2).collect()
    want = {(a, tuple(f"v{v}" for v in b)) for a in itertools.combinations(range(40), 3) for b in itertools.combinations(range(8 if not any(x % 2 for x in a) else 7), 2)}
    assert len(rows) == len(want) and {(tuple(r.us), tuple(r.vs)) for r in rows} == want
    assert max(spark.read.parquet(f"file://{x}").count() for x in tmp_path.iterdir() if any(x.glob("*.parquet"))) <= 300


def test_a_tint_is_put_in_order_in_one_place(spark, monkeypatch):
    """300 rivals in 8 tints: most withdraw in pass after pass, for which no table is stored."""
    edges = spark.createDataFrame([(u, v) for u in range(300) for v in (-1, -2, u)], "u long, v long")
    drawn, whole = [], coloring.written
    monkeypatch.setattr(coloring, "written", lambda df, name: drawn.append(name) or whole(df, name))
    colors = coloring.rounds_side(edges, "u", 2, palette=128, offers=2).collect()
    assert len({r["color"] for r in colors}) == 300 and "color-kept" in drawn
    assert max(drawn.count(n) for n in set(drawn)) <= drawn.count("color-kept") + 1


def test_a_core_is_peeled_without_storing_its_rounds(spark, monkeypatch):
    """A path that loses an end in each round, beside a graph that stays; more at once than PEELED are left to rounds."""
    pairs = [(u, v) for u in range(6) for v in range(5)] + [(100 + i // 2, 100 + (i + 1) // 2) for i in range(4)] + [(0, 9)]
    e, drawn, whole = spark.createDataFrame(pairs, "u long, v long"), [], G.written
    monkeypatch.setattr(G, "written", lambda df, name: drawn.append(name) or whole(df, name))
    assert sorted(rows(G.core_reduce(e, 2, 2, one_task=0))) == pairs[:30] and drawn.count("core") == 2
    monkeypatch.setattr(G, "PEELED", 0)
    assert G.core_by_peeling(e, 2, 2) is None and sorted(rows(G.core_reduce(e, 2, 2, one_task=0))) == pairs[:30]


def test_pairs_are_counted_and_not_stored(spark, monkeypatch):
    """Of pairs that share neighbours there are more than edges; blocks, meetings and names of any kind make no difference."""
    from biclique_spark.operators import twins

    rng = random.Random(5)
    pairs = sorted({(u, v) for u in range(40) for v in rng.sample(range(40), 10)} | {(u, 50 + u % 2) for u in range(20)})
    n, stored, whole = brute(pairs, 3, 2), [], twins.written

    def kept(df, name):
        out = whole(df, name)
        stored.append(out.count())
        return out

    monkeypatch.setattr(twins, "written", kept)
    e = spark.createDataFrame(pairs, "u long, v long")
    assert one(twins.count(e, 3, 2)) == n and max(stored) <= len(pairs)
    monkeypatch.setattr(twins, "BLOCK", 100)
    monkeypatch.setattr(twins, "MEETINGS", 300)
    copies = e.unionByName(e.select((F.col("u") + 1000).alias("u"), "v"))  # twins on the left
    named = copies.select(F.concat(F.lit("a"), "u").alias("u"), F.concat(F.lit("b"), "v").alias("v"))
    assert one(twins.count(named, 3, 2)) == brute(rows(copies), 3, 2)
    assert one(twins.pair_count(twins.representatives(copies), 3)) == brute(rows(copies), 2, 3)


def test_layers_stored_by_runs_are_the_same(small):
    want = {tuple(r) for r in broom_index(colored_by_key(small), 3, 4, "decimal").collect()}
    assert {tuple(r) for r in broom_index(colored_by_key(small), 3, 4, "decimal", cut=True).collect()} == want


def test_large_exact_indexes_stay_off_the_driver(small, monkeypatch):
    """Exact weights are objects: beyond LOCAL_EXACT walks are joins, and the same ones; doubles may still be sent."""
    stats = planner.statistics(small) | {"edges": planner.LOCAL_EXACT}
    assert [planner.choose(stats, 3, 4, w).engine for w in ("double", "decimal")] == ["local", "join"]
    want = estimator.estimate(G.transpose(small), 3, 4, 60, strategy="none", weight="decimal").first()
    monkeypatch.setattr(planner, "LOCAL_EXACT", 0)
    monkeypatch.setattr(sampler, "_local_walks", None)
    got = estimator.estimate(G.transpose(small), 3, 4, 60, strategy="none", weight="decimal").first()
    assert (got.brooms, got.hits) == (want.brooms, want.hits) and abs(got.estimate - want.estimate) <= 1e-9 * want.estimate
