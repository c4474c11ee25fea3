import corpus_pipeline
from biclique_spark.llm import exact_dedup, queries
from tests.llm.test_dedup import brute_components, brute_exact

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        before = {r.doc_id: r for r in docs.collect()}
        out = stage(spark, docs, SF)
        rows = out.collect()
        if k < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == docs.columns
            assert all(before[r.doc_id] == r for r in rows)
        ids = {r.doc_id for r in rows}
        if k == 1:
            assert ids == {x[0] for x in brute_exact([(i, r.text) for i, r in before.items()]) if x[3]}
        if k == 2:
            assert ids == {x[0] for x in brute_components([(i, r.text) for i, r in before.items()], 5, 80) if x[0] == x[2]}
        if k == 3:
            assert max(sum(r.doc_id == i for r in rows) for i in ids) <= 3
        if k == 4:
            assert ids == set(before) and all(r.n_tokens > 0 for r in rows)
        docs = spark.createDataFrame(rows, out.schema)


def test_queries_are_registered():
    assert [n.split("_")[0] for n in sorted(queries.QUERIES, key=lambda n: int(n[2:].split("_")[0]))] == [f"op{i}" for i in range(1, 11)]
    assert exact_dedup.STATE


def test_heaps_are_shrunk_before_the_later_stages(spark, monkeypatch):
    import corpus_pipeline
    from biclique_spark.llm import common

    beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()
    spent = lambda: sum(beans.get(i).getCollectionCount() for i in range(beans.size()))
    before = spent()
    common.shrink_heaps(spark)
    assert spent() > before
    calls = []
    monkeypatch.setattr(corpus_pipeline, "shrink_heaps", calls.append)
    docs = spark.createDataFrame([(1, "one two three", "en", "a", 13)], "doc_id long, text string, lang string, source string, n_chars long")
    for _, stage in corpus_pipeline.STAGES[2:]:
        stage(spark, docs, "")
    assert len(calls) == 3
