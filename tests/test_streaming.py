from pyspark.sql import functions as F

from biclique_spark.operators.exact import count_vertex_expand
from biclique_spark.streaming import edges as S

SF = "/root/testdata/sf0.001"


def slices(spark, tmp_path):
    folder = str(tmp_path / "events")
    spark.read.parquet(f"{SF}/events.parquet").repartitionByRange(3, "ts").sortWithinPartitions("ts").write.parquet(folder)
    return folder


def test_windows_equal_batch(spark, tmp_path):
    folder = slices(spark, tmp_path)
    batch = S.windowed_graphs(spark.read.parquet(folder))
    stream = S.run_to_table(S.windowed_graphs(S.event_stream(spark, folder), late="36500 days"), "windows", "update")
    latest = stream.groupBy("window_start", "u", "v").agg(F.max("n").alias("n"))
    assert sorted(map(tuple, latest.collect())) == sorted(map(tuple, batch.collect()))


def test_store_and_estimates_follow_the_stream(spark, tmp_path):
    folder, counts = slices(spark, tmp_path), []
    stream = S.stream_edges(S.event_stream(spark, folder), late="36500 days")
    S.maintain_graph(stream, str(tmp_path / "store"), lambda g, n: counts.append(count_vertex_expand(g, 2, 2).first()[0]))
    batch = S.stream_edges(spark.read.parquet(folder)).select("u", "v")
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "store")).select("u", "v").distinct().collect())) == sorted(map(tuple, batch.collect()))
    assert counts[-1] == count_vertex_expand(batch, 2, 2).first()[0]


def test_neighbor_sets(spark, tmp_path):
    folder = slices(spark, tmp_path)
    rows = S.event_stream(spark, folder).select(F.col("user_id").alias("u"), F.col("event_type").alias("v"))
    out = S.run_to_table(S.neighbor_sets(rows), "degrees", "update").groupBy("u").agg(F.max("degree").alias("d"))
    want = spark.read.parquet(folder).groupBy("user_id").agg(F.count_distinct("event_type").alias("d"))
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, want.collect()))


def test_sessions_and_coactions(spark):
    e = spark.createDataFrame([(1, "a", 0), (1, "b", 60), (1, "a", 10_000_000), (2, "a", 100), (3, "b", 90_000)], "user_id long, event_type string, s long").withColumn("ts", F.timestamp_seconds("s"))
    assert sorted((r.u, r.degree) for r in S.session_graphs(e).collect()) == [(1, 1), (1, 2), (2, 1), (3, 1)]
    assert [tuple(r) for r in S.coaction_edges(e).collect()] == [(1, 2)]


def test_coactions_of_blocks_of_users(spark, monkeypatch):
    """Blocks, slices of them and parts of meetings are small; pairs are not dealt out to be made distinct."""
    rows = [(f"u{i * 7 % 23}", i % 3, i * 613 % 9_973 * 20) for i in range(400)] + [("u1", 0, 5), ("u1", 0, 5), (None, 0, 5), ("u2", None, 5)]
    e = spark.createDataFrame(rows, "user_id string, event_type int, s long").withColumn("ts", F.timestamp_seconds("s"))
    whole = [r for r in rows if None not in r]
    want = sorted({(a[0], b[0]) for a in whole for b in whole if a[0] < b[0] and a[1] == b[1] and abs(a[2] - b[2]) <= 3600})
    for block, marks, meetings in ((1 << 16, 1 << 26, 1 << 22), (50, 20, 30)):
        monkeypatch.setattr(S, "BLOCK", block)
        monkeypatch.setattr(S, "MARKS", marks)
        monkeypatch.setattr(S, "MEETINGS", meetings)
        out = S.coaction_edges(e)
        assert sorted(map(tuple, out.collect())) == want
        assert "Exchange hashpartitioning" not in out._jdf.queryExecution().toString()
    assert not S.coaction_edges(e.where("s < 0")).count()
