"""Edges that arrive as a stream of events."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import pairwise

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from biclique_spark.sources.io import shared_dir, written

#: Events of a packed block of users, about; pairs of users marked, and meetings of events, at once.
BLOCK, MARKS, MEETINGS = 1 << 16, 1 << 26, 1 << 22


def _timed(events: DataFrame, ts: str, late: str) -> DataFrame:
    """Batch rows as they are; a stream with its watermark, which needs a time with zone."""
    return events.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, late) if events.isStreaming else events


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """A stream over a folder of event files."""
    schema = spark.read.parquet(folder).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def stream_edges(events: DataFrame, u: str = "user_id", v: str = "event_type", ts: str = "ts", late: str = "2 hours") -> DataFrame:
    """u, v, ts: the first event of each pair within the watermark; later rows than that are dropped."""
    rows = events.select(F.col(u).alias("u"), F.col(v).alias("v"), F.col(ts).alias("ts")).dropna()
    if not events.isStreaming:
        return rows.groupBy("u", "v").agg(F.min("ts").alias("ts"))
    return _timed(rows, "ts", late).dropDuplicatesWithinWatermark(["u", "v"])


def windowed_graphs(events: DataFrame, size: str = "1 day", slide: str | None = None, u: str = "user_id", v: str = "event_type", ts: str = "ts", late: str = "2 hours") -> DataFrame:
    """window_start, u, v, n: a graph for each window; the same for batch and stream."""
    rows = events.select(F.col(u).alias("u"), F.col(v).alias("v"), F.col(ts).alias("ts")).dropna()
    rows = _timed(rows, "ts", late)
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return rows.groupBy(w.alias("w"), "u", "v").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("window_start"), "u", "v", "n")


def session_graphs(events: DataFrame, gap: str = "6 hours", u: str = "user_id", v: str = "event_type", ts: str = "ts", late: str = "2 hours") -> DataFrame:
    """session_start, u, degree: a user's sessions and how many neighbours each has."""
    rows = events.select(F.col(u).alias("u"), F.col(v).alias("v"), F.col(ts).alias("ts")).dropna()
    rows = _timed(rows, "ts", late)
    s = rows.groupBy(F.session_window("ts", gap).alias("s"), "u").agg(F.size(F.collect_set("v")).alias("degree"))
    return s.select(F.col("s.start").alias("session_start"), "u", "degree")


def _packed(rows: DataFrame, blocks: int) -> DataFrame:
    """(block, users, keys, ends, who, s): the events (u, k, s) of each block of users in one row, sorted by key and time:
    users and keys as lists, where each key's events end, users by place (32 bits) and seconds (64 bits) as bytes."""
    kind = dict(rows.dtypes)

    def pack(key: tuple, tables: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(tables)).combine_chunks()
        users, keys = (t[c].chunk(0).dictionary_encode() for c in ("u", "k"))
        who, k, s = users.indices.to_numpy(), keys.indices.to_numpy(), t["s"].chunk(0).to_numpy()
        order = np.lexsort((who, s, k))
        ends = np.cumsum(np.bincount(k, minlength=len(keys.dictionary)))
        row = (key[0].as_py(), users.dictionary.to_pylist(), keys.dictionary.to_pylist(), ends.tolist(), who[order].astype(np.uint32).tobytes(), s[order].astype(np.int64).tobytes())
        types = (pa.int32(), pa.list_(users.dictionary.type), pa.list_(keys.dictionary.type), pa.list_(pa.int64()), pa.binary(), pa.binary())
        yield pa.record_batch([pa.array([x], y) for x, y in zip(row, types, strict=True)], ["block", "users", "keys", "ends", "who", "s"])

    block = F.pmod(F.xxhash64("u"), F.lit(blocks)).cast("int").alias("block")
    schema = f"block int, users array<{kind['u']}>, keys array<{kind['k']}>, ends array<long>, who binary, s binary"
    return rows.select("u", "k", "s", block).groupBy("block").applyInArrow(pack, schema)


def _met(a: dict, b: dict, seconds: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places of users of two packed blocks that did the same within so many seconds, each pair once."""
    of = lambda x, c, kind: np.frombuffer(x[c].as_buffer(), kind)
    parts = lambda x: {k: slice(*y) for k, y in zip(x["keys"].as_py(), pairwise([0, *x["ends"].as_py()]), strict=True)}
    (wa, sa), (wb, sb) = ((of(x, "who", np.uint32).astype(np.int64), of(x, "s", np.int64)) for x in (a, b))
    left, right, n, m = parts(a), parts(b), len(a["users"]), len(b["users"])
    step = max(1, MARKS // m)
    for low in range(0, n, step):
        marks = np.zeros(min(step, n - low) * m, bool)
        for k in left.keys() & right.keys():
            u, s, v, t = wa[left[k]] - low, sa[left[k]], wb[right[k]], sb[right[k]]
            if step < n:
                own = (u >= 0) & (u < step)
                u, s = u[own], s[own]
            first, last = np.searchsorted(t, s - seconds), np.searchsorted(t, s + seconds, "right")
            ends = np.cumsum(last - first)
            at = 0
            while at < len(u):  # so many meetings at once, and one event's at least
                to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + MEETINGS, "right")))
                count = (last - first)[at:to]
                place = np.arange(count.sum()) + np.repeat(first[at:to] - np.cumsum(count) + count, count)
                marks[np.repeat(u[at:to] * m, count) + v[place]] = True
                at = to
        found = np.nonzero(marks)[0]
        yield found // m + low, found % m


def coaction_edges(events: DataFrame, within: str = "1 hour", key: str = "event_type", who: str = "user_id", ts: str = "ts") -> DataFrame:
    """u, v: users (u < v) who did the same within a time. Users are dealt out to blocks, a block's events are one packed
    row, and each two blocks meet in one place, which finds each of their pairs of users once: neither meetings of events
    nor pairs are shuffled or stored."""
    seconds = int(pd.Timedelta(within).total_seconds())
    rows = events.select(F.col(who).alias("u"), F.col(key).alias("k"), F.unix_timestamp(ts).alias("s")).dropna()
    blocks = max(1, -(-rows.count() // BLOCK))
    kind = dict(rows.dtypes)["u"]
    packed = written(_packed(rows, blocks), "user-blocks")
    side = lambda n: packed.select(*[F.col(c).alias(f"{c}_{n}") for c in packed.columns])

    def pairs(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in source:
            for i in range(batch.num_rows):
                a, b = ({c.removesuffix(end): batch.column(c)[i] for c in batch.schema.names if c.endswith(end)} for end in ("_a", "_b"))
                names = pa.concat_arrays([a["users"].values, b["users"].values])
                rank = pc.rank(names, tiebreaker="dense").to_numpy().astype(np.int64)
                for x, y in _met(a, b, seconds):
                    y = y + len(a["users"])
                    if a["block"].as_py() == b["block"].as_py():
                        x, y = x[rank[x] < rank[y]], y[rank[x] < rank[y]]
                    swap = rank[x] > rank[y]
                    x, y = np.where(swap, y, x), np.where(swap, x, y)
                    for at in range(0, len(x), 1 << 16):
                        yield pa.record_batch([names.take(pa.array(z[at : at + (1 << 16)])) for z in (x, y)], ["u", "v"])

    return side("a").crossJoin(side("b")).where("block_a <= block_b").mapInArrow(pairs, f"u {kind}, v {kind}")


def neighbor_sets(edges: DataFrame, idle_ms: int | None = None) -> DataFrame:
    """u, degree after each batch: a state of each user's neighbours, kept by a custom stateful operator. With
    ``idle_ms`` a user without new edges for that time is forgotten, and reported with degree 0."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({"u": [key[0]], "degree": [0]})
            return
        known = set(state.get[0]) if state.exists else set()
        for b in batches:
            known.update(b["v"].astype(str))
        state.update((sorted(known),))
        if idle_ms is not None:
            state.setTimeoutDuration(idle_ms)
        yield pd.DataFrame({"u": [key[0]], "degree": [len(known)]})

    kind = dict(edges.dtypes)["u"]
    return edges.groupBy("u").applyInPandasWithState(
        update, f"u {kind}, degree long", "known array<string>", "update", GroupStateTimeout.NoTimeout if idle_ms is None else GroupStateTimeout.ProcessingTimeTimeout
    )


def run_to_table(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there now and return its output as a table in the shared folder."""
    spark = stream.sparkSession
    out, mark = shared_dir(spark, name), shared_dir(spark, f"{name}-marks")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).outputMode(mode)
    else:
        q = stream.writeStream.outputMode(mode).foreachBatch(lambda df, n: df.write.mode("overwrite").parquet(f"{out}/batch={n}"))
    q.option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def maintain_graph(stream: DataFrame, path: str, then: Callable[[DataFrame, int], None] | None = None) -> None:
    """Merge each batch's new edges into a store of one folder a batch; ``then`` gets the whole graph, to estimate
    anew. A batch that runs again replaces its own folder."""
    spark = stream.sparkSession

    def merge(batch: DataFrame, n: int) -> None:
        batch.select("u", "v").distinct().write.mode("overwrite").parquet(f"{path}/batch={n}")
        if then is not None:
            then(spark.read.parquet(path).select("u", "v").distinct(), n)

    stream.writeStream.foreachBatch(merge).option("checkpointLocation", shared_dir(spark, "graph-marks")).trigger(availableNow=True).start().awaitTermination()
