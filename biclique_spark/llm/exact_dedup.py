"""Exact deduplication by a stateful stream.

A Structured Streaming query without watermark keeps, in RocksDB, one entry a digest: the smallest
identifier seen, a locator of its content (input file and identifier) and how many rows had it. Nothing
expires. Rows of one digest are summed in each task before they reach the state, so a group with a third
of all rows costs one state update a task. A digest that more than one row has is a hit: the full bytes of
its rows are compared, again with a map-side sum, and rows whose bytes differ part.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DataType, MapType, StructType, VariantType

from biclique_spark.llm.common import one_space, setting, shared_dir, small, unused, written

STATE = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def sha(text: Column) -> Column:
    return F.sha2(text.cast("binary"), 256)


def fingerprints(docs: DataFrame, id_col: str, text_col: str, digest: Callable[[Column], Column]) -> DataFrame:
    """(id, digest, locator) of each row; the text itself is not carried."""
    clean = one_space(F.col(text_col))
    return docs.select(
        F.col(id_col).alias("id"),
        digest(clean).alias("digest"),
        F.struct(F.input_file_name().alias("file"), F.col(id_col).alias("id")).alias("locator"),
    )


def stream_state(spark: SparkSession, thin_path: str, schema, files_per_trigger: int) -> DataFrame:
    """Run the stream over all files of a table and return its last state: digest, id, locator, n."""
    out = shared_dir(spark, "dedup-state")
    source = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(thin_path)
    keyed = source.groupBy("digest").agg(
        F.min("id").alias("id"),
        F.min(F.struct(F.col("id"), F.col("locator"))).getField("locator").alias("locator"),
        F.count(F.lit(1)).alias("n"),
    )

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")  # a batch that runs again writes the same

    # Read at the start of the stream, and put back at its end.
    with setting(
        spark,
        spark__sql__streaming__stateStore__providerClass=STATE,
        spark__sql__streaming__stateStore__rocksdb__boundedMemoryUsage="true",
        spark__sql__streaming__stateStore__rocksdb__maxMemoryUsageMB="64",
        # State is spread over as many stores as a shuffle has partitions: none reserves disk ahead, and a commit
        # writes what changed.
        spark__sql__streaming__stateStore__rocksdb__allowFAllocate="false",
        spark__sql__streaming__stateStore__rocksdb__changelogCheckpointing__enabled="true",
    ):
        query = (
            keyed.writeStream.outputMode("update")
            .foreachBatch(keep)
            .option("checkpointLocation", shared_dir(spark, "dedup-stream"))
            .trigger(availableNow=True)
            .start()
        )
        query.awaitTermination()
    state = "digest string, id long, locator struct<file: string, id: long>, n long"
    if not query.recentProgress or not any(p["numInputRows"] for p in map(_as_dict, query.recentProgress)):
        return spark.createDataFrame([], state)
    # Later batches only lower the identifier and raise the count.
    return (
        spark.read.schema(state).parquet(out)
        .groupBy("digest")
        .agg(F.min("id").alias("id"), F.min_by("locator", "id").alias("locator"), F.max("n").alias("n"))
    )


def _as_dict(progress) -> dict:
    return progress if isinstance(progress, dict) else {"numInputRows": progress.numInputRows}


def dedup(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    digest: Callable[[Column], Column] = sha,
    files_per_trigger: int = 10_000,
) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal when they are the same after each run of white space became one space; the smallest id
    of equal texts stays. Null text counts as empty. Rows with a null id are counted in their group, never
    become keep_id while another id is there, and are not kept. Repeated rows (same id and text) are the same
    document: all are kept or none. An empty table gives an empty result; other columns are not read.
    ``digest`` may be any function of the text: hits are settled by their bytes.
    """
    spark = docs.sparkSession
    thin = fingerprints(docs, id_col, text_col, digest)
    path = shared_dir(spark, "dedup-thin")
    thin.write.parquet(path)
    thin = spark.read.schema(thin.schema).parquet(path)
    state = written(stream_state(spark, path, thin.schema, files_per_trigger), "dedup-last")
    hits = state.where("n > 1").select("digest")

    clean = one_space(F.col(text_col))
    texts = docs.select(F.col(id_col).alias("id"), clean.alias("clean")).withColumn("digest", digest(F.col("clean")))
    exact = written(
        texts.join(small(hits), "digest", "left_semi")
        .groupBy("digest", "clean")
        .agg(F.min("id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
        .groupBy("digest")
        .agg(
            F.count(F.lit(1)).alias("variants"),
            F.min("keep_id").alias("keep_id"),
            F.sum("group_size").alias("group_size"),
        ),
        "dedup-exact",
    )
    plain = thin.join(exact, "digest", "left").where("variants is null or variants = 1")
    out = plain.select(
        F.col("id").alias("doc_id"),
        F.coalesce("keep_id", "id").alias("keep_id"),
        F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"),
        F.col("digest").alias("text_sha256") if digest is sha else F.lit(None).cast("string").alias("text_sha256"),
    )
    apart = exact.where("variants > 1").select("digest")
    if apart.limit(1).count():  # different bytes under one digest: these rows are told apart by their bytes
        both = texts.join(small(apart), "digest", "left_semi")
        groups = both.groupBy("digest", "clean").agg(F.min("id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
        out = out.unionByName(
            both.join(groups, ["digest", "clean"]).select(
                F.col("id").alias("doc_id"), F.coalesce("keep_id", "id").alias("keep_id"), "group_size",
                F.lit(None).cast("string").alias("text_sha256"),
            )
        )
    if digest is not sha:
        out = out.drop("text_sha256").join(texts.select(F.col("id").alias("doc_id"), sha(F.col("clean")).alias("text_sha256")).distinct(), "doc_id")
    return out.select(
        "doc_id", "keep_id", "group_size", F.coalesce(F.col("doc_id") == F.col("keep_id"), F.lit(False)).alias("kept"), "text_sha256"
    )


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each text, with all its columns: the one with the smallest id, nulls last. Of rows with one id and
    equal texts the smallest by all columns stays (any, where a column has no order). Rows are judged one by one, by id
    and digest, so an id that repeats with another text changes nothing. Null texts are empty ones; an empty table
    gives an empty result."""
    found = dedup(docs, id_col, text_col).groupBy("doc_id", "text_sha256").agg(F.max(F.col("kept") | F.col("keep_id").isNull()).alias("first"), F.count(F.lit(1)).alias("n"))
    found = written(found.where("not first or n > 1"), "dedup-judged")
    sha_col = unused("digest", docs)
    rows = docs.withColumn(sha_col, sha(one_space(F.col(text_col))))
    same = lambda of: rows[id_col].eqNullSafe(of["doc_id"]) & (rows[sha_col] == of["text_sha256"])
    gone, many = found.select("doc_id", "text_sha256"), found.where("first and n > 1").select("doc_id", "text_sha256")
    alone = rows.join(small(gone), same(gone), "left_anti").drop(sha_col)
    if not many.limit(1).count():
        return alone
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    pick = F.min if all(is_ordered(f.dataType) for f in docs.schema) else F.first
    one = rows.join(small(many), same(many), "left_semi").groupBy(F.col(id_col), F.col(sha_col)).agg(pick(whole).alias("row"))
    return alone.unionByName(one.select("row.*"))


def is_ordered(kind: DataType) -> bool:
    """Whether Spark can compare values of a type."""
    if isinstance(kind, ArrayType):
        return is_ordered(kind.elementType)
    return all(is_ordered(f.dataType) for f in kind) if isinstance(kind, StructType) else not isinstance(kind, MapType | VariantType)
