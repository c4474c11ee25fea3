"""Reading edges, storing graphs and layers, and tables that cut a lineage."""

from __future__ import annotations

import atexit
import gc
import re
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_local: list[str] = []


def shared_dir(spark: SparkSession, name: str) -> str:
    """A fresh path in the folder that all executors share (spark.checkpoint.dir). Only where Spark is one process on
    one machine may that be unset: then it is a local folder, gone with the process."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        if not _local:
            _local.append(tempfile.mkdtemp(prefix="graphs-"))
            atexit.register(shutil.rmtree, _local[0], ignore_errors=True)
        base = f"file://{_local[0]}"
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a Parquet table in the shared folder: what is computed from it survives lost executors."""
    spark, path = df.sparkSession, shared_dir(df.sparkSession, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.table_path = path
    return out


def released(spark: SparkSession) -> None:
    """Have Spark delete the shuffle files of what nothing reads any more, which it does as the driver collects garbage."""
    gc.collect()
    spark._jvm.System.gc()


def discard(*tables: DataFrame) -> None:
    """Delete tables of written() that nothing reads any more."""
    for t in tables:
        spark = t.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(t.table_path)
        path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def read_edge_text(spark: SparkSession, path: str, comment: str = "%#", u: int = 0, v: int = 1) -> DataFrame:
    """Edge lists of public graph repositories: two or more columns between white space, comment lines apart."""
    line = F.trim("value")
    parts = F.split(line, r"[\s,]+")
    rows = spark.read.text(path).where((line != "") & ~F.substring(line, 1, 1).isin(*comment))
    return rows.select(F.get(parts, F.lit(u)).cast("long").alias("u"), F.get(parts, F.lit(v)).cast("long").alias("v")).dropna().distinct()


def read_edges(spark: SparkSession, path: str, form: str = "parquet", u: str = "u", v: str = "v", **options) -> DataFrame:
    """Edges from Parquet, ORC, JSON or CSV files (header expected for CSV)."""
    reader = spark.read.options(**({"header": "true"} if form == "csv" else {}), **options)
    return reader.format(form).load(path).select(F.col(u).alias("u"), F.col(v).alias("v")).dropna().distinct()


def save_graph(edges: DataFrame, path: str, buckets: int = 64) -> None:
    """Two copies, dealt by hash of either side, so that a join on a side reads only its own folder's buckets."""
    for side in ("u", "v"):
        dealt = edges.withColumn("bucket", F.pmod(F.xxhash64(side), F.lit(buckets)))
        dealt.repartition("bucket").write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/by_{side}")


def load_graph(spark: SparkSession, path: str, side: str = "u") -> DataFrame:
    return spark.read.parquet(f"{path}/by_{side}").select("u", "v")


def save_index(long_index: DataFrame, path: str) -> None:
    """A folder a layer: a walk step reads its own only."""
    long_index.write.mode("overwrite").partitionBy("layer").parquet(path)


def load_layer(spark: SparkSession, path: str, layer: int) -> DataFrame:
    return spark.read.parquet(path).where(F.col("layer") == layer)


def save_table(edges: DataFrame, name: str, side: str = "u", buckets: int = 64) -> None:
    """A bucketed and sorted table: joins and windows on the side need no shuffle."""
    edges.write.mode("overwrite").bucketBy(buckets, side).sortBy(side).saveAsTable(name)


def views(edges: DataFrame, colored: DataFrame | None = None, index: DataFrame | None = None) -> None:
    """SQL views edges, colored_edges and broom_index."""
    for df, name in ((edges, "edges"), (colored, "colored_edges"), (index, "broom_index")):
        if df is not None:
            df.createOrReplaceTempView(name)
