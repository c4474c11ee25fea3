"""What the operators share: places for tables, size checks and the white space of the contracts."""

from __future__ import annotations

import atexit
import ctypes
import functools
import re
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space between words, as a class for Java's regular expressions.
SPACE = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"
#: A side that takes no more bytes than this in a hash table may be broadcast.
BROADCAST_BYTES, ROW_BYTES = 48 << 20, 40

_local: list[str] = []


def shared_dir(spark: SparkSession, name: str) -> str:
    """A fresh path in the folder that all executors share (spark.checkpoint.dir). Only where Spark is one process on
    one machine may that be unset: then it is a local folder, gone with the process."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        if not _local:
            _local.append(tempfile.mkdtemp(prefix="shared-"))
            atexit.register(shutil.rmtree, _local[0], ignore_errors=True)
        base = f"file://{_local[0]}"
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a Parquet table in the shared folder: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    path = shared_dir(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.table_path = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete tables of written() that nothing reads any more."""
    for t in tables:
        spark = t.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(t.table_path)
        path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def small(df: DataFrame, most: int = BROADCAST_BYTES) -> DataFrame:
    """df with a broadcast hint if its bytes, summed now, are within the bound; df itself beyond. No more rows than
    could be within it are read."""
    rows = most // ROW_BYTES
    wide = [F.coalesce(F.octet_length(F.col(f"`{c}`")), F.lit(0)).cast("long") for c, kind in df.dtypes if kind in ("string", "binary")]
    n, held = df.limit(rows + 1).agg(F.count(F.lit(1)), F.coalesce(F.sum(sum(wide, F.lit(0).cast("long"))), F.lit(0))).first()
    return F.broadcast(df) if n <= rows and n * (ROW_BYTES + 8 * len(df.columns)) + held <= most else df


def unused(name: str, *tables: DataFrame) -> str:
    """A column name that none of the tables has, whatever the case of letters."""
    taken = {c.lower() for t in tables for c in t.columns}
    while name.lower() in taken:
        name += "_"
    return name


def size_of(df: DataFrame, column: str) -> int:
    """Bytes in a text column of all rows."""
    return df.agg(F.sum(F.octet_length(F.col(column)).cast("long"))).first()[0] or 0


@contextmanager
def setting(spark: SparkSession, **values: str) -> Iterator[None]:
    """SQL settings for the time of a block; dots in names are written as two underscores."""
    names = {k.replace("__", "."): v for k, v in values.items()}
    before = {k: spark.conf.get(k, None) for k in names}
    for k, v in names.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)


def one_space(text: Column) -> Column:
    """Each run of white space as one space; null as empty."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACE, " ")


def give_back() -> None:
    """Return what a Python worker freed to the system: it lives on beside the JVM, into other stages."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc
    if trim is not None:
        trim(0)


def shrink_heaps(spark: SparkSession) -> None:
    """Have the executors' JVMs collect now and return the room that earlier steps took: their heaps else stay as large as
    they ever were, beside Python workers that need the memory. A task for each core, so that every executor has one."""
    n = spark.sparkContext.defaultParallelism
    collect = F.expr("java_method('java.lang.System', 'gc')").alias("done")
    spark.range(0, n, 1, n).select(collect).write.format("noop").mode("overwrite").save()


def lean(run: Callable[..., Iterator[pa.RecordBatch]]) -> Callable[..., Iterator[pa.RecordBatch]]:
    """A function of Arrow batches, or of a key and the batches of its group, that gives memory back at its end."""

    def through(*args) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(*args)
        finally:
            give_back()

    if run.__code__.co_argcount == 1:  # Spark counts the arguments
        return functools.wraps(run)(lambda source: through(source))
    return functools.wraps(run)(lambda key, source: through(key, source))


def parts(batch, rows: int = 256) -> Iterator:
    """An Arrow batch or array in parts, so that few texts are Python strings at once."""
    return (batch.slice(i, rows) for i in range(0, len(batch), rows))
