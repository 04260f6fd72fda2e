"""Shared folder, written tables and key-grouped Arrow batches for the operators of this subpackage."""

from __future__ import annotations

import atexit
import ctypes
import gc
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SMALL_IDS = 2_000_000  # ids that may be broadcast (16 MB); a larger set takes the shuffled join
ROWS_AT_ONCE = 1024

_local: str | None = None


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or where that is unset the warehouse; a temporary folder in local mode only."""
    global _local
    if there := spark.conf.get("spark.checkpoint.dir", None):
        return there.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        return spark.conf.get("spark.sql.warehouse.dir").rstrip("/")
    if _local is None:
        _local = tempfile.mkdtemp(prefix="domsearch-")
        atexit.register(shutil.rmtree, _local, ignore_errors=True)
    return _local


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def written(df: DataFrame, name: str, path: str | None = None) -> DataFrame:
    """``df`` as a table in the shared folder: lineage ends here and a lost executor loses nothing."""
    spark = df.sparkSession
    path = path or new_path(spark, name)
    df.write.mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def with_ids(df: DataFrame, ids: DataFrame, key: str, how: str) -> DataFrame:
    """Semi or anti join on ``key``; ``ids`` is broadcast when it is counted and small, else both sides are shuffled."""
    if ids.count() <= SMALL_IDS:
        ids = F.broadcast(ids)
    return df.join(ids, key, how)


def documents_only(df: DataFrame) -> DataFrame:
    """doc_id and text of the rows that have an id; other columns play no part."""
    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("doc_id is not null")


def as_bytes(column: Column | str) -> Column:
    return F.col(column).cast("binary") if isinstance(column, str) else column.cast("binary")


def tidy() -> None:
    """Give memory that a finished task freed back to the system; a reused worker would keep it."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library


def batches(rows: Iterator[pa.RecordBatch], at_once: int = ROWS_AT_ONCE) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of bounded height."""
    for batch in rows:
        for k in range(0, batch.num_rows, at_once):
            yield batch.slice(k, at_once)
    tidy()


def key_groups(rows: Iterator[pa.RecordBatch], n_keys: int) -> Iterator[tuple[tuple, pa.Table]]:
    """Groups of consecutive rows with equal first ``n_keys`` columns, of rows sorted by them."""
    held: list[pa.RecordBatch] = []
    key: tuple | None = None
    for batch in rows:
        if not batch.num_rows:
            continue
        keys = list(zip(*(batch.column(k).to_pylist() for k in range(n_keys)), strict=True))
        at = 0
        while at < len(keys):
            end = at + 1
            while end < len(keys) and keys[end] == keys[at]:
                end += 1
            if held and keys[at] != key:
                yield key, pa.Table.from_batches(held)
                held = []
            key = keys[at]
            held.append(batch.slice(at, end - at))
            at = end
    if held:
        yield key, pa.Table.from_batches(held)
    tidy()


def by_key(df: DataFrame, keys: list[str], function: Callable, schema: str, n: int | None = None) -> DataFrame:
    """``function(key, table)`` on every group, many groups to a task; it yields record batches of ``schema``."""
    columns = keys + [c for c in df.columns if c not in keys]
    n_keys = len(keys)

    def run(rows):
        for key, table in key_groups(rows, n_keys):
            yield from function(key, table)

    dealt = df.select(columns).repartition(n or partitions(df.sparkSession), *keys)
    return dealt.sortWithinPartitions(*keys).mapInArrow(run, schema)
