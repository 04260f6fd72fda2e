"""Intermediate tables in the folder that driver and executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

_local: list[str] = []


def folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where that is unset the warehouse, or in local mode a temporary folder."""
    if there := spark.conf.get("spark.checkpoint.dir", None):
        return there.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        return spark.conf.get("spark.sql.warehouse.dir").rstrip("/")
    if not _local:
        _local.append(tempfile.mkdtemp(prefix="domsearch-"))
        atexit.register(shutil.rmtree, _local[0], ignore_errors=True)
    return _local[0]


def fresh(spark: SparkSession, name: str) -> str:
    return f"{folder(spark)}/{name}-{uuid.uuid4().hex}"


BLOCK_ROWS = 3_000_000  # rows that one task sorts and packs at a time


def bucket_of(ids: np.ndarray, n: int) -> np.ndarray:
    """The bucket of n in which Spark puts a 64-bit id."""
    x = ids.astype(np.int64).view(np.uint64)
    h = np.full(len(x), 42, np.uint32)
    for k in ((x & np.uint64(0xFFFFFFFF)).astype(np.uint32), (x >> np.uint64(32)).astype(np.uint32)):
        k = k * np.uint32(0xCC9E2D51)
        k = ((k << np.uint32(15)) | (k >> np.uint32(17))) * np.uint32(0x1B873593)
        h = h ^ k
        h = ((h << np.uint32(13)) | (h >> np.uint32(19))) * np.uint32(5) + np.uint32(0xE6546B64)
    h = h ^ np.uint32(8)
    h = (h ^ (h >> np.uint32(16))) * np.uint32(0x85EBCA6B)
    h = (h ^ (h >> np.uint32(13))) * np.uint32(0xC2B2AE35)
    h = h ^ (h >> np.uint32(16))
    return h.view(np.int32).astype(np.int64) % n


def _distinct(ids: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct pairs in order."""
    low, least = int(ids.min()), int(values.min())
    span = int(values.max()) - least + 1
    if (int(ids.max()) - low + 1) * span < 2**63:
        both = np.unique((ids - low) * span + (values - least))
        return both // span + low, both % span + least
    order = np.lexsort((values, ids))
    ids, values = ids[order], values[order]
    new = np.append(True, (ids[1:] != ids[:-1]) | (values[1:] != values[:-1]))
    return ids[new], values[new]


def packed(numbers: np.ndarray) -> bytes:
    """Differences of 64-bit numbers, their bytes laid out by significance, compressed."""
    steps = np.diff(numbers, prepend=np.int64(0))
    return pa.compress(np.ascontiguousarray(steps.view(np.uint8).reshape(-1, 8).T).tobytes(), codec="zstd", asbytes=True)


def unpacked(block: bytes, n: int) -> np.ndarray:
    planes = np.frombuffer(pa.decompress(block, decompressed_size=8 * n, codec="zstd", asbytes=True), np.uint8)
    return np.cumsum(np.ascontiguousarray(planes.reshape(8, n).T).view(np.int64).ravel())


def _blocks(ids: np.ndarray, values: np.ndarray, n: int) -> pa.RecordBatch:
    """One row for each bucket: the distinct pairs of its ids."""
    ids, values = _distinct(ids, values)
    starts = np.flatnonzero(np.append(True, ids[1:] != ids[:-1]))
    runs = np.diff(np.append(starts, len(ids)))
    bucket = bucket_of(ids[starts], n)
    order = np.argsort(bucket, kind="stable")
    rows = []
    for own in np.split(order, np.flatnonzero(np.diff(bucket[order])) + 1):
        held = np.concatenate([values[a : a + k] for a, k in zip(starts[own].tolist(), runs[own].tolist(), strict=True)])
        rows.append((int(ids[starts[own[0]]]), len(own), len(held), packed(ids[starts[own]]), packed(runs[own].astype(np.int64)), packed(held)))
    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], ["first", "n_ids", "n_values", "ids", "runs", "held"])


def _dealt(df: DataFrame, n: int) -> DataFrame:
    """Rows of an id and a value, sent once as sorted blocks into n parts of the id."""

    def pack(batches):
        ids, values, size = [], [], 0
        for batch in batches:
            ids.append(batch.column(0).to_numpy(zero_copy_only=False))
            values.append(batch.column(1).to_numpy(zero_copy_only=False))
            size += batch.num_rows
            if size >= BLOCK_ROWS:
                yield _blocks(np.concatenate(ids), np.concatenate(values), n)
                ids, values, size = [], [], 0
        if size:
            yield _blocks(np.concatenate(ids), np.concatenate(values), n)

    blocks = df.mapInArrow(pack, "first bigint, n_ids bigint, n_values bigint, ids binary, runs binary, held binary")
    return blocks.repartition(n, "first")


def _undealt(batches) -> tuple[np.ndarray, np.ndarray] | None:
    """Distinct pairs, in order, of all blocks of a part."""
    ids, values = [], []
    for batch in batches:
        for r in batch.to_pylist():
            ids.append(np.repeat(unpacked(r["ids"], r["n_ids"]), unpacked(r["runs"], r["n_ids"])))
            values.append(unpacked(r["held"], r["n_values"]))
    return _distinct(np.concatenate(ids), np.concatenate(values)) if ids else None


def dealt_numbers(df: DataFrame, n: int, name: str = "table") -> DataFrame:
    """Distinct rows of an id and a value, 64-bit numbers that are not null, written once into n buckets of the id.

    They are sent as sorted blocks of differences, one for each bucket and some millions of rows: several times less than
    the rows themselves, and a row that repeats within a block is sent once.
    """
    spark, (key, value) = df.sparkSession, df.columns

    def unpack(batches):
        if (both := _undealt(batches)) is not None:
            a, b = both
            for k in range(0, len(a), 100_000):
                yield pa.RecordBatch.from_arrays([pa.array(a[k : k + 100_000]), pa.array(b[k : k + 100_000])], [key, value])

    path = fresh(spark, name)
    kept = f"{name}_{uuid.uuid4().hex}"
    rows = _dealt(df, n).mapInArrow(unpack, f"{key} bigint, {value} bigint")
    rows.write.bucketBy(n, key).option("path", path).option("compression", "zstd").saveAsTable(kept)
    return spark.table(kept)


SETS = "domain_id bigint, size bigint, sig array<int>, steps array<bigint>"
SKETCHES = "domain_id bigint, size bigint, sig array<bigint>"


def dealt_sets(df: DataFrame, n: int, sketch, min_size: int, signs_only: bool = False) -> DataFrame:
    """The same rows as whole sets, one row for each id of ``min_size`` values or more, with its signature.

    ``sketch`` gives the signatures (one row for each set) of values that lie set by set from ``starts`` on.  Values
    are in order and stand as differences; ``signs_only`` leaves them out, and minima are of 64 bits.
    """

    def unpack(batches):
        if (both := _undealt(batches)) is None:
            return
        ids, values = both
        starts = np.flatnonzero(np.append(True, ids[1:] != ids[:-1]))
        sizes = np.diff(np.append(starts, len(ids)))
        kept = sizes >= min_size
        values, ids, sizes = values[np.repeat(kept, sizes)], ids[starts[kept]], sizes[kept]
        if not len(ids):
            return
        ends = np.cumsum(sizes)
        starts = ends - sizes
        sig = sketch(values, starts)
        if signs_only:
            for a in range(0, len(ids), 4_096):
                some = sig[a : a + 4_096].astype(np.int64)
                signs = pa.ListArray.from_arrays(pa.array(np.arange(0, some.size + 1, some.shape[1], dtype=np.int32)), pa.array(some.ravel()))
                yield pa.RecordBatch.from_arrays([pa.array(ids[a : a + 4_096]), pa.array(sizes[a : a + 4_096]), signs], ["domain_id", "size", "sig"])
            return
        steps = np.diff(values, prepend=np.int64(0))
        steps[starts] = values[starts]
        # cut into batches of some 200,000 values, a large set alone
        cuts = np.unique(np.append(np.searchsorted(starts, np.arange(0, ends[-1], 200_000)), len(ids)))
        for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            signs = pa.ListArray.from_arrays(pa.array(np.arange(0, (b - a + 1) * sig.shape[1], sig.shape[1])[: b - a + 1].astype(np.int32)), pa.array(sig[a:b].ravel()))
            held = pa.ListArray.from_arrays(pa.array(np.append(starts[a:b], ends[b - 1]).astype(np.int64) - starts[a], pa.int32()), pa.array(steps[starts[a] : ends[b - 1]]))
            yield pa.RecordBatch.from_arrays([pa.array(ids[a:b]), pa.array(sizes[a:b]), signs, held], ["domain_id", "size", "sig", "steps"])

    return _dealt(df, n).mapInArrow(unpack, SKETCHES if signs_only else SETS)


def bucketed(df: DataFrame, key: str, n: int, name: str = "table") -> DataFrame:
    """Written once into n buckets of ``key``, for rows that are dealt out by it already."""
    kept = f"{name}_{uuid.uuid4().hex}"
    df.write.bucketBy(n, key).option("path", fresh(df.sparkSession, name)).saveAsTable(kept)
    return df.sparkSession.table(kept)


def materialise(df: DataFrame, name: str = "table") -> DataFrame:
    """Written once and read back, for a result that several parts of a plan need."""
    path = fresh(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
