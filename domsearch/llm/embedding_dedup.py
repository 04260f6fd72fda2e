"""Embedding near-dedup: random-hyperplane sign hashing, exact cosines, connected components.

Equal vectors of one label are collapsed first, so a large group of copies is
one point with a weight.  Each point gets ``tables`` keys of ``bits`` signs;
points of one label and key meet in a bucket.  Buckets are formed from keys;
vectors join when the blocks are known.  A bucket is compared in blocks of
bounded size, so a hot bucket is spread over many tasks, and nothing is
emitted but each point's number of new links and a spanning forest.  A pair
that meets in several tables counts in the first of them only.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .frames import batches, by_key, written

THRESHOLD = 0.93
RECALL = 0.999  # of pairs that stand exactly at the threshold
BLOCK = 1024
SEED = 20011


def hashing_shape(points: int, threshold: float = THRESHOLD, recall: float = RECALL) -> tuple[int, int]:
    """Bits and tables: buckets of about 32 points for the largest label, and as many tables as the recall needs."""
    bits = min(60, max(6, math.ceil(math.log2(max(points, 2) / 32))))
    same = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, math.ceil(math.log(1 - recall) / math.log(1 - same))


def _hyperplanes(dimension: int, bits: int, tables: int) -> np.ndarray:
    return np.random.default_rng(SEED).standard_normal((dimension, bits * tables))


def _unit(m: np.ndarray) -> np.ndarray:
    m = m / np.abs(m).max(axis=1, keepdims=True)
    return m / np.sqrt((m * m).sum(axis=1, keepdims=True))


def _packed(m: np.ndarray) -> list[bytes]:
    """Each row's components as floats of 32 bits where those hold them exactly, else of 64."""
    with np.errstate(over="ignore"):
        short = m.astype("<f4")
    exact = (short == m).all(axis=1)
    return [(short[k] if exact[k] else m[k].astype("<f8")).tobytes() for k in range(len(m))]


def _unpacked(rows: list[bytes], dimension: int) -> np.ndarray:
    out = np.empty((len(rows), dimension))
    short = np.array([len(x) == 4 * dimension for x in rows], bool)
    for at, kind in ((np.flatnonzero(short), "<f4"), (np.flatnonzero(~short), "<f8")):
        if len(at):
            out[at] = np.frombuffer(b"".join(rows[k] for k in at.tolist()), kind).reshape(len(at), dimension)
    return out


def near_duplicates(vectors: DataFrame, threshold: float = THRESHOLD, recall: float = RECALL) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row with a vec_id.

    Only vectors of equal, non-null label and equal length are compared.  A vector that is null or zero, or that holds a null or
    non-finite component, links with nothing.  Rows that repeat a vec_id are one vector (the first in component order
    counts).  Extra columns play no part.
    """
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"), F.col("embedding").cast("array<double>").alias("v")).where("vec_id is not null")
    rows = rows.groupBy("vec_id").agg(F.min(F.struct("label", "v")).alias("x")).select("vec_id", "x.label", "x.v")
    bad = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    fine = rows.where(F.col("label").isNotNull() & F.col("v").isNotNull() & ~F.coalesce(bad, F.lit(True)) & F.exists("v", lambda x: x != 0))
    fine = fine.withColumn("v", F.transform("v", lambda x: x + F.lit(0.0)))  # -0.0 and 0.0 are one value
    fine = fine.select("vec_id", "label", "v", F.sha2(F.concat_ws(",", F.col("v").cast("array<string>")), 256).alias("digest"))
    fine = written(fine, "vectors")
    points = fine.groupBy("label", "digest").agg(F.min("vec_id").alias("rep"), F.count("*").alias("weight"))
    points = written(points, "points")
    largest = points.groupBy("label").count().agg(F.max("count")).first()[0] or 0
    bits, tables = hashing_shape(largest, threshold, recall)
    reps = points.select("rep", "label", "weight").join(fine.select(F.col("vec_id").alias("rep"), "v"), "rep")
    width = (bits + 7) // 8  # bytes of one table's signs

    def sketch(rows):
        for batch in batches(rows):
            lists = batch.column(3)
            size = np.array(pa.compute.list_value_length(lists).to_pylist(), np.int64)
            flat = lists.flatten().to_numpy(zero_copy_only=False)
            ends = np.cumsum(size)
            signs = np.zeros((len(size), tables), np.int64)
            raw: list[bytes] = [b""] * len(size)
            for d in np.unique(size).tolist():
                at = np.flatnonzero(size == d)
                m = np.stack([flat[ends[k] - d : ends[k]] for k in at])
                bit = (_unit(m) @ _hyperplanes(d, bits, tables) > 0).reshape(len(at), tables, bits)
                signs[at] = bit @ (1 << np.arange(bits, dtype=np.int64))
                for k, row in zip(at.tolist(), _packed(m), strict=True):
                    raw[k] = row
            packed = signs.astype("<i8").view(np.uint8).reshape(len(size), tables, 8)[:, :, :width]
            keys = pa.ListArray.from_arrays(pa.array(np.arange(len(size) + 1, dtype=np.int32) * tables), pa.array(signs.ravel()))
            yield pa.RecordBatch.from_arrays([
                batch.column(0), batch.column(1), batch.column(2), pa.array(size), keys, pa.array([x.tobytes() for x in packed], pa.binary()), pa.array(raw, pa.binary()),
            ], ["rep", "label", "weight", "dimension", "keys", "signs", "raw"])

    sketched = written(reps.mapInArrow(sketch, "rep long, label long, weight long, dimension long, keys array<long>, signs binary, raw binary"), "sketches")
    bucket = ["label", "dimension", "turn", "key"]
    # buckets are formed and cut into blocks by keys alone; blocks meet in pairs, and only their members' vectors are sent, once for each pair
    light = sketched.select("label", "dimension", F.posexplode("keys").alias("turn", "key"), "rep")
    sizes = light.groupBy(bucket).agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"), F.count("*").alias("m")).where("m > 1").drop("m")
    met = light.join(sizes, bucket).withColumn("block", F.pmod(F.xxhash64("rep"), "blocks").cast("int"))
    met = met.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    met = met.withColumn("i", F.least("block", "other")).withColumn("j", F.greatest("block", "other")).drop("other", "blocks")
    met = met.join(sketched.select("rep", "weight", "signs", "raw"), "rep")
    met = met.withColumn("signs", F.expr(f"substring(signs, 1, turn * {width})"))  # a turn asks for those before it only

    def compare(key, table):
        turn, i, j = key[2], key[4], key[5]
        block = table["block"].to_numpy()
        rep, weight = table["rep"].to_numpy(), table["weight"].to_numpy()
        signs = np.zeros((len(rep), turn, 8), np.uint8)
        if turn:
            signs[:, :, :width] = np.frombuffer(b"".join(table["signs"].to_pylist()), np.uint8).reshape(len(rep), turn, width)
        signs = signs.view("<i8")[:, :, 0]
        unit = _unit(_unpacked(table["raw"].to_pylist(), key[1]))
        a, b = np.flatnonzero(block == i), np.flatnonzero(block == j)
        close = unit[a] @ unit[b].T >= threshold
        for t in range(turn):
            close &= signs[a, t][:, None] != signs[b, t][None, :]
        if i == j:
            np.fill_diagonal(close, False)
        if not close.any():
            return
        links = np.zeros(len(rep), np.int64)
        links[a] += (close * weight[b][None, :]).sum(axis=1)
        if i != j:
            links[b] += (close * weight[a][:, None]).sum(axis=0)
        parent = np.full(len(rep), -1, np.int64)
        # a spanning forest by search: rows of unvisited points, each added once
        place_a, place_b = {x: k for k, x in enumerate(a.tolist())}, {x: k for k, x in enumerate(b.tolist())}
        seen: set[int] = set()
        for root in a.tolist():
            if root in seen or not close[place_a[root]].any():
                continue
            seen.add(root)
            stack = [root]
            while stack:
                x = stack.pop()
                found = []
                if x in place_a:
                    found += b[np.flatnonzero(close[place_a[x]])].tolist()
                if x in place_b:
                    found += a[np.flatnonzero(close[:, place_b[x]])].tolist()
                for y in found:
                    if y not in seen:
                        seen.add(y)
                        parent[y] = x
                        stack.append(y)
        some = np.flatnonzero((links > 0) | (parent >= 0))
        yield pa.RecordBatch.from_arrays([pa.array(rep[some]), pa.array(links[some]), pa.array([int(rep[p]) if p >= 0 else None for p in parent[some].tolist()], pa.int64())], ["rep", "links", "linked"])

    found = by_key(met, [*bucket, "i", "j"], compare, "rep long, links long, linked long")
    found = written(found, "links")
    counts = found.groupBy("rep").agg(F.sum("links").alias("links"))
    merged = connected_components(found.where("linked is not null").select("rep", "linked").distinct(), "rep", "linked")
    label = points.join(counts, "rep", "left").join(merged, points.rep == merged.node, "left")
    label = label.select("label", "digest", (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    members = fine.select("vec_id", "label", "digest").join(label, ["label", "digest"]).select("vec_id", "n_links", "component_id")
    out = rows.select("vec_id").join(members, "vec_id", "left")
    out = out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.col("vec_id") == F.col("component_id"))
