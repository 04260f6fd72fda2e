"""MinHash signatures: one pass, combined before the shuffle."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .convert import containment_of
from .hashing import PRIME, Native, Portable, coefficients, hashed_digits, hashed_int, hashed_long

CACHED = 32_768  # numbers that are hashed at a time, within a processor's cache
REPEATED = 4  # times that a value must occur to be hashed once
CODEGEN_FIELDS = 60  # minima in one aggregate; beyond about 100 fields Spark gives up generating code


def signatures(entries: DataFrame, family=None) -> DataFrame:
    """(domain_id, size, sig) of distinct entries (domain_id, value).

    Partial minima leave the map side, so a giant domain sends one row for each task.  Wide families are computed in
    slices of the function list that share the one shuffle of partial aggregates.
    """
    family = family or Portable()
    hashed = entries.select("domain_id", family.base(F.col("value")).alias("h"))
    functions = family.functions(F.col("h"))
    if len(functions) <= 2 * CODEGEN_FIELDS:
        mins = [F.min(f).alias(f"m{k}") for k, f in enumerate(functions)]
        return hashed.groupBy("domain_id").agg(F.count("*").alias("size"), *mins).select("domain_id", "size", F.array(*(f"m{k}" for k in range(len(functions)))).alias("sig"))
    slices = [functions[k : k + CODEGEN_FIELDS] for k in range(0, len(functions), CODEGEN_FIELDS)]
    part = F.explode(F.sequence(F.lit(0), F.lit(len(slices) - 1)))
    wide = hashed.withColumn("slice", part)
    choice = [[s[k] for s in slices if k < len(s)] for k in range(CODEGEN_FIELDS)]
    mins = []
    for k, options in enumerate(choice):
        value = F.lit(None).cast("bigint")
        for number, f in enumerate(options):
            value = F.when(F.col("slice") == number, f).otherwise(value)
        mins.append(F.min(value).alias(f"m{k}"))
    blocks = wide.groupBy("domain_id", "slice").agg(F.count("*").alias("size"), *mins)
    packed = blocks.select("domain_id", "size", F.struct("slice", F.array(*(f"m{k}" for k in range(CODEGEN_FIELDS))).alias("v")).alias("b"))
    whole = packed.groupBy("domain_id").agg(F.max("size").alias("size"), F.sort_array(F.collect_list("b")).alias("bs"))
    return whole.select("domain_id", "size", F.filter(F.flatten(F.transform("bs", lambda b: b["v"])), lambda x: x.isNotNull()).alias("sig"))


def portable_sketch(m: int, seed: int = 1):
    """Portable signatures of sets of whole numbers by numpy: every distinct value is hashed once."""
    maps = coefficients(m, seed)

    def sketch(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
        each, at = np.unique(values, return_inverse=True)
        base = np.array([int(hashlib.md5(str(v).encode()).hexdigest()[:15], 16) % PRIME for v in each.tolist()], np.int64)
        out = np.empty((len(starts), m), np.int32)
        for k, (a, b) in enumerate(maps):
            out[:, k] = np.minimum.reduceat(((a * base + b) % PRIME).astype(np.int32)[at], starts)
        return out

    return sketch


def native_sketch(m: int, seed: int = 1):
    """Signatures of ``Native`` of sets of whole numbers by numpy.

    Where values repeat much, every distinct one is hashed once; elsewhere finding it again costs more than its hash.
    """

    def of_distinct(base: np.ndarray, at: np.ndarray, starts: np.ndarray) -> np.ndarray:
        out = np.empty((m, len(starts)), np.int64)
        held, wide = np.empty(len(base), np.uint64), np.empty(len(at), np.uint64)
        for k in range(m):
            for a in range(0, len(base), CACHED):
                hashed_int(k, base[a : a + CACHED], held[a : a + CACHED])
            out[k] = np.minimum.reduceat(np.take(held, at, out=wide, mode="clip").view(np.int64), starts)
        return out

    def of_all(base: np.ndarray, starts: np.ndarray) -> np.ndarray:
        out = np.full((m, len(starts)), np.iinfo(np.int64).max)
        held, spare = np.empty((2, CACHED), np.uint64)
        for a in range(0, len(base), CACHED):
            some = base[a : a + CACHED]
            x, y = held[: len(some)], spare[: len(some)]
            # sets that have values here; the first may have begun before
            low, high = np.searchsorted(starts, a, "right") - 1, np.searchsorted(starts, a + len(some))
            here = np.maximum(starts[low:high] - a, 0)
            for k in range(m):
                least = np.minimum.reduceat(hashed_int(k, some, x, y).view(np.int64), here)
                np.minimum(out[k, low:high], least, out=out[k, low:high])
        return out

    def sketch(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
        each, at = np.unique(values, return_inverse=True)
        with np.errstate(over="ignore"):
            base = hashed_digits(each, hashed_int(seed, np.array([42], np.uint64))[0])
            base = hashed_long(base.view(np.int64))
            out = of_distinct(base, at, starts) if len(each) * REPEATED <= len(at) else of_all(np.take(base, at), starts)
        return np.ascontiguousarray(out.T)

    return sketch


def numeric_sketch(family):
    """Signatures of a family, of sets of whole numbers, by numpy."""
    return (native_sketch if isinstance(family, Native) else portable_sketch)(family.m, family.seed)


def merge(fragments: DataFrame, key: str = "domain_id") -> DataFrame:
    """Signature of a union of fragments: minima position by position."""
    rows = fragments.select(key, F.posexplode("sig").alias("i", "v")).groupBy(key, "i").agg(F.min("v").alias("v"))
    return rows.groupBy(key).agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "v"))), lambda x: x["v"]).alias("sig"))


def estimate_jaccard(a: Column, b: Column) -> Column:
    same = F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x)
    return same.cast("double") / F.size(a)


def estimate_containment(a: Column, b: Column, x: Column, q: Column) -> Column:
    return F.least(F.lit(1.0), containment_of(estimate_jaccard(a, b), x, q))


def estimate_size(sig: Column, family=None) -> Column:
    """Set size from the mean of the minima, scaled to [0, 1]."""
    family = family or Portable()
    total = F.aggregate(sig, F.lit(0.0), lambda s, v: s + (v.cast("double") - F.lit(float(family.low))) / F.lit(float(family.span)))
    return F.size(sig).cast("double") / total - 1


def _mixed(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values, in place."""
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(29)
    return x


def vector_signatures(entries: DataFrame, m: int = 256, seed: int = 1) -> DataFrame:
    """(domain_id, size, sig) with 64-bit functions evaluated by numpy, a batch of entries at a time.

    Entries are dealt out by domain; adaptive execution may split a giant domain over tasks, whose few partial
    signatures are merged position by position afterwards.  Only 64-bit hashes of values reach Python.
    """
    seeds = np.random.default_rng(seed).integers(0, 2**64, m, dtype=np.uint64)

    def partial(rows):
        held: tuple[str, int, np.ndarray] | None = None

        def out(parts):
            sig = np.stack([p[2] for p in parts]).view(np.int64)
            values = pa.array(sig.ravel())
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, sig.size + 1, m, dtype=np.int32)), values)
            return pa.RecordBatch.from_arrays([pa.array([p[0] for p in parts], pa.string()), pa.array([p[1] for p in parts], pa.int64()), lists], ["domain_id", "size", "sig"])

        for batch in rows:
            if not batch.num_rows:
                continue
            ids = batch.column(0).to_pylist()
            h = batch.column(1).to_numpy().astype(np.uint64)
            starts = np.array([0] + [k for k in range(1, len(ids)) if ids[k] != ids[k - 1]])
            mins = np.empty((len(starts), m), np.uint64)
            for k in range(m):
                mins[:, k] = np.minimum.reduceat(_mixed(h ^ seeds[k]) >> np.uint64(1), starts)
            done = []
            for k, (a, n) in enumerate(zip(starts.tolist(), np.diff(np.append(starts, len(ids))).tolist(), strict=True)):
                if held is not None and held[0] == ids[a]:
                    held = (held[0], held[1] + n, np.minimum(held[2], mins[k]))
                else:
                    if held is not None:
                        done.append(held)
                    held = (ids[a], n, mins[k])
            if done:
                yield out(done)
        if held is not None:
            yield out([held])

    hashed = entries.select("domain_id", F.xxhash64("value").alias("h")).hint("rebalance", "domain_id").sortWithinPartitions("domain_id")
    parts = hashed.mapInArrow(partial, "domain_id string, size long, sig array<bigint>")
    merged = parts.groupBy("domain_id").agg(F.sum("size").alias("size"), F.collect_list("sig").alias("sigs"))
    least = F.aggregate(F.slice("sigs", 2, F.size("sigs")), F.element_at("sigs", 1), lambda a, b: F.zip_with(a, b, lambda x, y: F.least(x, y)))
    return merged.select("domain_id", "size", least.alias("sig"))
