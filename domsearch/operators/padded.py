"""The padded baseline: every set is filled up to the largest size with fresh values, the query is not."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, Portable
from ..functions.minhash import signatures


def pad_entries(entries: DataFrame, sizes: DataFrame, most: DataFrame) -> DataFrame:
    """Literal padding, for small collections: M - x fresh values for each domain."""
    room = sizes.crossJoin(F.broadcast(most)).where("m > size").select("domain_id", F.explode(F.sequence(F.col("size") + 1, F.col("m"))).alias("i"))
    fresh = room.select("domain_id", F.concat(F.lit("pad:"), F.col("domain_id"), F.lit(":"), F.col("i").cast("string")).alias("value"))
    return entries.select("domain_id", "value").unionByName(fresh)


def draws(name: Column, m: int) -> Column:
    """The 52 random bits of each position of a domain's signature, from which the least fresh hash is drawn."""
    return F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda i: F.pmod(F.xxhash64(name, i, F.lit(97)), F.lit(2**52)))


def padded_signatures(signed: DataFrame, most) -> DataFrame:
    """Padding simulated on signatures in O(m): the least of k fresh uniform hashes, drawn by its distribution function."""
    fresh = F.greatest(F.lit(0), most - F.col("size")).cast("double")
    draw = lambda i: (F.pmod(F.xxhash64("domain_id", i, F.lit(97)), F.lit(2**52)).cast("double") + 0.5) / F.lit(float(2**52))
    least = lambda i: F.floor(F.lit(float(PRIME)) * (1 - F.pow(1 - draw(i), 1 / fresh))).cast("bigint")
    padded = F.transform(F.col("sig"), lambda v, i: F.when(fresh > 0, F.least(v, least(i))).otherwise(v))
    return signed.withColumn("own", F.col("sig")).withColumn("sig", padded)


def literal(entries: DataFrame, sizes: DataFrame, family: Portable) -> DataFrame:
    """Signatures of the padded sets, with the real sizes and the unpadded signature as ``own``."""
    most = sizes.agg(F.max("size").alias("m"))
    padded = signatures(pad_entries(entries, sizes, most), family).select("domain_id", "sig")
    own = signatures(entries, family).select("domain_id", "size", F.col("sig").alias("own"))
    return own.join(padded, "domain_id")
