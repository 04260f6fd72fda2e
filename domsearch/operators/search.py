"""Exact search: the problem itself, the ground truth, and the filters that isolate sources of error."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.convert import conservative_threshold
from ..functions.scores import containment, jaccard
from ..store import fresh, materialise

SMALL_ENTRIES = 1_500_000  # query entries that are broadcast at once, as a number each under their values
SMALL_QUERIES = 100_000  # queries that may be broadcast
SALTS = 16
ASKED = 20
SLACK = 1e-12


def query_sample(domains: DataFrame, k: int | None, one_in: int = ASKED) -> DataFrame:
    """The k domains whose md5 comes first, the same in every engine; without k, every domain that is asked for."""
    chosen = domains.where(is_asked("domain_id", one_in)) if k is None else domains.orderBy(F.md5("domain_id"), "domain_id").limit(k)
    return chosen.select(F.col("domain_id").alias("query_id"), F.col("size").alias("q"))


def is_asked(key: str, one_in: int = ASKED) -> Column:
    """Whether the portable hash of an id is divisible by ``one_in``: a share of the ids that grows with the table."""
    return F.conv(F.substring(F.md5(key), 1, 15), 16, 10).cast("bigint") % one_in == 0


def overlaps(entries: DataFrame, sizes: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, q, domain_id, x, overlap) of all pairs that share a value.

    Query entries are broadcast by value, as many at once as ``SMALL_ENTRIES``: entries that are dealt out by domain are
    read in place for each batch of queries, and the counts stay in their tasks.  Several batches append to one table.
    ``queries`` may name the domain of a query in ``id`` where ``query_id`` is only its name in the result.
    """
    given = queries if "id" in queries.columns else queries.withColumn("id", F.col("query_id"))
    numbered = materialise(given.select("query_id", "q", "id", F.monotonically_increasing_id().alias("number")), "numbered")
    few = numbered.count() <= SMALL_QUERIES
    numbers = numbered.select(F.col("id").alias("domain_id"), "number")
    asked = materialise(entries.join(F.broadcast(numbers) if few else numbers, "domain_id").select("value", "number"), "asked")
    n = asked.count()

    def counts(some: DataFrame) -> DataFrame:
        some = materialise(some.groupBy("value").agg(F.collect_list("number").alias("numbers")), "asked")
        met = entries.join(F.broadcast(some), "value").select("domain_id", F.explode("numbers").alias("number"))
        met = met.groupBy("number", "domain_id").agg(F.count("*").alias("overlap"))
        return met.join(sizes.select("domain_id", F.col("size").alias("x")).hint("shuffle_hash"), "domain_id")

    if n <= SMALL_ENTRIES:
        rows = counts(asked)
    else:
        passes = -(-n // SMALL_ENTRIES)
        path, schema = fresh(entries.sparkSession, "pairs"), None
        for k in range(passes):
            found = counts(asked.where(F.pmod(F.xxhash64("number"), F.lit(passes)) == k))
            schema = found.schema
            found.sortWithinPartitions("domain_id", "number").write.mode("append").option("compression", "zstd").parquet(path)
        rows = entries.sparkSession.read.schema(schema).parquet(path)
    named = numbered.drop("id")
    return rows.join(F.broadcast(named) if few else named, "number").select("query_id", "q", "domain_id", "x", "overlap")


def exact(pairs: DataFrame, t: float | Column) -> DataFrame:
    """Pairs of at least containment t.  t = 0 holds for every pair by definition; here only those that share a value."""
    t = F.lit(float(t)) if not isinstance(t, Column) else t
    return pairs.withColumn("t", containment(F.col("overlap"), F.col("q"))).where(F.col("t") >= t)


def exact_jaccard(pairs: DataFrame, s: float) -> DataFrame:
    return pairs.withColumn("s", jaccard(F.col("overlap"), F.col("q"), F.col("x"))).where(F.col("s") >= s)


def exact_topk(pairs: DataFrame, k: int) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("t"), "domain_id"))
    return pairs.withColumn("t", containment(F.col("overlap"), F.col("q"))).withColumn("rank", rank).where(F.col("rank") <= k)


def joinable_datasets(pairs: DataFrame, dataset_of, t: float) -> DataFrame:
    """Per (query, dataset) the best attribute with containment of at least t."""
    hits = exact(pairs, t).withColumn("dataset", dataset_of(F.col("domain_id")))
    best = F.max_by(F.col("domain_id"), F.struct(F.col("t"), F.col("overlap"), F.col("domain_id")))
    return hits.groupBy("query_id", "dataset").agg(best.alias("domain_id"), F.round(F.max("t"), 6).alias("t"))


def ideal_filter(pairs: DataFrame, assigned: DataFrame, t: float) -> DataFrame:
    """Pairs whose exact Jaccard passes the conservative threshold of the domain's partition: no false negatives, some false positives."""
    parts = assigned.select("domain_id", "part_id", "part_size_max")
    rows = pairs.join(parts, "domain_id").withColumn("s", jaccard(F.col("overlap"), F.col("q"), F.col("x")))
    # the slack keeps pairs that stand exactly at the threshold whatever way the two sides round
    return rows.where(F.col("s") + SLACK >= conservative_threshold(F.lit(t), F.col("part_size_max"), F.col("q")))


def salted_overlaps(entries: DataFrame, queries_entries: DataFrame, salts: int = SALTS) -> DataFrame:
    """(query_id, domain_id, overlap) by a shuffled join in which every value is spread over ``salts`` tasks."""
    left = entries.withColumn("salt", F.pmod(F.xxhash64("domain_id"), F.lit(salts)).cast("int"))
    right = queries_entries.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return left.join(right.hint("shuffle_hash"), ["value", "salt"]).groupBy("query_id", "domain_id").agg(F.count("*").alias("overlap"))
