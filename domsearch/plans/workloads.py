"""The experiment workloads: accuracy sweeps over thresholds, query sizes, skew, drift and signature length, in single plans."""

from __future__ import annotations

from functools import cached_property

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import accuracy, extract, partition, search, stats
from ..sources.tables import table
from ..store import materialise
from . import sqltext as q
from .methods import Corpus, settings_of, share_rank
from .registry import query

THRESHOLDS = [k / 20 for k in range(1, 21)]
SPECS = [("minhash_lsh", 1, False), ("padded", 1, True), ("spci_n8", 8, False), ("spci_n16", 16, False), ("spci_n32", 32, False)]
CUTS = tuple(k / 20 for k in range(1, 21))
LAMBDAS = tuple(k / 10 for k in range(11))


class Bench:
    """A corpus whose domains are written once as whole rows and shared by all index settings of a sweep.

    Answers are judged pair by pair where the domains lie (see ``pairwise``), for all settings in one pass.
    """

    def __init__(self, spark, sf_dir: str, corpus: str = "slices", k: int | None = None, m: int = 256, where: str = "true", one_in: int = search.ASKED):
        self.spark, self.m = spark, m
        self.corpus = c = Corpus(spark, sf_dir, corpus, m=m)
        self.signed = extract.labelled(c.whole.select("domain_id", "size", F.col("sig").cast("array<bigint>").alias("sig")), corpus)
        self.sizes = materialise(self.signed.select("domain_id", "size"), "sizes")
        self.queries = materialise(search.query_sample(self.sizes.where(where), k, one_in), "queries")

    @cached_property
    def pairs(self) -> DataFrame:
        return self.corpus.overlaps(self.queries)

    @cached_property
    def hist(self) -> DataFrame:
        return materialise(stats.histogram(self.sizes), "histogram")

    def cuts(self, n: int, partitioner=partition.equi_depth) -> list:
        return partitioner(self.hist, n).orderBy("part_id").collect()  # n rows

    def measure(self, settings: list, names: list[tuple], columns: str) -> DataFrame:
        """Summary of settings by the columns that name them and the threshold."""
        keys = [(*name, t) for s, name in zip(settings, names, strict=True) for t in s.thresholds]
        keys = self.spark.createDataFrame([(k, *key) for k, key in enumerate(keys)], f"key bigint, {columns}, t_star double")
        return accuracy.summary(self.corpus.counted(self.queries, settings, keys), tuple(c for c in keys.columns if c != "key"))

    def sweep(self, specs=SPECS, thresholds=THRESHOLDS) -> DataFrame:
        settings = [settings_of([self.cuts(n)], list(thresholds), self.m, pad=pad)[0] for _, n, pad in specs]
        return self.measure(settings, [(name,) for name, _, _ in specs], "index_id string")

    def nested(self, specs, cuts, t: float) -> DataFrame:
        """Answers and truth in nested collections, the domains up to each quantile of the sizes, as one index of each setting.

        Every collection has partitions of its own; a domain stands in one partition of each collection that holds it.
        """
        most = self.sizes.select(F.percentile("size", F.array(*(F.lit(c) for c in cuts))).alias("p")).first()["p"]
        cut = F.broadcast(self.spark.createDataFrame(list(zip(cuts, most, strict=True)), "cut double, most double"))
        hist = self.hist.select("size", "n_domains").join(cut, F.col("size") <= F.col("most"))
        before = Window.partitionBy("cut").orderBy("size").rowsBetween(Window.unboundedPreceding, -1)
        hist = hist.withColumn("cum_before", F.coalesce(F.sum("n_domains").over(before), F.lit(0))).withColumn("total", F.sum("n_domains").over(Window.partitionBy("cut")))
        hist = materialise(hist, "nested")
        settings, names = [], []
        for name, n, pad in specs:
            part = F.least(F.lit(n - 1), F.floor(F.lit(n) * F.col("cum_before") / F.col("total")))
            parts = hist.groupBy("cut", "most", part.alias("part")).agg(F.min("size").alias("size_lo"), F.max("size").alias("size_max"))
            held: dict[tuple, list] = {}
            for r in parts.orderBy("cut", "part").collect():  # cuts x n rows
                held.setdefault((r["cut"], r["most"]), []).append(r)
            for (at, largest), rows in held.items():
                settings += settings_of([rows], [t], self.m, pad=pad, most=largest)
                names.append((name, at))
        skew = self.sizes.join(cut, F.col("size") <= F.col("most")).groupBy("cut").agg(F.count("*").alias("n_domains"), F.round(F.skewness("size"), 6).alias("skewness"))
        return self.measure(settings, names, "index_id string, cut double").join(F.broadcast(skew), "cut").withColumnRenamed("cut", "share_of_domains")


@query("acc_vs_threshold")
def acc_vs_threshold(spark, sf_dir, corpus: str = "slices", **options):
    return Bench(spark, sf_dir, corpus, **options).sweep()


def _by_query_size(spark, sf_dir, where: str, corpus: str = "slices", thresholds=THRESHOLDS, **options) -> DataFrame:
    sizes = extract.sizes(extract.CORPORA[corpus](spark, sf_dir))
    low, high = sizes.select(F.percentile("size", F.array(F.lit(0.1), F.lit(0.9))).alias("p")).first()["p"]
    return Bench(spark, sf_dir, corpus, where=where.format(low=low, high=high), one_in=1, **options).sweep(thresholds=thresholds)


@query("acc_large_queries")
def acc_large_queries(spark, sf_dir, **options):
    return _by_query_size(spark, sf_dir, "size >= {high}", **options)


@query("acc_small_queries")
def acc_small_queries(spark, sf_dir, **options):
    return _by_query_size(spark, sf_dir, "size <= {low}", **options)


@query("acc_vs_skew")
def acc_vs_skew(spark, sf_dir, corpus: str = "slices", cuts: tuple[float, ...] = CUTS, **options):
    """Twenty nested subsets of the smallest sizes, each with its skewness."""
    return Bench(spark, sf_dir, corpus, **options).nested(SPECS, cuts, 0.5)


@query("acc_vs_drift")
def acc_vs_drift(spark, sf_dir, corpus: str = "slices", lambdas: tuple[float, ...] = LAMBDAS, **options):
    """From equi-depth to equi-width: accuracy beside the deviation of partition sizes."""
    b = Bench(spark, sf_dir, corpus, **options)
    names, drift = [f"drift_{lam:g}" for lam in lambdas], []
    metas = [b.cuts(32, lambda hist, n, lam=lam: partition.blended(hist, n, lam)) for lam in lambdas]
    for name, rows in zip(names, metas, strict=True):
        drift.append((name, float(np.std([r["n_domains"] for r in rows]))))
    drift = b.spark.createDataFrame(drift, "index_id string, stddev double").withColumn("stddev", F.round("stddev", 6))
    return b.measure(settings_of(metas, [0.5], b.m), [(n,) for n in names], "index_id string").join(F.broadcast(drift), "index_id")


@query("acc_vs_length")
def acc_vs_length(spark, sf_dir, corpus: str = "slices", lengths: tuple[int, ...] = (64, 128, 256), thresholds=(0.3, 0.5, 0.7), **options):
    """Accuracy against the number m of hash functions, for plain MinHash LSH and 32 partitions."""
    b = Bench(spark, sf_dir, corpus, m=max(lengths), **options)
    kept = [(s, m) for s in SPECS if s[1] in (1, 32) and not s[2] for m in lengths]
    settings = [settings_of([b.cuts(s[1])], list(thresholds), m)[0] for s, m in kept]
    return b.measure(settings, [(f"{s[0]}_m{m}",) for s, m in kept], "index_id string")


@query("cost_vs_domains")
def cost_vs_domains(spark, sf_dir, corpus: str = "slices", shares: tuple[int, ...] = (20, 40, 60, 80, 100), ns: tuple[int, ...] = (1, 8, 32), m: int = 64, t: float = 0.5):
    """Size of the index and candidates of all queries for growing shares of the domains; wall times are in the bench."""
    b = Bench(spark, sf_dir, corpus, m=m)
    settings, keys = [], []
    for share in shares:
        kept = b.sizes.where(share_rank(F.col("domain_id")) < share)
        hist, n_domains = materialise(stats.histogram(kept), "histogram"), kept.count()
        for n in ns:
            keys.append((len(keys), share, n, n_domains))
            settings += settings_of([partition.equi_depth(hist, n).orderBy("part_id").collect()], [t], m, share=share)
    keys = spark.createDataFrame(keys, "key bigint, share int, n_partitions int, n_domains bigint")
    found = b.corpus.counted(b.queries, settings, keys).groupBy("key").agg(F.sum("n_answer").alias("n"))
    return keys.join(found, "key", "left").select("share", "n_partitions", "n_domains", F.coalesce("n", F.lit(0)).cast("bigint").alias("n_candidates"))


# --- questions on the remaining tables ------------------------------------------------------------------------------
_DOC = r"d as materialized (select distinct doc_id, unnest(string_split_regex(lower(text), '\s+')) as value from documents)"


def _tokens(df: DataFrame, key: str) -> DataFrame:
    return df.select(key, F.explode(F.array_distinct(F.split(F.lower("text"), r"\s+"))).alias("value")).distinct()


def _contained(asked: DataFrame, key: str, docs: DataFrame, t: float) -> DataFrame:
    """Pairs of queries and documents with containment of at least t."""
    q_ = asked.groupBy(key).agg(F.count("*").alias("q"))
    counts = docs.join(asked, "value").groupBy(key, "doc_id").agg(F.count("*").alias("overlap"))
    return counts.join(q_, key).where(F.col("overlap") / F.col("q") >= t).select(key, "doc_id", F.round(F.col("overlap") / F.col("q"), 6).alias("t"))


@query("benchmark_containment", r"with " + _DOC + r", b as (select distinct item_id, unnest(string_split_regex(lower(text), '\s+')) as value from benchmark), n as (select item_id, count(*) q from b group by 1) select item_id, doc_id, round(overlap / q, 6) t from (select item_id, doc_id, count(*) overlap from b join d using (value) group by 1, 2) join n using (item_id) where overlap / q >= 0.9")
def benchmark_containment(spark, sf_dir):
    return _contained(_tokens(table(spark, sf_dir, "benchmark"), "item_id"), "item_id", _tokens(table(spark, sf_dir, "documents"), "doc_id"), 0.9)


@query("conversation_search", r"with " + _DOC + r", b as (select distinct conv_id, unnest(string_split_regex(lower(text), '\s+')) as value from conversations where conv_id % 20 = 0), n as (select conv_id, count(*) q from b group by 1) select conv_id, doc_id, round(overlap / q, 6) t from (select conv_id, doc_id, count(*) overlap from b join d using (value) group by 1, 2) join n using (conv_id) where overlap / q >= 0.5")
def conversation_search(spark, sf_dir, where="conv_id % 20 = 0"):
    return _contained(_tokens(table(spark, sf_dir, "conversations").where(where), "conv_id"), "conv_id", _tokens(table(spark, sf_dir, "documents"), "doc_id"), 0.5)


@query("near_copies", r"with " + _DOC + r", n as (select doc_id, count(*) q from d group by 1), k as (select doc_id from n where doc_id % 20 = 0), o as (select a.doc_id a, b.doc_id b, count(*) overlap from d a join d b using (value) where a.doc_id in (select doc_id from k) and a.doc_id <> b.doc_id group by 1, 2) select a, b, overlap from o join n x on x.doc_id = a join n y on y.doc_id = b where overlap / x.q >= 0.8 and overlap / y.q >= 0.8")
def near_copies(spark, sf_dir):
    """Pairs that share 0.8 of either side's tokens, of every document whose id is divisible by 20.

    With the tokens of all documents in one order, rarest first, two such sets share l of their first tokens: of q, a
    set may miss q - o with o = ceil(0.8 q), so q - o + l are enough, and l is o / 8.  Only those are joined, by their
    hashes, and the pairs found are compared whole.  The order tells apart tokens of more than one document in 500; they number 500 times the mean set at most.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    words = F.array_distinct(F.split(F.lower("text"), r"\s+"))
    common = docs.select(F.explode(words).alias("value")).groupBy("value").agg(F.count("*").alias("n")).where(F.col("n") > docs.count() / 500)
    # dealt by document once, so that its tokens are gathered where they are
    tokens = _tokens(docs.repartition("doc_id"), "doc_id").join(F.broadcast(common), "value", "left")
    ordered = F.sort_array(F.collect_list(F.struct(F.coalesce("n", F.lit(0)).alias("n"), F.xxhash64("value").alias("h"))))
    sets = tokens.groupBy("doc_id").agg(ordered.alias("w")).withColumn("q", F.size("w")).withColumn("o", F.expr("(4 * q + 4) div 5"))
    sets = sets.withColumn("l", F.expr("greatest(o div 8, 1)"))
    first = sets.select("doc_id", "q", "l", F.explode(F.slice("w", F.lit(1), F.expr("cast(q - o + l as int)"))["h"]).alias("h"))
    a = first.where(F.col("doc_id") % search.ASKED == 0)
    near = a.select(F.col("doc_id").alias("a"), F.col("q").alias("qa"), F.col("l").alias("la"), "h").join(first, "h").where("a <> doc_id and 5 * least(qa, q) >= 4 * greatest(qa, q)")
    near = near.groupBy("a", F.col("doc_id").alias("b")).agg(F.count("*").alias("n"), F.min(F.least("la", "l")).alias("l"))
    pairs = materialise(near.where("n >= l").select("a", "b"), "pairs")
    ids = pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    whole = _tokens(docs.join(ids, "doc_id", "left_semi"), "doc_id").groupBy("doc_id").agg(F.collect_list("value").alias("w"))
    both = pairs.join(whole.select(F.col("doc_id").alias("a"), F.col("w").alias("wa")), "a").join(whole.select(F.col("doc_id").alias("b"), F.col("w").alias("wb")), "b")
    both = both.withColumn("overlap", F.size(F.array_intersect("wa", "wb")).cast("long"))
    return both.where("overlap / size(wa) >= 0.8 and overlap / size(wb) >= 0.8").select("a", "b", "overlap")


@query("labels_of_matches", r"with " + _DOC + r", b as (select distinct item_id, unnest(string_split_regex(lower(text), '\s+')) as value from benchmark), n as (select item_id, count(*) q from b group by 1), f as (select distinct doc_id from (select item_id, doc_id, count(*) overlap from b join d using (value) group by 1, 2) join n using (item_id) where overlap / q >= 0.9) select count(*) n_found, count(l.doc_id) n_labelled, cast(coalesce(sum(l.quality), 0) as bigint) n_good, cast(coalesce(sum(l.toxic), 0) as bigint) n_toxic from f left join labels l using (doc_id)")
def labels_of_matches(spark, sf_dir):
    found = benchmark_containment(spark, sf_dir).select("doc_id").distinct()
    labels = table(spark, sf_dir, "labels").withColumn("labelled", F.lit(1))
    return found.join(labels, "doc_id", "left").agg(F.count("*").alias("n_found"), F.count("labelled").alias("n_labelled"), F.coalesce(F.sum("quality"), F.lit(0)).cast("long").alias("n_good"), F.coalesce(F.sum("toxic"), F.lit(0)).cast("long").alias("n_toxic"))


@query("embedding_centroids")
def embedding_centroids(spark, sf_dir):
    rows = table(spark, sf_dir, "embeddings").select("label", F.posexplode("embedding").alias("i", "v"))
    return rows.groupBy("label", "i").agg(F.round(F.avg("v"), 5).alias("mean"), F.count("*").alias("n"))


__all__ = ["Bench", "q"]
