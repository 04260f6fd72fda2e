"""Benchmark decontamination by size-partitioned MinHash containment search.

A test item is a small set of word shingles, a document a large one that may
hold it; their Jaccard similarity is small even where containment is 1.  Two
steps keep the search sharp without losing anything.  First a document is
restricted to the shingles that any item has, which changes no intersection
with an item, and so no containment.  Then items and restricted documents are
partitioned by size; in every pair of partitions the containment threshold
becomes a conservative Jaccard threshold through the largest sizes, and the
band width of the MinHash search is the widest that still finds a pair at that
threshold with a chance of at least ``1 - MISS``.  Where no band width does,
the pair of partitions is probed by shared shingles, which misses nothing.
Candidates are verified by exact shingle containment on the texts.  All steps
are DataFrame expressions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .frames import SMALL_IDS, documents_only, with_ids, written

HASHES = 256  # restricted sets are small, so a wide signature costs little
MISS = 1e-7
SMALL_GRAMS = 2_000_000  # item shingles that may be broadcast (16 MB)
_SPACES = r"[\x20\x09-\x0D]+"


def words_of(text: Column) -> Column:
    """Lower-case words; a leading white space leaves an empty one, which goes."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), _SPACES), lambda w: w != "")


def gram_hashes(words: Column, n: int) -> Column:
    at = F.when(F.size(words) >= n, F.sequence(F.lit(1), F.size(words) - n + 1)).otherwise(F.expr("cast(array() as array<int>)"))
    return F.transform(at, lambda i: F.xxhash64(F.lit(n), *(F.element_at(words, i + k) for k in range(n))))


def gram_texts(words: Column, n: int) -> Column:
    at = F.when(F.size(words) >= n, F.sequence(F.lit(1), F.size(words) - n + 1)).otherwise(F.expr("cast(array() as array<int>)"))
    return F.transform(at, lambda i: F.concat_ws(" ", F.slice(words, i, n)))


def signature(grams: Column, hashes: int = HASHES) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(hashes - 1)), lambda j: F.array_min(F.transform(grams, lambda h: F.xxhash64(h, j))))


def band_width(q: int, x: int, percent: int, hashes: int = HASHES, miss: float = MISS) -> int:
    """Widest band that finds a contained pair of sizes up to (q, x); 0: none does."""
    least = percent / 100 * q
    s = least / (x + q - least)
    return max([r for r in range(1, hashes + 1) if (1 - min(s, 1.0) ** r) ** (hashes // r) <= miss], default=0)


def find_contained(docs: DataFrame, items: DataFrame, n_words: int = 5, percent: int = 80, hashes: int = HASHES) -> DataFrame:
    """(doc_id, item_id, n_shingles, n_shared, containment) of every pair with containment >= percent/100.

    An item of fewer than ``n_words`` words is one shingle of all its words and is looked for as such.  Items without
    words and rows without an id are left out; documents without words hold nothing.  Each text of an
    item_id is looked for by itself; a pair stands once, with the text of which the document holds the largest share.
    Extra columns play no part.
    """
    spark = docs.sparkSession
    docs = documents_only(docs)
    items = items.select(F.col("item_id").cast("long").alias("item_id"), words_of(F.col("text").cast("string")).alias("words")).where("item_id is not null and size(words) > 0")
    items = items.withColumn("n", F.least(F.size("words"), F.lit(n_words)))
    by_n = [F.when(F.col("n") == n, F.array_distinct(gram_hashes(F.col("words"), n))) for n in range(1, n_words + 1)]
    items = items.dropDuplicates(["item_id", "words"]).select("item_id", "n", "words", F.coalesce(*by_n).alias("grams"))
    items = written(items.withColumn("part", F.monotonically_increasing_id()), "items")  # numbered once, one number for each text
    lengths = sorted(r["n"] for r in items.select("n").distinct().collect())  # n_words values at most
    universe = items.select(F.explode("grams").alias("h")).distinct()
    if universe.count() <= SMALL_GRAMS:
        universe = F.broadcast(universe)

    words = docs.select("doc_id", words_of(F.col("text")).alias("words"))
    all_grams = F.concat(*(gram_hashes(F.col("words"), n) for n in lengths)) if lengths else F.expr("cast(array() as array<bigint>)")
    held = words.select("doc_id", F.explode(all_grams).alias("h")).join(universe, "h", "left_semi").distinct()
    held = held.groupBy("doc_id").agg(F.collect_list("h").alias("grams"))
    fewest = items.agg(F.min(F.size("grams"))).first()[0] or 1
    held = held.where(F.size("grams") * 100 >= percent * fewest)
    held = written(held.withColumn("size_class", F.ceil(F.log2(F.size("grams"))).cast("int")), "restricted")
    sized = items.withColumn("size_class", F.ceil(F.log2(F.size("grams"))).cast("int"))

    # one row for each pair of partitions: a plan of (largest class)**2 rows at most
    item_classes = [(r[0], r[1], r[2]) for r in sized.groupBy("size_class").agg(F.max(F.size("grams")), F.min(F.size("grams"))).collect()]
    doc_classes = [(r[0], r[1]) for r in held.groupBy("size_class").agg(F.max(F.size("grams"))).collect()]
    # the smallest item of a class gives the lowest threshold; partitions too small for any item are pruned
    plan = [(i, d, band_width(low, x, percent, hashes)) for i, _, low in item_classes for d, x in doc_classes if 100 * x >= percent * low]
    plan = spark.createDataFrame(plan, "item_class int, doc_class int, r int")

    def bands(rows: DataFrame, key: str, own: str) -> DataFrame:
        rows = rows.select(key, F.col("size_class").alias(own), signature(F.col("grams"), hashes).alias("sig")).join(F.broadcast(plan.where("r > 0")), own)
        at = F.sequence(F.lit(0), F.floor(F.lit(hashes) / F.col("r")).cast("int") - 1)
        keys = F.transform(at, lambda b: F.xxhash64(b, F.slice("sig", b * F.col("r") + 1, F.col("r"))))
        return rows.select(key, "item_class", "doc_class", F.explode(keys).alias("band"))

    near = bands(held, "doc_id", "doc_class").join(bands(sized, "part", "item_class"), ["item_class", "doc_class", "band"]).select("doc_id", "part")
    exact = F.broadcast(plan.where("r = 0"))
    wide = held.withColumnRenamed("size_class", "doc_class").join(exact, "doc_class").select("doc_id", "item_class", F.explode("grams").alias("h"))
    probe = sized.select("part", F.col("size_class").alias("item_class"), F.explode("grams").alias("h"))
    candidates = written(near.unionByName(wide.join(probe, ["item_class", "h"]).select("doc_id", "part")).distinct(), "pairs")

    # verification on the texts themselves
    texts = with_ids(docs, candidates.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", words_of(F.col("text")).alias("doc_words"))
    pairs = texts.join(candidates, "doc_id").join(items.select("part", "item_id", "n", "words"), "part")
    shared = [F.when(F.col("n") == n, F.struct(F.size(F.array_distinct(gram_texts(F.col("words"), n))).alias("q"), F.size(F.array_intersect(gram_texts(F.col("words"), n), gram_texts(F.col("doc_words"), n))).alias("o"))) for n in range(1, n_words + 1)]
    pairs = pairs.select("doc_id", "item_id", F.coalesce(*shared).alias("s"))
    pairs = pairs.select("doc_id", "item_id", F.col("s.q").cast("long").alias("n_shingles"), F.col("s.o").cast("long").alias("n_shared"))
    best = F.max(F.struct(F.col("n_shared") / F.col("n_shingles"), "n_shingles", "n_shared")).alias("best")
    pairs = pairs.where(F.col("n_shared") * 100 >= F.col("n_shingles") * percent).groupBy("doc_id", "item_id").agg(best)
    return pairs.select("doc_id", "item_id", "best.n_shingles", "best.n_shared").withColumn("containment", F.round(F.col("n_shared") / F.col("n_shingles"), 6))


def decontaminate(docs: DataFrame, items: DataFrame, n_words: int = 5, percent: int = 80) -> DataFrame:
    """The documents that hold no item; rows without a doc_id stay."""
    found = find_contained(docs, items, n_words, percent).select("doc_id").distinct()
    return with_ids(docs, found, "doc_id", "left_anti")


__all__ = ["SMALL_IDS", "band_width", "decontaminate", "find_contained", "gram_hashes", "signature", "words_of"]
