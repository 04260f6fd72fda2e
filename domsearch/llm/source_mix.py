"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

Every source is cut into blocks in a permuted order.  The words that the mix
takes from a source are whole passes over its blocks and the first blocks of
one more pass; the last of these gives part of its documents, and one document
part of its words, so a source meets its target to the word.  The exact block
quotas of all sources are split over the output shards by a binary tree: at
each node the left half's quotas are drawn without replacement from the
node's.  A leaf takes the next blocks of each source's permuted order, so
shards are disjoint.  Prefix sums over the blocks of a source run in two
levels, so a source with very many blocks is spread over tasks.  Only
expressions of Spark SQL run on the executors; the tree itself works on one
count per source, on the driver.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .frames import written

WEIGHTS = (5, 2, 1)
SHARE, MOST = 1.5, 2.0  # words of the mix for each word of input; repeats of a source at most
BLOCK_DOCUMENTS = 512
SMALL_PLAN = 500_000  # rows of a plan that may be broadcast; a larger one is joined by a shuffle


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def waterfill(sizes: list[int], weights: list[float], share: float = SHARE, most: float = MOST) -> list[float]:
    """Targets in proportion to the weights, none above ``most`` times its size; what is cut off is shared again."""
    left = share * sum(sizes)
    targets = [0.0] * len(sizes)
    open_ = [k for k, w in enumerate(weights) if w > 0]
    while open_:
        weight = sum(weights[k] for k in open_)
        full = [k for k in open_ if left * weights[k] / weight >= most * sizes[k]]
        if not full:
            for k in open_:
                targets[k] = left * weights[k] / weight
            break
        for k in full:
            targets[k] = most * sizes[k]
        left -= sum(targets[k] for k in full)
        open_ = [k for k in open_ if k not in set(full)]
    return targets


def splitting_tree(quotas: list[int], shards: int, seed: int) -> list[list[int]]:
    """Block quotas of every shard and source; columns add up to ``quotas``, rows differ by one block at most."""
    rng = np.random.default_rng(seed)
    out: list[list[int]] = []

    def split(counts: np.ndarray, n: int) -> None:
        if n == 1:
            out.append(counts.tolist())
            return
        half = n // 2
        size = int(counts.sum()) * half // n
        left = rng.multivariate_hypergeometric(counts, size, method="marginals") if counts.sum() else counts
        split(left, half)
        split(counts - left, n - half)

    split(np.array(quotas, np.int64), shards)
    return out


def mix_sources(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST, shards: int = 16, seed: int = 7, block_documents: int = BLOCK_DOCUMENTS) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, taken and draws (shard, pass, block, position, words).

    Sources by code point, null last, have the weights in turn.  Null or empty texts have size 0 and are never drawn;
    rows with a null doc_id, and repeated rows, take part each for itself.  Extra columns play no part.  An empty table
    gives no rows.  The driver holds one count for each source.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), n_words(F.col("text").cast("string")).alias("size"))
    rows = written(rows.withColumn("key", F.xxhash64(F.lit(seed), "doc_id", "size")), "sizes")
    per = rows.groupBy("source").agg(F.sum("size").alias("words"), F.count("*").alias("n")).orderBy(F.col("source").asc_nulls_last()).collect()
    small = F.broadcast if len(per) * shards <= SMALL_PLAN else (lambda df: df)
    targets = waterfill([r["words"] for r in per], [float(weights[k % len(weights)]) for k in range(len(per))], share, most)
    plan = []
    for k, (r, t) in enumerate(zip(per, targets, strict=True)):
        whole = int(round(t)) // r["words"] if r["words"] else 0
        plan.append((k, r["source"], r["words"], t, whole, int(round(t)) - whole * r["words"], -(-r["n"] // block_documents)))
    schema = "sid int, source string, source_size long, target double, passes int, rest long, blocks int"
    sources = small(spark.createDataFrame(plan, schema))

    rows = rows.join(sources, rows.source.eqNullSafe(sources.source)).drop(sources.source)
    rows = rows.withColumn("block", F.pmod(F.xxhash64("key", F.lit(seed + 1)), "blocks").cast("int"))
    # blocks in permuted order, with the words before each: sums over slices of the order, then inside each slice
    blocks = rows.groupBy("sid", "block", "blocks", "passes", "rest").agg(F.sum("size").alias("block_size"))
    blocks = blocks.withColumn("order", F.xxhash64("sid", "block", F.lit(seed + 2))).withColumn("slice", F.shiftrightunsigned("order", 54).cast("int"))
    slices = blocks.groupBy("sid", "slice").agg(F.count("*").alias("n"), F.sum("block_size").alias("words"))
    earlier = Window.partitionBy("sid").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    slices = slices.select("sid", "slice", *(F.coalesce(F.sum(c).over(earlier), F.lit(0)).alias(f"{c}_ahead") for c in ("n", "words")))
    permuted = Window.partitionBy("sid", "slice").orderBy("order", "block")
    inside = F.coalesce(F.sum("block_size").over(permuted.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    blocks = blocks.withColumn("at", F.row_number().over(permuted) - 1).withColumn("inside", inside).join(slices, ["sid", "slice"])
    blocks = blocks.withColumn("rank", F.col("n_ahead") + F.col("at")).withColumn("words_before", F.col("words_ahead") + F.col("inside"))
    blocks = blocks.drop("order", "slice", "at", "inside", "n_ahead", "words_ahead")
    blocks = written(blocks, "blocks")
    used = blocks.groupBy("sid").agg((F.max("passes") * F.count("*") + F.sum((F.col("words_before") < F.col("rest")).cast("long"))).alias("q"), F.count("*").alias("n")).collect()
    quota = {r["sid"]: (r["q"], r["n"]) for r in used}
    tree = splitting_tree([quota.get(k, (0, 0))[0] for k in range(len(per))], shards, seed)
    spans, at = [], [0] * len(per)
    for shard, counts in enumerate(tree):
        for k, n in enumerate(counts):
            if n:
                spans.append((k, shard, at[k], at[k] + n))
                at[k] += n
    leaves = small(spark.createDataFrame(spans, "sid int, shard int, low long, high long"))

    # every drawn block of every pass finds its leaf
    turns = blocks.withColumn("turn", F.explode(F.sequence(F.lit(0), F.col("passes"))))
    turns = turns.where((F.col("turn") < F.col("passes")) | (F.col("words_before") < F.col("rest")))
    counts = small(spark.createDataFrame([(k, n) for k, (_, n) in quota.items()], "sid int, n_blocks long"))
    turns = turns.join(counts, "sid").withColumn("place", F.col("turn") * F.col("n_blocks") + F.col("rank"))
    turns = turns.join(leaves, "sid").where((F.col("place") >= F.col("low")) & (F.col("place") < F.col("high")))
    homes = turns.groupBy("sid", "block").agg(F.max("words_before").alias("words_before"), F.collect_list(F.struct("turn", "shard")).alias("homes"))

    within = Window.partitionBy("sid", "block").orderBy(F.xxhash64("key", F.lit(seed + 3)), "key", F.col("doc_id").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    drawn = rows.withColumn("ahead", F.coalesce(F.sum("size").over(within), F.lit(0))).join(homes, ["sid", "block"], "left")
    drawn = drawn.withColumn("part", F.greatest(F.lit(0), F.least(F.col("size"), F.col("rest") - F.col("words_before") - F.col("ahead"))))
    words = lambda h: F.when(h.turn < F.col("passes"), F.col("size")).otherwise(F.col("part"))
    draws = F.transform("homes", lambda h: F.struct(h.shard.alias("shard"), h.turn.alias("pass"), F.col("block").alias("block"), F.xxhash64("key", h.turn, F.lit(seed + 4)).alias("position"), words(h).alias("words")))
    draws = F.coalesce(F.filter(draws, lambda d: d["words"] > 0), F.expr("cast(array() as array<struct<shard:int,pass:int,block:int,position:bigint,words:bigint>>)"))
    taken = F.aggregate("draws", F.lit(0).cast("long"), lambda a, d: a + d["words"])
    return drawn.withColumn("draws", draws).select("doc_id", "source", "size", "source_size", "target", taken.alias("taken"), "draws")


def shard_rows(mix: DataFrame) -> DataFrame:
    """The mix itself: one row per draw, dealt to its shard and shuffled inside it."""
    rows = mix.select("doc_id", "source", F.explode("draws").alias("d")).select("doc_id", "source", "d.shard", "d.pass", "d.position", "d.words")
    return rows.repartition("shard").sortWithinPartitions("shard", "position")
