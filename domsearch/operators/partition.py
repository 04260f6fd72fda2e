"""Partitioners of the size axis.  All work on the histogram of sizes, never on the domains."""

from __future__ import annotations


from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F



MAX_HISTOGRAM = 1_000_000  # rows that the driver takes; beyond it sizes are binned geometrically first


def bounds_of(assigned: DataFrame) -> DataFrame:
    """(part_id, size_lo, size_hi_excl, size_max, n_domains) of a histogram with part_id; empty partitions are left out."""
    meta = assigned.groupBy("part_id").agg(F.min("size").alias("size_lo"), F.max("size").alias("size_max"), F.sum("n_domains").alias("n_domains"))
    after = F.lead("size_lo").over(Window.orderBy("part_id"))
    return meta.withColumn("size_hi_excl", F.coalesce(after, F.col("size_max") + 1)).select("part_id", "size_lo", "size_hi_excl", "size_max", "n_domains")


def equi_depth(hist: DataFrame, n: int) -> DataFrame:
    """Equal numbers of domains, as far as equal sizes stay together."""
    total = F.sum("n_domains").over(Window.partitionBy())
    part = F.least(F.lit(n - 1), F.floor(F.lit(n) * F.col("cum_before") / total)).cast("int")
    return bounds_of(hist.withColumn("part_id", part))


def equi_width(hist: DataFrame, n: int) -> DataFrame:
    return blended(hist, n, 1.0)


def blended(hist: DataFrame, n: int, lam: float) -> DataFrame:
    """Lower edges that move from those of equi-depth (0) to those of equi-width (1)."""
    depth = equi_depth(hist, n).select("part_id", F.col("size_lo").alias("depth_lo"))
    span = hist.agg(F.min("size").alias("a"), F.max("size").alias("b"))
    edge = F.lit(1 - lam) * F.col("depth_lo").cast("double") + F.lit(lam) * (F.col("a") + F.col("part_id") * (F.col("b") - F.col("a") + 1) / F.lit(float(n)))
    slots = hist.sparkSession.range(n).select(F.col("id").cast("int").alias("part_id"))
    if lam < 1:
        slots = slots.join(depth, "part_id")
    else:
        slots = slots.withColumn("depth_lo", F.lit(0))
    edges = slots.crossJoin(F.broadcast(span)).select("part_id", F.when(F.col("part_id") == 0, F.col("a").cast("double")).otherwise(edge).alias("edge"))
    # n edges against the histogram: a range join with a broadcast side of n rows
    placed = hist.join(F.broadcast(edges), F.col("edge") <= F.col("size")).groupBy("size", "n_domains", "cum_before").agg(F.max("part_id").alias("part_id"))
    return bounds_of(placed)


def collect_histogram(hist: DataFrame) -> list[tuple[int, int]]:
    """The histogram on the driver; a very long one is first binned to relative steps of one part in 10,000 (upper sizes kept)."""
    if hist.count() > MAX_HISTOGRAM:
        step = F.floor(F.log(F.col("size").cast("double")) * 10_000)
        hist = hist.groupBy(step.alias("k")).agg(F.max("size").alias("size"), F.sum("n_domains").alias("n_domains"))
    return [(r["size"], r["n_domains"]) for r in hist.select("size", "n_domains").orderBy("size").collect()]


def _fill(hist: list[tuple[int, int]], cap: float, measure) -> list[int] | None:
    """First indices of the intervals that a greedy fill makes under the cap; None if one size alone exceeds it."""
    starts, k = [], 0
    while k < len(hist):
        starts.append(k)
        count = total = 0
        low = hist[k][0]
        first = k
        while k < len(hist):
            c, t = count + hist[k][1], total + hist[k][0] * hist[k][1]
            if measure(low, hist[k][0] + 1, c, t) > cap:
                break
            count, total, k = c, t, k + 1
        if k == first:
            return None
    return starts


def _least_maximum(hist: list[tuple[int, int]], n: int, measure) -> list[int]:
    """Bisection on the cap: the measure grows with the interval, so a greedy fill needs the fewest intervals."""
    low, high = 0.0, measure(hist[0][0], hist[-1][0] + 1, sum(c for _, c in hist), sum(s * c for s, c in hist))
    best = [0]
    for _ in range(100):
        mid = (low + high) / 2
        starts = _fill(hist, mid, measure)
        if starts is not None and len(starts) <= n:
            best, high = starts, mid
        else:
            low = mid
        if high - low <= 1e-9 * max(1.0, high):
            break
    return best


def fp_measure(q: int):
    return lambda low, u, count, total: (u * count - total) / (u + q)


def m_measure(low: int, u: int, count: int, total: int) -> float:
    return count * (u - low + 1) / (2 * u)


def _as_bounds(spark: SparkSession, hist: list[tuple[int, int]], starts: list[int]) -> DataFrame:
    rows = []
    for k, a in enumerate(starts):
        b = starts[k + 1] if k + 1 < len(starts) else len(hist)
        hi = hist[b][0] if b < len(hist) else hist[-1][0] + 1
        rows.append((k, hist[a][0], hi, hist[b - 1][0], sum(c for _, c in hist[a:b])))
    return spark.createDataFrame(rows, "part_id int, size_lo long, size_hi_excl long, size_max long, n_domains long")


def equi_fp(hist: DataFrame, n: int, q: int) -> DataFrame:
    """The partitioning whose worst expected number of false positives is least for queries of q values."""
    rows = collect_histogram(hist)
    return _as_bounds(hist.sparkSession, rows, _least_maximum(rows, n, fp_measure(q)) if rows else [])


def equi_m(hist: DataFrame, n: int) -> DataFrame:
    """The partitioning whose worst bound M is least, for all queries at once."""
    rows = collect_histogram(hist)
    return _as_bounds(hist.sparkSession, rows, _least_maximum(rows, n, m_measure) if rows else [])


def powerlaw_equidepth_bounds(alpha: float, low: int, n: int) -> list[float]:
    """Lower edges of equal mass under a power law from ``low`` on; the last partition is open above."""
    return [low * ((n - i) / n) ** (-1 / (alpha - 1)) for i in range(n)]



def assign(domains: DataFrame, meta: DataFrame) -> DataFrame:
    """part_id and size_max by a range join with the handful of intervals; sizes outside go to the edge partitions."""
    first, last = Window.orderBy("part_id"), Window.orderBy(F.desc("part_id"))
    wide = meta.withColumn("lo", F.when(F.row_number().over(first) == 1, F.lit(0)).otherwise(F.col("size_lo")))
    wide = wide.withColumn("hi", F.when(F.row_number().over(last) == 1, F.lit(2**62)).otherwise(F.col("size_hi_excl")))
    wide = wide.select("part_id", "lo", "hi", F.col("size_max").alias("part_size_max"))
    return domains.join(F.broadcast(wide), (F.col("size") >= F.col("lo")) & (F.col("size") < F.col("hi"))).drop("lo", "hi")


PARTITIONERS = {"equi_depth": equi_depth, "equi_width": equi_width, "equi_m": equi_m}



