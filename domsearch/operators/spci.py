"""The size-partitioned containment index: partitions, stored buckets, plan, search, refinement, shards, persistence.

What is stored are bucket rows (part_id, r, band, bucket, domain_id), written once and partitioned by size partition
and depth, sorted by bucket.  A search derives keys for its queries only, reads the partitions and depths that its
plan names, and never hashes the index again.  An index that was not stored derives its bucket rows in the plan.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import tuning
from ..functions.convert import conservative_threshold, containment_of
from ..functions.hashing import Native, Portable, Vector
from ..functions.minhash import estimate_jaccard, estimate_size, signatures
from ..store import fresh, materialise
from . import lsh, partition, stats

GRID = tuple(k / 20 for k in range(1, 21))  # thresholds for which buckets are stored unless others are named
META = "part_id int, size_lo long, size_hi_excl long, size_max long, n_domains long"
MANIFEST = "m int, native boolean, layout string, family string, seed int, depths string, id_type string"
FAMILIES = {f.__name__: f for f in (Portable, Native, Vector)}


@dataclass
class Index:
    signatures: DataFrame  # domain_id, size, sig, part_id, part_size_max
    meta: DataFrame  # part_id, size_lo, size_hi_excl, size_max, n_domains
    m: int
    native: bool = False
    layout: str | tuple[int, int] = "free"
    family: object = None
    buckets: DataFrame | None = None  # part_id, r, band, bucket, domain_id
    depths: dict[int, int] = field(default_factory=dict)  # bands stored for each depth r
    path: str | None = None

    def __post_init__(self):
        self.family = self.family or (Native(self.m) if self.native else Portable(self.m))


def build(signed: DataFrame, n: int = 32, m: int = 64, partitioner="equi_depth", native: bool = False, layout="free", family=None) -> Index:
    """Index of signatures (domain_id, size, sig).  n = 1 is plain MinHash LSH with one bound for all."""
    make = partition.PARTITIONERS[partitioner] if isinstance(partitioner, str) else partitioner
    meta = make(stats.histogram(signed.select("size")), n)
    return Index(partition.assign(signed, meta), meta, m, native, layout, family)


def build_from_entries(entries: DataFrame, n: int = 32, m: int = 256, min_size: int = 10, family=None, **options) -> Index:
    family = family or Portable(m)
    return build(signatures(entries, family).where(F.col("size") >= min_size), n, family.m, family=family, **options)


def sketched(entries: DataFrame, family=None) -> DataFrame:
    """(query_id, q, sig) of queries that come as values (query_id, value); they need not be indexed."""
    distinct = entries.where("value is not null and value <> ''").select(F.col("query_id").alias("domain_id"), "value").distinct()
    return signatures(distinct, family).select(F.col("domain_id").alias("query_id"), F.col("size").alias("q"), "sig")


def tuned_depths(index: Index, thresholds) -> dict[int, int]:
    """For every depth r that the tuner takes at these thresholds, the most bands b."""
    most: dict[int, int] = {}
    for _, _, _, b, r, _, _ in tuning.precompute(index.m, list(thresholds), layout=index.layout):
        most[r] = max(most.get(r, 0), b)
    return most


def bucket_rows(signed: DataFrame, depths: dict[int, int], native: bool, stride: int | None = None) -> DataFrame:
    """(part_id, r, band, bucket, domain_id) of signatures with part_id, in one scan."""
    shapes = F.explode(F.array(*(F.struct(F.lit(r).alias("r"), F.lit(b).alias("most")) for r, b in sorted(depths.items()))))
    rows = signed.select("domain_id", "part_id", "sig", shapes.alias("s"))
    keys = lsh.band_keys(F.col("sig"), F.col("s.most"), F.col("s.r"), native, stride)
    return rows.select("part_id", F.col("s.r").alias("r"), F.posexplode(keys).alias("band", "bucket"), "domain_id")


def make_plan(index: Index, queries: DataFrame, thresholds: list[float], prune: bool = True, fn_weight: float = 1.0) -> DataFrame:
    """(query_id, q, t_star, part_id, b, r): one row for each query, partition and threshold that can hold an answer.

    ``queries`` is a batch of stated queries; partitions and the tuning table are small and broadcast, so a batch of
    any size is planned without a shuffle.
    """
    spark = queries.sparkSession
    table = [(k, t, b, r) for k, _, t, b, r, _, _ in tuning.precompute(index.m, thresholds, layout=index.layout, fn_weight=fn_weight)]
    table = spark.createDataFrame(table, "ratio_bin int, t_star double, b int, r int")
    rows = queries.crossJoin(F.broadcast(index.meta.select("part_id", "size_max")))
    rows = rows.withColumn("ratio_bin", tuning.ratio_bin(F.col("size_max"), F.col("q"))).join(F.broadcast(table), "ratio_bin")
    if prune:
        rows = rows.where(F.col("size_max") / F.col("q") >= F.col("t_star"))  # divided as the exact score is, so that both round alike
    return rows.select("query_id", "q", "t_star", "part_id", "size_max", "b", "r")


def with_signatures(index: Index, queries: DataFrame) -> DataFrame:
    """(query_id, q, sig): signatures that the queries bring, else those of the indexed domains of the same id.

    An id that has neither raises an error that names it.  Where q is null it is estimated from the signature.
    """
    own = queries
    if "sig" not in queries.columns:
        asked = queries.select("query_id", "q") if "q" in queries.columns else queries.select("query_id", F.lit(None).cast("bigint").alias("q"))
        held = index.signatures.select(F.col("domain_id").alias("query_id"), "sig")
        if asked.count() <= lsh.SMALL_QUERIES:  # no signature is sent but theirs
            held = held.join(F.broadcast(asked.select("query_id")), "query_id", "left_semi")
        own = materialise(asked.join(held, "query_id", "left"), "asked")
        lost = [r["query_id"] for r in own.where("sig is null").select("query_id").limit(5).collect()]
        if lost:
            raise ValueError(f"neither indexed nor brought with a signature: {', '.join(map(str, lost))}")
    q = F.col("q") if "q" in own.columns else F.lit(None).cast("bigint")
    estimate = F.greatest(F.lit(1), F.round(estimate_size(F.col("sig"), index.family))).cast("bigint")
    return own.select("query_id", F.coalesce(q, estimate).alias("q"), "sig")


def search(index: Index, queries: DataFrame, thresholds: list[float], prune: bool = True, refine: str = "none", entries: DataFrame | None = None, fn_weight: float = 1.0) -> DataFrame:
    """Candidates (query_id, t_star, domain_id); refined by the sketch or by the values if asked for.

    Values are those of ``entries``; without them the index is of whole sets (``store.dealt_sets``), and candidates are
    compared in the tasks that hold them.

    ``queries`` holds query_id and, where known, the size q; with a column ``sig`` (see ``sketched``) they may be any
    sets, without it they are indexed domains.
    """
    asked = with_signatures(index, queries)
    plan = make_plan(index, asked.select("query_id", "q"), thresholds, prune, fn_weight)
    signs = asked.select("query_id", "sig")
    if refine == "exact" and entries is None:
        if index.buckets is not None or "steps" not in index.signatures.columns:
            raise ValueError("the index holds no values: entries are needed")
        held = index.signatures.select(F.col("domain_id").alias("query_id"), "steps")
        signs = signs.join(held.join(F.broadcast(asked.select("query_id")), "query_id", "left_semi") if asked.count() <= lsh.SMALL_QUERIES else held, "query_id")
        return probe(index, plan, signs).select("query_id", "t_star", "domain_id")
    found = probe(index, plan, signs).select("query_id", "t_star", "domain_id")
    if refine == "none":
        return found
    if refine == "exact":
        return refine_exact(found, entries, asked.select("query_id", "q"))
    pairs = found.join(asked.select("query_id", "q", F.col("sig").alias("q_sig")), "query_id").join(index.signatures.select("domain_id", "size", "sig"), "domain_id")
    estimate = containment_of(estimate_jaccard(F.col("q_sig"), F.col("sig")), F.col("size"), F.col("q"))
    return pairs.where(estimate >= F.col("t_star")).select("query_id", "t_star", "domain_id")


def probe(index: Index, plan: DataFrame, signs: DataFrame | None = None) -> DataFrame:
    """Candidates (query_id, t_star, part_id, domain_id) of a plan and the queries' signatures: from the stored buckets where they hold its depths, else from the signatures."""
    if signs is None:  # they stand in the plan's rows
        signs, plan = plan.select("query_id", "sig").dropDuplicates(["query_id"]), plan.drop("sig")
    plan = materialise(plan, "plan")
    if index.buckets is None:
        return lsh.probe(index.signatures, plan, signs, index.native, lsh.stride_of(index.layout))
    shapes = plan.groupBy("part_id", "r").agg(F.max("b").alias("b")).collect()  # partitions x depths: a few hundred rows
    if any(index.depths.get(s["r"], 0) < s["b"] for s in shapes):
        return lsh.probe(index.signatures, plan, signs, index.native, lsh.stride_of(index.layout))
    return lsh.probe_buckets(index.buckets, plan, signs, sorted({(s["part_id"], s["r"]) for s in shapes}), index.native, lsh.stride_of(index.layout))


def refine_exact(found: DataFrame, entries: DataFrame, queries: DataFrame, query_entries: DataFrame | None = None) -> DataFrame:
    """Candidates whose exact containment reaches the threshold; only entries of candidates are joined.

    ``query_entries`` (query_id, value) holds the queries' values where they are not indexed domains.
    """
    pairs = found.select("query_id", "domain_id").distinct()
    if query_entries is None:
        asked = entries.join(queries, entries.domain_id == queries.query_id).select("query_id", "q", "value")
    else:
        asked = query_entries.join(queries, "query_id").select("query_id", "q", "value")
    counts = pairs.join(entries, "domain_id").join(asked, ["query_id", "value"]).groupBy("query_id", "q", "domain_id").agg(F.count("*").alias("overlap"))
    return found.join(counts, ["query_id", "domain_id"]).where(F.col("overlap") / F.col("q") >= F.col("t_star")).select("query_id", "t_star", "domain_id")


def thresholds_of(index: Index, queries: DataFrame, t: float) -> DataFrame:
    rows = queries.crossJoin(F.broadcast(index.meta.select("part_id", "size_max")))
    return rows.withColumn("s_star", conservative_threshold(F.lit(t), F.col("size_max"), F.col("q")))


def shard_of(domain_id: str, shards: int):
    """A portable hash of the id, the same in every engine."""
    return (F.conv(F.substring(F.md5(domain_id), 1, 15), 16, 10).cast("bigint") % shards).cast("int")


def build_shards(signed: DataFrame, shards: int = 5, n: int = 32, m: int = 64, **options) -> list[Index]:
    """One index for each hash shard, with partitions of its own: what each machine would build from its share."""
    spread = signed.withColumn("shard_id", shard_of("domain_id", shards))
    return [build(spread.where(F.col("shard_id") == k).drop("shard_id"), n, m, **options) for k in range(shards)]


def search_shards(shards: list[Index], queries: DataFrame, thresholds: list[float], **options) -> DataFrame:
    """All shards asked the same queries (with signatures, see ``sketched``), in one plan: (query_id, t_star, domain_id, shard_id)."""
    return reduce(DataFrame.unionByName, [search(s, queries, thresholds, **options).withColumn("shard_id", F.lit(k)) for k, s in enumerate(shards)])


def _write(index: Index, path: str, signed: DataFrame, mode: str) -> None:
    """Signatures and buckets of some domains into the partitions' folders."""
    signed.drop("part_size_max").repartition("part_id", F.pmod(F.xxhash64("domain_id"), F.lit(8))).sortWithinPartitions("part_id", "size").write.mode(mode).partitionBy("part_id").parquet(f"{path}/signatures")
    if index.depths:
        rows = bucket_rows(signed, index.depths, index.native, lsh.stride_of(index.layout)).repartition("part_id", "r", F.pmod(F.xxhash64("bucket"), F.lit(4)))
        rows.sortWithinPartitions("part_id", "r", "bucket").write.mode(mode).partitionBy("part_id", "r").parquet(f"{path}/buckets")


def _describe(index: Index, path: str) -> None:
    meta = [tuple(r) for r in index.meta.select("part_id", "size_lo", "size_hi_excl", "size_max", "n_domains").collect()]  # one row for each partition
    spark = index.meta.sparkSession
    spark.createDataFrame(meta, META).coalesce(1).write.mode("overwrite").parquet(f"{path}/meta")
    depths = ",".join(f"{r}:{b}" for r, b in sorted(index.depths.items()))
    id_type = index.signatures.schema["domain_id"].dataType.simpleString()
    manifest = [(index.m, index.native, str(index.layout), type(index.family).__name__, index.family.seed, depths, id_type)]
    spark.createDataFrame(manifest, MANIFEST).coalesce(1).write.mode("overwrite").json(f"{path}/manifest")


def save(index: Index, path: str, thresholds: tuple[float, ...] | None = GRID) -> None:
    """Signatures by partition, buckets by partition and depth, for the depths of these thresholds (None: signatures only)."""
    stored = replace(index, depths=tuned_depths(index, thresholds) if thresholds else {})
    _write(stored, path, index.signatures, "overwrite")
    _describe(stored, path)


def load(spark: SparkSession, path: str) -> Index:
    kept = spark.read.schema(MANIFEST).json(f"{path}/manifest").first()
    layout = kept["layout"] if kept["layout"] == "free" else tuple(int(x) for x in kept["layout"].strip("()").split(","))
    depths = {int(r): int(b) for r, _, b in (x.partition(":") for x in (kept["depths"] or "").split(",") if x)}
    meta = spark.read.schema(META).parquet(f"{path}/meta")
    signed = spark.read.schema(f"domain_id {kept['id_type']}, size long, sig array<long>, part_id int").parquet(f"{path}/signatures").join(F.broadcast(meta.select("part_id", F.col("size_max").alias("part_size_max"))), "part_id")
    bucket = "long" if kept["native"] else "string"
    buckets = spark.read.schema(f"band int, bucket {bucket}, domain_id {kept['id_type']}, part_id int, r int").parquet(f"{path}/buckets") if depths else None
    return Index(signed, meta, kept["m"], kept["native"], layout, FAMILIES[kept["family"]](kept["m"], kept["seed"]), buckets, depths, path)


def stored(index: Index, thresholds: tuple[float, ...] | list[float] = GRID, path: str | None = None) -> Index:
    """The index, saved and loaded: searches read its buckets."""
    spark = index.meta.sparkSession
    path = path or fresh(spark, "index")
    save(index, path, tuple(thresholds))
    return load(spark, path)


def _grown(meta: DataFrame, fresh_rows: DataFrame) -> DataFrame:
    more = fresh_rows.groupBy("part_id").agg(F.max("size").alias("new_max"), F.min("size").alias("new_min"), F.count("*").alias("more"))
    return meta.join(more, "part_id", "left").select(
        "part_id", F.least("size_lo", "new_min").alias("size_lo"), F.greatest("size_hi_excl", F.col("new_max") + 1).alias("size_hi_excl"),
        F.greatest("size_max", "new_max").alias("size_max"), (F.col("n_domains") + F.coalesce("more", F.lit(0))).alias("n_domains"),
    )


def insert(index: Index, signed: DataFrame) -> Index:
    """New domains enter existing partitions; outside sizes go to the edge partitions, whose largest size grows.

    A stored index is appended to: only the new domains' rows are written, and the meta data anew.
    """
    new = partition.assign(signed, index.meta)
    meta = _grown(index.meta, new)
    if index.path is not None:
        new = materialise(new, "new")
        meta = _grown(index.meta, new)
        grown = replace(index, meta=materialise(meta, "meta"))
        _write(grown, index.path, new, "append")
        _describe(grown, index.path)
        return load(meta.sparkSession, index.path)
    both = index.signatures.drop("part_size_max").unionByName(new.drop("part_size_max"))
    both = both.join(F.broadcast(meta.select("part_id", F.col("size_max").alias("part_size_max"))), "part_id")
    return Index(both, meta, index.m, index.native, index.layout, index.family)


def drift(index: Index) -> tuple[int, float, float]:
    """Number of partitions, mean and deviation of their numbers of domains."""
    n, mean, dev = index.meta.agg(F.count("*"), F.avg("n_domains"), F.stddev_pop("n_domains")).first()
    return n, mean or 0.0, dev or 0.0


def needs_rebuild(index: Index, times: float = 2.7) -> bool:
    """Whether partition sizes have drifted: their deviation exceeds ``times`` the equi-depth size."""
    n, mean, dev = drift(index)
    return bool(n and dev > times * mean)


def rebuild(index: Index, n: int = 32, partitioner="equi_depth", path: str | None = None) -> Index:
    """The same domains under partitions made anew from their present sizes; stored if the index was."""
    signed = index.signatures.select("domain_id", "size", "sig")
    anew = build(signed, n, index.m, partitioner, index.native, index.layout, index.family)
    if index.path is None and path is None:
        return anew
    path = path or fresh(index.meta.sparkSession, "index")
    _write(replace(anew, depths=index.depths), path, anew.signatures, "overwrite")
    _describe(replace(anew, depths=index.depths), path)
    return load(index.meta.sparkSession, path)


def footprint(index: Index) -> DataFrame:
    """(part, files, bytes) on disk of a stored index."""
    spark, out = index.meta.sparkSession, []
    jvm = spark.sparkContext._jvm
    for part in ("signatures", "buckets", "meta"):
        p = jvm.org.apache.hadoop.fs.Path(f"{index.path}/{part}")
        files = p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        if files.exists(p):
            held = files.getContentSummary(p)
            out.append((part, held.getFileCount(), held.getLength()))
    return spark.createDataFrame(out, "part string, files long, bytes long")


def register_search(index: Index, thresholds: list[float], name: str = "search_domains") -> None:
    """SQL table function ``name(asked, t)`` over a stored index with portable keys: domains that are candidates for an indexed one.

    The tuning table, the partitions and the buckets are views that the function joins.
    """
    spark = index.meta.sparkSession
    edges = [*tuning.RATIO_EDGES, float("inf")]
    rows = [(float(edges[k]), float(edges[k + 1]), float(t), b, r) for k, _, t, b, r, _, _ in tuning.precompute(index.m, thresholds, layout=index.layout)]
    spark.createDataFrame(rows, "low double, high double, t_star double, b int, r int").createOrReplaceTempView(f"{name}_tuning")
    for part in ("signatures", "meta", "buckets"):
        getattr(index, part).createOrReplaceTempView(f"{name}_{part}")
    stride = lsh.stride_of(index.layout) or "k.r"
    spark.sql(f"drop temporary function if exists {name}")
    spark.sql(f"""
        create temporary function {name}(asked string, t double) returns table (domain_id string)
        return select distinct held.domain_id
        from (
            select p.part_id, p.r, p.band, array_join(transform(slice(p.sig, p.band * p.stride + 1, p.r), v -> cast(v as string)), '-') as bucket
            from (
                select k.part_id, k.r, k.sig, {stride} as stride, explode(sequence(0, k.b - 1)) as band
                from (
                    select m.part_id, n.r, n.b, s.sig
                    from {name}_signatures s cross join {name}_meta m
                    join {name}_tuning n on m.size_max / s.size >= n.low and m.size_max / s.size < n.high
                    where s.domain_id = {name}.asked and n.t_star = {name}.t and m.size_max / s.size >= {name}.t
                ) k
            ) p
        ) own
        join {name}_buckets held on held.part_id = own.part_id and held.r = own.r and held.band = own.band and held.bucket = own.bucket
    """)
