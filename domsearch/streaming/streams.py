"""Streams: event-time domains, late data, continuous search, incremental signatures.

Every function returns a streaming DataFrame; ``drain`` runs one to its end and
hands back what it wrote.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.minhash import signatures
from ..operators import spci
from ..store import fresh, materialise


def read_stream(spark: SparkSession, sf_dir: str, name: str, files_per_trigger: int = 1, parts: int = 4, order: str | None = None, arrival: tuple[int, ...] | None = None) -> DataFrame:
    """A table replayed as a stream of files; with ``order``, files arrive in the order of that time column.

    ``arrival`` names the files in another order, which makes some of their rows late.
    """
    source = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    path = fresh(spark, f"replay-{name}")
    if order:
        at = F.col(order).cast("timestamp").cast("double")
        cuts = source.select(at.alias("at")).approxQuantile("at", [k / parts for k in range(1, parts)], 0.01)
        spans = list(zip([float("-inf"), *cuts], [*cuts, float("inf")], strict=True))
        for low, high in [spans[k] for k in arrival] if arrival else spans:
            source.where((at > F.lit(low)) & (at <= F.lit(high))).coalesce(1).write.mode("append").parquet(path)
    else:
        source.repartition(parts).write.parquet(path)
    return spark.readStream.schema(source.schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def events_stream(spark: SparkSession, sf_dir: str, arrival: tuple[int, ...] | None = None) -> DataFrame:
    """Events in order of time; timestamps without zone become UTC instants, which watermarks need."""
    return read_stream(spark, sf_dir, "events", order="ts", arrival=arrival).withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append", trigger: str = "availableNow") -> DataFrame:
    """Run to the end of the data and return the sink's rows as a table; ``trigger`` is availableNow or an interval.

    Rows that are appended go to files; only the other modes, which send groups, keep them on the driver.
    """
    spark = stream.sparkSession
    name, path = f"sink_{uuid.uuid4().hex}", fresh(spark, "sink")
    writer = stream.writeStream.format("parquet").option("path", path) if mode == "append" else stream.writeStream.format("memory")
    writer = writer.queryName(name).outputMode(mode).option("checkpointLocation", fresh(spark, "stream"))
    if trigger == "availableNow":
        query = writer.trigger(availableNow=True).start()
        query.awaitTermination()
    else:
        query = writer.trigger(processingTime=trigger).start()
        query.processAllAvailable()
        query.stop()
    return spark.read.schema(stream.schema).parquet(path) if mode == "append" else spark.table(name)


def drain_batches(stream: DataFrame, function) -> None:
    query = stream.writeStream.foreachBatch(function).option("checkpointLocation", fresh(stream.sparkSession, "stream")).trigger(availableNow=True).start()
    query.awaitTermination()


def tumbling(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events of each kind in each hour; rows of a window that ended before the watermark are dropped."""
    counts = events.withWatermark("ts", late).groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return counts.select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n")


def sliding(events: DataFrame) -> DataFrame:
    counts = events.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count("*").alias("n"))
    return counts.select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    counts = events.withWatermark("ts", "1 hour").groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"))
    return counts.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "30 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")


def click_after_error(events: DataFrame, other: DataFrame, minutes: int = 10) -> DataFrame:
    """Clicks of a user within some minutes after one of their errors."""
    errors = events.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("u"), F.col("ts").alias("error_ts")).withWatermark("error_ts", "1 hour")
    clicks = other.where("event_type = 'click'").select("event_id", "user_id", "ts").withWatermark("ts", "1 hour")
    near = F.expr(f"user_id = u and ts >= error_ts and ts <= error_ts + interval {minutes} minutes")
    return clicks.join(errors, near).select("event_id", "error_id")


def incremental_signatures(stream: DataFrame, family) -> DataFrame:
    """Signatures of domains that grow: each batch's signatures are merged with those kept so far, minimum by minimum.

    Entries must not repeat over batches for sizes to be right; signatures are right anyway.
    """
    spark = stream.sparkSession
    state: dict[str, DataFrame] = {}

    def merge(batch: DataFrame, _: int) -> None:
        new = signatures(batch.select("domain_id", "value").distinct(), family)
        if "kept" in state:
            both = state["kept"].unionByName(new)
            rows = both.select("domain_id", "size", F.posexplode("sig").alias("i", "v")).groupBy("domain_id", "i").agg(F.min("v").alias("v"), F.sum("size").alias("size"))
            new = rows.groupBy("domain_id").agg(F.max("size").alias("size"), F.transform(F.sort_array(F.collect_list(F.struct("i", "v"))), lambda x: x["v"]).alias("sig"))
        state["kept"] = materialise(new, "state")

    drain_batches(stream, merge)
    return state.get("kept", spark.createDataFrame([], "domain_id string, size long, sig array<bigint>"))


def index_arrivals(stream: DataFrame, index: spci.Index, family, min_size: int = 10, times: float = 2.7, n: int | None = None) -> tuple[spci.Index, DataFrame]:
    """Domains that arrive as entries (domain_id, value) enter a stored index, batch by batch; drift is watched.

    A domain is to arrive in one batch.  Returns the index and (batch, n_partitions, mean, stddev, rebuilt).  With
    ``n``, partitions whose deviation exceeds ``times`` their mean are made anew.
    """
    spark = stream.sparkSession
    state, log = {"index": index}, []

    def insert(batch: DataFrame, number: int) -> None:
        new = signatures(batch.select("domain_id", "value").distinct(), family).where(f"size >= {min_size}")
        state["index"] = spci.insert(state["index"], materialise(new, "arrived"))
        parts, mean, dev = spci.drift(state["index"])
        again = n is not None and spci.needs_rebuild(state["index"], times)
        if again:
            state["index"] = spci.rebuild(state["index"], n)
        log.append((number, parts, float(mean), float(dev), again))

    drain_batches(stream, insert)
    return state["index"], spark.createDataFrame(log, "batch long, n_partitions int, mean double, stddev double, rebuilt boolean")


def search_arrivals(stream: DataFrame, index: spci.Index, family, thresholds: list[float], min_size: int = 10) -> DataFrame:
    """Sets that arrive as entries (query_id, value) are asked of a stored index: (query_id, t_star, domain_id)."""
    spark = stream.sparkSession
    path = fresh(spark, "answers")

    def ask(batch: DataFrame, _: int) -> None:
        asked = materialise(spci.sketched(batch, family).where(f"q >= {min_size}"), "asked")
        spci.search(index, asked, thresholds).write.mode("append").parquet(path)

    drain_batches(stream, ask)
    return spark.read.schema("query_id string, t_star double, domain_id string").parquet(path)
