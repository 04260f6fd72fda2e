"""Stream queries, run to the end of their data and held against the same question in batch."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.hashing import Portable
from ..functions.minhash import signatures
from ..operators import extract, spci
from ..plans import sqltext as q
from ..plans.registry import query
from ..sources.tables import table
from ..store import materialise
from . import streams


@query("stream_tumbling", "select strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') as start, event_type, count(*) n from events group by 1, 2")
def stream_tumbling(spark, sf_dir):
    return streams.drain(streams.tumbling(streams.events_stream(spark, sf_dir)), "complete")


@query("stream_sliding", "select strftime(w, '%Y-%m-%d %H:%M') as start, count(*) n from (select unnest([time_bucket(interval 30 minutes, ts), time_bucket(interval 30 minutes, ts) - interval 30 minutes]) w from events) group by 1")
def stream_sliding(spark, sf_dir):
    return streams.drain(streams.sliding(streams.events_stream(spark, sf_dir)), "complete")


@query("stream_session", "with m as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minutes then 0 else 1 end new from events), s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) k from m) select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as start, count(*) n from s group by user_id, k")
def stream_session(spark, sf_dir):
    return streams.drain(streams.sessions(streams.events_stream(spark, sf_dir)), "complete")


@query("stream_dedup", "select event_id, user_id from events")
def stream_dedup(spark, sf_dir):
    events = streams.events_stream(spark, sf_dir)
    return streams.drain(streams.deduplicated(events.unionByName(streams.events_stream(spark, sf_dir))))


@query("stream_stream_join", "select c.event_id, e.event_id error_id from events c join events e on c.user_id = e.user_id and c.event_type = 'click' and e.event_type = 'error' and c.ts >= e.ts and c.ts <= e.ts + interval 10 minutes")
def stream_stream_join(spark, sf_dir):
    return streams.drain(streams.click_after_error(streams.events_stream(spark, sf_dir), streams.events_stream(spark, sf_dir)))


_ITEMS = r"b as (select distinct item_id, unnest(string_split_regex(lower(text), '\s+')) as value from benchmark), n as (select item_id, count(*) q from b group by 1)"


@query("stream_search", r"with d as (select distinct doc_id, unnest(string_split_regex(lower(text), '\s+')) as value from documents), " + _ITEMS + " select item_id, doc_id, overlap from (select item_id, doc_id, count(*) overlap from b join d using (value) group by 1, 2) join n using (item_id) where overlap / q >= 0.9")
def stream_search(spark, sf_dir):
    """Arriving documents against a standing set of queries, batch by batch."""
    items = table(spark, sf_dir, "benchmark").select("item_id", F.explode(F.array_distinct(F.split(F.lower("text"), r"\s+"))).alias("value"))
    sizes = items.groupBy("item_id").agg(F.count("*").alias("q"))
    path = streams.fresh(spark, "found")

    def probe(batch, _):
        words = batch.select("doc_id", F.explode(F.array_distinct(F.split(F.lower("text"), r"\s+"))).alias("value"))
        counts = words.join(F.broadcast(items), "value").groupBy("item_id", "doc_id").agg(F.count("*").alias("overlap"))
        counts.join(F.broadcast(sizes), "item_id").where("overlap / q >= 0.9").select("item_id", "doc_id", "overlap").write.mode("append").parquet(path)

    streams.drain_batches(streams.read_stream(spark, sf_dir, "documents"), probe)
    return spark.read.schema("item_id long, doc_id long, overlap long").parquet(path)


@query("stream_minhash", q.sql(["ent as (select distinct 'user:' || user_id domain_id, props as value from events)", *[x.replace("sig as materialized", "sig as") for x in q.sketches("slices", 8)[3:]]], "select domain_id, string_agg(cast(v as varchar), ',' order by i) sig from sig group by 1"))
def stream_minhash(spark, sf_dir):
    entries = streams.read_stream(spark, sf_dir, "events").select(F.concat(F.lit("user:"), F.col("user_id").cast("string")).alias("domain_id"), F.col("props").alias("value"))
    signed = streams.incremental_signatures(entries, Portable(8))
    return signed.select("domain_id", F.array_join(F.transform("sig", lambda v: v.cast("string")), ",").alias("sig"))


@query("stream_late_data")
def stream_late_data(spark, sf_dir, arrival: tuple[int, ...] = (2, 3, 0, 1), late: str = "1 hour"):
    """Files out of order: rows of windows that ended before the watermark of the batch before last are late and dropped."""
    sink = streams.drain(streams.tumbling(streams.events_stream(spark, sf_dir, arrival), late), "update")
    return sink.groupBy("start", "event_type").agg(F.max("n").alias("n"))


_CLOSED = "date_trunc('hour', ts) + interval 1 hour <= (select max(ts) from events) - interval 1 hour"


@query("stream_output_modes", f"select 'append' as output_mode, 'availableNow' as run_by, count(*) n from events where {_CLOSED} union all select unnest(['update', 'complete', 'complete']), unnest(['availableNow', 'availableNow', '0 seconds']), (select count(*) from events)")
def stream_output_modes(spark, sf_dir):
    """Events counted by each output mode and trigger: append emits the windows that the watermark has closed."""
    out = None
    for mode, trigger in (("append", "availableNow"), ("update", "availableNow"), ("complete", "availableNow"), ("complete", "0 seconds")):
        sink = streams.drain(streams.tumbling(streams.events_stream(spark, sf_dir)), mode, trigger)
        last = sink.groupBy("start", "event_type").agg(F.max("n").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
        row = last.select(F.lit(mode).alias("output_mode"), F.lit(trigger).alias("run_by"), "n")
        out = row if out is None else out.unionByName(row)
    return out


def _document_tokens(docs):
    return extract.from_tokens(docs, F.concat(F.lit("doc:"), F.col("doc_id").cast("string")), F.col("text")).where("value <> ''")


_EARLY = "cast(substr(domain_id, 5) as bigint) % 10 < 6"
_DOCUMENTS = [*q.sketches("documents", 8)[:2], f"early as (select * from dom where {_EARLY})", *(x.replace("from dom ", "from early ") for x in q.histogram()), f"placed as ({q.equi_depth(8)})", f"meta as ({q.META.format('placed')})",
              f"late as (select d.size, m.part_id from dom d join (select part_id, case when part_id = (select min(part_id) from meta) then 0 else size_lo end lo, case when part_id = (select max(part_id) from meta) then 9e15 else size_hi_excl end hi from meta) m on d.size >= lo and d.size < hi where not ({_EARLY}))"]


@query("stream_index_insert", q.sql(_DOCUMENTS, "select part_id, greatest(size_max, coalesce((select max(size) from late where late.part_id = meta.part_id), 0)) size_max, n_domains + (select count(*) from late where late.part_id = meta.part_id) n_domains from meta"))
def stream_index_insert(spark, sf_dir):
    """Documents that arrive enter a stored index of earlier ones."""
    return arriving(spark, sf_dir)[0].meta.select("part_id", "size_max", "n_domains")


def arriving(spark, sf_dir, n: int | None = None, times: float = 2.7):
    family = Portable(8)
    early = F.col("doc_id") % 10 < 6
    signed = signatures(_document_tokens(table(spark, sf_dir, "documents").where(early)).distinct(), family).where("size >= 10")
    index = spci.stored(spci.build(materialise(signed, "early"), 8, 8), [0.5])
    return streams.index_arrivals(_document_tokens(streams.read_stream(spark, sf_dir, "documents").where(~early)), index, family, times=times, n=n)


_M = 32
_ITEM_SETS = [*q.sketches("documents and items", _M), "docs as (select * from dom where domain_id like 'doc:%')", *(x.replace("from dom ", "from docs ") for x in q.index(8)), "qs as (select domain_id query_id, size q from dom where domain_id like 'item:%')"]


@query("stream_index_search", q.sql([*_ITEM_SETS, *q.candidates(_M, [0.5])], "select query_id, t_star, domain_id from found"))
def stream_index_search(spark, sf_dir):
    """Items that arrive are asked of a stored index of all documents."""
    family = Portable(_M)
    signed = signatures(_document_tokens(table(spark, sf_dir, "documents")).distinct(), family).where("size >= 10")
    index = spci.stored(spci.build(materialise(signed, "documents"), 8, _M), [0.5])
    items = streams.read_stream(spark, sf_dir, "benchmark")
    items = extract.from_tokens(items, F.concat(F.lit("item:"), F.col("item_id").cast("string")), F.col("text")).withColumnRenamed("domain_id", "query_id")
    return streams.search_arrivals(items, index, family, [0.5])
