"""The operators, sources and functions around the methods, each on the given tables with its SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import minhash, tuning
from ..functions.hashing import Portable
from ..operators import extract, partition, search, stats
from ..sources import formats
from ..sources.tables import register, table
from . import sqltext as q
from .registry import query

r6 = lambda c, n: F.round(c, 6).alias(n)


def on(name: str, sql: str | None, *tables: str):
    """Register a query over named tables: the function gets them as DataFrames."""

    def add(function):
        query(name, sql)(lambda spark, sf_dir: function(*(table(spark, sf_dir, t) for t in tables)))
        return function

    return add


# --- scans, sources, sinks ------------------------------------------------------------------------------------------
on("scan_parquet", "select o_orderkey, o_totalprice from orders where o_totalprice > 150000 and o_orderstatus = 'F'", "orders")(lambda o: o.where("o_totalprice > 150000 and o_orderstatus = 'F'").select("o_orderkey", "o_totalprice"))
_NATION = "n_nationkey int, n_name string, n_regionkey int"
_NATION_SQL = "select n_nationkey, n_name, n_regionkey from nation"
for _fmt, _options in (("csv", {"header": "true"}), ("json", {}), ("orc", {}), ("xml", {"rowTag": "nation"})):
    on(f"scan_{_fmt}", _NATION_SQL, "nation")(lambda n, f=_fmt, o=_options: formats.roundtrip(n, f, _NATION, **o))
on("scan_text", "select count(*) n_lines, cast(sum(len(n_name)) as bigint) n_chars from nation", "nation")(lambda n: formats.roundtrip(n.select("n_name"), "text", "value string").agg(F.count("*").alias("n_lines"), F.sum(F.length("value")).alias("n_chars")))
on("scan_inferred", "select c_custkey, c_mktsegment, round(c_acctbal, 2) c_acctbal from customer", "customer")(lambda c: formats.roundtrip(c, "csv", None, header="true").select(F.col("c_custkey").cast("long").alias("c_custkey"), "c_mktsegment", F.round("c_acctbal", 2).alias("c_acctbal")))
on("pages_to_tokens", r"select page_id, count(distinct w) n_tokens from (select page_id, unnest(string_split_regex(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '\s+')) w from pages) where w <> '' group by 1", "pages")(lambda p: p.select("page_id", F.explode(F.split(F.lower(F.regexp_replace("html", "<[^>]*>", " ")), r"\s+")).alias("w")).where("w <> ''").groupBy("page_id").agg(F.countDistinct("w").alias("n_tokens")))
query("source_nested_domains", "select 'nested:' || k domain_id, (k + 1) * 10 n from range(4) t(k)")(lambda spark, sf_dir: formats.nested_domains(spark).groupBy("domain_id").agg(F.count("*").alias("n")))


_FILES = ["region", "nation", "supplier", "customer", "part"]


@query("source_domains", q.sql([f"ent as ({q.columns_of(_FILES)})"], "select domain_id, count(*) n_values, min(value) least, max(value) greatest from ent group by 1"))
def source_domains(spark, sf_dir):
    """Entries read file by file by a data source of our own."""
    entries = formats.domain_files(spark, sf_dir, tuple(f"{n}.parquet" for n in _FILES)).distinct()
    return entries.groupBy("domain_id").agg(F.count("*").alias("n_values"), F.min("value").alias("least"), F.max("value").alias("greatest"))


@on("sink_roundtrip", "select n_regionkey, count(*) n from nation group by 1", "nation")
def sink_roundtrip(n):
    path = formats.fresh(n.sparkSession, "sink")
    n.write.partitionBy("n_regionkey").parquet(path)
    return n.sparkSession.read.parquet(path).groupBy("n_regionkey").agg(F.count("*").alias("n"))


@on("sink_bucketed", "select o_custkey, count(*) n, round(sum(o_totalprice), 2) total from orders join customer on o_custkey = c_custkey group by 1", "orders", "customer")
def sink_bucketed(o, c):
    a, b = formats.bucketed(o, "orders_by_customer", 4, "o_custkey"), formats.bucketed(c, "customers_by_key", 4, "c_custkey")
    return a.join(b, a.o_custkey == b.c_custkey).groupBy("o_custkey").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


# --- projection, filter ---------------------------------------------------------------------------------------------
on("project_exprs", "select l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 6) revenue, case when l_quantity >= 25 then 'bulk' else 'single' end size_class, coalesce(nullif(l_returnflag, 'N'), '-') flag, try_cast(l_linestatus as integer) as_int from lineitem", "lineitem")(
    lambda li: li.select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 6).alias("revenue"), F.when(F.col("l_quantity") >= 25, "bulk").otherwise("single").alias("size_class"), F.coalesce(F.nullif("l_returnflag", F.lit("N")), F.lit("-")).alias("flag"), F.col("l_linestatus").try_cast("int").alias("as_int"))
)
on("filter_predicates", "select p_partkey from part where (p_size between 5 and 20 or p_brand in ('Brand#11', 'Brand#22')) and p_name like '%a%' and regexp_matches(p_type, '[A-Z]') and not p_retailprice is null", "part")(
    lambda p: p.where((F.col("p_size").between(5, 20) | F.col("p_brand").isin("Brand#11", "Brand#22")) & F.col("p_name").like("%a%") & F.col("p_type").rlike("[A-Z]") & F.col("p_retailprice").isNotNull()).select("p_partkey")
)
on("filter_nullsafe", "select d.doc_id, l.toxic is not distinct from 1 as is_toxic from documents d left join labels l using (doc_id)", "documents", "labels")(lambda d, lb: d.select("doc_id").join(lb, "doc_id", "left").select("doc_id", F.col("toxic").eqNullSafe(1).alias("is_toxic")))

# --- joins ----------------------------------------------------------------------------------------------------------
_LO = "select o_orderstatus, count(*) n, cast(sum(l_linenumber) as bigint) total from lineitem join orders on l_orderkey = o_orderkey group by 1"


def _line_orders(li, o, hint):
    return li.select("l_orderkey", "l_linenumber").join(o.select("o_orderkey", "o_orderstatus").hint(hint), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("l_linenumber").alias("total"))


on("join_shuffle_hash", _LO, "lineitem", "orders")(lambda li, o: _line_orders(li, o, "shuffle_hash"))
on("join_sort_merge", _LO, "lineitem", "orders")(lambda li, o: _line_orders(li, o, "merge"))
on("join_broadcast", "select n_name, count(*) n from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey group by 1", "lineitem", "supplier", "nation")(
    lambda li, s, n: li.join(F.broadcast(s.join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name")), F.col("l_suppkey") == F.col("s_suppkey")).groupBy("n_name").agg(F.count("*").alias("n"))
)
on("join_outer", "select coalesce(cast(quality as varchar), 'none') quality, count(*) n from documents full outer join labels using (doc_id) group by 1", "documents", "labels")(lambda d, lb: d.select("doc_id").join(lb, "doc_id", "full").groupBy(F.coalesce(F.col("quality").cast("string"), F.lit("none")).alias("quality")).agg(F.count("*").alias("n")))
on("join_cross", "select r_name, count(*) n from region, nation group by 1", "region", "nation")(lambda r, n: r.crossJoin(n).groupBy("r_name").agg(F.count("*").alias("n")))
for _how, _op in (("semi", "in"), ("anti", "not in")):
    on(f"join_{_how}", f"select c_custkey from customer where c_custkey {_op} (select o_custkey from orders)", "customer", "orders")(lambda c, o, h=_how: c.join(o, c.c_custkey == o.o_custkey, f"left_{h}").select("c_custkey"))
_SIZED = q.sql([*q.sketches("slices")[:2], *q.index(8)], "select part_id, count(*) n, max(size) largest from dom join meta on size >= size_lo and size < size_hi_excl group by 1")


def _sizes_and_meta(spark, sf_dir):
    sizes = extract.sizes(extract.slice_entries(spark, sf_dir))
    return sizes, partition.equi_depth(stats.histogram(sizes), 8)


@query("join_range", _SIZED)
def join_range(spark, sf_dir):
    sizes, meta = _sizes_and_meta(spark, sf_dir)
    return partition.assign(sizes, meta).groupBy("part_id").agg(F.count("*").alias("n"), F.max("size").alias("largest"))


@query("join_theta", q.sql([*q.sketches("slices")[:2], *q.index(8)], "select part_id, count(*) n from dom join meta on size > size_max group by 1"))
def join_theta(spark, sf_dir):
    sizes, meta = _sizes_and_meta(spark, sf_dir)
    return sizes.join(F.broadcast(meta), F.col("size") > F.col("size_max")).groupBy("part_id").agg(F.count("*").alias("n"))


@on("join_interval", "select strftime(h, '%Y-%m-%d %H') slot, count(*) n from (select distinct date_trunc('hour', ts) h from events) join events on ts >= h and ts < h + interval 1 hour group by 1", "events")
def join_interval(e):
    """Equality on the interval's bin carries the join; the bounds are checked on top."""
    hours = e.select(F.date_trunc("hour", "ts").alias("h")).distinct()
    return e.withColumn("bin", F.date_trunc("hour", "ts")).join(hours, (F.col("bin") == F.col("h")) & (F.col("ts") < F.col("h") + F.expr("interval 1 hour"))).groupBy(F.date_format("h", "yyyy-MM-dd HH").alias("slot")).agg(F.count("*").alias("n"))


@on("join_asof", "with c as (select event_id, user_id, ts from events where event_type = 'click'), e as (select event_id error_id, user_id, ts from events where event_type = 'error') select c.event_id, (select max(error_id) from e e2 where e2.user_id = c.user_id and e2.ts = m.last_ts) error_id from c left join (select c2.event_id, max(e.ts) last_ts from c c2 join e on e.user_id = c2.user_id and e.ts <= c2.ts group by 1) m using (event_id)", "events")
def join_asof(e):
    """The last error of the same user at or before each click, by one pass over the union."""
    both = e.where("event_type in ('click', 'error')").withColumn("error", F.when(F.col("event_type") == "error", F.struct("ts", "event_id")))
    last = F.max("error").over(Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow))
    return both.withColumn("last", last).where("event_type = 'click'").select("event_id", F.col("last.event_id").alias("error_id"))


@query("join_lateral", "select c_custkey, o_orderkey from customer, lateral (select o_orderkey from orders where o_custkey = c_custkey order by o_totalprice desc, o_orderkey limit 2)")
def join_lateral(spark, sf_dir):
    """The order stands in the window: Spark plans a lateral ``order by ... limit`` as a sort of all rows, a shuffle and a
    window without an order, and blocks of a shuffle come in any order."""
    register(spark, sf_dir, ("customer", "orders"))
    ranked = "select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc nulls last, o_orderkey nulls last) as at from orders"
    return spark.sql(f"select c_custkey, o_orderkey from customer, lateral (select o_orderkey from ({ranked}) where o_custkey = c_custkey and at <= 2)")


@query("join_salted", q.sql([*q.sketches("slices", 1)[:3], *q.sample(), *q.truth()], "select query_id, domain_id, overlap from pairs"))
def join_salted(spark, sf_dir, k=None):
    entries = extract.slice_entries(spark, sf_dir)
    sizes = extract.sizes(entries)
    live = entries.join(sizes.select("domain_id"), "domain_id", "left_semi")
    qs = search.query_sample(sizes, k)
    asked = live.join(qs, F.col("domain_id") == F.col("query_id")).select("query_id", "value")
    return search.salted_overlaps(live, asked)


# --- aggregates -----------------------------------------------------------------------------------------------------
on("agg_hash", "select l_returnflag, l_linestatus, count(*) n, cast(sum(l_quantity) as bigint) qty, round(avg(l_discount), 6) disc from lineitem group by 1, 2", "lineitem")(lambda li: li.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("qty"), r6(F.avg("l_discount"), "disc")))
on("agg_sorted_list", "select c_nationkey, string_agg(cast(c_custkey as varchar), ',' order by c_custkey) keys from customer group by 1", "customer")(lambda c: c.groupBy("c_nationkey").agg(F.array_join(F.transform(F.sort_array(F.collect_list("c_custkey")), lambda x: x.cast("string")), ",").alias("keys")))
on("agg_count_distinct", "select event_type, count(distinct user_id) users from events group by 1", "events")(lambda e: e.groupBy("event_type").agg(F.countDistinct("user_id").alias("users")))
on("agg_multi_distinct", "select event_type, count(distinct user_id) users, count(distinct props) props, count(*) n from events group by 1", "events")(lambda e: e.groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.countDistinct("props").alias("props"), F.count("*").alias("n")))
on("agg_approx_distinct", None, "events")(lambda e: e.groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users")))
on("agg_hll", None, "events")(lambda e: e.groupBy("event_type").agg(F.hll_sketch_agg("user_id").alias("s")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("users")))
_YEAR = "cast(year(o_orderdate) as integer)"
for _kind in ("rollup", "cube"):
    on(f"agg_{_kind}", f"select o_orderstatus, o_orderpriority, count(*) n from orders group by {_kind}(o_orderstatus, o_orderpriority)", "orders")(lambda o, k=_kind: getattr(o, k)("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")))
on("agg_grouping_sets", f"select o_orderstatus, o_orderpriority, {_YEAR} y, count(*) n from orders group by grouping sets ((o_orderstatus, o_orderpriority), (y), ())", "orders")(
    lambda o: o.withColumn("y", F.year("o_orderdate")).groupingSets([["o_orderstatus", "o_orderpriority"], ["y"], []], "o_orderstatus", "o_orderpriority", "y").agg(F.count("*").alias("n"))
)
on("agg_pivot", f"select {_YEAR} y, count(*) filter (where o_orderstatus = 'F') f, count(*) filter (where o_orderstatus = 'O') o, count(*) filter (where o_orderstatus = 'P') p from orders group by 1", "orders")(
    lambda o: o.groupBy(F.year("o_orderdate").alias("y")).pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).select("y", *(F.coalesce(F.col(x), F.lit(0)).alias(x.lower()) for x in "FOP"))
)
on("agg_unpivot", "select s_suppkey, name, v from (select s_suppkey, 'nation' as name, cast(s_nationkey as double) v from supplier union all select s_suppkey, 'balance', s_acctbal from supplier)", "supplier")(
    lambda s: s.select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance")).unpivot("s_suppkey", ["nation", "balance"], "name", "v")
)
on("agg_moments", "select l_returnflag, round(avg(l_quantity), 6) mean, round(stddev_pop(l_quantity), 6) sd, round(var_samp(l_quantity), 6) var from lineitem group by 1", "lineitem")(lambda li: li.groupBy("l_returnflag").agg(r6(F.avg("l_quantity"), "mean"), r6(F.stddev_pop("l_quantity"), "sd"), r6(F.var_samp("l_quantity"), "var")))
on("agg_corr", "select round(corr(l_quantity, l_extendedprice), 6) r, round(covar_pop(l_quantity, l_extendedprice), 2) cov, round(regr_slope(l_extendedprice, l_quantity), 4) slope from lineitem", "lineitem")(lambda li: li.agg(r6(F.corr("l_quantity", "l_extendedprice"), "r"), F.round(F.covar_pop("l_quantity", "l_extendedprice"), 2).alias("cov"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope")))
on("agg_percentile", "select o_orderstatus, round(quantile_cont(o_totalprice, 0.25), 4) p25, round(median(o_totalprice), 4) p50 from orders group by 1", "orders")(lambda o: o.groupBy("o_orderstatus").agg(F.round(F.percentile("o_totalprice", 0.25), 4).alias("p25"), F.round(F.median("o_totalprice"), 4).alias("p50")))
on("agg_histogram", "select cast(floor(p_size / 10.0) as bigint) bin, count(*) n from part group by 1", "part")(lambda p: p.groupBy(F.floor(F.col("p_size") / 10).alias("bin")).agg(F.count("*").alias("n")))
on("agg_filter_having", "select o_custkey, count(*) n, count(*) filter (where o_orderstatus = 'F') n_f from orders group by 1 having count(*) > 12", "orders")(lambda o: o.groupBy("o_custkey").agg(F.count("*").alias("n"), F.count_if(F.col("o_orderstatus") == "F").alias("n_f")).where("n > 12"))
on("agg_minmax_by", "select o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) dearest, bool_or(o_orderstatus = 'F') any_f, bool_and(o_totalprice > 1000) all_big from orders group by 1", "orders")(lambda o: o.groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.bool_or(F.col("o_orderstatus") == "F").alias("any_f"), F.bool_and(F.col("o_totalprice") > 1000).alias("all_big")))
on("agg_collect_set", "select o_orderpriority, string_agg(distinct o_orderstatus, ',' order by o_orderstatus) s from orders group by 1", "orders")(lambda o: o.groupBy("o_orderpriority").agg(F.array_join(F.sort_array(F.collect_set("o_orderstatus")), ",").alias("s")))

# --- windows, sorts, sets -------------------------------------------------------------------------------------------
_W = "over (partition by o_custkey order by o_orderdate, o_orderkey)"
_w = lambda: Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
on("win_ranking", f"select o_orderkey, cast(row_number() {_W} as integer) rn, cast(rank() over (partition by o_custkey order by o_orderpriority) as integer) rk, cast(dense_rank() over (partition by o_custkey order by o_orderpriority) as integer) dr, round(cume_dist() {_W}, 6) cd, round(percent_rank() {_W}, 6) pr from orders", "orders")(
    lambda o: o.select("o_orderkey", F.row_number().over(_w()).alias("rn"), F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("rk"), F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("dr"), r6(F.cume_dist().over(_w()), "cd"), r6(F.percent_rank().over(_w()), "pr"))
)
on("win_ntile", "select s_suppkey, cast(ntile(3) over (partition by s_nationkey order by s_suppkey) as integer) n from supplier", "supplier")(lambda s: s.select("s_suppkey", F.ntile(3).over(Window.partitionBy("s_nationkey").orderBy("s_suppkey")).alias("n")))
on("win_analytic", f"select o_orderkey, lag(o_orderkey) {_W} before, lead(o_orderkey, 2) {_W} after, first_value(o_orderkey) {_W} first, nth_value(o_orderkey, 2) {_W} nth, last_value(case when o_orderstatus = 'F' then o_orderkey end ignore nulls) {_W} last_f from orders", "orders")(
    lambda o: o.select("o_orderkey", F.lag("o_orderkey").over(_w()).alias("before"), F.lead("o_orderkey", 2).over(_w()).alias("after"), F.first("o_orderkey").over(_w()).alias("first"), F.nth_value("o_orderkey", 2).over(_w()).alias("nth"), F.last(F.when(F.col("o_orderstatus") == "F", F.col("o_orderkey")), True).over(_w()).alias("last_f"))
)
on("win_rows_frame", "select o_orderkey, round(avg(o_totalprice) over (partition by o_custkey order by o_orderdate, o_orderkey rows between 2 preceding and current row), 4) m from orders", "orders")(lambda o: o.select("o_orderkey", F.round(F.avg("o_totalprice").over(_w().rowsBetween(-2, 0)), 4).alias("m")))
on("win_range_frame", "select p_partkey, count(*) over (partition by p_brand order by p_size range between 3 preceding and 3 following) n from part", "part")(lambda p: p.select("p_partkey", F.count("*").over(Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-3, 3)).alias("n")))
query("win_running_total", q.sql([*q.sketches("slices")[:2], *q.histogram()], "select size, n_domains, cum_before from hist"))(lambda spark, sf_dir: stats.histogram(extract.sizes(extract.slice_entries(spark, sf_dir))))
on("sort_multi", "select p_partkey, p_brand, p_size from part order by p_brand desc, p_size nulls last, p_partkey", "part")(lambda p: p.select("p_partkey", "p_brand", "p_size").orderBy(F.desc("p_brand"), F.asc_nulls_last("p_size"), "p_partkey"))
on("limit_offset", "select o_orderkey from orders order by o_orderkey limit 10 offset 20", "orders")(lambda o: o.select("o_orderkey").orderBy("o_orderkey").offset(20).limit(10))
on("topk_global", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 15", "orders")(lambda o: o.select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(15))
on("topk_per_group", "select o_orderpriority, o_orderkey from orders qualify row_number() over (partition by o_orderpriority order by o_totalprice desc, o_orderkey) <= 3", "orders")(lambda o: o.withColumn("k", F.row_number().over(Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("k <= 3").select("o_orderpriority", "o_orderkey"))
on("sample_bernoulli", None, "orders")(lambda o: o.select("o_orderkey").sample(0.1, seed=3))
on("sample_stratified", None, "orders")(lambda o: o.select("o_orderkey", "o_orderstatus").sampleBy("o_orderstatus", {"F": 0.1, "O": 0.05}, seed=3))
_A, _B = "select l_partkey k from lineitem where l_suppkey = 1", "select l_partkey k from lineitem where l_suppkey = 2"
for _name, _sql, _f in (("set_union", "union", lambda a, b: a.union(b).distinct()), ("set_intersect", "intersect", DataFrame.intersect), ("set_except", "except", DataFrame.subtract), ("set_intersect_all", "intersect all", DataFrame.intersectAll), ("set_except_all", "except all", DataFrame.exceptAll)):
    on(_name, f"{_A} {_sql} {_B}", "lineitem")(lambda li, f=_f: f(*(li.where(F.col("l_suppkey") == k).select(F.col("l_partkey").alias("k")) for k in (1, 2))))

# --- functions ------------------------------------------------------------------------------------------------------
on("fn_string", "select p_partkey, lower(p_name) lo, trim('  ' || p_brand || ' ') tr, substr(p_type, 2, 4) su, len(p_name) n, concat_ws('-', p_brand, p_type) cw, levenshtein(p_brand, p_type) lv, translate(p_brand, '#', '_') tl from part", "part")(
    lambda p: p.select("p_partkey", F.lower("p_name").alias("lo"), F.trim(F.concat(F.lit("  "), "p_brand", F.lit(" "))).alias("tr"), F.substring("p_type", 2, 4).alias("su"), F.length("p_name").cast("long").alias("n"), F.concat_ws("-", "p_brand", "p_type").alias("cw"), F.levenshtein("p_brand", "p_type").cast("long").alias("lv"), F.translate("p_brand", "#", "_").alias("tl"))
)
on("fn_regexp", r"select p_partkey, regexp_extract(p_brand, '#(\d)', 1) d, regexp_replace(p_brand, '[0-9]', 'x', 'g') r from part", "part")(lambda p: p.select("p_partkey", F.regexp_extract("p_brand", r"#(\d)", 1).alias("d"), F.regexp_replace("p_brand", "[0-9]", "x").alias("r")))
on("fn_hash", "select doc_id, md5(text) m, sha256(text) s from documents", "documents")(lambda d: d.select("doc_id", F.md5(F.col("text").cast("binary")).alias("m"), F.sha2(F.col("text").cast("binary"), 256).alias("s")))
on("fn_date", "select o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') m, cast(date_diff('day', o_orderdate, timestamp '1999-01-01') as bigint) dd, strftime(o_orderdate + interval 2 month, '%Y-%m-%d') am, cast(quarter(o_orderdate) as bigint) q, cast(dayofyear(o_orderdate) as bigint) dy from orders", "orders")(
    lambda o: o.select("o_orderkey", F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("m"), F.datediff(F.lit("1999-01-01"), "o_orderdate").cast("long").alias("dd"), F.date_format(F.add_months("o_orderdate", 2), "yyyy-MM-dd").alias("am"), F.quarter("o_orderdate").cast("long").alias("q"), F.dayofyear("o_orderdate").cast("long").alias("dy"))
)
on("fn_math", "select p_partkey, round(ln(p_size), 6) l, round(power(p_size, 0.5), 6) p, round(exp(p_size / 100.0), 6) e, cast(floor(p_retailprice) as bigint) f, p_size % 7 m, greatest(p_size, 10) g, p_size & 6 b from part", "part")(
    lambda p: p.select("p_partkey", r6(F.log("p_size"), "l"), r6(F.pow("p_size", F.lit(0.5)), "p"), r6(F.exp(F.col("p_size") / 100.0), "e"), F.floor("p_retailprice").alias("f"), F.pmod("p_size", F.lit(7)).alias("m"), F.greatest("p_size", F.lit(10)).alias("g"), F.col("p_size").bitwiseAND(6).alias("b"))
)
_TOK = r"list_distinct(string_split_regex(lower(text), '\s+'))"
on("fn_array_sets", f"with t as (select item_id, {_TOK} w from benchmark) select a.item_id a, b.item_id b, len(list_intersect(a.w, b.w)) n, round(len(list_intersect(a.w, b.w)) / len(a.w), 6) t from t a, t b where a.item_id <> b.item_id and len(list_intersect(a.w, b.w)) > 0", "benchmark")(lambda b: _array_containment(b))


def _array_containment(b):
    """Containment by arrays, for small domains; pairs are those that share a token."""
    t = b.select("item_id", F.array_distinct(F.split(F.lower("text"), r"\s+")).alias("w"))
    one, two = (t.select(F.col("item_id").alias(n), F.explode("w").alias("value")) for n in "ab")
    pairs = one.join(two, "value").where("a <> b").select("a", "b").distinct()
    both = pairs.join(t.select(F.col("item_id").alias("a"), F.col("w").alias("wa")), "a").join(t.select(F.col("item_id").alias("b"), F.col("w").alias("wb")), "b")
    n = F.size(F.array_intersect("wa", "wb"))
    return both.select("a", "b", n.cast("long").alias("n"), r6(n / F.size("wa"), "t"))


on("fn_array_hof", r"select item_id, len(list_filter(string_split(text, ' '), lambda w: len(w) > 5)) n_long, cast(list_sum(list_transform(string_split(text, ' '), lambda w: len(w))) as bigint) chars from benchmark", "benchmark")(
    lambda b: b.select("item_id", F.size(F.filter(F.split("text", " "), lambda w: F.length(w) > 5)).cast("long").alias("n_long"), F.aggregate(F.split("text", " "), F.lit(0).cast("long"), lambda s, w: s + F.length(w)).alias("chars"))
)
on("fn_array_explode", "select item_id, cast(i - 1 as integer) pos, w[i] word from (select item_id, string_split(text, ' ') w, unnest(range(1, len(string_split(text, ' ')) + 1)) i from benchmark)", "benchmark")(lambda b: b.select("item_id", F.posexplode(F.split("text", " ")).alias("pos", "word")))
on("fn_embedding_dot", "select a.vec_id, round(list_dot_product(a.embedding::double[], b.embedding::double[]), 4) dot from embeddings a, embeddings b where b.vec_id = 0", "embeddings")(
    lambda e: e.crossJoin(F.broadcast(e.where("vec_id = 0").select(F.col("embedding").alias("z")))).select("vec_id", F.round(F.aggregate(F.zip_with("embedding", "z", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x), 4).alias("dot"))
)
_K = "cast(json_extract_string(props, '$.k') as bigint)"
on("fn_json", f"select event_id, {_K} k from events", "events")(lambda e: e.select("event_id", F.from_json("props", "k bigint")["k"].alias("k")))
on("fn_variant", f"select event_id, {_K} k from events", "events")(lambda e: e.select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k")))
on("fn_map", f"select event_id, event_type as key, {_K} v from events where {_K} > 50", "events")(lambda e: e.select("event_id", F.explode(F.map_filter(F.create_map("event_type", F.get_json_object("props", "$.k").cast("bigint")), lambda k, v: v > 50)).alias("key", "v")))
on("fn_struct", "select event_type, max(value) top, arg_max(event_id, (value, event_id)) event_id from events group by 1", "events")(lambda e: e.groupBy("event_type").agg(F.max(F.struct("value", "event_id")).alias("s")).select("event_type", F.col("s.value").alias("top"), "s.event_id"))


# --- SQL surface, Python functions ----------------------------------------------------------------------------------
def _sql(name: str, text: str, *tables: str):
    def run(spark, sf_dir):
        register(spark, sf_dir, tables)
        return spark.sql(text)

    query(name, text)(run)


_sql("sql_subqueries", "select c_custkey from customer c where c_acctbal > (select avg(c_acctbal) from customer) and exists (select 1 from orders o where o.o_custkey = c.c_custkey and o.o_totalprice > 200000)", "customer", "orders")
_sql("sql_cte", "with t as (select o_custkey, count(*) n from orders group by 1), m as (select max(n) most from t) select o_custkey, n from t join m on n = most", "orders")
_sql("sql_recursive_cte", "with recursive r(k, v) as (select 1, 1 union all select k + 1, v * 2 from r where k < 12) select k, v from r")


@query("sql_udf_convert", "select x, round(t / (x / 20.0::double + 1 - t), 6) s from (select unnest(range(1, 21)) x, 0.5::double t)")
def sql_udf_convert(spark, sf_dir=None):
    spark.sql("create or replace temporary function jaccard_of(t double, x double, q double) returns double return t / (x / q + 1 - t)")
    return spark.sql("select id as x, round(jaccard_of(:t, id, :q), 6) as s from range(1, 21)", args={"t": 0.5, "q": 20.0})


@query("udf_scalar_tuner")
def udf_scalar_tuner(spark, sf_dir=None):
    table_ = {k: b * 1000 + r for k, _, _, b, r, _, _ in tuning.precompute(64, [0.5])}

    @F.pandas_udf("int")
    def shape(bins: pd.Series) -> pd.Series:
        return bins.map(table_).astype("int32")

    return spark.range(len(tuning.RATIO_EDGES)).select(F.col("id").alias("ratio_bin"), shape("id").alias("shape"))


_UDAF = q.sql(q.sketches("slices", 4), "select domain_id, string_agg(cast(v as varchar), ',' order by i) sig from sig group by 1")


def _hashes(spark, sf_dir):
    entries = extract.slice_entries(spark, sf_dir)
    live = entries.join(extract.sizes(entries).select("domain_id"), "domain_id", "left_semi")
    return live.select("domain_id", Portable(4).base(F.col("value")).alias("h"))


@query("udaf_minhash", _UDAF)
def udaf_minhash(spark, sf_dir):
    from ..functions.hashing import PRIME, coefficients

    pairs = coefficients(4)

    @F.pandas_udf("string")
    def signature(h: pd.Series) -> str:
        return ",".join(str(int(((a * h.astype("int64") + b) % PRIME).min())) for a, b in pairs)

    return _hashes(spark, sf_dir).groupBy("domain_id").agg(signature("h").alias("sig"))


@query("map_in_arrow_signatures", _UDAF)
def map_in_arrow_signatures(spark, sf_dir):
    """Partial signatures of every batch by numpy, then minima by Spark."""
    import numpy as np
    import pyarrow as pa

    from ..functions.hashing import PRIME, coefficients

    pairs = coefficients(4)

    def partial(rows):
        for batch in rows:
            ids, back = np.unique(np.array(batch.column(0).to_pylist(), dtype=object).astype(str), return_inverse=True)
            h = batch.column(1).to_numpy()
            out = np.full((len(ids), len(pairs)), PRIME, np.int64)
            for k, (a, b) in enumerate(pairs):
                np.minimum.at(out[:, k], back, (a * h + b) % PRIME)
            yield pa.RecordBatch.from_arrays([pa.array(ids.tolist(), pa.string()), *(pa.array(out[:, k]) for k in range(len(pairs)))], ["domain_id", *(f"m{k}" for k in range(len(pairs)))])

    parts = _hashes(spark, sf_dir).mapInArrow(partial, "domain_id string, m0 long, m1 long, m2 long, m3 long")
    mins = parts.groupBy("domain_id").agg(*(F.min(f"m{k}").cast("string").alias(f"m{k}") for k in range(4)))
    return mins.select("domain_id", F.concat_ws(",", "m0", "m1", "m2", "m3").alias("sig"))


@query("udtf_band_keys", q.sql(q.sketches("slices", 4), "select domain_id, cast(i // 2 as integer) band, string_agg(cast(v as varchar), '-' order by i) bucket from sig group by 1, 2"))
def udtf_band_keys(spark, sf_dir):
    @F.udtf(returnType="band int, bucket string")
    class BandKeys:
        def eval(self, sig: list, r: int):
            for k in range(len(sig) // r):
                yield k, "-".join(str(v) for v in sig[k * r : (k + 1) * r])

    spark.udtf.register("band_keys", BandKeys)
    entries = extract.slice_entries(spark, sf_dir)
    minhash.signatures(entries, Portable(4)).where("size >= 10").createOrReplaceTempView("supplier_signatures")
    return spark.sql("select domain_id, band, bucket from supplier_signatures, lateral band_keys(sig, 2)")


@query("cogroup_verify", q.sql([*q.sketches("slices", 1)[:3], *q.sample(), *q.truth()], "select query_id, domain_id, overlap from pairs"))
def cogroup_verify(spark, sf_dir, k=None, slots=1024):
    """Overlaps by cogrouped value ranges; partial counts are summed by Spark."""
    entries = extract.slice_entries(spark, sf_dir)
    sizes = extract.sizes(entries)
    live = entries.join(sizes.select("domain_id"), "domain_id", "left_semi").withColumn("slot", F.pmod(F.xxhash64("value"), F.lit(slots)))
    asked = live.join(search.query_sample(sizes, k), F.col("domain_id") == F.col("query_id")).select("query_id", F.col("value").alias("asked"), F.col("slot").alias("at"))

    def count(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        m = a.merge(b, left_on="value", right_on="asked").groupby(["query_id", "domain_id"]).size().reset_index(name="overlap")
        return m.astype({"overlap": "int64"})

    parts = live.groupBy("slot").cogroup(asked.groupBy("at")).applyInPandas(count, "query_id string, domain_id string, overlap long")
    return parts.groupBy("query_id", "domain_id").agg(F.sum("overlap").alias("overlap"))
