"""The stored index: what a search reads, queries from outside, maintenance; streams that feed it; trends of the experiments."""

import collections
import datetime

import pytest
from pyspark.sql import functions as F

from domsearch.functions.hashing import Portable
from domsearch.operators import lsh, spci
from domsearch.plans import workloads
from domsearch.plans.catalog import QUERIES
from domsearch.streaming import queries as arriving


@pytest.fixture(scope="module")
def bench(spark, sf):
    return workloads.Bench(spark, sf, "slices", m=64)


@pytest.fixture(scope="module")
def index(bench):
    return spci.stored(spci.build(bench.signed, 8, 64), [0.5, 0.8])


def rows(df, *columns):
    return {tuple(r) for r in df.select(*(columns or df.columns)).collect()}


def test_stored_buckets_answer_as_signatures_do(bench, index):
    plain = spci.build(bench.signed, 8, 64)
    assert index.depths and index.buckets is not None
    for thresholds in ([0.5], [0.5, 0.8], [0.3]):  # depths of 0.3 are not all stored
        assert rows(spci.search(index, bench.queries, thresholds)) == rows(spci.search(plain, bench.queries, thresholds))


def test_a_search_reads_its_partitions_and_depths_only(bench, index, monkeypatch):
    asked = spci.with_signatures(index, bench.queries)
    plan = spci.make_plan(index, asked.select("query_id", "q"), [0.8]).join(asked.select("query_id", "sig"), "query_id")
    monkeypatch.setattr(lsh, "FEW_KEYS", 10**9)
    text = spci.probe(index, plan)._jdf.queryExecution().executedPlan().toString()
    scan = next(x for x in text.split("\n") if "FileScan" in x and "bucket" in x)
    assert "PartitionFilters: [" in scan and "part_id" in scan.split("PartitionFilters")[1] and "In(bucket" in scan
    assert "sig" not in scan.split("ReadSchema")[1]
    shapes = plan.select("part_id", "r").distinct().count()
    assert shapes < index.meta.count() * len(index.depths)


def test_queries_from_outside(spark, bench, index, sf):
    sets = {"mine": [str(v) for v in range(1, 60)], "tiny": ["1", "1", "", "2"]}
    entries = spark.createDataFrame([(k, v) for k, vs in sets.items() for v in vs], "query_id string, value string")
    asked = spci.sketched(entries, Portable(64))
    assert rows(asked, "query_id", "q") == {("mine", 59), ("tiny", 2)}
    got = rows(spci.search(index, asked, [0.5]), "query_id", "domain_id")
    assert got and {a for a, _ in got} <= set(sets)
    unsized = asked.select("query_id", "sig").where("query_id = 'mine'")
    assert rows(spci.search(index, unsized, [0.5]), "query_id")
    with pytest.raises(ValueError, match="nobody"):
        spci.search(index, spark.createDataFrame([("nobody", 12)], "query_id string, q long"), [0.5])


def test_appended_and_rebuilt(spark, bench):
    late = F.pmod(F.xxhash64("domain_id"), F.lit(3)) == 0
    grown = spci.insert(spci.stored(spci.build(bench.signed.where(~late), 8, 64), [0.5]), bench.signed.where(late))
    plain = spci.insert(spci.build(bench.signed.where(~late), 8, 64), bench.signed.where(late))
    assert rows(grown.meta) == rows(plain.meta)
    assert rows(spci.search(grown, bench.queries, [0.5])) == rows(spci.search(plain, bench.queries, [0.5]))
    anew = spci.rebuild(grown, 8)
    assert rows(anew.meta) == rows(spci.build(bench.signed, 8, 64).meta)
    assert rows(spci.search(anew, bench.queries, [0.5])) == rows(spci.search(spci.build(bench.signed, 8, 64), bench.queries, [0.5]))


def test_signatures_do_not_grow_with_the_sets(spark):
    def bytes_of(size):
        signed = spark.range(200).select(F.concat(F.lit("d"), F.col("id")).alias("domain_id"), F.lit(size).cast("long").alias("size"), F.transform(F.sequence(F.lit(1), F.lit(64)), lambda i: F.xxhash64("id", i)).alias("sig"))
        return {r["part"]: r["bytes"] for r in spci.footprint(spci.stored(spci.build(signed, 2, 64), [0.5])).collect()}

    small, large = bytes_of(20), bytes_of(2_000_000)
    assert large["signatures"] == pytest.approx(small["signatures"], rel=0.05)


def test_arrivals_and_drift(spark, sf):
    index, log = arriving.arriving(spark, sf, n=8, times=0.0)
    log = log.orderBy("batch").collect()
    assert len(log) == 4 and all(r["rebuilt"] for r in log)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    sizes = docs.select(F.size(F.array_distinct(F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != ""))).alias("n")).where("n >= 10").count()
    assert index.signatures.count() == sizes == index.meta.agg(F.sum("n_domains")).first()[0]


def test_late_rows_are_dropped(spark, sf):
    at = [r[0] for r in spark.read.parquet(f"{sf}/events.parquet").select("ts").collect()]
    seconds = F.col("ts").cast("timestamp").cast("double").alias("at")
    cuts = spark.read.parquet(f"{sf}/events.parquet").select(seconds).approxQuantile("at", [0.25, 0.5, 0.75], 0.01)
    cuts = [datetime.datetime.fromtimestamp(c, datetime.UTC).replace(tzinfo=None) for c in cuts]
    files = collections.defaultdict(list)
    for t in at:
        files[sum(t > c for c in cuts)].append(t)
    hour, marks, kept = datetime.timedelta(hours=1), [datetime.datetime.min] * 2, 0
    for k in (2, 3, 0, 1):  # rows are late against the watermark of the batch before the last
        ends = [t.replace(minute=0, second=0, microsecond=0) + hour for t in files[k]]
        kept += sum(e > marks[-2] for e in ends)
        marks.append(max(marks[-1], max(files[k]) - hour))
    total = QUERIES["stream_late_data"](spark, sf).agg(F.sum("n")).first()[0]
    assert total == kept < len(at)
    assert QUERIES["stream_late_data"](spark, sf, arrival=(0, 1, 2, 3)).agg(F.sum("n")).first()[0] == len(at)


def test_trends_over_thresholds(bench):
    at = [0.2, 0.5, 0.9, 1.0]
    got = {(r["index_id"], r["t_star"]): r for r in bench.sweep([s for s in workloads.SPECS if s[1] != 16], at).collect()}
    mean = lambda name, what: sum(got[name, t][what] or 0 for t in at) / len(at)
    assert mean("minhash_lsh", "precision") < mean("spci_n8", "precision") < mean("spci_n32", "precision")
    assert mean("spci_n8", "recall") >= mean("spci_n32", "recall") - 0.02
    assert mean("spci_n32", "recall") > mean("padded", "recall")
    assert got["padded", 1.0]["empty_share"] > got["spci_n32", 1.0]["empty_share"]


def test_nested_collections_and_drift(spark, sf, bench):
    skew = bench.nested([workloads.SPECS[0], workloads.SPECS[4]], (0.5, 0.9, 1.0), 0.5).collect()
    by = {(r["index_id"], r["share_of_domains"]): r for r in skew}
    assert len(by) == 6 and by["minhash_lsh", 1.0]["skewness"] > by["minhash_lsh", 0.5]["skewness"]
    assert by["spci_n32", 1.0]["precision"] > by["minhash_lsh", 1.0]["precision"]
    # a collection of its own gives what its part of the nested index gives
    whole = {r["index_id"]: r for r in bench.sweep([workloads.SPECS[0], workloads.SPECS[4]], [0.5]).collect()}
    assert all(by[n, 1.0][c] == r[c] for n, r in whole.items() for c in ("precision", "recall", "f1", "mean_answer"))
    drift = {r["index_id"]: r for r in QUERIES["acc_vs_drift"](spark, sf, m=64, lambdas=(0.0, 1.0)).collect()}
    assert drift["drift_1"]["stddev"] > drift["drift_0"]["stddev"] and drift["drift_1"]["mean_answer"] > drift["drift_0"]["mean_answer"]


def test_candidates_grow_with_domains_and_fall_with_partitions(spark, sf):
    got = {(r["share"], r["n_partitions"]): r for r in QUERIES["cost_vs_domains"](spark, sf, shares=(20, 100), ns=(1, 32)).collect()}
    for n in (1, 32):
        assert got[20, n]["n_candidates"] < got[100, n]["n_candidates"]
    assert got[100, 32]["n_candidates"] < got[100, 1]["n_candidates"]
