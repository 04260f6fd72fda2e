"""Accuracy judged pair by pair where the domains lie, beside searches and counts of the same."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from domsearch.functions.hashing import PRIME, Portable
from domsearch.functions.minhash import portable_sketch
from domsearch.operators import accuracy, padded, pairwise, search, spci
from domsearch.plans import workloads
from domsearch.plans.catalog import QUERIES

AT = [0.1, 0.5, 0.9]
SPECS = [workloads.SPECS[0], workloads.SPECS[1], workloads.SPECS[2]]


@pytest.fixture(scope="module")
def bench(spark, sf):
    return workloads.Bench(spark, sf, "slices", m=64)


def probed(bench, spec, thresholds):
    """Candidates of one setting by its buckets."""
    name, n, pad = spec
    index = spci.build(bench.signed, n, bench.m, native=True, family=Portable(bench.m))
    if not pad:
        return spci.search(index, bench.queries, thresholds).withColumn("index_id", F.lit(name))
    held = padded.padded_signatures(index.signatures, F.col("part_size_max"))
    own = held.select(F.col("domain_id").alias("query_id"), F.col("own").alias("sig"))
    return spci.probe(spci.Index(held, index.meta, index.m, True), spci.make_plan(index, bench.queries, thresholds), own).drop("part_id").withColumn("index_id", F.lit(name))


def test_sweep_counts_what_buckets_return(bench, monkeypatch):
    """Searches through bucket rows and shuffled truth give the same figures; queries in many batches as well."""
    keys = bench.spark.createDataFrame([(s[0], t) for s in SPECS for t in AT], "index_id string, t_star double")
    truth = bench.pairs.join(F.broadcast(keys), F.col("overlap") / F.col("q") >= F.col("t_star")).select("index_id", "t_star", "query_id", "domain_id")
    found = probed(bench, SPECS[0], AT).unionByName(probed(bench, SPECS[1], AT)).unionByName(probed(bench, SPECS[2], AT))
    want = sorted(map(tuple, accuracy.summary(accuracy.per_query(found, truth)).collect()))
    assert sorted(map(tuple, bench.sweep(SPECS, AT).collect())) == want
    monkeypatch.setattr(search, "SMALL_ENTRIES", 300)
    monkeypatch.setattr(pairwise, "CELLS", 50)
    assert sorted(map(tuple, bench.sweep(SPECS, AT).collect())) == want


@pytest.mark.parametrize("name", ["acc_vs_threshold", "acc_large_queries", "acc_small_queries", "acc_vs_skew", "acc_vs_drift", "acc_vs_length", "cost_vs_domains"])
def test_no_pair_is_sent(spark, sf, name, monkeypatch):
    """Neither bucket rows nor pairs leave the tasks that hold the domains: blocks of counts are all that is dealt out."""
    seen, make = [], pairwise.over_pairs
    monkeypatch.setattr(pairwise, "over_pairs", lambda *a, **b: seen.append(make(*a, **b)) or seen[-1])
    monkeypatch.setattr(spci, "probe", None)
    options = {"m": 16} if name != "acc_vs_length" else {"lengths": (8, 16)}
    assert QUERIES[name](spark, sf, **options).count()
    plan = seen[0]._jdf.queryExecution().executedPlan().toString()
    assert len(seen) == 1 and "Exchange" not in plan


def test_shared_hashes_are_met(spark):
    """Two values of one hash make sets meet that share no value; the overlap stays 0."""
    batch = pairwise.Batch(np.array([7]), np.array([2]), np.zeros((1, 4), np.int32), np.array([3, 5]), np.array([0, 1, 2]), np.array([0, 0], np.int32), np.array([[5, 9], [9, 5]]))
    (got,) = pairwise.met(batch, np.array([3, 4, 9, 11]), np.array([2, 1, 1]))
    assert [x.tolist() for x in got] == [[0, 1], [0, 0], [1, 0]]
    values = spark.createDataFrame([(1, "a"), (2, "b"), (3, "c")], "code long, value string")

    class Coarse:
        base = staticmethod(lambda value: F.when(value == "c", 1).otherwise(0))

    assert pairwise.twins(values, Coarse).tolist() == [[1, 2], [2, 1]]


def test_first_bands():
    rng = np.random.default_rng(5)
    same = rng.random((400, 24)) < rng.random((400, 1))
    got = pairwise.first_bands(same, [1, 3, 5, 24])
    for k, r in enumerate([1, 3, 5, 24]):
        met = same[:, : 24 // r * r].reshape(400, -1, r).all(axis=2)
        assert (got[k] == np.where(met.any(axis=1), met.argmax(axis=1), pairwise.NEVER)).all()


def test_portable_sketch(bench):
    """Signatures by numpy are those of the SQL functions."""
    values, starts = np.array([4, 9, 100, 9, 7]), np.array([0, 3])
    df = bench.spark.createDataFrame([("a", "4"), ("a", "9"), ("a", "100"), ("b", "9"), ("b", "7")], "domain_id string, value string")
    from domsearch.functions.minhash import signatures

    want = {r["domain_id"]: r["sig"] for r in signatures(df, Portable(16)).collect()}
    assert portable_sketch(16)(values, starts).tolist() == [want["a"], want["b"]] and max(want["a"]) < PRIME


def test_estimator_error_sends_sums_only(spark, sf, monkeypatch):
    """The figures of the pairs beside their sketches, with one row of sums from each task."""
    from domsearch.functions import minhash, scores
    from domsearch.plans.methods import M, Corpus

    seen, make = [], pairwise.over_pairs
    monkeypatch.setattr(pairwise, "over_pairs", lambda *a, **b: seen.append(make(*a, **b)) or seen[-1])
    got = QUERIES["estimator_error"](spark, sf).first()
    assert "Exchange" not in seen[0]._jdf.queryExecution().executedPlan().toString()
    c = Corpus(spark, sf)
    own = c.signed.select(F.col("domain_id").alias("query_id"), F.col("sig").alias("a"))
    s = scores.jaccard(F.col("overlap"), F.col("q"), F.col("x"))
    rows = c.pairs.join(own, "query_id").join(c.signed.select("domain_id", "sig"), "domain_id")
    n, error, deviation = rows.agg(F.count("*"), F.avg(F.abs(minhash.estimate_jaccard(F.col("a"), F.col("sig")) - s)), F.avg(F.sqrt(s * (1 - s) / M))).first()
    assert (got["n"], got["mean_error"], got["standard_error"]) == (n, pytest.approx(error, abs=1e-6), pytest.approx(deviation, abs=1e-6))


def test_padded_partitions_send_counts_only(spark, sf, monkeypatch):
    monkeypatch.setattr(spci, "probe", None)
    got = {(r["index_id"], r["t_star"]): r for r in QUERIES["padded_partitioned"](spark, sf).collect()}
    assert len(got) == 20 and got["padded_n32", 0.1]["recall"] > got["padded_n1", 0.1]["recall"]


def test_name_rank(spark):
    """Stored ids in the order of their names: numbers as text, negative ones as well."""
    from domsearch.operators import extract

    keys = [0, 1, 2, 9, 10, 11, 19, 100, 101, 1000, 8035, 8401, 10957, 123456789012345678]
    codes = [k * 16 + kind for k in keys for kind in range(len(extract.KINDS)) if k < 20_000 or ":" not in extract.KINDS[kind]]
    codes += [-k * 16 + kind for k in keys[1:12] for kind in range(len(extract.KINDS))]
    rows = spark.createDataFrame([(c,) for c in codes], "c long").select("c", extract.label("c", "slices").alias("name"))
    want = [r["c"] for r in rows.orderBy("name").collect()]
    assert np.array(codes)[np.argsort(extract.name_rank(np.array(codes)))].tolist() == want


def test_ranks_send_packed_numbers(spark, sf, monkeypatch):
    """Ranks come from blocks of packed numbers: no pair is sent as a row; many batches and blocks give the same."""
    from pyspark.sql import Window

    from domsearch.functions import scores
    from domsearch.plans.methods import Corpus

    w = Window.partitionBy("query_id")
    by = lambda s: F.row_number().over(w.orderBy(F.desc(s), "domain_id"))
    o, q, x = F.col("overlap"), F.col("q"), F.col("x")
    rows = Corpus(spark, sf).pairs.select("query_id", by(scores.containment(o, q)).alias("a"), by(scores.jaccard(o, q, x)).alias("b"))
    want = rows.groupBy("query_id").agg(F.count("*").alias("n"), F.sum((F.col("a") != F.col("b")).cast("long")), F.max(F.abs(F.col("a") - F.col("b"))).cast("long"))
    want = sorted(map(tuple, want.collect()))
    got = QUERIES["rank_disagreement"](spark, sf)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "Window" not in plan and "overlaps#" in plan
    assert sorted(map(tuple, got.collect())) == want
    monkeypatch.setattr(search, "SMALL_ENTRIES", 300)
    monkeypatch.setattr(pairwise, "SENT_PAIRS", 500)
    assert sorted(map(tuple, QUERIES["rank_disagreement"](spark, sf).collect())) == want
