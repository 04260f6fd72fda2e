"""Searches that neither send entries again nor broadcast without bound, and questions on given tables."""

import re

import pytest
from pyspark.sql import functions as F

from domsearch import store
from domsearch.operators import extract, lsh, search, spci
from domsearch.plans.catalog import QUERIES
from domsearch.plans.methods import Corpus


@pytest.mark.parametrize("name", ["convert_roundtrip", "effective_thresholds", "fp_probability", "powerlaw_bounds", "s_curve", "fp_area", "fn_area"])
def test_model_queries_read_a_table(spark, sf, name):
    assert any("lineitem" in f for f in QUERIES[name](spark, sf).inputFiles())


def test_overlaps_leave_entries_where_they_are(spark, sf):
    """Entries are dealt out by domain once: counting pairs reads them in place, with no shuffle but that of the sizes."""
    plan = Corpus(spark, sf).pairs._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") <= 1 and "Bucketed: true" in plan


def test_keys_in_several_passes(spark, sf, monkeypatch):
    c = Corpus(spark, sf)
    index = c.index(8)
    want = sorted(map(tuple, spci.search(index, c.queries, [0.3, 0.7]).collect()))
    sizes = []
    monkeypatch.setattr(lsh, "SMALL_KEYS", 500)
    broadcast = F.broadcast

    def counted(df):
        if "bucket" in df.columns:
            sizes.append(df.count())
        return broadcast(df)

    monkeypatch.setattr(F, "broadcast", counted)
    for at in (index, spci.stored(index, [0.3, 0.7])):
        sizes.clear()
        assert sorted(map(tuple, spci.search(at, c.queries, [0.3, 0.7]).collect())) == want
        assert len(sizes) > 1


def test_appended_rows_of_a_stream_go_to_files(spark, sf):
    got = QUERIES["stream_dedup"](spark, sf)
    assert got.inputFiles()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, spark.read.parquet(f"{sf}/events.parquet").select("event_id", "user_id").collect()))


def test_numbers_are_dealt_as_blocks(spark):
    """Ids and values anywhere in 64 bits, repeated within and between blocks: distinct rows, each in Spark's bucket of its id."""
    rows = [(i * (2**58 - 7) if i % 3 else -i, v * (2**61 - 1)) for i in range(-20, 20) for v in (-3, 0, 1, 1)]
    df = spark.createDataFrame(rows, "id long, value long").repartition(3)
    got = store.dealt_numbers(df.unionAll(df), 5)
    assert sorted(map(tuple, got.collect())) == sorted(set(rows))
    plan = got.groupBy("id").count()._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Bucketed: true" in plan
    where = got.select("id", F.pmod(F.hash("id"), F.lit(5)).alias("b")).distinct().toPandas()
    assert (store.bucket_of(where["id"].to_numpy(), 5) == where["b"]).all()


@pytest.mark.parametrize("name", ["score_jaccard", "score_containment", "score_dice_cosine"])
def test_pairs_in_batches_of_queries(spark, sf, monkeypatch, name):
    """However many entries the queries have, a batch is broadcast at once and no entry is sent; the pairs are the same."""
    want = sorted(map(tuple, QUERIES[name](spark, sf).collect()))
    most, broadcast = [], F.broadcast

    def counted(df):
        if "numbers" in df.columns:
            most.append(df.select(F.explode("numbers")).count())
        return broadcast(df)

    monkeypatch.setattr(search, "SMALL_ENTRIES", 300)
    monkeypatch.setattr(F, "broadcast", counted)
    got = QUERIES[name](spark, sf)
    assert sorted(map(tuple, got.collect())) == want
    assert len(most) > 1 and max(most) < 2 * 300


def test_stored_slices_are_the_slices(spark, sf):
    c = Corpus(spark, sf)
    assert sorted(map(tuple, c.all.collect())) == sorted(map(tuple, extract.slice_entries(spark, sf).collect()))


@pytest.mark.parametrize("name", ["accuracy_fbeta", "accuracy_precision", "accuracy_recall", "empty_answer_share"])
def test_accuracy_sends_numbers(spark, sf, name):
    """Answers and truth are compared on stored ids: no domain or query is sent by name."""
    plan = QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    sent = [c for x in re.findall(r"Exchange hashpartitioning\((.*?), \d+\)", plan) for c in x.split(", ")]
    assert any(c.startswith("domain_id#") for c in sent) and "Bucketed: true" in plan
    assert all(c.endswith("L") for c in sent if c.startswith(("domain_id#", "query_id#")))


def test_lateral_limit_orders_its_window(spark, sf):
    """Rows of a customer are ranked by the window's own order, whatever order a shuffle delivers them in."""
    df = QUERIES["join_lateral"](spark, sf)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert re.search(r"row_number\(\) windowspecdefinition\(o_custkey#\d+L, o_totalprice#\d+ DESC NULLS LAST, o_orderkey#\d+L ASC NULLS LAST", plan)
    orders = {}
    for r in spark.read.parquet(f"{sf}/orders.parquet").select("o_custkey", "o_totalprice", "o_orderkey").collect():
        orders.setdefault(r[0], []).append((-r[1], r[2]))
    keys = [r["c_custkey"] for r in spark.read.parquet(f"{sf}/customer.parquet").collect()]
    assert sorted(map(tuple, df.collect())) == sorted((c, o) for c in keys for _, o in sorted(orders.get(c, []))[:2])
