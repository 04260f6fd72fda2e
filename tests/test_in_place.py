"""Searches by stored numbers: keys and values are compared in the tasks that hold the domains."""

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from domsearch.functions import minhash
from domsearch.functions.hashing import Native, Portable
from domsearch.operators import extract, lsh, pairwise, search, spci
from domsearch.plans.catalog import QUERIES
from domsearch.plans.methods import Corpus


def rows(df):
    return sorted(map(tuple, df.collect()))


def sent(df):
    """Columns by which a plan's rows are dealt out; those of the histogram of sizes are the partitions' own."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return {c.split("#")[0] for x in re.findall(r"Exchange hashpartitioning\((.*?), \d+\)", plan) for c in x.split(", ")}


def test_native_sketch(spark, monkeypatch):
    """Signatures by numpy are those of Spark's own hashes, for numbers of every length and sign."""
    rng = np.random.default_rng(3)
    each = np.unique(np.concatenate([s * rng.integers(0, 10**k, 30) for k in range(1, 19) for s in (1, -1)] + [np.array([-(2**63), 2**63 - 1])]))
    starts = np.arange(0, len(each), 7)
    got = minhash.native_sketch(70)(each, starts)
    monkeypatch.setattr(minhash, "CACHED", 10)  # sets that lie across blocks
    assert (minhash.native_sketch(70)(each, starts) == got).all()
    monkeypatch.setattr(minhash, "REPEATED", 0)  # every distinct value hashed once
    assert (minhash.native_sketch(70)(each, starts) == got).all()
    ids = np.searchsorted(starts, np.arange(len(each)), "right") - 1
    entries = spark.createDataFrame(list(zip(ids.tolist(), each.tolist(), strict=True)), "domain_id long, value long")
    want = {r["domain_id"]: r["sig"] for r in minhash.signatures(entries, Native(70)).collect()}
    assert got.shape == (len(want), 70) and all(got[k].tolist() == sig for k, sig in want.items())


def test_native_search_by_numbers(spark, sf):
    """spci_native gives the rows of bucket rows under names, derives no bucket row and sends no signature."""
    c = Corpus(spark, sf)
    signed = c.sketches(Native(256))
    want = rows(spci.search(spci.build(signed, 32, 256, native=True), c.queries, [0.5]))
    got = QUERIES["spci_native"](spark, sf)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "bucket#" not in plan and sent(got) <= {"size", "part_id"}
    assert rows(got) == want


@pytest.mark.parametrize("layout", ["free", (16, 4)])
@pytest.mark.parametrize("prune", [True, False])
def test_probe_in_place_is_the_probe_of_buckets(spark, sf, monkeypatch, layout, prune):
    """Several thresholds, batches of queries and blocks of domains and pairs: the rows that bucket keys give."""
    c = Corpus(spark, sf)
    sets = c.whole.select("domain_id", "size", F.col("sig").cast("array<bigint>").alias("sig"))
    at = [0.1, 0.5, 0.8]
    want = rows(spci.search(spci.build(extract.labelled(sets, c.name), 8, 64, layout=layout), c.queries, at, prune))
    index, asked = spci.build(sets, 8, 64, layout=layout), c.asked(sets)
    assert rows(c.named(spci.search(index, asked, at, prune))) == want
    monkeypatch.setattr(lsh, "SMALL_SIGNS", 640)
    monkeypatch.setattr(lsh, "HELD_SIGNS", 6_400)
    monkeypatch.setattr(lsh, "MET", 5)
    assert rows(c.named(spci.search(index, asked, at, prune))) == want


def test_refined_where_the_sets_lie(spark, sf, monkeypatch):
    """Candidates are compared on the spot: neither entries nor candidates are sent, and the rows are those of joined entries."""
    c = Corpus(spark, sf)
    index = spci.build(c.sketches(Portable(64)), 8, 64)
    want = rows(spci.refine_exact(spci.search(index, c.queries, [0.5]), c.entries, c.queries))
    got = QUERIES["spci_refined"](spark, sf)
    assert sent(got) <= {"size", "part_id"}
    assert want and rows(got) == want
    asked, whole = c.asked(c.whole), spci.build(c.whole, 8, 64)
    joined = rows(c.named(spci.search(whole, asked, [0.2, 0.5], refine="exact", entries=c.stored)))
    monkeypatch.setattr(search, "SMALL_ENTRIES", 300)
    monkeypatch.setattr(pairwise, "CELLS", 50)
    assert rows(c.named(spci.search(whole, asked, [0.2, 0.5], refine="exact"))) == joined
    with pytest.raises(ValueError, match="entries"):
        spci.search(index, c.queries, [0.5], refine="exact")
