"""The index against exact search: invariants, trends and maintenance."""

import pytest
from pyspark.sql import functions as F

from domsearch.functions.hashing import PRIME, Portable
from domsearch.functions.minhash import signatures
from domsearch.operators import extract, padded, partition, search, spci, stats
from domsearch.plans import methods, workloads
from domsearch.plans.methods import Corpus
from domsearch.store import fresh, materialise


@pytest.fixture(scope="module")
def corpus(spark, sf):
    c = Corpus(spark, sf, k=30)
    bench = workloads.Bench(spark, sf, "slices", k=30)
    bench.entries = materialise(c.entries, "entries")
    return bench


def rows(df, *columns):
    return {tuple(r) for r in df.select(*columns).collect()}


def test_worked_example(spark):
    got = {r["domain_id"]: (r["t"], r["s"]) for r in methods.worked_example(spark).collect()}
    assert got["provinces"] == (0.5, 0.25)
    assert got["locations"] == (1.0, pytest.approx(1 / 6, abs=1e-6))


def test_ideal_filter_loses_nothing(corpus):
    for n in (1, 4, 32):
        for make in (partition.equi_depth, partition.equi_width, partition.equi_m):
            assigned = partition.assign(corpus.sizes, make(stats.histogram(corpus.sizes), n))
            assert assigned.count() == corpus.sizes.count()
            for t in (0.2, 0.6, 1.0):
                truth = rows(search.exact(corpus.pairs, t), "query_id", "domain_id")
                assert truth <= rows(search.ideal_filter(corpus.pairs, assigned, t), "query_id", "domain_id")


def test_more_partitions_fewer_false_candidates(corpus):
    index = {n: spci.build(corpus.signed, n, corpus.m) for n in (1, 8, 32)}
    truth = rows(search.exact(corpus.pairs, 0.5), "query_id", "domain_id")
    size, recall = {}, {}
    for n, i in index.items():
        found = rows(spci.search(i, corpus.queries, [0.5]), "query_id", "domain_id")
        size[n], recall[n] = len(found), len(found & truth) / len(truth)
    assert size[32] < size[8] < size[1]
    assert recall[1] > 0.7 and recall[32] > 0.5
    every = {tuple(r) for r in corpus.queries.select("query_id", F.col("query_id").alias("domain_id")).collect()}
    assert every <= rows(spci.search(index[8], corpus.queries, [0.5]), "query_id", "domain_id")


def test_pruning_shards_and_storage_change_no_answer(spark, corpus):
    index = spci.build(corpus.signed, 8, corpus.m)
    plain = rows(spci.search(index, corpus.queries, [0.5]), "query_id", "domain_id")
    shards = spci.build_shards(corpus.signed, 5, 8, corpus.m)
    assert sum(s.signatures.count() for s in shards) == corpus.signed.count() and all(s.meta.count() <= 8 for s in shards)
    asked = corpus.signed.join(corpus.queries, F.col("domain_id") == F.col("query_id")).select("query_id", "q", "sig")
    found = spci.search_shards(shards, asked, [0.5])
    assert found.where(spci.shard_of("domain_id", 5) != F.col("shard_id")).count() == 0
    right = rows(search.exact(corpus.pairs, 0.5), "query_id", "domain_id")
    assert len(rows(found, "query_id", "domain_id") & right) >= 0.9 * len(plain & right)
    truth = rows(search.exact(corpus.pairs, 0.9), "query_id", "domain_id")
    free, pruned = (rows(spci.search(index, corpus.queries, [0.9], prune), "query_id", "domain_id") for prune in (False, True))
    assert pruned <= free and pruned & truth == free & truth
    path = fresh(spark, "index")
    spci.save(index, path, (0.5,))
    assert rows(spci.search(spci.load(spark, path), corpus.queries, [0.5]), "query_id", "domain_id") == plain
    exact = rows(spci.search(index, corpus.queries, [0.5], refine="exact", entries=corpus.entries), "query_id", "domain_id")
    assert exact == plain & rows(search.exact(corpus.pairs, 0.5), "query_id", "domain_id")


def test_insert_keeps_all_domains(corpus):
    early = corpus.signed.where(F.pmod(F.xxhash64("domain_id"), F.lit(10)) < 6)
    late = corpus.signed.where(F.pmod(F.xxhash64("domain_id"), F.lit(10)) >= 6)
    index = spci.insert(spci.build(early, 8, corpus.m), late)
    assert index.signatures.count() == corpus.signed.count() == index.meta.agg(F.sum("n_domains")).first()[0]
    assert index.signatures.where("size > part_size_max").count() == 0
    assert not spci.needs_rebuild(index)


def test_padding_hurts_recall_on_skewed_sizes(corpus):
    got = {(r["index_id"], r["t_star"]): r for r in corpus.sweep([workloads.SPECS[0], workloads.SPECS[1]], [0.3, 0.9]).collect()}
    assert got["padded", 0.9]["recall"] < got["minhash_lsh", 0.9]["recall"]


def test_simulated_padding_has_the_right_distribution(spark):
    entries = spark.createDataFrame([(f"d{k}", f"{k}-{v}") for k in range(60) for v in range(20)], "domain_id string, value string")
    signed = signatures(entries, Portable(64))
    fast = padded.padded_signatures(signed, F.lit(200)).select(F.explode("sig").alias("v")).agg(F.avg("v")).first()[0]
    assert fast == pytest.approx(PRIME / 201, rel=0.1)
    sizes = extract.sizes(entries)
    most = spark.createDataFrame([(200,)], "m long")
    literal = signatures(padded.pad_entries(entries, sizes, most), Portable(64)).select(F.explode("sig").alias("v")).agg(F.avg("v")).first()[0]
    assert fast == pytest.approx(literal, rel=0.1)


def test_precision_rises_with_partitions(corpus):
    got = {r["index_id"]: r["precision"] for r in corpus.sweep([s for s in workloads.SPECS if not s[2]], [0.5]).collect()}
    assert got["minhash_lsh"] <= got["spci_n8"] <= got["spci_n32"]


def test_empty_collection(spark):
    empty = spark.createDataFrame([], "domain_id string, value string")
    signed = signatures(empty, Portable(16))
    index = spci.build(signed, 8, 16)
    qs = search.query_sample(signed.select("domain_id", "size"), 5)
    assert spci.search(index, qs, [0.5]).count() == 0
    assert spci.search(spci.stored(index, [0.5]), qs, [0.5]).count() == 0
    assert search.exact(search.overlaps(empty, extract.sizes(empty), qs), 0.5).count() == 0
