"""Queries over whole tables against brute force: no sample, no range of ids, no family."""

import hashlib

import pytest
from pyspark.sql import functions as F

from domsearch.operators import extract, search
from domsearch.plans.catalog import QUERIES


def asked(key):
    return int(hashlib.md5(key.encode()).hexdigest()[:15], 16) % 20 == 0


@pytest.fixture(scope="module")
def sets(spark, sf):
    rows = extract.slice_entries(spark, sf).groupBy("domain_id").agg(F.collect_set("value")).collect()
    return {k: set(v) for k, v in rows if len(v) >= 10}


def test_queries_grow_with_the_table(spark):
    for n in (2_000, 6_000):
        domains = spark.range(n).select(F.concat(F.lit("d:"), F.col("id").cast("string")).alias("domain_id"), F.lit(10).alias("size"))
        got = [r["query_id"] for r in search.query_sample(domains, None).collect()]
        assert sorted(got) == sorted(k for k in (f"d:{i}" for i in range(n)) if asked(k))
        assert len(got) > 50


def test_whole_containment_search(spark, sf, sets):
    want = {(a, b): len(sets[a] & sets[b]) / len(sets[a]) for a in sets if asked(a) for b in sets}
    want = {k: t for k, t in want.items() if t >= 0.5}
    got = {(r["query_id"], r["domain_id"]): r["t"] for r in QUERIES["exact_containment_search"](spark, sf).collect()}
    assert got == pytest.approx(want, abs=1e-6)


def test_sketches_meet_all_domains(spark, sf, sets):
    got = {(r["query_id"], r["domain_id"]) for r in QUERIES["jaccard_estimates"](spark, sf).collect()}
    assert got == {(a, b) for a in sets if asked(a) for b in sets if a != b}


def test_no_query_stands_beside_a_whole_one():
    assert not [n for n in QUERIES if n.startswith("whole_")]


def test_near_copies_of_all_documents(spark, tmp_path):
    """Each asked document has a copy with two words in twenty changed and one with six."""
    rows = []
    for i in range(0, 3_000, 20):
        words = [f"w{i}x{j}" for j in range(16)] + ["the", "of", "and", "to"]
        rows += [(i, " ".join(words)), (i + 1, " ".join(words[2:] + ["new", "words"])), (i + 2, " ".join(words[6:] + [f"n{j}" for j in range(6)])), (i + 3, " ".join(words[1:]))]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    sets = {k: set(t.split()) for k, t in rows}
    near = lambda x, y: len(x & y) / max(len(x), len(y)) >= 0.8
    want = {(a, a + j, len(sets[a] & sets[a + j])) for a in range(0, 3_000, 20) for j in (1, 2, 3) if near(sets[a], sets[a + j])}
    assert len(want) == 300
    assert {tuple(r) for r in QUERIES["near_copies"](spark, str(tmp_path)).collect()} == want


def test_near_copies_of_given_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", F.expr(r"array_distinct(split(lower(text), '\\s+'))").alias("w")).collect()
    sets = {k: set(w) for k, w in docs}
    want = {(a, b, len(sets[a] & sets[b])) for a in sets if a % 20 == 0 for b in sets if a != b and len(sets[a] & sets[b]) / max(len(sets[a]), len(sets[b])) >= 0.8}
    assert {tuple(r) for r in QUERIES["near_copies"](spark, sf).collect()} == want


def test_all_orders_and_customers(spark):
    sf = "/root/testdata/sf0.01"
    lines, orders = (spark.read.parquet(f"{sf}/{n}.parquet") for n in ("lineitem", "orders"))
    keys = ("l_orderkey", "l_linenumber")
    assert sorted(QUERIES["project_exprs"](spark, sf).select(*keys).collect()) == sorted(lines.select(*keys).collect())
    best = {}
    for c, o, total in sorted(orders.select("o_custkey", "o_orderkey", "o_totalprice").collect(), key=lambda r: (r[0], -r[2], r[1])):
        best.setdefault(c, []).append(o)
    assert max(best) >= 300
    assert {tuple(r) for r in QUERIES["join_lateral"](spark, sf).collect()} == {(c, o) for c, os in best.items() for o in os[:2]}


def test_all_items_and_conversations(spark, sf):
    def sets_of(name, key):
        out = {}
        for k, w in spark.read.parquet(f"{sf}/{name}.parquet").select(key, F.expr(r"split(lower(text), '\\s+')")).collect():
            out.setdefault(k, set()).update(w)
        return out

    items, talks, docs = sets_of("benchmark", "item_id"), sets_of("conversations", "conv_id"), sets_of("documents", "doc_id")
    want = {(a, b, len(items[a] & items[b])) for a in items for b in items if a != b and items[a] & items[b]}
    assert {tuple(r)[:3] for r in QUERIES["fn_array_sets"](spark, sf).select("a", "b", "n").collect()} == want
    want = {(c, d) for c in talks if c % 20 == 0 for d in docs if len(talks[c] & docs[d]) / len(talks[c]) >= 0.5}
    assert {tuple(r)[:2] for r in QUERIES["conversation_search"](spark, sf).select("conv_id", "doc_id").collect()} == want


def test_all_families(spark, sf, sets):
    overlaps = {(a, b, len(sets[a] & sets[b])) for a in sets if asked(a) for b in sets if sets[a] & sets[b]}
    assert {tuple(r) for r in QUERIES["cogroup_verify"](spark, sf).select("query_id", "domain_id", "overlap").collect()} == overlaps
    signed = {n: sorted(tuple(r) for r in QUERIES[n](spark, sf).select("domain_id", "sig").collect()) for n in ("udaf_minhash", "map_in_arrow_signatures")}
    assert signed["udaf_minhash"] == signed["map_in_arrow_signatures"] and {r[0] for r in signed["udaf_minhash"]} == set(sets)
    assert {(r["domain_id"], r["band"]) for r in QUERIES["udtf_band_keys"](spark, sf).collect()} == {(k, b) for k in sets for b in (0, 1)}
    found = {(r["query_id"], r["domain_id"]) for r in QUERIES["padded_minhash"](spark, sf).collect()}
    assert {a for a, _ in found} <= {k for k in sets if asked(k)} and any(not a.startswith("part_by_supp") for a, _ in found)


def test_large_queries_are_all_asked(spark, sf, sets):
    sizes = extract.sizes(extract.slice_entries(spark, sf))
    high = sizes.select(F.percentile("size", F.lit(0.9))).first()[0]
    assert {r["query_id"] for r in search.query_sample(sizes.where(f"size >= {high}"), None, 1).collect()} == {k for k, v in sets.items() if len(v) >= high}
