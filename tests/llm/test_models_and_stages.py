"""The ordinal model against differences and enumeration, quotas of the mix against its tree, stages on untidy rows."""

import collections

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_operators import make_docs


def test_ordinal_gradient():
    from domsearch.llm.toxicity import ordinal_gradient

    rng = np.random.default_rng(5)
    x, y = rng.standard_normal((40, 6)), rng.integers(0, 4, 40)
    params = [rng.standard_normal(6), np.array(-0.4), rng.standard_normal(2) * 0.3]
    _, grads = ordinal_gradient(*params, x, y, 1.0)
    for k, g in enumerate(grads):
        for j in range(np.size(params[k])):
            ends = []
            for step in (1e-5, -1e-5):
                moved = [np.array(p, float) for p in params]
                moved[k].reshape(-1)[j] += step
                ends.append(ordinal_gradient(*moved, x, y, 1.0)[0])
            assert np.reshape(g, -1)[j] == pytest.approx((ends[0] - ends[1]) / 2e-5, abs=1e-6)


def test_ordinal_chances_and_scores(spark):
    """Scores of the operator against the formula, row by row, from counts taken another way."""
    import math
    import re

    from domsearch.llm.toxicity import ToxicityModel, features_of

    names = ["=vile", "^vil", "=awful", "=calm", "^cal"]
    model = ToxicityModel(names, 3, np.array([0.7, 0.2, 1.1, -0.9, -0.3, 0.5, 0.1]), np.array([0.5, 1.5, 2.5]))
    texts = [None, "", "vile vile Awful villain", "calm calmly and awful", "nothing " * 2000, "VILE-vile! awful\n" * 500]
    got = {r["doc_id"]: r for r in model.score(make_docs(spark, [(k, t, "a") for k, t in enumerate(texts)] + [(2, texts[2], "b")])).collect()}
    for k, text in enumerate(texts):
        words = re.findall(r"[^\W\d_]+", (text or "").lower())
        counts = [sum(features_of(w).count(f) for w in words) for f in names]
        hits = sum(bool(set(features_of(w)) & set(names[:3])) for w in words)
        x = [math.log1p(c) for c in counts] + ([math.log1p(hits), math.log1p(1000 * hits / max(len(words), 1))] if any(counts) else [0, 0])
        z = sum(a * b for a, b in zip(x, model.weights))
        below = [0, *(1 / (1 + math.exp(z - t)) for t in model.thresholds), 1]
        p = [b - a for a, b in zip(below, below[1:])]
        assert got[k]["severity"] == pytest.approx(sum(g * v for g, v in enumerate(p)), abs=1e-9)
        assert got[k]["chance"] == pytest.approx(1 - p[0], abs=1e-9) and got[k]["grade"] == int(np.argmax(p)) and got[k]["toxic"] == (1 - p[0] >= 0.5)


def test_shards_have_the_quotas_of_the_tree(spark):
    from domsearch.llm.source_mix import mix_sources, splitting_tree

    rows = [(k, "w " * (1 + k % 7), "abc"[k % 5 % 3]) for k in range(600)]
    draws = mix_sources(make_docs(spark, rows), block_documents=10, shards=4, seed=7).select("source", F.explode("draws").alias("d")).select("source", "d.*").collect()
    blocks = collections.defaultdict(set)
    for r in draws:
        blocks[r["source"], r["shard"]].add((r["pass"], r["block"]))
    quotas = [sum(len(blocks[s, k]) for k in range(4)) for s in "abc"]
    assert [[len(blocks[s, k]) for s in "abc"] for k in range(4)] == splitting_tree(quotas, 4, 7)
    for s in "abc":  # shards are disjoint
        assert sum(len(blocks[s, k]) for k in range(4)) == len(set().union(*(blocks[s, k] for k in range(4))))


def test_many_sources(spark):
    from domsearch.llm.source_mix import mix_sources

    got = mix_sources(make_docs(spark, [(k, "a b c", f"s{k}") for k in range(300)]), shards=2).collect()
    assert len(got) == 300 and all(r["taken"] <= 6 for r in got)


def test_stages_on_untidy_rows(spark, sf):
    """Null and repeated ids are judged row by row; columns, empty texts and empty tables come through."""
    pipeline = pytest.importorskip("corpus_pipeline")
    item = spark.read.parquet(f"{sf}/benchmark.parquet").where("length(text) > 80").first()["text"]
    clean = " ".join(f"plain{k}" for k in range(40))
    secret = "password = hunter2secret"
    rows = [(1, clean, "a"), (1, clean, "a"), (None, clean, "a"), (2, secret, "a"), (2, "all is well here", "a"), (None, secret, "b"), (3, f"x y {item} z", "a"), (3, "", None), (None, f"q {item} r", "a"), (4, None, "a")]
    docs = make_docs(spark, rows)
    got = {n: [(r["doc_id"], r["text"]) for r in stage(spark, docs, sf).collect()] for n, stage in pipeline.STAGES[1:4]}
    kept = [(k, t) for k, t, _ in rows]
    key = lambda rs: sorted(rs, key=repr)
    assert key(got["secret scans"]) == key([r for r in kept if r[1] != secret])
    assert key(got["benchmark decontamination"]) == key([r for r in kept if not r[1] or item not in r[1]])
    left = got["n-gram Jaccard join"]
    assert left.count((1, clean)) == 1 and (None, clean) not in left and left.count((2, secret)) == 1 and (None, secret) not in left
    for name, stage in pipeline.STAGES:
        out = stage(spark, docs, sf)
        empty = stage(spark, docs.limit(0), sf)
        if name != pipeline.STAGES[-1][0]:
            assert out.columns == docs.columns == empty.columns
        assert empty.count() == 0
