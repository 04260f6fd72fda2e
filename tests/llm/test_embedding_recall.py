"""Recall of the sign hashing near the threshold, against all pairs, on a planted table."""

import numpy as np


def test_recall_near_the_threshold(spark):
    """30,400 vectors of one label in clusters of eight whose cosines lie around 0.94: over 50,000 pairs between 0.93 and 0.95."""
    from domsearch.llm.embedding_dedup import THRESHOLD, near_duplicates

    rng = np.random.default_rng(7)
    clusters, members, dimension = 3800, 8, 64
    base = rng.standard_normal((clusters, 1, dimension))
    v = (base + 0.2526 * rng.standard_normal((clusters, members, dimension))).reshape(-1, dimension).astype(np.float32)
    unit = v.astype(np.float64)
    unit /= np.linalg.norm(unit, axis=1, keepdims=True)
    want, near = np.zeros(len(v), np.int64), 0
    for at in range(0, len(v), 2000):
        cosine = unit[at : at + 2000] @ unit.T
        cosine[np.arange(len(cosine)), at + np.arange(len(cosine))] = -1.0
        want[at : at + 2000] = (cosine >= THRESHOLD).sum(axis=1)
        near += int(((cosine >= THRESHOLD) & (cosine < 0.95)).sum()) // 2
    assert near >= 50_000
    rows = spark.createDataFrame([(k, x) for k, x in enumerate(v.tolist())], "vec_id long, embedding array<double>").selectExpr("vec_id", "embedding", "0 as label")
    got = {r["vec_id"]: r["n_links"] for r in near_duplicates(rows).collect()}
    found = np.array([got[k] for k in range(len(v))])
    print(f"pairs {want.sum() // 2}, below 0.95 {near}, found {found.sum() // 2}")
    assert (found <= want).all() and found.sum() >= 0.99 * want.sum()
