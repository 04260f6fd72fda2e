"""Words that a polynomial hash confuses, repeated and conflicting ids, hot anchors."""

import random

import pytest
from test_operators import components, make_docs, removed


def thue_morse(n):
    out = "a"
    while len(out) < n:
        out += out.translate(str.maketrans("ab", "ba"))
    return out


A = thue_morse(1024)
B = A.translate(str.maketrans("ab", "ba"))


def test_words_that_modular_polynomials_confuse(spark):
    from domsearch.llm.ngram_join import jaccard_components
    from domsearch.llm.substring_dedup import dedup_substrings

    for n in (8, 16, 64, 65, 1024):
        got = {r[0]: r[2] for r in jaccard_components(make_docs(spark, [(1, A[:n], "a"), (2, B[:n], "a"), (3, A[:n], "a")])).collect()}
        assert got == {1: 1, 2: 2, 3: 1}
    words = [f"w{k}" for k in range(19)]
    rows = [(1, " ".join([A, *words]), "a"), (2, " ".join([B, *words]), "a"), (3, " ".join([A, *words]), "a")]
    assert {r[0]: tuple(r[1:4]) for r in dedup_substrings(make_docs(spark, rows), shares=()).collect()} == removed(rows)


@pytest.mark.parametrize("words", [["a", "b"], ["xyzxyzxyz", "pqrpqrpqr"]])
def test_sequences_that_modular_polynomials_confuse(spark, words):
    from domsearch.llm.substring_dedup import dedup_substrings

    one, two = (" ".join(words["ab".index(c)] for c in text[:256]) for text in (A, B))
    rows = [(1, one, "a"), (2, two, "a"), (3, one + " end", "a")]
    assert {r[0]: tuple(r[1:4]) for r in dedup_substrings(make_docs(spark, rows), shares=()).collect()} == removed(rows)


def test_repeated_and_conflicting_ids(spark):
    from domsearch.llm.ngram_join import jaccard_components

    draw = random.Random(2)
    text = lambda n: " ".join(f"w{draw.randrange(500)}" for _ in range(n))
    a, b, c = text(60), text(80), text(30)
    rows = [(4, "x y z", "a"), (4, "x y z", "a"), (7, a, "a"), (7, b, "a"), (3, b, "a"), (9, a + " more", "a"), (5, c, "a"), (6, None, "a"), (6, "", "a"), (6, c, "a"), (8, None, "a"), (8, None, "a")]
    got = {r[0]: (r[1], r[2]) for r in jaccard_components(make_docs(spark, rows)).collect()}
    sizes = {k: components([(1, t, "a")])[1][0] for k, t in (("a", a), ("b", b), ("c", c))}
    assert got == {4: (1, 4), 7: (max(sizes["a"], sizes["b"]), 3), 3: (sizes["b"], 3), 9: (sizes["a"] + 1, 3), 5: (sizes["c"], 5), 6: (sizes["c"], 5), 8: (0, 8)}


def test_a_common_phrase_in_many_contexts(spark, monkeypatch):
    """One phrase in every text, with words of its own around it: its anchors are hot in every block."""
    from domsearch.llm import substring_dedup

    draw = random.Random(4)
    phrase = [f"p{k}" for k in range(24)]
    rows = []
    for k in range(120):
        around = [f"{draw.choice('xyz')}{draw.randrange(4)}" for _ in range(30)]
        rows.append((k, " ".join([*around, *phrase, *(around[::-1] if k % 3 else ["end"] * 6)]), "a"))
    want = removed(rows)
    docs = make_docs(spark, rows).repartition(5)
    for hot in (1, 8):
        monkeypatch.setattr(substring_dedup, "HOT", hot)
        assert {r[0]: tuple(r[1:4]) for r in substring_dedup.dedup_substrings(docs).collect()} == want


def test_an_append_moves_no_history(spark):
    from domsearch.llm.substring_dedup import FingerprintIndex

    index = FingerprintIndex(spark)
    for k in range(2):
        index.append(make_docs(spark, [(10 * k + j, " ".join(f"w{i * j}" for i in range(40)), "a") for j in range(10)]))
    plan = index.merged(make_docs(spark, [(50, "a " * 40, "a")]))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "Bucketed: true" in plan  # the batch's own
    paths = [p for _, p in index.runs]
    index.compact()
    assert len(index.runs) == 1 and not {p for _, p in index.runs} & set(paths)
    jvm = spark.sparkContext._jvm
    for path in paths:
        p = jvm.org.apache.hadoop.fs.Path(path)
        assert not p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)
