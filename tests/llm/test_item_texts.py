"""Benchmark rows that share an item_id and differ in text."""

from domsearch.llm.decontamination import decontaminate, find_contained


def test_every_text_of_an_item_is_looked_for(spark):
    texts = [" ".join(f"{c}{k}" for k in range(n)) for c, n in (("a", 30), ("b", 12), ("c", 3), ("d", 20))]
    items = spark.createDataFrame([(7, t) for t in texts] + [(7, texts[0]), (8, texts[3])], "item_id long, text string")
    docs = [(k, f"x y z {t} u v w") for k, t in enumerate(texts)] + [(4, f"{texts[1]} and {texts[0]}"), (5, "nothing of it")]
    docs = spark.createDataFrame(docs, "doc_id long, text string")
    got = {tuple(r) for r in find_contained(docs, items).collect()}
    assert got == {(0, 7, 26, 26, 1.0), (1, 7, 8, 8, 1.0), (2, 7, 1, 1, 1.0), (3, 7, 16, 16, 1.0), (3, 8, 16, 16, 1.0), (4, 7, 26, 26, 1.0)}
    assert [r["doc_id"] for r in decontaminate(docs, items).collect()] == [5]
