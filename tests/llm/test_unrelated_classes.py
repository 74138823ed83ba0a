"""Unrelated texts under a null id or one repeated id are classes of their own."""

import random

from hopwise.llm import near_duplicates as nd


def test_each_class_keeps_one_row(spark):
    draw = random.Random(3)
    text = lambda: " ".join(f"u{draw.randrange(10**6)}" for _ in range(60))
    a, b, c, d = text(), text(), text(), text()
    docs = [(None, a), (None, b), (7, c), (7, d), (None, a), (7, c), (8, c + " tail")]
    rows = nd.first_documents(spark.createDataFrame(docs, "doc_id long, text string")).collect()
    assert sorted((r["doc_id"] or 0, r["text"]) for r in rows) == sorted([(0, a), (0, b), (7, c), (7, d)])
