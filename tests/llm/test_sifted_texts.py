"""op10: texts without a shared bucket are not shuffled, and the sieve before the exact join loses no row."""

import random

from hopwise.llm import near_duplicates as N
from hopwise.llm.near_duplicates import near_duplicates, sifted
from hopwise.operators.measures import shuffled_bytes


def test_only_texts_of_shared_buckets_move(spark):
    rng = random.Random(51)
    text = lambda: " ".join("".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=7)) for _ in range(15000))
    texts = [text() for _ in range(40)]
    rows = [*enumerate(texts), (900, texts[0] + " more"), (901, texts[1]), (902, None), (903, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        before = shuffled_bytes(spark)
        found = {r["doc_id"]: r["class_id"] for r in near_duplicates(docs).collect()}
        moved = shuffled_bytes(spark) - before
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert found == {i: i for i in range(40)} | {900: 0, 901: 1, 902: 902, 903: 902}
    assert moved < sum(map(len, texts)) / 2, moved


def test_a_sieve_loses_no_row(spark):
    rows = spark.createDataFrame([(str(i % 3000).encode(), i) for i in range(6000)], "node binary, n int")
    wanted = rows.where("n % 7 = 0 and n < 3000").select("node")
    want = {(bytes(r["node"]), r["n"]) for r in rows.join(wanted, "node", "left_semi").collect()}
    for most in (1 << 20, 1):
        found = [(bytes(r["node"]), r["n"]) for r in sifted(rows, wanted, most=most).collect()]
        assert len(found) == len(set(found)) and want <= set(found)
        assert most == 1 or len(found) < len(want) + 400
    assert sifted(rows, wanted.where("false")).count() == 0


def test_texts_are_dealt_once(spark, monkeypatch):
    """Copies stay where they are, and a node's text moves once: to the join, and no further to be made one row."""
    plans, own, sift, kept = [], N.written, N.sifted, []
    monkeypatch.setattr(N, "written", lambda df, name: (name == "texts" and plans.append(df._jdf.queryExecution().executedPlan().toString())) or own(df, name))
    monkeypatch.setattr(N, "sifted", lambda *a, **k: kept.append(sift(*a, **k)) or kept[-1])
    body = " ".join(f"w{i}" for i in range(90))
    rows = [(i, body) for i in range(50)] + [(50, body + " more"), (50, body + " more"), (None, body + " end"), (None, None), (60, "quite different words are in this text alone")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        found = N.near_duplicates(docs).select("doc_id", "class_id").collect()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert len(found) == len(rows) and sum(r["class_id"] == 0 for r in found) == 53
    assert kept[0].count() <= 8  # one row of 50 copies, the repeated row twice
    moved = [x for x in plans[0].splitlines() if "Exchange hashpartitioning(node" in x]
    assert 1 <= len(moved) <= 2  # the texts, and the keys they are joined to
