"""Op 10 where one passage puts texts of several classes into the same buckets."""

import random

from hopwise.llm import near_duplicates as nd


def test_common_passage_loses_no_link(spark):
    draw = random.Random(5)
    word = lambda: f"w{draw.randrange(10**6)}"
    passage = [word() for _ in range(120)]
    texts = []
    for i in range(70):  # like one another at 0.6 to 0.9, by the words each changes
        mine = passage + [word() for _ in range(10)]
        for _ in range(draw.randrange(4)):
            mine[draw.randrange(120)] = word()
        texts.append((i, " ".join(mine)))
    for i in range(70, 100):  # half of it is their own
        texts.append((i, " ".join(passage + [word() for _ in range(70)])))
    sets = {i: nd.elements_of(t, nd._Bytes()) for i, t in texts}
    root = {i: i for i in sets}

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for a in sets:
        for b in sets:
            if a < b and nd.jaccard(sets[a], sets[b]) >= 0.8:
                x, y = sorted((top(a), top(b)))
                root[y] = x
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    got = {r["doc_id"]: r["class_id"] for r in nd.near_duplicates(docs).collect()}
    assert got == {i: top(i) for i in sets}
    assert 1 < len(set(got.values())) < 100
    # the second stage by itself, from one bucket that holds everything
    rows = docs.select("doc_id", nd.node_of().alias("node"), "text")
    members = rows.selectExpr("0L as bucket", "node")
    roots = nd.rooted(rows.select("doc_id", "node"), nd.links(members, rows.select("node", "text"), 0.8, small=4, rounds=2))
    by_root = {}
    for r in roots.collect():
        by_root.setdefault(bytes(r["root"]), set()).add(r["doc_id"])
    assert {min(x) for x in by_root.values()} == set(got.values())
