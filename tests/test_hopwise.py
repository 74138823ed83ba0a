import random
from collections import deque

import pytest
from pyspark.sql import functions as F

from hopwise.operators import cohorts as C
from hopwise.operators import landmarks as L
from hopwise.operators import measures as M
from hopwise.operators import search as S
from hopwise.operators.twohop import TwoHopIndex, batch_sizes
from hopwise.sources.graphs import HopGraph, from_pairs

EXAMPLE = [(1, 2), (1, 3), (2, 4), (3, 4), (4, 5), (5, 6), (2, 7)]


def graph(spark, pairs, directed=False) -> HopGraph:
    return from_pairs(spark.createDataFrame(pairs, "src long, dst long"), directed).cached()


def truth(pairs, s, directed=False):
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        if not directed:
            near.setdefault(b, set()).add(a)
    dist, todo = {s: 0}, deque([s])
    while todo:
        u = todo.popleft()
        for v in near.get(u, ()):
            if v not in dist:
                dist[v] = dist[u] + 1
                todo.append(v)
    return dist


def cohort(spark, members, cid=0):
    return spark.createDataFrame([(cid, b, s, b == 0) for b, s in enumerate(members)], C.SCHEMA)


def exploded(arrivals, c, d):
    return {(r["s"], r["v"]): r["dist"] for r in S.explode_records(S.records(arrivals, d), c).collect()}


def test_worked_example(spark):
    g, c = graph(spark, EXAMPLE), cohort(spark, [1, 2, 3])
    got = {r["v"]: (r["base"], list(r["m"])) for r in S.records(S.cluster_sweep(g, c, 2), 2).collect()}
    assert got == {1: (0, [1, 6, 0]), 2: (0, [2, 1, 4]), 3: (0, [4, 1, 2]), 4: (1, [6, 1, 0]), 5: (2, [6, 1, 0]), 6: (3, [6, 1, 0]), 7: (1, [2, 1, 4])}


@pytest.mark.parametrize("seed", [0, 1])
def test_sweep_modes_give_all_distances(spark, seed):
    rng = random.Random(seed)
    pairs = [(rng.randrange(60), rng.randrange(60)) for _ in range(110)]
    g = graph(spark, pairs + pairs[:5] + [(3, 3)])
    c = C.pick_cohorts(g, 1, 12, 2)
    members = [r["s"] for r in c.collect()]
    want = {(s, v): d for s in members for v, d in truth(pairs, s).items()}
    for how in ({}, {"mode": "pull"}, {"mode": "auto"}, {"delta": False}):
        arrivals = S.cluster_sweep(g, c, 2, **how)
        assert exploded(arrivals, c, 2) == want, how
    assert arrivals.groupBy("v").count().agg(F.max("count")).first()[0] <= 3
    star = S.star_sweep(g, c)
    assert exploded(star, c, 2) == want
    each = S.bfs_each(g, c.select("s"), "pull")
    assert {(r["s"], r["v"]): r["dist"] for r in each.collect()} == want


def test_wide_and_directed_cohorts(spark):
    pairs = [(i, (i * 7 + 1) % 90) for i in range(90)] + [(i, (i * 5 + 3) % 90) for i in range(90)]
    g = graph(spark, pairs, directed=True)
    c = cohort(spark, list(range(70)))
    long = S.cluster_sweep(g, c, None)
    rows = long.join(c.select("s", (F.col("bit") % 64).alias("b"), F.floor(F.col("bit") / 64).cast("int").alias("word")), "word")
    got = {(r["s"], r["v"]): r["round"] for r in rows.where(F.expr("(fresh & shiftleft(1L, cast(b as int))) <> 0")).collect()}
    assert got == {(s, v): d for s in range(70) for v, d in truth(pairs, s, True).items()}


def test_index_and_exact_answers(spark):
    rng = random.Random(5)
    pairs = [(rng.randrange(50), rng.randrange(50)) for _ in range(70)] + [(100, 101)]
    g = graph(spark, pairs)
    sample = L.sample_pairs(g, 150).persist()
    exact = {(r["u"], r["v"]): truth(pairs, r["u"]).get(r["v"]) for r in sample.collect()}
    by = {r["pid"]: (r["u"], r["v"]) for r in sample.collect()}
    c = C.pick_cohorts(g, 2, 8, 2)
    members = [r["s"] for r in c.collect()]
    best = {k: min((truth(pairs, h)[k[0]] + truth(pairs, h)[k[1]] for h in members if k[0] in truth(pairs, h) and k[1] in truth(pairs, h)), default=None) for k in exact}
    for encoding in L.ENCODINGS:
        got = {by[r["pid"]]: r["est"] for r in L.LandmarkIndex.build(g, c, 2, encoding).query(sample).collect()}
        assert got == best, encoding
    for r in (0, 1):
        got = {(x["u"], x["v"]): x["est"] for x in TwoHopIndex.build(g, r, 8, first=12).query(sample).collect()}
        assert got == exact
    met = {by[r["pid"]]: r["est"] for r in L.local_meet(g, sample, 1000).collect()}
    assert met == exact
    assert all(met[k] is None or best[k] is None or met[k] <= best[k] for k in met)


def test_budgets_batches_and_measures(spark):
    assert [C.clusters_for_budget(1024, w) for w in (1, 64, 32, 16, 8)] == [1024, 60, 113, 204, 341]
    assert (C.clusters_for_budget(1024, 64, 3), C.clusters_for_budget(1024, 64, 4)) == (40, 31)
    assert batch_sizes(2000) == [200, 300, 450, 675, 375]
    a = spark.createDataFrame([(1, 2), (2, 3), (3, None)], "pid long, est int")
    t = spark.createDataFrame([(1, 2), (2, 2), (3, 4)], "pid long, truth int")
    assert tuple(M.mean_excess(a, t).first()) == (2, 0.25, 1, 1.5)
    assert M.geo_mean([2, 8]) == pytest.approx(4)


def test_registered_queries_have_oracles():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
