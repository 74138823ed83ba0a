"""Graphs whose edges are joined and made distinct once, and indexes that take their records and cohorts from the broadcast graph."""

import pytest
from test_findings_r02 import SF, random_pairs
from test_hopwise import graph

from hopwise import catalog
from hopwise.operators import cohorts as C
from hopwise.operators import compact as K
from hopwise.operators import search as S
from hopwise.sources import graphs as G

PAIRS = [*random_pairs(51, 150, 260), *((1000 + i, 1001 + i) for i in range(9)), *((3, i) for i in range(2000, 3100))]


@pytest.fixture(scope="module")
def case(spark):
    return graph(spark, PAIRS)


def plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_a_graph_reads_its_tables_once(spark):
    """both orientations of an undirected edge come of one join and one distinct row."""
    assert plan(G.customer_part(spark, SF).edges).count("Join") == 1
    assert plan(G.copurchase(spark, SF).edges).count("Join") == 1
    both = graph(spark, [(1, 2), (2, 1), (2, 2), (2, 3), (2, 3)])
    assert sorted(map(tuple, both.edges.collect())) == [(1, 2), (2, 1), (2, 3), (3, 2)] and both.size == 4
    one = graph(spark, [(1, 2), (2, 1), (2, 2), (2, 3), (2, 3)], True)
    assert sorted(map(tuple, one.edges.collect())) == [(1, 2), (2, 1), (2, 3)] and one.size == 3
    kept = G.HopGraph(both.edges).cached()
    assert sorted(kept.edges.collect()) == sorted(both.edges.collect()) and kept.size == 4


@pytest.mark.parametrize("d", [0, 1, 2, 3, 4, 6])
def test_records_of_a_broadcast_sweep(spark, case, d):
    """the task that sweeps puts the records together; the same as those of arrivals, also of members without an edge."""
    near = C.pick_cohorts(case, 3, 64, d).select("cid", "bit", "s")
    more = [(7, b, s) for b, s in enumerate((1000, 1001))] + [(8, 0, 5555), (8, 5, 5555), (8, 63, 5556)] + [(9, b, 40 + b) for b in range(70)]
    cohorts = near.unionByName(spark.createDataFrame(more, "cid int, bit int, s long"))
    rows = lambda joined: sorted(tuple(r) for r in S.cluster_sweep(case, cohorts, d, "broadcast", joined=joined).select("v", "cid", "word", "base", "m").collect())
    plain = sorted(tuple(r) for r in S.records(S.cluster_sweep(case, cohorts, d), d).select("v", "cid", "word", "base", "m").collect())
    assert rows(True) == plain
    with pytest.raises(ValueError):
        S.cluster_sweep(case, cohorts, None, "broadcast", joined=True)


@pytest.mark.parametrize(("r", "w", "d"), [(1, 1, 2), (5, 16, 2), (3, 64, 4), (20, 8, 3), (4, 8, 0), (400, 64, 2)])
def test_cohorts_on_the_broadcast_graph(spark, case, r, w, d):
    """chosen by the driver on the edges it broadcast, as chosen by jobs."""
    fresh = graph(spark, PAIRS)
    by_jobs = C.pick_cohorts(fresh, r, w, d).collect()
    K.compact(case)
    assert K.held(case) is not None and K.held(fresh) is None
    assert C.pick_cohorts(case, r, w, d).collect() == by_jobs


def no_jobs_for_cohorts(monkeypatch):
    asked, own = [], C.balls
    monkeypatch.setattr(C, "balls", lambda *a: asked.append(a) or own(*a))
    return asked


def test_diameters_choose_cohorts_without_jobs(spark, monkeypatch):
    asked = no_jobs_for_cohorts(monkeypatch)
    assert catalog.QUERIES["landmark_diameter_eps"](spark, SF).count() == 3 and not asked


@pytest.mark.parametrize("name", ["landmark_distortion_profile", "landmark_exact_hits"])
def test_graded_queries_search_truths_first(spark, name, monkeypatch):
    """the graph is broadcast for the truths before cohorts are chosen on it."""
    asked = no_jobs_for_cohorts(monkeypatch)
    assert catalog.QUERIES[name](spark, SF).count() > 0 and not asked
