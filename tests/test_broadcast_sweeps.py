"""Cohorts swept on a broadcast graph: the arrivals of the sweep by plans, and indexes that use them."""

import pytest
from test_findings_r02 import SF, random_pairs
from test_hopwise import graph

from hopwise import catalog
from hopwise.operators import cohorts as C
from hopwise.operators import compact as K
from hopwise.operators import landmarks as L
from hopwise.operators import search as S
from hopwise.sources import graphs as G


@pytest.fixture(scope="module")
def case(spark):
    return graph(spark, [p for p in random_pairs(41, 140, 200) if p[0] != p[1]] + [(1000 + i, 1001 + i) for i in range(9)])


def rows(df):
    out = [tuple(r) for r in df.select("v", "cid", "word", "round", "fresh").collect()]
    assert len(out) == len(set(out))
    return set(out)


@pytest.mark.parametrize(("d", "stop"), [(2, None), (4, None), (2, 3), (None, None)])
def test_arrivals_of_a_broadcast_sweep(spark, case, d, stop):
    """Cohorts of 64 bits and more (with the sign bit), one far away, one with a member that has no edge."""
    near = C.pick_cohorts(case, 3, 64, 4 if d == 4 else 2).select("cid", "bit", "s")
    more = [(7, b, s) for b, s in enumerate((1000, 1001, 1002))] + [(8, 0, 5555)] + ([(9, b, b) for b in range(130)] if d is None else [])
    cohorts = near.unionByName(spark.createDataFrame(more, "cid int, bit int, s long"))
    assert rows(S.cluster_sweep(case, cohorts, d, "broadcast", stop_after=stop)) == rows(S.cluster_sweep(case, cohorts, d, stop_after=stop))


def test_a_broadcast_sweep_refuses_what_it_has_not(spark, case):
    cohorts = C.pick_cohorts(case, 1, 8)
    for how in ({"delta": False}, {"report": S.Report()}):
        with pytest.raises(ValueError):
            S.cluster_sweep(case, cohorts, 2, "broadcast", **how)
    with pytest.raises(ValueError):
        S.cluster_sweep(graph(spark, [(1, 2)], True), cohorts, 2, "broadcast")


def test_a_graph_above_the_bound_is_pushed_along(spark, case, monkeypatch):
    cohorts, asked = C.pick_cohorts(case, 2, 8), []
    sweep = L.cluster_sweep
    monkeypatch.setattr(L, "cluster_sweep", lambda *a: asked.append(a[3]) or sweep(*a))
    few, many = (L.LandmarkIndex.build(case, cohorts, 2, most_edges=n).table.collect() for n in (10, 10**6))
    assert asked == ["push", "broadcast"] and sorted(few) == sorted(many)


def test_the_cluster_phase_has_no_job_a_round(spark, monkeypatch):
    """cohorts are swept on the broadcast graph that the hubs are searched on; it is collected once."""
    monkeypatch.setattr(S, "RoundLog", None)
    made, sc = [], type(spark.sparkContext)
    broadcast = sc.broadcast
    monkeypatch.setattr(sc, "broadcast", lambda self, x: made.append(len(x)) or broadcast(self, x))
    assert catalog.QUERIES["exact_cluster_phase_query"](spark, SF).count() > 0
    assert made.count(3) == 2  # (ids, starts, heads) and (v, i, cut)


def test_vertices_of_a_kept_graph_are_written_once(spark, monkeypatch):
    """choosing pairs, cohorts and places does not count the degrees of all edges again."""
    made, own = [], G.HopGraph.vertices
    monkeypatch.setattr(G.HopGraph, "vertices", property(lambda g: made.append(g.known is None) or own.fget(g)))
    assert catalog.QUERIES["exact_trimmed_query"](spark, SF).count() > 0
    assert made.count(True) == 1 and len(made) > 3


@pytest.mark.parametrize("directed", [False, True])
def test_kept_vertices_are_those_of_the_edges(spark, directed):
    g = G.from_pairs(spark.createDataFrame(random_pairs(42, 60, 150) + [(7, i) for i in range(100, 1200)], "src long, dst long"), directed)
    assert sorted(g.cached().vertices.collect()) == sorted(g.vertices.collect())


@pytest.mark.parametrize("name", ["landmark_distortion_profile", "landmark_exact_hits", "landmark_diameter_eps"])
def test_graded_queries_sweep_where_they_search(spark, name, monkeypatch):
    """truths and cohorts share one broadcast of the graph; no sweep goes along its edges by jobs."""
    made, modes, sc, sweep = [], [], type(spark.sparkContext), L.cluster_sweep
    broadcast = sc.broadcast
    monkeypatch.setattr(sc, "broadcast", lambda self, x: made.append(len(x)) or broadcast(self, x))
    monkeypatch.setattr(L, "cluster_sweep", lambda *a: modes.append(a[3]) or sweep(*a))
    assert catalog.QUERIES[name](spark, SF).count() > 0
    assert set(modes) == {"broadcast"} and made.count(3) == 1
