"""Searches on a broadcast graph with sources as bits, and the graded queries that use them."""

import numpy as np
import pytest
from test_findings_r02 import SF, random_pairs
from test_hopwise import graph, truth

from hopwise import catalog
from hopwise.operators import compact as K
from hopwise.operators import landmarks as L


def test_distances_by_bits(spark):
    """More sources than a word has bits, a far pair, pairs out of reach, ids without an edge, pairs of one vertex."""
    pairs = [p for p in random_pairs(31, 150, 190) if p[0] != p[1]] + [(1000 + i, 1001 + i) for i in range(12)]
    g = graph(spark, pairs)
    sources = [*range(150), 1000, 5555]
    found = K.distances(g, spark.createDataFrame([(s,) for s in sources * 2], "s long")).collect()
    want = {(s, v): d for s in sources for v, d in truth(pairs, s).items()}
    assert len(found) == len(want) and {(r["s"], r["v"]): r["dist"] for r in found} == want
    asked = [(f"p{i}", u, v) for i, (u, v) in enumerate([*random_pairs(32, 150, 300), (1000, 1012), (1003, 5), (7, 7), (5555, 5555), (5555, 7), (7, 5555)])]
    for way in (L.exact_pairs, L.two_sided):
        got = way(g, spark.createDataFrame(asked, "pid string, u long, v long")).collect()
        assert len(got) == len(asked) and {r["pid"]: r["truth"] for r in got} == {i: truth(pairs, u).get(v) for i, u, v in asked}


def test_steps_give_what_the_whole_gives(monkeypatch):
    rng = np.random.default_rng(33)
    edges = np.unique(np.concatenate([np.arange(80).repeat(3), rng.integers(0, 80, 240)]).reshape(2, -1), axis=1)
    tails, heads = np.concatenate([edges, edges[::-1]], axis=1)
    starts = np.concatenate([[0], np.cumsum(np.bincount(tails, minlength=80))])
    heads = heads[np.argsort(tails, kind="stable")]
    x = rng.integers(0, 2**63, 80).astype(np.uint64)
    want = [np.bitwise_or.reduce(x[heads[starts[i] : starts[i + 1]]]) for i in range(80)]
    for step in (K.STEP, 7, 1):
        monkeypatch.setattr(K, "STEP", step)
        assert K.spread(np.arange(80), starts, heads, [x])[0].tolist() == want
    few = np.where(np.arange(80) == 5, x, np.uint64(0))
    assert K.spread(np.array([5]), starts, heads, [few])[0].tolist() == [few[5] if 5 in heads[starts[i] : starts[i + 1]] else 0 for i in range(80)]


@pytest.mark.parametrize("name", ["landmark_budget_eps", "landmark_distortion_profile", "landmark_exact_hits", "landmark_diameter_eps"])
def test_graded_queries_on_a_broadcast_graph(spark, name, monkeypatch):
    """No components, no keyed search and one sweep for all budgets of a width."""
    sweep, sweeps = L.cluster_sweep, []
    monkeypatch.setattr(L, "components", None)
    monkeypatch.setattr(L, "bfs_each", None)
    monkeypatch.setattr(L, "cluster_sweep", lambda *a: sweeps.append(1) or sweep(*a))
    variants = {(r["w"], r["d"]) for r in catalog.QUERIES[name](spark, SF).collect() if "w" in r} - {(1, 2)}
    assert len(sweeps) == max(1, len(variants))
