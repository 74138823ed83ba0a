"""The exact index with a batch's hubs as bits: its labels by their definition, whichever way they are searched."""

import pytest
from test_findings_r02 import random_pairs
from test_hopwise import graph, truth

from hopwise.operators import cohorts as C
from hopwise.operators import twohop as T
from hopwise.plans.store import RoundLog


def defined(g, pairs, closed, first, trim):
    """(v, hub, dist) of hubs that reach v without an earlier batch's hub, or a member of a cohort, on any shortest path."""
    degrees = {r["v"]: r["deg"] for r in g.vertices.collect()}
    order = sorted((v for v in degrees if v not in closed), key=lambda v: (-degrees[v], v))
    batch, at = dict.fromkeys(closed, -1), 0
    for i, size in enumerate(T.batch_sizes(len(order), first)):
        batch |= dict.fromkeys(order[at : at + size], i)
        at += size
    place = dict.fromkeys(closed, -1) | {v: i for i, v in enumerate(order)}
    dist = {v: truth(pairs, v) for v in degrees}

    def before(x, h):
        return batch[x] < batch[h] or (trim and place[x] < place[h])

    return {(v, h, dv) for h in order for v, dv in dist[h].items() if not any(before(x, h) and dx + dist[x].get(v, 10**9) == dv for x, dx in dist[h].items())}


@pytest.fixture(scope="module")
def case(spark):
    pairs = [p for p in random_pairs(21, 130, 210) if p[0] != p[1]] + [(900, 901), (901, 902), (902, 903), (903, 904)]
    return pairs, graph(spark, pairs)


def check(spark, case, r, first, trim, **how):
    pairs, g = case
    closed = {x["s"] for x in C.pick_cohorts(g, r, 8).collect()} if r else set()
    index = T.TwoHopIndex.build(g, r, 8, first=first, trim=trim, **how)
    rows = [tuple(x) for x in index.labels.select("v", "hub", "dist").collect()]
    want = defined(g, pairs, closed, first, trim)
    assert len(rows) == len(want) and set(rows) == want
    ends = sorted({x for p in pairs for x in p})
    asked = [(i, u, ends[(7 * i + 3) % len(ends)]) for i, u in enumerate(ends * 2)]
    found = {x["pid"]: x["est"] for x in index.query(spark.createDataFrame(asked, "pid long, u long, v long")).collect()}
    assert found == {i: truth(pairs, u).get(v) for i, u, v in asked}
    return g


@pytest.mark.parametrize(("r", "first", "trim"), [(0, 20, False), (2, 20, False), (2, 70, True)])
def test_a_task_searches_from_a_word_of_hubs(spark, case, r, first, trim, monkeypatch):
    """No row for a pair of hub and vertex goes along the edges."""
    monkeypatch.setattr(T, "sent_along", None)
    check(spark, case, r, first, trim)


@pytest.mark.parametrize(("r", "first", "trim"), [(0, 20, False), (2, 70, True)])
def test_graphs_above_the_bound_are_searched_by_plans(spark, case, r, first, trim, monkeypatch):
    """A round has a row for a vertex and 64 hubs at most."""
    append, rows = RoundLog.append, []

    def counted(log, df):
        append(log, df)
        rows.append(log.last().count())

    monkeypatch.setattr(RoundLog, "append", counted)
    g = check(spark, case, r, first, trim, most_edges=10)
    n = g.vertices.count()
    assert n > 128 and max(rows) <= n * -(-n // 64)
