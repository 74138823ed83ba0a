"""What the survey lists and the registered queries do not show: plans, selections, measures, workloads, streams, files."""

import random
import shutil
import subprocess
import sys
from pathlib import Path

import pytest
from pyspark.sql import functions as F
from test_hopwise import cohort, exploded, graph, truth

from hopwise import sql
from hopwise.operators import cohorts as C
from hopwise.operators import landmarks as L
from hopwise.operators import measures as M
from hopwise.operators import search as S
from hopwise.operators.twohop import TwoHopIndex, label_inflation
from hopwise.plans import store, workloads
from hopwise.sources import graphs as G
from hopwise.streaming import feeds

SF = "/root/testdata/sf0.001"


def random_pairs(seed, n, m):
    rng = random.Random(seed)
    return [(rng.randrange(n), rng.randrange(n)) for _ in range(m)]


def greedy(pairs, r, w, radius):
    """Cohorts one at a time, on the whole graph."""
    near = {}
    for a, b in pairs:
        if a != b:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
    order, marked, out = sorted(near, key=lambda v: (-len(near[v]), v)), set(), []
    for _ in range(r):
        anchor = next((v for v in order if v not in marked), None)
        if anchor is None:
            break
        dist = truth(pairs, anchor)
        members = [anchor, *[v for v in order if v not in marked and v != anchor and dist.get(v, 99) <= radius][: w - 1]]
        marked.update(members)
        out.append(members)
    return out


@pytest.mark.parametrize(("w", "d", "chunk"), [(4, 2, 5), (6, 4, 16)])
def test_chunks_choose_as_one_at_a_time_does(spark, w, d, chunk):
    pairs = random_pairs(3, 120, 250)
    chosen = C.pick_cohorts(graph(spark, pairs), 24, w, d, chunk=chunk).orderBy("cid", "bit").collect()
    got = [[x["s"] for x in chosen if x["cid"] == cid] for cid in sorted({x["cid"] for x in chosen})]
    assert got == greedy([p for p in pairs if p[0] != p[1]], 24, w, d // 2)


def test_a_round_moves_what_its_messages_touch(spark):
    """On a long path the log of a round has the few vertices of its wave, and no round reads the whole state."""
    n = 120
    g, report = graph(spark, [(i, i + 1) for i in range(n)]), S.Report()
    assert S.cluster_sweep(g, cohort(spark, [0, 1]), 2, stop_after=12, report=report).count() > 12
    assert all(r["messages"] <= 12 and r["activations"] <= 12 for r in report.rounds)
    assert report.activations < n * 4


def test_direction_changes_nothing_but_work(spark):
    pairs = random_pairs(8, 80, 400)
    g = graph(spark, pairs)
    for how in ("push", "pull", "auto"):
        report = S.Report()
        found = S.bfs_each(g, spark.createDataFrame([(pairs[0][0],)], "s long"), how, report=report)
        assert {r["v"]: r["dist"] for r in found.collect()} == truth(pairs, pairs[0][0])
        modes = {r["mode"] for r in report.rounds}
        assert modes == {how} if how != "auto" else "pull" in modes
    assert report.activations < 2 * len(pairs) * len(report.rounds)


def test_hubs_are_dealt_over_parts(spark):
    pairs = [(0, i) for i in range(1, 3000)] + [(i, i + 1) for i in range(1, 2000)]
    g = graph(spark, pairs)
    assert [r["v"] for r in g.hubs.collect()] == [0]
    assert g.parted.where("src = 0").groupBy("part").count().count() == G.HUB_PARTS
    assert {r["v"]: r["dist"] for r in S.bfs(g, 5).collect()} == truth(pairs, 5)


def test_gated_directed_sweep(spark):
    pairs = [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4), (4, 5), (9, 0)]
    g, c = graph(spark, pairs, directed=True), cohort(spark, [0, 1, 2])
    assert C.cohort_diameter(g, c).first()["diameter"] == 2
    got = exploded(S.cluster_sweep(g, c, 2), c, 2)
    assert got == {(s, v): d for s in (0, 1, 2) for v, d in truth(pairs, s, True).items()}


def test_full_words_of_64(spark):
    pairs = [(0, i) for i in range(1, 200)] + [(i, 1000 + i) for i in range(1, 100)] + [(1000 + i, 2000) for i in range(1, 60)]
    g = graph(spark, pairs)
    c = C.star(g, 0, 64)
    want = {(r["s"], v): d for r in c.collect() for v, d in truth(pairs, r["s"]).items()}
    for arrivals in (S.cluster_sweep(g, c, 2), S.star_sweep(g, c), S.sweep_postprocess(g, c)):
        assert exploded(arrivals, c, 2) == want
    assert exploded(S.cluster_sweep(g, C.pick_cohorts(g, 1, 64, 5), 5), c, 5).keys() <= want.keys()
    assert C.spread_cohorts(g, 3, 8).groupBy("cid").count().count() == 3


def test_index_layouts_answers_and_bounds(spark):
    pairs = random_pairs(5, 60, 130)
    g = graph(spark, pairs)
    sample = L.sample_pairs(g, 300).persist()
    exact = {r["pid"]: truth(pairs, r["u"]).get(r["v"]) for r in sample.collect()}
    assert len({r["u"] for r in sample.collect()}) > 30 and len({r["v"] for r in sample.collect()}) > 30
    assert {r["pid"]: r["truth"] for r in L.exact_pairs(g, sample).collect()} == exact
    long = L.plain_index(g, C.pick_landmarks(g, 5))
    a, b = ({r["pid"]: r["est"] for r in L.plain_query(x, sample).collect()} for x in (long, L.wide(long)))
    assert a == b
    assert {r["s"] for r in C.pick_landmarks(g, 5, "hash", 1).collect()} != {r["s"] for r in C.pick_landmarks(g, 5).collect()}
    c = C.pick_cohorts(g, 2, 8, 3, "edge")
    index = L.LandmarkIndex.build(g, c, 3, "complement")
    found = {r["pid"]: r["est"] for r in index.query(sample).collect()}
    members = [r["s"] for r in c.collect()]
    for r in sample.collect():
        best = min((truth(pairs, m)[r["u"]] + truth(pairs, m)[r["v"]] for m in members if r["u"] in truth(pairs, m) and r["v"] in truth(pairs, m)), default=None)
        assert found[r["pid"]] == best
        if best is not None:
            assert best >= exact[r["pid"]] and (best - exact[r["pid"]]) <= 2 * max(truth(pairs, members[0]).values())
            if any(m in (r["u"], r["v"]) for m in members):
                assert best == exact[r["pid"]]
    assert store.forget is not None and M.stored_bytes(index.table) > 0


def test_local_search_scope_and_skip(spark):
    pairs = random_pairs(9, 70, 160)
    g = graph(spark, pairs)
    sample = L.sample_pairs(g, 60).persist()

    def ball(s, tau, closed=()):
        kept = [p for p in pairs if p[0] not in closed and p[1] not in closed]
        near = {}
        for a, b in kept:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
        if s in closed:  # an end is its own ball's first, and its edges leave it
            near[s] = {b if a == s else a for a, b in pairs if s in (a, b)} - set(closed)
            near = {k: v - ({s} if k != s else set()) for k, v in near.items()}
        dist, todo = {s: 0}, [s]
        for u in todo:
            for v in near.get(u, ()):
                if v not in dist and v != s:
                    dist[v] = dist[u] + 1
                    todo.append(v)
        return dict(sorted(dist.items(), key=lambda x: (x[1], x[0]))[:tau])

    skip = C.pick_landmarks(g, 4)
    closed = {r["s"] for r in skip.collect()}
    for tau, scope, left, gone in ((12, "side", None, ()), (12, "total", None, ()), (12, "side", skip, closed)):
        room = tau if scope == "side" else tau // 2
        got = {r["pid"]: r["est"] for r in L.local_meet(g, sample, tau, left, scope).collect()}
        for r in sample.collect():
            a, b = ball(r["u"], room, gone), ball(r["v"], room, gone)
            assert got[r["pid"]] == min((a[x] + b[x] for x in a.keys() & b.keys()), default=None)


def test_exact_index_plans(spark):
    pairs = random_pairs(2, 12, 18)
    g = graph(spark, pairs)
    sample = L.sample_pairs(g, 200).persist()
    exact = {r["pid"]: truth(pairs, r["u"]).get(r["v"]) for r in sample.collect()}
    sizes = {}
    for name, how in {"one": {"first": 1, "growth": 1.0, "cap": 1}, "batches": {}, "trimmed": {"trim": True}, "phase": {"r": 1, "w": 4, "first": 4}}.items():
        index = TwoHopIndex.build(g, **how)
        assert {r["pid"]: r["est"] for r in index.query(sample).collect()} == exact, name
        sizes[name] = index.labels
        assert index.seconds.keys() == {"phase_one", "phase_two"}
    assert sizes["one"].join(sizes["batches"], ["v", "hub", "dist"], "left_anti").count() == 0
    assert sizes["trimmed"].count() == sizes["one"].count() < sizes["batches"].count()
    assert label_inflation(sizes["batches"], sizes["one"]) > 1
    sql.register(g, exact=index, prefix="t")
    assert spark.sql("SELECT count(*) AS n FROM t_edges").first()["n"] == g.edges.count()
    with pytest.raises(ValueError, match="undirected"):
        TwoHopIndex.build(graph(spark, pairs, directed=True))


def test_workloads_give_their_rows(spark):
    g = G.copurchase(spark, SF).cached()
    micro = workloads.micro_bench(spark, g, "copurchase", 8, 1, plain=1)
    assert {r["algo"] for r in workloads.gain_summary(micro).collect()} == {"one_by_one", "keyed_frontier", "star_one_partition", "cluster_sweep", "cluster_sweep_auto"}
    ds = workloads.diameter_sweep(spark, g, "copurchase", 8, (2, 3))
    assert {r["d"]: r["relative"] for r in M.relative_times(ds).collect()}[2] == 1
    rows = workloads.budget_table(spark, g, "copurchase", 17, 100, (1, 64))
    assert {(r["w"], r["clusters"], r["landmarks"]) for r in rows.collect()} == {(1, 17, 17), (64, 1, 64)}
    assert workloads.budget_scorecard(rows).first()["graphs"] == 1
    local = {r["tau"]: r["eps"] for r in workloads.local_search_sweep(spark, g, "copurchase", (16, 400), 60).collect()}
    assert local[400] <= local[16] <= local[0] and local[400] == 0
    assert workloads.fill_rates(spark, G.turn_path(spark, SF).cached(), "turn_path", 2, 64, (2, 4)).orderBy("d").first()["mean_members"] <= 3
    variants = {r["variant"]: r for r in workloads.ablation(spark, g, "copurchase", 16).collect()}
    assert variants["no_bits"]["messages"] > variants["push"]["messages"] <= variants["seen_bits"]["messages"]
    assert variants["no_bits"]["activations"] > 4 * variants["push"]["activations"]
    assert M.shuffled_bytes(spark) > 0 and M.work_saving(10, 5) == 2 and M.model_saving(64, 2) > 3


def test_stats_streams_and_files(spark, tmp_path):
    g = G.nation_region(spark, SF).cached()
    stats = S.graph_stats(g).first()
    assert stats["n"] == g.vertices.count() and stats["diameter_at_least"] >= 2
    assert M.scorecard(spark.createDataFrame([("a", 2.0, 1.0, 0.5, 0.4), ("b", 1.0, 2.0, 0.5, 0.6)], "graph string, base_s double, other_s double, base_eps double, other_eps double")).first()[:4] == (1, 1, 1, 1)
    spark.sql("DROP TABLE IF EXISTS bucketed_edges")
    kept = store.save_bucketed(g.edges, "bucketed_edges", "src", 4)
    assert kept.count() == g.edges.count()
    spark.sql("DROP TABLE bucketed_edges")
    (tmp_path / "edges.txt").write_text("# a comment\n1\t2\n2\t3\n2\t2\n")
    assert G.read_edge_list(spark, str(tmp_path / "edges.txt")).edges.count() == 4
    assert feeds.drained(feeds.sessions(feeds.events(spark, SF))).count() > 0
    index = L.LandmarkIndex.build(g, C.pick_cohorts(g, 1, 8), 2)
    L.sample_pairs(g, 20).write.parquet(f"{tmp_path}/pairs")
    stream = spark.readStream.schema("pid long, u long, v long").parquet(f"{tmp_path}/pairs")
    assert feeds.drained(feeds.answered(stream, index)).count() <= 20


def test_the_rest_works_without_the_training_data_operators(tmp_path):
    root = Path(__file__).parent.parent
    copy = tmp_path / "repo"
    shutil.copytree(root, copy, ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "__pycache__"))
    code = "import __spark_entry__ as e; q = e.queries(); assert 'sweep_pull' in q and 'pipeline' not in q; assert set(e.oracle_sql()) <= set(q); import hopwise.plans.workloads, hopwise.streaming.feeds, hopwise.sql"
    subprocess.run([sys.executable, "-c", code], cwd=copy, check=True, timeout=120)
    # and where they are there but can't be imported
    (copy / "hopwise" / "llm").mkdir()
    (copy / "hopwise" / "llm" / "__init__.py").write_text("")
    (copy / "hopwise" / "llm" / "queries.py").write_text("import no_such_module\n")
    (copy / "corpus_pipeline.py").write_text("import hopwise.llm.queries\n")
    subprocess.run([sys.executable, "-c", code], cwd=copy, check=True, timeout=120)


def test_broadcast_searches_and_components(spark):
    pairs = [*random_pairs(4, 40, 45), (100, 101), (101, 102)]
    g = graph(spark, pairs)
    sources = spark.createDataFrame([(pairs[0][0],), (100,), (999,)], "s long")
    got = {(r["s"], r["v"]): r["dist"] for r in S.bfs_broadcast(g, sources).collect()}
    assert got == {(s, v): d for s in (pairs[0][0], 100) for v, d in truth(pairs, s).items()} | {(999, 999): 0}
    with pytest.raises(ValueError, match="bfs_each"):
        S.bfs_broadcast(g, sources, 3)
    assert {r["v"]: r["component"] for r in S.components(g).collect()} == {v: min(truth(pairs, v)) for p in pairs if p[0] != p[1] for v in p}
