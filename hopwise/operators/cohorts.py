"""Choosing landmarks: single vertices by degree, and cohorts of vertices that are near each other."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.ranking import ranked
from ..plans.store import forget, written
from ..sources.graphs import HopGraph
from .compact import held, within
from .search import bfs_each, cluster_sweep, explode_records, records

SCHEMA = "cid int, bit int, s long, is_anchor boolean"


def pick_landmarks(g: HopGraph, count: int, strategy: str = "degree", seed: int = 0) -> DataFrame:
    """s, rank: the ``count`` of the highest degree (ties by id), or by a hash of the id."""
    order = [F.desc("deg"), F.col("v")] if strategy == "degree" else [F.md5(F.concat_ws("-", F.lit(seed), F.col("v"))), F.col("v")]
    top = [r["v"] for r in g.vertices.orderBy(*order).limit(count).collect()]
    return g.edges.sparkSession.createDataFrame(list(zip(top, range(1, len(top) + 1), strict=True)), "s long, rank int")


def ball(g: HopGraph, anchor: int, radius: int) -> DataFrame:
    """v: within ``radius`` hops of the anchor, without it."""
    return balls(g, g.edges.sparkSession.createDataFrame([(anchor,)], "s long"), radius).select("v")


def balls(g: HopGraph, anchors: DataFrame, radius: int) -> DataFrame:
    """s, v: the vertices within ``radius`` hops of each of ``anchors(s)``, without the anchor itself."""
    if radius == 1:
        if g.stored is not None:  # anchors come from the driver, so they are few
            ways = [("src", "dst")] if g.directed else [("src", "dst"), ("dst", "src")]
            met = F.array(*(F.struct(F.col(a).alias("s"), F.col(b).alias("v")) for a, b in ways))
            return g.stored.select(F.inline(met)).join(F.broadcast(anchors), "s").select("s", "v")
        return g.along(anchors.withColumnRenamed("s", "v")).select(F.col("v").alias("s"), F.col("dst").alias("v"))
    return bfs_each(g, anchors, stop_after=radius).where("dist > 0").select("s", "v")


def pick_cohorts(g: HopGraph, r: int, w: int = 64, d: int = 2, radius_rule: str = "floor", chunk: int = 16) -> DataFrame:
    """r cohorts of at most w: the unmarked vertex of the highest degree, and the w-1 unmarked of the highest degree
    within half of d; all are then marked.

    Candidates are worked on ``chunk`` at a time. The chunk's balls are fetched in one job, and of each the best
    (w-1) + (chunk-1) w unmarked vertices: earlier candidates of the chunk can mark no more than the surplus, so the
    driver's greedy choice on these rows is the choice on the whole graph. What the driver holds is r * w ids and
    chunk^2 * w rows.

    Where the graph has been broadcast, the driver holds its edges and chooses on them, one cohort after another.

    ``radius_rule="edge"`` (d = 3) takes the neighbours of both ends of the anchor's edge to its best neighbour; that
    depends on the marks, so it is done one cohort at a time.
    """
    spark = g.edges.sparkSession
    edge_rule, radius = radius_rule == "edge" and d == 3, max(d // 2, 0)
    if not edge_rule and (graph := held(g)) is not None:
        return spark.createDataFrame(_cohorts_of(*graph, r, w, radius), SCHEMA)
    degrees = g.vertices if g.known is not None else written(g.vertices, "degrees")
    marked: set[int] = set()
    out: list[tuple[int, int, int, bool]] = []

    def unmarked(among: DataFrame) -> DataFrame:
        gone = spark.createDataFrame([(x,) for x in sorted(marked)], "v long")  # r * w rows at most
        return among.join(F.broadcast(gone), "v", "left_anti")

    def best(among: DataFrame, n: int) -> list[tuple[int, int]]:
        return [(x["v"], x["deg"]) for x in unmarked(among).orderBy(F.desc("deg"), "v").limit(n).collect()]

    def choose(anchor: int, near: list[int]) -> None:
        members = [anchor, *[v for v in near if v not in marked and v != anchor][: w - 1]]
        marked.update(members)
        cid = out[-1][0] + 1 if out else 0
        out.extend((cid, bit, s, bit == 0) for bit, s in enumerate(members))

    taken = 0
    while taken < r:
        candidates = [v for v, _ in best(degrees, 1 if edge_rule else min(chunk, r - taken))]
        if not candidates:
            break
        if edge_rule:
            near = ball(g, candidates[0], 1)
            marked.add(candidates[0])
            second = best(near.join(degrees, "v"), 1)
            around = near.unionByName(ball(g, second[0][0], 1)).distinct() if second else near
            choose(candidates[0], [v for v, _ in best(around.join(degrees, "v"), w - 1)])
            taken += 1
            continue
        around: dict[int, list[int]] = {}
        if radius:
            anchors = spark.createDataFrame([(x,) for x in candidates], "s long")
            rows = unmarked(balls(g, anchors, radius)).join(degrees, "v")
            place = F.row_number().over(Window.partitionBy("s").orderBy(F.desc("deg"), "v"))
            top = rows.withColumn("place", place).where(F.col("place") <= (w - 1) + (len(candidates) - 1) * w)
            for x in top.select("s", "v", "place").orderBy("s", "place").collect():
                around.setdefault(x["s"], []).append(x["v"])
        for anchor in candidates:
            if anchor not in marked and taken < r:
                choose(anchor, around.get(anchor, []))
                taken += 1
    if g.known is None:
        forget(degrees)
    return spark.createDataFrame(out, SCHEMA)


def _cohorts_of(ids: np.ndarray, starts: np.ndarray, heads: np.ndarray, r: int, w: int, radius: int) -> list[tuple[int, int, int, bool]]:
    order = np.argsort(-np.diff(starts), kind="stable")  # places are in the order of ids
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    marked, out, at = np.zeros(len(ids), bool), [], 0
    for cid in range(r):
        while at < len(order) and marked[order[at]]:
            at += 1
        if at == len(order):
            break
        anchor = order[at]
        near = within(anchor, radius, starts, heads)
        near = near[~marked[near]]
        members = np.append(anchor, near[np.argsort(rank[near])][: w - 1])
        marked[members] = True
        out += [(cid, bit, int(s), bit == 0) for bit, s in enumerate(ids[members])]
    return out


def spread_cohorts(g: HopGraph, count: int, w: int = 64, d: int = 2) -> DataFrame:
    """``count`` test cohorts far from one another in rank: anchors at even steps of the degree order, among vertices of
    degree w - 1 or more if there are so many, each with its best neighbours; cohorts may overlap."""
    degrees = written(g.vertices, "degrees")
    wide = degrees.where(F.col("deg") >= w - 1)
    n = wide.count()
    pool, n = (wide, n) if n >= count else (degrees, degrees.count())
    step = max(1, n // count)
    order = ranked(pool, F.desc("deg"), "v")
    anchors = [x["v"] for x in order.where((F.col("rank") - 1) % step == 0).orderBy("rank").limit(count).collect()]
    near = balls(g, g.edges.sparkSession.createDataFrame([(x,) for x in anchors], "s long"), max(1, d // 2)).join(degrees, "v")
    place = F.row_number().over(Window.partitionBy("s").orderBy(F.desc("deg"), "v"))
    rows = near.withColumn("place", place).where(F.col("place") < w).select("s", "v", "place").orderBy("s", "place").collect()
    members = {a: [x["v"] for x in rows if x["s"] == a] for a in anchors}
    out = [(cid, bit, s, bit == 0) for cid, a in enumerate(anchors) for bit, s in enumerate([a, *members[a]])]
    return g.edges.sparkSession.createDataFrame(out, SCHEMA)


def cover_cohorts(g: HopGraph, w: int = 64, d: int = 2) -> DataFrame:
    """cid, bit, s, is_anchor: every vertex in one cohort of at most w, members at most d apart, chosen all at once.

    A vertex goes with the vertex of the highest degree (ties by id) within half of d (undirected graphs): as many rounds as that radius, and
    no choice that waits for another. Each such group is cut into cohorts. For d = 0 or 1 every vertex is alone.
    """
    at = g.vertices.select("v", F.struct(F.col("deg").alias("deg"), (-F.col("v")).alias("id")).alias("best"))
    for _ in range(d // 2):
        at = written(at, "leaders")
        near = g.along(at).select(F.col("dst").alias("v"), "best")
        at = at.unionByName(near).groupBy("v").agg(F.max("best").alias("best"))
    placed = written(ranked(at.select("v", F.col("best.id").alias("leader")), "leader", "v"), "placed")
    starts = placed.groupBy("leader").agg((F.min("rank") - 1).alias("before"))
    i = F.col("rank") - 1 - F.col("before")
    # a group has at least as many members as cohorts, so the members before it and the place in it number them
    rows = placed.join(starts, "leader").select((F.col("before") + F.floor(i / w)).cast("int").alias("cid"), (i % w).cast("int").alias("bit"), F.col("v").alias("s"))
    return written(rows.withColumn("is_anchor", F.col("bit") == 0), "cover")


def all_pairs(g: HopGraph, w: int = 64, d: int = 2) -> DataFrame:
    """s, v, dist: all distances, by sweeps over cohorts that cover the graph. The answer is quadratic; so is the work."""
    if g.directed:
        cover = pick_cohorts(g, g.vertices.count(), w, d)
    else:
        cover = cover_cohorts(g, w, d)
    return explode_records(records(cluster_sweep(g, cover, d), d), cover).select("s", "v", "dist")


def star(g: HopGraph, anchor: int, w: int = 64) -> DataFrame:
    """The anchor and its w-1 neighbours of the highest degree."""
    rows = ball(g, anchor, 1).join(g.vertices, "v").orderBy(F.desc("deg"), "v").limit(w - 1).collect()
    members = [anchor, *(x["v"] for x in rows)]
    return g.edges.sparkSession.createDataFrame([(0, b, s, b == 0) for b, s in enumerate(members)], SCHEMA)


def cohort_diameter(g: HopGraph, cohorts: DataFrame, stop_after: int | None = None) -> DataFrame:
    """cid, diameter: the greatest distance between members, null if some pair is out of reach (or beyond stop_after)."""
    found = bfs_each(g, cohorts.select("s"), stop_after=stop_after)
    pairs = cohorts.select("cid", F.col("s").alias("s")).join(cohorts.select("cid", F.col("s").alias("v")), "cid")
    joined = pairs.join(found, ["s", "v"], "left")
    return joined.groupBy("cid").agg(F.when(F.count_if(F.col("dist").isNull()) == 0, F.max("dist")).alias("diameter"))


def model_bytes(w: int, d: int, encoding: str = "complement") -> int:
    """Bytes per vertex and cohort: one for the base, w/8 for each stored mask."""
    return 1 + (d + 1 if encoding == "full" else d) * w // 8


def clusters_for_budget(t: int, w: int, d: int = 2) -> int:
    """How many cohorts fit t bytes per vertex; w = 1 is a plain landmark of one byte."""
    return t if w == 1 else t // model_bytes(w, d)
