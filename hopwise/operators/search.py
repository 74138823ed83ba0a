"""Level-synchronous traversals: plain searches keyed by source, and cluster sweeps that carry sources as bits.

A round is one job. Frontier rows meet their edges; what they send, and the rows of the log that could know it
already, are combined in one aggregation by vertex (min or bit_or, all idempotent, so repeated tasks are safe);
what is new is appended to the log, which is the answer. In an undirected graph neighbours are reached at most a
round apart, so only the last rounds of the log can know a vertex that is met now: two for a plain search, d + 2
for a sweep of gate d. Nothing that no message touches moves, and no state is written twice.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions import masks
from ..plans.ranking import ranked
from ..plans.store import RoundLog, forget, written
from ..sources.graphs import HopGraph
from .compact import arrivals, sweep_records

#: "auto" pulls while the frontier's edges are more than this share of the edges of vertices not yet met
PULL_SHARE = 0.5


@dataclass
class Report:
    """Per round: mode, frontier rows that went in, edges that they activated, messages after combining, rows that arrived."""

    rounds: list[dict] = field(default_factory=list)

    def total(self, what: str) -> int:
        return sum(r[what] for r in self.rounds)

    @property
    def messages(self) -> int:
        return self.total("messages")

    @property
    def activations(self) -> int:
        return self.total("activations")


def sent_along(g: HopGraph, frontier: DataFrame, open_: DataFrame | None = None) -> DataFrame:
    """``frontier(v, ...)`` once for every out-edge, v being the head.

    With ``open_(v)`` the step pulls: open vertices look along their in-edges for rows of the frontier. (Searches
    that carry bits must see all of them; for one source a semi-join stops at the first, see ``reached_by_pull``.)
    """
    if open_ is None:
        return g.along(frontier).drop("v").withColumnRenamed("dst", "v")
    looked = g.incoming().along(open_)
    tails = frontier.withColumnRenamed("v", "_tail")
    return looked.join(tails, looked.dst == tails["_tail"]).drop("dst", "_tail")


def reached_by_pull(g: HopGraph, frontier: DataFrame, open_: DataFrame) -> DataFrame:
    """v: open vertices with an in-neighbour in ``frontier(v)``; an edge is dropped at its first hit, and one row a vertex leaves each task."""
    looked = g.incoming().along(open_)
    return looked.join(frontier.select(F.col("v").alias("dst")), "dst", "left_semi").select("v").distinct()


class Direction:
    """Push, pull or, by the edges ahead, either."""

    def __init__(self, g: HopGraph, mode: str):
        self.mode, self.degrees, self.unmet = mode, None, 0
        if mode == "auto":
            self.degrees = written(g.vertices, "degrees")
            self.unmet = self.degrees.agg(F.sum("deg")).first()[0] or 0
        self.ahead = 0

    def weigh(self, arrived: DataFrame) -> DataFrame:
        """``arrived(v, first, ...)`` with the out-degree of v, where it is needed."""
        return arrived.withColumn("deg", F.lit(0).cast("long")) if self.degrees is None else arrived.join(self.degrees, "v", "left").fillna(0, ["deg"])

    def saw(self, edges: int, first_edges: int) -> None:
        self.ahead, self.unmet = edges, self.unmet - first_edges

    def pull(self) -> bool:
        return self.mode == "pull" or self.mode == "auto" and self.ahead > PULL_SHARE * self.unmet


def cluster_sweep(
    g: HopGraph, cohorts: DataFrame, d: int | None = 2, mode: str = "push", delta: bool = True, stop_after: int | None = None, report: Report | None = None,
    joined: bool = False,
) -> DataFrame:
    """Arrivals (v, cid, word, round, fresh) of the cohorts ``(cid, bit, s)``; word = bit div 64.

    ``d`` is a bound on the distance between members of a cohort, both ways if the graph is directed: a vertex takes
    part for d rounds after its first. None lifts the gate: right for any set of sources. ``delta`` sends fresh
    bits only; else all seen ones. ``mode``: push, pull, auto, or broadcast (an undirected graph that fits every task, and
    fresh bits alone, without a report). ``joined``: the records of the arrivals instead, which a task on a broadcast graph
    puts together itself.
    """
    if joined and (d is None or stop_after is not None):
        raise ValueError("records are of whole sweeps with a gate")
    if mode == "broadcast":
        if g.directed or not delta or report is not None:
            raise ValueError("a broadcast graph is undirected; its sweep sends fresh bits and keeps no report")
        return sweep_records(g, cohorts, d) if joined else arrivals(g, cohorts, d, stop_after)
    spark, keys = g.edges.sparkSession, ["cid", "word"]
    none = F.lit(0).cast("long")
    seeds = cohorts.select(F.col("s").cast("long").alias("v"), F.col("cid").cast("int").alias("cid"), F.floor(F.col("bit") / 64).cast("int").alias("word"), masks.bit(F.col("bit") % 64).alias("m"))
    whole = written(seeds.groupBy(*keys).agg(F.bit_or("m").alias("whole")), "whole")
    log, way = RoundLog(spark, "sweep", "v long, cid int, word int, fresh long"), Direction(g, mode)
    back = None if d is None or g.directed else d + 2
    counted = Observation()
    start = way.weigh(seeds.groupBy("v", *keys).agg(F.bit_or("m").alias("fresh"))).observe(counted, F.count("*").alias("n"), F.sum("deg").alias("deg"))
    log.append(start.select("v", *keys, "fresh"))
    arrived, i = counted.get["n"], 0
    way.saw(counted.get["deg"] or 0, counted.get["deg"] or 0)
    while arrived and (stop_after is None or i < stop_after):
        i += 1
        recent = log.since(0 if back is None else i - back)
        frontier = log.last().select("v", *keys, F.col("fresh").alias("msg"))
        if not delta:
            frontier = recent.join(frontier.drop("msg"), ["v", *keys], "left_semi").groupBy("v", *keys).agg(F.bit_or("fresh").alias("msg"))
        pull = way.pull()
        activated, combined, counted = Observation(), Observation(), Observation()
        sent = sent_along(g, frontier, _open(g, log.since(), whole, d, i) if pull else None).observe(activated, F.count("*").alias("n"))
        # a vertex at its last offset still sends: a neighbour met a round later is open for its bits
        both = sent.select("v", *keys, "msg", none.alias("fresh"), F.lit(None).cast("int").alias("round"))
        both = both.unionByName(recent.select("v", *keys, none.alias("msg"), "fresh", "round"))
        met = both.groupBy("v", *keys).agg(F.bit_or("msg").alias("msg"), F.bit_or("fresh").alias("seen"), F.min("round").alias("base"))
        met = met.observe(combined, F.count_if(F.col("msg") != 0).alias("n"))
        gate = F.lit(True) if d is None else F.coalesce(i - F.col("base") <= d, F.lit(True))
        new = met.withColumn("fresh", masks.minus(F.col("msg"), F.col("seen"))).where((F.col("fresh") != 0) & gate)
        new = way.weigh(new).observe(counted, F.count("*").alias("n"), F.sum("deg").alias("deg"), F.sum(F.when(F.col("base").isNull(), F.col("deg"))).alias("first"))
        log.append(new.select("v", *keys, "fresh"))
        if report is not None:
            report.rounds.append({"round": i, "mode": "pull" if pull else "push", "frontier": arrived, "activations": activated.get["n"], "messages": combined.get["n"], "arrived": counted.get["n"]})
        arrived = counted.get["n"]
        way.saw(counted.get["deg"] or 0, counted.get["first"] or 0)
    found = log.since().select("v", *keys, "round", "fresh")
    return records(found, d) if joined else found


def _open(g: HopGraph, log: DataFrame, whole: DataFrame, d: int | None, i: int) -> DataFrame:
    """Vertices at which some cohort can gain a bit: not met in full, nor beyond their gate, by all of them."""
    met = log.groupBy("v", "cid", "word").agg(F.bit_or("fresh").alias("seen"), F.min("round").alias("base"))
    done = F.col("seen") == F.col("whole")
    if d is not None:
        done = done | (F.lit(i) - F.col("base") > d)
    n = whole.count()  # words of cohorts: a number of the call
    closed = met.join(whole, ["cid", "word"]).groupBy("v").agg(F.count_if(done).alias("done")).where(F.col("done") == n)
    return g.vertices.select("v").join(closed.select("v"), "v", "left_anti")


def bfs_each(g: HopGraph, sources: DataFrame, mode: str = "push", stop_after: int | None = None, report: Report | None = None) -> DataFrame:
    """(s, v, dist): plain searches from all of ``sources(s)`` side by side, one row per source and vertex, no bits."""
    spark = g.edges.sparkSession
    log, way = RoundLog(spark, "bfs", "v long, s long"), Direction(g, mode)
    own = sources.select(F.col("s").cast("long").alias("s")).distinct()
    counted = Observation()
    log.append(way.weigh(own.select(F.col("s").alias("v"), "s")).observe(counted, F.count("*").alias("n"), F.sum("deg").alias("deg")).select("v", "s"))
    k = arrived = counted.get["n"]
    way.unmet *= max(k, 1)
    way.saw(counted.get["deg"] or 0, counted.get["deg"] or 0)
    i = 0
    while arrived and (stop_after is None or i < stop_after):
        i += 1
        recent, frontier = log.since(0 if g.directed else i - 2), log.last().select("v", "s")
        pull = way.pull()
        activated, combined, counted = Observation(), Observation(), Observation()
        if pull and k == 1:
            open_ = g.vertices.select("v").join(log.since().select("v"), "v", "left_anti")
            sent = reached_by_pull(g, frontier, open_).crossJoin(F.broadcast(own))  # one source
        else:
            open_ = g.vertices.select("v").join(log.since().groupBy("v").count().where(F.col("count") == k).select("v"), "v", "left_anti") if pull else None
            sent = sent_along(g, frontier, open_)
        sent = sent.observe(activated, F.count("*").alias("n"))
        both = sent.select("v", "s", F.lit(True).alias("met")).unionByName(recent.select("v", "s", F.lit(False).alias("met")))
        new = both.groupBy("v", "s").agg(F.every("met").alias("new"), F.some("met").alias("met")).observe(combined, F.count_if("met").alias("n"))
        new = way.weigh(new.where("new")).observe(counted, F.count("*").alias("n"), F.sum("deg").alias("deg"))
        log.append(new.select("v", "s"))
        if report is not None:
            report.rounds.append({"round": i, "mode": "pull" if pull else "push", "frontier": arrived, "activations": activated.get["n"], "messages": combined.get["n"], "arrived": counted.get["n"]})
        arrived = counted.get["n"]
        way.saw(counted.get["deg"] or 0, counted.get["deg"] or 0)
    return log.since().select("s", "v", F.col("round").alias("dist"))


def bfs(g: HopGraph, source: int, mode: str = "push", stop_after: int | None = None) -> DataFrame:
    """(v, dist)"""
    spark = g.edges.sparkSession
    return bfs_each(g, spark.createDataFrame([(source,)], "s long"), mode, stop_after).select("v", "dist")


def bfs_broadcast(g: HopGraph, sources: DataFrame, most_edges: int = 5_000_000) -> DataFrame:
    """(s, v, dist) on a graph that fits every task: the edges are broadcast, each source is searched by one task.

    Only for graphs of ``most_edges`` at most (16 bytes an edge); a larger one is refused, ``bfs_each`` and ``bfs_any_size`` are for those.
    """
    import numpy as np
    import pandas as pd

    if g.edges.limit(most_edges + 1).count() > most_edges:
        raise ValueError(f"more than {most_edges} edges: use bfs_each")
    rows = g.edges.select("src", "dst").toPandas()
    ids, ends = np.unique(rows.to_numpy(np.int64).ravel(), return_inverse=True)
    src, dst = ends[::2], ends[1::2]
    order = np.argsort(src, kind="stable")
    starts = np.searchsorted(src[order], np.arange(len(ids) + 1))
    shared = g.edges.sparkSession.sparkContext.broadcast((ids, starts, dst[order]))

    def search(frames):
        ids, starts, heads = shared.value
        for frame in frames:
            for s in frame["s"].to_numpy(np.int64):
                dist = np.full(len(ids), -1, np.int32)
                at = np.searchsorted(ids, s)
                if at == len(ids) or ids[at] != s:
                    yield pd.DataFrame({"s": [s], "v": [s], "dist": [0]})
                    continue
                front, depth = np.array([at]), 0
                dist[at] = 0
                while len(front):
                    depth += 1
                    sizes = starts[front + 1] - starts[front]
                    offsets = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
                    near = heads[np.repeat(starts[front], sizes) + offsets]
                    front = np.unique(near[dist[near] < 0])
                    dist[front] = depth
                met = dist >= 0
                yield pd.DataFrame({"s": s, "v": ids[met], "dist": dist[met]})

    own = sources.select(F.col("s").cast("long").alias("s")).distinct()
    return own.mapInPandas(search, "s long, v long, dist int")


def bfs_bits(g: HopGraph, sources: DataFrame) -> DataFrame:
    """(s, v, dist) from any ``sources(s)``: a sweep without gate, 64 sources a word, so that an edge is passed once a word and round."""
    own = ranked(sources.select(F.col("s").cast("long").alias("s")).distinct(), "s")
    numbered = written(own.select(F.lit(0).alias("cid"), (F.col("rank") - 1).alias("bit"), "s"), "sources")
    arrivals = cluster_sweep(g, numbered, None)
    members = numbered.select("s", F.floor(F.col("bit") / 64).cast("int").alias("word"), (F.col("bit") % 64).alias("b"))
    found = arrivals.join(F.broadcast(members), "word").where(masks.has(F.col("fresh"), F.col("b")))
    return found.select("s", "v", F.col("round").alias("dist"))


def bfs_any_size(g: HopGraph, sources: DataFrame, most_edges: int = 5_000_000) -> DataFrame:
    """(s, v, dist): on a broadcast graph as long as it has ``most_edges`` at most; the edges of a larger one stay where
    they are and the sources come to them as bits. The same rows, whatever the size."""
    few = g.edges.limit(most_edges + 1).count() <= most_edges
    return bfs_broadcast(g, sources, most_edges) if few else bfs_bits(g, sources)


def components(g: HopGraph) -> DataFrame:
    """v, component: the least vertex of the (weakly) connected component, by stars that are drawn to their least neighbours.

    Two aggregations a turn, and about log(n) turns, whatever the diameter.
    """
    ends = g.edges.select("src", "dst")
    now = written(ends.select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).distinct(), "stars")
    before = None
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(least, "a").where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").select(F.explode(F.array(F.struct(F.col("a").alias("x"), F.col("m").alias("y")), F.struct(F.col("b").alias("x"), F.col("m").alias("y")))).alias("e"))
        after = written(small.select(F.col("e.x").alias("a"), F.col("e.y").alias("b")).where("a <> b").distinct(), "stars")
        state = after.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        forget(now)
        now = after
        if state == before:
            break
        before = state
    found = now.select(F.col("a").alias("v"), F.col("b").alias("component"))
    return g.vertices.select("v").join(found, "v", "left").select("v", F.coalesce("component", "v").alias("component"))


def bfs_sequential(g: HopGraph, sources: list[int]) -> DataFrame:
    """One search after another: the slow baseline."""
    out = None
    for s in sources:
        one = bfs(g, s).select(F.lit(s).cast("long").alias("s"), "v", "dist")
        out = one if out is None else out.unionByName(one)
    return out


def records(arrivals: DataFrame, d: int) -> DataFrame:
    """(v, cid, word, base, m): the mask of each offset from 0 to d."""
    parts = arrivals.groupBy("v", "cid", "word").agg(F.min("round").alias("base"), F.collect_list(F.struct("round", "fresh")).alias("a"))
    pick = lambda i: F.aggregate(
        F.filter("a", lambda x: x["round"] == F.col("base") + i), F.lit(0).cast("long"), lambda s, x: s.bitwiseOR(x["fresh"])
    )
    return parts.select("v", "cid", "word", "base", F.transform(F.sequence(F.lit(0), F.lit(d)), pick).alias("m"))


def explode_records(recs: DataFrame, cohorts: DataFrame) -> DataFrame:
    """(cid, s, v, dist) from records."""
    long = recs.select("v", "cid", "word", "base", F.posexplode("m").alias("off", "mask")).where("mask <> 0")
    c = cohorts.select("cid", "s", F.floor(F.col("bit") / 64).cast("int").alias("word"), (F.col("bit") % 64).alias("b"))
    return long.join(c, ["cid", "word"]).where(masks.has(F.col("mask"), F.col("b"))).select("cid", "s", "v", (F.col("base") + F.col("off")).alias("dist"))


def star_sweep(g: HopGraph, cohorts: DataFrame) -> DataFrame:
    """Arrivals of one star cohort (bit 0 the anchor, others its neighbours), by classifying edges within and between levels.

    With c the distance to the anchor, members are at c-1 (near), c (same) or c+1 of a vertex. Near masks come from the
    level before; same masks from the level before and from near masks of the same level: two combinations a level.
    """
    anchor = cohorts.where("bit = 0").first()["s"]
    level = written(bfs(g, anchor).withColumnRenamed("dist", "c"), "levels")
    own = cohorts.select(F.col("s").alias("v"), masks.bit("bit").alias("own"), "bit")
    top = level.agg(F.max("c")).first()[0]
    between = g.edges.join(level.select(F.col("v").alias("src"), F.col("c").alias("cs")), "src").join(level.select(F.col("v").alias("dst"), F.col("c").alias("cd")), "dst")
    between = written(between.where("cs = cd or cs + 1 = cd"), "classified")
    zero = F.lit(0).cast("long")
    now = level.where("c = 0").select("v", zero.alias("near"), F.lit(1).cast("long").alias("same"))
    out = now.withColumn("c", F.lit(0))
    for c in range(1, top + 1):
        here = level.where(F.col("c") == c).select("v").join(own.where("bit > 0").select("v", "own"), "v", "left") if c == 1 else level.where(F.col("c") == c).select("v", F.lit(None).cast("long").alias("own"))
        down = between.where((F.col("cd") == c) & (F.col("cs") == c - 1)).join(now.withColumnRenamed("v", "src"), "src").groupBy(F.col("dst").alias("v")).agg(F.bit_or("near").alias("dn"), F.bit_or("same").alias("ds"))
        half = written(here.join(down, "v", "left").select("v", masks.union(F.coalesce("own", zero), F.coalesce("dn", zero)).alias("near"), F.coalesce("ds", zero).alias("ds")), "half")
        side = between.where((F.col("cd") == c) & (F.col("cs") == c)).join(half.select(F.col("v").alias("src"), "near"), "src").groupBy(F.col("dst").alias("v")).agg(F.bit_or("near").alias("sn"))
        now = written(half.join(side, "v", "left").select("v", "near", masks.minus(masks.union(F.col("ds"), F.coalesce("sn", zero)), F.col("near")).alias("same")), "level")
        out = out.unionByName(now.withColumn("c", F.lit(c)))
    whole = cohorts.agg(F.bit_or(masks.bit("bit"))).first()[0]
    far = masks.minus(F.lit(whole), masks.union(F.col("near"), F.col("same")))
    cid = cohorts.first()["cid"]
    three = F.array(*(F.struct((F.col("c") + i - 1).alias("round"), m.alias("fresh")) for i, m in enumerate((F.col("near"), F.col("same"), far))))
    rows = out.select("v", F.lit(cid).cast("int").alias("cid"), F.lit(0).alias("word"), F.explode(three).alias("x"))
    return rows.select("v", "cid", "word", "x.round", "x.fresh").where("fresh <> 0")


def sweep_postprocess(g: HopGraph, cohorts: DataFrame) -> DataFrame:
    """Arrivals by running unions: the sets of sources that reach each vertex within i rounds, for all i; then what each
    round adds. No frontier, no gate, all edges in every round: a slow second way, for any set of sources."""
    keys = ["v", "cid", "word"]
    seeds = cohorts.select(F.col("s").cast("long").alias("v"), F.col("cid").cast("int").alias("cid"), F.floor(F.col("bit") / 64).cast("int").alias("word"), masks.bit(F.col("bit") % 64).alias("m"))
    log = RoundLog(g.edges.sparkSession, "unions", "v long, cid int, word int, reached long, before long")
    log.append(seeds.groupBy(*keys).agg(F.bit_or("m").alias("reached")).withColumn("before", F.lit(0).cast("long")))
    changed = True
    while changed:
        now = log.last().select(*keys, "reached")
        own = now.withColumn("before", F.col("reached"))
        sent = sent_along(g, now).withColumn("before", F.lit(0).cast("long"))
        counted = Observation()
        after = own.unionByName(sent.select(*own.columns)).groupBy(*keys).agg(F.bit_or("reached").alias("reached"), F.bit_or("before").alias("before"))
        log.append(after.observe(counted, F.count_if(F.col("reached") != F.col("before")).alias("n")))
        changed = counted.get["n"] > 0
    return log.since().select(*keys, "round", masks.minus(F.col("reached"), F.col("before")).alias("fresh")).where("fresh <> 0")


def graph_stats(g: HopGraph) -> DataFrame:
    """n, m, max_deg and a lower bound on the diameter by a double sweep from the vertex of the highest degree."""
    v = g.vertices
    start = v.orderBy(F.desc("deg"), "v").first()["v"]
    far = bfs(g, start).orderBy(F.desc("dist"), "v").first()
    depth = bfs(g, far["v"]).agg(F.max("dist")).first()[0]
    return v.agg(F.count("*").alias("n"), F.sum("deg").alias("m"), F.max("deg").alias("max_deg")).withColumn("diameter_at_least", F.lit(max(depth, far["dist"])))
