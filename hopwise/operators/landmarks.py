"""Approximate distance index: landmarks alone, or cohorts of them as offset-mask records."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..functions import masks
from ..plans.ranking import ranked
from ..plans.store import RoundLog, written
from ..sources.graphs import HopGraph
from .compact import MOST_EDGES, fits, pair_distances
from .search import bfs_each, cluster_sweep, components, sent_along

ENCODINGS = ("full", "complement", "anchor")


def sample_pairs(g: HopGraph, count: int, seed: int = 0) -> DataFrame:
    """pid, u, v: ``count`` deterministic pairs of different vertices, spread over the whole square.

    Both ends are drawn by hashes of the pair's number among the vertices in the order of their ids.
    """
    v = written(ranked(g.vertices.select("v"), "v").select("v", (F.col("rank") - 1).alias("i")), "numbered")
    n = v.count()
    draw = lambda k: F.conv(F.substring(F.md5(F.concat_ws("-", F.lit(seed), F.col("id"), F.lit(k))), 1, 12), 16, 10).cast("long") % n
    at = g.edges.sparkSession.range(count).select(F.col("id").alias("pid"), draw("a").alias("a"), draw("b").alias("b")).where("a <> b")
    return at.join(v.select(F.col("i").alias("a"), F.col("v").alias("u")), "a").join(v.select(F.col("i").alias("b"), "v"), "b").select("pid", "u", "v")


def plain_index(g: HopGraph, landmarks: DataFrame) -> DataFrame:
    """v, h, dist: the long layout."""
    return bfs_each(g, landmarks).select("v", F.col("s").alias("h"), "dist")


def wide(index: DataFrame) -> DataFrame:
    """v, marks: the wide layout of a plain index, one row a vertex with (h, dist) of its landmarks."""
    return index.groupBy("v").agg(F.sort_array(F.collect_list(F.struct("h", "dist"))).alias("marks"))  # as many as landmarks


def plain_query(index: DataFrame, pairs: DataFrame) -> DataFrame:
    """pid, est: the least sum over a common landmark; 0 for u = v, null without one. The index may be long or wide."""
    if "marks" in index.columns:
        a, b = index.select(F.col("v").alias("u"), F.col("marks").alias("x")), index.select("v", F.col("marks").alias("y"))
        sums = masks.once(F.map_from_entries("y"), lambda y: F.transform("x", lambda x: x["dist"] + F.try_element_at(y, x["h"])))
        est = pairs.join(a, "u").join(b, "v").select("pid", F.array_min(sums).alias("est"))
    else:
        a = index.select(F.col("v").alias("u"), "h", F.col("dist").alias("du"))
        b = index.select("v", "h", F.col("dist").alias("dv"))
        est = pairs.join(a, "u").join(b, ["v", "h"]).groupBy("pid").agg(F.min(F.col("du") + F.col("dv")).alias("est"))
    return pairs.join(est, "pid", "left").select("pid", F.when(F.col("u") == F.col("v"), 0).otherwise(F.col("est")).alias("est"))


@dataclass
class LandmarkIndex:
    """v, recs: one row per vertex with a record (cid, base, m) of every cohort that reaches it, in the order of cid."""

    table: DataFrame
    d: int
    encoding: str = "full"
    whole: dict[int, int] | None = None  # cid -> mask of all members

    @classmethod
    def build(cls, g: HopGraph, cohorts: DataFrame, d: int = 2, encoding: str = "full", mode: str | None = None, most_edges: int = MOST_EDGES) -> LandmarkIndex:
        """``mode`` is that of the sweep: by default an undirected graph of ``most_edges`` at most is broadcast, others are pushed along."""
        if encoding not in ENCODINGS or encoding == "anchor" and d != 2:
            raise ValueError("encoding is full, complement, or for d = 2 anchor")
        found = cohorts.groupBy("cid").agg(F.bit_or(masks.bit(F.col("bit") % 64)).alias("m"), F.max("bit").alias("last")).collect()
        if any(r["last"] > 63 for r in found):
            raise ValueError("a cohort of an index has 64 members at most")
        whole = {r["cid"]: r["m"] for r in found}
        mode = mode or ("broadcast" if fits(g, most_edges) else "push")
        recs = cluster_sweep(g, cohorts, d, mode, True, None, None, True)
        if encoding == "complement":
            recs = recs.withColumn("m", F.slice("m", 1, d))
        elif encoding == "anchor":  # base becomes the anchor's distance; masks one below it and at it
            off = F.array_min(F.transform("m", lambda m, i: F.when(masks.has(m, F.lit(0)), i)))
            at = lambda i: F.coalesce(F.get("m", i), F.lit(0).cast("long"))
            recs = recs.withColumn("off", off).withColumn("m", F.array(at(F.col("off") - 1), at(F.col("off")))).withColumn("base", F.col("base") + F.col("off"))
        rows = recs.groupBy("v").agg(F.sort_array(F.collect_list(F.struct("cid", "base", "m"))).alias("recs"))
        return cls(written(rows, "landmarks"), d, encoding, whole)

    def first(self, n: int) -> LandmarkIndex:
        """The index of the first ``n`` cohorts alone."""
        return LandmarkIndex(self.table.withColumn("recs", F.filter("recs", lambda x: x["cid"] < n)), self.d, self.encoding, self.whole)

    def _restored(self, masks_: Column, cid: Column) -> Column:
        """The d+1 masks of a record of the complement form: what no earlier offset holds is at the last."""
        whole = F.create_map(*(x for c, m in self.whole.items() for x in (F.lit(c), F.lit(m)))) if self.whole else F.lit(None)
        held = F.aggregate(masks_, F.lit(0).cast("long"), lambda s, m: s.bitwiseOR(m))
        return F.concat(masks_, F.array(masks.minus(F.element_at(whole, cid), held)))

    def _offset(self, a: Column, b: Column) -> Column:
        """The least i + j at which masks of both ends meet, tried from low sums up."""
        if self.encoding == "anchor":
            near = masks.meets(F.get(a, 0), F.get(b, 0))
            mid = masks.meets(F.get(a, 0), F.get(b, 1)) | masks.meets(F.get(a, 1), F.get(b, 0))
            return F.when(near, -2).when(mid, -1).otherwise(0)
        out = None
        for s in range(2 * self.d + 1):
            met = F.lit(False)
            for i in range(max(0, s - self.d), min(s, self.d) + 1):
                met = met | masks.meets(F.get(a, i), F.get(b, s - i))
            out = F.when(met, s) if out is None else out.when(met, s)
        return out

    def query(self, pairs: DataFrame) -> DataFrame:
        """pid, est: never below the distance; 0 for u = v, null without a common cohort.

        The rows of both ends meet the pair as they are; records of one cohort meet inside the row. Of the index, only
        rows of ends move, none if the pairs are few enough to be broadcast.
        """
        a = self.table.select(F.col("v").alias("u"), F.col("recs").alias("x"))
        b = self.table.select("v", F.map_from_entries(F.transform("recs", lambda y: F.struct(y["cid"], y))).alias("y"))

        def full(rec: Column) -> Column:
            return self._restored(rec["m"], rec["cid"]) if self.encoding == "complement" else rec["m"]

        def one(x: Column, y: Column) -> Column:
            met = masks.once(full(x), lambda ma: masks.once(full(y), lambda mb: self._offset(ma, mb)))
            return F.when(y.isNotNull(), x["base"] + y["base"] + met)

        sums = F.transform("x", lambda x: masks.once(F.try_element_at("y", x["cid"]), lambda y: one(x, y)))
        est = pairs.join(a, "u").join(b, "v").select("pid", F.array_min(sums).alias("est"))
        return pairs.join(est, "pid", "left").select("pid", F.when(F.col("u") == F.col("v"), 0).otherwise(F.col("est")).alias("est"))


def exact_pairs(g: HopGraph, pairs: DataFrame, most_edges: int = MOST_EDGES) -> DataFrame:
    """pid, truth: the distance from u to v; null out of reach. An undirected graph of ``most_edges`` at most is broadcast and
    searched with sources as bits; the pairs of others meet in two-sided searches."""
    if fits(g, most_edges):
        return written(pair_distances(g, pairs).select("pid", F.col("dist").alias("truth")), "truth")
    return two_sided(g, pairs)


def two_sided(g: HopGraph, pairs: DataFrame) -> DataFrame:
    """pid, truth: two-sided searches, from u along the edges and from v against them; null out of reach.

    A round grows the side with the smaller frontier by one hop, for all pairs that have not met. Balls of radii i and j
    that have no vertex in common are more than i + j apart, so the first round in which the two frontiers share one has
    the distance. Pairs of different components are out of reach without a search.
    """
    spark, kind = g.edges.sparkSession, pairs.schema["pid"].dataType.simpleString()
    part = written(components(g), "components")
    same = pairs.where("u <> v").join(part.select(F.col("v").alias("u"), "component"), "u").join(part, ["v", "component"])
    left = written(same.select("pid", "u", "v"), "open-pairs")
    sides = [("u", g, RoundLog(spark, "from-u", "s long, v long")), ("v", g.incoming(), RoundLog(spark, "from-v", "s long, v long"))]
    answers, sizes = RoundLog(spark, "answers", f"pid {kind}, truth int"), []
    for end, _, log in sides:
        counted = Observation()
        own = left.select(F.col(end).cast("long").alias("s")).distinct()
        log.append(own.select("s", F.col("s").alias("v")).observe(counted, F.count("*").alias("n")))
        sizes.append(counted.get["n"])
    answers.append(pairs.where("u = v").select("pid", F.lit(0).alias("truth")))
    while not left.isEmpty():
        i = 0 if sizes[0] <= sizes[1] else 1
        end, graph, log = sides[i]
        frontier = log.last().join(left.select(F.col(end).alias("s")), "s", "left_semi").select("v", "s")
        recent, counted = log.since(0 if g.directed else log.rounds - 2), Observation()
        both = sent_along(graph, frontier).select("v", "s", F.lit(True).alias("met")).unionByName(recent.select("v", "s", F.lit(False).alias("met")))
        new = both.groupBy("v", "s").agg(F.every("met").alias("met")).where("met").select("s", "v")
        log.append(new.observe(counted, F.count("*").alias("n")))
        sizes[i] = counted.get["n"]
        a, b = (at.last().select(F.col("s").alias(of), F.col("v").alias("x")) for of, _, at in sides)
        met = left.join(a, "u").join(b, ["v", "x"]).select("pid").distinct()
        answers.append(met.select("pid", F.lit(sum(at.rounds - 1 for _, _, at in sides)).alias("truth")))
        apart = left.join(answers.last(), "pid", "left_anti").join(log.last().select(F.col("s").alias(end)), end, "left_semi")
        left = written(apart.select("pid", "u", "v"), "open-pairs")
    return pairs.select("pid").join(answers.since().select("pid", "truth"), "pid", "left")


def local_meet(g: HopGraph, pairs: DataFrame, tau: int, skip: DataFrame | None = None, scope: str = "side") -> DataFrame:
    """pid, est: the least sum over vertices in both balls, each the first ``tau`` vertices by (distance, id).

    ``scope="total"`` shares tau between the two sides. Vertices of ``skip(s)`` are not visited: a query that also
    asks the index has their answers already. A ball that is full grows no further; of what a round reaches, only the
    first by id that still fit are kept.
    """
    if scope not in ("side", "total"):
        raise ValueError("scope is side or total")
    room = tau if scope == "side" else max(1, tau // 2)
    ends = pairs.select(F.col("u").alias("s")).union(pairs.select(F.col("v").alias("s"))).distinct()
    edges = g.edges if skip is None else g.edges.join(skip.select(F.col("s").alias("dst")), "dst", "left_anti").select("src", "dst")
    # of a hub, a ball of ``room`` can use the first by id that it has not visited: they are among the first 2 * room
    first = edges.withColumn("place", F.row_number().over(Window.partitionBy("src").orderBy("dst"))).where(F.col("place") <= 2 * room)
    inner = HopGraph(written(first.select("src", "dst"), "first-edges"), g.directed)
    log, counted = RoundLog(g.edges.sparkSession, "balls", "s long, v long"), Observation()
    log.append(ends.select("s", F.col("s").alias("v")).observe(counted, F.count("*").alias("n")))
    while counted.get["n"]:
        left = log.since().groupBy("s").agg((room - F.count("*")).alias("left")).where("left > 0")
        frontier = log.last().select("v", "s").join(left.select("s"), "s", "left_semi")
        sent = sent_along(inner, frontier)
        recent = log.since() if g.directed else log.since(log.rounds - 2)
        both = sent.select("s", "v", F.lit(True).alias("met")).unionByName(recent.select("s", "v", F.lit(False).alias("met")))
        new = both.groupBy("s", "v").agg(F.every("met").alias("met")).where("met")
        place = F.row_number().over(Window.partitionBy("s").orderBy("v"))
        kept = new.join(left, "s").withColumn("place", place).where(F.col("place") <= F.least("left", F.lit(room))).select("s", "v")
        counted = Observation()
        log.append(kept.observe(counted, F.count("*").alias("n")))
    state = log.since()
    a = state.select(F.col("s").alias("u"), F.col("v").alias("x"), F.col("round").alias("du"))
    b = state.select(F.col("s").alias("v"), F.col("v").alias("x"), F.col("round").alias("dv"))
    est = pairs.join(a, "u").join(b, ["v", "x"]).groupBy("pid").agg(F.min(F.col("du") + F.col("dv")).alias("est"))
    return pairs.join(est, "pid", "left").select("pid", "est")


def least_answer(a: DataFrame, b: DataFrame) -> DataFrame:
    """pid, est: the smaller of two answers."""
    return a.join(b.withColumnRenamed("est", "other"), "pid").select("pid", F.least("est", "other").alias("est"))
