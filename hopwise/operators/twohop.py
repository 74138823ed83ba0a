"""Exact two-hop index: cluster sweeps first, then pruned searches of the rest, a batch's hubs carried as bits.

A vertex gets a label of a hub unless the index of the batches before answers their distance already, and it does so just
where a hub of those batches, or a member of a cohort, lies on a shortest path between the two. So a search needs no look
at labels: each bit carries whether it came past such a vertex, which is handed on along shortest paths. A hub whose
bits have all done so can give no more labels and is dropped; no batch waits for another.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions import masks
from ..plans.ranking import ranked
from ..plans.store import RoundLog, written
from ..sources.graphs import HopGraph
from .cohorts import pick_cohorts
from .compact import MOST_EDGES, compact, fits, spread
from .landmarks import LandmarkIndex
from .search import sent_along


def batch_sizes(n: int, first: int = 200, growth: float = 1.5, cap: int = 1000) -> list[int]:
    """Sizes of the batches that cover n vertices."""
    out, i = [], 0
    while n > 0:
        size = min(n, cap, int(first * growth**i))
        out.append(size)
        n, i = n - size, i + 1
    return out


# The published sizes of batches.
FIRST, GROWTH, CAP = 200, 1.5, 1000

#: words of 64 hubs that plans search side by side
WORDS_AT_ONCE = 16

ROWS = "v long, word int, dist int, hubs long"


@dataclass
class TwoHopIndex:
    packed: DataFrame  # v, word, dist, hubs: hubs at that distance as bits
    order: DataFrame  # hub, word, bit
    phase_one: LandmarkIndex | None
    seconds: dict[str, float] = field(default_factory=dict)  # of the two phases

    @classmethod
    def build(
        cls, g: HopGraph, r: int = 0, w: int = 64, d: int = 2, first: int = FIRST, growth: float = GROWTH, cap: int = CAP, trim: bool = False, most_edges: int = MOST_EDGES
    ) -> TwoHopIndex:
        """``first=1, growth=1`` is a batch for each hub: the smallest index.

        ``trim`` leaves out labels that better hubs of the same batch answer already. Graphs of ``most_edges`` at most
        are broadcast and a task searches from a word of hubs; those of larger ones are searched by plans. The same labels.
        """
        if g.directed:
            raise ValueError("the index is for undirected graphs")
        began = time.perf_counter()
        cohorts = pick_cohorts(g, r, w, d) if r else None
        phase_one = LandmarkIndex.build(g, cohorts, d, most_edges=most_edges) if r else None
        between = time.perf_counter()
        placed, n = _placed(g, cohorts, first, growth, cap, trim)
        packed = written(_searched_on_broadcast(g, placed, n), "labels") if fits(g, most_edges) else _searched_by_plans(g, placed, n)
        order = placed.where(F.col("i") < n).select(F.col("v").alias("hub"), F.floor(F.col("i") / 64).cast("int").alias("word"), (F.col("i") % 64).cast("int").alias("bit"))
        return cls(packed, order, phase_one, {"phase_one": between - began, "phase_two": time.perf_counter() - between})

    @property
    def labels(self) -> DataFrame:
        """v, hub, dist"""
        return self.packed.join(self.order, "word").where(masks.has(F.col("hubs"), F.col("bit"))).select("v", "hub", "dist")

    def query(self, pairs: DataFrame) -> DataFrame:
        """pid, u, v, est: the least sum over common hubs and phase one; null out of reach. Of the labels, only rows of ends move."""
        ends = written(pairs.select("v").union(pairs.select("u")).distinct(), "ends")
        own = written(self.packed.join(ends, "v", "left_semi"), "end-labels")
        a = own.select(F.col("v").alias("u"), "word", F.col("dist").alias("du"), F.col("hubs").alias("x"))
        b = own.select("v", "word", F.col("dist").alias("dv"), F.col("hubs").alias("y"))
        est = pairs.join(a, "u").join(b, ["v", "word"]).where(masks.meets(F.col("x"), F.col("y"))).select("pid", (F.col("du") + F.col("dv")).alias("est"))
        if self.phase_one is not None:
            est = est.unionByName(self.phase_one.query(pairs).where("est is not null"))
        est = est.groupBy("pid").agg(F.min("est").alias("est"))
        out = pairs.join(est, "pid", "left")
        return out.select("pid", "u", "v", F.when(F.col("u") == F.col("v"), 0).otherwise(F.col("est")).alias("est"))


def _placed(g: HopGraph, cohorts: DataFrame | None, first: int, growth: float, cap: int, trim: bool) -> tuple[DataFrame, int]:
    """v, i, cut, and how many are hubs: hubs by degree from place 0, then members of cohorts. A vertex answers for the hubs from
    place ``cut`` on: those of later batches, if trimmed also the later ones of its own, and all if it is in a cohort."""
    closed = F.lit(False)
    rest = g.vertices
    if cohorts is not None:
        rest = rest.join(cohorts.select(F.col("s").alias("v"), F.lit(True).alias("_in")).distinct(), "v", "left")
        closed = F.coalesce("_in", F.lit(False))
    at = written(ranked(rest.select("v", "deg", closed.alias("closed")), "closed", F.desc("deg"), "v").select("v", "closed", (F.col("rank") - 1).alias("i")), "places")
    n = at.where("not closed").count()
    if trim:
        cut = at.select("v", "i", "closed", (F.col("i") + 1).alias("cut"))
    else:
        ends, end = [], 0
        for size in batch_sizes(n, first, growth, cap):
            ends.append((end, end := end + size))
        batches = g.edges.sparkSession.createDataFrame(ends, "low long, cut long")
        cut = at.join(batches.select(F.explode(F.sequence("low", F.col("cut") - 1)).alias("i"), "cut"), "i", "left")
    return written(cut.select("v", "i", F.when(F.col("closed"), 0).otherwise(F.col("cut")).cast("long").alias("cut")), "placed"), n


def _searched_on_broadcast(g: HopGraph, placed: DataFrame, n: int) -> DataFrame:
    """ROWS: a task searches from the 64 hubs of a word, on the broadcast that the cohorts were swept on."""
    spark, graph = g.edges.sparkSession, compact(g)
    rows = placed.toPandas()
    shared = spark.sparkContext.broadcast(tuple(rows[x].to_numpy(np.int64) for x in ("v", "i", "cut")))

    def search(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, starts, heads = graph.value
        v, i, cuts = shared.value
        at = np.searchsorted(ids, v)
        hubs, cut = np.empty_like(at), np.empty_like(cuts)
        hubs[i], cut[at] = at, cuts
        for frame in frames:
            for word in frame["word"]:
                shift = np.clip(cut - 64 * word, 0, 64)
                passed = np.where(shift < 64, np.uint64(2**64 - 1) << np.minimum(shift, 63).astype(np.uint64), np.uint64(0))
                own = hubs[64 * word : min(64 * word + 64, n)]
                fresh = np.zeros(len(ids), np.uint64)
                fresh[own] = np.uint64(1) << np.arange(len(own), dtype=np.uint64)
                seen, clear, dist = fresh.copy(), fresh.copy(), 0
                while len(at := np.flatnonzero(clear)):
                    yield pd.DataFrame({"v": ids[at], "word": np.int32(word), "dist": np.int32(dist), "hubs": clear[at].view(np.int64)})
                    fresh &= np.bitwise_or.reduce(clear)
                    msg, hit = spread(np.flatnonzero(fresh), starts, heads, [fresh, fresh & ~clear])
                    fresh = msg & ~seen
                    seen |= fresh
                    clear = fresh & ~(hit | passed)
                    dist += 1

    words = -(-n // 64)
    parts = max(1, min(words, 4 * spark.sparkContext.defaultParallelism))
    # words of high degrees have most to do: every task gets some
    dealt = spark.range(0, parts, 1, parts).select(F.explode(F.sequence(F.col("id"), F.lit(max(words, parts) - 1), F.lit(parts))).alias("word")).where(F.col("word") < words)
    return dealt.mapInPandas(search, ROWS)


def _searched_by_plans(g: HopGraph, placed: DataFrame, n: int) -> DataFrame:
    """ROWS: the same by one job a round, WORDS_AT_ONCE words side by side; neighbours are met at most a round apart."""
    keys, none = ["v", "word"], F.lit(0).cast("long")
    word = F.floor(F.col("i") / 64).cast("int")
    shift = F.greatest(F.col("cut") - 64 * F.col("word").cast("long"), F.lit(0))
    passed = F.when(shift < 64, F.call_function("shiftleft", F.lit(-1).cast("long"), shift.cast("int"))).otherwise(none)
    cuts, out = placed.select("v", "cut"), None
    for low in range(0, -(-n // 64), WORDS_AT_ONCE):
        own = placed.where((F.col("i") < n) & word.between(low, low + WORDS_AT_ONCE - 1))
        log, counted = RoundLog(g.edges.sparkSession, "labels", "v long, word int, fresh long, clear long"), Observation()
        start = own.select("v", word.alias("word"), masks.bit(F.col("i") % 64).alias("fresh"))
        log.append(start.withColumn("clear", F.col("fresh")).observe(counted, F.count_if(F.col("clear") != 0).alias("n")))
        while counted.get["n"]:
            alive = log.last().groupBy("word").agg(F.bit_or("clear").alias("alive"))  # one row a word
            frontier = log.last().join(F.broadcast(alive), "word").select(*keys, F.col("fresh").bitwiseAND(F.col("alive")).alias("msg"), masks.minus(F.col("fresh").bitwiseAND(F.col("alive")), F.col("clear")).alias("hit"))
            sent = sent_along(g, frontier.where("msg <> 0")).select(*keys, "msg", "hit", none.alias("seen"))
            both = sent.unionByName(log.since(log.rounds - 2).select(*keys, none.alias("msg"), none.alias("hit"), F.col("fresh").alias("seen")))
            met = both.groupBy(*keys).agg(*(F.bit_or(x).alias(x) for x in ("msg", "hit", "seen")))
            new = met.withColumn("fresh", masks.minus(F.col("msg"), F.col("seen"))).where("fresh <> 0").join(cuts, "v")
            new, counted = new.select(*keys, "fresh", masks.minus(F.col("fresh"), masks.union(F.col("hit"), passed)).alias("clear")), Observation()
            log.append(new.observe(counted, F.count_if(F.col("clear") != 0).alias("n")))
        one = log.since().where("clear <> 0").select("v", "word", F.col("round").alias("dist"), F.col("clear").alias("hubs"))
        out = one if out is None else out.unionByName(one)
    return g.edges.sparkSession.createDataFrame([], ROWS) if out is None else out


def label_inflation(batched: DataFrame, one_by_one: DataFrame) -> float:
    """Labels of a build in batches over labels of a build of one search at a time."""
    return batched.count() / max(1, one_by_one.count())
