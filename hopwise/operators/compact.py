"""Searches by tasks on a broadcast undirected graph of checked size, 64 sources to a word of bits."""

from __future__ import annotations

import sys
import weakref
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import HopGraph

# tasks need not have this package
cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: graphs of more edges are not broadcast (4 bytes an edge in every task)
MOST_EDGES = 16_000_000
#: edges that are looked at in one step: bounds what a step holds
STEP = 1 << 22


#: what was counted and broadcast of a graph, for as long as the graph is used
_COUNTED, _BROADCAST = weakref.WeakKeyDictionary(), weakref.WeakKeyDictionary()


def fits(g: HopGraph, most_edges: int = MOST_EDGES) -> bool:
    """Whether the graph is undirected and of ``most_edges`` at most; edges are counted once, where they are."""
    if g.directed:
        return False
    if g.size is not None:
        return g.size <= most_edges
    if g not in _COUNTED:
        _COUNTED[g] = g.edges.count()
    return _COUNTED[g] <= most_edges


def compact(g: HopGraph):
    """Broadcast (ids, starts, heads): vertices in the order of ids, and the places of the neighbours of each. Tasks number the
    edges, one of each two orientations reaches the driver, at 8 bytes; all searches of a graph share one broadcast."""
    if g in _BROADCAST:
        return _BROADCAST[g]
    sc = g.edges.sparkSession.sparkContext
    ids = np.sort(g.vertices.select("v").toPandas()["v"].to_numpy(np.int64))
    known = sc.broadcast(ids)

    def number(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            a, b = (np.searchsorted(known.value, frame[x].to_numpy(np.int64)).astype(np.int32).tobytes() for x in ("src", "dst"))
            yield pd.DataFrame({"a": [a], "b": [b]})

    parts = (g.edges if g.stored is None else g.stored).select("src", "dst").where("src < dst").mapInPandas(number, "a binary, b binary").collect()
    a, b = (np.frombuffer(b"".join(r[x] for r in parts), np.int32) for x in ("a", "b"))
    del parts
    both = np.concatenate([a.astype(np.int64) << 32 | b, b.astype(np.int64) << 32 | a])
    both.sort()
    starts = np.concatenate([[0], np.cumsum(np.bincount(a, minlength=len(ids)) + np.bincount(b, minlength=len(ids)))]).astype(np.int64)
    _BROADCAST[g] = sc.broadcast((ids, starts, (both & 0xFFFFFFFF).astype(np.int32)))
    return _BROADCAST[g]


def held(g: HopGraph) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """(ids, starts, heads) on the driver, if the graph has been broadcast."""
    return _BROADCAST[g].value if g in _BROADCAST else None


def within(at: int, radius: int, starts: np.ndarray, heads: np.ndarray) -> np.ndarray:
    """The places within ``radius`` hops of one, without it."""
    met = np.zeros(len(starts) - 1, bool)
    met[at], front = True, np.array([at])
    for _ in range(radius):
        sizes = starts[front + 1] - starts[front]
        near = heads[np.arange(sizes.sum()) + np.repeat(starts[front] - np.cumsum(sizes) + sizes, sizes)]
        front = np.unique(near[~met[near]])
        met[front] = True
    met[at] = False
    return np.flatnonzero(met)


def spread(front: np.ndarray, starts: np.ndarray, heads: np.ndarray, values: list[np.ndarray]) -> list[np.ndarray]:
    """For each of ``values`` the union of what neighbours hold; nothing is held outside of ``front``."""
    sizes = starts[front + 1] - starts[front]
    outs = [np.zeros(len(x), np.uint64) for x in values]
    if 16 * sizes.sum() < len(heads):
        to = heads[np.arange(sizes.sum()) + np.repeat(starts[front] - np.cumsum(sizes) + sizes, sizes)]
        order = np.argsort(to, kind="stable")
        met, at = np.unique(to[order], return_index=True)
        if len(met):
            for x, out in zip(values, outs, strict=True):
                out[met] = np.bitwise_or.reduceat(np.repeat(x[front], sizes)[order], at)
        return outs
    # every vertex of an edge list has an edge, so no run is empty
    bounds = np.unique(np.append(np.searchsorted(starts, np.arange(0, len(heads), STEP)), len(starts) - 1))
    for low, high in zip(bounds, bounds[1:], strict=False):
        near = heads[starts[low] : starts[high]]
        for x, out in zip(values, outs, strict=True):
            out[low:high] = np.bitwise_or.reduceat(x[near], starts[low:high] - starts[low])
    return outs


def rounds(at: np.ndarray, starts: np.ndarray, heads: np.ndarray, bits: np.ndarray | None = None, d: int | None = None) -> Iterator[np.ndarray]:
    """Round by round the bits that are new at each vertex, from the places ``at`` of at most 64 sources.

    ``bits``: the bit of each source, by default its number. With ``d`` a vertex takes part for d rounds after its first.
    """
    fresh = np.zeros(len(starts) - 1, np.uint64)
    np.bitwise_or.at(fresh, at, np.uint64(1) << np.asarray(np.arange(len(at)) if bits is None else bits, np.uint64))
    seen, until, i = fresh.copy(), np.full(len(fresh), -1), 0
    while fresh.any():
        yield fresh
        i += 1
        fresh = spread(np.flatnonzero(fresh), starts, heads, [fresh])[0] & ~seen
        if d is not None:
            until[(seen != 0) & (until < 0)] = i - 1 + d
            fresh[(until >= 0) & (until < i)] = 0
        seen |= fresh


def placed(ids: np.ndarray, of: np.ndarray) -> np.ndarray:
    """The place of each id, -1 if it is not a vertex."""
    at = np.searchsorted(ids, of)
    return np.where(ids[np.minimum(at, len(ids) - 1)] == of, at, -1) if len(ids) else np.full(len(of), -1)


def distances(g: HopGraph, sources: DataFrame) -> DataFrame:
    """(s, v, dist) from any ``sources(s)``."""
    shared, parts = compact(g), g.edges.sparkSession.sparkContext.defaultParallelism

    def search(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, starts, heads = shared.value
        for frame in frames:
            own = frame["s"].to_numpy(np.int64)
            at = placed(ids, own)
            yield pd.DataFrame({"s": own[at < 0], "v": own[at < 0], "dist": np.int32(0)})
            own, at = own[at >= 0], at[at >= 0]
            for low in range(0, len(at), 64):
                for dist, fresh in enumerate(rounds(at[low : low + 64], starts, heads)):
                    for bit, s in enumerate(own[low : low + 64]):
                        met = np.flatnonzero(fresh & np.uint64(1 << bit))
                        yield pd.DataFrame({"s": s, "v": ids[met], "dist": np.int32(dist)})

    return sources.select(F.col("s").cast("long").alias("s")).distinct().repartition(parts, "s").mapInPandas(search, "s long, v long, dist int")


def pair_distances(g: HopGraph, pairs: DataFrame) -> DataFrame:
    """pid, dist of each of ``pairs(pid, u, v)``, null out of reach; a word is searched until its pairs have met."""
    shared, parts = compact(g), g.edges.sparkSession.sparkContext.defaultParallelism
    kind = pairs.schema["pid"].dataType.simpleString()

    def search(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, starts, heads = shared.value
        for frame in frames:
            u, v = (frame[x].to_numpy(np.int64) for x in ("u", "v"))
            found = np.where(u == v, 0, -1)
            a, b = placed(ids, u), placed(ids, v)
            own = np.unique(a[(a >= 0) & (b >= 0) & (u != v)])
            for low in range(0, len(own), 64):
                some = own[low : low + 64]
                left = np.flatnonzero(np.isin(a, some) & (b >= 0) & (u != v))
                for dist, fresh in enumerate(rounds(some, starts, heads)):
                    bit = np.searchsorted(some, a[left]).astype(np.uint64)
                    met = (fresh[b[left]] >> bit) & np.uint64(1) == 1
                    found[left[met]] = dist
                    left = left[~met]
                    if not len(left):
                        break
            yield pd.DataFrame({"pid": frame["pid"], "dist": pd.array(found, "Int32")}).assign(dist=lambda x: x["dist"].mask(x["dist"] < 0))

    return pairs.select("pid", "u", "v").repartition(parts, "u").mapInPandas(search, f"pid {kind}, dist int")


def arrivals(g: HopGraph, cohorts: DataFrame, d: int | None = 2, stop_after: int | None = None) -> DataFrame:
    """(v, cid, word, round, fresh) of the cohorts ``(cid, bit, s)``: the arrivals of ``cluster_sweep``, a task for each 64
    members of a cohort. A member that is no vertex arrives at itself alone."""
    shared = compact(g)

    def sweep(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, starts, heads = shared.value
        for frame in frames:
            for cid, word, s, bit in zip(frame["cid"], frame["word"], frame["s"], frame["bit"], strict=True):
                own, bits = np.asarray(s, np.int64), np.asarray(bit, np.uint64)
                at = placed(ids, own)

                def rows(v: np.ndarray, i: int, fresh: np.ndarray, cid=cid, word=word) -> pd.DataFrame:
                    return pd.DataFrame({"v": v, "cid": np.int32(cid), "word": np.int32(word), "round": np.int32(i), "fresh": fresh.view(np.int64)})

                yield rows(own[at < 0], 0, np.uint64(1) << bits[at < 0])
                for i, fresh in enumerate(rounds(at[at >= 0], starts, heads, bits[at >= 0], d)):
                    if stop_after is not None and i > stop_after:
                        break
                    met = np.flatnonzero(fresh)
                    yield rows(ids[met], i, fresh[met])

    return _words(g, cohorts).mapInPandas(sweep, "v long, cid int, word int, round int, fresh long")


def _words(g: HopGraph, cohorts: DataFrame) -> DataFrame:
    """cid, word, s, bit: a row for each 64 members of a cohort, dealt over tasks."""
    member = F.struct(F.col("s").cast("long").alias("s"), (F.col("bit") % 64).cast("long").alias("bit"))
    members = cohorts.select(F.col("cid").cast("int").alias("cid"), F.floor(F.col("bit") / 64).cast("int").alias("word"), member.alias("m")).distinct()
    dealt = members.repartition(g.edges.sparkSession.sparkContext.defaultParallelism, "cid", "word")
    return dealt.groupBy("cid", "word").agg(F.collect_list("m").alias("m")).select("cid", "word", "m.s", "m.bit")  # the members of 64 bits


def sweep_records(g: HopGraph, cohorts: DataFrame, d: int = 2) -> DataFrame:
    """(v, cid, word, base, m): the records of ``arrivals``. A record is complete d rounds after its first, so the task that
    sweeps its word puts it together and holds the arrivals of d + 1 rounds."""
    shared = compact(g)
    offsets = [f"m{k}" for k in range(d + 1)]

    def sweep(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, starts, heads = shared.value
        for frame in frames:
            for cid, word, s, bit in zip(frame["cid"], frame["word"], frame["s"], frame["bit"], strict=True):
                own, bits = np.asarray(s, np.int64), np.asarray(bit, np.uint64)
                at = placed(ids, own)

                def rows(v: np.ndarray, base: int, marks: list[np.ndarray], cid=cid, word=word) -> pd.DataFrame:
                    named = {name: x.view(np.int64) for name, x in zip(offsets, marks, strict=True)}
                    return pd.DataFrame({"v": v, "cid": np.int32(cid), "word": np.int32(word), "base": np.int32(base)} | named)

                def complete(base: int, recent: list) -> pd.DataFrame:
                    """Records of the first of d + 1 rounds; what it met for the first time."""
                    met, _, first = recent[0]
                    met, marks = met[first], []
                    for where, values, _ in recent:
                        place = np.minimum(np.searchsorted(where, met), max(len(where) - 1, 0))
                        marks.append(np.where(where[place] == met, values[place], 0).astype(np.uint64) if len(where) else np.zeros(len(met), np.uint64))
                    return rows(ids[met], base, marks)

                out, known = np.flatnonzero(at < 0), np.zeros(len(ids), bool)
                # an id that is no vertex may come under several bits
                alone = np.unique(own[out])
                if len(alone):
                    mark = np.zeros(len(alone), np.uint64)
                    np.bitwise_or.at(mark, np.searchsorted(alone, own[out]), np.uint64(1) << bits[out])
                    yield rows(alone, 0, [mark, *[np.zeros(len(alone), np.uint64)] * d])
                recent: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
                none, i = np.zeros(0, np.int64), 0
                for i, fresh in enumerate(rounds(at[at >= 0], starts, heads, bits[at >= 0], d), 1):
                    met = np.flatnonzero(fresh)
                    recent.append((met, fresh[met], ~known[met]))
                    known[met] = True
                    if len(recent) > d:
                        yield complete(i - 1 - d, recent)
                        recent.pop(0)
                base = i - len(recent)
                while recent:
                    yield complete(base, recent + [(none, none.view(np.uint64), none.view(bool)[:0])] * (d + 1 - len(recent)))
                    recent.pop(0)
                    base += 1

    rows = _words(g, cohorts).mapInPandas(sweep, f"v long, cid int, word int, base int, {', '.join(f'{x} long' for x in offsets)}")
    return rows.select("v", "cid", "word", "base", F.array(*offsets).alias("m"))
