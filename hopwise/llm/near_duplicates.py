"""Near-duplicate classes by DartMinHash signatures.

An element is a run of five consecutive words (a shorter text that has a word is one element). Elements throw
darts: element e with weight w owns the region [0, w] of weights over all ranks, cut into strips of unit height;
on a strip, darts fall as a Poisson process of rate 1 along the rank axis, at places that depend on the hash of
(element, strip) alone. A dart's hash also gives its coordinate, one of k, and its height in the strip: in a
strip that the weight fills in part, darts above the weight are not thrown. Each coordinate keeps its earliest
dart. Two sets keep the same dart at a coordinate with the probability of their weighted Jaccard similarity,
and only ranks up to t / (total weight), t = k (ln k + 2), need to be looked at, so the work is the elements
plus k ln k darts and not elements times k. A coordinate that stays empty is looked for again at higher ranks.

Bands of consecutive coordinates are hashed into buckets; texts that share one are candidates, and a pair is a
link if its elements have a Jaccard similarity of ``least`` or more, counted on the texts themselves. Classes
are the connected components of the links.

At any size
* Texts that are equal byte for byte are one node (known by their MD5) before anything is joined, so a group of
  copies costs one row; null is the empty text; texts without a word are near-duplicates of their copies alone.
* A bucket's nodes are first linked to one representative: as many pairs as nodes. Inside a component no further
  pair is needed. The nodes of buckets that still hold several components (a passage that many texts share does
  this) are joined by their rarest elements instead of all pairs: two sets of the wanted similarity share one of
  the rarest size - least * size + 1 of each, at places that leave room for the overlap. Rare elements of few nodes
  give their pairs at once. Of common ones a block of picks (16 a bucket, in each turn four times as many) is tried
  against all nodes of the bucket in other components whose places allow a link, and leaves the bucket: every link of
  a pick has been tried. This goes on until a bucket is of one component or small, so no link of different components
  that share a bucket is lost, and a turn makes at most (picks x nodes) pairs, dealt over tasks by the node.
* Texts stay where they are unless their node shares a bucket: rows are sifted by a broadcast table of bits (at most 2^20
  words) before they are joined exactly. Pairs to verify are written first, so that where they are few the texts
  are not dealt again.
* Counts combine before the shuffle; rows of hot copies, hot classes and hot buckets are dealt over tasks by a salt.
  Of a pair to verify one text moves; the other is sent once for some hundreds of pairs.
* Components are labelled by alternating neighbour minima on tables in the shared folder; the driver sees counts.

Rows that repeat are copies. The class id is the least doc_id of a class (null if all are null); classes of unrelated
texts under one id share it, and stay apart by their root. An empty table
gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordHashes, forget, hot_join, id_as_string, id_back, mixed, written

WORDS = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
SHINGLE = 5


def words_of(text: str | None) -> list[bytes]:
    return WORDS.findall(text.encode("utf-8", "surrogatepass").lower()) if text else []


class _Bytes(WordHashes):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        value = self[word] = xxhash.xxh64_intdigest(word)
        return value


def elements_of(text: str | None, hashes: _Bytes, size: int = SHINGLE) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the runs of ``size`` words."""
    words = words_of(text)
    if not words:
        return np.zeros(0, np.uint64)
    h = hashes.of(words)
    n = max(1, len(h) - size + 1)
    out = np.zeros(n, np.uint64)
    for k in range(min(size, len(h))):
        out = mixed(out * np.uint64(0x100000001B3) + h[k : k + n])
    return np.unique(out)


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    if not len(a) or not len(b):
        return 0.0
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


def _uniform(x: np.ndarray) -> np.ndarray:
    return ((x >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53


def darts(elements: np.ndarray, weights: np.ndarray, limits: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(element number, coordinate, rank, dart hash) of all darts of a rank below the element's limit."""
    strips = np.ceil(weights).astype(np.int64)
    owner = np.repeat(np.arange(len(elements)), strips)
    strip = np.arange(len(owner)) - np.repeat(np.cumsum(strips) - strips, strips)
    filled = np.minimum(1.0, weights[owner] - strip)
    partly = bool((filled < 1).any())
    seed = mixed(elements[owner] + strip.astype(np.uint64) * np.uint64(0xA24BAED4963EE407))
    rank, limit, found = np.zeros(len(seed)), limits[owner], []
    while len(seed):
        seed = mixed(seed + np.uint64(0x9FB21C651E98DF25))
        rank = rank - np.log(_uniform(seed))
        stay = rank < limit
        seed, rank, limit, owner, filled = seed[stay], rank[stay], limit[stay], owner[stay], filled[stay]
        if partly:
            hit = _uniform(mixed(seed ^ np.uint64(0x5851F42D4C957F2D))) < filled
            found.append((owner[hit], rank[hit], seed[hit]))
        else:
            found.append((owner, rank, seed))
    of, ranks, dart = (np.concatenate(x) for x in zip(*found, strict=True))
    return of, (mixed(dart ^ np.uint64(0x2545F4914F6CDD1D)) % np.uint64(k)).astype(np.int64), ranks, dart


def signatures(sets: list[np.ndarray], weights: list[np.ndarray] | None = None, k: int = 192) -> np.ndarray:
    """A row of k dart hashes per set, at one go; ``weights`` (positive) default to 1 each. A set needs an element."""
    out = np.zeros((len(sets), k), np.uint64)
    todo, factor = np.arange(len(sets)), 1.0
    while len(todo):
        sizes = np.array([len(sets[i]) for i in todo])
        of_set = np.repeat(np.arange(len(todo)), sizes)
        elements = np.concatenate([sets[i] for i in todo])
        heavy = np.ones(len(elements)) if weights is None else np.concatenate([np.asarray(weights[i], float) for i in todo])
        limits = factor * k * (np.log(k) + 2) / np.bincount(of_set, heavy)
        of, coordinate, rank, dart = darts(elements, heavy, limits[of_set], k)
        cell = of_set[of] * k + coordinate
        best = np.full(len(todo) * k, np.inf)
        np.minimum.at(best, cell, rank)
        first = rank == best[cell]
        got = np.zeros(len(todo) * k, np.uint64)
        got[cell[first]] = dart[first]
        full = np.isfinite(best).reshape(-1, k).all(axis=1)
        out[todo[full]] = got.reshape(-1, k)[full]
        todo, factor = todo[~full], factor * 1.5
    return out


def signature(elements: np.ndarray, weights: np.ndarray | None = None, k: int = 192) -> np.ndarray:
    return signatures([elements], None if weights is None else [weights], k)[0]


def in_batches(sizes: list[int], most: int = 60_000) -> Iterator[list[int]]:
    """Numbers of sets with an element, in runs of about ``most`` elements."""
    run, total = [], 0
    for i, n in enumerate(sizes):
        if n:
            run.append(i)
            total += n
        if total >= most:
            yield run
            run, total = [], 0
    if run:
        yield run


def bands_of(sig: np.ndarray, rows: int) -> np.ndarray:
    """One 64-bit key per band, different bands never sharing one."""
    grid = sig.reshape(-1, rows)
    out = np.arange(len(grid), dtype=np.uint64) * np.uint64(0xD1342543DE82EF95)
    for j in range(rows):
        out = mixed(out * np.uint64(0x100000001B3) + grid[:, j])
    return out.view(np.int64)


def node_of(text: str = "text"):
    return F.unhex(F.md5(F.coalesce(F.col(text), F.lit("")).cast("binary")))


def banded(docs: DataFrame, bands: int, rows: int) -> DataFrame:
    """doc_id, node, bands: a row per row of ``docs``; no bands for texts without a word."""

    def sign(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        hashes = _Bytes()
        for frame in frames:
            sets = [elements_of(text, hashes) for text in frame["text"]]
            out = [np.zeros(0, np.int64)] * len(sets)
            for run in in_batches([len(e) for e in sets]):
                for i, sig in zip(run, signatures([sets[i] for i in run], k=bands * rows), strict=True):
                    out[i] = bands_of(sig, rows)
            yield pd.DataFrame({"doc_id": frame["doc_id"], "node": frame["node"], "bands": out})

    made = docs.select(id_as_string(docs, "doc_id"), node_of().alias("node"), "text").mapInPandas(sign, "doc_id string, node binary, bands array<long>")
    return made.withColumn("doc_id", id_back(docs, "doc_id"))


def sifted(rows: DataFrame, wanted: DataFrame, key: str | list[str] = "node", most: int = 1 << 20) -> DataFrame:
    """All of ``rows`` whose ``key`` (one column or several) is one of ``wanted``'s, and few others, without a shuffle of ``rows``.

    A key sets a bit of a table of as many words of 64 bits as there are keys, ``most`` at most: it is broadcast. One
    that is full lets more rows through, and none is lost.
    """
    n = min(max(wanted.count(), 1), most)
    h = F.xxhash64(*([key] if isinstance(key, str) else key))
    word, bit = F.pmod(F.shiftrightunsigned(h, 6), F.lit(n)), F.pmod(h, F.lit(64)).cast("int")
    one = F.call_function("shiftleft", F.lit(1).cast("long"), bit)
    words = wanted.select(word.alias("_word"), one.alias("_bit")).groupBy("_word").agg(F.bit_or("_bit").alias("_bits"))
    met = rows.withColumn("_word", word).join(F.broadcast(words), "_word").where(F.col("_bits").bitwiseAND(one) != 0)
    return met.select(*rows.columns)


def verified(pairs: DataFrame, texts: DataFrame, least: float, each: int = 256) -> DataFrame:
    """The rows of ``pairs(a, b)`` whose texts are similar enough.

    Rows with b's text come behind the text of their a, which is sent once for about ``each`` pairs.
    """

    def compare(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        hashes, head, own = _Bytes(), None, None
        for frame in frames:
            keep = []
            for a, b, text in zip(frame["a"], frame["b"], frame["text"], strict=True):
                if b is None:
                    head, own = a, elements_of(text, hashes)
                elif a == head and jaccard(own, elements_of(text, hashes)) >= least:
                    keep.append((a, b))
            if keep:
                yield pd.DataFrame(keep, columns=["a", "b"])

    sizes = written(pairs.groupBy("a").agg(F.count("*").alias("size")), "pair-counts")
    parts = F.ceil(F.col("size") / each).cast("int")
    heads = sizes.join(texts.withColumnRenamed("node", "a"), "a").select("a", F.explode(F.sequence(F.lit(1), parts)).alias("part"), F.lit(None).cast("binary").alias("b"), "text")
    dealt = written(hot_join(pairs, sizes, ["a"], "size", ["b"]).select("a", (F.pmod(F.xxhash64("b"), parts) + 1).cast("int").alias("part"), "b"), "dealt")
    rows = dealt.join(texts.withColumnRenamed("node", "b"), "b").select("a", "part", "b", "text")
    both = heads.unionByName(rows).repartition("a", "part").sortWithinPartitions("a", "part", F.col("b").asc_nulls_first())
    return both.select("a", "b", "text").mapInPandas(compare, "a binary, b binary")


def components(edges: DataFrame) -> DataFrame:
    """node, root: for every node of ``edges(a, b)`` the least node of its component."""
    now = written(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    measure = lambda df: df.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
    before = measure(now)
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("n")).select("a", F.least("a", "m").alias("m"), "n")
        # large star: greater neighbours are linked to the least
        large = hot_join(both, least, ["a"], "n", ["b"]).where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        # small star: a node and its lesser neighbours are linked to the least
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low.withColumnRenamed("a", "u"), large.a == F.col("u")).select(F.explode(F.array(F.struct("b", "m"), F.struct(F.col("a").alias("b"), "m"))).alias("x"))
        after = written(small.select(F.col("x.b").alias("a"), F.col("x.m").alias("b")).where("a <> b").distinct(), "edges")
        forget(now)
        now, was = after, before
        before = measure(now)
        if before == was:
            break
    roots = now.select(F.col("b").alias("node")).distinct().withColumn("root", F.col("node"))
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(roots)


def merged(roots: DataFrame, good: DataFrame) -> DataFrame:
    """``roots(node, root)`` after the links ``good(a, b)``: only the links between components are worked on."""
    for side in ("a", "b"):
        of = roots.select(F.col("node").alias(side), F.col("root").alias("r"))
        good = good.join(of, side, "left").withColumn(side, F.coalesce("r", side)).drop("r")
    grown = written(components(good), "grown")
    up = grown.select(F.col("node").alias("root"), F.col("root").alias("r"))
    old = roots.join(up, "root", "left").select("node", F.coalesce("r", "root").alias("root"))
    return written(old.unionByName(grown.join(roots, "node", "left_anti")), "roots")


def prefixes(nodes: DataFrame, texts: DataFrame, least: float) -> DataFrame:
    """bucket, node, size, place: the elements that a node must share one of with any node similar enough.

    Elements are put in order, those of the fewest nodes first; ``place`` is the element's place in this order of the
    node's ``size`` elements. Two sets as similar as ``least`` share an element of the first size - least * size + 1
    of each. Elements of one node take up places but make no rows.
    """

    def split(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        hashes = _Bytes()
        for frame in frames:
            yield pd.DataFrame({"node": frame["node"], "elements": [elements_of(t, hashes).view(np.int64) for t in frame["text"]]})

    sets = written(texts.join(nodes, "node", "left_semi").select("node", "text").mapInPandas(split, "node binary, elements array<long>"), "elements")
    each = sets.select("node", F.size("elements").alias("size"), F.explode("elements").alias("bucket"))
    spread = each.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1")
    known = hot_join(each, spread, ["bucket"], "n", ["node"]).groupBy("node", "size").agg(F.array_sort(F.collect_list(F.struct("n", "bucket"))).alias("x"))  # a text's elements at most
    alone = F.col("size") - F.size("x")
    first = F.greatest(F.lit(0), (F.col("size") - F.ceil(least * F.col("size") - 1e-9) + 1 - alone).cast("int"))
    rows = known.select("node", "size", alone.alias("alone"), F.posexplode(F.slice("x", F.lit(1), first)).alias("at", "e"))
    found = rows.select(F.col("e.bucket").alias("bucket"), "node", "size", (F.col("alone") + F.col("at")).alias("place"))
    found = written(found, "prefix-rows")
    many = found.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1")
    out = written(hot_join(found, many, ["bucket"], "n", ["node"]).drop("n"), "prefixes")
    forget(sets)
    forget(found)
    return out


def may_match(least: float):
    """Whether x and y (size, place) can be similar enough if the element at these places is the first that they share."""
    left = F.least(F.col("x.size") - F.col("x.place"), F.col("y.size") - F.col("y.place"))
    return left >= least / (1 + least) * (F.col("x.size") + F.col("y.size")) - 1e-6


def rooted(members: DataFrame, roots: DataFrame) -> DataFrame:
    return members.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))


def links(members: DataFrame, texts: DataFrame, least: float, small: int = 24, rounds: int | None = None) -> DataFrame:
    """node, root: components of the nodes with links, for ``members(bucket, node)``, each bucket with two nodes or more.

    ``rounds``: the turn at which what is left of every bucket is tried pair by pair (None: never)."""
    picks = members.groupBy("bucket").agg(F.min("node").alias("a"), F.count("*").alias("size"))
    star = written(hot_join(members, picks, ["bucket"], "size", ["node"]).where("node <> a").select("a", F.col("node").alias("b")).distinct(), "pairs")
    roots = written(components(written(verified(star, texts, least), "links")), "roots")
    still = rooted(members, roots).groupBy("bucket").agg(F.min("root").alias("low"), F.max("root").alias("high"), F.count("*").alias("size")).where("low <> high")
    open_nodes = written(hot_join(members, still.select("bucket", "size"), ["bucket"], "size", ["node"]).select("node").distinct(), "open")
    if open_nodes.isEmpty():
        return roots
    postings, tested, block, turn = prefixes(open_nodes, texts, least), star, 16, 0
    while True:
        turn += 1
        open_ = rooted(postings, roots).select("bucket", "root", F.struct("size", "place", "node").alias("y"))
        state = open_.groupBy("bucket").agg(F.min("root").alias("low"), F.max("root").alias("high"), F.count("*").alias("n"))
        state = written(state.where("low <> high").select("bucket", "n"), "state")
        if state.isEmpty():
            break
        here = written(hot_join(open_, state, ["bucket"], "n", ["y"]), "here")
        few = F.lit(turn == rounds) | (F.col("n") <= small)
        mine, wide = here.where(few), here.where(~few)
        other = mine.select("bucket", F.col("y").alias("x"), F.col("root").alias("x_root"))
        tried = mine.join(other, "bucket").where((F.col("root") != F.col("x_root")) & may_match(least)).where(F.col("x.node") < F.col("y.node")).select("x", "y")
        # a pick of each slot of a bucket; slots are drawn anew in every bucket and turn
        slotted = wide.withColumn("slot", F.pmod(F.xxhash64("bucket", "y.node", F.lit(block)), F.lit(block)))
        draw = F.min(F.struct(F.xxhash64("y.node", "bucket", F.lit(block)).alias("draw"), "y", "root")).alias("p")
        picks = written(slotted.groupBy("bucket", "slot").agg(draw).select("bucket", F.col("p.y").alias("x"), F.col("p.root").alias("x_root")), "picks")
        salts = 8
        spread = picks.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
        against = wide.withColumn("salt", F.pmod(F.xxhash64("y.node"), F.lit(salts)).cast("int")).join(spread, ["bucket", "salt"])
        tried = tried.unionByName(against.where((F.col("root") != F.col("x_root")) & may_match(least)).select("x", "y"))
        pairs = tried.select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b")).distinct()
        pairs = written(pairs.join(tested, ["a", "b"], "left_anti"), "pairs")
        if not pairs.isEmpty():
            tested = tested.unionByName(pairs)
            good = written(verified(pairs, texts, least), "links")
            if not good.isEmpty():
                roots = merged(roots, good)
        done = picks.select("bucket", F.col("x.node").alias("node"))
        old, postings = postings, written(wide.select("bucket", "y.node", "y.size", "y.place").join(done, ["bucket", "node"], "left_anti"), "postings")
        for used in (old, state, here, picks):
            forget(used)
        if postings.isEmpty():
            break
        block *= 4
    return roots


def near_duplicates(docs: DataFrame, least: float = 0.8, bands: int = 32, rows: int = 6) -> DataFrame:
    """doc_id, node, root (the class's own key), class_id, is_first (the row's id is the class id): a row per row of ``docs(doc_id, text)``."""
    signed = written(banded(docs, bands, rows), "signed")
    nodes = signed.groupBy("node").agg(F.min("doc_id").alias("id"), F.first("bands").alias("bands"), F.count("*").alias("copies"))
    nodes = written(nodes, "nodes")
    keyed = nodes.select("node", "id", F.explode("bands").alias("bucket"))
    shared = keyed.groupBy("bucket").agg(F.min("node").alias("low"), F.max("node").alias("high"), F.count("*").alias("size")).where("low <> high").select("bucket", "size")
    members = written(hot_join(keyed, shared, ["bucket"], "size", ["node"]).select("bucket", "node", "id"), "members")
    wanted = written(members.select("node", "id").distinct(), "wanted")
    # a node's text is that of its row of the least id: copies are sifted out, and rows stay where the join has dealt them
    keys = ["node", "_id", "_none"]
    keyed_by = lambda df: df.withColumns({"_id": F.coalesce(F.col("id").cast("string"), F.lit("")), "_none": F.col("id").isNull()}).drop("id")
    wanted = keyed_by(wanted)
    own = sifted(keyed_by(docs.select(node_of().alias("node"), F.col("doc_id").alias("id"), F.coalesce("text", F.lit("")).alias("text"))), wanted, keys)
    # a semi-join would be pushed below the sieve
    texts = written(own.join(wanted, keys).groupBy(*keys).agg(F.first("text").alias("text")).select("node", "text"), "texts")
    of_nodes = written(rooted(nodes.select("node", "id", "copies"), links(members.select("bucket", "node"), texts, least)), "of-nodes")
    classes = of_nodes.groupBy("root").agg(F.min("id").alias("class_id"), F.count("*").alias("size"))
    named = hot_join(of_nodes.select("node", "root", "copies"), classes, ["root"], "size", ["node"]).select("node", "root", "class_id", "copies")
    out = hot_join(signed.select("doc_id", "node"), named, ["node"], "copies", ["doc_id"])
    return out.select("doc_id", "node", "root", "class_id", F.col("doc_id").eqNullSafe(F.col("class_id")).alias("is_first"))


def first_documents(docs: DataFrame, **how) -> DataFrame:
    """The rows of ``docs`` that are first of their class, one for each class, with all their columns."""
    kept = near_duplicates(docs, **how).where("is_first").select("root", "node", F.col("doc_id").alias("_id")).distinct()
    kept = kept.groupBy("root", "_id").agg(F.min("node").alias("_node"))  # an id that several texts of a class share counts once
    mine = docs.withColumn("_node", node_of())
    found = mine.join(kept, (mine["_node"] == kept["_node"]) & mine["doc_id"].eqNullSafe(kept["_id"]), "left_semi")
    columns = [F.first(c, ignorenulls=False).alias(c) for c in docs.columns if c != "doc_id"]
    return found.groupBy("doc_id", "_node").agg(*columns).select(*docs.columns)
