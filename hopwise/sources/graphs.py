"""Graphs from the given tables: distinct ``edges(src, dst)``, no self-loops, both orientations if undirected."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.ranking import ranked
from ..plans.store import written


#: a vertex with more than this share of all edges is a hub; there are no more hubs than its inverse
HUB_SHARE = 1 / 512
HUB_PARTS = 16


@dataclass(frozen=True)
class HopGraph:
    edges: DataFrame
    directed: bool = False
    parted: DataFrame | None = None  # src, part, dst: a hub's edges in HUB_PARTS parts
    hubs: DataFrame | None = None  # v: at most 1 / HUB_SHARE rows
    known: DataFrame | None = None  # v, deg: the vertices, where they have been written
    stored: DataFrame | None = None  # src, dst as written, undirected edges once (src < dst): for what reads them once
    size: int | None = None  # how many edges there are, undirected ones twice
    once: DataFrame | None = None  # src, dst: the plan of an undirected graph's edges, each once (src < dst)

    @property
    def vertices(self) -> DataFrame:
        """v, deg: degrees over out-edges; a vertex with in-edges alone has degree 0."""
        if self.known is not None:
            return self.known
        ends = self.edges.select(F.col("src").alias("v"), F.lit(1).alias("one"))
        if self.directed:
            ends = ends.unionByName(self.edges.select(F.col("dst").alias("v"), F.lit(0).alias("one")))
        return ends.groupBy("v").agg(F.sum("one").cast("long").alias("deg"))

    def reverse(self) -> HopGraph:
        return HopGraph(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")), self.directed)

    def incoming(self) -> HopGraph:
        """The graph whose out-edges are this one's in-edges: itself, if undirected."""
        return self.reverse() if self.directed else self

    def cached(self) -> HopGraph:
        """Edges written once, dealt by source and kept: loops join them round after round. A lost part is read again.

        They are dealt when a loop first asks for them; what reads the edges once reads them as written. The edges of hubs
        are dealt over HUB_PARTS parts, so that no task gets a hub's whole adjacency. Vertices and their degrees are written
        once, too.
        """
        counted = Observation()
        own = self.edges if self.directed else self.edges.where("src < dst") if self.once is None else self.once
        stored = written(own.observe(counted, F.count("*").alias("n")), "edges")
        edges, size = (stored, counted.get["n"]) if self.directed else (_both_ways(stored), 2 * counted.get["n"])
        known = written(HopGraph(edges, self.directed).vertices, "vertices")
        most = max(1000, int(size * HUB_SHARE))
        hubs = written(known.where(F.col("deg") > most).select("v"), "hubs")
        if hubs.isEmpty():
            return HopGraph(edges.repartition("src").persist(), self.directed, known=known, stored=stored, size=size)
        marked = edges.join(F.broadcast(hubs), edges.src == hubs.v, "left")
        part = F.when(F.col("v").isNotNull(), F.pmod(F.xxhash64("dst"), F.lit(HUB_PARTS))).otherwise(0).cast("int")
        parted = marked.select("src", part.alias("part"), "dst").repartition("src", "part").persist()
        return HopGraph(parted.select("src", "dst"), self.directed, parted, hubs, known, stored, size)

    def along(self, rows: DataFrame) -> DataFrame:
        """``rows(v, ...)`` and the head ``dst`` of each out-edge of v."""
        if self.hubs is None:
            return rows.join(self.edges.withColumnRenamed("src", "v"), "v")
        hub = self.hubs.withColumn("_hub", F.lit(True))
        parts = F.when(F.col("_hub"), F.sequence(F.lit(0), F.lit(HUB_PARTS - 1))).otherwise(F.array(F.lit(0)))
        dealt = rows.join(F.broadcast(hub), "v", "left").withColumn("part", F.explode(parts)).drop("_hub")
        return dealt.join(self.parted.withColumnRenamed("src", "v"), ["v", "part"]).drop("part")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def from_pairs(pairs: DataFrame, directed: bool = False) -> HopGraph:
    """``pairs(src, dst)`` with nulls, repeats and self-loops dropped; undirected ones are made distinct as one of both orientations."""
    one = pairs.select(F.col("src").cast("long"), F.col("dst").cast("long")).where("src is not null and dst is not null and src <> dst")
    if directed:
        return HopGraph(one.distinct(), directed)
    once = one.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()
    return HopGraph(_both_ways(once), once=once)


def _both_ways(once: DataFrame) -> DataFrame:
    back = F.struct(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return once.select(F.inline(F.array(F.struct("src", "dst"), back)))


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", directed: bool = False) -> HopGraph:
    """A text edge list: two ids a line, comment lines from ``#``."""
    return from_pairs(spark.read.csv(path, sep=sep, comment="#", schema="src long, dst long"), directed)


def read_edge_json(spark: SparkSession, path: str, directed: bool = False) -> HopGraph:
    """JSON lines with the fields src and dst."""
    return from_pairs(spark.read.schema("src long, dst long").json(path), directed)


def _sides(df: DataFrame, left: str, right: str) -> HopGraph:
    return from_pairs(df.select((2 * F.col(left)).alias("src"), (2 * F.col(right) + 1).alias("dst")))


def part_supplier(spark: SparkSession, d: str) -> HopGraph:
    return _sides(table(spark, d, "lineitem"), "l_partkey", "l_suppkey")


def order_part(spark: SparkSession, d: str) -> HopGraph:
    return _sides(table(spark, d, "lineitem"), "l_orderkey", "l_partkey")


def _ordered(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").join(table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))


def customer_part(spark: SparkSession, d: str) -> HopGraph:
    return _sides(_ordered(spark, d), "o_custkey", "l_partkey")


def customer_supplier(spark: SparkSession, d: str) -> HopGraph:
    return _sides(_ordered(spark, d), "o_custkey", "l_suppkey")


def customer_order(spark: SparkSession, d: str) -> HopGraph:
    return _sides(table(spark, d, "orders"), "o_custkey", "o_orderkey")


def copurchase(spark: SparkSession, d: str) -> HopGraph:
    """Parts in one order. An order has a few lines, so the pairs stay in proportion."""
    lines = table(spark, d, "lineitem").select("l_orderkey", F.col("l_partkey").alias("src"))
    a = lines.repartition("l_orderkey").distinct()  # orders are dealt once, for what is distinct and for the join
    return from_pairs(a.join(a.withColumnRenamed("src", "dst"), "l_orderkey").where("src < dst"))


def nation_region(spark: SparkSession, d: str) -> HopGraph:
    """Regions 1.., nations 1000.., suppliers 10000..: a forest."""
    n = table(spark, d, "nation").select((1000 + F.col("n_nationkey")).alias("src"), (1 + F.col("n_regionkey")).alias("dst"))
    s = table(spark, d, "supplier").select((10_000 + F.col("s_suppkey")).alias("src"), (1000 + F.col("s_nationkey")).alias("dst"))
    return from_pairs(n.unionByName(s))


def page_link(spark: SparkSession, d: str, directed: bool = False) -> HopGraph:
    """Pages to link targets; targets get ids from 10^9 on, by the rank of their text (UTF-8 order)."""
    links = table(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("to"))
    links = links.distinct()
    ids = ranked(links.select("to").distinct(), "to")
    return from_pairs(links.join(ids, "to").select(F.col("page_id").alias("src"), (F.lit(10**9) + F.col("rank")).alias("dst")), directed)


def event_flow(spark: SparkSession, d: str, directed: bool = False) -> HopGraph:
    """User to the next user within an hour's events."""
    e = table(spark, d, "events")
    w = Window.partitionBy(F.date_trunc("hour", "ts")).orderBy("ts", "event_id")
    return from_pairs(e.select(F.col("user_id").alias("src"), F.lead("user_id").over(w).alias("dst")), directed)


def turn_path(spark: SparkSession, d: str) -> HopGraph:
    t = table(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("src"), "conv_id", "turn")
    return from_pairs(t.join(t.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("src").alias("dst")), ["conv_id", "turn"]).select("src", "dst"))


def embedding_knn(spark: SparkSession, d: str, k: int = 4, block: int = 2048) -> HopGraph:
    """The k nearest by cosine (ties by id), symmetrised: blocks of ``block`` query vectors against all.

    A block is what is broadcast, so its size is a number of the call; every task keeps the k best of its rows for each
    query of the block, and these few rows are merged.
    """
    import numpy as np
    import pandas as pd

    e = table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("x")).where("vec_id is not null and x is not null")

    def unit(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return x, np.sqrt((x * x).sum(axis=1))

    def against(ids: np.ndarray, x: np.ndarray) -> DataFrame:
        shared = spark.sparkContext.broadcast((ids, *unit(x)))

        def near(frames):
            ids, x, nx = shared.value
            for frame in frames:
                own = frame["vec_id"].to_numpy(np.int64)
                y, ny = unit(np.stack(frame["x"].to_numpy()))
                cosine = np.round(x @ y.T / (nx[:, None] * ny[None, :]), 9)
                cosine[ids[:, None] == own[None, :]] = -np.inf
                order = np.lexsort((np.broadcast_to(own, cosine.shape), -cosine), axis=1)[:, :k]
                rows = np.repeat(np.arange(len(ids)), order.shape[1])
                found = pd.DataFrame({"vec_id": ids[rows], "o": own[order.ravel()], "c": cosine[rows, order.ravel()]})
                yield found[found["c"] > -np.inf]

        return e.mapInPandas(near, "vec_id long, o long, c double")

    out, ids, rows = None, [], []
    for r in e.toLocalIterator():
        ids.append(r["vec_id"])
        rows.append(r["x"])
        if len(ids) == block:
            one, ids, rows = against(np.array(ids), np.array(rows)), [], []
            out = one if out is None else out.unionByName(one)
    if ids or out is None:
        one = against(np.array(ids, np.int64), np.array(rows, float).reshape(len(ids), -1))
        out = one if out is None else out.unionByName(one)
    best = F.row_number().over(Window.partitionBy("vec_id").orderBy(F.desc("c"), "o"))
    return from_pairs(out.withColumn("r", best).where(F.col("r") <= k).select(F.col("vec_id").alias("src"), F.col("o").alias("dst")))


def near_duplicate(spark: SparkSession, d: str, least_tenths: int = 8) -> HopGraph:
    """Documents whose sets of word 5-grams have a Jaccard similarity of ``least_tenths`` / 10 or more, by representatives.

    Documents of equal words are one class: each is linked to the class's least doc_id, and representatives to each
    other. Candidates share one of the rarest size - least * size + 1 grams of each (any two sets so similar do), and
    have sizes that allow the similarity; then the sets are compared.
    """
    words = table(spark, d, "documents").select("doc_id", F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0)).alias("w")).where(F.size("w") >= 5)
    keyed = words.select("doc_id", F.md5(F.array_join("w", " ")).alias("k"), "w")
    own = F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 4), lambda i: F.xxhash64(F.array_join(F.slice("w", i, 5), " "))))
    sets = written(keyed.groupBy("k").agg(F.min("doc_id").alias("rep"), F.first("w").alias("w")).select("k", "rep", own.alias("grams")), "gram-sets")
    each = sets.select("rep", F.size("grams").alias("size"), F.explode("grams").alias("g"))
    counts = each.groupBy("g").agg(F.count("*").alias("n")).where("n > 1")
    known = each.join(counts, "g").groupBy("rep", "size").agg(F.array_sort(F.collect_list(F.struct("n", "g"))).alias("x"))  # a text's grams at most
    alone = F.col("size") - F.size("x")  # grams of no other class come first, and make no rows
    first = F.greatest(F.lit(0), F.col("size") - F.ceil(least_tenths * F.col("size") / 10) + 1 - alone).cast("int")
    prefix = written(known.select("rep", "size", F.explode(F.slice("x", F.lit(1), first)).alias("e")).select("rep", "size", "e.g"), "gram-prefixes")
    other = prefix.select(F.col("rep").alias("rep2"), F.col("size").alias("size2"), "g")
    near = prefix.join(other, "g").where((F.col("rep") < F.col("rep2")) & (10 * F.col("size") >= least_tenths * F.col("size2")) & (10 * F.col("size2") >= least_tenths * F.col("size")))
    pairs = near.select("rep", "rep2").distinct()
    sided = pairs.join(sets.select("rep", "grams"), "rep").join(sets.select(F.col("rep").alias("rep2"), F.col("grams").alias("grams2")), "rep2")
    both = F.size(F.array_intersect("grams", "grams2"))
    links = sided.where(10 * both >= least_tenths * (F.size("grams") + F.size("grams2") - both)).select(F.col("rep").alias("src"), F.col("rep2").alias("dst"))
    copies = keyed.select("doc_id", "k").join(sets.select("k", "rep"), "k").select(F.col("doc_id").alias("src"), F.col("rep").alias("dst"))
    return from_pairs(links.unionByName(copies))


BUILDERS: dict[str, Callable[[SparkSession, str], HopGraph]] = {
    f.__name__: f for f in (part_supplier, order_part, customer_part, customer_supplier, copurchase, customer_order, page_link, event_flow, turn_path, nation_region, embedding_knn, near_duplicate)
}
