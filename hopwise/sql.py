"""SQL surface: the tables of an index as temporary views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import cohorts as C
from .operators import search as S
from .operators.landmarks import LandmarkIndex
from .operators.twohop import TwoHopIndex
from .sources.graphs import HopGraph


class ExplodeRecord:
    """Table function: (bit, dist) of the sources in a record, from its base and its masks in the order of offsets."""

    def eval(self, base: int, masks: list):
        for offset, mask in enumerate(masks):
            mask &= (1 << 64) - 1
            while mask:
                low = mask & -mask
                yield low.bit_length() - 1, base + offset
                mask ^= low


def register_functions(spark: SparkSession) -> None:
    """explode_record(base, masks), for SQL users; in plans ``search.explode_records`` does it without Python."""
    spark.udtf.register("explode_record", F.udtf(ExplodeRecord, returnType="bit long, dist int"))


def exploded(spark: SparkSession, g: HopGraph, w: int) -> DataFrame:
    """v, bit, dist of one star cohort, by SQL over its records."""
    register_functions(spark)
    S.records(S.cluster_sweep(g, C.pick_cohorts(g, 1, w), 2), 2).createOrReplaceTempView("hop_records_of_one_cohort")
    return spark.sql("SELECT v, x.bit, x.dist FROM hop_records_of_one_cohort, LATERAL explode_record(base, m) x")


def register(g: HopGraph, index: LandmarkIndex | None = None, exact: TwoHopIndex | None = None, prefix: str = "hop") -> None:
    """<prefix>_edges, _vertices, _records (v, cid, base, off, mask), _labels (v, hub, dist): answering is a join and a min."""
    g.edges.createOrReplaceTempView(f"{prefix}_edges")
    g.vertices.createOrReplaceTempView(f"{prefix}_vertices")
    if index is not None:
        rows = index.table.select("v", F.explode("recs").alias("r")).select("v", "r.cid", "r.base", F.posexplode("r.m").alias("off", "mask"))
        rows.where("mask <> 0").createOrReplaceTempView(f"{prefix}_records")
    if exact is not None:
        exact.labels.createOrReplaceTempView(f"{prefix}_labels")
