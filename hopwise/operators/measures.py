"""Accuracy, work and size measures."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .cohorts import model_bytes


def scored(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """pid, truth, est of reachable pairs of different vertices."""
    return answers.select("pid", "est").join(truth.select("pid", "truth"), "pid").where("truth > 0 and est is not null")


def mean_excess(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """pairs, eps (mean of answer / truth, less one), hits (exact answers), worst."""
    ratio = F.col("est") / F.col("truth")
    return scored(answers, truth).agg(
        F.count("*").alias("pairs"), F.round(F.avg(ratio) - 1, 6).alias("eps"), F.count_if(F.col("est") == F.col("truth")).alias("hits"), F.round(F.max(ratio), 6).alias("worst")
    )


def distortion_profile(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """By true distance: pairs, eps, hits. Short pairs are the weak ones."""
    ratio = F.col("est") / F.col("truth")
    return scored(answers, truth).groupBy("truth").agg(F.count("*").alias("pairs"), F.round(F.avg(ratio) - 1, 6).alias("eps"), F.count_if(F.col("est") == F.col("truth")).alias("hits"))


def timed(run: Callable[[], object]) -> tuple[object, float]:
    began = time.perf_counter()
    out = run()
    return out, time.perf_counter() - began


def geo_mean(values: list[float]) -> float:
    return math.exp(sum(map(math.log, values)) / len(values))


def speedup(base: float, other: float) -> float:
    return base / other


def model_saving(w: int, d: int) -> float:
    """Bytes of w plain distances over bytes of one record."""
    return w / model_bytes(w, d)


def stored_bytes(df: DataFrame) -> int:
    """Bytes of the files under a table read from Parquet."""
    jvm, conf = df.sparkSession._jvm, df.sparkSession._jsc.hadoopConfiguration()
    total = 0
    for f in df.inputFiles():
        path = jvm.org.apache.hadoop.fs.Path(f)
        total += path.getFileSystem(conf).getFileStatus(path).getLen()
    return total


def label_stats(labels: DataFrame) -> DataFrame:
    """n, labels, per_vertex."""
    return labels.groupBy("v").agg(F.count("*").alias("k")).agg(F.count("*").alias("n"), F.sum("k").alias("labels"), F.round(F.avg("k"), 6).alias("per_vertex"))


def scorecard(rows: DataFrame) -> DataFrame:
    """From (graph, base_s, other_s, base_eps, other_eps): graphs improved in time, in accuracy, in both, in either."""
    t, e = F.col("other_s") < F.col("base_s"), F.col("other_eps") < F.col("base_eps")
    return rows.agg(F.count_if(t).alias("time"), F.count_if(e).alias("accuracy"), F.count_if(t & e).alias("both"), F.count_if(t | e).alias("either"), F.count("*").alias("graphs"))


def work_saving(one_by_one: int, swept: int) -> float:
    """Edge activations of separate searches over those of a sweep."""
    return one_by_one / max(1, swept)


def relative_times(rows: DataFrame, base_d: int = 2) -> DataFrame:
    """From (graph, d, seconds): each time over the graph's time at ``base_d``."""
    base = rows.where(F.col("d") == base_d).select("graph", F.col("seconds").alias("base"))
    return rows.join(base, "graph").select("graph", "d", (F.col("seconds") / F.col("base")).alias("relative"))


def shuffled_bytes(spark) -> int:
    """Bytes that the stages of this session have written to shuffles so far."""
    sc = spark.sparkContext
    stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
    return sum(stages.apply(i).shuffleWriteBytes() for i in range(stages.size()))
