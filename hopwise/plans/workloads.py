"""Experiment workloads: what is timed and compared. Timings are rows like any others; they come from this session."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import cohorts as C
from ..operators import landmarks as L
from ..operators import measures as M
from ..operators import search as S
from ..operators.twohop import TwoHopIndex
from ..sources.graphs import BUILDERS, HopGraph

QUERIES_TIMED = 10_000


def graphs(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> dict[str, HopGraph]:
    return {n: BUILDERS[n](spark, sf_dir).cached() for n in names}


@contextmanager
def one_partition(spark: SparkSession) -> Iterator[None]:
    """Shuffles of one partition: what the sequential baselines run on."""
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "1")
    try:
        yield
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def micro_bench(spark: SparkSession, g: HopGraph, name: str, w: int = 64, cohorts: int = 10, plain: int | None = None) -> DataFrame:
    """graph, algo, cohort, seconds, activations, speedup: test cohorts by each traversal.

    The baseline searches from one source after another: from all w, or from ``plain`` of them, scaled. The star
    sweep without parallelism runs on one partition.
    """
    spread = C.spread_cohorts(g, cohorts, w)
    single = HopGraph(g.edges.coalesce(1).persist(), g.directed)
    rows = []
    for cid in range(cohorts):
        one = spread.where(F.col("cid") == cid).persist()
        sources = [r["s"] for r in one.orderBy("bit").collect()]
        some = sources[: plain or len(sources)]
        reports = {k: S.Report() for k in ("keyed_frontier", "cluster_sweep", "cluster_sweep_auto")}

        def on_one_partition(one=one) -> int:
            with one_partition(spark):
                return S.star_sweep(single, one).count()

        runs: dict[str, Callable[[], int]] = {
            "one_by_one": lambda some=some: S.bfs_sequential(g, some).count(),
            "keyed_frontier": lambda one=one, r=reports: S.bfs_each(g, one, report=r["keyed_frontier"]).count(),
            "star_one_partition": on_one_partition,
            "cluster_sweep": lambda one=one, r=reports: S.cluster_sweep(g, one, 2, report=r["cluster_sweep"]).count(),
            "cluster_sweep_auto": lambda one=one, r=reports: S.cluster_sweep(g, one, 2, "auto", report=r["cluster_sweep_auto"]).count(),
        }
        base = None
        for algo, run in runs.items():
            _, seconds = M.timed(run)
            if algo == "one_by_one":
                base = seconds = seconds * len(sources) / len(some)
            rows.append((name, algo, cid, seconds, reports[algo].activations if algo in reports else None, M.speedup(base, seconds)))
        one.unpersist()
    single.edges.unpersist()
    return spark.createDataFrame(rows, "graph string, algo string, cohort int, seconds double, activations long, speedup double")


def gain_summary(rows: DataFrame) -> DataFrame:
    """algo, gain: the geometric mean of the speed-ups over graphs and cohorts."""
    return rows.groupBy("algo").agg(F.exp(F.avg(F.ln("speedup"))).alias("gain"))


def diameter_sweep(spark: SparkSession, g: HopGraph, name: str, w: int = 64, ds: tuple[int, ...] = (2, 3, 4, 5, 6)) -> DataFrame:
    """graph, d, members, seconds, activations, messages. ``measures.relative_times`` puts the times over that of d = 2."""
    rows = []
    for d in ds:
        cohort, report = C.pick_cohorts(g, 1, w, d), S.Report()
        _, seconds = M.timed(lambda: S.cluster_sweep(g, cohort, d, report=report).count())  # noqa: B023
        rows.append((name, d, cohort.count(), seconds, report.activations, report.messages))
    return spark.createDataFrame(rows, "graph string, d int, members long, seconds double, activations long, messages long")


INDEX_ROW = "graph string, t int, w int, d int, clusters int, landmarks long, eps double, build_s double, query_ms double"


def _index_rows(g: HopGraph, name: str, variants: list[tuple[int, int, int]], pairs: int) -> list[tuple]:
    """INDEX_ROW for variants (t, w, d); w = 1 is single landmarks. query_ms is of QUERIES_TIMED pairs."""
    sample = L.sample_pairs(g, pairs).persist()
    truth = L.exact_pairs(g, sample).persist()
    many = L.sample_pairs(g, QUERIES_TIMED, seed=1).persist()
    many.count()
    rows = []
    for t, w, d in variants:
        r = C.clusters_for_budget(t, w, d)
        if w == 1:
            marks = C.pick_landmarks(g, r)
            index, built = M.timed(lambda: L.written(L.wide(L.plain_index(g, marks)), "plain"))  # noqa: B023
            answers = lambda p: L.plain_query(index, p)  # noqa: B023, E731
            n = marks.count()
        else:
            chosen = C.pick_cohorts(g, r, w, d)
            index, built = M.timed(lambda: L.LandmarkIndex.build(g, chosen, d, "complement", mode="push"))  # noqa: B023
            answers = index.query
            n = chosen.count()
        eps = M.mean_excess(answers(sample), truth).first()["eps"]
        _, asked = M.timed(lambda: answers(many).agg(F.sum("est")).collect())  # noqa: B023
        rows.append((name, t, w, d, r, n, eps, built, 1000 * asked * 10_000 / QUERIES_TIMED))
    for used in (sample, truth, many):
        used.unpersist()
    return rows


def budget_table(spark: SparkSession, g: HopGraph, name: str, t: int = 68, pairs: int = 1000, widths: tuple[int, ...] = (1, 8, 16, 32, 64), d: int = 2) -> DataFrame:
    return spark.createDataFrame(_index_rows(g, name, [(t, w, d) for w in widths], pairs), INDEX_ROW)


def tradeoff(spark: SparkSession, g: HopGraph, name: str, budgets: tuple[int, ...] = (17, 34, 68, 136), widths: tuple[int, ...] = (1, 8, 64), pairs: int = 1000) -> DataFrame:
    return spark.createDataFrame(_index_rows(g, name, [(t, w, 2) for t in budgets for w in widths], pairs), INDEX_ROW)


def diameter_index(spark: SparkSession, g: HopGraph, name: str, t: int = 132, w: int = 64, ds: tuple[int, ...] = (2, 3, 4), pairs: int = 1000) -> DataFrame:
    return spark.createDataFrame(_index_rows(g, name, [(t, w, d) for d in ds], pairs), INDEX_ROW)


def budget_scorecard(rows: DataFrame) -> DataFrame:
    """Of INDEX_ROW rows: on how many graphs the best clustered variant beats single landmarks in time, in accuracy, in both."""
    plain = rows.where("w = 1").select("graph", F.col("build_s").alias("base_s"), F.col("eps").alias("base_eps"))
    best = rows.where("w > 1").groupBy("graph").agg(F.min("build_s").alias("other_s"), F.min("eps").alias("other_eps"))
    return M.scorecard(plain.join(best, "graph"))


def local_search_sweep(spark: SparkSession, g: HopGraph, name: str, taus: tuple[int, ...] = (128, 256, 512, 1024, 2048), pairs: int = 1000, skip: bool = False) -> DataFrame:
    """graph, tau, eps, seconds: index answers improved by the local search; tau = 0 is the index alone."""
    sample = L.sample_pairs(g, pairs).persist()
    truth = L.exact_pairs(g, sample).persist()
    chosen = C.pick_cohorts(g, 2, 64)
    index = L.LandmarkIndex.build(g, chosen, 2, mode="push")
    left = chosen.select("s") if skip else None
    rows = []
    for tau in (0, *taus):
        answers = lambda: index.query(sample) if not tau else L.least_answer(index.query(sample), L.local_meet(g, sample, tau, left))  # noqa: B023, E731
        found, s = M.timed(lambda: M.mean_excess(answers(), truth).first())  # noqa: B023
        rows.append((name, tau, found["eps"], s))
    return spark.createDataFrame(rows, "graph string, tau int, eps double, seconds double")


def exact_index_bench(spark: SparkSession, g: HopGraph, name: str, rs: tuple[int, ...] = (0, 2), w: int = 64, one_by_one: bool = False) -> DataFrame:
    """graph, r, plan, labels, per_vertex, inflation (over one search at a time, if that was built), phase_one_s, phase_two_s."""
    rows = []
    for r in rs:
        plans = {"batches": {}, "trimmed": {"trim": True}}
        if one_by_one:
            plans = {"one_by_one": {"first": 1, "growth": 1.0, "cap": 1}} | plans
        least = None
        for plan, how in plans.items():
            index = TwoHopIndex.build(g, r, w, **how)
            st = M.label_stats(index.labels).first()
            least = st["labels"] if plan == "one_by_one" else least
            rows.append((name, r, plan, st["labels"], st["per_vertex"], st["labels"] / least if least else None, index.seconds["phase_one"], index.seconds["phase_two"]))
    return spark.createDataFrame(rows, "graph string, r int, plan string, labels long, per_vertex double, inflation double, phase_one_s double, phase_two_s double")


def ablation(spark: SparkSession, g: HopGraph, name: str, w: int = 64) -> DataFrame:
    """graph, variant, seconds, activations, messages: direction, fresh against seen bits, gate, bits against keyed searches."""
    cohort = C.pick_cohorts(g, 1, w)
    runs = {
        "push": lambda rep: S.cluster_sweep(g, cohort, 2, report=rep),
        "pull": lambda rep: S.cluster_sweep(g, cohort, 2, "pull", report=rep),
        "auto": lambda rep: S.cluster_sweep(g, cohort, 2, "auto", report=rep),
        "seen_bits": lambda rep: S.cluster_sweep(g, cohort, 2, delta=False, report=rep),
        "no_gate": lambda rep: S.cluster_sweep(g, cohort, None, report=rep),
        "no_bits": lambda rep: S.bfs_each(g, cohort, report=rep),
    }
    rows = []
    for variant, run in runs.items():
        report = S.Report()
        _, seconds = M.timed(lambda: run(report).count())  # noqa: B023
        rows.append((name, variant, seconds, report.activations, report.messages))
    return spark.createDataFrame(rows, "graph string, variant string, seconds double, activations long, messages long")


def fill_rates(spark: SparkSession, g: HopGraph, name: str, r: int = 8, w: int = 64, ds: tuple[int, ...] = (2, 3, 4, 6)) -> DataFrame:
    """graph, d, mean_members: how full cohorts get; low degrees leave star cohorts short."""
    rows = []
    for d in ds:
        sizes = C.pick_cohorts(g, r, w, d).groupBy("cid").count()
        rows.append((name, d, sizes.agg(F.avg("count")).first()[0]))
    return spark.createDataFrame(rows, "graph string, d int, mean_members double")
