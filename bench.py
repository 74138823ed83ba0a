"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one JSON line."""

import json
import os
import sys
import time
from pathlib import Path

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).parent))

#: searches that the plain baseline runs; its time for 64 is scaled from them
PLAIN = 4


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from hopwise.operators import cohorts as C
    from hopwise.operators import landmarks as L
    from hopwise.operators import search as S
    from hopwise.plans.workloads import one_partition
    from hopwise.sources.graphs import HopGraph, customer_part

    g = customer_part(spark, sf_dir).cached()
    g.edges.count()
    c = C.pick_cohorts(g, 1, 64).persist()
    sources, spread = [r["s"] for r in c.orderBy("bit").collect()], C.spread_cohorts(g, 10, 64).persist()
    single = HopGraph(g.edges.coalesce(1).persist())
    single.edges.count()
    reports = {k: S.Report() for k in ("sweep", "keyed")}
    made: dict = {}

    def star_on_one_partition() -> None:
        with one_partition(spark):
            S.star_sweep(single, c).count()

    pairs = L.sample_pairs(g, 10_000).persist()
    pairs.count()
    answered = lambda df: df.agg(F.sum("est")).collect()
    runs = {
        "pick_cohorts_4x64": lambda: C.pick_cohorts(g, 4, 64).count(),
        "pick_cohorts_60x64": lambda: C.pick_cohorts(g, 60, 64).count(),
        "cluster_sweep_64": lambda: S.cluster_sweep(g, c, 2, report=reports["sweep"]).count(),
        "cluster_sweep_64_auto": lambda: S.cluster_sweep(g, c, 2, "auto").count(),
        "cluster_sweep_10x64": lambda: S.cluster_sweep(g, spread, 2).count(),
        "bfs_each_64_keyed": lambda: S.bfs_each(g, c, report=reports["keyed"]).count(),
        "bfs_single": lambda: S.bfs(g, sources[0]).count(),
        f"bfs_one_by_one_{PLAIN}": lambda: S.bfs_sequential(g, sources[:PLAIN]).count(),
        "star_one_partition_64": star_on_one_partition,
        "landmark_build_4x64": lambda: made.update(index=L.LandmarkIndex.build(g, C.pick_cohorts(g, 4, 64), 2, "complement", mode="push")),
        "landmark_query_10000": lambda: answered(made["index"].query(pairs)),
        "plain_build_68": lambda: made.update(plain=L.written(L.wide(L.plain_index(g, C.pick_landmarks(g, 68))), "plain")),
        "plain_query_10000": lambda: answered(L.plain_query(made["plain"], pairs)),
        "local_meet_500_tau_128": lambda: answered(L.local_meet(g, pairs.limit(500), 128)),
    }
    times = {}
    for name, run in runs.items():
        began = time.perf_counter()
        run()
        times[name] = round(time.perf_counter() - began, 3)
    sweep = times["cluster_sweep_64"]
    ratios = {
        "one_by_one_64_scaled_over_sweep": round(times[f"bfs_one_by_one_{PLAIN}"] * len(sources) / PLAIN / sweep, 2),
        "keyed_over_sweep": round(times["bfs_each_64_keyed"] / sweep, 2),
        "star_one_partition_over_sweep": round(times["star_one_partition_64"] / sweep, 2),
        "ten_cohorts_over_one": round(times["cluster_sweep_10x64"] / sweep, 2),
        "plain_build_over_clustered": round(times["plain_build_68"] / times["landmark_build_4x64"], 2),
    }
    work = {k: {"activations": r.activations, "messages": r.messages, "rounds": len(r.rounds)} for k, r in reports.items()}
    print(json.dumps({"metric": "hop_distance_suite", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": Path(sf_dir).name, "ratios": ratios, "work": work}))
    spark.stop()


if __name__ == "__main__":
    main()
