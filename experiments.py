"""Runs the experiment workloads on the given tables and prints one JSON line for each row.

python experiments.py [--sf DIR] [--cores N] [NAME ...]: names of WORKLOADS, or scaling, which starts itself with 1, 2, 4 and
8 cores: the cluster sweep (bits) and the keyed searches (no bits) on each, for self-speed-up and the two-by-two ablation.
"""

import argparse
import json
import subprocess
import sys
from pathlib import Path

from pyspark.sql import SparkSession

sys.path.insert(0, str(Path(__file__).parent))

GRAPHS = ("copurchase", "customer_part")
WORKLOADS = ("micro_bench", "diameter_sweep", "budget_table", "tradeoff", "diameter_index", "local_search_sweep", "exact_index_bench", "ablation", "fill_rates")
PLAIN = {"micro_bench": {"plain": 4, "cohorts": 2}}
#: exact indexes are built on smaller graphs with cycles
ON = {"exact_index_bench": ("event_flow",), "fill_rates": ("embedding_knn", "customer_part")}


def session(cores: int) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", cores)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main() -> None:
    args = argparse.ArgumentParser()
    args.add_argument("--sf", default="/root/testdata/sf0.01")
    args.add_argument("--cores", type=int, default=8)
    args.add_argument("names", nargs="*", default=[*WORKLOADS])
    args = args.parse_args()
    if "scaling" in args.names:
        for cores in (1, 2, 4, 8):
            subprocess.run([sys.executable, __file__, "--sf", args.sf, "--cores", str(cores), "one_size"], check=True)
    names = [n for n in args.names if n != "scaling"]
    if not names:
        return
    spark = session(args.cores)
    from hopwise.operators import cohorts as C
    from hopwise.operators import measures as M
    from hopwise.operators import search as S
    from hopwise.plans import workloads

    def out(name: str, rows) -> None:
        for r in rows:
            print(json.dumps({"workload": name, "sf": Path(args.sf).name, "cores": args.cores, **r.asDict()}), flush=True)

    for name in names:
        for graph, g in workloads.graphs(spark, args.sf, ON.get(name, GRAPHS)).items():
            if name == "one_size":
                c = C.pick_cohorts(g, 1, 64).persist()
                c.count()
                for bits, run in (("on", lambda: S.cluster_sweep(g, c, 2).count()), ("off", lambda: S.bfs_each(g, c).count())):  # noqa: B023
                    run()
                    print(json.dumps({"workload": "scaling", "sf": Path(args.sf).name, "cores": args.cores, "graph": graph, "bits": bits, "seconds": round(M.timed(run)[1], 3)}), flush=True)
                continue
            rows = getattr(workloads, name)(spark, g, graph, **PLAIN.get(name, {}))
            out(name, rows.collect())
            if name == "micro_bench":
                out("gain_summary", workloads.gain_summary(rows).collect())
            if name == "diameter_sweep":
                out("relative_times", M.relative_times(rows).collect())
            if name == "budget_table":
                out("budget_scorecard", workloads.budget_scorecard(rows).collect())
            g.edges.unpersist()
    spark.stop()


if __name__ == "__main__":
    main()
