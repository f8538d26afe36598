"""Headline queries over $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Times are wall seconds of whole runs: nodes are built and written first (nodes_*), then summary, solving on it and
evaluation on all nodes (summary_*), and the baselines of the same result.  quality_* are costs over the full-data solver's, gap_* the
summary's relative error for its own solution.
"""

import json
import os
import sys
import time
from dataclasses import replace

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")

from pyspark.sql import SparkSession  # noqa: E402

from hazemedian.model import PRACTICAL  # noqa: E402
from hazemedian.plans import experiment  # noqa: E402
from hazemedian.sources.workloads import workload  # noqa: E402


def main() -> None:
    sf, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g").config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.files.maxPartitionBytes", "32m").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    queries: dict[str, float] = {}
    facts: dict[str, float] = {}
    profile = replace(PRACTICAL, per_k=200)
    # Code is compiled and workers are started before anything is timed.
    warm, d = workload(spark, sf, "tower")
    for method in ("summary", "full_solver"):
        experiment.run_method(warm, d, method, 5, 1, profile)

    def timed(name, f):
        t = time.perf_counter()
        out = f()
        queries[name] = round(time.perf_counter() - t, 3)
        return out

    for name, ks, full in (("tower", (5, 20), 20), ("lines", (5, 10, 20, 40), 20), ("cover", (20,), 20), ("census", (20,), 20), ("cross", (20,), None), ("descriptors_pair", (2,), 2)):
        nodes, d = timed(f"nodes_{name}", lambda name=name: workload(spark, sf, name))
        n = nodes.count()
        for k in ks:
            cost, small, rows, _ = timed(f"summary_{name}_k{k}", lambda: experiment.run_method(nodes, d, "summary", k, 1, profile))
            facts[f"gap_{name}_k{k}"] = round(abs(small - cost) / cost, 4)
            facts[f"nodes_per_s_{name}_k{k}"] = round(n / queries[f"summary_{name}_k{k}"])
            if k == full:
                base = timed(f"full_solver_{name}_k{k}", lambda: experiment.run_method(nodes, d, "full_solver", k, 1, profile))
                facts[f"quality_{name}_k{k}"] = round(cost / base[0], 4)
    ks, seconds = zip(*((k, queries[f"summary_lines_k{k}"]) for k in (5, 10, 20, 40)), strict=True)
    slope = sum((k - sum(ks) / 4) * t for k, t in zip(ks, seconds, strict=True)) / sum((k - sum(ks) / 4) ** 2 for k in ks)
    facts["seconds_per_centre_lines"] = round(slope, 4)
    nodes, d = workload(spark, sf, "tower")
    timed("stream_kmeanspp_tower_k20", lambda: experiment.run_method(nodes, d, "stream_kmeanspp", 20, 1, profile))
    timed("feature_tree_tower_k20", lambda: experiment.run_method(nodes, d, "feature_tree", 20, 1, profile))
    ours = {k: v for k, v in queries.items() if k.startswith(("nodes_", "summary_"))}
    print(json.dumps({"metric": "sum of node building and summary runs", "value": round(sum(ours.values()), 3), "unit": "sec", "queries": queries, "facts": facts, "sf": os.path.basename(sf.rstrip("/"))}))


if __name__ == "__main__":
    main()
