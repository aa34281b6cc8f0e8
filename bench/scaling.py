"""Seconds of a serial sweep against shares of a planted graph, with the R squared of a line, and seconds per document and link of each kind. Argument: repeats."""

from __future__ import annotations

import os
import sys
import time

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = os.pathsep.join([ROOT, os.environ.get("PYTHONPATH", "")])
os.environ.setdefault("OPENBLAS_NUM_THREADS", "1")


def main() -> None:
    from pyspark.sql import SparkSession

    from commlens.config import ProfilerConfig
    from commlens.plans.experiments import linearity, sample_graph
    from commlens.plans.kernel import SerialSampler
    from commlens.plans.study import collect_graph
    from commlens.sources.planted import PlantedConfig, generate

    repeats = int(sys.argv[1]) if len(sys.argv) > 1 else 3
    spark = SparkSession.builder.master("local[8]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "8").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    graph = generate(spark, PlantedConfig(users=300, docs_per_user=8, communities=6, topics=8, vocabulary=160)).graph.cached()
    cfg = ProfilerConfig(communities=6, topics=8, alpha=0.5, rho=0.5, pg="exact")
    points = []
    for share in (0.25, 0.5, 0.75, 1.0):
        g = collect_graph(sample_graph(graph, share))
        took = []
        for _ in range(repeats):
            m = SerialSampler(g, cfg)
            began = time.process_time()
            m.fit(1)
            took.append(time.process_time() - began)
        points.append((len(g.user), sum(took) / repeats))
        print(f"| {share} | {len(g.user)} documents, {len(g.friends)} and {len(g.diffs)} links | {points[-1][1]:.3f} s |")
    print(f"R squared of seconds against documents: {linearity(points):.4f}")
    spark.stop()


if __name__ == "__main__":
    main()
