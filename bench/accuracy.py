"""All methods on folds of a planted graph; prints a table of means, gains of the full model and one-tailed p-values. Arguments: folds to run (of ten), sweeps."""

from __future__ import annotations

import os
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = os.pathsep.join([ROOT, os.environ.get("PYTHONPATH", "")])
os.environ.setdefault("OPENBLAS_NUM_THREADS", "1")


def main() -> None:
    from pyspark.sql import SparkSession

    from commlens.config import ProfilerConfig
    from commlens.plans import study
    from commlens.sources.planted import PlantedConfig, generate

    only, sweeps = int(sys.argv[1]) if len(sys.argv) > 1 else 10, int(sys.argv[2]) if len(sys.argv) > 2 else 25
    spark = SparkSession.builder.master("local[8]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "8").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    shape = PlantedConfig(users=150, docs_per_user=8, communities=6, topics=8, vocabulary=160, loyalty=0.75, stars=0.8, trends=0.6, diffs_per_doc=0.9)
    cfg = ProfilerConfig(communities=6, topics=8, sweeps=sweeps, burnin=sweeps // 2, alpha=0.5, rho=0.5, pg="exact")
    rows = study.table(study.run(generate(spark, shape).graph, cfg, only=only, top=2, most=5))
    print(f"planted graph of {shape.users} users, {shape.users * shape.docs_per_user} documents; {only} of ten folds; {sweeps} sweeps; drawn augmentation variables")
    print("| measure | method | mean | gain of the full model | p |\n| --- | --- | --- | --- | --- |")
    for r in rows:
        if r["measure"] in ("conductance", "friendship_auc", "diffusion_auc", "perplexity", "maf1", "maf5"):
            p = "" if r["p"] is None else f"{r['p']:.4f}"
            print(f"| {r['measure']} | {r['method']} | {r['mean']:.4f} | {100 * r['gain']:.1f} % | {p} |")
    spark.stop()


if __name__ == "__main__":
    main()
