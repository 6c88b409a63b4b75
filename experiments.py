"""

``python experiments.py [--trials 50] [--frames 600] [--side 32] [--max-n 120] [--scenes 1 2 3] [--sf-dir DIR] [WORKLOAD ...]``
runs each workload (cycles, shake, noise, occlude, missing, alpha, kernel, landmarks) as one job over
its whole grid of conditions and trials, and prints one row a scene, level and variant.
"""

from __future__ import annotations

import argparse
import os
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")

WORKLOADS = ("cycles", "shake", "noise", "occlude", "missing", "alpha", "kernel", "landmarks")


def main() -> None:
    ask = argparse.ArgumentParser()
    ask.add_argument("workloads", nargs="*", default=WORKLOADS[:5])
    ask.add_argument("--trials", type=int, default=50)
    ask.add_argument("--frames", type=int, default=600)
    ask.add_argument("--side", type=int, default=32)
    ask.add_argument("--max-n", type=int, default=120)
    ask.add_argument("--scenes", type=int, nargs="*", default=[1, 2, 3])
    ask.add_argument("--surrogate", default="auto")
    ask.add_argument("--sf-dir", default="/root/testdata/sf0.01")
    given = ask.parse_args()

    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from cyclefold.plans import workloads

    spark = (
        SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '8')}]").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    embeddings = spark.read.parquet(f"{given.sf_dir}/embeddings.parquet")
    config = {"max_n": given.max_n, "surrogate": given.surrogate}
    for name in given.workloads:
        began = time.time()
        grid, variants = workloads.study(spark, name, given.side, given.trials, tuple(given.scenes), **config)
        found = workloads.errors(spark, embeddings, grid, variants, given.frames, given.side, given.side, 3)
        table = found.groupBy("scene", "cycles", "corruption", "level", "variant").agg(F.avg("err_deg").alias("mean"), F.stddev_samp("err_deg").alias("sd"), F.avg("k").alias("k"), F.avg("sigma").alias("sigma"), F.count("*").alias("trials"))
        rows = sorted(table.collect())
        print(f"# {name}: {grid.count()} videos, {time.time() - began:.0f} s")
        for r in rows:
            print(f"scene {r.scene} cycles {r.cycles:g} {r.corruption} {r.level:g} {r.variant}: {r['mean']:.2f} sd {r.sd or 0:.2f}, k {r.k:.2f}, sigma {r.sigma:.3f}, {r.trials} trials", flush=True)


if __name__ == "__main__":
    main()
