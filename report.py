"""Runs the studies at a chosen size and prints their tables as Markdown: REPLICATES (default 4), N (5000), M (100)."""

from __future__ import annotations

import os
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from collanom import workloads
from collanom.operators import evaluate
from collanom.plans.ship import ship

REPLICATES, N, M = (int(os.environ.get(k, d)) for k, d in (("REPLICATES", 4), ("N", 5000), ("M", 100)))


def table(df: DataFrame) -> str:
    rows = df.collect()
    lines = ["| " + " | ".join(df.columns) + " |", "|" + " --- |" * len(df.columns)]
    return "\n".join([*lines, *("| " + " | ".join(f"{v:.3f}" if isinstance(v, float) else str(v) for v in r) + " |" for r in rows)])


def main() -> None:
    spark = ship(SparkSession.builder.master(os.environ.get("MASTER", "local[8]")).config("spark.sql.shuffle.partitions", "16").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate())
    spark.sparkContext.setLogLevel("ERROR")
    print(f"# Studies with {REPLICATES} replicates, n = {N}, M = {M}\n\n## Location: mean distance of the ends over truths that all methods find\n")
    for p in (10, 100):
        for number in (1, 2, 3, 4):
            for points in (False, True):
                began = time.time()
                print(table(workloads.location_study(spark, number, p, points, REPLICATES, N, M)), f"\n\n({time.time() - began:.0f} s)\n", flush=True)
                spark.catalog.clearCache()
    print("## Area under the curve of true over false positives, up to one false positive a series\n")
    for number in (1, 2, 3, 4):
        roc = workloads.roc_study(spark, number, 10, False, REPLICATES, min(N, 2000), min(M, 60)).persist()
        for (method,) in roc.select("method").distinct().orderBy("method").collect():
            area = evaluate.auc(roc.where(F.col("method") == method)).first()["auc"]
            print(f"setting {number}, {method}: {area:.3f}")
        spark.catalog.clearCache()
    for title, df in (("Runtime over n, noise", workloads.runtime_study(spark, "n")), ("Runtime over n, an anomaly every 100", workloads.runtime_study(spark, "n", True)), ("Runtime over p", workloads.runtime_study(spark, "p"))):
        print(f"\n## {title}\n\n{table(df)}", flush=True)
    print(f"\n## Known windows found at 4 % flagged\n\n{table(workloads.catalogue_study(spark, os.environ.get('BENCH_SF_DIR', '/root/testdata/sf0.01')))}")
    print(f"\n## Power\n\n{table(workloads.power_study(spark))}")


if __name__ == "__main__":
    main()
