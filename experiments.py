"""The comparisons of scenarios, budgets and classifiers, printed as tables.

    python experiments.py [tables' folder] [clean|dirty|biased|census ...]
"""

from __future__ import annotations

import sys
import time

from fairlink.plans import grids, scenarios
from pyspark.sql import SparkSession


def main(sf_dir: str, flavours: list[str]) -> None:
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    print("flavour | feature | classifier | scenario | eps | comparisons | fake pairs | FPR | recall | F* | fairness")
    for flavour in flavours:
        for feature in ("gender",) if flavour == "census" else ("gender", "age_band"):
            began = time.time()
            counts = scenarios.grid(spark, sf_dir, grids.four(), flavour, (feature,), ("threshold", "logistic"))
            for r in scenarios.summaries(counts).orderBy("classifier", "scenario", "eps").collect():
                print(f"{flavour} | {feature} | {r['classifier']} | {r['scenario']} | {r['eps']} | {r['comparisons']} | {r['fake']} | {r['fpr']:.5f} | {r['recall']:.4f} | {r['fstar']:.4f} | {r['fairness']:.5f}", flush=True)
            print(f"{flavour} | {feature} | {time.time() - began:.0f} seconds for {len(grids.four())} runs and both classifiers", flush=True)


if __name__ == "__main__":
    main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01", sys.argv[2:] or ["clean", "dirty", "biased", "census"])
