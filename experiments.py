"""Run the experiment queries and print a JSON line a measurement.

    python experiments.py [chunk size tagging skew partition compare sinks kernel]     (all by default)

EXP_SF_DIR: tables; EXP_CPUS: threads; EXP_COPIES: how often an input is repeated in its file; EXP_RUNS: runs a median is of.
"""

from __future__ import annotations

import inspect
import json
import os
import sys

SF_DIR = os.environ.get("EXP_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("EXP_CPUS", "8")
GIVEN = {"copies": int(os.environ.get("EXP_COPIES", "1")), "runs": int(os.environ.get("EXP_RUNS", "3"))}
NAMES = {"sinks": "measure_sinks", "kernel": "measure_kernel_vs_end_to_end"}


def main() -> None:
    from delimscan.plans import experiments
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g").config("spark.driver.maxResultSize", "4g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    wanted = [NAMES.get(n, f"exp_{n}") for n in sys.argv[1:]] or list(experiments.Q)
    for name in wanted:
        run = experiments.Q[name]
        options = {k: v for k, v in GIVEN.items() if k in inspect.signature(run).parameters}
        for r in run(spark, SF_DIR, **options).collect():
            print(json.dumps({"experiment": name, **{k: round(v, 4) if isinstance(v, float) else v for k, v in r.asDict().items()}}), flush=True)


if __name__ == "__main__":
    main()
