"""Headline timings: one JSON line.

Rendering of inputs is not timed; every parse runs its passes and casts all columns.  Small inputs are the tables as
they are, medians of three runs; ``*_large`` is one file with the text set repeated (``BENCH_LARGE_MB``, default 1000),
where fixed costs no longer rule, each timed once.
"""

from __future__ import annotations

import json
import os
import time
from statistics import median

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
LARGE_MB = int(os.environ.get("BENCH_LARGE_MB", "1000"))


def main() -> None:
    from delimscan.operators import baselines
    from delimscan.plans import measures, workloads
    from delimscan.plans.reader import read_delimited
    from delimscan.sources.files import listed
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    size, queries, rates = {}, {}, {}
    inputs = {n: workloads.one_large(spark, SF_DIR, n) for n in ("text9", "num17", "pages", "conversations")}
    of_size = lambda path: sum(n for _, n in listed(spark, path))
    size |= {n: of_size(p) for n, p in inputs.items()}
    split = lambda n: max(1 << 20, -(-size[n] // int(CPUS)))
    schema = {n: workloads.frame(spark, SF_DIR, n).schema for n in inputs}

    def timed(name: str, run, of: str, times: int = 3) -> None:
        taken = []
        for _ in range(times):
            began = time.perf_counter()
            measures.force(run())
            taken.append(time.perf_counter() - began)
        queries[name] = round(median(taken), 3)
        rates[name] = round(size[of] / 1e6 / queries[name], 2)

    scan = lambda n, **o: read_delimited(spark, inputs[n], schema=schema[n], split_bytes=split(n), **o).df
    measures.force(scan("conversations"))  # starts workers, compiles code
    for n in tuple(inputs):
        timed(f"parse_{n}", lambda n=n: scan(n), n)
    timed("parse_text9_two_columns", lambda: scan("text9", columns=["doc_id", "lang"]), "text9")
    timed("infer_num17", lambda: read_delimited(spark, inputs["num17"], split_bytes=split("num17")).df, "num17")
    timed("baseline_spark_csv_text9", lambda: baselines.spark_csv(spark, inputs["text9"], schema["text9"]), "text9")
    timed("baseline_spark_csv_num17", lambda: baselines.spark_csv(spark, inputs["num17"], schema["num17"], multiline=False), "num17")
    timed("baseline_sequential_text9", lambda: baselines.sequential(spark, inputs["text9"], schema["text9"]), "text9")
    timed("baseline_prepass_text9", lambda: baselines.prepass(spark, inputs["text9"], schema["text9"], split_bytes=split("text9")), "text9")
    timed("baseline_speculative_text9", lambda: baselines.speculative(spark, inputs["text9"], schema["text9"], split_bytes=split("text9"))[0], "text9")
    timed("baseline_one_task_per_field_text9", lambda: baselines.one_task_per_field(spark, inputs["text9"], schema["text9"], split_bytes=split("text9")), "text9", 1)
    timed("pricing_on_parsed", lambda: scan("num17", columns=["l_returnflag", "l_linestatus", "l_quantity"]).groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity")), "num17")
    total = sum(v for k, v in queries.items() if k.startswith("parse_"))
    if LARGE_MB:
        copies = max(1, LARGE_MB * 10**6 // size["text9"])
        inputs["large"], schema["large"] = workloads.one_large(spark, SF_DIR, "text9", copies), schema["text9"]
        size["large"] = of_size(inputs["large"])
        timed("parse_text9_large", lambda: read_delimited(spark, inputs["large"], schema=schema["large"], split_bytes=32 << 20).df, "large", 1)
        timed("baseline_spark_csv_text9_large", lambda: baselines.spark_csv(spark, inputs["large"], schema["large"]), "large", 1)
        timed("baseline_sequential_text9_large", lambda: baselines.sequential(spark, inputs["large"], schema["large"]), "large", 1)
    print(json.dumps({"metric": "parse_seconds", "value": round(total, 3), "unit": "sec", "queries": queries, "mb_per_second": rates, "sf": SF_DIR}))


if __name__ == "__main__":
    main()
