"""Headline timings: python bench.py prints one JSON line. BENCH_SF_DIR and BENCH_CPUS choose the input and the threads."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def main() -> None:
    from pyspark.sql import SparkSession

    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", str(2 * int(cpus)))
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.files.maxPartitionBytes", "4m").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from stablegrammar.operators.build import build_grammar
    from stablegrammar.operators.post import inline_singletons, run_length
    from stablegrammar.plans import baselines, measures, workloads

    def build(strings):
        return build_grammar(strings.repartition(2 * int(cpus)))

    build(workloads.benchmark(spark, sf_dir)).rules.count()  # starts workers and compiles
    took, size = {}, {}

    def timed(name, f):
        began = time.perf_counter()
        out = f()
        took[name] = round(time.perf_counter() - began, 3)
        return out

    docs = workloads.documents(spark, sf_dir)
    g = timed("build_documents", lambda: build(docs))
    rl = timed("run_length_documents", lambda: run_length(g))
    done = timed("inline_documents", lambda: inline_singletons(rl))
    size["documents"] = measures.plain_bytes(docs)
    for name in ("w3", "w4", "w5", "w6", "w9", "w10"):
        strings = workloads.ALL[name](spark, sf_dir)
        timed(f"build_{name}", lambda s=strings: build(s))
        if "text" in strings.columns:
            size[name] = measures.plain_bytes(strings)
    timed("lz_codec_documents", lambda: baselines.lz_codec(docs).collect())
    timed("level_stats_documents", lambda: measures.level_stats(g).collect())
    a, b, c = (measures.totals(x) for x in (g, rl, done))
    extra = {
        "mb_per_s": {k: round(v / 1e6 / took[f"build_{k}"], 2) for k, v in size.items()},
        "stages": {"run_length": measures.stage_stats(a, b), "inline": measures.stage_stats(b, c)},
        "ratio_documents": round(size["documents"] * 8 / measures.encoded_bits(c, 101), 3),
    }
    print(json.dumps({"metric": "total seconds of headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(sf_dir), **extra}))


if __name__ == "__main__":
    main()
