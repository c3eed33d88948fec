"""Headline queries at ``$BENCH_SF_DIR`` on ``local[$BENCH_CPUS]``; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time
from pathlib import Path

ROOT = Path(__file__).resolve().parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = os.pathsep.join([str(ROOT), *filter(None, [os.environ.get("PYTHONPATH")])])

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", "4"))


def main() -> None:
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", str(2 * CPUS))
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="bench-"))
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from pyspark.sql import functions as F

    from detspark import catalogue, workloads
    from detspark.operators import baseline, dedup, generate, metrics
    from detspark.plans.scratch import staged
    from detspark.sources.tables import configuration_set

    spec, sources = configuration_set(spark, SF_DIR, "ord4")
    sources = staged(sources, "sources")
    made = generate.moves(sources.repartition(4 * CPUS), spec)
    keys = staged(made, "keys")
    generated = keys.count()
    parts = 32
    noop = lambda f: f.write.format("noop").mode("overwrite").save()
    jobs = {
        "generation_ord4": lambda: noop(made),
        "dedup_range_sampled": lambda: noop(dedup.range_sampled(keys, parts)),
        "dedup_range_native": lambda: noop(dedup.range_native(keys, parts)),
        "dedup_hash": lambda: noop(baseline.dedup_hash(keys)),
        "dedup_salted": lambda: noop(baseline.dedup_salted(keys, parts)),
        "dedup_central": lambda: noop(baseline.dedup_central(keys, parts)),
        "generation_and_range_dedup": lambda: noop(dedup.range_native(made, parts)),
    }
    for name in ("config_pack_orders4", "couple_join", "couple_batch", "couple_rowwise", "local_energy", "global_energy", "topk_two_level", "iteration", "w3_medium"):
        jobs[name] = lambda q=catalogue.QUERIES[name]: noop(q(spark, SF_DIR))
    jobs["iteration"]()  # compile and start workers
    jobs["couple_batch"]()
    seconds = {}
    for name, job in jobs.items():
        began = time.perf_counter()
        job()
        seconds[name] = round(time.perf_counter() - began, 3)
    balance = {}
    for p in (32, 64):
        report = dedup.report(keys, p)
        for side in ("exchanged", "unique"):
            row = metrics.balance(report.parts, side).first()
            balance[f"{side}_{p}"] = {"ratio": row["ratio"] and round(row["ratio"], 3), "cv": round(row["cv"], 4)}
    shares = {}
    for r in workloads.breakdown(spark, SF_DIR, problems=("heavy",)).collect():
        shares.setdefault(r["variant"], {})[r["stage"]] = round(r["share"], 3)
    unique = report.unique
    print(json.dumps({
        "metric": "headline_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": SF_DIR, "cpus": CPUS,
        "generated": generated, "unique": unique, "redundancy": round(1 - unique / generated, 4),
        "generated_millions_per_s": round(generated / seconds["generation_ord4"] / 1e6, 3), "dedup_millions_per_s": round(generated / seconds["dedup_range_sampled"] / 1e6, 3),
        "balance": balance, "stage_shares": shares,
    }))


if __name__ == "__main__":
    main()
