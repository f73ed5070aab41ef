"""Times the headline queries and prints one JSON line.

BENCH_SF_DIR (default /root/testdata/sf0.1), BENCH_CPUS (default 8).  Each query is run
into the ``noop`` sink, once to warm up and then timed; the metric is the sum.
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from coverdistinct.functions import theory
from coverdistinct.operators import counters, estimators, fused, probe, sampling
from coverdistinct.plans import catalogue
from coverdistinct.sources import streams

HEADLINE = ["m1_sampled", "m1_grouped", "m2_sampled", "m2_grouped", "b1_naive", "b2_full", "b3_exact", "g1_spectrum", "g2_heads", "r3_probe_value_hash", "c5_bottom_m", "k1_best_split", "x_rollup_registers"]


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g")
             .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate())
    spark.sparkContext.setLogLevel("ERROR")
    jobs = {name: (lambda q=catalogue.QUERIES[name]: q(spark, sf_dir)) for name in HEADLINE}
    x = lambda: streams.load(spark, sf_dir, "part_key", native=True)
    jobs |= {
        # the same methods with the fast hash, as production would run them
        "fast_m1": lambda: estimators.estimate_from(x(), 0.1, counters.HyperLogLog(200, fast=True), fast=True),
        "fast_m2": lambda: estimators.estimate_subsampled(sampling.bernoulli(x(), 0.1, fast=True), 500, counters.HyperLogLog(200, fast=True), fast=True),
        "fast_fused": lambda: fused.fused(sampling.bernoulli(x(), 0.1, fast=True), 500, counters.HyperLogLog(200, fast=True)),
        "fast_full": lambda: estimators.full(x(), counters.HyperLogLog(200, fast=True)),
        "fast_probe": lambda: probe.probe(x(), 500, fast=True),
        "builtin_full": lambda: estimators.full(x(), counters.BuiltinHll()),
    }
    took = {}
    for name, job in jobs.items():
        for turn in range(2):
            start = time.perf_counter()
            job().write.format("noop").mode("overwrite").save()
            took[name] = round(time.perf_counter() - start, 3)
    rows = x().count()
    runs = int(os.environ.get("BENCH_RUNS", "200"))
    start = time.perf_counter()
    accuracy = {}
    tables = {"example": catalogue._w1_model(spark, sf_dir, runs), "sampled": catalogue.model_sampled(spark, sf_dir, runs), "subsampled": catalogue.model_subsampled(spark, sf_dir, runs=runs),
              "heavy": catalogue.model_subsampled(spark, sf_dir, "heavy", runs=runs), "storage": catalogue.model_storage(spark, sf_dir, runs)}
    for table, got in tables.items():
        for r in (x.asDict() for x in got.collect()):
            key = " ".join(filter(None, (r.get("stream") or r.get("method"), f"P={r['rate']:g} m={r['m']}", f"u={r['u']}" if r.get("u") else None)))
            accuracy.setdefault(table, {})[key] = {k: round(r[k], 5) for k in ("bias", "variance", "analysis", "published_bias", "published_simulation") if r.get(k) is not None}
    took["model_tables"] = round(time.perf_counter() - start, 3)
    print(json.dumps({"metric": "headline queries, second run, sum", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf_dir.rstrip("/").rpartition("sf")[2], "runs": runs, "accuracy": accuracy,
                      "rows_per_sec_full_stream": {k: round(rows / took[k]) for k in ("fast_m1", "fast_m2", "fast_full", "builtin_full")},
                      "storage_units": {"sampled": theory.storage("sampled", 200, int(rows * 0.1)), "subsampled": theory.storage("subsampled", 200, u=500)}}))


if __name__ == "__main__":
    main()
