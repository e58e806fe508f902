"""Headline timings: one JSON line.

Queries run up to three times each, those of more than 15 seconds once, after a warm-up,
into a sink that discards rows; the median counts. "contexts" has the cost of packed document contexts by backend and
length (compression, reading what is left, both, reading at most 8192 tokens of the
context itself), "kernel" and "scaling" the compression of random vectors.
"""

from __future__ import annotations

import json
import os
import statistics
import sys
import time
from pathlib import Path

import numpy as np
from pyspark.sql import SparkSession

sys.path.insert(0, str(Path(__file__).resolve().parent))

from tokenfold import registry
from tokenfold.functions import kernels
from tokenfold.options import CompressOptions

TIMES, MOST_SECONDS = 3, 15
HEADLINE = ("chunk_rho4", "local_lsh_rho4", "adaptive_rho4", "adaptive_rho8", "pack_sequences", "actual_ratio")


def seconds(run, times: int = 3) -> float:
    run()
    out = []
    for _ in range(times):
        start = time.perf_counter()
        run()
        out.append(time.perf_counter() - start)
    return round(statistics.median(out), 4)


def kernel_times() -> dict[str, dict[str, float]]:
    """Seconds to compress one prompt by backend, ratio and length."""
    table = np.random.default_rng(0).normal(size=(23092, 64))
    table /= np.linalg.norm(table, axis=1, keepdims=True)

    def one(n: int, backend: str, rho: int) -> float:
        return seconds(lambda: kernels.compress(table[:n], CompressOptions(backend=backend, rho=rho)))

    grid = {f"{b}_rho{r}": one(4096, b, r) for b in ("chunk", "local", "adaptive") for r in (2, 4, 8, 16)}
    return {"kernel": grid, "scaling": {f"{b}_{n}": one(n, b, 4) for b in ("chunk", "local", "adaptive") for n in (2884, 5780, 11546, 23092)}}


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = (
        SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '8')}]")
        .config("spark.sql.shuffle.partitions", "16")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    queries, took = registry.queries(), {}
    queries[HEADLINE[0]](spark, sf_dir).write.format("noop").mode("overwrite").save()  # starts workers, compiles
    for name in HEADLINE:
        each = []
        while len(each) < TIMES and sum(each) < MOST_SECONDS:
            start = time.perf_counter()
            queries[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
            each.append(time.perf_counter() - start)
        took[name] = round(statistics.median(each), 3)
    costs = ("n_macro", "n_reference", "preprocess_s", "prefill_s", "total_s", "reference_s", "speedup", "peak_mb")
    contexts = {f"{r['backend']}_{r['n_tokens']}": {c: round(r[c], 4) for c in costs} for r in queries["w_scaling"](spark, sf_dir).collect()}
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf_dir.rsplit("sf", 1)[-1], "contexts": contexts, **kernel_times()}))
    spark.stop()


if __name__ == "__main__":
    main()
