"""Headline timings: one JSON line. BENCH_SF_DIR is the tables' folder, BENCH_CPUS the cores, BENCH_RUNS the runs of each figure after one that isn't counted."""

from __future__ import annotations

import json
import os
import statistics
import sys
import tempfile
import time

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from symseek.functions import kernels
from symseek.functions.costmodel import SPEEDS
from symseek.operators import baselines, hits, sifter
from symseek.plans.methods import docs, lines100
from symseek.plans.registry import Tables
from symseek.plans.workloads import cut_patterns
from symseek.sources import scratch
from symseek.sources import streams as S

RUNS = int(os.environ.get("BENCH_RUNS", "5"))
LENGTH, LPS, KS, PATTERNS = 3104, (5, 7, 10, 15), (2, 3, 4, 5), (1, 5, 10, 20, 40)


def timed(run, runs: int = RUNS) -> tuple[float, float]:
    """Median and deviation of the seconds of some runs, after one that isn't counted."""
    run()
    seconds = []
    for _ in range(runs):
        began = time.perf_counter()
        run()
        seconds.append(time.perf_counter() - began)
    return statistics.median(seconds), statistics.stdev(seconds) if runs > 1 else 0.0


def sweep() -> dict[str, dict]:
    """Nanoseconds of the kernel for a start, and for a cell of its full matrix, in one process: symbol bits x lp x K. Codes have 32 bits whatever the alphabet."""
    out = {}
    rng = np.random.default_rng(1)
    for bits in (4, 8, 12, 16):
        codes = rng.integers(0, 1 << bits, 20_000 + 64).astype(np.uint32)
        starts = np.arange(20_000)
        for lp in (8, 16, 24, 32):
            pattern = rng.integers(0, 1 << bits, lp).astype(np.uint32)
            for k in (1, 2, 3, 4):
                began = time.perf_counter()
                kernels.band_distances(codes, starts, pattern, k)
                ns = (time.perf_counter() - began) / len(starts) * 1e9
                out[f"{bits}x{lp}x{k}"] = {"start": round(ns, 1), "cell": round(ns / (lp * (lp + k)), 3)}
    return out


def main() -> None:
    folder, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    home = tempfile.mkdtemp(prefix="bench-")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").config("spark.sql.warehouse.dir", f"{home}/warehouse").config("spark.checkpoint.dir", f"{home}/shared").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    t = Tables(spark, folder)
    text = S.first_symbols(lines100(t), LENGTH).repartition(int(cpus)).persist()
    count, symbols = text.agg(F.count(F.lit(1)), F.sum("n")).first()
    given = {(lp, k): p for (lp, k), (_, p, _) in zip([(lp, k) for lp in LPS for k in KS], S.collected(cut_patterns(t, [(10 * lp + k, lp, k) for lp in LPS for k in KS])), strict=True)}
    seconds, extra = {}, {}

    def run(name: str, job, runs: int = RUNS, **more) -> None:
        seconds[name], spread = timed(lambda: job().agg(F.count(F.lit(1))).collect(), runs)
        scratch.clear(spark)
        extra[name] = {"std": round(spread, 4), "runs": runs} | more

    def sift(streams, patterns, engine: str = "kernel"):
        table = S.pattern_frame(spark, patterns)
        return lambda: sifter.sift(streams, table, engine=engine, number=False)

    published = {(test, lp, k): software for test, lp, k, software, _, _ in SPEEDS}
    for _ in range(2):  # warm
        sift(text, [(0, given[7, 3], 3)])().count()
    # the whole grid of the two speed tests: pattern length by threshold, all streams together
    for (lp, k), pattern in given.items():
        name = f"speed_lp{lp}_k{k}"
        run(name, sift(text, [(0, pattern, k)]))
        extra[name] |= {"seconds_per_stream": round(seconds[name] / count, 5), "symbols_per_second": round(symbols / seconds[name]), "cells_per_second": round(symbols * lp * (lp + k) / seconds[name])}
        for test in (1, 2):
            if (test, lp, k) in published:
                extra[name] |= {f"published_software_{test}": published[test, lp, k], f"times_faster_{test}": round(published[test, lp, k] / (seconds[name] / count), 1)}
    # the same pattern and threshold by the other engines, the parts, and the baselines
    one, few = [(0, given[7, 3], 3)], min(3, RUNS)
    table = S.pattern_frame(spark, one)
    run("hits_only_lp7_k3", lambda: hits.find_hits(text, table), few)
    run("hits_wavefront_lp7_k3", lambda: hits.find_hits(text, table, kernel="wavefront"), few)
    for engine in ("auto", "native", "serial"):
        run(f"{engine}_lp7_k3", sift(text, one, engine), few)
    run("free_start_lp7_k3", lambda: baselines.free_start_ends(text, table), few)
    short = S.first_symbols(text, 256).where("stream_id < 25").repartition(int(cpus)).persist()
    run("exhaustive_25x256_lp7_k3", lambda: hits.exhaustive_hits(short, table, materialize=False), few)
    run("free_start_25x256_lp7_k3", lambda: baselines.free_start_ends(short, table), few)
    run("online_25x256_lp7_k3", sift(short, one), few)
    # the bank: a growing number of patterns over all documents
    every = docs(t).repartition(4 * int(cpus)).persist()
    size = every.agg(F.sum("n")).first()[0]
    bank = S.collected(S.pattern_bank(t.benchmark, F.col("item_id"), S.fold_ascii(F.col("text")), 16, 4))
    for p in PATTERNS:
        run(f"bank_{p}", sift(every, bank[:p]), min(2, RUNS), symbols=size, symbol_patterns_per_second=0)
        extra[f"bank_{p}"]["symbol_patterns_per_second"] = round(size * p / seconds[f"bank_{p}"])
    extra["kernel_ns"] = sweep()
    extra["rates"] = {"streams": count, "symbols": symbols, "symbols_per_second_lp7_k3": round(symbols / seconds["speed_lp7_k3"]), "published_software_symbols_per_second_lp7_k3": round(LENGTH / published[1, 7, 3], 1)}
    total = sum(seconds.values())
    print(json.dumps({"metric": "online_sifter_total", "value": round(total, 3), "unit": "sec", "queries": {k: round(v, 4) for k, v in seconds.items()}, "sf": folder.rstrip("/").rpartition("sf")[2], "details": extra}))


if __name__ == "__main__":
    sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
    main()
