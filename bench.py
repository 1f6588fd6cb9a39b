"""Headline queries on one machine; prints one JSON line.

``$BENCH_SF_DIR`` names the tables (default sf0.1), ``$BENCH_CPUS`` the cores.
``queries`` holds seconds of each headline query, the best of two runs after a
warm-up. ``duel`` compares the kernels of the contenders on equal terms, the
arrays and the interpreter being the same; ``growth`` is the slope of log time
over log window; ``ordered`` is the time on ascending input, with and without
noise, over that on uniform random input. ``studies`` are the experiments of
``slidemedian.workloads`` within a budget.
"""

from __future__ import annotations

import json
import os
import tempfile
import time

import numpy as np
from pyspark.sql import SparkSession

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
#: Seconds for the short forms of the studies.
STUDY_SECONDS = 40
HEADLINE = (
    "median_events_global",
    "median_events_per_user",
    "median_lineitem_price_k25",
    "median_lineitem_price_k1001",
    "median_lineitem_price_k20001",
    "median_lineitem_per_supp",
    "multi_quantile",
    "piecewise_sort_k1001",
    "baseline_engine_percentile",
    "baseline_double_heap",
    "sort_by_filter_isolated",
    "medians_from_sorted",
)


def session() -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", f"file://{tempfile.mkdtemp(prefix='slidemedian-bench-')}")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def timed(run) -> float:
    began = time.perf_counter()
    run()
    return time.perf_counter() - began


def best(run, rounds: int = 3) -> float:
    """The best of some runs; slow ones are not repeated."""
    first = timed(run)
    return first if first > 1 else min([first, *(timed(run) for _ in range(rounds - 1))])


def duel(rows: int = 60_000) -> dict:
    """Kernel seconds by method, generator and window, and what the published claims come to."""
    from slidemedian.functions.baselines import METHODS
    from slidemedian.functions.kernels import window_ranks
    from slidemedian.measures import growth_exponent

    rng = np.random.default_rng(1)
    inputs = {"wide_random": rng.integers(0, 1 << 31, rows), "noisy_up": np.arange(rows) + rng.integers(0, 10_000, rows), "ramp_up": np.arange(rows)}
    starts = np.array([0, rows])
    kernel = lambda name: lambda codes, k: window_ranks(codes, starts, k, [k // 2], kernel=name)
    windows = (5, 21, 101, 501, 2001)
    out: dict = {"seconds": {}, "growth": {}, "ordered": {}}
    methods = {"sorted_blocks": kernel("auto"), "sorted_blocks_lockstep": kernel("lockstep")}
    methods |= {m: (lambda c, k, f=f: f(c.tolist(), k, k // 2)) for m, f in METHODS.items()}
    for name, run in methods.items():
        times = {k: best(lambda r=run, k=k: r(inputs["wide_random"], k)) for k in windows}
        out["seconds"][name] = {str(k): round(t, 4) for k, t in times.items()}
        out["growth"][name] = round(growth_exponent(list(times.items())[1:]), 2)
        out["ordered"][name] = {g: round(best(lambda r=run, g=g: r(inputs[g], 501)) / max(times[501], 1e-9), 2) for g in ("noisy_up", "ramp_up")}
    others = {k: min(t[str(k)] for m, t in out["seconds"].items() if not m.startswith("sorted_blocks")) for k in windows}
    for name in ("sorted_blocks", "sorted_blocks_scalar"):
        out[f"{name}_to_best_other"] = {str(k): round(out["seconds"][name][str(k)] / max(others[k], 1e-9), 2) for k in windows}
    out["ratio_to_best_other"] = out["sorted_blocks_to_best_other"]
    out["scalar_to_double_heap"] = {str(k): round(out["seconds"]["sorted_blocks_scalar"][str(k)] / out["seconds"]["double_heap"][str(k)], 2) for k in windows}
    return out


def recovery(spark: SparkSession) -> dict:
    from slidemedian import catalog

    return {r["method"]: {"mae": r["mae"], "rmse": r["rmse"]} for r in catalog.QUERIES["recovery_quality"](spark, SF_DIR).collect()}


def main() -> None:
    from slidemedian import catalog, workloads

    spark = session()
    seconds: dict[str, float] = {}
    for name in HEADLINE:
        run = lambda n=name: catalog.QUERIES[n](spark, SF_DIR).write.format("noop").mode("overwrite").save()
        run()
        seconds[name] = round(min(timed(run) for _ in range(2)), 3)
    rows = spark.read.parquet(f"{SF_DIR}/lineitem.parquet").count()
    line = {"metric": "headline queries, total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": SF_DIR.rsplit("sf", 1)[-1]}
    line["rows_per_second_k1001"] = round(rows / seconds["median_lineitem_price_k1001"])
    line |= {"duel": duel(), "studies": workloads.studies(STUDY_SECONDS), "recovery": recovery(spark)}
    print(json.dumps(line))


if __name__ == "__main__":
    main()
