"""What the experiments measure."""

from __future__ import annotations

import math
import time
import tracemalloc
from collections.abc import Callable, Iterable, Sequence

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions.kernels import window_ranks
from .functions.links import walk_series
from .functions.sorting import ORDERS


def time_runs(run: Callable[[int], object], seeds: Iterable[int]) -> list[float]:
    """Wall seconds of one run for each seed."""
    out = []
    for seed in seeds:
        began = time.perf_counter()
        run(seed)
        out.append(time.perf_counter() - began)
    return out


def summary(times: Sequence[float]) -> dict[str, float]:
    """Median, and the band that holds the middle 80 % of the runs."""
    return {"median": float(np.median(times)), "p10": float(np.quantile(times, 0.1)), "p90": float(np.quantile(times, 0.9)), "runs": len(times)}


def relative(results: dict[str, float], method: str) -> float:
    """Time of the method over that of the fastest other one; below 1 it wins."""
    return results[method] / min(t for m, t in results.items() if m != method)


def growth_exponent(points: Sequence[tuple[float, float]]) -> float:
    """Slope of log time over log window size: near 1 for time in proportion to n k, near 0 for a flat one."""
    x, y = (np.log([p[i] for p in points]) for i in (0, 1))
    return float(np.polyfit(x, y, 1)[0])


def walk_counts(values: Sequence[int], k: int) -> dict[str, int]:
    """Pointer writes and marker moves of one scalar filter, with the bounds on both."""
    counts = {"writes": 0, "moves": 0}
    walk_series(values, k, counts=counts)
    blocks = math.ceil(len(values) / k)
    return {**counts, "write_bound": blocks * (2 * (k + 1) + 6 * k), "move_bound": 5 * blocks * k}


def peak_memory(run: Callable[[], object]) -> int:
    """Most bytes that the interpreter and its arrays held at once during one run, above what they held before."""
    tracemalloc.start()
    try:
        before = tracemalloc.get_traced_memory()[0]
        run()
        return tracemalloc.get_traced_memory()[1] - before
    finally:
        tracemalloc.stop()


def recovery(df: DataFrame, clean: str, estimate: str, within: float = 2.0) -> DataFrame:
    """One row: mean absolute, root mean square and greatest error, and the share within ``within``."""
    gap = F.abs(F.col(estimate) - F.col(clean))
    return df.agg(
        F.avg(gap).alias("mae"),
        F.sqrt(F.avg(gap * gap)).alias("rmse"),
        F.max(gap).alias("worst"),
        F.avg((gap <= within).cast("double")).alias("share_within"),
        F.count("*").alias("points"),
    )


def rank_error(df: DataFrame, approximate: DataFrame, value: str, k: int, order_by: Sequence[str], partition_by: Sequence[str] = (), out: str = "med") -> DataFrame:
    """One row: by how many ranks approximate medians (series, pos, out) miss the middle of their windows.

    The ranks of a value are those of the items of its window that equal it, or
    the two between which it falls.
    """
    keys, r = list(partition_by), k // 2
    by = Window.partitionBy(*keys).orderBy(*order_by)
    windows = df.select(*keys, (F.row_number().over(by).cast("long") - 1).alias("pos"), F.collect_list(value).over(by.rowsBetween(0, k - 1)).alias("__held"))
    both = windows.join(approximate.select(*keys, "pos", F.col(out).alias("__a")), [*keys, "pos"])
    below = F.size(F.filter("__held", lambda x: x < F.col("__a")))
    upto = F.size(F.filter("__held", lambda x: x <= F.col("__a")))
    miss = F.greatest(below - r, r + 1 - F.greatest(upto, below + 1), F.lit(0))
    return both.select(miss.alias("miss")).agg(F.count("*").alias("rows"), F.sum((F.col("miss") > 0).cast("long")).alias("different"), F.max("miss").alias("worst"), F.avg("miss").alias("mean"))


def shuffle_stats(df: DataFrame) -> dict[str, int]:
    """Exchanges, sorts and Python stages in the executed plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {name: text.count(mark) for name, mark in (("exchanges", "Exchange hashpartitioning"), ("single", "Exchange SinglePartition"), ("sorts", "Sort ["), ("python", "MapInArrow"))}


def traffic(spark: SparkSession, run: Callable[[], object]) -> dict[str, int]:
    """Bytes that the stages of one run shuffled and spilled, and the rows and bytes that they read."""
    store, gateway = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._gateway

    def stages() -> dict:
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
        listed = store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
        return {(s.stageId(), s.attemptId()): s for s in (listed.apply(i) for i in range(listed.size()))}

    before = stages().keys()
    run()
    fresh = [s for key, s in stages().items() if key not in before]
    names = {"shuffle_written": "shuffleWriteBytes", "shuffle_read": "shuffleReadBytes", "memory_spilled": "memoryBytesSpilled", "disk_spilled": "diskBytesSpilled", "rows_read": "inputRecords", "bytes_read": "inputBytes"}
    return {name: sum(getattr(s, method)() for s in fresh) for name, method in names.items()}


def phases(values: np.ndarray, k: int, sorter: str = "adaptive") -> dict[str, float]:
    """Seconds of the sort of all blocks, and of the linear pass that walks them with the orders given."""
    blocks = len(values) // k
    data = values[: blocks * k]
    began = time.perf_counter()
    order = ORDERS[sorter](np.ascontiguousarray(data.reshape(blocks, k).T))
    sorted_at = time.perf_counter()
    window_ranks(data, np.array([0, len(data)]), k, [k // 2], orders=np.ascontiguousarray(order.T).ravel())
    return {"sort": sorted_at - began, "walk": time.perf_counter() - sorted_at}
