"""Sliding medians, order statistics, and filters made of them."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.planner import plan
from ..plans.positions import positions_in_range
from ..plans.spec import SlidingSpec, median_rank, names


def _spec(value: str, k: int, order_by, partition_by, **options) -> SlidingSpec:
    keys = names(partition_by)
    return SlidingSpec(value, k, tuple(c for c in names(order_by) if c not in keys), tuple(keys), **options)


def sliding_median(df: DataFrame, value: str, k: int, order_by: str | Sequence[str], partition_by: str | Sequence[str] = (), *, even: str = "mean", out: str = "med", out_range: tuple[int, int] | None = None, pre_filter: Column | None = None, hints: dict[str, int] | None = None, **options) -> DataFrame:
    """Median of every window of ``k`` consecutive rows of a series.

    Gives partition and order columns of the row that carries the window (its
    first one, by default), that row's position, and the median. ``pre_filter``
    removes rows before windows are formed; ``out_range`` keeps windows whose
    carrying position lies in the half-open range, and reads no further than
    they reach where positions are at hand. Other options are fields of
    ``SlidingSpec``: align, edges, constant, nulls, kernel, sorter, route,
    ties, stride, extra.
    """
    if even not in ("mean", "lower", "upper"):
        raise ValueError(f"even must be mean, lower or upper, not {even!r}")
    rank, share = median_rank(k, even) if k >= 1 else (0, 1.0)
    if options.get("edges") == "partial" and even == "mean":
        share = 0.5  # incomplete windows may have two middle items
    rows = df if pre_filter is None else df.where(pre_filter)
    found = plan(rows, _spec(value, k, order_by, partition_by, ranks=(rank,), outputs=(out,), shares=(share,), **options), hints)
    return found if out_range is None else found.where((F.col("pos") >= out_range[0]) & (F.col("pos") < out_range[1]))


def median_in_range(df: DataFrame, value: str, k: int, order_by, low: int, high: int, out: str = "med", **options) -> DataFrame:
    """Windows that start at positions low ... high - 1, from just the rows they reach.

    The range on the output becomes one on the input, wider by k - 1 rows.
    """
    placed = positions_in_range(df, names(order_by), low, high + k - 1).withColumnRenamed("pos", "__pos")
    found = sliding_median(placed, value, k, "__pos", out=out, extra=tuple(names(order_by)), **options)
    return found.select(*names(order_by), F.col("__pos").alias("pos"), out)


def sliding_order_stat(df: DataFrame, value: str, k: int, r: int, order_by, partition_by=(), *, out: str = "stat", hints=None, **options) -> DataFrame:
    """The item of 0-based rank ``r`` of every window; 0 is the moving minimum, k - 1 the maximum."""
    return plan(df, _spec(value, k, order_by, partition_by, ranks=(r,), outputs=(out,), shares=(1.0,), **options), hints)


def quantile_rank(k: int, q: float, interpolate: bool) -> tuple[int, float]:
    """(rank, share of the upper item) of quantile q, at q * (k - 1)."""
    at = q * (k - 1)
    if not interpolate:
        return math.floor(at), 1.0
    return math.ceil(at), 1.0 if at == int(at) else at - math.floor(at)


def multi_quantile(df: DataFrame, value: str, k: int, quantiles: dict[str, float], order_by, partition_by=(), *, interpolate: bool = False, hints=None, **options) -> DataFrame:
    """Several quantiles of every window, one column each, in one walk of the lists."""
    placed = [quantile_rank(k, q, interpolate) for q in quantiles.values()]
    return plan(df, _spec(value, k, order_by, partition_by, ranks=tuple(r for r, _ in placed), shares=tuple(s for _, s in placed), outputs=tuple(quantiles), **options), hints)


def sliding_quantile(df: DataFrame, value: str, k: int, q: float, order_by, partition_by=(), *, interpolate: bool = False, out: str = "quantile", **options) -> DataFrame:
    return multi_quantile(df, value, k, {out: q}, order_by, partition_by, interpolate=interpolate, **options)


def sliding_iqr(df: DataFrame, value: str, k: int, order_by, partition_by=(), *, out: str = "iqr", **options) -> DataFrame:
    """Distance of the quartiles (items of ranks floor(q * (k - 1))) of every window."""
    both = multi_quantile(df, value, k, {"__q1": 0.25, "__q3": 0.75}, order_by, partition_by, **options)
    return both.withColumn(out, F.col("__q3") - F.col("__q1")).drop("__q1", "__q3")


def hampel_fast(df: DataFrame, value: str, k: int, order_by, partition_by=(), *, factor: float = 3.0, **options) -> DataFrame:
    """Rows with the centred median ``med``, the centred median ``mad`` of |value - med at that row|, and ``outlier``.

    Rows whose windows are not full keep no ``mad`` and are dropped. The second
    pass runs over the first's deviations, so it costs two filters.
    """
    keys, order = names(partition_by), names(order_by)
    first = sliding_median(df, value, k, order, keys, align="centered", extra=(value,), **options)
    gaps = first.drop("pos").withColumn("__gap", F.abs(F.col(value) - F.col("med")))
    second = sliding_median(gaps, "__gap", k, order, keys, align="centered", out="mad", extra=(value, "med", "__gap"), **options)
    return second.withColumn("outlier", F.col("__gap") > F.lit(factor) * F.col("mad")).drop("__gap", "pos")


def hampel(df: DataFrame, value: str, k: int, order_by, partition_by=(), *, factor: float = 3.0) -> DataFrame:
    """Rows with centred ``med``, the exact ``mad`` of their window, and ``outlier``.

    Deviations change with the window's centre, so each window's median of
    absolute deviations is taken on its own, as an array expression.
    """
    from pyspark.sql import Window

    keys, order = names(partition_by), names(order_by)
    h = k // 2
    frame = Window.partitionBy(*keys).orderBy(*order).rowsBetween(-h, k - 1 - h)
    held = F.collect_list(value).over(frame)
    rows = df.select(*keys, *order, value, held.alias("__held")).where(F.size("__held") == k)
    rows = rows.withColumn("med", F.element_at(F.array_sort("__held"), k // 2 + 1))
    gaps = F.array_sort(F.transform("__held", lambda x: F.abs(x - F.col("med"))))
    rows = rows.withColumn("mad", F.element_at(gaps, k // 2 + 1)).drop("__held")
    return rows.withColumn("outlier", F.abs(F.col(value) - F.col("med")) > F.lit(factor) * F.col("mad"))


def despike(df: DataFrame, value: str, k: int, order_by, partition_by=(), *, factor: float = 3.0, out: str = "clean") -> DataFrame:
    """Rows with outliers replaced by their window's median."""
    flagged = hampel(df, value, k, order_by, partition_by, factor=factor)
    return flagged.withColumn(out, F.when(F.col("outlier"), F.col("med")).otherwise(F.col(value)))
