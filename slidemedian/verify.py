"""Cross-checks of methods against each other."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .operators.baselines import run
from .plans.spec import names


def differences(one: DataFrame, other: DataFrame) -> DataFrame:
    """Rows of either that the other lacks."""
    return one.exceptAll(other).unionByName(other.exceptAll(one))


def agree(df: DataFrame, methods: Sequence[str], value: str, k: int, order_by, partition_by=()) -> DataFrame:
    """(method_a, method_b, rows, mismatches) of every pair of methods; one pass over their joined outputs."""
    on = [*names(partition_by), "pos"]
    outputs = [run(df, m, value, k, order_by, partition_by).select(*on, F.lit(m).alias("method"), F.col("med")) for m in methods]
    wide = reduce(DataFrame.unionByName, outputs).groupBy(*on).pivot("method", list(methods)).agg(F.first("med"))
    pairs = list(combinations(methods, 2))
    counts = [F.count_if(~F.col(a).eqNullSafe(F.col(b))).alias(f"{a}|{b}") for a, b in pairs]
    row = wide.agg(F.count("*").alias("rows"), *counts)
    items = F.array(*[F.struct(F.lit(a).alias("method_a"), F.lit(b).alias("method_b"), F.col(f"`{a}|{b}`").alias("mismatches")) for a, b in pairs])
    return row.select("rows", F.explode(items).alias("pair")).select("pair.method_a", "pair.method_b", "rows", "pair.mismatches")
