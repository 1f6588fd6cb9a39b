"""The hard direction: sorting blocks by one median filter.

A block of m values between m - 1 low and m - 1 high pads is filtered with
2 m - 1 rows: the window that starts at i holds m - 1 - i low pads, all values
and i high pads, so its median is the value of rank i.

Nothing but the filter compares values: positions number the rows by the order
columns, a pad is a side (-1 or 1) without a value, and the filter's medians are
the sorted values themselves.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.positions import global_positions
from ..plans.spec import names
from ..plans.tiles import assign_blocks
from .filters import sliding_median


def padded(df: DataFrame, value: str, m: int, order_by, partition_by=()) -> DataFrame:
    """(series, blk, seat, side, value): each block between its pads, which have no value, so real extremes stay legal."""
    keys = names(partition_by)
    placed = assign_blocks(global_positions(df.select(*dict.fromkeys([*keys, *names(order_by), value])), names(order_by), keys), m)
    real = placed.select(*keys, "blk", (F.col("off") + m - 1).cast("long").alias("seat"), F.lit(0).alias("side"), value)
    blocks = placed.groupBy(*keys, "blk").agg(F.count("*").alias("held"))
    pads = blocks.select(*keys, "blk", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(3 * m - 3).cast("long"))).alias("seat"), "held")
    pads = pads.where((F.col("seat") < m - 1) | (F.col("seat") >= F.col("held") + m - 1))
    side = F.when(F.col("seat") < m - 1, -1).otherwise(1)
    return real.unionByName(pads.select(*keys, "blk", "seat", side.alias("side"), F.lit(None).cast(df.schema[value].dataType).alias(value)))


def sort_blocks_by_median(df: DataFrame, value: str, block_len: int, order_by: str | Sequence[str], partition_by: str | Sequence[str] = (), *, isolate: bool = True) -> DataFrame:
    """(series, blk, rnk, value): blocks sorted by filtering.

    ``isolate`` makes each padded block a series of its own; else all of them
    form one vector for one filter, and windows that straddle blocks are left
    out. Values are null only in pads; a null in the input is refused.
    """
    m, keys = block_len, names(partition_by)
    rows = padded(df, value, m, order_by, keys)
    if isolate:
        found = sliding_median(rows, value, 2 * m - 1, "seat", [*keys, "blk"], route="short_series", pads="side", extra=("side",), out="__med")
        found = found.withColumnRenamed("pos", "rnk")
    else:
        line = rows.withColumn("line", F.col("blk") * (3 * m - 2) + F.col("seat"))
        found = sliding_median(line, value, 2 * m - 1, "line", keys, pads="side", extra=("blk", "seat"), out="__med")
        found = found.where(F.col("seat") < m).withColumn("rnk", F.col("seat"))
    # A last block has fewer values; the windows behind its last value show pads.
    held = rows.where("side = 0").groupBy(*keys, "blk").agg(F.count("*").alias("__held"))
    named = held.withColumnsRenamed({k: f"__{k}" for k in [*keys, "blk"]})
    same = [F.col(k).eqNullSafe(F.col(f"__{k}")) for k in [*keys, "blk"]]
    return found.join(named, same).where("rnk < __held").select(*keys, "blk", "rnk", F.col("__med").alias(value))
