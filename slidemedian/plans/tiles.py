"""Blocks, and tiles of consecutive blocks that a task can filter by itself."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows that a tile aims at, and the least blocks in it: at four blocks the repeated one adds a quarter.
TILE_ROWS, LEAST_BLOCKS = 1 << 17, 4


def assign_blocks(df: DataFrame, k: int) -> DataFrame:
    """Add ``blk`` and ``off`` to rows that have ``pos``."""
    return df.withColumns({"blk": F.expr(f"pos div {k}"), "off": F.expr(f"pos % {k}")})


def blocks_per_tile(k: int, tile_rows: int = TILE_ROWS) -> int:
    return max(LEAST_BLOCKS, tile_rows // k)


def with_halo(df: DataFrame, k: int, per_tile: int) -> DataFrame:
    """Add ``tile``; the last block of each tile comes again, marked ``halo``, at the start of the next."""
    rows = per_tile * k
    own = F.expr(f"pos div {rows}")
    last = F.expr(f"pos % {rows} >= {rows - k}")
    places = F.when(last, F.array(F.struct(own.alias("tile"), F.lit(False).alias("halo")), F.struct((own + 1).alias("tile"), F.lit(True).alias("halo")))).otherwise(
        F.array(F.struct(own.alias("tile"), F.lit(False).alias("halo")))
    )
    return df.withColumn("__place", F.explode(places)).select("*", "__place.tile", "__place.halo").drop("__place")


def neighbour_summaries(df: DataFrame, value: str, k: int, partition_by: Sequence[str] = ()) -> DataFrame:
    """(series, blk, low, high, before_low, before_high): each block's range and that of the block before."""
    blocks = assign_blocks(df, k).groupBy(*partition_by, "blk").agg(F.min(value).alias("low"), F.max(value).alias("high"))
    before = blocks.select(*partition_by, (F.col("blk") + 1).alias("blk"), F.col("low").alias("before_low"), F.col("high").alias("before_high"))
    return blocks.join(before, [*partition_by, "blk"])
