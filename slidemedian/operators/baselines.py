"""The contenders, behind one call with one input, specification and output."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.baselines import METHODS
from ..functions.codes import encode
from ..functions.kernels import whole_series
from ..plans.positions import global_positions
from ..plans.spec import names
from ..plans.tiles import blocks_per_tile, with_halo
from .filters import sliding_median

#: Outputs of a tile when one long series is cut for a contender.
TILE_ROWS = 1 << 15
ENGINE_METHODS = ("engine_percentile", "engine_approx", "collect_sort", "self_join")
ALL_METHODS = ("sorted_blocks", *METHODS, *ENGINE_METHODS)


def run(df: DataFrame, method: str, value: str, k: int, order_by, partition_by=()) -> DataFrame:
    """(series, order, pos, med) by the method of that name; odd ``k``, full windows, leading rows."""
    keys = names(partition_by)
    order = [c for c in names(order_by) if c not in keys]
    if method == "sorted_blocks":
        return sliding_median(df, value, k, order, keys)
    if method in METHODS:
        return _per_series(df, method, value, k, order, keys)
    return {"engine_percentile": engine_percentile, "engine_approx": engine_approx, "collect_sort": collect_sort, "self_join": self_join}[method](df, value, k, order, keys)


def _per_series(df: DataFrame, method: str, value: str, k: int, order: list[str], keys: list[str]) -> DataFrame:
    """Whole series in a task where there are series; one long series in tiles of rows that overlap by k - 1."""
    rows = df.select(*dict.fromkeys([*keys, *order, value]))
    schema = T.StructType([*[df.schema[c] for c in (*keys, *order)], T.StructField("pos", T.LongType()), T.StructField("med", df.schema[value].dataType)])
    tiled = not keys
    if tiled:
        placed = global_positions(rows, order)
        tiles = F.sequence(F.greatest(F.expr(f"(pos - {k - 1}) div {TILE_ROWS}"), F.lit(0)).cast("long"), F.expr(f"pos div {TILE_ROWS}"))
        dealt = placed.withColumn("tile", F.explode(tiles)).repartition("tile").sortWithinPartitions("tile", "pos")
        units = ["tile"]
    else:
        dealt = rows.repartition(*keys).sortWithinPartitions(*keys, *order)
        units = keys

    def walk(batches):
        slide = METHODS[method]
        for table, cuts in whole_series(batches, units):
            coded = encode(table.column(value))
            results, carriers, position = [], [], []
            for a, b in zip(cuts, cuts[1:], strict=False):
                series = coded.codes[a:b].tolist()
                if tiled:
                    # A tile gives the windows that start in it.
                    first = int(table.column("pos")[int(a)].as_py())
                    series = series[: TILE_ROWS + k - 1]
                else:
                    first = 0
                found = slide(series, k, k // 2)
                results += found
                carriers.append(np.arange(a, a + len(found)))
                position.append(np.arange(first, first + len(found)))
            if not results:
                continue
            out = table.select([*keys, *order]).take(pa.array(np.concatenate(carriers)))
            out = out.append_column("pos", pa.array(np.concatenate(position).astype(np.int64))).append_column("med", coded.back(np.array(results, dtype=np.int64)))
            yield from out.combine_chunks().to_batches()

    return dealt.mapInArrow(walk, schema)


def _framed(df: DataFrame, k: int, order: list[str], keys: list[str], item) -> DataFrame:
    by = Window.partitionBy(*keys).orderBy(*order)
    frame = by.rowsBetween(0, k - 1)
    rows = df.select(*keys, *order, (F.row_number().over(by).cast("long") - 1).alias("pos"), item(frame).alias("med"), F.count(F.lit(1)).over(frame).alias("__held"))
    return rows.where(F.col("__held") == k).drop("__held")


def engine_percentile(df: DataFrame, value: str, k: int, order_by, partition_by=()) -> DataFrame:
    """The engine's own exact percentile over a frame, computed afresh for each row."""
    kind = df.schema[value].dataType
    return _framed(df, k, names(order_by), names(partition_by), lambda w: F.percentile(value, 0.5).over(w).cast(kind))


def engine_approx(df: DataFrame, value: str, k: int, order_by, partition_by=(), accuracy: int = 20) -> DataFrame:
    """The engine's quantile sketch over a frame: approximate."""
    return _framed(df, k, names(order_by), names(partition_by), lambda w: F.percentile_approx(value, 0.5, accuracy).over(w))


def collect_sort(df: DataFrame, value: str, k: int, order_by, partition_by=()) -> DataFrame:
    """The frame as a list, sorted, and its middle item."""
    return _framed(df, k, names(order_by), names(partition_by), lambda w: F.try_element_at(F.array_sort(F.collect_list(value).over(w)), F.lit(k // 2 + 1)))


def self_join(df: DataFrame, value: str, k: int, order_by, partition_by=()) -> DataFrame:
    """Rows joined with the windows they lie in, by blocks of positions, and a percentile of each window."""
    keys, order = names(partition_by), names(order_by)
    placed = global_positions(df.select(*dict.fromkeys([*keys, *order, value])), order, keys)
    members = placed.select(*keys, F.col("pos").alias("__p"), F.col(value).alias("__v"), F.explode(F.array(F.expr(f"pos div {k}"), F.expr(f"pos div {k} - 1"))).alias("__blk"))
    windows = placed.select(*keys, *order, "pos", F.expr(f"pos div {k}").alias("__blk"))
    pairs = windows.join(members, [*keys, "__blk"]).where(F.expr(f"__p BETWEEN pos AND pos + {k - 1}"))
    kind = df.schema[value].dataType
    grouped = pairs.groupBy(*keys, *order, "pos").agg(F.percentile("__v", 0.5).cast(kind).alias("med"), F.count("*").alias("__held"))
    return grouped.where(F.col("__held") == k).drop("__held")


def moving_average(df: DataFrame, value: str, k: int, order_by, partition_by=(), *, align: str = "leading", out: str = "avg") -> DataFrame:
    """(series, order, pos, out): mean of every full window, the quality baseline.

    Without series keys the windows lie in tiles that repeat k rows, so no task has the whole series.
    """
    keys, order = names(partition_by), names(order_by)
    shift = {"leading": 0, "trailing": k - 1, "centered": k // 2}[align]
    rows = df.select(*dict.fromkeys([*keys, *order, value]))
    if keys:
        by = Window.partitionBy(*keys).orderBy(*order)
        rows = rows.withColumn("pos", F.row_number().over(by).cast("long") - 1)
        whole = F.col("__held") == k
    else:
        per_tile = blocks_per_tile(k)
        rows = with_halo(global_positions(rows, order), k, per_tile)
        by = Window.partitionBy("tile").orderBy("pos")
        # A window that ends in the repeated rows belongs to the tile before.
        whole = (F.col("__held") == k) & (F.col("pos") - shift + k - 1 >= F.col("tile") * (per_tile * k))
    frame = by.rowsBetween(-shift, k - 1 - shift)
    found = rows.withColumns({out: F.avg(value).over(frame), "__held": F.count(F.lit(1)).over(frame)})
    return found.where(whole).select(*keys, *order, "pos", out)
