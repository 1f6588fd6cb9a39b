"""Piecewise sorting of a series, and filters from sorted blocks."""

from __future__ import annotations

import bisect
from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.codes import encode
from ..functions.kernels import whole_series, window_ranks
from ..functions.sorting import ORDERS
from ..plans.positions import global_positions
from ..plans.spec import names
from ..plans.tiles import assign_blocks, blocks_per_tile

SORTERS = ("auto", "engine", "adaptive", "radix", "array", "window")


def _ranked_in_task(placed: DataFrame, value: str, k: int, keys: list[str], sorter: str) -> DataFrame:
    """Sort in the task: by the engine's external sort, or by the matrix sorts."""
    per_tile = blocks_per_tile(k)
    dealt = placed.withColumn("tile", F.expr(f"blk div {per_tile}")).repartition(*keys, "tile")
    columns = [*keys, "blk", "rnk", "off", value]
    schema = T.StructType([*[placed.schema[c] for c in keys], T.StructField("blk", T.LongType()), T.StructField("rnk", T.LongType()), T.StructField("off", T.LongType()), placed.schema[value]])

    def number(batches):
        for table, cuts in whole_series(batches, [*keys, "blk"]):
            ranks = np.arange(table.num_rows) - np.repeat(cuts[:-1], np.diff(cuts))
            yield from table.append_column("rnk", pa.array(ranks)).select(columns).combine_chunks().to_batches()

    def arrange(batches):
        for table, cuts in whole_series(batches, [*keys, "blk"]):
            codes, lengths = encode(table.column(value)).codes, np.diff(cuts)
            order = np.arange(table.num_rows)
            for size in np.unique(lengths):
                at = cuts[:-1][lengths == size]
                place = at + np.arange(size)[:, None]
                inside = ORDERS[sorter](codes[place])
                order[place] = at + inside
            ranks = np.arange(table.num_rows) - np.repeat(cuts[:-1], lengths)
            yield from table.take(pa.array(order)).append_column("rnk", pa.array(ranks)).select(columns).combine_chunks().to_batches()

    if sorter == "engine":
        return dealt.sortWithinPartitions(*keys, "blk", value, "off").select(*keys, "blk", "off", value).mapInArrow(number, schema)
    return dealt.sortWithinPartitions(*keys, "blk", "off").select(*keys, "blk", "off", value).mapInArrow(arrange, schema)


def piecewise_sort(df: DataFrame, value: str, k: int, order_by: str | Sequence[str], partition_by: str | Sequence[str] = (), *, sorter: str = "auto") -> DataFrame:
    """(series, blk, rnk, off, value): the rows of each block of ``k`` in stable ascending order."""
    if sorter not in SORTERS:
        raise ValueError(f"sorter must be one of {SORTERS}")
    keys = names(partition_by)
    placed = assign_blocks(global_positions(df.select(*dict.fromkeys([*keys, *names(order_by), value])), names(order_by), keys), k)
    placed = placed.withColumn("off", F.col("off").cast("long"))
    if sorter == "window":
        rank = F.row_number().over(Window.partitionBy(*keys, "blk").orderBy(value, "off")).cast("long") - 1
        return placed.select(*keys, "blk", rank.alias("rnk"), "off", value)
    if sorter == "array":
        held = placed.groupBy(*keys, "blk").agg(F.array_sort(F.collect_list(F.struct(F.col(value).alias("v"), F.col("off").alias("o")))).alias("held"))
        return held.select(*keys, "blk", F.posexplode("held").alias("rnk", "item")).select(*keys, "blk", F.col("rnk").cast("long").alias("rnk"), F.col("item.o").alias("off"), F.col("item.v").alias(value))
    return _ranked_in_task(placed, value, k, keys, sorter)


def block_permutations(df: DataFrame, value: str, k: int, order_by, partition_by=(), *, inverse: bool = False) -> DataFrame:
    """(series, blk, order): offsets in sorted order as an array, or each offset's rank."""
    keys = names(partition_by)
    ranked = piecewise_sort(df, value, k, order_by, keys, sorter="window")
    by, what = ("off", "rnk") if inverse else ("rnk", "off")
    held = F.array_sort(F.collect_list(F.struct(F.col(by).alias("by"), F.col(what).alias("what"))))
    return ranked.groupBy(*keys, "blk").agg(F.transform(held, lambda x: x["what"]).alias("order"))


def medians_from_sorted_blocks(sorted_blocks: DataFrame, value: str, k: int, r: int | None = None, partition_by=(), out: str = "med") -> DataFrame:
    """(series, pos, out): the linear pass alone, from rows (series, blk, rnk, off, value) sorted in blocks.

    ``pos`` is the first row of the window. Nothing is compared to sort: the
    order of each block is what the input says.
    """
    keys, rank = names(partition_by), k // 2 if r is None else r
    per_tile = blocks_per_tile(k)
    own = F.expr(f"blk div {per_tile}")
    places = F.when(F.expr(f"blk % {per_tile} = {per_tile - 1}"), F.array(own, own + 1)).otherwise(F.array(own))
    tiled = sorted_blocks.withColumn("tile", F.explode(places)).withColumn("halo", F.col("blk") < F.col("tile") * per_tile)
    tiled = tiled.select(*keys, "tile", "halo", "blk", "rnk", "off", value)
    schema = T.StructType([*[sorted_blocks.schema[c] for c in keys], T.StructField("pos", T.LongType()), T.StructField(out, sorted_blocks.schema[value].dataType)])

    def run(batches):
        for table, cuts in whole_series(batches, [*keys, "tile"]):
            lengths = np.diff(cuts)
            blk, off = np.asarray(table.column("blk")), np.asarray(table.column("off"))
            sorted_codes = encode(table.column(value))
            # Rows come by rank; the kernel wants values by offset and the order beside them.
            first_blk = np.repeat(blk[cuts[:-1]], lengths)
            block_start = np.repeat(cuts[:-1], lengths) + (blk - first_blk) * k
            codes = np.empty(table.num_rows, dtype=np.int64)
            codes[block_start + off] = sorted_codes.codes
            upper, _ = window_ranks(codes, cuts, k, [rank], orders=off.astype(np.int64))
            inner = np.arange(table.num_rows) - np.repeat(cuts[:-1], lengths)
            halo = np.repeat(np.asarray(table.column("halo"))[cuts[:-1]].astype(bool), lengths)
            ends = np.flatnonzero((inner > k - 1) | ((inner == k - 1) & ~halo))
            start = (first_blk * k + inner - (k - 1))[ends]
            columns = {key: table.column(key).take(pa.array(ends)) for key in keys}
            done = pa.table({**columns, "pos": pa.array(start.astype(np.int64)), out: sorted_codes.back(upper[0, ends])})
            yield from done.combine_chunks().to_batches()

    return tiled.repartition(*keys, "tile").sortWithinPartitions(*keys, "tile", "blk", "rnk").mapInArrow(run, schema)


def inversions(codes: list) -> int:
    """Pairs of items that stand in the wrong order."""
    held, total = [], 0
    for code in codes:
        place = bisect.bisect_right(held, code)
        total += len(held) - place
        held.insert(place, code)
    return total


def disorder_per_block(df: DataFrame, value: str, k: int, order_by, partition_by=()) -> DataFrame:
    """(series, blk, rows, descents, runs, is_sorted, inversions) of each block."""
    keys = names(partition_by)
    placed = assign_blocks(global_positions(df.select(*dict.fromkeys([*keys, *names(order_by), value])), names(order_by), keys), k)
    per_tile = blocks_per_tile(k)
    dealt = placed.withColumn("tile", F.expr(f"blk div {per_tile}")).repartition(*keys, "tile").sortWithinPartitions(*keys, "blk", "off")
    schema = T.StructType([*[placed.schema[c] for c in keys], *[T.StructField(c, T.BooleanType() if c == "is_sorted" else T.LongType()) for c in ("blk", "rows", "descents", "runs", "is_sorted", "inversions")]])

    def measure(batches):
        for table, cuts in whole_series(batches, [*keys, "blk"]):
            codes, first = encode(table.column(value)).codes, pa.array(cuts[:-1])
            down = np.concatenate([[False], codes[1:] < codes[:-1]])
            down[cuts[:-1]] = False
            descents = np.add.reduceat(down.astype(np.int64), cuts[:-1])
            wrong = [inversions(codes[a:b].tolist()) for a, b in zip(cuts, cuts[1:], strict=False)]
            columns = {key: table.column(key).take(first) for key in keys}
            counts = {"blk": table.column("blk").take(first), "rows": np.diff(cuts), "descents": descents, "runs": descents + 1, "is_sorted": descents == 0, "inversions": pa.array(wrong, pa.int64())}
            yield from pa.table({**columns, **counts}).combine_chunks().to_batches()

    return dealt.select(*keys, "blk", "off", value).mapInArrow(measure, schema)
