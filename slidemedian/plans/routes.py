"""Physical routes of a sliding filter.

``short_series``: whole series in one exchange. ``blocks``: positions, tiles
with a repeated block, two exchanges. ``wide``: windows too large for a task;
tiles of neighbouring windows share a core, of which only a few ranks matter.
"""

from __future__ import annotations

import bisect
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.codes import encode
from ..functions.kernels import filter_batches, whole_series
from .positions import global_positions
from .spec import SlidingSpec
from .tiles import blocks_per_tile, with_halo


def result_schema(df: DataFrame, spec: SlidingSpec) -> T.StructType:
    fields = [df.schema[c] for c in (*spec.partition_by, *spec.order_by, *spec.extra)]
    outputs = [T.StructField(name, spec.result_type(df.schema, i)) for i, name in enumerate(spec.outputs)]
    return T.StructType([*fields, T.StructField("pos", T.LongType()), *outputs])


def needed(df: DataFrame, spec: SlidingSpec) -> DataFrame:
    """Only the columns the filter reads, and no null values under nulls='drop'."""
    columns = list(dict.fromkeys((*spec.partition_by, *spec.order_by, *spec.extra, spec.value, *filter(None, [spec.pads]))))
    rows = df.select(*columns)
    return rows.where(F.col(spec.value).isNotNull()) if spec.nulls == "drop" else rows


def short_series(df: DataFrame, spec: SlidingSpec) -> DataFrame:
    """One exchange by series; a task filters all its series at once."""
    keys = list(spec.partition_by)
    rows = needed(df, spec)
    dealt = rows.repartition(*keys) if keys else rows.coalesce(1)
    return dealt.sortWithinPartitions(*keys, *spec.order_by).mapInArrow(filter_batches(spec, keys), result_schema(df, spec))


def blocks(df: DataFrame, spec: SlidingSpec, per_tile: int | None = None, rows: int | None = None) -> DataFrame:
    """Positions, then tiles of equal size whatever the lengths of the series.

    Edge policies concern the ends of a series only. ``pad`` and ``reflect``
    add rows around each series, and full windows of the longer series do the
    rest; ``partial`` and ``keep`` add the results of the rows that carry no
    full window, from the k - 1 rows at each end.
    """
    keys = list(spec.partition_by)
    placed = global_positions(needed(df, spec), spec.order_by, keys, rows=rows)
    if spec.edges == "valid":
        return _tiled(df, placed, spec, per_tile)
    plain = replace(spec, edges="valid", stride=1)
    if spec.edges in ("pad", "reflect"):
        found = _tiled(df, _surrounded(placed, spec), plain, per_tile).withColumn("pos", F.col("pos") - spec.shift())
    else:
        # Incomplete windows may have two middle items where the full ones have one.
        whole = replace(plain, shares=tuple(1.0 if spec.edges == "partial" and s == 0.5 and spec.window % 2 else s for s in spec.shares))
        found = _tiled(df, placed, whole, per_tile)
        found = found.withColumns({name: F.col(name).cast(spec.result_type(df.schema, i)) for i, name in enumerate(spec.outputs)})
        if spec.window > 1:
            found = found.unionByName(_incomplete(df, placed, spec))
    return found.where(F.expr(f"pos % {spec.stride} = 0"))


def _tiled(df: DataFrame, placed: DataFrame, spec: SlidingSpec, per_tile: int | None) -> DataFrame:
    keys = list(spec.partition_by)
    tiled = with_halo(placed, spec.window, per_tile or blocks_per_tile(spec.window))
    dealt = tiled.repartition(*keys, "tile").sortWithinPartitions(*keys, "tile", "pos")
    return dealt.mapInArrow(filter_batches(spec, [*keys, "tile"], "halo"), result_schema(df, spec))


def _with_length(placed: DataFrame, keys: list[str]) -> DataFrame:
    """Add ``__n``, the rows of each series."""
    if not keys:
        return placed.crossJoin(F.broadcast(placed.agg((F.max("pos") + 1).alias("__n"))))  # one row
    lengths = placed.groupBy(*keys).agg((F.max("pos") + 1).alias("__n"))
    named = lengths.select(*[F.col(k).alias(f"__k{i}") for i, k in enumerate(keys)], "__n")
    same = [placed[k].eqNullSafe(named[f"__k{i}"]) for i, k in enumerate(keys)]
    return placed.join(named, same).drop(*[f"__k{i}" for i in range(len(keys))])


def _surrounded(placed: DataFrame, spec: SlidingSpec) -> DataFrame:
    """Rows at positions 0 ... n + k - 2, the series' own from ``shift`` on; the rows around repeat or replace values."""
    keys, before, after = list(spec.partition_by), spec.shift(), spec.window - 1 - spec.shift()
    own = placed.withColumn("pos", F.col("pos") + before)
    known = _with_length(placed, keys)
    if spec.edges == "reflect":
        # A row's images lie at -1 - p and 2 n - 1 - p, and again every 2 n rows.
        reach = F.ceil(F.lit(float(max(before, after) + 1)) / (2 * F.col("__n"))).cast("int") + 1
        turns = F.sequence(-reach, reach)
        images = F.flatten(F.transform(turns, lambda m: F.array(F.col("pos") + 2 * F.col("__n") * m, 2 * F.col("__n") * m - 1 - F.col("pos"))))
        outside = F.filter(images, lambda at: ((at < 0) & (at >= -before)) | ((at >= F.col("__n")) & (at < F.col("__n") + after)))
        near = (F.col("pos") < before) | (F.col("pos") >= F.col("__n") - after)
        around = known.where(near).withColumn("__at", F.explode(outside)).withColumn("pos", F.col("__at") + before)
    else:
        first = known.where("pos = 0")
        places = F.concat(*[F.sequence(low, high) if count else F.array().cast("array<bigint>") for count, low, high in ((before, F.lit(0).cast("long"), F.lit(before - 1).cast("long")), (after, F.col("__n") + before, F.col("__n") + before + after - 1))])
        kind = placed.schema[spec.value].dataType
        around = first.withColumn("pos", F.explode(places)).withColumn(spec.value, F.lit(spec.constant).cast(kind))
    return own.unionByName(around.select(*own.columns))


def _incomplete(df: DataFrame, placed: DataFrame, spec: SlidingSpec) -> DataFrame:
    """Results of the rows that carry no full window."""
    keys, k, before = list(spec.partition_by), spec.window, spec.shift()
    after = k - 1 - before
    known = _with_length(placed, keys)
    short = F.col("__n") < k
    head, tail = F.col("pos") < k - 1, F.col("pos") >= F.col("__n") - (k - 1)
    side = lambda n: F.array(F.lit(n))
    none = F.array().cast("array<int>")
    sides = F.when(short, side(0)).otherwise(F.concat(F.when(head, side(1)).otherwise(none), F.when(tail, side(2)).otherwise(none)))
    ends = known.withColumn("__side", F.explode(sides)).withColumn("__pos", F.col("pos")).drop("pos")
    own = replace(spec, edges=spec.edges, stride=1, partition_by=(*keys, "__side"), extra=(*spec.extra, "__pos", "__n"))
    dealt = ends.repartition(*keys, "__side").sortWithinPartitions(*keys, "__side", "__pos")
    found = dealt.mapInArrow(filter_batches(own, [*keys, "__side"]), result_schema(ends, own)).withColumn("pos", F.col("__pos"))
    carried = (F.col("__side") == 0) | ((F.col("__side") == 1) & (F.col("pos") < before)) | ((F.col("__side") == 2) & (F.col("pos") >= F.col("__n") - after))
    return found.where(carried).select(*[f.name for f in result_schema(df, spec)])


def wide(df: DataFrame, spec: SlidingSpec, tile: int | None = None, rows: int | None = None) -> DataFrame:
    """Windows of any size in memory proportional to the tile.

    A tile of w neighbouring windows shares the k - w + 1 values that lie in
    all of them. At most w - 1 other values are in a window, so its item of
    rank r is among the core's items of ranks r - (w - 1) to r and the changing
    values. Prefix counts of the core find the values that can hold those ranks;
    only those rows go on, with the number of smaller core rows.
    """
    k, rank = spec.window, spec.ranks[0]
    if len(spec.ranks) > 1 or spec.shares != (1.0,) or spec.edges != "valid" or spec.stride != 1 or spec.nulls == "poison":
        raise ValueError("the wide route gives one rank of full windows")
    w = tile or max(1, k // 4)
    keys = list(spec.partition_by)
    placed = global_positions(needed(df, spec), spec.order_by, keys, rows=rows)
    # Row p lies in windows p - k + 1 ... p, hence in these tiles of windows.
    tiles = F.sequence(F.greatest(F.expr(f"(pos - {k - 1}) div {w}"), F.lit(0)).cast("long"), F.expr(f"pos div {w}"))
    spread = placed.withColumn("tile", F.explode(tiles))
    ends = placed.groupBy(*keys).agg(F.max("pos").alias("end"))
    spread = spread.join(ends, keys) if keys else spread.crossJoin(F.broadcast(ends))  # one row
    first, last = F.col("tile") * w, F.col("tile") * w + w - 1
    spread = spread.withColumn("core", (F.col("pos") >= last) & (F.col("pos") <= first + k - 1))
    unit = [*keys, "tile"]
    core = spread.where("core")
    # Ranks of equal values are shared out by position, so each row has one.
    slices = bounds_of(df, spec.value)
    cell = F.size(F.filter(F.array(*[F.lit(b) for b in slices]), lambda b: b <= F.col(spec.value))) if slices else F.lit(0)
    cells = core.groupBy(*unit, cell.alias("cell")).agg(F.count("*").alias("n"))
    smaller = F.coalesce(F.sum("n").over(Window.partitionBy(*unit).orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    useful = cells.withColumn("less", smaller).where((F.col("less") <= rank) & (F.col("less") + F.col("n") > rank - (w - 1))).select(*unit, "cell", "less")
    kept = core.withColumn("cell", cell).join(useful, [*unit, "cell"])
    order = Window.partitionBy(*unit, "cell").orderBy(spec.value, "pos")
    kept = kept.withColumn("rank", F.col("less") + F.row_number().over(order) - 1).where((F.col("rank") <= rank) & (F.col("rank") >= rank - (w - 1)))
    changing = spread.where("NOT core").withColumn("rank", F.lit(None).cast("long"))
    columns = [*unit, "pos", "end", spec.value, "core", "rank"]
    walked = kept.select(*columns).unionByName(changing.select(*columns))

    def run(batches):
        for table, cuts in whole_series(batches, unit):
            for a, b in zip(cuts, cuts[1:], strict=False):
                part = table.slice(int(a), int(b - a))
                yield from walk_core(part, spec, w)

    schema = T.StructType([*[df.schema[k] for k in keys], T.StructField("pos", T.LongType()), T.StructField(spec.outputs[0], df.schema[spec.value].dataType)])
    found = walked.repartition(*unit).sortWithinPartitions(*unit, "pos").mapInArrow(run, schema)
    labels = placed.select(*keys, *[c for c in (*spec.order_by, *spec.extra) if c not in keys], (F.col("pos")).alias("pos"))
    shifted = found.withColumn("pos", F.col("pos") + spec.shift())
    return shifted.join(labels, [*keys, "pos"]).select(*keys, *[c for c in (*spec.order_by, *spec.extra) if c not in keys], "pos", spec.outputs[0])


def bounds_of(df: DataFrame, value: str, cells: int = 256) -> list:
    """Values that cut the column in about equal parts; any cut is right, even ones are fast."""
    kind = df.schema[value].dataType
    if not isinstance(kind, (T.NumericType, T.DateType, T.TimestampType, T.TimestampNTZType)):
        return []
    found = df.agg(F.percentile_approx(value, [i / cells for i in range(1, cells)], 4096)).first()[0] or []
    return sorted(set(found))


def walk_core(part: pa.Table, spec: SlidingSpec, w: int):
    """The w windows of a tile: core survivors stay, changing values leave and arrive."""
    coded = encode(part.column(spec.value))
    codes, pos = coded.codes, np.asarray(part.column("pos"))
    core = np.asarray(part.column("core"))
    k, rank = spec.window, spec.ranks[0]
    start = int(part.column("tile")[0].as_py()) * w
    windows = min(w, part.column("end")[0].as_py() - k + 2 - start)
    if windows < 1:
        return
    below = np.asarray(part.column("rank").combine_chunks().fill_null(-1))[core]
    offset = int(below.min()) if len(below) else min(rank, max(0, k - w + 1))
    held = sorted(codes[core].tolist())
    changing = dict(zip(pos[~core].tolist(), codes[~core].tolist(), strict=True))
    for p in range(start, start + min(w - 1, k)):
        bisect.insort(held, changing[p])
    # ``offset`` core rows lie below every survivor; a changing value may too.
    out = np.empty(windows, dtype=np.int64)
    for i in range(windows):
        if i:
            held.pop(bisect.bisect_left(held, changing[start + i - 1]))
            bisect.insort(held, changing[start + k + i - 1])
        out[i] = held[rank - offset]
    first = {key: part.column(key)[0].as_py() for key in spec.partition_by}
    arrays = [pa.array([first[key]] * windows, part.schema.field(key).type) for key in spec.partition_by]
    yield pa.RecordBatch.from_arrays([*arrays, pa.array(np.arange(start, start + windows)), coded.back(out)], names=[*spec.partition_by, "pos", spec.outputs[0]])


def run_route(df: DataFrame, spec: SlidingSpec, route: str, rows: int | None = None) -> DataFrame:
    """``rows``: the rows of the table, where they are known."""
    own = replace(spec, route=route)
    return short_series(df, own) if route == "short_series" else {"blocks": blocks, "wide": wide}[route](df, own, rows=rows)
