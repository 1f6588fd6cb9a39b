"""The filter on event-time streams.

Rows leave the state in event-time order once the watermark has passed them,
so late rows inside the watermark still find their place. A series keeps its
last k - 1 released rows and those not yet released; a release of m rows runs
the ordinary kernel over k - 1 + m values and gives m windows.
"""

from __future__ import annotations

import bisect
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.codes import fold_doubles, unfold_doubles
from ..functions.kernels import window_ranks
from ..plans.store import fresh_path

STATE = T.StructType(
    [
        T.StructField("micros", T.BinaryType()),
        T.StructField("ids", T.BinaryType()),
        T.StructField("values", T.BinaryType()),
        T.StructField("carried", T.LongType()),
        T.StructField("released", T.LongType()),
    ]
)
OUTPUT = "series long, id long, pos long, med double"
#: Windows of consecutive positions in one row: the position behind the last, ids and medians as arrays.
PACKED = "series long, past long, ids binary, meds binary"
MODES = ("auto", "blocks", "ordered")
#: A release of fewer than one row for so many of a window moves the ordered window on instead of running the kernel.
FEW = 16
#: Windows that leave a state at once.
PACK_ROWS = 1 << 16
#: Settings of a stream with one state: Spark ships the whole state again with each batch of rows to its worker, and each
#: trigger commits all partitions of the state, of which one holds something.
ONE_STATE = {"spark.sql.execution.arrow.maxRecordsPerBatch": str(1 << 20), "spark.sql.shuffle.partitions": "1"}
_KINDS = (np.int64, np.int64, np.float64)


def _advance(k: int, mode: str, packed: bool, rows: int):
    def medians(values: np.ndarray, carried: int) -> np.ndarray:
        """Of the full windows that end in rows ``carried`` and on."""
        codes = fold_doubles(values)
        fresh = len(values) - carried
        if mode == "blocks" or (mode == "auto" and fresh * FEW >= k):
            upper, _ = window_ranks(codes, np.array([0, len(codes)]), k, [k // 2])
            return unfold_doubles(upper[0, max(carried, k - 1) :])
        out, held, codes = [], np.sort(codes[:carried]).tolist(), codes.tolist()
        for i in range(carried, len(codes)):
            bisect.insort(held, codes[i])
            if len(held) > k:
                held.pop(bisect.bisect_left(held, codes[i - k]))
            if len(held) == k:
                out.append(held[k // 2])
        return unfold_doubles(np.array(out, dtype=np.int64))

    def advance(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        *columns, carried, released = state.get if state.exists else (b"", b"", b"", 0, 0)
        parts = [[np.frombuffer(column, kind)] for column, kind in zip(columns, _KINDS, strict=True)]
        if not state.hasTimedOut:
            for frame in frames:
                for part, name, kind in zip(parts, ("micros", "id", "value"), _KINDS, strict=True):
                    part.append(frame[name].astype(kind).to_numpy())
        micros, ids, values = map(np.concatenate, parts)
        # Rows still waiting keep the order of arrival, which breaks ties when they leave.
        passed = micros[carried:] <= state.getCurrentWatermarkMs() * 1000
        leaving, waiting = carried + np.flatnonzero(passed), carried + np.flatnonzero(~passed)
        leaving = leaving[np.lexsort((ids[leaving], micros[leaving]))]
        ready = carried + len(leaving)
        order = np.concatenate([np.arange(carried), leaving, waiting])
        micros, ids, values = micros[order], ids[order], values[order]
        released += len(leaving)
        cut = max(0, ready - (k - 1))
        state.update((micros[cut:].tobytes(), ids[cut:].tobytes(), values[cut:].tobytes(), ready - cut, released))
        if len(waiting):
            state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs() + 1, int(micros[ready:].min()) // 1000 + 1))
        if len(leaving) and ready >= k:
            found = medians(values[:ready], carried)
            first = max(carried, k - 1) - (k - 1)
            for low in range(0, len(found), rows):
                some, start = found[low : low + rows], first + low
                past, pos = start + len(some), released - ready + start
                if packed:
                    yield pd.DataFrame({"series": [key[0]], "past": [pos + len(some)], "ids": [ids[start:past].tobytes()], "meds": [some.tobytes()]})
                else:
                    yield pd.DataFrame({"series": key[0], "id": ids[start:past], "pos": np.arange(pos, pos + len(some)), "med": some})

    return advance


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for row in batch.to_pylist():
            ids, meds = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["meds"], np.float64)
            columns = np.full(len(ids), row["series"], np.int64), ids, np.arange(row["first"], row["first"] + len(ids)), meds
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["series", "id", "pos", "med"])


def stream_sliding_median(rows: DataFrame, value: str, k: int, ts: str, id_: str, series: str | None = None, delay: str = "1 hour", mode: str = "auto") -> DataFrame:
    """Streaming (series, id, pos, med) in append mode, for odd ``k``; each window comes once.

    ``ts`` orders rows, ties by ``id_``; rows later than ``delay`` are dropped
    by the watermark. ``pos`` and ``id`` are those of the window's first row.
    ``mode``: ``blocks`` runs the kernel over what a trigger releases and the
    k - 1 values before, ``ordered`` moves a sorted window on row by row, and
    ``auto`` does the latter for small releases. One global order has one state,
    and the task that holds it does no more than order rows and run the filter:
    its windows leave packed and become rows in the tasks of the next stage.
    Series run side by side.
    """
    if mode not in MODES:
        raise ValueError(f"mode must be one of {MODES}, not {mode!r}")
    timed = rows.select(
        (F.col(series) if series else F.lit(0)).cast("long").alias("series"),
        F.col(id_).cast("long").alias("id"),
        F.col(value).cast("double").alias("value"),
        F.col(ts).cast("timestamp").alias("event_time"),
    )
    timed = timed.withColumn("micros", F.unix_micros("event_time")).withWatermark("event_time", delay)
    grouped = timed.groupBy("series")
    if series:
        return grouped.applyInPandasWithState(_advance(k, mode, False, PACK_ROWS), OUTPUT, STATE, "append", GroupStateTimeout.EventTimeTimeout)
    packed = grouped.applyInPandasWithState(_advance(k, mode, True, PACK_ROWS), PACKED, STATE, "append", GroupStateTimeout.EventTimeTimeout)
    # The rows of the state's operator fit no exchange before a projection has computed something.
    placed = packed.select("series", F.expr("past - octet_length(ids) div 8").alias("first"), "ids", "meds")
    return placed.repartition(rows.sparkSession.sparkContext.defaultParallelism, "first").mapInArrow(_unpack, OUTPUT)


def slices(df: DataFrame, ts: str, parts: int, folder: str) -> None:
    """Write a table as consecutive time slices, one file each, in file order."""
    low, high = df.agg(F.min(F.unix_micros(F.col(ts).cast("timestamp"))), F.max(F.unix_micros(F.col(ts).cast("timestamp")))).first()
    step = (high - low) // parts + 1
    marked = df.withColumn("__slice", F.expr(f"(unix_micros(cast({ts} as timestamp)) - {low}) div {step}"))
    for i in range(parts):
        marked.where(F.col("__slice") == i).drop("__slice").repartition(1).write.mode("append").parquet(folder)


def flush_row(df: DataFrame, ts: str, id_: str, series: str | None) -> DataFrame:
    """One row far in the future, in a series of its own, that lets the watermark pass all others."""
    row = {ts: F.lit("2200-01-01 00:00:00").cast(df.schema[ts].dataType), id_: F.lit(-1).cast(df.schema[id_].dataType)}
    if series:
        row[series] = F.lit(-1).cast(df.schema[series].dataType)
    columns = [row.get(f.name, F.lit(None).cast(f.dataType)).alias(f.name) for f in df.schema]
    return df.sparkSession.range(1).select(*columns)


def run_counted(stream: DataFrame, label: str, one_state: bool = False) -> tuple[DataFrame, int]:
    """Run a stream over what is there, into shared files; gives those and the number of rows that came too late.

    ``one_state`` says that no operator of the stream has more than one state.
    """
    spark = stream.sparkSession
    folder = fresh_path(spark, label)
    sink = stream.writeStream.format("parquet").outputMode("append").option("checkpointLocation", f"{folder}/checkpoint").option("path", f"{folder}/out").trigger(availableNow=True)
    settings = ONE_STATE if one_state else {}
    held = {name: spark.conf.get(name) for name in settings}
    # A stream keeps the settings that it starts with.
    try:
        for name, setting in settings.items():
            spark.conf.set(name, setting)
        query = sink.start()
    finally:
        for name, setting in held.items():
            spark.conf.set(name, setting)
    query.awaitTermination()
    late = sum(op["numRowsDroppedByWatermark"] for progress in query.recentProgress for op in progress["stateOperators"])
    return spark.read.schema(stream.schema).parquet(f"{folder}/out"), late


def run_to_end(stream: DataFrame, label: str, one_state: bool = False) -> DataFrame:
    return run_counted(stream, label, one_state)[0]


def replay(df: DataFrame, ts: str, id_: str, series: str | None, parts: int, label: str) -> DataFrame:
    """The table as a file stream of time slices, closed by a row that flushes it."""
    folder = fresh_path(df.sparkSession, label)
    slices(df, ts, parts, folder)
    flush_row(df, ts, id_, series).coalesce(1).write.mode("append").parquet(folder)
    return df.sparkSession.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(folder)


def time_window_medians(stream: DataFrame, ts: str, value: str, length: str, slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """(first, past, rows, med) of tumbling or sliding time windows."""
    timed = stream.withColumn("event_time", F.col(ts).cast("timestamp")).withWatermark("event_time", delay)
    window = F.window("event_time", length, slide) if slide else F.window("event_time", length)
    grouped = timed.groupBy(window).agg(F.count(value).alias("rows"), F.percentile(value, 0.5).alias("med"))
    return grouped.select(F.col("window.start").alias("first"), F.col("window.end").alias("past"), "rows", "med")


def session_medians(stream: DataFrame, ts: str, value: str, series: str, gap: str, delay: str = "1 hour") -> DataFrame:
    """(series, first, rows, med) of sessions that a gap ends."""
    timed = stream.withColumn("event_time", F.col(ts).cast("timestamp")).withWatermark("event_time", delay)
    grouped = timed.groupBy(F.col(series).alias("series"), F.session_window("event_time", gap).alias("session")).agg(F.count(value).alias("rows"), F.percentile(value, 0.5).alias("med"))
    return grouped.select("series", F.col("session.start").alias("first"), "rows", "med")


def deduplicated(stream: DataFrame, ts: str, id_: str, delay: str = "1 hour") -> DataFrame:
    """The stream without repeated ids within the watermark."""
    return stream.withColumn("event_time", F.col(ts).cast("timestamp")).withWatermark("event_time", delay).dropDuplicatesWithinWatermark([id_]).drop("event_time")
