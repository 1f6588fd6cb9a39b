"""The filters in SQL: a table function, and functions on array cells."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult

from .functions.codes import encode
from .functions.kernels import window_ranks
from .plans.spec import median_rank


#: Rows that the table function holds before it gives results, or four windows if that is more.
TABLE_ROWS = 1 << 14


class SlidingMedianFunction:
    """``sliding_median(TABLE(t) PARTITION BY s ORDER BY (a, b), 'value', k)``: every input row that starts a full window, with ``pos`` and ``med``."""

    @staticmethod
    def analyze(table: AnalyzeArgument, value: AnalyzeArgument, k: AnalyzeArgument) -> AnalyzeResult:
        if not table.isTable:
            raise ValueError("the first argument must be a table")
        schema: T.StructType = table.dataType
        kind = schema[value.value].dataType
        mean = k.value % 2 == 0
        return AnalyzeResult(T.StructType([*schema.fields, T.StructField("pos", T.LongType()), T.StructField("med", T.DoubleType() if mean else kind)]))

    def __init__(self):
        self.rows, self.value, self.k, self.done = [], None, 0, 0

    def eval(self, row, value: str, k: int):
        """Holds rows of some windows only: results are given as soon as enough have come."""
        self.rows.append(tuple(row))
        if self.value is None:
            self.value, self.k = list(row.asDict()).index(value), k
        if len(self.rows) >= max(TABLE_ROWS, 4 * k):
            yield from self._windows()

    def terminate(self):
        yield from self._windows()

    def _windows(self):
        if len(self.rows) < self.k or not self.rows:
            return
        coded = encode(pa.array([r[self.value] for r in self.rows]))
        rank, share = median_rank(self.k, "mean")
        upper, below = window_ranks(coded.codes, np.array([0, len(self.rows)]), self.k, [rank], lower=share != 1.0)
        up = coded.back(upper[0, self.k - 1 :])
        found = up.to_pylist() if share == 1.0 else ((coded.as_double(upper[0, self.k - 1 :]) + coded.as_double(below[0, self.k - 1 :])) / 2).tolist()
        for place, med in enumerate(found):
            yield (*self.rows[place], self.done + place, med)
        self.done += len(found)
        self.rows = self.rows[len(found) :]


def register(spark: SparkSession) -> None:
    """Make ``sliding_median`` (table function) and ``median_cells`` (array function) known to SQL."""
    spark.udtf.register("sliding_median", F.udtf(SlidingMedianFunction))
    spark.udf.register("median_cells", _cells(T.DoubleType()))


def _cells(kind: T.DataType):
    @F.arrow_udf(T.ArrayType(kind))
    def median_cells(column: pa.Array, k: pa.Array, r: pa.Array) -> pa.Array:
        window, rank = k[0].as_py(), r[0].as_py()
        flat = column.flatten()
        lengths = np.array([0 if x is None else x for x in pc.list_value_length(column).to_pylist()], dtype=np.int64)
        starts = np.concatenate([[0], np.cumsum(lengths)])
        coded = encode(flat)
        upper, _ = window_ranks(coded.codes, starts, window, [rank])
        inner = np.arange(len(flat)) - np.repeat(starts[:-1], lengths)
        full = inner >= window - 1
        counts = np.maximum(lengths - window + 1, 0)
        offsets = pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32))
        return pa.ListArray.from_arrays(offsets, coded.back(upper[0, full]))

    return median_cells


def median_cells(column: str, kind: T.DataType, k: int, r: int | None = None) -> Column:
    """The filter inside each array: arrays of ``kind``, all of a batch in lockstep; null arrays give empty ones."""
    return _cells(kind)(F.col(column), F.lit(k), F.lit(k // 2 if r is None else r))


def median_groups(df: DataFrame, value: str, k: int, order: list[str], keys: list[str]) -> DataFrame:
    """The filter by ``applyInArrow``, for series that fit a task."""
    from .functions.kernels import filter_series
    from .plans.routes import result_schema
    from .plans.spec import SlidingSpec

    rank, share = median_rank(k, "mean")
    spec = SlidingSpec(value, k, tuple(order), tuple(keys), (rank,), ("med",), (share,))

    def run(table: pa.Table) -> pa.Table:
        return filter_series(table.sort_by([(c, "ascending") for c in order]), np.array([0, table.num_rows]), spec)

    return df.select(*keys, *order, value).groupBy(*keys).applyInArrow(run, result_schema(df, spec))


def block_digest(df: DataFrame, value: str, keys: list[str]) -> DataFrame:
    """(series, blk, low, high, rows) of rows that have ``blk``."""
    return df.groupBy(*keys, "blk").agg(F.min(value).alias("low"), F.max(value).alias("high"), F.count("*").alias("rows"))
