"""0-based positions of rows in their series, without sorting a series in one task.

Rows are dealt by ranges of all keys together, series and order, so equal
leading keys may lie in any number of partitions and no partition depends on
how the values of one column are spread. Inside a partition rows are sorted and
numbered as they stream by; the numbered rows are written once, and counts of
the partitions give each its base.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from itertools import accumulate

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .store import settle

#: Rows that a partition aims at where the number of rows is known.
PARTITION_ROWS = 4_000_000
#: ``monotonically_increasing_id`` counts the rows of a partition in these bits.
_COUNTER = (1 << 33) - 1


def range_partitions(df: DataFrame, rows: int | None = None) -> int:
    """As many partitions as the session shuffles to, more if ``rows`` would overfill them."""
    return max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-(rows or 0) // PARTITION_ROWS))


def _numbered(df: DataFrame, order: list[str], partitions: int) -> DataFrame:
    """``df``, written once, with each row's partition of the order and its place in there."""
    ranged = df.repartitionByRange(partitions, *order).sortWithinPartitions(*order)
    return settle(ranged.withColumns({"__part": F.spark_partition_id(), "__inside": F.monotonically_increasing_id().bitwiseAND(F.lit(_COUNTER))}), "positions")


def positions_in_range(df: DataFrame, order_by: Sequence[str], low: int, high: int, partitions: int | None = None) -> DataFrame:
    """Rows of one series at positions low ... high - 1, with ``pos``; of the numbered rows only the partitions that reach there are read."""
    numbered = _numbered(df, list(order_by), partitions or range_partitions(df))
    counts = sorted(numbered.groupBy("__part").count().collect())  # one row for each partition
    ends = list(accumulate(n for _, n in counts))
    reached = [(part, end - n) for (part, n), end in zip(counts, ends, strict=True) if end - n < high and end > low]
    rows = numbered.where(F.col("__part").between(reached[0][0], reached[-1][0])) if reached else numbered.limit(0)
    bases = F.create_map(*[F.lit(x) for pair in reached for x in pair]) if reached else F.create_map(F.lit(0), F.lit(0))
    placed = rows.withColumn("pos", (F.col("__inside") + bases[F.col("__part")]).cast("long"))
    return placed.where((F.col("pos") >= low) & (F.col("pos") < high)).select(*[F.col(f"`{c}`") for c in df.columns], "pos")


def global_positions(df: DataFrame, order_by: Sequence[str], partition_by: Sequence[str] = (), partitions: int | None = None, rows: int | None = None) -> DataFrame:
    """``df`` with ``pos``; ``order_by`` must be a total order in each series."""
    keys, order = list(partition_by), list(dict.fromkeys([*partition_by, *order_by]))
    numbered = _numbered(df, order, partitions or range_partitions(df, rows))
    # One row for each series of a partition; a series goes on in the next partitions.
    counts = numbered.groupBy("__part", *keys).agg(F.count("*").alias("__rows"), F.min("__inside").alias("__first"))
    before = Window.partitionBy(*keys).orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    bases = counts.select("__part", *keys, (F.coalesce(F.sum("__rows").over(before), F.lit(0)) - F.col("__first")).alias("__base"))
    named = {k: f"__same{i}" for i, k in enumerate(["__part", *keys])}
    bases = bases.withColumnsRenamed(named)
    if not keys:
        bases = F.broadcast(bases)  # one row for each partition
    same = [F.col(f"`{k}`").eqNullSafe(F.col(n)) for k, n in named.items()]
    joined = numbered.join(bases, reduce(lambda a, b: a & b, same))
    return joined.select(*[F.col(f"`{c}`") for c in df.columns], (F.col("__inside") + F.col("__base")).alias("pos"))


def duplicate_orders(df: DataFrame, order_by: Sequence[str], partition_by: Sequence[str] = ()) -> DataFrame:
    """Order keys that more than one row of a series has: empty if the order is total."""
    return df.groupBy(*partition_by, *order_by).count().where("count > 1")


def assert_total_order(df: DataFrame, order_by: Sequence[str], partition_by: Sequence[str] = ()) -> None:
    first = duplicate_orders(df, order_by, partition_by).take(1)
    if first:
        raise ValueError(f"{list(order_by)} is no total order: {first[0].asDict()}")
