"""Helpers that the training-data operators share.

Cut points between jobs are tables in a folder that driver and executors share
(see ``plans.store``).
"""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Callable, Hashable
from functools import reduce
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.store import forget, fresh_path, settle

__all__ = ["bucket_of", "forget", "fresh_path", "load", "look_up", "settle", "stateless_worker", "worker_state"]


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_STATE: dict[str, tuple[Hashable, Any]] = {}


def worker_state(owner: str, key: Hashable, make: Callable[[], Any]) -> Any:
    """What an operator keeps in a worker process between batches: models, memos.

    A worker outlives its task and serves other stages, so it keeps the state
    of one operator only: another owner's, or another key's, replaces it.
    """
    held = _STATE.get(owner)
    if held is None or held[0] != key:
        held = None
        _STATE.clear()
        give_back()
        held = _STATE[owner] = key, make()
    return held[1]


def stateless_worker(owner: str) -> None:
    """Called by operators that keep nothing, so that what others kept goes."""
    worker_state(owner, None, lambda: None)


def give_back() -> None:
    """Return to the system what this process has freed."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # not every C library has it
        ctypes.CDLL(None).malloc_trim(0)


def bucket_of(column: str, modulus: int):
    """crc32 of the column as text, modulo ``modulus``: the fold rule of the queries."""
    return F.crc32(F.col(column).cast("string")) % F.lit(modulus)


#: Bound on the entries of a lookup table that are broadcast.
FREQUENT = 10_000


def look_up(rows: DataFrame, entries: DataFrame, keys: list[str], weight: str, name: str, total: int | None = None) -> DataFrame:
    """Left join of ``rows`` with their entry, as the struct column ``name``, whatever the skew of the keys.

    ``entries`` has one row for each value of ``keys`` and tells in ``weight``
    how many rows have it; ``total`` is their sum where it is known. Keys with
    more than 1/``FREQUENT`` of all rows are fewer than ``FREQUENT`` at any
    size, so they are broadcast; rows served by them join nothing else, and
    spread over the partitions of the second join.
    """
    if total is None:
        total = entries.agg(F.sum(weight)).first()[0] or 0
    often = F.col(weight) * FREQUENT > F.lit(total)
    payload = F.struct(*[c for c in entries.columns if c not in keys])
    frequent = entries.where(often).select(*keys, payload.alias("__hot"))
    own = F.xxhash64(*keys)
    # The second key is a function of the first ones, not a constant, or the planner would drop it;
    # rows that are served, or have no key, get one of their own and spread.
    rare = entries.where(~often).select(*[F.col(k).alias(f"__{k}") for k in keys], own.alias("__spread"), payload.alias("__cold"))
    served = rows.join(F.broadcast(frequent), keys, "left")
    asks = reduce(lambda a, b: a & b, [F.col("__hot").isNull(), *[F.col(k).isNotNull() for k in keys]])
    named = [F.when(asks, F.col(k)).alias(f"__{k}") for k in keys]
    salted = served.select("*", *named, F.when(asks, own).otherwise(F.xxhash64(F.monotonically_increasing_id())).alias("__spread"))
    joined = salted.join(rare, [*[f"__{k}" for k in keys], "__spread"], "left")
    return joined.withColumn(name, F.coalesce("__hot", "__cold")).drop("__hot", "__cold", "__spread", *[f"__{k}" for k in keys])
