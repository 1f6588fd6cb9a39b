"""Inputs of the experiments, as relational transforms of positions.

All arithmetic is on 64-bit integers without overflow, so that other engines
compute the same numbers.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.positions import global_positions

GENERATORS = ("ramp_up", "ramp_down", "noisy_up", "noisy_down", "wide_random", "narrow_random", "steps")
#: Range of the small noise, rows of a step, noise on a step, levels of steps.
NOISE, STEP_ROWS, STEP_NOISE, STEP_LEVELS = 10_000, 1000, 100, 1_000_000


def mix_text(pos: str, seed: int, divide: str = "div") -> str:
    """SQL for a 31-bit pseudo-random number; ``divide`` is the engine's integer division."""
    first = f"((({pos}) * 1103515245 + 12345 + {seed} * 977) % 2147483648)"
    return f"(({first} * 48271 + ({first} {divide} 65536) * 69621) % 2147483647)"


def value_text(name: str, n: str, seed: int = 1, width: int = 32, divide: str = "div") -> str:
    """SQL for the generator's value at column ``pos`` of a vector of ``n`` rows."""
    u = mix_text("pos", seed, divide)
    if name == "ramp_up":
        return "pos"
    if name == "ramp_down":
        return f"{n} - pos"
    if name == "noisy_up":
        return f"pos + {u} % {NOISE}"
    if name == "noisy_down":
        return f"{n} - pos + {u} % {NOISE}"
    if name == "wide_random":
        return u if width == 32 else f"{u} * 2147483648 + {mix_text('pos', seed + 1, divide)}"
    if name == "narrow_random":
        return f"{u} % {NOISE}"
    if name == "steps":
        level = mix_text(f"pos {divide} {STEP_ROWS}", seed, divide)
        return f"{level} % {STEP_LEVELS} + {u} % {STEP_NOISE}"
    raise ValueError(f"no generator {name!r}; there are {GENERATORS}")


def generate(df: DataFrame, order_by: Sequence[str], name: str, seed: int = 1, width: int = 32) -> DataFrame:
    """(pos, x): the generator over the positions of a table."""
    rows = df.count()
    return global_positions(df.select(*order_by), order_by).select("pos", F.expr(value_text(name, str(rows), seed, width)).cast("long").alias("x"))


def vector(spark: SparkSession, n: int, name: str, seed: int = 1, width: int = 32) -> DataFrame:
    """(pos, x) of any length, without a table."""
    return spark.range(n).withColumnRenamed("id", "pos").select("pos", F.expr(value_text(name, str(n), seed, width)).cast("long").alias("x"))


def corrupted_signal(spark: SparkSession, n: int = 2000, seed: int = 1) -> DataFrame:
    """(pos, clean, dirty, corrupted): a smooth signal, small noise, and a quarter of the points replaced."""
    u, v = F.expr(mix_text("pos", seed)), F.expr(mix_text("pos", seed + 1))
    clean: Column = triangle(F.col("pos"))
    rows = spark.range(n).withColumnRenamed("id", "pos").select("pos", clean.alias("clean"), (u % 4 == 0).alias("corrupted"), ((v % 21 - 10) / 10.0).alias("noise"), (v % 200).cast("double").alias("wrong"))
    return rows.select("pos", "clean", F.when(F.col("corrupted"), F.col("wrong")).otherwise(F.col("clean") + F.col("noise")).alias("dirty"), "corrupted")


def triangle(pos: Column) -> Column:
    """A wave of period 500 between 50 and 150."""
    return F.lit(50.0) + F.abs(pos % 500 - 250) * 0.4
