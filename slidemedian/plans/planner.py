"""Choice of the route."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .routes import needed, run_route
from .spec import SlidingSpec
from .tiles import blocks_per_tile

#: Longest series that a task takes whole; largest window that a tile of blocks takes.
LONGEST_SERIES, WIDEST_BLOCK = 1 << 20, 1 << 22


def profile(df: DataFrame, spec: SlidingSpec) -> dict[str, int]:
    """Rows, series and the longest series, from one small aggregation."""
    counts = needed(df, spec).groupBy(*spec.partition_by).agg(F.count("*").alias("n"))
    row = counts.agg(F.sum("n").alias("rows"), F.count("*").alias("series"), F.max("n").alias("longest")).first()
    return {key: row[key] or 0 for key in ("rows", "series", "longest")}


def choose(spec: SlidingSpec, facts: dict[str, int]) -> str:
    if facts["longest"] <= LONGEST_SERIES and (spec.partition_by or facts["rows"] <= 4096):
        return "short_series"
    return "blocks" if spec.window <= WIDEST_BLOCK or spec.edges != "valid" else "wide"


def plan(df: DataFrame, spec: SlidingSpec, hints: dict[str, int] | None = None) -> DataFrame:
    """The filter's DataFrame; ``hints`` stand in for the profile."""
    spec.validate(df.schema)
    if spec.route != "auto":
        return run_route(df, spec, spec.route, (hints or {}).get("rows"))
    facts = hints or profile(df, spec)
    return run_route(df, spec, choose(spec, facts), facts.get("rows"))


def explain_plan(df: DataFrame, spec: SlidingSpec) -> str:
    facts = profile(df, spec)
    route = spec.route if spec.route != "auto" else choose(spec, facts)
    per_tile = blocks_per_tile(spec.window)
    return f"route {route}; {facts['rows']} rows in {facts['series']} series, longest {facts['longest']}; window {spec.window}, {per_tile} blocks a tile, kernel {spec.kernel}, sorter {spec.sorter}"
