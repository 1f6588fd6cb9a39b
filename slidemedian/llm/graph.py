"""Connected components of an undirected graph, as DataFrame rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import forget, look_up, settle


def _with_least(ways: DataFrame, total: int) -> DataFrame:
    """(u, v, m): ``m`` is the least vertex among u and the v of its ways. A vertex with very many ways is looked up from a broadcast."""
    least = ways.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"), F.count("*").alias("n"))
    return look_up(ways, least, ["u"], "n", "hub", total).select("u", "v", F.col("hub.m").alias("m"))


def _edges(a: str, b: str):
    return F.struct(F.col(a).alias("a"), F.col(b).alias("b"))


def _far(edges: DataFrame, total: int) -> DataFrame:
    """Each vertex ties its larger neighbours to the least vertex of its neighbourhood."""
    both = edges.select(F.explode(F.array(_edges("a", "b"), _edges("b", "a"))).alias("e")).select(F.col("e.a").alias("u"), F.col("e.b").alias("v"))
    return _with_least(both, 2 * total).where("v > u").select(F.col("m").alias("a"), F.col("v").alias("b")).where("a != b").distinct()


def _near(edges: DataFrame, total: int) -> DataFrame:
    """Each vertex ties itself and its smaller neighbours to the least of them."""
    down = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    tied = _with_least(down, total).select(F.explode(F.array(_edges("m", "v"), _edges("m", "u"))).alias("e"))
    return tied.select("e.a", "e.b").where("a != b").distinct()


def components(edges: DataFrame) -> DataFrame:
    """(v, component) of every vertex of ``edges`` (a, b); a component is named by its least vertex.

    Alternates two star contractions until the edges are stars; each round is
    written to the shared folder. The minima are combined before the shuffle,
    and a vertex with very many edges is looked up from a broadcast of bounded
    size, so no task has to take all edges of one vertex.
    """
    spark = edges.sparkSession
    now = settle(edges.where("a != b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    total, mark = now.count(), None
    while total:
        after = settle(_near(_far(now, total), total), "edges")
        forget(spark, now)
        state = after.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        now, total = after, state[0]
        if state == mark:
            break
        mark = state
    roots = now.select(F.col("b").alias("v"), F.col("a").alias("component"))
    return roots.unionByName(now.select(F.col("a").alias("v"), F.col("a").alias("component")).distinct())
