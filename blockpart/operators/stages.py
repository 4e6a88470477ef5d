"""Streaming stages of a graph: edges at random or by time, and snowballs from start nodes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.functions.math import u01


def emerging(edges: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """Adds stage 1 .. k at random; a node appears with its first edge."""
    return edges.withColumn("stage", (F.floor(u01(seed, "stage", 0, F.concat_ws(":", "src", "dst")) * k) + 1).cast("int"))


def by_time(rows: DataFrame, ts: str, width: str = "day") -> DataFrame:
    """Adds stage: periods since the first, from 1."""
    unit = F.date_trunc(width, ts)
    first = rows.agg(F.min(unit).alias("first"))
    return rows.join(F.broadcast(first)).withColumn("stage", (F.datediff(unit, "first") + 1).cast("int")).drop("first")


def snowball(edges: DataFrame, seeds: DataFrame, k: int) -> DataFrame:
    """Edges by the ring in which both ends are reached (at least 1); unreached ones never come."""
    from blockpart.operators.relops import bfs_rings

    rings = bfs_rings(edges, seeds, k)
    a, b = rings.toDF("src", "ra"), rings.toDF("dst", "rb")
    return edges.join(a, "src").join(b, "dst").select("src", "dst", "w", F.greatest("ra", "rb", F.lit(1)).cast("int").alias("stage"))


def upto(edges: DataFrame, k: int) -> DataFrame:
    return edges.where(F.col("stage") <= k)


def only(edges: DataFrame, k: int) -> DataFrame:
    return edges.where(F.col("stage") == k)


def first_stage(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("i"), "stage").unionAll(edges.select("dst", "stage")).groupBy("i").agg(F.min("stage").alias("stage"))
