"""The table of all landmark distances, and the all-pairs index for small graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from graphdist.operators import bfs, graph


def full_table(edges: DataFrame, landmarks: DataFrame) -> DataFrame:
    """(v, lm, d) for all vertices that are no landmark."""
    full = bfs.levels(edges, landmarks)
    return full.join(F.broadcast(landmarks.select(F.col("id").alias("v"))), "v", "left_anti").select("v", "lm", "d")


def all_pairs(edges: DataFrame) -> DataFrame:
    """(s, t, dist) of every connected pair: n breadth-first searches at once, for small graphs."""
    return bfs.levels(edges, graph.vertices(edges)).select(F.col("lm").alias("s"), F.col("v").alias("t"), F.col("d").alias("dist"))
