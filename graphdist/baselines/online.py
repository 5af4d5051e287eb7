"""Search without an index."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from graphdist.operators import bfs, search


def bidirectional(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    """(pair_id, s, t, dist) by bidirectional search on the whole graph, unbounded."""
    free = pairs.select("pair_id", "s", "t", F.lit(None).cast("int").alias("ub"))
    return search.bounded(edges, free).select("pair_id", "s", "t", F.col("core_d").alias("dist"))


def one_sided(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    """(pair_id, s, t, dist) by plain breadth-first search from every s."""
    reach = bfs.levels(edges, pairs.select(F.col("s").alias("id")).distinct())
    return pairs.join(reach.select(F.col("lm").alias("s"), F.col("v").alias("t"), F.col("d").alias("dist")), ["s", "t"], "left").select("pair_id", "s", "t", "dist")
