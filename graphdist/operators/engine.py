"""Exact distance queries: an upper bound from labels, then a bounded search on the graph without landmarks."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

from graphdist.operators import gateway, graph, landmarks as lm, local_search, query, search
from graphdist.runtime import cut, materialize


@dataclass
class Index:
    edges: DataFrame
    landmarks: DataFrame
    labels: DataFrame
    matrix: DataFrame
    core: DataFrame

    @classmethod
    def build(cls, edges: DataFrame, landmarks: DataFrame | int = 20, mode: str = "masks", dealt: graph.Dealt | None = None) -> Index:
        if isinstance(landmarks, int):
            landmarks = cut(lm.top_degree(edges, landmarks))
        labels, matrix = gateway.build(edges, landmarks, mode, dealt=dealt)
        return cls(edges, landmarks, materialize(labels, "labels"), matrix, materialize(graph.core(edges, landmarks), "core"))  # read in every round of a search

    def upper_bound(self, pairs: DataFrame, method: str = "pruned") -> DataFrame:
        return query.upper_bound(pairs, self.labels, self.matrix, self.landmarks, method)

    def distance(self, pairs: DataFrame, balance: str = "visited") -> DataFrame:
        """(pair_id, s, t, ub, core_d, dist, covered, steps). dist NULL: no path."""
        bounds = cut(self.upper_bound(pairs))
        r = F.broadcast(self.landmarks.select("id"))
        ends = bounds.join(r.select(F.col("id").alias("s"), F.lit(True).alias("a")), "s", "left").join(r.select(F.col("id").alias("t"), F.lit(True).alias("b")), "t", "left")
        ends = cut(ends.withColumn("settled", F.col("a").isNotNull() | F.col("b").isNotNull() | (F.col("s") == F.col("t"))))
        found = search.bounded(self.core, ends.filter("not settled").select("pair_id", "s", "t", "ub"), balance)
        quick = ends.filter("settled").select("pair_id", "s", "t", "ub", F.lit(None).cast("int").alias("core_d"), F.lit(0).alias("steps"))
        all_rows = found.union(quick).withColumn("dist", F.least("ub", "core_d"))
        covered = (F.col("s") != F.col("t")) & F.col("dist").isNotNull() & (F.col("ub").eqNullSafe(F.col("dist")))
        return all_rows.select("pair_id", "s", "t", "ub", "core_d", "dist", covered.alias("covered"), "steps")

    def distance_local(self, pairs: DataFrame, max_edges: int = local_search.MAX_EDGES) -> DataFrame:
        """(pair_id, s, t, ub, core_d, dist): the same answers by searches inside the workers, if the core is small enough to send."""
        bounds = cut(self.upper_bound(pairs).select("pair_id", "s", "t", "ub"))
        found = local_search.bounded(self.core, bounds, max_edges)
        if found is None:
            return self.distance(pairs).select("pair_id", "s", "t", "ub", "core_d", "dist")
        return found.select("pair_id", "s", "t", "ub", "core_d", F.least("ub", "core_d").alias("dist"))
