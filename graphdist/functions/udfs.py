"""Arrow-based functions: a vectorised bound, distances inside small components, a table function for neighbourhoods."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.types import IntegerType

from graphdist.operators import bfs, components, query


MAX_EDGES = 1_000_000  # edge rows a table function sends to the tasks


def bound_by_pandas(pairs: DataFrame, labels: DataFrame, matrix: DataFrame, landmarks: DataFrame) -> DataFrame:
    """The upper bound by a pandas UDF over packed labels; the matrix (k * k numbers) is broadcast."""
    spark = pairs.sparkSession
    ids = {r["id"]: r["rank"] for r in landmarks.collect()}  # k rows
    m = np.full((len(ids), len(ids)), np.inf)
    for r in matrix.collect():  # at most k * k rows
        m[ids[r["lm_a"]], ids[r["lm_b"]]] = r["d"]
    shared = spark.sparkContext.broadcast((ids, m))

    def least(ls, lt):
        ids, m = shared.value
        if ls is None or lt is None or not len(ls) or not len(lt):
            return None
        a, b = [ids[x["lm"]] for x in ls], [ids[x["lm"]] for x in lt]
        s = np.array([x["d"] for x in ls])[:, None] + m[np.ix_(a, b)] + np.array([x["d"] for x in lt])[None, :]
        best = s.min()
        return None if np.isinf(best) else int(best)

    @F.pandas_udf(IntegerType())
    def bound(ls: pd.Series, lt: pd.Series) -> pd.Series:
        return pd.Series([least(a, b) for a, b in zip(ls, lt)], dtype="Int32")

    both = query._sides(pairs, query.with_virtual(labels, landmarks))
    return both.select("pair_id", "s", "t", F.when(F.col("s") == F.col("t"), 0).otherwise(bound("ls", "lt")).alias("ub"))


def component_distances(edges: DataFrame) -> DataFrame:
    """(s, t, dist) with s < t inside every component, one component a call. For graphs of small components."""
    comp = components.connected_components(edges, "src", "dst").withColumnRenamed("id", "src")

    def solve(f: pd.DataFrame) -> pd.DataFrame:
        near: dict = {}
        for a, b in zip(f["src"], f["dst"]):
            near.setdefault(a, []).append(b)
        rows = []
        for s in near:
            dist, queue = {s: 0}, [s]
            for v in queue:
                for w in near[v]:
                    if w not in dist:
                        dist[w] = dist[v] + 1
                        queue.append(w)
            rows += [(s, t, d) for t, d in dist.items() if s < t]
        return pd.DataFrame(rows, columns=["s", "t", "dist"]).astype({"dist": "int32"})

    return edges.join(comp, "src").groupBy("component").applyInPandas(solve, "s long, t long, dist int")


def neighbours_within(edges: DataFrame, sources: DataFrame, hops: int) -> DataFrame:
    """(v, w, hops): vertices within ``hops`` of the sources, as a join plan (see ``register_udtf`` for SQL)."""
    return bfs.levels(edges, sources, hops).filter("d > 0").select(F.col("lm").alias("v"), F.col("v").alias("w"), F.col("d").alias("hops"))


def within_reach(edges: DataFrame, sources: DataFrame, hops: int) -> DataFrame:
    """The edges that a search of ``hops`` levels from the sources reads: those of the vertices at most ``hops`` - 1 away."""
    read = bfs.levels(edges, sources, hops - 1).select(F.col("v").alias("src")).distinct()
    return edges.join(read, "src", "left_semi")


def register_udtf(spark, edges: DataFrame, max_edges: int = MAX_EDGES) -> None:
    """SQL: ``SELECT * FROM neighbours_within(v, h)`` on a graph of at most ``max_edges`` edge rows (checked), sent to the tasks."""
    from pyspark.sql.functions import udtf

    if edges.limit(max_edges + 1).count() > max_edges:
        raise ValueError(f"graph has more than {max_edges} edge rows; use neighbours_within(edges, sources, hops)")
    near: dict = {}
    for r in edges.collect():
        near.setdefault(r["src"], []).append(r["dst"])
    shared = spark.sparkContext.broadcast(near)

    @udtf(returnType="w long, hops int")
    class NeighboursWithin:
        def eval(self, v: int, h: int):
            dist, queue = {v: 0}, [v]
            for x in queue:
                if dist[x] == h:
                    continue
                for w in shared.value.get(x, ()):
                    if w not in dist:
                        dist[w] = dist[x] + 1
                        queue.append(w)
            for w, d in dist.items():
                if d:
                    yield w, d

    spark.udtf.register("neighbours_within", NeighboursWithin)


def decode_label(data: bytes, lm_bits: int = 8) -> list[tuple[int, int]]:
    """(landmark rank, distance) entries of a packed label, outside Spark."""
    step = lm_bits // 8 + 1
    return [(int.from_bytes(data[i : i + step - 1], "big"), data[i + step - 1]) for i in range(0, len(data), step)]
