"""Cost and accuracy measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from graphdist.operators import graph
from graphdist.runtime import cut


def entries(labels: DataFrame) -> DataFrame:
    return labels.agg(F.count("*").alias("entries"))


def als(labels: DataFrame, edges: DataFrame, landmarks: DataFrame) -> DataFrame:
    """One row: entries, labelled vertices (all but the landmarks, empty labels included) and their quotient."""
    n = graph.vertices(edges).join(F.broadcast(landmarks.select("id")), "id", "left_anti").agg(F.count("*").alias("labelled"))
    e = entries(labels)
    return e.join(F.broadcast(n)).select("entries", "labelled", (F.col("entries") / F.col("labelled")).alias("als"))  # one row each


def index_bytes(labels: DataFrame) -> DataFrame:
    """Bytes of the labels with 8 and with 32 bits for the landmark, 8 for the distance."""
    return entries(labels).select("entries", (F.col("entries") * 2).alias("bytes_8"), (F.col("entries") * 5).alias("bytes_32"))


def mask_bytes(n_vertices: int, roots: int) -> int:
    """Bytes of the mask hybrid: a 32-bit root, an 8-bit distance and two 64-bit masks a root and vertex."""
    return n_vertices * roots * (5 + 16)


def graph_bytes(edges: DataFrame) -> DataFrame:
    return edges.agg((F.count("*") / 2 * 8).cast("long").alias("graph_bytes"))


def index_ratio(labels: DataFrame, edges: DataFrame) -> DataFrame:
    a, b = index_bytes(labels), graph_bytes(edges)
    return a.join(F.broadcast(b)).select("entries", "bytes_8", "bytes_32", "graph_bytes", (F.col("bytes_8") / F.col("graph_bytes")).alias("ratio_8"), (F.col("bytes_32") / F.col("graph_bytes")).alias("ratio_32"))


def coverage(answers: DataFrame) -> DataFrame:
    """Share of pairs whose bound is exact; ``strict``: pairs whose distance only goes through a landmark."""
    strict = F.col("covered") & F.col("core_d").isNull()
    return answers.agg(
        F.count("*").alias("pairs"), F.sum(F.col("covered").cast("long")).alias("covered"), F.avg(F.col("covered").cast("double")).alias("coverage"),
        F.sum(strict.cast("long")).alias("searched_to_bound"),
    )


def bound_gap(answers: DataFrame) -> DataFrame:
    """(gap, pairs): how far the bound is from the distance; pairs without a path don't count."""
    return answers.filter("dist is not null").groupBy((F.col("ub") - F.col("dist")).alias("gap")).agg(F.count("*").alias("pairs"))


def distance_histogram(answers: DataFrame) -> DataFrame:
    return answers.groupBy("dist").agg(F.count("*").alias("pairs"))


def edges_traversed(edges: DataFrame, landmarks: DataFrame, labels: DataFrame) -> DataFrame:
    """(lm, edges): adjacency rows that a landmark's open frontier reads: its own and those of the vertices it labels."""
    deg = graph.degrees(edges)
    open_at = labels.select("lm", F.col("v").alias("id")).union(landmarks.select(F.col("id").alias("lm"), "id"))
    return open_at.join(deg, "id").groupBy("lm").agg(F.sum("deg").alias("edges"))


def traversed(edges: DataFrame, landmarks: DataFrame) -> DataFrame:
    """(lm, open_edges, shut_edges): adjacency rows a pruned search of each landmark reads, by a search that counts them.

    A vertex is open if all its shortest paths avoid other landmarks, else shut; both are expanded while a level of the landmark has an
    open vertex.
    """
    deg = cut(graph.degrees(edges).select(F.col("id").alias("v"), "deg"))
    hub = F.broadcast(landmarks.select(F.col("id").alias("v"), F.lit(True).alias("hub")))  # k rows
    layer = cut(landmarks.select(F.col("id").alias("lm"), F.col("id").alias("v"), F.lit(False).alias("shut")))
    seen, counts = layer.select("lm", "v"), None
    while True:
        live = layer.filter("not shut").select("lm").distinct()
        layer = cut(layer.join(F.broadcast(live), "lm", "left_semi"))
        if layer.isEmpty():
            break
        read = layer.join(deg, "v").groupBy("lm", "shut").agg(F.sum("deg").alias("n"))
        counts = read if counts is None else cut(counts.union(read))
        reached = layer.join(edges, layer["v"] == edges["src"]).groupBy("lm", F.col("dst").alias("v")).agg(F.max("shut").alias("shut"))
        fresh = reached.join(seen, ["lm", "v"], "left_anti").join(hub, "v", "left")
        layer = cut(fresh.select("lm", "v", (F.col("shut") | F.col("hub").isNotNull()).alias("shut")))
        seen = cut(seen.union(layer.select("lm", "v")))
    part = lambda c, name: F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0)).cast("long").alias(name)
    return counts.groupBy("lm").agg(part(~F.col("shut"), "open_edges"), part(F.col("shut"), "shut_edges"))


def ratio(a: float, b: float) -> float | None:
    """Speed-up or saving: a / b, None where b is 0."""
    return a / b if b else None
