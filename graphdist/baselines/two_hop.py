"""Pruned labelling: one landmark after the other, in an order that decides the size.

``pruned_two_hop`` drops a reached vertex (and does not expand it) when the labels so far already give a distance that is not
longer by a shared hub. ``pruned_cover`` uses the landmark matrix instead: an earlier entry of the vertex plus the
matrix distance from the current landmark to it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from graphdist.operators import graph
from graphdist.runtime import cut

_LABELS = "v long, lm long, d int"


def _levels(edges: DataFrame, root: int, labels: DataFrame, test) -> DataFrame:
    """New entries (v, lm, d) of one root; ``test(reached)`` gives the rows that stay."""
    spark = edges.sparkSession
    start = spark.createDataFrame([(root, 0)], "v long, d int")
    frontier = cut(test(start))
    kept, depth = frontier, 0
    seen = frontier.select("v")
    while not frontier.isEmpty():
        depth += 1
        reached = frontier.join(edges, frontier["v"] == edges["src"]).select(F.col("dst").alias("v")).distinct().join(seen, "v", "left_anti")
        frontier = cut(test(reached.withColumn("d", F.lit(depth))))
        seen = cut(seen.union(frontier.select("v")))
        kept = kept.union(frontier)
    return cut(kept.select("v", F.lit(root).cast("long").alias("lm"), "d"))


def pruned_two_hop(edges: DataFrame, ordered: DataFrame, bound=None) -> DataFrame:
    """labels(v, lm, d) of all vertices, landmarks included (each has itself at 0). ``bound(root, reached)`` may prune further."""
    spark = edges.sparkSession
    labels = spark.createDataFrame([], _LABELS)
    for row in ordered.orderBy("rank").collect():  # k rows
        root = row["id"]
        mine = F.broadcast(cut(labels.filter(F.col("v") == root).select("lm", F.col("d").alias("dr"))))  # at most k entries

        def stays(reached: DataFrame, mine=mine, root=root, labels=labels) -> DataFrame:
            known = labels.join(mine, "lm").groupBy("v").agg(F.min(F.col("d") + F.col("dr")).alias("known"))
            out = reached.join(known, "v", "left").filter("known is null or known > d").select("v", "d")
            return bound(root, out) if bound else out

        labels = cut(labels.union(_levels(edges, root, labels, stays)))
    return labels


def pruned_cover(edges: DataFrame, ordered: DataFrame, matrix: DataFrame) -> DataFrame:
    """labels(v, lm, d) of the vertices that are no landmark. Landmarks are expanded untested, so lengths stay right."""
    spark = edges.sparkSession
    r = F.broadcast(ordered.select(F.col("id").alias("v"), F.lit(True).alias("is_landmark")))
    labels = spark.createDataFrame([], _LABELS)
    for row in ordered.orderBy("rank").collect():  # k rows
        root = row["id"]
        near = F.broadcast(matrix.filter(F.col("lm_a") == root).select(F.col("lm_b").alias("lm"), F.col("d").alias("dr")))

        def stays(reached: DataFrame, near=near, labels=labels) -> DataFrame:
            known = labels.join(near, "lm").groupBy("v").agg(F.min(F.col("d") + F.col("dr")).alias("known"))
            tested = reached.join(known, "v", "left").join(r, "v", "left")
            return tested.filter("is_landmark or known is null or known > d").select("v", "d")

        new = _levels(edges, root, labels, stays).join(r, "v", "left_anti")
        labels = cut(labels.union(new))
    return labels


def complete(edges: DataFrame) -> DataFrame:
    """Pruned labelling over all vertices in order of degree: exact by shared hubs alone. One search a vertex: small graphs."""
    from graphdist.operators.landmarks import top_degree

    return pruned_two_hop(edges, top_degree(edges, graph.vertices(edges).count()))


def pruned_from_full(full: DataFrame, ordered: DataFrame) -> DataFrame:
    """The pruned labels by their closed form: keep (r_i, v) unless an earlier r_j has d(r_j, r_i) + d(r_j, v) <= d(r_i, v).

    A vertex's distances stand in one row, so its entries are compared where they are: one aggregation, whatever k is.
    """
    order = [r["id"] for r in ordered.orderBy("rank").collect()]  # k rows
    if not order:
        return full.select("v", "lm", "d").limit(0)
    between = full.join(F.broadcast(ordered.select(F.col("id").alias("v"))), "v", "left_semi").select("lm", "v", "d").collect()  # k * k rows
    between = {(r["lm"], r["v"]): r["d"] for r in between}
    wide = full.groupBy("v").agg(*[F.min(F.when(F.col("lm") == r, F.col("d"))).alias(f"d{i}") for i, r in enumerate(order)])
    entries = []
    for i, r in enumerate(order):
        ways = [F.col(f"d{j}") + F.lit(between[q, r]) for j, q in enumerate(order[:i]) if (q, r) in between]
        known = F.least(*ways, F.lit(None).cast("int"), F.lit(None).cast("int"))  # NULL counts for nothing
        entries.append(F.struct(F.lit(r).cast("long").alias("lm"), F.when(known.isNull() | (known > F.col(f"d{i}")), F.col(f"d{i}")).alias("d")))
    return wide.select("v", F.explode(F.array(*entries)).alias("e")).select("v", "e.lm", "e.d").filter("d is not null")


def pruned_after_masks(full: DataFrame, ordered: DataFrame, masks: DataFrame) -> DataFrame:
    """The closed form of ``pruned_two_hop`` with ``mask_hybrid.pruning(masks)``: of the pruned labels those that the masks don't answer.

    A mask bound is exact if a root or a chosen neighbour lies on a shortest path. Whatever lies beyond a pruned vertex then has the same
    hub on a shortest path and is pruned too, so no search is needed to know what one would reach.
    """
    at = ordered.select(F.col("id").alias("v"), F.col("id").alias("r"))
    near = masks.join(F.broadcast(at), "v").select("lm", "r", F.col("d").alias("dr"), F.col("m1").alias("r1"), F.col("m0").alias("r0"))  # roots * k rows
    hit = lambda x, y: F.col(x).bitwiseAND(F.col(y)) != 0
    less = F.when(hit("r1", "m1"), 2).when(hit("r1", "m0") | hit("r0", "m1"), 1).otherwise(0)
    ub = masks.join(F.broadcast(near), "lm").groupBy("v", F.col("r").alias("lm")).agg(F.min(F.col("d") + F.col("dr") - less).alias("ub"))
    kept = pruned_from_full(full, ordered).join(ub, ["v", "lm"], "left")
    return kept.filter("ub is null or ub > d or v = lm").select("v", "lm", "d")
