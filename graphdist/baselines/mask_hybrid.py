"""Mask hybrid: a few landmark trees, each with two 64-bit masks a vertex over neighbours of the root, then a bounded search.

For root r with chosen neighbours u_0..u_63: bit j of ``m1`` of v is set if d(u_j, v) = d(r, v) - 1, of ``m0`` if equal. A pair's bound
through r is d(r, s) + d(r, t), less 2 if the m1 masks share a bit, else less 1 if an m1 and an m0 mask do.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window, functions as F

from graphdist.operators import bfs, graph, landmarks as lmk, search
from graphdist.runtime import cut, discard, materialize


def choose_neighbours(edges: DataFrame, roots: DataFrame, width: int = 64, dealt: graph.Dealt | None = None) -> DataFrame:
    """(lm, u, bit): up to ``width`` neighbours a root, by degree, no roots and none chosen by an earlier root. ``dealt``: the edges dealt with the roots as hubs."""
    r = F.broadcast(roots.select(F.col("id").alias("dst")))
    near = (dealt.hub_edges if dealt else edges).join(F.broadcast(roots.select(F.col("id").alias("src"), "rank")), "src").join(r, "dst", "left_anti")
    deg = graph.degrees(dealt.rest if dealt else edges).select(F.col("id").alias("dst"), "deg")
    ranked = cut(near.join(deg, "dst").select(F.col("src").alias("lm"), F.col("dst").alias("u"), "rank", "deg"))
    spark = edges.sparkSession
    taken = spark.createDataFrame([], "lm long, u long, bit int")
    for row in roots.orderBy("rank").collect():  # k rows, width neighbours each
        free = ranked.filter(F.col("lm") == row["id"]).join(taken.select("u"), "u", "left_anti").orderBy(F.desc("deg"), "u").limit(width)
        w = Window.orderBy(F.desc("deg"), "u")
        taken = cut(taken.union(free.select("lm", "u", (F.row_number().over(w) - 1).cast("int").alias("bit"))))
    return taken


def _bit(n):
    return F.when(n == 63, F.expr("-9223372036854775807L - 1L")).otherwise(F.expr("shiftleft(1L, least(bit, 62))"))


def labels(edges: DataFrame, roots: DataFrame, width: int = 64, dealt: graph.Dealt | None = None) -> DataFrame:
    """(lm, v, d, m1, m0) for every vertex that a root reaches: two mask aggregations a level. ``dealt``: the edges already dealt with the roots as hubs.

    A row without a bit tells its neighbours nothing and is not sent.
    """
    ids = [r["id"] for r in roots.select("id").distinct().collect()]  # k rows
    with graph.dealing(edges, ids, dealt) as mine:
        chosen = choose_neighbours(edges, roots, width, mine)
        own = F.broadcast(chosen.select("lm", F.col("u").alias("v"), _bit(F.col("bit")).alias("own")))  # k * width rows
        full = bfs.levels_by_masks(edges, roots, mine)
        zero = F.lit(0).cast("long")
        layer = cut(full.filter("d = 0").select("lm", "v", "d", zero.alias("m1"), zero.alias("m0")))
        out, depth = [layer], 0
        while True:
            depth += 1
            here = full.filter(F.col("d") == depth).select("lm", "v")
            if here.isEmpty():
                break
            telling = layer.filter("m1 != 0 or m0 != 0").select("lm", "v", "m1", "m0")
            from_up = graph.to_neighbours(telling, mine).groupBy("lm", F.col("dst").alias("v")).agg(F.bit_or("m1").alias("p1"), F.bit_or("m0").alias("p0"))
            first = here.join(from_up, ["lm", "v"], "left").join(own, ["lm", "v"], "left")
            m1 = F.coalesce("p1", zero)
            if depth == 1:
                m1 = m1.bitwiseOR(F.coalesce("own", zero))
            first = materialize(first.select("lm", "v", m1.alias("m1"), F.coalesce("p0", zero).alias("p0")), "masks")
            beside = first.filter("m1 != 0").select("lm", "v", F.col("m1").alias("s1"))
            across = graph.to_neighbours(beside, mine).groupBy("lm", F.col("dst").alias("v")).agg(F.bit_or("s1").alias("s1"))
            layer = materialize(
                first.join(across, ["lm", "v"], "left").select(
                    "lm", "v", F.lit(depth).alias("d"), "m1", F.coalesce("s1", zero).bitwiseOR(F.col("p0")).bitwiseAND(F.bitwise_not("m1")).alias("m0")
                ),
                "masks",
            )
            discard(first)
            out.append(layer)
    return reduce(DataFrame.union, out)


def upper_bound(pairs: DataFrame, masks: DataFrame) -> DataFrame:
    a = masks.select("lm", F.col("v").alias("s"), F.col("d").alias("da"), F.col("m1").alias("a1"), F.col("m0").alias("a0"))
    b = masks.select("lm", F.col("v").alias("t"), F.col("d").alias("db"), F.col("m1").alias("b1"), F.col("m0").alias("b0"))
    hit = lambda x, y: F.col(x).bitwiseAND(F.col(y)) != 0
    less = F.when(hit("a1", "b1"), 2).when(hit("a1", "b0") | hit("a0", "b1"), 1).otherwise(0)
    met = pairs.join(a, "s").join(b, ["t", "lm"]).groupBy("pair_id").agg(F.min(F.col("da") + F.col("db") - less).alias("ub"))
    return pairs.join(met, "pair_id", "left").select("pair_id", "s", "t", F.when(F.col("s") == F.col("t"), 0).otherwise(F.col("ub")).cast("int").alias("ub"))


def pruning(masks: DataFrame):
    """A further test for ``two_hop.pruned_two_hop``: drop reached vertices that the masks answer already."""

    def bound(root: int, reached: DataFrame) -> DataFrame:
        reached = cut(reached)
        ask = reached.select(F.col("v").alias("pair_id"), F.lit(root).cast("long").alias("s"), F.col("v").alias("t"))
        ub = upper_bound(ask, masks).select(F.col("pair_id").alias("v"), "ub")
        return reached.join(ub, "v", "left").filter(f"ub is null or ub > d or v = {int(root)}").select("v", "d")

    return bound


def distance(edges: DataFrame, roots: DataFrame, masks: DataFrame, pairs: DataFrame) -> DataFrame:
    """(pair_id, s, t, ub, dist): the refined bound made exact by the search without the roots."""
    bounds = cut(upper_bound(pairs, masks))
    r = F.broadcast(roots.select("id"))
    rest = bounds.join(r, bounds["s"] == r["id"], "left_anti").join(r, bounds["t"] == r["id"], "left_anti")
    found = search.bounded(graph.core(edges, roots), rest)
    at_root = bounds.join(rest.select("pair_id"), "pair_id", "left_anti").select("pair_id", "s", "t", "ub", F.col("ub").alias("dist"))
    return found.select("pair_id", "s", "t", "ub", F.least("ub", "core_d").alias("dist")).union(at_root)


def default_roots(edges: DataFrame, k: int = 20) -> DataFrame:
    return cut(lmk.top_degree(edges, k))
