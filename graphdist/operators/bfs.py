"""Level-synchronous breadth-first search from many sources at once."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, functions as F

from graphdist.operators import graph
from graphdist.runtime import cut, materialize

WORD = 63


def levels(edges: DataFrame, sources: DataFrame, max_depth: int | None = None) -> DataFrame:
    """(lm, v, d): hop distance from every source (column id) to every vertex it reaches, itself included.

    One join, one aggregation and one reliable checkpoint a level; the search ends with an empty frontier.
    """
    found = cut(sources.select(F.col("id").alias("lm"), F.col("id").alias("v"), F.lit(0).alias("d")).distinct())
    layers, frontier, depth = [found], found, 0
    while max_depth is None or depth < max_depth:
        depth += 1
        reached = frontier.join(edges, frontier["v"] == edges["src"]).select("lm", F.col("dst").alias("v")).distinct()
        # a vertex next to the frontier can only be in the two layers before it
        known = reduce(DataFrame.union, [x.select("lm", "v") for x in layers[-2:]])
        frontier = cut(reached.join(known, ["lm", "v"], "left_anti").withColumn("d", F.lit(depth)))
        if frontier.isEmpty():
            break
        layers.append(frontier)
    return reduce(DataFrame.union, layers)


def levels_by_masks(edges: DataFrame, sources: DataFrame, dealt: graph.Dealt | None = None) -> DataFrame:
    """The rows of ``levels`` for sources that are a table of k rows: a vertex carries one bit a source, 63 a word.

    A level is one join and one aggregation for all sources together and is kept as (v, mask) in compressed columns; the rows (lm, v, d)
    are made when they are read, never stored. ``dealt``: the edges already dealt, with any hubs.
    """
    ids = sorted(r["id"] for r in sources.select("id").distinct().collect())
    spark, zero = edges.sparkSession, F.lit(0).cast("long")
    parts = [spark.createDataFrame([], "lm long, v long, d int")]
    with graph.dealing(edges, ids, dealt) as mine:
        for lo in range(0, len(ids), WORD):
            members = list(enumerate(ids[lo : lo + WORD]))
            bits = F.array(*[F.when(F.col("mask").bitwiseAND(F.lit(1 << b)) != 0, F.lit(v).cast("long")) for b, v in members])
            layers = [spark.createDataFrame([(v, 1 << b) for b, v in members], "v long, mask long")]
            while True:
                sent = graph.to_neighbours(layers[-1], mine).select(F.col("dst").alias("v"), F.col("mask").alias("got"), zero.alias("known"))
                # a vertex next to the frontier can only be in the two layers before it
                before = [x.select("v", zero.alias("got"), F.col("mask").alias("known")) for x in layers[-2:]]
                met = reduce(DataFrame.union, [sent, *before]).groupBy("v").agg(F.bit_or("got").alias("got"), F.bit_or("known").alias("known"))
                layer = materialize(met.select("v", F.col("got").bitwiseAND(F.bitwise_not("known")).alias("mask")).filter("mask != 0"), "level")
                if layer.isEmpty():
                    break
                layers.append(layer)
            parts += [x.select(F.explode(bits).alias("lm"), "v", F.lit(d).alias("d")).filter("lm is not null") for d, x in enumerate(layers)]
    return reduce(DataFrame.union, parts)


def relax(weighted: DataFrame, source: int, max_rounds: int = 200) -> DataFrame:
    """(v, d): least weighted distance from ``source`` over (src, dst, w), w > 0: frontier relaxation."""
    spark = weighted.sparkSession
    best = cut(spark.createDataFrame([(int(source), 0)], "v long, d long"))
    frontier = best
    for _ in range(max_rounds):
        offers = frontier.join(weighted, frontier["v"] == weighted["src"]).groupBy(F.col("dst").alias("v")).agg(F.min(F.col("d") + F.col("w")).cast("long").alias("o"))
        merged = best.join(offers, "v", "full_outer")
        new = cut(merged.select("v", F.least("d", "o").alias("d"), (F.col("o").isNotNull() & (F.col("d").isNull() | (F.col("o") < F.col("d")))).alias("moved")))
        best, frontier = new.select("v", "d"), new.filter("moved").select("v", "d")
        if frontier.isEmpty():
            return best
    raise RuntimeError("relaxation did not settle")
