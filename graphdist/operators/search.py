"""Distance-bounded bidirectional search, for all pairs at once.

Tables: ``visited`` (pair_id, side, v, d) and one row a pair with both depths, both visited counts and the bound. A round
expands one side of every open pair (the one with fewer visited vertices, ties to s), finds meetings by a join with the
other side, and closes pairs that met, whose depths add up to their bound, or whose side has no new vertex.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, functions as F

from graphdist.runtime import cut


def bounded(core: DataFrame, pairs: DataFrame, balance: str = "visited", max_rounds: int = 10_000) -> DataFrame:
    """pairs (pair_id, s, t, ub) with core_d and steps. core_d is the distance in ``core`` if it is at most ub (any
    distance, if ub is NULL), else NULL: no path, or none that is shorter than the bound.
    """
    kept = pairs.select("pair_id", "s", "t", F.col("ub").cast("int").alias("ub"))
    same = kept.filter("s = t").select("pair_id", F.lit(0).alias("core_d"), F.lit(0).alias("steps"))
    todo = kept.filter("s != t")
    open_pairs = cut(todo.select("pair_id", "ub", F.lit(0).alias("ds"), F.lit(0).alias("dt"), F.lit(1).cast("long").alias("ns"), F.lit(1).cast("long").alias("nt"), F.lit(1).cast("long").alias("fs"), F.lit(1).cast("long").alias("ft")).filter("ub is null or ub > 0"))
    visited = cut(
        todo.select("pair_id", F.lit(0).alias("side"), F.col("s").alias("v"), F.lit(0).alias("d")).union(todo.select("pair_id", F.lit(1).alias("side"), F.col("t").alias("v"), F.lit(0).alias("d")))
    )
    done = [same]
    for step in range(1, max_rounds + 1):
        if open_pairs.isEmpty():
            break
        rule = {"visited": "ns <= nt", "frontier": "fs <= ft", "alternate": "ds <= dt"}[balance]
        turn = open_pairs.withColumn("side", F.when(F.expr(rule), 0).otherwise(1)).withColumn("at", F.when(F.col("side") == 0, F.col("ds")).otherwise(F.col("dt")))
        edge = visited.join(turn.select("pair_id", "side", F.col("at").alias("d")), ["pair_id", "side", "d"], "left_semi")
        reached = edge.join(core, edge["v"] == core["src"]).select("pair_id", "side", F.col("dst").alias("v")).distinct()
        new = cut(
            reached.join(visited.select("pair_id", "side", "v"), ["pair_id", "side", "v"], "left_anti")
            .join(turn.select("pair_id", (F.col("at") + 1).alias("d")), "pair_id").select("pair_id", "side", "v", "d")
        )
        other = visited.select("pair_id", (1 - F.col("side")).alias("side"), "v")
        met = new.join(other, ["pair_id", "side", "v"], "left_semi").select("pair_id").distinct().withColumn("met", F.lit(True))
        grown = new.groupBy("pair_id").agg(F.count("*").alias("c"))
        after = turn.join(grown, "pair_id", "left").join(met, "pair_id", "left").select(
            "pair_id", "ub", "side", F.coalesce("met", F.lit(False)).alias("met"), F.coalesce("c", F.lit(0)).alias("c"),
            (F.col("ds") + (F.col("side") == 0).cast("int")).alias("ds"), (F.col("dt") + (F.col("side") == 1).cast("int")).alias("dt"), "ns", "nt", "fs", "ft",
        )
        after = cut(after.withColumn("end", F.col("met") | (F.col("c") == 0) | (F.coalesce(F.col("ds") + F.col("dt") == F.col("ub"), F.lit(False)))))
        done.append(after.filter("end").select("pair_id", F.when(F.col("met"), F.col("ds") + F.col("dt")).alias("core_d"), F.lit(step).alias("steps")))
        first = F.col("side") == 0
        open_pairs = after.filter("not end").select(
            "pair_id", "ub", "ds", "dt", (F.col("ns") + F.when(first, F.col("c")).otherwise(0)).alias("ns"), (F.col("nt") + F.when(first, 0).otherwise(F.col("c"))).alias("nt"),
            F.when(first, F.col("c")).otherwise(F.col("fs")).alias("fs"), F.when(first, F.col("ft")).otherwise(F.col("c")).alias("ft"),
        )
        visited = visited.join(open_pairs.select("pair_id"), "pair_id", "left_semi").union(new)
        if step % 4 == 0:
            visited = cut(visited)
    else:
        raise RuntimeError("search did not end")
    return kept.join(reduce(DataFrame.union, done), "pair_id", "left").select("pair_id", "s", "t", "ub", F.col("core_d").cast("int").alias("core_d"), F.coalesce("steps", F.lit(0)).alias("steps"))


def bounded_value(core: DataFrame, pairs: DataFrame, **options) -> DataFrame:
    """(pair_id, s, t, ub, value): the smaller of the bound and the distance in ``core``, for any given bound."""
    return bounded(core, pairs, **options).select("pair_id", "s", "t", "ub", F.least("ub", "core_d").alias("value"))
