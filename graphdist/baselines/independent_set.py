"""Independent-set hybrid: peel independent sets, keep distances by weighted shortcuts, label vertices with their ancestors.

A round removes an independent set (a vertex that beats all its neighbours by lower degree, then by hash); its neighbours are joined
pairwise by shortcuts of the summed weight. A removed vertex remembers its weighted neighbours of that moment. Labels
are these, followed upwards. A query is the least of the shared-ancestor sums and of a weighted search on the residual
graph that starts from both labels.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, functions as F

from graphdist.runtime import cut, discard, materialize


def _key(w_deg: DataFrame) -> DataFrame:
    return w_deg.select(F.col("src").alias("v"), "deg", F.struct(F.col("deg"), F.xxhash64("src").alias("h"), F.col("src").alias("k")).alias("key"))


def _both(half: DataFrame) -> DataFrame:
    return half.union(half.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))


def peel(edges: DataFrame, levels: int = 6, max_degree: int | None = None, residual: bool = True) -> tuple[DataFrame, DataFrame | None]:
    """(ups, residual): ups(v, up, w, level) of removed vertices, residual(src, dst, w). With ``max_degree``, vertices of more
    neighbours are never removed, which bounds the shortcuts a vertex makes (and changes the peeling).

    Weights are the same both ways, so a level stores an edge once (src < dst), in compressed columns, and deletes the level before it.
    Without ``residual`` (None then) the shortcuts of the last level, which no label reads, are not made.
    """
    half = materialize(edges.filter("src < dst").select("src", "dst", F.lit(1).alias("w")), "peel")
    ups = [edges.sparkSession.createDataFrame([], "v long, up long, w int, level int")]
    for level in range(levels):
        g = _both(half)
        key = _key(g.groupBy("src").agg(F.count("*").alias("deg")))
        around = g.join(key.select(F.col("v").alias("dst"), F.col("key").alias("nk")), "dst").groupBy(F.col("src").alias("v")).agg(F.min("nk").alias("best"))
        gone = materialize(key.join(around, "v").filter((F.col("key") < F.col("best")) & (F.lit(max_degree is None) | (F.col("deg") <= (max_degree or 0)))).select("v"), "peel")
        if gone.isEmpty():
            discard(gone)
            break
        star = materialize(g.join(gone, g["src"] == gone["v"]).select("v", F.col("dst").alias("up"), "w", F.lit(level).alias("level")), "peel")
        ups.append(star)
        if level == levels - 1 and not residual:
            discard(half, gone)
            return reduce(DataFrame.union, ups), None
        a, b = star.select("v", F.col("up").alias("src"), F.col("w").alias("w1")), star.select("v", F.col("up").alias("dst"), F.col("w").alias("w2"))
        short = a.join(b, "v").filter("src < dst").select("src", "dst", (F.col("w1") + F.col("w2")).alias("w"))
        rest = half.join(gone, half["src"] == gone["v"], "left_anti").join(gone, half["dst"] == gone["v"], "left_anti")
        after = materialize(rest.union(short).groupBy("src", "dst").agg(F.min("w").alias("w")), "peel")
        discard(half, gone)
        half = after
    return reduce(DataFrame.union, ups), _both(half) if residual else None


def labels(ups: DataFrame, ids: DataFrame) -> DataFrame:
    """(v, anc, d): every vertex's ancestors with their least upward distance, itself at 0.

    A vertex's neighbours of its level were removed later, so levels are labelled from the last to the first, each once.
    """
    own = ids.select(F.col("id").alias("v"), F.col("id").alias("anc"), F.lit(0).alias("d"))
    done = []
    for level in sorted((r["level"] for r in ups.select("level").distinct().collect()), reverse=True):  # a row a level
        star = ups.filter(F.col("level") == level).select("v", "up", "w")
        offers = star.select("v", F.col("up").alias("anc"), F.col("w").alias("d"))
        if done:
            higher = reduce(DataFrame.union, done).withColumnRenamed("v", "up")
            offers = offers.union(star.join(higher, "up").select("v", "anc", (F.col("d") + F.col("w")).alias("d")))
        done.append(materialize(offers.groupBy("v", "anc").agg(F.min("d").alias("d")), "ancestors"))
    return reduce(DataFrame.union, done, own)


def distance(edges: DataFrame, pairs: DataFrame, levels: int = 6) -> DataFrame:
    """(pair_id, s, t, dist)."""
    from graphdist.operators import graph

    ups, residual = peel(edges, levels)
    lab = labels(ups, graph.vertices(edges))  # stored level by level
    a = pairs.join(lab.select(F.col("v").alias("s"), "anc", F.col("d").alias("da")), "s").select("pair_id", "anc", "da")
    b = pairs.join(lab.select(F.col("v").alias("t"), "anc", F.col("d").alias("db")), "t").select("pair_id", "anc", "db")
    shared = cut(a.join(b, ["pair_id", "anc"]).groupBy("pair_id").agg(F.min(F.col("da") + F.col("db")).alias("best")))
    # a weighted search on the residual from the label of s; it stops where it can't beat the best sum found
    best = cut(a.select("pair_id", F.col("anc").alias("v"), F.col("da").alias("d")))
    frontier = best
    while not frontier.isEmpty():
        offers = frontier.join(residual, frontier["v"] == residual["src"]).groupBy("pair_id", F.col("dst").alias("v")).agg(F.min(F.col("d") + F.col("w")).alias("o"))
        offers = offers.join(shared, "pair_id", "left").filter("best is null or o < best").drop("best")
        known = best.withColumnRenamed("d", "k")
        frontier = cut(offers.join(known, ["pair_id", "v"], "left").filter("k is null or o < k").select("pair_id", "v", F.col("o").alias("d")))
        best = cut(best.union(frontier).groupBy("pair_id", "v").agg(F.min("d").alias("d")))
    met = best.join(b, (best["pair_id"] == b["pair_id"]) & (best["v"] == b["anc"])).groupBy(best["pair_id"]).agg(F.min(F.col("d") + F.col("db")).alias("dist"))
    return pairs.join(met, "pair_id", "left").select("pair_id", "s", "t", F.col("dist").cast("int").alias("dist"))
