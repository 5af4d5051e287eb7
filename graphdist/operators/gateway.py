"""The minimal landmark labelling ("gateway" labels) and the landmark matrix.

A vertex v keeps the entry (r, d) exactly if no shortest r-v path meets a landmark besides r. All landmarks search together: a
vertex carries one bit a landmark in three masks. ``seen``: reached before; ``open``: reached in this level by
paths free of other landmarks only; ``shut``: reached in this level by some path that meets one. A level is one
aggregation of neighbours' masks by ``bit_or``; shut wins over open within a level, which is the all-paths rule.
A landmark reached openly gives a direct matrix entry and passes the bit on shut. A bit retires when it is open
nowhere. The matrix is then closed under min-plus.

Landmarks are the hubs, so their adjacency is joined with their k state rows by broadcast, wherever it lies; all other
edges stay partitioned and sorted by source beside the state, dealt once for all words. At most 63 bits fit a word; more landmarks take several words.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, functions as F

from graphdist.operators import graph
from graphdist.runtime import cut

WORD = 63


def _bits(mask, landmarks: list[tuple[int, int]]):
    """Landmark ids of the set bits, as an array column."""
    pairs = F.array(*[F.struct(F.lit(1 << b).alias("bit"), F.lit(v).alias("id")) for b, v in landmarks])
    return F.transform(F.filter(pairs, lambda p: F.col(mask).bitwiseAND(p.bit) != 0), lambda p: p.id)


def _word(dealt: graph.Dealt, state0: DataFrame, members: list[tuple[int, int]], trace: list | None):
    """Labels (v, lm, d) and direct pairs (lm_a, lm_b, d) of the landmarks of one mask word."""
    own = F.coalesce(F.create_map(*[F.lit(x) for b, v in members for x in (v, 1 << b)])[F.col("v")], F.lit(0)).cast("long")
    zero = F.lit(0).cast("long")
    state = cut(state0.select("v", "is_landmark", own.alias("seen"), own.alias("open"), zero.alias("shut"), zero.alias("direct")))
    active = sum(1 << b for b, _ in members)
    labels, direct, depth = [], [], 0
    while active:
        depth += 1
        moving = state.filter("open != 0 or shut != 0").select("v", F.col("open").bitwiseAND(F.lit(active)).alias("open"), F.col("shut").bitwiseAND(F.lit(active)).alias("shut"), "is_landmark")
        if trace is not None:
            trace.append((depth, moving, active))
        heard = graph.to_neighbours(moving.select("v", "open", "shut"), dealt).groupBy("dst").agg(F.bit_or("open").alias("io"), F.bit_or("shut").alias("is"))
        unseen = F.bitwise_not("seen")
        nxt = state.join(heard, state["v"] == heard["dst"], "left").select(
            "v", "is_landmark", "seen", F.coalesce("io", zero).bitwiseAND(unseen).alias("io"), F.coalesce("is", zero).bitwiseAND(unseen).alias("ns")
        )
        nxt = nxt.select("v", "is_landmark", "seen", F.col("io").bitwiseAND(F.bitwise_not("ns")).alias("no"), "ns")
        state = cut(
            nxt.select(
                "v", "is_landmark", F.col("seen").bitwiseOR(F.col("no")).bitwiseOR(F.col("ns")).alias("seen"),
                F.when(F.col("is_landmark"), zero).otherwise(F.col("no")).alias("open"),
                F.when(F.col("is_landmark"), F.col("ns").bitwiseOR(F.col("no"))).otherwise(F.col("ns")).alias("shut"),
                F.when(F.col("is_landmark"), F.col("no")).otherwise(zero).alias("direct"),
            )
        )
        labels.append(state.filter("open != 0").select("v", F.col("open").alias("mask"), F.lit(depth).alias("d")))
        direct.append(state.filter("direct != 0").select("v", F.col("direct").alias("mask"), F.lit(depth).alias("d")))
        active = state.agg(F.coalesce(F.bit_or("open"), zero)).first()[0]
    spread = lambda parts: reduce(DataFrame.union, parts).select("v", F.explode(_bits("mask", members)).alias("lm"), "d")
    return spread(labels), spread(direct).select(F.col("lm").alias("lm_a"), F.col("v").alias("lm_b"), "d")


def build(edges: DataFrame, landmarks: DataFrame, mode: str = "masks", trace: list | None = None, dealt: graph.Dealt | None = None) -> tuple[DataFrame, DataFrame]:
    """(labels, matrix): labels(v, lm, d) of all other vertices, matrix(lm_a, lm_b, d) over connected landmarks.

    mode ``masks``: up to 63 landmarks a word, all in one pass a level; ``sequential``: one landmark after the other.
    ``rows``: one row a (landmark, vertex), no masks, any number of landmarks in one pass. ``dealt``: the edges already dealt with
    these landmarks as hubs, if others read them too.
    """
    ids = [r["id"] for r in landmarks.orderBy("rank").collect()]  # k rows
    spark = edges.sparkSession
    r = F.broadcast(spark.createDataFrame([(v, True) for v in ids], "id long, is_landmark boolean"))
    if not ids or edges.isEmpty():
        empty = spark.createDataFrame([], "v long, lm long, d int")
        direct = spark.createDataFrame([], "lm_a long, lm_b long, d int")
        return empty, close_matrix(direct, landmarks)
    if mode == "rows":
        return _rows(edges, landmarks)
    with graph.dealing(edges, ids, dealt) as mine:
        everyone = graph.dealt_vertices(mine).withColumnRenamed("id", "v").repartition(mine.rest.rdd.getNumPartitions(), "v")
        state0 = cut(everyone.join(r, everyone["v"] == r["id"], "left").select("v", F.coalesce("is_landmark", F.lit(False)).alias("is_landmark")))
        step = 1 if mode == "sequential" else WORD
        labels, direct = [], []
        for lo in range(0, len(ids), step):
            a, b = _word(mine, state0, list(enumerate(ids[lo : lo + step])), trace)
            labels.append(a)
            direct.append(b)
    return reduce(DataFrame.union, labels), close_matrix(reduce(DataFrame.union, direct), landmarks)


def _rows(edges: DataFrame, landmarks: DataFrame) -> tuple[DataFrame, DataFrame]:
    """One row a (landmark, vertex): frontier rows carry whether every path so far is free of other landmarks."""
    r = F.broadcast(landmarks.select(F.col("id").alias("r")))
    found = cut(landmarks.select(F.col("id").alias("lm"), F.col("id").alias("v"), F.lit(False).alias("shut"), F.lit(True).alias("hub")))
    layers, depth, labels, direct = [found], 0, [], []
    frontier = found
    while True:
        depth += 1
        heard = frontier.join(edges, frontier["v"] == edges["src"]).groupBy("lm", F.col("dst").alias("v")).agg(F.max("shut").alias("shut"))
        known = reduce(DataFrame.union, [x.select("lm", "v") for x in layers[-2:]])
        new = heard.join(known, ["lm", "v"], "left_anti")
        new = new.join(r, new["v"] == r["r"], "left").select("lm", "v", F.col("shut").alias("was_shut"), F.col("r").isNotNull().alias("hub"))
        layer = cut(new.select("lm", "v", (F.col("was_shut") | F.col("hub")).alias("shut"), "hub", "was_shut"))
        labels.append(layer.filter("not shut").select("v", "lm", F.lit(depth).alias("d")))
        direct.append(layer.filter("hub and not was_shut").select(F.col("lm").alias("lm_a"), F.col("v").alias("lm_b"), F.lit(depth).alias("d")))
        layers.append(layer)
        going = layer.filter("not shut").select("lm").distinct()
        frontier = layer.join(F.broadcast(going), "lm", "left_semi")  # a landmark without open vertices retires (at most k rows)
        if going.isEmpty():
            break
    return reduce(DataFrame.union, labels), close_matrix(reduce(DataFrame.union, direct), landmarks)


def close_matrix(direct: DataFrame, landmarks: DataFrame) -> DataFrame:
    """All landmark distances from the direct ones: min-plus doubling over at most k * k rows."""
    own = landmarks.select(F.col("id").alias("lm_a"), F.col("id").alias("lm_b"), F.lit(0).alias("d"))
    both = direct.union(direct.select(F.col("lm_b").alias("lm_a"), F.col("lm_a").alias("lm_b"), "d"))
    m = cut(both.union(own).groupBy("lm_a", "lm_b").agg(F.min("d").alias("d")))
    k = landmarks.count()
    hops = 1
    while hops < max(1, k - 1):
        left = m.select("lm_a", F.col("lm_b").alias("via"), F.col("d").alias("d1"))
        right = F.broadcast(m.select(F.col("lm_a").alias("via"), "lm_b", F.col("d").alias("d2")))  # at most k * k rows
        new = cut(left.join(right, "via").groupBy("lm_a", "lm_b").agg(F.min(F.col("d1") + F.col("d2")).alias("d")))
        hops *= 2
        same = new.exceptAll(m).isEmpty()
        m = new
        if same:
            break
    return m


def from_full(full: DataFrame, landmarks: DataFrame) -> DataFrame:
    """Labels by the closed criterion: drop (r, v) if some landmark q other than r lies on a shortest r-v path."""
    q = F.broadcast(landmarks.select(F.col("id").alias("q")))
    own = full.join(q, full["v"] == q["q"], "left_anti")
    matrix = F.broadcast(matrix_from_full(full, landmarks).filter("lm_a != lm_b").select(F.col("lm_a").alias("lm"), F.col("lm_b").alias("q"), F.col("d").alias("rq")))
    via = full.select(F.col("lm").alias("q"), "v", F.col("d").alias("qv"))
    passed = own.join(matrix, "lm").join(via, ["q", "v"]).filter("rq + qv = d").select("lm", "v").distinct()
    return own.join(passed, ["lm", "v"], "left_anti").select("v", "lm", "d")


def matrix_from_full(full: DataFrame, landmarks: DataFrame) -> DataFrame:
    r = F.broadcast(landmarks.select("id"))
    return full.join(r, full["v"] == r["id"], "left_semi").select(F.col("lm").alias("lm_a"), F.col("v").alias("lm_b"), "d")
