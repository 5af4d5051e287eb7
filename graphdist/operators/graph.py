"""Graphs as edge tables: both directions, no repeats, no loops; ids are longs."""

from __future__ import annotations

import uuid
from contextlib import contextmanager
from typing import NamedTuple

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window, functions as F

from graphdist.runtime import cut, discard, materialize


def build(raw: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """Edges (src, dst) of the simple undirected graph of ``raw``; directed input is read as undirected."""
    one = raw.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst")).filter("src is not null and dst is not null and src != dst")
    half = one.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()  # an edge moves once
    both = F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst")))
    return half.select(F.inline(both))


class Dealt(NamedTuple):
    """Edges as the levels of a search read them: those of the hubs, and all others dealt and sorted by src."""

    ids: list
    hub_edges: DataFrame
    rest: DataFrame


def deal(edges: DataFrame, ids: list) -> Dealt:
    """Done once for all levels. ``rest`` lies on the executors' disks in compressed columns and keeps its partitions and order, so a
    level neither shuffles nor sorts it; what is lost with an executor is dealt again from ``edges``.
    """
    n, hub = int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), F.col("src").isin(ids)
    own = F.lit(uuid.uuid4().hex) != ""  # else Spark takes the plan for that of an earlier deal, and one undeal would end both
    rest = edges.filter(~hub & own).select("src", "dst").repartition(n, "src").sortWithinPartitions("src").persist(StorageLevel.DISK_ONLY)
    try:
        rest.count()  # joins see the partitions only of a table that is stored
        return Dealt(ids, materialize(edges.filter(hub).select("src", "dst"), "hubs"), rest)
    except BaseException:  # also a job cancelled by its limit
        rest.unpersist()
        raise


def undeal(dealt: Dealt) -> None:
    """Delete what ``deal`` stored."""
    dealt.rest.unpersist()
    discard(dealt.hub_edges)


@contextmanager
def dealing(edges: DataFrame, ids: list, dealt: Dealt | None = None):
    """``dealt``, or a deal of its own that is deleted in the end, also if a job in between is cancelled."""
    if dealt:
        yield dealt
        return
    mine = deal(edges, ids)
    try:
        yield mine
    finally:
        undeal(mine)


def to_neighbours(rows: DataFrame, dealt: Dealt) -> DataFrame:
    """``rows`` (v, ...) once for each neighbour of v: (dst, ...). The rows of hubs are few and go to all of their edges."""
    hub, others = F.col("v").isin(dealt.ids), [c for c in rows.columns if c != "v"]
    sent = lambda e, r: e.join(r, e["src"] == r["v"]).select("dst", *others)
    return sent(dealt.hub_edges, F.broadcast(rows.filter(hub))).union(sent(dealt.rest, rows.filter(~hub)))


def dealt_vertices(dealt: Dealt) -> DataFrame:
    """``vertices`` without a shuffle: every vertex is the src of some edge."""
    return vertices(dealt.rest).union(vertices(dealt.hub_edges))


def vertices(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("id")).distinct()


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg"))


def core(edges: DataFrame, landmarks: DataFrame) -> DataFrame:
    """The graph without its landmarks (k rows, so both anti joins are broadcast and nothing is shuffled)."""
    r = F.broadcast(landmarks.select("id"))
    return edges.join(r, edges["src"] == r["id"], "left_anti").join(r, edges["dst"] == r["id"], "left_anti")


def induced(edges: DataFrame, keep: DataFrame) -> DataFrame:
    """The graph on the vertices ``keep`` (column id)."""
    a, b = keep.select(F.col("id").alias("a")).distinct(), keep.select(F.col("id").alias("b")).distinct()
    return edges.join(a, edges["src"] == a["a"], "left_semi").join(b, edges["dst"] == b["b"], "left_semi")


def stats(edges: DataFrame) -> DataFrame:
    """One row: n, m, density (m/n), mean and largest degree."""
    return degrees(edges).agg(
        F.count("*").alias("n"), (F.sum("deg") / 2).cast("long").alias("m"), (F.sum("deg") / 2 / F.count("*")).alias("density"), F.avg("deg").alias("mean_deg"),
        F.max("deg").alias("max_deg"),
    )


def ranked(ids: DataFrame) -> DataFrame:
    """(rank, id): position of each id in ascending order, from 0, without one task holding all of them.

    Ids are dealt by range; a table of one row a range gives each range its offset.
    """
    n = int(ids.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = cut(ids.select("id").distinct().repartitionByRange(n, "id").withColumn("part", F.spark_partition_id()))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = dealt.groupBy("part").agg(F.count("*").alias("c")).select("part", F.coalesce(F.sum("c").over(before), F.lit(0)).alias("offset"))
    inside = dealt.withColumn("k", F.row_number().over(Window.partitionBy("part").orderBy("id")) - 1)
    return inside.join(F.broadcast(offsets), "part").select((F.col("offset") + F.col("k")).cast("long").alias("rank"), "id")


def sample_pairs(edges: DataFrame, n_pairs: int) -> DataFrame:
    """(pair_id, s, t): the portable rule, integer arithmetic on ranks, the same here and in the oracles."""
    rank = cut(ranked(vertices(edges)))
    n = rank.count()
    spark = edges.sparkSession
    wanted = spark.range(n_pairs if n else 0).select(
        F.col("id").alias("pair_id"), F.expr(f"pmod(id * 7919 + 13, {max(n, 1)})").alias("rs"), F.expr(f"pmod(id * 104729 + 57, {max(n, 1)})").alias("rt")
    )
    a, b = rank.select(F.col("rank").alias("rs"), F.col("id").alias("s")), rank.select(F.col("rank").alias("rt"), F.col("id").alias("t"))
    return wanted.join(a, "rs").join(b, "rt").select("pair_id", "s", "t")


def hashed_pairs(edges: DataFrame, n_pairs: int, seed: int = 1) -> DataFrame:
    """(pair_id, s, t) drawn from V x V by a hash of the pair number: for benches, any number of pairs."""
    rank = cut(ranked(vertices(edges)))
    n = rank.count()
    spark = edges.sparkSession
    wanted = spark.range(n_pairs if n else 0).select(
        F.col("id").alias("pair_id"), F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(max(n, 1))).alias("rs"), F.pmod(F.xxhash64("id", F.lit(seed + 1)), F.lit(max(n, 1))).alias("rt")
    )
    a, b = rank.select(F.col("rank").alias("rs"), F.col("id").alias("s")), rank.select(F.col("rank").alias("rt"), F.col("id").alias("t"))
    return wanted.join(a, "rs").join(b, "rt").select("pair_id", "s", "t")
