"""Graphs derived from the given tables. Ids: kind * 10**12 + key, so that ties break alike everywhere.

Kinds: 0 world, 1 region, 2 nation, 3 customer, 4 supplier, 5 part, 6 order, 7 brand, 8 user, 9 page, 10 link target,
11 vector, 12 conversation turn, 13 part size.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from graphdist.operators import graph
from graphdist.runtime import table

UNIT = 10**12

#: A 14-vertex graph that fits the facts of the worked example, rebuilt for the tests.
EXAMPLE14 = (
    (1, 4), (1, 5), (1, 9), (1, 11), (1, 14), (2, 5), (2, 7), (2, 12), (2, 14), (3, 12), (4, 10), (4, 11), (4, 13), (5, 7), (5, 8), (5, 12), (6, 10), (6, 13), (7, 9),
    (8, 12), (8, 14), (9, 10), (10, 11), (12, 14),
)
EXAMPLE14_LANDMARKS = (1, 5, 9)


def vid(kind: int, key: Column | str) -> Column:
    key = F.col(key) if isinstance(key, str) else key
    return F.lit(kind * UNIT) + key.cast("long")


def _pairs(df: DataFrame, a: Column, b: Column) -> DataFrame:
    return df.select(a.alias("src"), b.alias("dst"))


def example14(spark: SparkSession, sf_dir: str | None = None) -> DataFrame:
    return graph.build(spark.createDataFrame(list(EXAMPLE14), "src long, dst long"))


def geo(spark, sf_dir):
    nation = table(spark, sf_dir, "nation")
    raw = (
        _pairs(table(spark, sf_dir, "customer"), vid(3, "c_custkey"), vid(2, "c_nationkey"))
        .union(_pairs(table(spark, sf_dir, "supplier"), vid(4, "s_suppkey"), vid(2, "s_nationkey")))
        .union(_pairs(nation, vid(2, "n_nationkey"), vid(1, "n_regionkey")))
        .union(_pairs(table(spark, sf_dir, "region"), vid(1, "r_regionkey"), F.lit(0).cast("long")))
    )
    return graph.build(raw)


def supply(spark, sf_dir):
    items = table(spark, sf_dir, "lineitem").filter("l_returnflag = 'R' and l_linenumber = 1")
    nation = table(spark, sf_dir, "nation")
    raw = (
        _pairs(table(spark, sf_dir, "orders"), vid(6, "o_orderkey"), vid(3, "o_custkey"))
        .union(_pairs(table(spark, sf_dir, "customer"), vid(3, "c_custkey"), vid(2, "c_nationkey")))
        .union(_pairs(table(spark, sf_dir, "supplier"), vid(4, "s_suppkey"), vid(2, "s_nationkey")))
        .union(_pairs(nation, vid(2, "n_nationkey"), vid(1, "n_regionkey")))
        .union(_pairs(table(spark, sf_dir, "region"), vid(1, "r_regionkey"), F.lit(0).cast("long")))
        .union(_pairs(items, vid(6, "l_orderkey"), vid(4, "l_suppkey")))
    )
    return graph.build(raw)


def succession(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    urgent = o.filter("o_orderpriority = '1-URGENT'").select((F.col("o_orderkey") + 1).alias("o_orderkey"), F.col("o_custkey").alias("a"))
    nxt = o.select("o_orderkey", F.col("o_custkey").alias("b"))
    return graph.build(_pairs(urgent.join(nxt, "o_orderkey"), vid(3, "a"), vid(3, "b")))


def basket(spark, sf_dir):
    o, items = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    j = items.select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey").join(o.select("o_orderkey", "o_custkey"), "o_orderkey")
    return graph.build(_pairs(j, vid(3, "o_custkey"), vid(5, "l_partkey")))


def brandhub(spark, sf_dir):
    items = table(spark, sf_dir, "lineitem").filter("l_linenumber <= 2")
    parts = table(spark, sf_dir, "part").filter("p_size <= 25")
    brand = F.regexp_extract("p_brand", r"Brand#(\d+)", 1)
    return graph.build(_pairs(items, vid(6, "l_orderkey"), vid(5, "l_partkey")).union(_pairs(parts, vid(5, "p_partkey"), vid(7, brand))))


def catalog(spark, sf_dir):
    """Brands and the sizes their parts come in: few vertices however many parts, for the all-pairs index."""
    part = table(spark, sf_dir, "part")
    return graph.build(_pairs(part, vid(7, F.regexp_extract("p_brand", r"Brand#(\d+)", 1)), vid(13, "p_size")))


def fragments(spark, sf_dir):
    items = table(spark, sf_dir, "lineitem").filter("l_returnflag = 'R' and l_quantity <= 15")
    return graph.build(_pairs(items, vid(6, "l_orderkey"), vid(5, "l_partkey")))


def users(spark, sf_dir):
    """User of an error event to the user of the next event. The global order makes this for test sizes only."""
    e = table(spark, sf_dir, "events").select("ts", "event_id", "user_id", "event_type")
    nxt = e.withColumn("b", F.lead("user_id").over(Window.orderBy("ts", "event_id"))).filter("event_type = 'error' and b is not null")
    return graph.build(_pairs(nxt, vid(8, "user_id"), vid(8, "b")))


def page_links(spark, sf_dir):
    """(page_id, target): distinct link targets of each page."""
    p = table(spark, sf_dir, "pages").select("page_id", "html")
    return p.select("page_id", F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), 1)).alias("target")).distinct()


def web(spark, sf_dir):
    links = page_links(spark, sf_dir)
    ids = graph.ranked(links.select(F.col("target").alias("id"))).select((F.col("rank") + 1).alias("n"), F.col("id").alias("target"))
    return graph.build(_pairs(links.join(ids, "target"), vid(9, "page_id"), vid(10, "n")))


#: Vectors a block of ``knn``: two blocks meet in one task.
BLOCK = 32_768


def _exact_cosines(a: np.ndarray, b: np.ndarray, na: np.ndarray, nb: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Cosines of the pairs (i, j), summed in order of the components, as ``aggregate`` does."""
    out = np.empty(len(i))
    for lo in range(0, len(i), 1 << 18):
        p, q = i[lo : lo + (1 << 18)], j[lo : lo + (1 << 18)]
        dot = np.zeros(len(p))
        for k in range(a.shape[1]):
            dot += a[p, k] * b[q, k]
        with np.errstate(divide="ignore", invalid="ignore"):
            out[lo : lo + (1 << 18)] = dot / (na[p] * nb[q])
    return out


def _norms(v: np.ndarray) -> np.ndarray:
    total = np.zeros(len(v))
    for k in range(v.shape[1]):
        total += v[:, k] * v[:, k]
    return np.sqrt(total)


def _nearest(near: int):
    """One block of vectors against another: a product in single precision leaves out what can't be among the nearest of the block, the
    rest is compared exactly. NaN (a zero vector) is above all, as in an ORDER BY.
    """

    def run(f: pd.DataFrame) -> pd.DataFrame:
        x, y = f[f["left"]], f[~f["left"]].sort_values("vec_id", kind="stable")
        ix, iy = x["vec_id"].to_numpy(), y["vec_id"].to_numpy()
        out = []
        if len(x) and len(y):
            a, b = np.stack(x["v"].to_list()), np.stack(y["v"].to_list())
            na, nb = _norms(a), _norms(b)
            with np.errstate(divide="ignore", invalid="ignore"):
                sa, sb = (a / na[:, None]).astype(np.float32), (b / nb[:, None]).astype(np.float32)
            margin = np.float32(4 * (a.shape[1] + 8) * 2.0**-23)  # above twice the rounding of a product of unit vectors
            for lo in range(0, len(x), 512):
                sim = sa[lo : lo + 512] @ sb.T
                sim[np.isnan(sim)] = np.inf
                sim[ix[lo : lo + 512, None] == iy[None, :]] = -np.inf
                least = np.partition(sim, -near, axis=1)[:, -near] if len(y) > near else np.full(len(sim), -np.inf, dtype=np.float32)
                i, j = np.nonzero((sim >= (least - margin)[:, None]) & (sim > -np.inf))
                exact = _exact_cosines(a[lo : lo + 512], b, na[lo : lo + 512], nb, i, j)
                order = np.lexsort((j, -np.where(np.isnan(exact), np.inf, exact), i))  # j ascends with the id
                first = np.searchsorted(i[order], i[order], side="left")
                kept = order[np.arange(len(order)) - first < near]
                out.append(pd.DataFrame({"x": ix[lo + i[kept]], "y": iy[j[kept]], "sim": exact[kept]}))
        return pd.concat(out) if out else pd.DataFrame({"x": [], "y": [], "sim": []}).astype({"x": "int64", "y": "int64", "sim": "float64"})

    return run


def knn(spark, sf_dir, near: int = 5):
    """Each vector and its most similar others by cosine, ties by id: blocks of ``BLOCK`` vectors against each other, all pairs."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"))
    whole = e.filter("v is not null and size(v) > 0 and not exists(v, c -> c is null)").withColumn("n", F.size("v"))
    n = e.count()
    blocks = max(1, -(-n // BLOCK), min(4, -(-n // 4096)))  # a few also where one would do, for the workers
    block = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left = whole.select("n", block.alias("i"), every.alias("j"), F.lit(True).alias("left"), "vec_id", "v")
    right = whole.select("n", every.alias("i"), block.alias("j"), F.lit(False).alias("left"), "vec_id", "v")
    sims = left.union(right).groupBy("n", "i", "j").applyInPandas(_nearest(near), "x long, y long, sim double")
    # pairs without a cosine (a null vector or component, another length) come last, in order of ids: of every kind of vector the first ids do
    shape = F.when(F.col("v").isNotNull() & (F.size("v") > 0) & ~F.exists("v", lambda c: c.isNull()), F.size("v")).otherwise(-1)
    kinds = e.select(F.col("vec_id"), shape.alias("n"))
    first = kinds.withColumn("r", F.row_number().over(Window.partitionBy("n").orderBy("vec_id"))).filter(F.col("r") <= near + 1).select(F.col("vec_id").alias("y"), F.col("n").alias("m"))
    if not first.filter("m = -1").isEmpty() or first.select("m").distinct().count() > 1:
        rest = kinds.join(F.broadcast(first), (F.col("vec_id") != F.col("y")) & ((F.col("n") != F.col("m")) | (F.col("n") == -1)))
        sims = sims.union(rest.select(F.col("vec_id").alias("x"), "y", F.lit(None).cast("double").alias("sim")))
    top = sims.withColumn("r", F.row_number().over(Window.partitionBy("x").orderBy(F.desc("sim"), "y"))).filter(F.col("r") <= near)
    return graph.build(_pairs(top, vid(11, "x"), vid(11, "y")))


def conv_paths(spark, sf_dir):
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn")
    key = F.col("conv_id") * 1000 + F.col("turn")
    nxt = c.select("conv_id", (F.col("turn") + 1).alias("turn")).join(c, ["conv_id", "turn"], "left_semi")
    return graph.build(_pairs(nxt, vid(12, key - 1), vid(12, key)))


GRAPHS = {
    "example14": example14, "geo": geo, "supply": supply, "succession": succession, "basket": basket, "brandhub": brandhub, "fragments": fragments, "users": users,
    "web": web, "knn": knn, "conv_paths": conv_paths, "catalog": catalog,
}
