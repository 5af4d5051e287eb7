"""Choice of landmarks: (rank, id), a table of k rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from graphdist.operators.graph import degrees, vertices


def _numbered(top: DataFrame, *order) -> DataFrame:
    return top.select((F.row_number().over(Window.orderBy(*order)) - 1).cast("int").alias("rank"), "id")  # k rows


def top_degree(edges: DataFrame, k: int) -> DataFrame:
    """The k vertices of highest degree, ties by ascending id."""
    order = (F.desc("deg"), F.asc("id"))
    return _numbered(degrees(edges).orderBy(*order).limit(k), *order)


def explicit(spark: SparkSession, ids) -> DataFrame:
    return spark.createDataFrame([(n, int(v)) for n, v in enumerate(ids)], "rank int, id long")


def random(edges: DataFrame, k: int, seed: int = 0) -> DataFrame:
    order = (F.xxhash64("id", F.lit(seed)), F.asc("id"))
    return _numbered(vertices(edges).orderBy(*order).limit(k), *order)


def reordered(landmarks: DataFrame, descending: bool = True) -> DataFrame:
    """The same vertices in another order, for order-dependence tests."""
    return _numbered(landmarks, F.desc("rank") if descending else F.asc("id"))
