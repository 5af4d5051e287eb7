"""Verifiers: the cover property, minimality and exactness. Each returns the rows that violate it."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from graphdist.operators import query


def cover(labels: DataFrame, matrix: DataFrame, full: DataFrame, landmarks: DataFrame) -> DataFrame:
    """(r, v, d, decoded): landmark distances that labels and matrix don't give back."""
    r = F.broadcast(landmarks.select(F.col("id").alias("v")))
    truth = full.join(r, "v", "left_anti").select(F.col("lm").alias("r"), "v", "d")
    got = query.from_landmark(labels, matrix).withColumnRenamed("d", "decoded")
    return truth.join(got, ["r", "v"], "full_outer").filter(~F.col("d").eqNullSafe(F.col("decoded"))).select("r", "v", "d", "decoded")


def redundant(labels: DataFrame, matrix: DataFrame) -> DataFrame:
    """(v, lm, d): entries that the vertex's other entries and the matrix give already."""
    other = labels.select("v", F.col("lm").alias("q"), F.col("d").alias("qd"))
    m = F.broadcast(matrix.select(F.col("lm_a").alias("lm"), F.col("lm_b").alias("q"), F.col("d").alias("dm")))
    return labels.join(other, "v").filter("lm != q").join(m, ["lm", "q"]).filter("dm + qd <= d").select("v", "lm", "d").distinct()


def exact(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """(pair_id, dist, true_dist): wrong answers."""
    t = truth.select("pair_id", F.col("dist").alias("true_dist"))
    return answers.join(t, "pair_id", "full_outer").filter(~F.col("dist").eqNullSafe(F.col("true_dist"))).select("pair_id", "dist", "true_dist")
