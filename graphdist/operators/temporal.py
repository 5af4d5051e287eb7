"""Joins in time: intervals and as-of."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F


def interval_join(left: DataFrame, right: DataFrame, key: str, ts: str, seconds: int) -> DataFrame:
    """Rows of ``right`` up to ``seconds`` after a row of ``left`` with the same key (later than it).

    Both sides are cut into buckets of that length; a left row looks into its own and the next one, so the join is an
    equi-join on (key, bucket) and neither a long key history nor a hot bucket is compared with all of itself.
    """
    bucket = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    a = left.withColumn("_b", F.explode(F.array(bucket(ts), bucket(ts) + 1))).withColumnRenamed(ts, "_lts")
    b = right.withColumn("_b", bucket(ts)).withColumnRenamed(ts, "_rts")
    met = a.join(b, [key, "_b"])
    return met.filter((F.col("_rts") > F.col("_lts")) & (F.col("_rts") <= F.col("_lts") + F.expr(f"INTERVAL {seconds} SECONDS"))).drop("_b")


def as_of(left: DataFrame, right: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """``left`` with the latest ``value`` of ``right`` at or before its time (ties: the larger value): union and one window."""
    names = left.columns
    a = left.select(*names, F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias(value))
    b = right.select(*[F.col(c) if c in (key, ts) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in names], F.lit(0).alias("_side"), value)
    w = Window.partitionBy(key).orderBy(ts, "_side", value).rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn("_last", F.last(value, ignorenulls=True).over(w)).filter("_side = 1").select(*names, F.col("_last").alias(value))
