"""Joins that stay even when one key holds a large share of the rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

#: A key is heavy if it holds at least this share of all rows, so there are at most this many heavy keys.
SHARE = 2000


def spread_join(many: DataFrame, one: DataFrame, keys: list[str], weight: str, total: int) -> DataFrame:
    """Left join of ``many`` with ``one`` (unique ``keys``; ``weight`` = rows of ``many`` that hold them, at least).

    ``total`` is the sum of the weights. Keys with at least 1 / ``SHARE`` of it are sent by broadcast: at most ``SHARE`` rows,
    whatever the data. Their rows are dealt by row number instead of by key, so no task gets a heavy key's rows.
    """
    names = [c for c in one.columns if c not in (*keys, weight)]
    packed = lambda name: one.select(*keys, F.col(weight).alias("_w"), F.struct(F.lit(True).alias("_hit"), *names).alias(name))
    heavy = packed("_heavy").filter(F.col("_w") * SHARE >= max(1, total)).drop("_w")
    rest = packed("_rest").filter(F.col("_w") * SHARE < max(1, total)).drop("_w")
    met = many.join(F.broadcast(heavy), keys, "left")
    dealt = F.when(F.col("_heavy").isNull(), F.xxhash64(*keys)).otherwise(F.monotonically_increasing_id())
    met = met.withColumn("_deal", dealt)
    rest = rest.select(F.xxhash64(*keys).alias("_deal"), *[F.col(k).alias(f"_k_{k}") for k in keys], "_rest")
    same = [F.col(k) == F.col(f"_k_{k}") for k in keys]
    on: Column = (met["_deal"] == rest["_deal"]) & met["_heavy"].isNull()
    for s in same:
        on = on & s
    joined = met.join(rest.hint("shuffle_hash"), on, "left")
    return joined.select(*[F.col(f"`{c}`") for c in many.columns], *[F.coalesce(f"_heavy.{n}", f"_rest.{n}").alias(n) for n in names])
