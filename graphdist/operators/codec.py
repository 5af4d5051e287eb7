"""Label compression: 8 or 32 bits for the landmark, 8 for the distance (16 as an option)."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def pack(labels: DataFrame, landmarks: DataFrame, lm_bits: int = 8, dist_bits: int = 8) -> DataFrame:
    """(v, n_entries, bytes): a vertex's entries in order of landmark rank, big-endian. Overflow raises."""
    k = F.broadcast(landmarks.select(F.col("id").alias("lm"), "rank"))
    top_lm, top_d = 2**lm_bits - 1, 2**dist_bits - 1
    e = labels.join(k, "lm")
    rank = F.when(F.col("rank") <= top_lm, F.col("rank")).otherwise(F.raise_error(F.lit(f"landmark rank exceeds {lm_bits} bits")).cast("int"))
    d = F.when(F.col("d") <= top_d, F.col("d")).otherwise(F.raise_error(F.lit(f"distance exceeds {dist_bits} bits")).cast("int"))
    text = F.concat(F.lpad(F.hex(rank), lm_bits // 4, "0"), F.lpad(F.hex(d), dist_bits // 4, "0"))
    packed = e.groupBy("v").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("rank", text.alias("x")))), lambda p: p.x), "").alias("h"), F.count("*").alias("n_entries"))
    return packed.select("v", "n_entries", F.unhex("h").alias("bytes"))


def unpack(packed: DataFrame, landmarks: DataFrame, lm_bits: int = 8, dist_bits: int = 8) -> DataFrame:
    """labels(v, lm, d) again."""
    k = F.broadcast(landmarks.select(F.col("id").alias("lm"), "rank"))
    a, b = lm_bits // 4, dist_bits // 4
    h = packed.select("v", F.hex("bytes").alias("h"), F.explode(F.sequence(F.lit(0), F.col("n_entries").cast("int") - 1)).alias("i"))
    part = lambda start, size: F.conv(F.substring(F.col("h"), F.col("i") * (a + b) + 1 + start, F.lit(size)), 16, 10).cast("int")
    return h.select("v", part(0, a).alias("rank"), part(a, b).alias("d")).join(k, "rank").select("v", "lm", "d")
