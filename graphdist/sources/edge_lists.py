"""Edge lists as CSV, JSON, text, Parquet or ORC; schemas are declared, never inferred."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

SCHEMA = "src long, dst long"


def read(spark: SparkSession, path: str, kind: str = "parquet", separator: str = r"\s+") -> DataFrame:
    """Raw edges (src, dst). Text: two numbers a line, ``#`` starts a comment line, other lines are skipped."""
    if kind == "text":
        parts = F.split(F.trim("value"), separator)
        lines = spark.read.text(path).filter(~F.startswith("value", F.lit("#")))
        return lines.select(F.try_element_at(parts, F.lit(1)).try_cast("long").alias("src"), F.try_element_at(parts, F.lit(2)).try_cast("long").alias("dst")).filter("src is not null and dst is not null")
    return spark.read.schema(SCHEMA).format(kind).load(path)


def write(edges: DataFrame, path: str, kind: str = "parquet") -> None:
    if kind == "text":
        edges.select(F.concat_ws("\t", "src", "dst").alias("value")).write.mode("overwrite").text(path)
    else:
        edges.select("src", "dst").write.mode("overwrite").format(kind).save(path)


def write_bucketed(edges: DataFrame, name: str, buckets: int) -> None:
    """A catalog table bucketed and sorted by src, so that joins with a state of the same bucketing don't move it."""
    edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(name)
