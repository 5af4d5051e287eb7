"""Saving and loading an index: versioned folders, the manifest last."""

from __future__ import annotations

import json

from pyspark.sql import SparkSession, functions as F

from graphdist.operators import codec
from graphdist.operators.engine import Index


def save(index: Index, path: str, version: str, lm_bits: int = 8) -> None:
    """Parquet below path/version; readers that go by the manifest never see a half-written index."""
    base = f"{path}/{version}"
    index.edges.sortWithinPartitions("src").write.parquet(f"{base}/edges")
    index.core.sortWithinPartitions("src").write.parquet(f"{base}/core")
    index.landmarks.write.parquet(f"{base}/landmarks")
    index.matrix.write.parquet(f"{base}/matrix")
    codec.pack(index.labels, index.landmarks, lm_bits).sortWithinPartitions("v").write.parquet(f"{base}/labels")
    spark = index.edges.sparkSession
    manifest = json.dumps({"version": version, "k": index.landmarks.count(), "lm_bits": lm_bits})
    spark.createDataFrame([(manifest,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/_manifest_{version}")


def load(spark: SparkSession, path: str, version: str) -> Index:
    manifest = json.loads(spark.read.text(f"{path}/_manifest_{version}").first()[0])
    base = f"{path}/{manifest['version']}"
    read = lambda name: spark.read.parquet(f"{base}/{name}")
    landmarks = read("landmarks")
    labels = codec.unpack(read("labels"), landmarks, manifest["lm_bits"])
    return Index(read("edges"), landmarks, labels, read("matrix"), read("core"))


def point_labels(spark: SparkSession, path: str, version: str, ids) -> object:
    """Labels of a few vertices: the filter reaches the Parquet scan, row groups are sorted by v."""
    return spark.read.parquet(f"{path}/{version}/labels").filter(F.col("v").isin(list(ids)))
