"""The pipeline's stages on a small table with planted cases."""

import random

import corpus_pipeline
import pytest
from pyspark.sql import functions as F


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    r = random.Random(9)
    d = tmp_path_factory.mktemp("tables")
    v = [f"{a}{b}{c}" for a in "bdfgk" for b in "aeiou" for c in ("lo", "ne", "rit", "s")]
    text = lambda n: "\n".join(" ".join(r.choice(v) for _ in range(12)) for _ in range(n))
    item = " ".join(r.choice(v) for _ in range(30))
    rows = [(i, text(6)) for i in range(40)]
    rows += [(100, rows[0][1]), (101, rows[1][1]), (102, text(1) + "\n" + item), (103, None), (104, "12 34 !"), (105, text(300))]
    spark.createDataFrame(rows, "doc_id long, text string").select("doc_id", "text", F.lit("en").alias("lang"), F.lit("s").alias("source"), F.length("text").cast("long").alias("n_chars")).write.parquet(f"{d}/documents.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
    return str(d)


def test_stages(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    names, seen = docs.columns, {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, folder)
        assert docs.columns == names
        docs = docs.checkpoint()
        seen[name] = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert set(seen["language_id"]) == set(range(40)) | {100, 101, 102, 105}
    assert seen["line_dedup"][100] == "" and seen["line_dedup"][0] != ""
    left = set(seen["simhash_dedup"])
    assert set(range(40)) | {102, 105} <= left and len(left & {100, 101}) == 1  # two emptied copies are one group
    assert 102 not in seen["decontamination"] and set(range(40)) <= set(seen["decontamination"])
    packed = corpus_pipeline.run(spark, folder).collect()
    assert {r["doc_id"] for r in packed} == set(seen["decontamination"])


def test_stage_names():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "line_dedup", "simhash_dedup", "decontamination", "packing"]
