import pytest
from pyspark.sql import functions as F


@pytest.fixture(scope="session")
def make_docs(spark):
    """documents from (doc_id, text) pairs, with the table's columns and one of a clashing name."""

    def make(rows):
        df = spark.createDataFrame(rows, "doc_id long, text string")
        return df.select("doc_id", "text", F.lit("en").alias("lang"), F.lit("s").alias("source"), F.length("text").cast("long").alias("n_chars"), F.lit(7).alias("id"))

    return make
