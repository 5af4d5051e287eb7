"""Streaming jobs: an edge log without repeats, running degrees, answers to arriving queries, an interval join of streams.

The labelling itself is static: the log is appended, and the index rebuilt from it now and then; answers carry the version
of the index that gave them.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from graphdist.operators.engine import Index


def edge_log(edges: DataFrame, delay: str = "10 minutes") -> DataFrame:
    """New undirected edges (ts, src, dst), each once within the watermark; later repeats and late rows are dropped."""
    low, high = F.least("src", "dst"), F.greatest("src", "dst")
    one = edges.filter("src != dst").select("ts", low.alias("src"), high.alias("dst"))
    return one.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["src", "dst"])


def running_degree(edges: DataFrame) -> DataFrame:
    """(id, deg): updates of the number of edge ends seen at each vertex."""
    ends = edges.select(F.col("src").alias("id")).union(edges.select(F.col("dst").alias("id")))

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        total = state.get[0] if state.exists else 0
        total += sum(len(f) for f in frames)
        state.update((total,))
        yield pd.DataFrame({"id": [key[0]], "deg": [total]})

    return ends.groupBy("id").applyInPandasWithState(update, "id long, deg long", "deg long", "update", GroupStateTimeout.NoTimeout)


def bounds_of_arriving(pairs: DataFrame, index: Index, version: str) -> DataFrame:
    """Upper bounds of a stream of (pair_id, s, t): stream-static joins only."""
    return index.upper_bound(pairs, "pruned").withColumn("version", F.lit(version))


def answer_arriving(pairs: DataFrame, index: Index, version: str, sink: Callable[[DataFrame, int], None], checkpoint: str):
    """Exact answers: each micro-batch is one call of the engine. ``sink(answers, batch_id)`` must be idempotent."""

    def batch(df: DataFrame, batch_id: int) -> None:
        sink(index.distance(df).withColumn("version", F.lit(version)), batch_id)

    return pairs.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint)


def followed_within(a: DataFrame, b: DataFrame, seconds: int, delay: str = "10 minutes") -> DataFrame:
    """Stream-stream join: rows of ``b`` up to ``seconds`` after a row of ``a`` of the same user; both sides keep bounded state."""
    x = a.select("user_id", F.col("ts").alias("ats"), F.col("event_id").alias("aid")).withWatermark("ats", delay)
    y = b.select(F.col("user_id").alias("u"), F.col("ts").alias("bts"), F.col("event_id").alias("bid")).withWatermark("bts", delay)
    return x.join(y, F.expr(f"user_id = u and bts > ats and bts <= ats + interval {seconds} seconds")).select("aid", "bid", "user_id")
