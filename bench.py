"""Bench: prints ONE JSON line. BENCH_SF_DIR (default sf0.1), BENCH_CPUS (default 8).

For each graph: build time of the gateway labels (all landmarks at once), of the mask hybrid, exact answers to a batch of pairs, and the online
baseline on a hundredth of them. ``detail`` has entries per label, coverage, edges and pairs a second.
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession, functions as F

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
PAIRS = int(os.environ.get("BENCH_PAIRS", "2000"))
LLM = os.environ.get("BENCH_LLM", "1") == "1"


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.driver.memory", "16g").config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from graphdist import datasets
    from graphdist.baselines import mask_hybrid, online
    from graphdist.operators import gateway, graph, landmarks
    from graphdist.operators.engine import Index
    from graphdist.runtime import cut

    times: dict[str, float] = {}
    detail: dict[str, dict] = {}

    def timed(name, f):
        start = time.time()
        out = f()
        times[name] = round(time.time() - start, 3)
        return out

    cut(datasets.geo(spark, SF_DIR)).count()  # starts the JVM's compilation
    for g in ("succession", "supply", "basket"):
        edges = cut(datasets.GRAPHS[g](spark, SF_DIR))
        m = edges.count() // 2
        marks = cut(landmarks.top_degree(edges, 20))

        def build():
            labels, matrix = gateway.build(edges, marks)
            labels = cut(labels)
            return Index(edges, marks, labels, matrix, cut(graph.core(edges, marks)))

        index = timed(f"construct_{g}", build)
        pairs = cut(graph.hashed_pairs(edges, PAIRS))
        answers = timed(f"query_{g}", lambda: cut(index.distance(pairs)))
        few = cut(pairs.filter(F.col("pair_id") < max(1, PAIRS // 100)))
        timed(f"bidirectional_{g}", lambda: cut(online.bidirectional(edges, few)))
        if g == "succession":
            masks = timed(f"mask_hybrid_construct_{g}", lambda: cut(mask_hybrid.labels(edges, marks)))
            timed(f"mask_hybrid_query_{g}", lambda: cut(mask_hybrid.distance(edges, marks, masks, pairs)))
        n = graph.vertices(edges).count()
        entries = index.labels.count()
        covered = answers.filter("covered").count()
        detail[g] = {
            "n": n, "m": m, "entries": entries, "als": round(entries / max(1, n - 20), 3), "bytes_8": 2 * entries, "graph_bytes": 8 * m, "coverage": round(covered / PAIRS, 4),
            "edges_per_s": round(m / times[f"construct_{g}"]), "pairs_per_s": round(PAIRS / times[f"query_{g}"], 1), "ms_per_pair": round(1000 * times[f"query_{g}"] / PAIRS, 3),
            "online_ms_per_pair": round(1000 * times[f"bidirectional_{g}"] / max(1, PAIRS // 100), 1),
        }
    if LLM:
        try:
            from graphdist.llm import queries as llm
        except ImportError:
            llm = None
        for name, f in llm.queries().items() if llm else ():
            timed(name, lambda: f(spark, SF_DIR).write.format("noop").mode("overwrite").save())
    print(json.dumps({"metric": "distance_engine_total", "value": round(sum(v for k, v in times.items() if not k.startswith("op")), 3), "unit": "sec", "queries": times, "sf": SF_DIR, "detail": detail}))
    spark.stop()


if __name__ == "__main__":
    main()
