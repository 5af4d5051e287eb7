"""Distances out of labels: upper bounds, constrained distances, two-hop answers, triangle bounds. NULL is infinity."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def with_virtual(labels: DataFrame, landmarks: DataFrame) -> DataFrame:
    """Labels of all vertices: a landmark gets the entry (itself, 0)."""
    return labels.select("v", "lm", "d").union(landmarks.select(F.col("id").alias("v"), F.col("id").alias("lm"), F.lit(0).alias("d")))


def packed(labels: DataFrame) -> DataFrame:
    """(v, label): one array of (lm, d) a vertex."""
    return labels.groupBy("v").agg(F.array_sort(F.collect_list(F.struct("lm", "d"))).alias("label"))  # at most k entries


def _sides(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """pairs with the packed labels ls, lt of their ends (NULL if empty). Pairs move, labels are read once a side."""
    p = packed(labels)
    a, b = p.select(F.col("v").alias("s"), F.col("label").alias("ls")), p.select(F.col("v").alias("t"), F.col("label").alias("lt"))
    return pairs.join(a, "s", "left").join(b, "t", "left")


def upper_bound(pairs: DataFrame, labels: DataFrame, matrix: DataFrame, landmarks: DataFrame, method: str = "pruned") -> DataFrame:
    """pairs with ``ub``. Landmark ends are answered by their virtual entry, equal ends by 0.

    ``cross``: every entry of s with every entry of t over the matrix. ``pruned``: a landmark in both labels only meets
    itself; the matrix is used for entries that the other side lacks.
    """
    lab = with_virtual(labels, landmarks)
    if method == "cross":
        s = pairs.join(lab.select(F.col("v").alias("s"), F.col("lm").alias("lm_a"), F.col("d").alias("da")), "s")
        st = s.join(F.broadcast(matrix.select("lm_a", "lm_b", F.col("d").alias("dm"))), "lm_a")  # at most k * k rows
        met = st.join(lab.select(F.col("v").alias("t"), F.col("lm").alias("lm_b"), F.col("d").alias("db")), ["t", "lm_b"])
        best = met.groupBy("pair_id").agg(F.min(F.col("da") + F.col("dm") + F.col("db")).alias("ub"))
        out = pairs.join(best, "pair_id", "left")
    else:
        # the matrix row of each landmark as a map, k maps of k entries, sent to every task
        rows = matrix.groupBy("lm_a").agg(F.map_from_entries(F.collect_list(F.struct("lm_b", "d"))).alias("row"))
        table = F.broadcast(rows.agg(F.map_from_entries(F.collect_list(F.struct("lm_a", "row"))).alias("m")))
        both = _sides(pairs, lab).join(table)  # one row
        shared = F.array_intersect(F.transform("ls", lambda e: e.lm), F.transform("lt", lambda e: e.lm))
        mine = both.withColumn("shared", shared)
        common = F.transform(
            "shared",
            lambda r: F.filter("ls", lambda e: e.lm == r)[0].d + F.filter("lt", lambda e: e.lm == r)[0].d,
        )
        only_s = F.filter("ls", lambda e: ~F.array_contains("shared", e.lm))
        only_t = F.filter("lt", lambda e: ~F.array_contains("shared", e.lm))
        crossed = F.flatten(F.transform(only_s, lambda a: F.transform(only_t, lambda b: a.d + b.d + F.try_element_at(F.try_element_at(F.col("m"), a.lm), b.lm))))
        out = mine.select("pair_id", "s", "t", F.array_min(F.concat(common, crossed)).cast("int").alias("ub"))
    return out.select("pair_id", "s", "t", F.when(F.col("s") == F.col("t"), 0).otherwise(F.col("ub")).cast("int").alias("ub"))


def constrained(triples: DataFrame, labels: DataFrame, matrix: DataFrame, landmarks: DataFrame) -> DataFrame:
    """(pair_id, s, t, r, d): length of the shortest s-t path through landmark r."""
    lab = with_virtual(labels, landmarks)
    m = F.broadcast(matrix.select("lm_a", F.col("lm_b").alias("r"), F.col("d").alias("dm")))
    to = triples.select("r").distinct()
    reach = lab.join(m, lab["lm"] == m["lm_a"]).join(F.broadcast(to), "r", "left_semi").groupBy("v", "r").agg(F.min(F.col("d") + F.col("dm")).alias("x"))
    a, b = reach.select(F.col("v").alias("s"), "r", F.col("x").alias("xs")), reach.select(F.col("v").alias("t"), "r", F.col("x").alias("xt"))
    return triples.join(a, ["s", "r"], "left").join(b, ["t", "r"], "left").select("pair_id", "s", "t", "r", (F.col("xs") + F.col("xt")).cast("int").alias("d"))


def from_landmark(labels: DataFrame, matrix: DataFrame) -> DataFrame:
    """(r, v, d): exact distance from every landmark to every labelled vertex, decoded from label and matrix."""
    m = F.broadcast(matrix.select(F.col("lm_a").alias("r"), "lm_b", F.col("d").alias("dm")))
    return labels.join(m, labels["lm"] == m["lm_b"]).groupBy("r", "v").agg(F.min(F.col("d") + F.col("dm")).cast("int").alias("d"))


def two_hop(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """(pair_id, s, t, d): least sum over hubs that both labels share; NULL if they share none; 0 for equal ends."""
    a = labels.select(F.col("v").alias("s"), "lm", F.col("d").alias("da"))
    b = labels.select(F.col("v").alias("t"), "lm", F.col("d").alias("db"))
    best = pairs.join(a, "s").join(b, ["t", "lm"]).groupBy("pair_id").agg(F.min(F.col("da") + F.col("db")).alias("d"))
    return pairs.join(best, "pair_id", "left").select("pair_id", "s", "t", F.when(F.col("s") == F.col("t"), 0).otherwise(F.col("d")).cast("int").alias("d"))


def triangle_bounds(pairs: DataFrame, full: DataFrame) -> DataFrame:
    """(pair_id, s, t, lower, upper): bounds from the distances to landmarks alone."""
    a = full.select(F.col("v").alias("s"), "lm", F.col("d").alias("da"))
    b = full.select(F.col("v").alias("t"), "lm", F.col("d").alias("db"))
    best = pairs.join(a, "s").join(b, ["t", "lm"]).groupBy("pair_id").agg(F.max(F.abs(F.col("da") - F.col("db"))).alias("lower"), F.min(F.col("da") + F.col("db")).alias("upper"))
    return pairs.join(best, "pair_id", "left").select("pair_id", "s", "t", F.col("lower").cast("int").alias("lower"), F.col("upper").cast("int").alias("upper"))
