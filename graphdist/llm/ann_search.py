"""Approximate nearest neighbours by learned partitions.

Fit (on a bounded sample of at most ``sample`` vectors, chosen by a hash of the id): the neighbour graph of the sample
is cut into ``parts`` balanced partitions by capacity-bounded label propagation, seeded by spread-out vectors; a small
softmax classifier then learns, for a vector, how its neighbours are shared out among the partitions. Every vector is indexed under its
most probable partition, and a query is sent to the most probable ``share`` of them, where all members are reranked by the
exact inner product in double precision. The same share is probed at every size; a query whose partitions hold too few candidates
is sent to further ones until it has ``k``.

Neighbouring partitions travel in ``GROUPS`` groups, so a query is copied at most once a group. A group is cut by hash into blocks of about
``block`` vectors, so a hot one (a third of all rows may be one vector) is read by many tasks; each gives its best ``k`` and the best
of those are merged.

Defined cases: vectors that are NULL, zero or hold NULL or non-finite numbers take no part, nor rows without an id; the router is fitted to
the most frequent length of the sample, and vectors of any other length are compared exactly with all of their own length; ties go to the
smaller id; rows that repeat an id are queries and candidates each, only a query's own row is left out; an empty table gives an
empty table.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window, functions as F

from graphdist.runtime import materialize

PARTS, SHARE, SAMPLE, BLOCK, K, EVERY, GROUPS = 256, 0.48, 8000, 8192, 20, 20, 32


def usable(vec: str = "embedding"):
    bad = F.exists(vec, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.col(vec).isNotNull() & ~bad & F.exists(vec, lambda x: x != 0)


class Router:
    """Softmax over partitions: unit vector -> probabilities."""

    def __init__(self, weights: np.ndarray, bias: np.ndarray):
        self.weights, self.bias = weights, bias

    def scores(self, x: np.ndarray) -> np.ndarray:
        unit = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
        return unit @ self.weights + self.bias


def neighbour_graph(x: np.ndarray, degree: int = 10) -> np.ndarray:
    """Row i: the ``degree`` nearest others of vector i by inner product of unit vectors."""
    out = np.zeros((len(x), min(degree, len(x) - 1)), dtype=np.int64)
    for lo in range(0, len(x), 1024):
        s = x[lo : lo + 1024] @ x.T
        s[np.arange(len(s)), np.arange(lo, lo + len(s))] = -np.inf
        out[lo : lo + 1024] = np.argpartition(-s, out.shape[1] - 1, axis=1)[:, : out.shape[1]]
    return out


def balanced_partition(x: np.ndarray, graph: np.ndarray, parts: int, rounds: int = 6, slackness: float = 1.15) -> np.ndarray:
    """Labels of the vertices: neighbours vote, no partition exceeds ``slackness`` times the mean size."""
    rng = np.random.default_rng(11)
    n = len(x)
    seeds = [int(rng.integers(n))]
    near = x @ x[seeds[0]]
    for _ in range(parts - 1):  # spread-out seeds
        far = np.maximum(1e-9, 1 - near) ** 2
        seeds.append(int(rng.choice(n, p=far / far.sum())))
        near = np.maximum(near, x @ x[seeds[-1]])
    centre = x[seeds]
    most = int(np.ceil(slackness * n / parts))
    label = np.zeros(n, dtype=np.int64)
    for r in range(rounds):
        votes = x @ centre.T
        if r:
            count = np.zeros((n, parts))
            np.add.at(count, (np.repeat(np.arange(n), graph.shape[1]), label[graph].ravel()), 1.0)
            votes = votes + 0.5 * count / graph.shape[1]
        room = np.full(parts, most)
        order = np.argsort(-(votes.max(axis=1) - np.partition(votes, -2, axis=1)[:, -2] if parts > 1 else votes[:, 0]), kind="stable")
        ranked = np.argsort(-votes, axis=1, kind="stable")
        for i in order:
            for p in ranked[i]:
                if room[p] > 0:
                    label[i] = p
                    room[p] -= 1
                    break
        sums = np.zeros_like(centre)
        np.add.at(sums, label, x)
        norm = np.linalg.norm(sums, axis=1, keepdims=True)
        centre = np.where(norm > 0, sums / np.maximum(norm, 1e-300), centre)
    return label


def fit(vectors: np.ndarray, parts: int = PARTS, steps: int = 250, degree: int = 20) -> Router:
    x = vectors / np.linalg.norm(vectors, axis=1, keepdims=True)
    parts = max(1, min(parts, len(x) // 8))
    if parts == 1:
        return Router(np.zeros((x.shape[1], 1)), np.zeros(1))
    graph = neighbour_graph(x, degree)
    label = balanced_partition(x, graph[:, :10], parts)
    label = np.argsort(np.argsort(_chain(x, label, parts)))[label]  # neighbouring numbers for similar partitions
    target = np.zeros((len(x), parts))
    np.add.at(target, (np.repeat(np.arange(len(x)), graph.shape[1]), label[graph].ravel()), 1.0 / graph.shape[1])
    w = np.zeros((x.shape[1], parts))
    np.add.at(w.T, label, x)
    w = 8.0 * w / np.maximum(np.linalg.norm(w, axis=0, keepdims=True), 1e-300)
    b = np.zeros(parts)
    for s in range(steps):
        z = x @ w + b
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        g = (p - target) / len(x)
        rate = 20.0 / (1 + 0.01 * s)
        w -= rate * (x.T @ g + 1e-5 * w)
        b -= rate * g.sum(axis=0)
    return Router(w, b)


def _chain(x: np.ndarray, label: np.ndarray, parts: int) -> np.ndarray:
    """A place for each partition on a chain that goes from one to the most similar one left."""
    centre = np.zeros((parts, x.shape[1]))
    np.add.at(centre, label, x)
    centre /= np.maximum(np.linalg.norm(centre, axis=1, keepdims=True), 1e-300)
    near, place, at = centre @ centre.T, np.zeros(parts, dtype=np.int64), 0
    left = np.ones(parts, dtype=bool)
    for k in range(parts):
        place[at] = k
        left[at] = False
        if left.any():
            at = int(np.where(left, near[at], -np.inf).argmax())
    return place


def _exact(v: np.ndarray, q: np.ndarray) -> np.ndarray:
    return (v * q).sum(axis=1)


def _best(k: int):
    """Candidates and queries of one block -> the ``k`` best of the asked partitions for each query."""
    empty = pd.DataFrame({"row": [], "query_id": [], "vec_id": [], "score": []}).astype({"row": "int64", "query_id": "int64", "vec_id": "int64", "score": "float64"})

    def run(key, cand, ask):
        out = []
        if len(cand) and len(ask):
            order = np.lexsort((cand["vec_id"].to_numpy(), cand["part"].to_numpy()))
            ids, rows, part = (cand[c].to_numpy()[order] for c in ("vec_id", "row", "part"))
            m = np.ascontiguousarray(np.vstack(cand["v"].to_numpy())[order])
            size = np.abs(m).max() + 1e-300
            names, starts = np.unique(part, return_index=True)
            ends = np.append(starts[1:], len(part))
            asked = {r: set(p.tolist()) for r, p in zip(ask["row"].tolist(), ask["parts"])}
            for lo in range(0, len(ask), 256):
                some = ask.iloc[lo : lo + 256]
                qs = np.vstack(some["q"].to_numpy())
                coarse = np.full((len(some), len(m)), -np.inf)
                for p, a, e in zip(names.tolist(), starts.tolist(), ends.tolist()):
                    who = np.flatnonzero([p in asked[r] for r in some["row"].tolist()])
                    if len(who):
                        coarse[who, a:e] = qs[who] @ m[a:e].T
                for i, (own, qid) in enumerate(zip(some["row"].tolist(), some["query_id"].tolist())):
                    row = coarse[i]
                    row[rows == own] = -np.inf
                    if len(row) > k:
                        edge = np.partition(row, len(row) - k)[len(row) - k]
                        at = np.flatnonzero(row >= edge - 1e-9 * size * (1 + np.abs(qs[i]).sum()))
                    else:
                        at = np.arange(len(row))
                    at = at[row[at] > -np.inf]
                    s = _exact(m[at], qs[i])
                    top = np.lexsort((ids[at], -s))[:k]
                    out.append(pd.DataFrame({"row": own, "query_id": qid, "vec_id": ids[at][top], "score": s[top]}))
        return pd.concat(out) if out else empty

    return run


def search(vectors: DataFrame, every: int = EVERY, k: int = K, parts: int = PARTS, share: float = SHARE, sample: int = SAMPLE, block: int = BLOCK) -> DataFrame:
    """(query_id, rank, vec_id, score): for each row with an id divisible by ``every`` its ``k`` nearest others found."""
    spark = vectors.sparkSession
    schema = "query_id long, rank int, vec_id long, score double"
    good = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v")).filter("vec_id is not null").filter(usable("v"))
    drawn = good.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).toPandas()  # at most ``sample`` vectors
    if not len(drawn):
        return spark.createDataFrame([], schema)
    lengths = drawn["v"].map(len)
    width = int(lengths.value_counts().sort_index().idxmax())
    router = fit(np.vstack(drawn["v"][lengths == width].to_numpy()).astype(float), parts)
    n_parts = len(router.bias)
    asked = max(1, int(np.ceil(share * n_parts)))
    shared = spark.sparkContext.broadcast(router)

    def route(frames):
        for f in frames:
            out = -f["v"].map(len).astype("int32")  # a partition of its own for every other length
            fits = (out == -width).to_numpy()
            if fits.any():
                out[fits] = shared.value.scores(np.vstack(f["v"][fits].to_numpy()).astype(float)).argmax(axis=1).astype("int32")
            yield pd.DataFrame({"vec_id": f["vec_id"], "v": f["v"], "part": out})

    routed = good.mapInPandas(route, "vec_id long, v array<double>, part int").withColumn("row", F.monotonically_increasing_id())
    routed = materialize(routed, "routed")
    sizes = {int(r["part"]): int(r["count"]) for r in routed.groupBy("part").count().collect()}  # one row a partition
    held = np.array([sizes.get(p, 0) for p in range(n_parts)])
    groups = min(GROUPS, n_parts)
    group_of = {p: p * groups // n_parts if p >= 0 else p for p in [*range(n_parts), *(p for p in sizes if p < 0)]}
    total: dict[int, int] = {}
    for p, n in sizes.items():
        total[group_of[p]] = total.get(group_of[p], 0) + n
    blocks = {g: -(-n // block) for g, n in total.items()}
    as_map = lambda d: F.create_map(*[F.lit(x) for pair in sorted(d.items()) for x in pair])
    rows = routed.withColumn("grp", F.element_at(as_map(group_of), F.col("part")))
    n_blocks = F.element_at(as_map(blocks), F.col("grp"))
    members = rows.select("grp", F.pmod(F.xxhash64("row", F.lit(9)), n_blocks).cast("int").alias("block"), "part", "vec_id", "row", "v")

    def ask(frames):
        for f in frames:
            out = []
            for qid, row, v, part in zip(f["vec_id"], f["row"], f["v"], f["part"]):
                chosen = [part]
                if part >= 0:
                    order = np.argsort(-shared.value.scores(np.asarray(v, dtype=float)[None, :])[0], kind="stable")
                    enough = int(np.searchsorted(np.cumsum(held[order]), k + 1)) + 1  # the query's own row is no candidate
                    chosen = order[: max(asked, enough)].tolist()
                by: dict[int, list[int]] = {}
                for p in chosen:
                    if sizes.get(p):
                        by.setdefault(group_of[p], []).append(p)
                out += [(qid, row, v, g, ps) for g, ps in by.items()]
            yield pd.DataFrame(out, columns=["query_id", "row", "q", "grp", "parts"])

    queries = routed.filter(F.col("vec_id") % every == 0).mapInPandas(ask, "query_id long, row long, q array<double>, grp int, parts array<int>")
    asks = queries.select("query_id", "row", "q", "grp", "parts", F.explode(F.sequence(F.lit(0), n_blocks - 1)).alias("block"))
    pairs = members.groupBy("grp", "block").cogroup(asks.groupBy("grp", "block"))
    found = pairs.applyInPandas(_best(k), "row long, query_id long, vec_id long, score double")
    w = Window.partitionBy("row").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op8_ann_search(spark, sf_dir):
    return search(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
