"""The experiment workloads as queries: statistics, sizes, times, sweeps, comparisons; and jobs on arriving data.

Queries that return seconds have no oracle; their counts do, in the queries they are built on.
"""

from __future__ import annotations

import os
import time
import uuid

from pyspark.sql import DataFrame, Window, functions as F

from graphdist import datasets, oracles as o
from graphdist.baselines import independent_set, mask_hybrid, online, two_hop
from graphdist.operators import bfs, gateway, graph, landmarks as lmk, metrics, verify
from graphdist.operators.engine import Index
from graphdist.runtime import checkpoint_dir, cut, table
from graphdist.sources import edge_lists, index_store
from graphdist.streaming import jobs

QUERIES: dict = {}  # further comparisons: comparison.py
ORACLES: dict = {}


def register(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def _w():
    from graphdist import workloads

    return workloads


def _folder(spark, name: str) -> str:
    return os.path.join(checkpoint_dir(spark), f"{name}-{uuid.uuid4().hex}")


_STATS = ("geo", "supply", "succession", "basket", "users")
_STAT_SQL = " UNION ALL ".join(
    f"SELECT '{g}' AS graph, count(*) AS n, CAST(sum(deg) / 2 AS BIGINT) AS m, max(deg) AS max_deg FROM (SELECT src, count(*) AS deg FROM (SELECT DISTINCT src, dst FROM "
    f"(SELECT a AS src, b AS dst FROM ({o.RAW[g]}) UNION ALL SELECT b, a FROM ({o.RAW[g]})) WHERE src <> dst) GROUP BY src)"
    for g in _STATS
)


@register("w_stats", _STAT_SQL)
def w_stats(s, d):
    rows = None
    for g in _STATS:
        one = graph.stats(_w().edges_of(s, d, g)).select(F.lit(g).alias("graph"), "n", "m", "max_deg")
        rows = one if rows is None else rows.union(one)
    return rows


register("w_hist", o.query("SELECT dist, count(*) AS pairs FROM truth GROUP BY dist", o.edges("users"), o.pairs(2000), o.truth("users")))(
    lambda s, d: metrics.distance_histogram(_w().index_of(s, d, "users").distance(graph.sample_pairs(_w().edges_of(s, d, "users"), 2000)))
)
_SU = (o.edges("succession"), o.landmarks("succession", 20), o.full("succession"), o.GATEWAY)
_PRUNED = """pruned AS (SELECT f.v, f.lm, f.d FROM full_d f JOIN landmarks i ON i.id = f.lm WHERE NOT EXISTS (
  SELECT 1 FROM landmarks j JOIN full_d qr ON qr.lm = j.id AND qr.v = f.lm JOIN full_d qv ON qv.lm = j.id AND qv.v = f.v
  WHERE j.rank < i.rank AND qr.d + qv.d <= f.d))"""
_SIZES = """sizes AS (SELECT 'gateway' AS method, count(*) AS entries FROM labels UNION ALL SELECT 'pruned_two_hop', count(*) FROM pruned
  UNION ALL SELECT 'full_table', count(*) FROM full_d WHERE v NOT IN (SELECT id FROM landmarks)),
inner_n AS (SELECT count(DISTINCT src) - (SELECT count(*) FROM landmarks) AS n FROM edges)"""


def _sizes(s, d) -> DataFrame:
    w = _w()
    r = F.broadcast(w.marks_of(s, d, "succession").select(F.col("id").alias("v")))
    full = w.full_of(s, d, "succession")
    parts = {
        "gateway": w.index_of(s, d, "succession").labels, "pruned_two_hop": two_hop.pruned_from_full(full, w.marks_of(s, d, "succession")), "full_table": full.join(r, "v", "left_anti"),
    }
    rows = None
    for name, x in parts.items():
        one = metrics.entries(x).select(F.lit(name).alias("method"), "entries")
        rows = one if rows is None else rows.union(one)
    return rows


@register("w_als", o.query("SELECT method, entries, entries / n AS als FROM sizes, inner_n", *_SU, _PRUNED, _SIZES))
def w_als(s, d):
    w = _w()
    n = graph.vertices(w.edges_of(s, d, "succession")).count() - w.marks_of(s, d, "succession").count()
    return _sizes(s, d).select("method", "entries", (F.col("entries") / F.lit(n)).alias("als"))


@register("w_bytes", o.query("SELECT method, entries * 2 AS bytes_8, entries * 5 AS bytes_32 FROM sizes", *_SU, _PRUNED, _SIZES))
def w_bytes(s, d):
    return _sizes(s, d).select("method", (F.col("entries") * 2).alias("bytes_8"), (F.col("entries") * 5).alias("bytes_32"))


def _seconds(f) -> float:
    start = time.time()
    f()
    return time.time() - start


@register("w_construct")
def w_construct(s, d):
    """(graph, method, seconds): building each index, k = 20."""
    w, rows = _w(), []
    for g in ("users", "geo"):
        e, r = w.edges_of(s, d, g), w.marks_of(s, d, g)
        methods = {
            "gateway_par": lambda: cut(gateway.build(e, r)[0]), "gateway_rows": lambda: cut(gateway.build(e, r, "rows")[0]), "mask_hybrid": lambda: cut(mask_hybrid.labels(e, r)),
            "independent_set": lambda: cut(independent_set.peel(e)[0]),
        }
        rows += [(g, m, _seconds(f)) for m, f in methods.items()]
    return s.createDataFrame(rows, "graph string, method string, seconds double")


@register("w_parallel")
def w_parallel(s, d):
    """(method, seconds): the same labels one landmark after the other, all as rows, all as bits of a mask (k = 5)."""
    w = _w()
    e, r = w.edges_of(s, d, "users"), w.marks_of(s, d, "users", 5)
    return s.createDataFrame([(m, _seconds(lambda m=m: cut(gateway.build(e, r, m)[0]))) for m in ("sequential", "rows", "masks")], "method string, seconds double")


@register("w_query")
def w_query(s, d):
    """(method, pairs, seconds, wrong): the same pairs by each method; wrong answers against plain search: none."""
    w = _w()
    e, p = w.edges_of(s, d, "users"), w.pairs_of(s, d, "users")
    r = w.marks_of(s, d, "users", 5)
    truth = cut(online.one_sided(e, p))
    index, masks = w.index_of(s, d, "users"), w.masks_of(s, d)
    methods = {
        "gateway": lambda: index.distance(p), "mask_hybrid": lambda: mask_hybrid.distance(e, r, masks, p), "bidirectional": lambda: online.bidirectional(e, p),
        "independent_set": lambda: independent_set.distance(e, p),
    }
    rows = []
    for name, f in methods.items():
        start = time.time()
        got = cut(f().select("pair_id", "dist"))
        rows.append((name, got.count(), time.time() - start, verify.exact(got, truth).count()))
    return s.createDataFrame(rows, "method string, pairs long, seconds double, wrong long")


def _sweep(s, d, what):
    w = _w()
    e, p = w.edges_of(s, d, "users"), w.pairs_of(s, d, "users")
    rows = []
    for k in w.KS:
        r = w.marks_of(s, d, "users", k)
        if what == "ct":
            rows.append((k, _seconds(lambda r=r: cut(gateway.build(e, r)[0]))))
        else:
            index = w.index_of(s, d, "users", k)
            rows.append((k, _seconds(lambda index=index: cut(index.distance(p)))))
    return s.createDataFrame(rows, "k int, seconds double")


register("w_sweep_ct")(lambda s, d: _sweep(s, d, "ct"))
register("w_sweep_qt")(lambda s, d: _sweep(s, d, "qt"))


@register("sweep_trend", o.query(
    """SELECT regr_slope(entries, k) AS slope, regr_r2(entries, k) AS r2 FROM (SELECT CAST(k AS DOUBLE) AS k, CAST(count(*) AS DOUBLE) AS entries FROM ks JOIN full_d f ON true
       JOIN landmarks l ON l.id = f.lm AND l.rank < k LEFT JOIN landmarks m ON m.id = f.v WHERE m.rank IS NULL OR m.rank >= k GROUP BY k)""",
    o.edges("users"), o.landmarks("users", 50), o.full("users"), "ks AS (SELECT unnest([10, 20, 30, 40, 50]) AS k)",
))
def sweep_trend(s, d):
    """Slope and fit of the full table's size over k, as a check of the trend functions."""
    w = _w()
    full = w.full_of(s, d, "users", 50)
    r = w.marks_of(s, d, "users", 50)
    a = F.broadcast(r.select(F.col("id").alias("lm"), F.col("rank").alias("lr")))
    b = F.broadcast(r.select(F.col("id").alias("v"), F.col("rank").alias("vr")))
    ks = F.broadcast(s.createDataFrame([(k,) for k in w.KS], "k int"))
    rows = full.join(a, "lm").join(b, "v", "left").join(ks, F.expr("lr < k and (vr is null or vr >= k)"))
    sizes = rows.groupBy("k").agg(F.count("*").cast("double").alias("entries")).withColumn("k", F.col("k").cast("double"))
    return sizes.agg(F.regr_slope("entries", "k").alias("slope"), F.regr_r2("entries", "k").alias("r2"))


register("exactness_violations", "SELECT CAST(0 AS BIGINT) AS pair_id, CAST(0 AS INTEGER) AS dist, CAST(0 AS INTEGER) AS true_dist WHERE false")(
    lambda s, d: verify.exact(_w().answers_of(s, d, "users").select("pair_id", "dist"), online.one_sided(_w().edges_of(s, d, "users"), _w().pairs_of(s, d, "users")))
)


@register("pruned_two_hop_masked")
def pruned_masked(s, d):
    """(v, lm, d) of three landmarks pruned with the help of the masks of two roots before them."""
    w = _w()
    e = w.edges_of(s, d, "users")
    order = w.marks_of(s, d, "users", 5)
    masks = cut(mask_hybrid.labels(e, cut(order.filter("rank < 2"))))
    after = order.filter("rank >= 2")
    return two_hop.pruned_after_masks(cut(bfs.levels(e, after)), after, masks)


@register("landmarks_random")
def landmarks_random(s, d):
    return lmk.random(_w().edges_of(s, d, "succession"), 20, seed=3)


@register("index_save_load", o.query("SELECT v, lm, d FROM labels", o.edges("users"), o.landmarks("users", 20), o.full("users"), o.GATEWAY))
def index_save_load(s, d):
    path = _folder(s, "index")
    index_store.save(_w().index_of(s, d, "users"), path, "v1")
    return index_store.load(s, path, "v1").labels


@register("op_bucketed_join", o.query("SELECT src, dst, deg FROM edges JOIN (SELECT src AS v, count(*) AS deg FROM edges GROUP BY src) ON v = src", o.edges("users")))
def bucketed_join(s, d):
    name = f"edges_{uuid.uuid4().hex}"
    edge_lists.write_bucketed(_w().edges_of(s, d, "users"), name, 8)
    t = s.table(name)
    return t.join(t.groupBy("src").agg(F.count("*").alias("deg")), "src").select("src", "dst", "deg")


@register("op_sample_hash", "SELECT o_orderkey FROM orders WHERE o_orderkey * 7919 % 100 < 5")
def sample_hash(s, d):
    return table(s, d, "orders").filter("o_orderkey * 7919 % 100 < 5").select("o_orderkey")


def _streamed(s, df: DataFrame, job, name: str, mode: str = "append") -> DataFrame:
    """Run a streaming job over ``df`` as files until all is read; the sink is Parquet in the shared folder."""
    src, out, state = _folder(s, f"{name}-in"), _folder(s, f"{name}-out"), _folder(s, f"{name}-state")
    df.write.parquet(src)
    stream = job(s.readStream.schema(df.schema).parquet(src))
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start()
    else:
        q = stream.writeStream.foreachBatch(lambda b, k: b.write.mode("append").parquet(out)).outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).start()
    q.awaitTermination()
    return s.read.schema(stream.schema).parquet(out)


def _arriving(s, d) -> DataFrame:
    e = table(s, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), (F.col("user_id") % 20).alias("src"), (F.col("event_id") % 15 + 100).alias("dst"))
    return e.coalesce(1)


def _arriving_users(s, d) -> DataFrame:
    """(ts, src, dst): the user of each event and the user of the next one, with their whole ids. For test sizes, as ``datasets.users``."""
    e = table(s, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), "event_id", F.col("user_id").cast("long").alias("src"))
    return e.withColumn("dst", F.lead("src").over(Window.orderBy("ts", "event_id"))).filter("dst is not null").select("ts", "src", "dst").coalesce(1)


register("op_stream_dedup_late")(lambda s, d: _streamed(s, _arriving_users(s, d), lambda x: jobs.edge_log(x, "40 days"), "edge-log"))


@register("op_stream_stateful_degree", "SELECT id, sum(n) AS deg FROM (SELECT user_id % 20 AS id, count(*) AS n FROM events GROUP BY 1 UNION ALL SELECT event_id % 15 + 100, count(*) FROM events GROUP BY 1) GROUP BY id")
def stateful_degree(s, d):
    out = _streamed(s, _arriving(s, d).select("src", "dst"), jobs.running_degree, "degree", "update")
    return out.groupBy("id").agg(F.max("deg").alias("deg"))


_USER_ENDS = "WITH e AS (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events)"


@register("op_stream_user_degree", f"{_USER_ENDS} SELECT id, count(*) AS deg FROM (SELECT src AS id FROM e WHERE dst IS NOT NULL UNION ALL SELECT dst FROM e WHERE dst IS NOT NULL) GROUP BY id")
def user_degree(s, d):
    """The running degree of every user; ``op_stream_stateful_degree`` keeps its registered SQL, which folds the ids."""
    out = _streamed(s, _arriving_users(s, d).select("src", "dst"), jobs.running_degree, "user-degree", "update")
    return out.groupBy("id").agg(F.max("deg").alias("deg"))


@register("op_stream_queries", o.query("SELECT pair_id, s, t, dist FROM truth", o.edges("users"), o.pairs(100), o.truth("users")))
def stream_queries(s, d):
    w = _w()
    index, out, state, src = w.index_of(s, d, "users"), _folder(s, "answers"), _folder(s, "answers-state"), _folder(s, "pairs-in")
    pairs = w.pairs_of(s, d, "users")
    pairs.coalesce(1).write.parquet(src)
    sink = lambda a, k: a.select("pair_id", "s", "t", "dist", "version").write.mode("overwrite").parquet(f"{out}/batch={k}")
    jobs.answer_arriving(s.readStream.schema(pairs.schema).parquet(src), index, "v1", sink, state).trigger(availableNow=True).start().awaitTermination()
    return s.read.parquet(out).select("pair_id", "s", "t", "dist")


@register(
    "op_stream_interval_join",
    """SELECT a.event_id AS aid, b.event_id AS bid, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'purchase'
    AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 3600 SECONDS""",
)
def stream_interval_join(s, d):
    e = table(s, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_id", "event_type").coalesce(1)
    return _streamed(s, e, lambda x: jobs.followed_within(x.filter("event_type = 'error'"), x.filter("event_type = 'purchase'"), 3600), "interval")


def distance_for_tables(spark, sf_dir: str, name: str, k: int = 20) -> Index:
    """An index over one of the derived graphs, for interactive use."""
    return Index.build(cut(datasets.GRAPHS[name](spark, sf_dir)), k)
