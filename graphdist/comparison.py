"""The methods side by side: same graphs, 20 landmarks or roots each, same pairs; sizes, answers, times, sweeps, properties.

Queries with seconds have no oracle. A run that takes longer than its limit is cancelled and reported as not finished.
"""

from __future__ import annotations

import threading
import time
import uuid

from pyspark import InheritableThread
from pyspark.sql import DataFrame, functions as F

from graphdist import oracles as o
from graphdist.baselines import full_table, independent_set, mask_hybrid, online, two_hop
from graphdist.functions import udfs
from graphdist.operators import bfs, gateway, graph, landmarks as lmk, metrics, query, search, verify
from graphdist.runtime import cut, materialize
from graphdist.workloads import KS, answers_of, dealt_of, edges_of, full_of, index_of, marks_of, n_pairs, pairs_of, _once, _given, _PRUNED

K, LIMIT = 20, 30.0
GRAPHS = ("succession", "supply", "basket")
QUERIES: dict = {}
ORACLES: dict = {}


def register(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def within(spark, seconds: float, f):
    """(status, seconds, result): f() in a job group that is cancelled after the limit; status ok or DNF."""
    group, out = uuid.uuid4().hex, {}

    def run():
        spark.sparkContext.setJobGroup(group, "measured", interruptOnCancel=True)
        try:
            out["result"] = f()
        except Exception as e:  # reported below, or the effect of the cancellation
            out["error"] = e

    thread, start = InheritableThread(target=run), time.time()
    thread.start()
    thread.join(seconds)
    if thread.is_alive():
        stop = threading.Event()
        while thread.is_alive() and not stop.wait(0.2):
            spark.sparkContext.cancelJobGroup(group)
            thread.join(0.1)
        return "DNF", time.time() - start, None
    if "error" in out:
        raise out["error"]
    return "ok", time.time() - start, out["result"]


def masks20(s, d, g) -> DataFrame:
    return _once(s, (d, g, "masks20"), lambda: mask_hybrid.labels(edges_of(s, d, g), marks_of(s, d, g, K), dealt=dealt_of(s, d, g, K)))  # stored level by level


def pruned20(s, d, g) -> DataFrame:
    return _once(s, (d, g, "pruned20"), lambda: materialize(two_hop.pruned_from_full(full_of(s, d, g), marks_of(s, d, g)), "pruned"))


def peeled(s, d, g):
    return _once(s, (d, g, "peeled"), lambda: independent_set.labels(independent_set.peel(edges_of(s, d, g), residual=False)[0], graph.vertices(edges_of(s, d, g))))  # stored level by level


def _kept(*items: str) -> tuple:
    """The labels and tables of an oracle, computed once however often they are read."""
    import re

    return tuple(re.sub(r"^((?:labels|pruned|sizes|swept)) AS \(", r"\1 AS MATERIALIZED (", x.replace("full_d AS (", "full_d AS MATERIALIZED (").replace("\nsizes AS (", "\nsizes AS MATERIALIZED (").replace("\nswept AS (", "\nswept AS MATERIALIZED (").replace("\nedges AS (", "\nedges AS MATERIALIZED (")) for x in items)


# sizes --------------------------------------------------------------------------------------------------------

#: bytes an entry: 8-bit landmark and distance; 32-bit vertex and 8-bit distance; the latter with two 64-bit masks
BYTES = {"gateway_8": 2, "gateway": 5, "pruned_two_hop": 5, "full_table": 5, "mask_hybrid": 21}
_INNER = "WHERE v NOT IN (SELECT id FROM landmarks)"
_SIZES = f"""counted AS (SELECT 'gateway' AS method, count(*) AS entries, 5 AS b FROM labels UNION ALL SELECT 'gateway_8', count(*), 2 FROM labels
  UNION ALL SELECT 'pruned_two_hop', count(*), 5 FROM pruned {_INNER} UNION ALL SELECT 'full_table', count(*), 5 FROM full_d {_INNER}
  UNION ALL SELECT 'mask_hybrid', count(*), 21 FROM full_d {_INNER}),
vertices AS (SELECT count(DISTINCT src) - (SELECT count(*) FROM landmarks) AS n, CAST(count(*) / 2 * 8 AS BIGINT) AS graph_bytes FROM edges),
sizes AS (SELECT method, entries, entries / n AS als, entries * b AS bytes, entries * b / graph_bytes AS of_graph FROM counted, vertices)"""


def sizes(s, d, g) -> DataFrame:
    """(method, entries, als, bytes, of_graph) over the vertices that are no landmark, all with 20 landmarks or roots."""
    r = F.broadcast(marks_of(s, d, g).select(F.col("id").alias("v")))
    inner = lambda x: x.join(r, "v", "left_anti").select("v")
    labels = index_of(s, d, g).labels
    parts = {"gateway": labels.select("v"), "gateway_8": labels.select("v"), "pruned_two_hop": inner(pruned20(s, d, g)), "full_table": inner(full_of(s, d, g)), "mask_hybrid": inner(masks20(s, d, g))}
    n = graph.dealt_vertices(dealt_of(s, d, g)).join(r, F.col("id") == F.col("v"), "left_anti").agg(F.count("*").alias("n"))
    whole = F.broadcast(n.join(F.broadcast(metrics.graph_bytes(edges_of(s, d, g)))))  # one row
    rows = None
    for name, x in parts.items():
        one = x.agg(F.count("*").alias("entries")).select(F.lit(name).alias("method"), "entries", F.lit(BYTES[name]).alias("b"))
        rows = one if rows is None else rows.union(one)
    size = F.col("entries") * F.col("b")
    return rows.join(whole).select("method", "entries", (F.col("entries") / F.col("n")).alias("als"), size.alias("bytes"), (size / F.col("graph_bytes")).alias("of_graph"))


for _g in GRAPHS:
    _items = _kept(*_given(_g), o.full(_g), o.GATEWAY, _PRUNED, _SIZES)
    register(f"compare_sizes_{_g}", o.query("SELECT method, entries, als, bytes, of_graph FROM sizes", *_items))(lambda s, d, g=_g: sizes(s, d, g))
    register(f"size_ratios_{_g}", o.query("SELECT a.method, a.bytes / b.bytes AS times_gateway FROM sizes a, sizes b WHERE b.method = 'gateway_8' AND a.method <> 'gateway_8'", *_items))(
        lambda s, d, g=_g: _ratios(s, d, g)
    )
    register(f"compare_sizes_independent_{_g}")(lambda s, d, g=_g: peeled(s, d, g).agg(F.lit("independent_set").alias("method"), F.count("*").alias("entries"), (F.count("*") * 8).alias("bytes")))


def _ratios(s, d, g):
    """(method, times_gateway): bytes over those of the packed gateway labels."""
    found = cut(sizes(s, d, g))
    least = F.broadcast(found.filter("method = 'gateway_8'").select(F.col("bytes").alias("least")))
    return found.filter("method <> 'gateway_8'").join(least).select("method", (F.col("bytes") / F.col("least")).alias("times_gateway"))


# answers and times --------------------------------------------------------------------------------------------


def pruned_distance(s, d, g, pairs) -> DataFrame:
    """Exact answers from pruned two-hop labels of 20 landmarks: the bound by shared hubs, then the bounded search."""
    bounds = cut(query.two_hop(pairs, pruned20(s, d, g)).withColumnRenamed("d", "ub"))
    r = F.broadcast(marks_of(s, d, g).select("id"))
    free = bounds.join(r, bounds["s"] == r["id"], "left_anti").join(r, bounds["t"] == r["id"], "left_anti")
    found = search.bounded(index_of(s, d, g).core, free)
    at_root = bounds.join(free.select("pair_id"), "pair_id", "left_anti").select("pair_id", "s", "t", F.col("ub").alias("dist"))
    return found.select("pair_id", "s", "t", F.least("ub", "core_d").alias("dist")).union(at_root)


def methods(s, d, g, pairs) -> dict:
    e, r = edges_of(s, d, g), marks_of(s, d, g, K)
    return {
        "gateway": lambda: index_of(s, d, g).distance(pairs),
        "gateway_local": lambda: index_of(s, d, g).distance_local(pairs),
        "mask_hybrid": lambda: mask_hybrid.distance(e, r, masks20(s, d, g), pairs),
        "pruned_two_hop": lambda: pruned_distance(s, d, g, pairs),
        "independent_set": lambda: independent_set.distance(e, pairs),
        "bidirectional": lambda: online.bidirectional(e, pairs),
    }


def compare_answers(s, d, g) -> DataFrame:
    """(method, pair_id, dist): the exact answer of each method that has an index of landmarks."""
    out = None
    for name, f in methods(s, d, g, pairs_of(s, d, g)).items():
        if name in ("independent_set", "bidirectional"):  # minutes on these graphs: see their own queries and compare_times
            continue
        one = cut(f().select(F.lit(name).alias("method"), "pair_id", "dist"))
        out = one if out is None else out.union(one)
    return out


_NAMES = ", ".join(f"('{m}')" for m in ("gateway", "gateway_local", "mask_hybrid", "pruned_two_hop"))
for _g in ("succession",):
    register(f"compare_answers_{_g}", o.query(f"SELECT method, pair_id, dist FROM truth, (VALUES {_NAMES}) m(method)", o.edges(_g), o.pairs(n_pairs(_g)), o.truth(_g)))(
        lambda s, d, g=_g: compare_answers(s, d, g)
    )
for _g in GRAPHS:
    register(f"exact_distance_local_{_g}", o.query("SELECT pair_id, s, t, dist FROM truth", o.edges(_g), o.pairs(n_pairs(_g)), o.truth(_g)))(
        lambda s, d, g=_g: index_of(s, d, g).distance_local(pairs_of(s, d, g)).select("pair_id", "s", "t", "dist")
    )


def compare_times(s, d, g, limit: float = LIMIT) -> DataFrame:
    """(graph, step, method, status, seconds, times_gateway): building each index and answering the same pairs."""
    e, r, p = edges_of(s, d, g), marks_of(s, d, g, K), pairs_of(s, d, g)
    build = {
        "gateway": lambda: cut(gateway.build(e, r)[0]), "gateway_sequential": lambda: cut(gateway.build(e, r, "sequential")[0]), "mask_hybrid": lambda: cut(mask_hybrid.labels(e, r)),
        "pruned_two_hop": lambda: two_hop.pruned_two_hop(e, r), "independent_set": lambda: cut(independent_set.peel(e)[0]),
    }
    index_of(s, d, g), masks20(s, d, g), cut(pruned20(s, d, g))  # what is asked stands before the clock starts
    ask = {m: (lambda f=f: cut(f().select("pair_id", "dist"))) for m, f in methods(s, d, g, p).items()}
    rows = []
    for step, jobs in (("construct", build), ("query", ask)):
        took = {m: within(s, limit, f)[:2] for m, f in jobs.items()}
        rows += [(g, step, m, status, sec, metrics.ratio(sec, took["gateway"][1]) if status == "ok" else None) for m, (status, sec) in took.items()]
    return s.createDataFrame(rows, "graph string, step string, method string, status string, seconds double, times_gateway double")


for _g in ("succession", "basket"):
    register(f"compare_times_{_g}")(lambda s, d, g=_g: compare_times(s, d, g))


# the mask hybrid with 20 roots --------------------------------------------------------------------------------

for _g in ("users", "succession"):
    register(f"mask_hybrid_distance_20_{_g}", o.query("SELECT pair_id, s, t, dist FROM truth", o.edges(_g), o.pairs(n_pairs(_g)), o.truth(_g)))(
        lambda s, d, g=_g: mask_hybrid.distance(edges_of(s, d, g), marks_of(s, d, g, K), masks20(s, d, g), pairs_of(s, d, g)).drop("ub")
    )


@register("pruned_two_hop_after_50_roots")
def _pruned_masked(s, d):
    """(v, lm, d): two landmarks pruned with the help of the masks of the 50 before them."""
    e = edges_of(s, d, "users")
    order = marks_of(s, d, "users", 52)
    masks = cut(mask_hybrid.labels(e, cut(order.filter("rank < 50"))))
    return two_hop.pruned_two_hop(e, order.filter("rank >= 50"), mask_hybrid.pruning(masks))


# sweeps over the number of landmarks --------------------------------------------------------------------------

_SWEEP = f"""ks AS (SELECT unnest([{', '.join(map(str, KS))}]) AS k),
ranked_full AS (SELECT f.lm, f.v, f.d, l.rank AS lm_rank, m.rank AS v_rank FROM full_d f JOIN landmarks l ON l.id = f.lm LEFT JOIN landmarks m ON m.id = f.v),
swept AS (SELECT CAST(k AS INTEGER) AS k, count(*) AS entries FROM ks JOIN ranked_full f ON f.lm_rank < k AND (f.v_rank IS NULL OR f.v_rank >= k)
  WHERE NOT EXISTS (SELECT 1 FROM ranked_full rq JOIN full_d qv ON qv.lm = rq.v WHERE rq.lm = f.lm AND rq.v_rank < k AND rq.v <> f.lm
    AND qv.v = f.v AND rq.d + qv.d = f.d) GROUP BY k)"""
_SWEPT = ("succession",)


def swept_sizes(s, d, g) -> DataFrame:
    rows = None
    for k in KS:
        one = metrics.entries(index_of(s, d, g, k).labels).select(F.lit(k).alias("k"), "entries")
        rows = one if rows is None else rows.union(one)
    return rows


def swept_times(s, d, g, limit: float = LIMIT) -> DataFrame:
    """(method, k, status, construct_seconds, query_seconds, entries, covered, pairs): the labels from 10 to 50 landmarks, the masks at 20 beside them."""
    e, p, rows = edges_of(s, d, g), pairs_of(s, d, g), []
    for k in KS:
        r = marks_of(s, d, g, k)
        status, ct, labels = within(s, limit, lambda r=r: cut(gateway.build(e, r)[0]))
        index = index_of(s, d, g, k)
        asked, qt, found = within(s, limit, lambda index=index: cut(index.distance(p)))
        covered = metrics.coverage(found).first() if found is not None else None
        rows.append(("gateway", k, status if asked == "ok" else asked, ct, qt, labels.count() if labels is not None else None, covered["covered"] if covered else None, covered["pairs"] if covered else None))
    r = marks_of(s, d, g, K)
    status, ct, masks = within(s, limit, lambda: cut(mask_hybrid.labels(e, r)))
    asked, qt, found = within(s, limit, lambda: cut(mask_hybrid.distance(e, r, masks, p))) if masks is not None else ("DNF", None, None)
    hit = found.agg(F.sum((F.col("ub").eqNullSafe(F.col("dist")) & (F.col("s") != F.col("t")) & F.col("dist").isNotNull()).cast("long"))).first()[0] if found is not None else None
    rows.append(("mask_hybrid", K, status if asked == "ok" else asked, ct, qt, masks.count() if masks is not None else None, hit, found.count() if found is not None else None))
    return s.createDataFrame(rows, "method string, k int, status string, construct_seconds double, query_seconds double, entries long, covered long, pairs long")


for _g in _SWEPT:
    _items = _kept(*_given(_g, 50), o.full(_g), _SWEEP)
    register(f"sweep_size_{_g}", o.query("SELECT k, entries FROM swept", *_items))(lambda s, d, g=_g: swept_sizes(s, d, g))
    register(f"sweep_trend_labels_{_g}", o.query("SELECT regr_slope(CAST(entries AS DOUBLE), CAST(k AS DOUBLE)) AS slope, regr_r2(CAST(entries AS DOUBLE), CAST(k AS DOUBLE)) AS r2 FROM swept", *_items))(
        lambda s, d, g=_g: swept_sizes(s, d, g).select(F.col("k").cast("double").alias("k"), F.col("entries").cast("double").alias("e")).agg(F.regr_slope("e", "k").alias("slope"), F.regr_r2("e", "k").alias("r2"))
    )
    register(f"sweep_times_{_g}")(lambda s, d, g=_g: swept_times(s, d, g))
    register(
        f"sweep_coverage_{_g}",
        o.query(
            """SELECT CAST(k AS INTEGER) AS k, count(*) AS pairs, CAST(sum(CAST(t.s <> t.t AND ub IS NOT DISTINCT FROM t.dist AND t.dist IS NOT NULL AS INTEGER)) AS BIGINT) AS covered FROM truth t JOIN
            (SELECT k, p.pair_id, min(a.d + b.d) AS ub FROM ks CROSS JOIN pairs p LEFT JOIN ranked_full a ON a.v = p.s AND a.lm_rank < k LEFT JOIN full_d b ON b.v = p.t AND b.lm = a.lm
             GROUP BY k, p.pair_id) u ON u.pair_id = t.pair_id GROUP BY k""",
            *_items, o.pairs(n_pairs(_g)), o.truth(_g),
        ),
    )(lambda s, d, g=_g: _swept_coverage(s, d, g))


def _swept_coverage(s, d, g):
    rows = None
    for k in KS:
        one = metrics.coverage(answers_of(s, d, g, k)).select(F.lit(k).alias("k"), "pairs", "covered")
        rows = one if rows is None else rows.union(one)
    return rows


# histograms, traversal, weights -------------------------------------------------------------------------------

for _g in ("geo", "succession"):
    register(f"w_hist_{_g}", o.query("SELECT dist, count(*) AS pairs FROM truth GROUP BY dist", o.edges(_g), o.pairs(2000), o.truth(_g)))(
        lambda s, d, g=_g: metrics.distance_histogram(index_of(s, d, g).distance_local(graph.sample_pairs(edges_of(s, d, g), 2000)))
    )
for _g in ("example14", "succession"):
    register(
        f"traversed_{_g}",
        o.query(
            """SELECT lm, CAST(sum(CASE WHEN o THEN deg ELSE 0 END) AS BIGINT) AS open_edges, CAST(sum(CASE WHEN o THEN 0 ELSE deg END) AS BIGINT) AS shut_edges FROM (
            SELECT f.lm, f.v, f.d, f.v = f.lm OR x.v IS NOT NULL AS o, max(CASE WHEN x.v IS NOT NULL THEN f.d ELSE 0 END) OVER (PARTITION BY f.lm) AS far
            FROM full_d f LEFT JOIN labels x ON x.lm = f.lm AND x.v = f.v) JOIN (SELECT src, count(*) AS deg FROM edges GROUP BY src) ON src = v WHERE d <= far GROUP BY lm""",
            *_kept(*_given(_g), o.full(_g), o.GATEWAY),
        ),
    )(lambda s, d, g=_g: metrics.traversed(edges_of(s, d, g), marks_of(s, d, g)))
register(
    "weighted_relax_uneven",
    o.query("SELECT v, min(d) AS d FROM walk GROUP BY v", o.edges("geo"), "walk(v, d) AS (SELECT CAST(0 AS BIGINT), CAST(0 AS BIGINT) UNION SELECT e.dst, w.d + 1 + (e.src + e.dst) % 5 FROM walk w JOIN edges e ON e.src = w.v WHERE w.d < 30)"),
)(lambda s, d: bfs.relax(edges_of(s, d, "geo").withColumn("w", (F.lit(1) + F.pmod(F.col("src") + F.col("dst"), F.lit(5))).cast("long")), 0))


# properties, scaling, trade-off -------------------------------------------------------------------------------


def _same(a: DataFrame, b: DataFrame) -> bool:
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def _two_hop_redundant(labels: DataFrame) -> DataFrame:
    """Entries (v, lm) whose distance another shared hub of v and lm gives as well."""
    mine = labels.select("v", F.col("lm").alias("q"), F.col("d").alias("qd"))
    theirs = labels.select(F.col("v").alias("lm"), F.col("lm").alias("q"), F.col("d").alias("ld"))
    return labels.filter("v != lm").join(mine, "v").join(theirs, ["lm", "q"]).filter("q != lm and q != v and qd + ld <= d").select("v", "lm").distinct()


@register("property_matrix")
def property_matrix(s, d):
    """(method, order_dependent, two_hop_minimal, cover_minimal, landmarks_parallel), measured on one graph with 4 landmarks.

    order_dependent: the reversed order gives other labels. two_hop_minimal: no entry is given by another shared hub (NULL: the labels are not
    meant to be read by shared hubs). cover_minimal: no entry is given by the other entries and the landmark matrix. landmarks_parallel:
    each landmark's labels are the same if it is built without the labels of the others.
    """
    g, k = "users", 4
    e, r, matrix = edges_of(s, d, g), marks_of(s, d, g, k), index_of(s, d, g, k).matrix
    back = cut(lmk.reordered(r))
    ids = [x["id"] for x in r.orderBy("rank").collect()]  # k rows
    alone = lambda build: [cut(build(cut(r.filter(F.col("id") == v)))) for v in (ids[0], ids[-1])]
    tree = lambda x: x.select("v", "lm", "d")
    both = {
        "gateway": (cut(gateway.build(e, r)[0]), cut(gateway.build(e, back)[0])),
        "pruned_two_hop": (cut(two_hop.pruned_from_full(full_of(s, d, g, k), r)), cut(two_hop.pruned_from_full(full_of(s, d, g, k), back))),
        "pruned_cover": (two_hop.pruned_cover(e, r, matrix), two_hop.pruned_cover(e, back, matrix)),
        "full_table": (cut(full_table.full_table(e, r)), cut(full_table.full_table(e, back))),
        "mask_hybrid": (cut(mask_hybrid.labels(e, r)), cut(mask_hybrid.labels(e, back))),
    }
    one_by_one = {
        "gateway": [cut(gateway.build(e, r, "sequential")[0])], "pruned_two_hop": alone(lambda x: two_hop.pruned_from_full(cut(bfs.levels(e, x)), x.withColumn("rank", F.lit(0)))), "pruned_cover": alone(lambda x: two_hop.pruned_cover(e, x, matrix)),
        "full_table": alone(lambda x: full_table.full_table(e, x)), "mask_hybrid": alone(lambda x: mask_hybrid.labels(e, x)),
    }
    rows = []
    marked = F.broadcast(r.select(F.col("id").alias("v")))
    for name, (a, b) in both.items():
        columns = a.columns
        parts = one_by_one[name]
        if name == "gateway":
            parallel = _same(a, parts[0].select(*columns))
        else:
            some = a.filter(F.col("lm").isin(ids[0], ids[-1])).join(marked, "v", "left_anti").select(*columns)
            parallel = _same(some, parts[0].union(parts[1]).join(marked, "v", "left_anti").select(*columns))
        whole = tree(full_of(s, d, g, k)) if name == "full_table" else tree(a)  # hubs need their own rows
        hop = None if name in ("gateway", "pruned_cover") else _two_hop_redundant(whole).isEmpty()
        cover = verify.redundant(tree(a).join(marked, "v", "left_anti"), matrix).isEmpty()
        rows.append((name, not _same(a, b.select(*columns)), hop, cover, parallel))
    # the peeling has no landmarks: its order is that of degrees, and a level needs the one before it
    up, residual = independent_set.peel(e)
    lab = cut(independent_set.labels(up, graph.vertices(e)).select("v", F.col("anc").alias("lm"), "d"))
    flipped = graph.vertices(e).agg(F.max("id")).first()[0]
    swap = lambda c: (F.lit(flipped) - F.col(c)).alias(c)
    again = independent_set.labels(independent_set.peel(e.select(swap("src"), swap("dst")))[0], graph.vertices(e).select(swap("id"))).select(swap("v"), F.col("anc").alias("lm"), "d").select("v", swap("lm"), "d")
    rows.append(("independent_set", not _same(lab, again), _two_hop_redundant(lab).isEmpty(), None, False))
    return s.createDataFrame(rows, "method string, order_dependent boolean, two_hop_minimal boolean, cover_minimal boolean, landmarks_parallel boolean")


@register("thread_scaling")
def thread_scaling(s, d):
    """(tasks, mode, seconds): the same labels with 1, 2, 4 and 8 tasks at a time; all landmarks at once, and one after the other with 8."""
    e, r, name = edges_of(s, d, "supply"), marks_of(s, d, "supply"), "spark.sql.shuffle.partitions"
    before, rows = s.conf.get(name), []
    try:
        for n in (1, 2, 4, 8):
            s.conf.set(name, str(n))
            dealt = cut(e.coalesce(n) if n < 8 else e)
            start = time.time()
            cut(gateway.build(dealt, r)[0])
            rows.append((n, "masks", time.time() - start))
    finally:
        s.conf.set(name, before)
    start = time.time()
    cut(gateway.build(edges_of(s, d, "succession"), marks_of(s, d, "succession", 5), "sequential")[0])
    rows.append((8, "sequential_5_landmarks", time.time() - start))
    return s.createDataFrame(rows, "tasks int, mode string, seconds double")


@register("tradeoff_scales")
def tradeoff_scales(s, d):
    """(graph, n, m, method, status, entries, construct_seconds, query_ms): size, build and query time on three scales of network.

    DNF: a step took longer than the limit; what it would have given is NULL.
    """
    rows = []
    for g in ("geo", "succession", "supply"):
        e, r, p = edges_of(s, d, g), marks_of(s, d, g), pairs_of(s, d, g)
        n, m, asked = graph.vertices(e).count(), e.count() // 2, p.count()
        for name, build, ask in (
            ("gateway", lambda: cut(gateway.build(e, r)[0]), lambda x: index_of(s, d, g).distance(p)),
            ("mask_hybrid", lambda: cut(mask_hybrid.labels(e, r)), lambda x: mask_hybrid.distance(e, r, x, p)),
        ):
            status, ct, labels = within(s, LIMIT, build)
            index_of(s, d, g)
            qt = None
            if status == "ok":
                status, qt, _ = within(s, LIMIT, lambda: cut(ask(labels).select("pair_id", "dist")))
            rows.append((g, n, m, name, status, labels.count() if labels is not None else None, ct, 1000 * qt / asked if status == "ok" else None))
    return s.createDataFrame(rows, "graph string, n long, m long, method string, status string, entries long, construct_seconds double, query_ms double")


# the table function as a query --------------------------------------------------------------------------------


@register(
    "op_udtf_neighbours_sql",
    o.query("SELECT lm AS v, v AS w, d AS hops FROM r WHERE d > 0", *_given("succession"), o.reach("r", "SELECT id FROM landmarks WHERE rank < 5", "edges", 2)),
)
def _udtf(s, d):
    sources = marks_of(s, d, "succession").filter("rank < 5")
    near = cut(udfs.within_reach(edges_of(s, d, "succession"), sources, 2))
    if near.limit(udfs.MAX_EDGES + 1).count() > udfs.MAX_EDGES:  # the same rows by joins
        return udfs.neighbours_within(edges_of(s, d, "succession"), sources, 2)
    udfs.register_udtf(s, near)
    sources.createOrReplaceTempView("udtf_sources")
    return s.sql("SELECT id AS v, w, hops FROM udtf_sources, LATERAL neighbours_within(id, 2)")
