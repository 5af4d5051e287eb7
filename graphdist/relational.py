"""Operators around the methods, one query each on the given tables, with their oracles."""

from __future__ import annotations

import os
import uuid

from pyspark.sql import DataFrame, Window, functions as F

from graphdist import datasets, oracles as o
from graphdist.functions import udfs
from graphdist.operators import graph, temporal
from graphdist.runtime import checkpoint_dir, table
from graphdist.sources import edge_lists
from graphdist.streaming import batch_twins

QUERIES: dict = {}
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


def _labels(s, d, g="succession") -> DataFrame:
    return _w().index_of(s, d, g).labels


_SU = (o.edges("succession"), o.landmarks("succession", 20), o.full("succession"), o.GATEWAY)

register("op_scan_project_filter", "SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_returnflag = 'R' AND l_quantity > 45")(
    lambda s, d: table(s, d, "lineitem").filter("l_returnflag = 'R' and l_quantity > 45").select("l_orderkey", "l_partkey", "l_quantity")
)


def _roundtrip(kind: str):
    def run(s, d):
        path = os.path.join(checkpoint_dir(s), f"edges-{kind}-{uuid.uuid4().hex}")
        edge_lists.write(_w().edges_of(s, d, "geo"), path, kind)
        return edge_lists.read(s, path, kind)

    return run


for _kind in ("csv", "json", "text", "parquet", "orc"):
    register(f"op_{_kind}_edges_roundtrip", o.query("SELECT src, dst FROM edges", o.edges("geo")))(_roundtrip(_kind))

register("op_json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events WHERE event_type = 'purchase'")(
    lambda s, d: table(s, d, "events").filter("event_type = 'purchase'").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
)
register("op_html_links", """SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS target FROM pages""")(lambda s, d: datasets.page_links(s, d))
register("op_url_host", "SELECT regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, count(*) AS pages FROM pages GROUP BY 1")(
    lambda s, d: table(s, d, "pages").groupBy(F.regexp_extract("url", "^[a-z]+://([^/?#]*)", 1).alias("host")).agg(F.count("*").alias("pages"))
)
_JOIN = "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON c_custkey = o_custkey WHERE o_orderstatus = 'F'"
for _name, _hint in (("broadcast", "broadcast"), ("sort_merge", "merge"), ("shuffle_hash", "shuffle_hash")):
    register(f"op_join_{_name}", _JOIN)(
        lambda s, d, h=_hint: table(s, d, "orders").filter("o_orderstatus = 'F'")
        .join(table(s, d, "customer").hint(h), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment")
    )
register("op_join_left", o.query("SELECT v.id, count(l.lm) AS entries FROM (SELECT DISTINCT src AS id FROM edges) v LEFT JOIN labels l ON l.v = v.id GROUP BY v.id", *_SU))(
    lambda s, d: graph.vertices(_w().edges_of(s, d, "succession")).join(_labels(s, d), F.col("id") == F.col("v"), "left").groupBy("id").agg(F.count("lm").alias("entries"))
)
register("op_join_full", "SELECT c_custkey, o_custkey FROM customer FULL OUTER JOIN (SELECT DISTINCT o_custkey FROM orders WHERE o_totalprice > 200000) ON c_custkey = o_custkey")(
    lambda s, d: table(s, d, "customer").select("c_custkey")
    .join(table(s, d, "orders").filter("o_totalprice > 200000").select("o_custkey").distinct(), F.col("c_custkey") == F.col("o_custkey"), "full_outer")
)
register("op_semi_orders", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")(
    lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")
)
register("op_anti_orders", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")(
    lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")
)
register(
    "op_theta_dominated",
    o.query("SELECT DISTINCT f.v, f.lm FROM full_d f JOIN full_d g ON g.v = f.v AND g.lm <> f.lm JOIN full_d m ON m.lm = f.lm AND m.v = g.lm WHERE m.d + g.d <= f.d", *_SU),
)(lambda s, d: _dominated(s, d))


def _dominated(s, d):
    f = _w().full_of(s, d, "succession")
    m = F.broadcast(_w().index_of(s, d, "succession").matrix.select(F.col("lm_a").alias("lm"), F.col("lm_b").alias("q"), F.col("d").alias("dm")))
    g = f.select(F.col("lm").alias("q"), "v", F.col("d").alias("qd"))
    return f.join(m, "lm").join(g, ["v", "q"]).filter("q != lm and dm + qd <= d").select("v", "lm").distinct()


register("op_cross_landmarks", o.query("SELECT a.id AS lm_a, b.id AS lm_b FROM landmarks a, landmarks b", *_SU[:2]))(
    lambda s, d: _w().marks_of(s, d, "succession").select(F.col("id").alias("lm_a")).crossJoin(F.broadcast(_w().marks_of(s, d, "succession").select(F.col("id").alias("lm_b"))))
)
_BANDS = ((0, 2, "low"), (3, 5, "middle"), (6, 10**9, "high"))
_BAND_SQL = "(VALUES " + ", ".join(f"({a}, {b}, '{c}')" for a, b, c in _BANDS) + ") t(lo, hi, band)"
register("op_range_degree_band", o.query(f"SELECT id, band FROM (SELECT src AS id, count(*) AS deg FROM edges GROUP BY src) JOIN {_BAND_SQL} ON deg BETWEEN lo AND hi", o.edges("succession")))(
    lambda s, d: graph.degrees(_w().edges_of(s, d, "succession"))
    .join(F.broadcast(s.createDataFrame(list(_BANDS), "lo long, hi long, band string")), F.col("deg").between(F.col("lo"), F.col("hi"))).select("id", "band")
)
register(
    "op_interval_events",
    """SELECT e.event_id AS error_id, p.event_id AS purchase_id FROM events e JOIN events p ON p.user_id = e.user_id AND p.event_type = 'purchase'
    AND p.ts > e.ts AND p.ts <= e.ts + INTERVAL 1 HOUR WHERE e.event_type = 'error'""",
)(
    lambda s, d: temporal.interval_join(
        table(s, d, "events").filter("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", "ts"),
        table(s, d, "events").filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "ts"), "user_id", "ts", 3600,
    ).select("error_id", "purchase_id")
)
register(
    "op_asof_events",
    """SELECT p.event_id, (SELECT arg_max(v.event_id, (v.ts, v.event_id)) FROM events v WHERE v.event_type = 'view' AND v.user_id = p.user_id AND v.ts <= p.ts) AS view_id
    FROM events p WHERE p.event_type = 'purchase'""",
)(
    lambda s, d: temporal.as_of(
        table(s, d, "events").filter("event_type = 'purchase'").select("event_id", "user_id", "ts"),
        table(s, d, "events").filter("event_type = 'view'").select(F.col("event_id").alias("view_id"), "user_id", "ts"), "user_id", "ts", "view_id",
    ).select("event_id", "view_id")
)
register("op_agg_hash", o.query("SELECT src AS id, count(*) AS deg FROM edges GROUP BY src", o.edges("basket")))(lambda s, d: graph.degrees(_w().edges_of(s, d, "basket")))
register("op_agg_distinct", "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY l_suppkey")(
    lambda s, d: table(s, d, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders"))
)


@register("op_agg_approx_degree")
def _approx(s, d):
    return table(s, d, "lineitem").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


_RANKED = "SELECT l.v, m.rank, l.d FROM labels l JOIN landmarks m ON m.id = l.lm"
register("op_agg_bitor", o.query(f"SELECT v, bit_or(CAST(1 AS BIGINT) << rank) AS mask, bit_count(bit_or(CAST(1 AS BIGINT) << rank)) AS entries FROM ({_RANKED}) GROUP BY v", *_SU))(
    lambda s, d: _ranked(s, d).groupBy("v").agg(F.bit_or(F.expr("shiftleft(1L, rank)")).alias("mask")).withColumn("entries", F.bit_count("mask"))
)


def _ranked(s, d):
    return _labels(s, d).join(F.broadcast(_w().marks_of(s, d, "succession").withColumnRenamed("id", "lm")), "lm").select("v", "rank", "d")


_SETS = f"SELECT {{cols}}, count(*) AS entries FROM ({_RANKED}) GROUP BY {{how}}"
register("op_rollup", o.query(_SETS.format(cols="rank, d", how="ROLLUP (rank, d)"), *_SU))(lambda s, d: _ranked(s, d).rollup("rank", "d").agg(F.count("*").alias("entries")))
register("op_cube", o.query(_SETS.format(cols="rank, d", how="CUBE (rank, d)"), *_SU))(lambda s, d: _ranked(s, d).cube("rank", "d").agg(F.count("*").alias("entries")))


@register("op_grouping_sets", o.query(_SETS.format(cols="rank, d, grouping(rank) * 2 + grouping(d) AS gid", how="GROUPING SETS ((rank), (d))"), *_SU))
def _grouping_sets(s, d):
    _ranked(s, d).createOrReplaceTempView("ranked_labels")
    return s.sql("SELECT rank, d, grouping_id() AS gid, count(*) AS entries FROM ranked_labels GROUP BY GROUPING SETS ((rank), (d))")


register(
    "op_pivot_distance",
    o.query("SELECT rank, " + ", ".join(f"count(*) FILTER (d = {x}) AS d{x}" for x in range(1, 6)) + f" FROM ({_RANKED}) GROUP BY rank", *_SU),
)(lambda s, d: _ranked(s, d).groupBy("rank").pivot("d", list(range(1, 6))).count().na.fill(0).select("rank", *[F.col(f"`{x}`").alias(f"d{x}") for x in range(1, 6)]))

_DEG = f"SELECT src AS id, src // {datasets.UNIT} AS kind, count(*) AS deg FROM edges GROUP BY src"


def _kinds(s, d):
    return graph.degrees(_w().edges_of(s, d, "geo")).withColumn("kind", F.expr(f"id div {datasets.UNIT}L"))


for _f in ("rank", "dense_rank"):
    register(f"op_win_{_f}", o.query(f"SELECT id, kind, deg, {_f}() OVER (PARTITION BY kind ORDER BY deg DESC) AS r FROM ({_DEG})", o.edges("geo")))(
        lambda s, d, f=_f: _kinds(s, d).select("id", "kind", "deg", getattr(F, f)().over(Window.partitionBy("kind").orderBy(F.desc("deg"))).cast("long").alias("r"))
    )
register("op_win_ntile", o.query(f"SELECT id, kind, ntile(4) OVER (PARTITION BY kind ORDER BY deg DESC, id) AS r FROM ({_DEG})", o.edges("geo")))(
    lambda s, d: _kinds(s, d).select("id", "kind", F.ntile(4).over(Window.partitionBy("kind").orderBy(F.desc("deg"), "id")).cast("long").alias("r"))
)
register(
    "op_win_lag_lead",
    """SELECT event_id, lag(user_id) OVER w AS before, lead(user_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id)""",
)(
    lambda s, d: table(s, d, "events").select(
        "event_id", F.lag("user_id").over(Window.partitionBy("event_type").orderBy("ts", "event_id")).alias("before"),
        F.lead("user_id").over(Window.partitionBy("event_type").orderBy("ts", "event_id")).alias("after"),
    )
)
register("op_win_running", o.query(f"SELECT d, CAST(sum(count(*)) OVER (ORDER BY d) AS BIGINT) AS entries FROM ({_RANKED}) GROUP BY d", *_SU))(
    lambda s, d: _ranked(s, d).groupBy("d").agg(F.count("*").alias("c")).select("d", F.sum("c").over(Window.orderBy("d").rowsBetween(Window.unboundedPreceding, 0)).alias("entries"))
)
register(
    "op_win_range",
    """SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(date_trunc('second', ts)) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS recent FROM events""",
)(
    lambda s, d: table(s, d, "events").withColumn("sec", F.unix_timestamp("ts")).select(
        "event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("sec").rangeBetween(-3600, 0)).alias("recent")
    )
)
register("op_topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")(
    lambda s, d: table(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")
)
register("op_topk_per_group", o.query(f"SELECT v, rank, d FROM (SELECT *, row_number() OVER (PARTITION BY v ORDER BY d, rank) AS r FROM ({_RANKED})) WHERE r <= 3", *_SU))(
    lambda s, d: _ranked(s, d).withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy("d", "rank"))).filter("r <= 3").select("v", "rank", "d")
)
_C = "SELECT c_nationkey AS n FROM customer WHERE c_acctbal > 9000"
_S = "SELECT s_nationkey AS n FROM supplier"
for _name, _op, _how in (("union", "UNION ALL", "unionAll"), ("intersect", "INTERSECT", "intersect"), ("intersect_all", "INTERSECT ALL", "intersectAll"), ("except", "EXCEPT", "subtract"), ("except_all", "EXCEPT ALL", "exceptAll")):
    register(f"op_{_name}", f"{_C} {_op} {_S}")(
        lambda s, d, h=_how: getattr(table(s, d, "customer").filter("c_acctbal > 9000").select(F.col("c_nationkey").alias("n")), h)(table(s, d, "supplier").select(F.col("s_nationkey").alias("n")))
    )
register("op_dedup", "SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")(lambda s, d: table(s, d, "lineitem").select("l_partkey", "l_suppkey").dropDuplicates())
register("op_array_label", o.query("SELECT v, count(*) AS entries, min(d) AS nearest, sum(d) AS total FROM labels GROUP BY v", *_SU))(
    lambda s, d: _labels(s, d).groupBy("v").agg(F.collect_list("d").alias("ds"))
    .select("v", F.size("ds").cast("long").alias("entries"), F.array_min("ds").alias("nearest"), F.aggregate("ds", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))
)
register("op_map_label", o.query("SELECT v, max(d) AS farthest FROM labels GROUP BY v", *_SU))(
    lambda s, d: _labels(s, d).groupBy("v").agg(F.map_from_entries(F.collect_list(F.struct("lm", "d"))).alias("m")).select("v", F.array_max(F.map_values("m")).alias("farthest"))
)
register("op_string_id", "SELECT c_custkey, 'customer:' || lpad(CAST(c_custkey AS VARCHAR), 9, '0') AS name, split_part(c_name, '#', 2) AS tail FROM customer")(
    lambda s, d: table(s, d, "customer").select("c_custkey", F.concat(F.lit("customer:"), F.lpad(F.col("c_custkey").cast("string"), 9, "0")).alias("name"), F.split_part("c_name", F.lit("#"), F.lit(2)).alias("tail"))
)
register("op_date_edges", "SELECT CAST(date_trunc('month', o_orderdate) AS DATE) AS month, count(*) AS orders FROM orders GROUP BY 1")(
    lambda s, d: table(s, d, "orders").groupBy(F.date_trunc("month", "o_orderdate").cast("date").alias("month")).agg(F.count("*").alias("orders"))
)
register("op_bit_masks", "SELECT l_orderkey, l_linenumber, xor(l_partkey & 255, l_suppkey | 3) AS x, bit_count(l_partkey) AS ones FROM lineitem WHERE l_linenumber = 2")(
    lambda s, d: table(s, d, "lineitem").filter("l_linenumber = 2").select(
        "l_orderkey", "l_linenumber", F.col("l_partkey").bitwiseAND(F.lit(255)).bitwiseXOR(F.col("l_suppkey").bitwiseOR(F.lit(3))).alias("x"), F.bit_count("l_partkey").alias("ones")
    )
)
register("op_decimal_price", "SELECT l_partkey, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS VARCHAR) AS price FROM lineitem GROUP BY l_partkey")(
    lambda s, d: table(s, d, "lineitem").groupBy("l_partkey").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("string").alias("price"))
)
_BOUND = o.query("SELECT pair_id, s, t, ub FROM bound", *_SU[:3], o.pairs(100), o.BOUND)
register("op_udf_pandas_bound", _BOUND)(
    lambda s, d: udfs.bound_by_pandas(_w().pairs_of(s, d, "succession"), _labels(s, d), _w().index_of(s, d, "succession").matrix, _w().marks_of(s, d, "succession"))
)
register(
    "op_udaf_component",
    o.query(
        """SELECT least(lm, v) AS s, greatest(lm, v) AS t, d AS dist FROM r WHERE lm < v""", o.edges("conv_paths"),
        o.reach("r", "SELECT DISTINCT src AS id FROM edges", "edges", o.CAP["conv_paths"]),
    ),
)(lambda s, d: udfs.component_distances(_w().edges_of(s, d, "conv_paths")))
register(
    "op_udtf_neighbours",
    o.query("SELECT lm AS v, v AS w, d AS hops FROM r WHERE d > 0", *_SU[:2], o.reach("r", "SELECT id FROM landmarks WHERE rank < 5", "edges", 2)),
)(lambda s, d: udfs.neighbours_within(_w().edges_of(s, d, "succession"), _w().marks_of(s, d, "succession").filter("rank < 5"), 2))
register("op_stream_tumbling", batch_twins.SQL["tumbling"])(lambda s, d: batch_twins.tumbling(table(s, d, "events")))
register("op_stream_sliding", batch_twins.SQL["sliding"])(lambda s, d: batch_twins.sliding(table(s, d, "events")))
register("op_stream_session", batch_twins.SQL["session"])(lambda s, d: batch_twins.session(table(s, d, "events")))
