"""Registered queries of the distance engine, each with its oracle where SQL can express one."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from graphdist import datasets, oracles as o
from graphdist.baselines import full_table, independent_set, mask_hybrid, online, two_hop
from graphdist.operators import bfs, codec, components, gateway, graph, landmarks as lmk, metrics, query, search, verify
from graphdist.operators.engine import Index
from graphdist.runtime import cut, materialize

K = 20
N_PAIRS = {"basket": 40, "supply": 60, "brandhub": 60}
QUERIES: dict = {}
ORACLES: dict = {}
_BUILT: dict = {}


def n_pairs(g: str) -> int:
    return N_PAIRS.get(g, 100)


def register(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def _once(spark, key: tuple, make):
    """Graphs and indexes are shared by the parts of a query (checkpointed, so reading them again is cheap)."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _BUILT:
        _BUILT[key] = make()
    return _BUILT[key]


def edges_of(spark, sf_dir, g) -> DataFrame:
    return _once(spark, (sf_dir, g), lambda: materialize(datasets.GRAPHS[g](spark, sf_dir), "edges"))


def marks_of(spark, sf_dir, g, k=K) -> DataFrame:
    def make():
        if g == "example14":
            return lmk.explicit(spark, datasets.EXAMPLE14_LANDMARKS)
        return lmk.top_degree(edges_of(spark, sf_dir, g), k)

    return _once(spark, (sf_dir, g, "marks", k), lambda: cut(make()))


def dealt_of(spark, sf_dir, g, k=K) -> graph.Dealt:
    """The edges as the levels of all labellings of ``k`` landmarks read them."""
    ids = lambda: [r["id"] for r in marks_of(spark, sf_dir, g, k).collect()]  # noqa: E731  k rows
    return _once(spark, (sf_dir, g, "dealt", k), lambda: graph.deal(edges_of(spark, sf_dir, g), ids()))


def index_of(spark, sf_dir, g, k=K) -> Index:
    return _once(spark, (sf_dir, g, "index", k), lambda: Index.build(edges_of(spark, sf_dir, g), marks_of(spark, sf_dir, g, k), dealt=dealt_of(spark, sf_dir, g, k)))


def full_of(spark, sf_dir, g, k=K) -> DataFrame:
    return _once(spark, (sf_dir, g, "full", k), lambda: bfs.levels_by_masks(edges_of(spark, sf_dir, g), marks_of(spark, sf_dir, g, k), dealt_of(spark, sf_dir, g, k)))


def pairs_of(spark, sf_dir, g) -> DataFrame:
    return _once(spark, (sf_dir, g, "pairs"), lambda: cut(graph.sample_pairs(edges_of(spark, sf_dir, g), n_pairs(g))))


def answers_of(spark, sf_dir, g, k=K) -> DataFrame:
    return _once(spark, (sf_dir, g, "answers", k), lambda: cut(index_of(spark, sf_dir, g, k).distance(pairs_of(spark, sf_dir, g))))


def _given(g: str, k: int = K) -> tuple:
    return o.edges(g), o.landmarks(g, k)


# graphs -------------------------------------------------------------------------------------------------------

for _g in datasets.GRAPHS:
    register(f"graph_{_g}_edges", o.query("SELECT src, dst FROM edges", o.edges(_g)))(lambda s, d, g=_g: edges_of(s, d, g))
    register(
        f"graph_{_g}_stats",
        o.query(
            """SELECT count(*) AS n, CAST(sum(deg) / 2 AS BIGINT) AS m, sum(deg) / 2 / count(*) AS density, avg(deg) AS mean_deg, max(deg) AS max_deg
            FROM (SELECT src, count(*) AS deg FROM edges GROUP BY src)""",
            o.edges(_g),
        ),
    )(lambda s, d, g=_g: graph.stats(edges_of(s, d, g)))

register("graph_degree_topk", o.query("SELECT rank, id FROM landmarks", *_given("supply")))(lambda s, d: marks_of(s, d, "supply"))
register("graph_core_edges", o.query("SELECT src, dst FROM core", *_given("succession"), o.CORE))(
    lambda s, d: graph.core(edges_of(s, d, "succession"), marks_of(s, d, "succession"))
)
register("graph_induced", o.query(f"SELECT src, dst FROM edges WHERE src < {3 * datasets.UNIT} AND dst < {3 * datasets.UNIT}", o.edges("geo")))(
    lambda s, d: graph.induced(edges_of(s, d, "geo"), graph.vertices(edges_of(s, d, "geo")).filter(F.col("id") < 3 * datasets.UNIT))
)
register(
    "graph_components",
    o.query("SELECT v AS id, min(lm) AS component FROM r GROUP BY v", o.edges("web"), o.reach("r", "SELECT DISTINCT src AS id FROM edges", "edges", o.CAP["web"])),
)(lambda s, d: components.connected_components(edges_of(s, d, "web"), "src", "dst"))
register("graph_ranked_ids", o.query("SELECT rank, id FROM ranked", o.edges("users"), o.pairs(1)))(lambda s, d: graph.ranked(graph.vertices(edges_of(s, d, "users"))))
register("query_pairs", o.query("SELECT pair_id, s, t FROM pairs", o.edges("succession"), o.pairs(100)))(lambda s, d: pairs_of(s, d, "succession"))

# methods ------------------------------------------------------------------------------------------------------

METHOD_GRAPHS = ("example14", "geo", "supply", "succession", "basket", "brandhub", "users", "web")

#: Full table, labels, exact distances and all pairs of the worked example run on a graph of a given table of about its size, with as many landmarks.
READ = {"example14": ("catalog", 3)}

for _g in METHOD_GRAPHS:
    _base = (*_given(_g), o.full(_g))
    _t, _k = READ.get(_g, (_g, K))
    _read = (*_given(_t, _k), o.full(_t))
    register(f"full_table_{_g}", o.query("SELECT v, lm, d FROM full_d WHERE v NOT IN (SELECT id FROM landmarks)", *_read))(
        lambda s, d, g=_t, k=_k: full_table.full_table(edges_of(s, d, g), marks_of(s, d, g, k))
    )
    register(f"gateway_labels_{_g}", o.query("SELECT v, lm, d FROM labels", *_read, o.GATEWAY))(lambda s, d, g=_t, k=_k: index_of(s, d, g, k).labels)
    register(f"landmark_matrix_{_g}", o.query("SELECT lm_a, lm_b, d FROM matrix", *_base, o.MATRIX))(lambda s, d, g=_g: index_of(s, d, g).matrix)
    for _m in ("cross", "pruned"):
        register(f"upper_bound_{_m}_{_g}", o.query("SELECT pair_id, s, t, ub FROM bound", *_base, o.pairs(n_pairs(_g)), o.BOUND))(
            lambda s, d, g=_g, m=_m: index_of(s, d, g).upper_bound(pairs_of(s, d, g), m)
        )
    register(
        f"exact_distance_{_g}",
        o.query(
            """SELECT t.pair_id, t.s, t.t, b.ub, t.dist, (t.s <> t.t AND t.dist IS NOT NULL AND b.ub IS NOT DISTINCT FROM t.dist) AS covered
            FROM truth t JOIN bound b ON b.pair_id = t.pair_id""",
            *_read, o.pairs(n_pairs(_t)), o.BOUND, o.truth(_t),
        ),
    )(lambda s, d, g=_t, k=_k: answers_of(s, d, g, k).select("pair_id", "s", "t", "ub", "dist", "covered"))

_EX = (*_given("example14"), o.full("example14"))
_SU = (*_given("succession"), o.full("succession"))
register("gateway_seq_example", o.query("SELECT v, lm, d FROM labels", *_EX, o.GATEWAY))(
    lambda s, d: gateway.build(edges_of(s, d, "example14"), marks_of(s, d, "example14"), "sequential")[0]
)
register("gateway_rows_succession", o.query("SELECT v, lm, d FROM labels", *_SU, o.GATEWAY))(
    lambda s, d: gateway.build(edges_of(s, d, "succession"), marks_of(s, d, "succession"), "rows")[0]
)
register("gateway_from_full_succession", o.query("SELECT v, lm, d FROM labels", *_SU, o.GATEWAY))(
    lambda s, d: gateway.from_full(full_of(s, d, "succession"), marks_of(s, d, "succession"))
)
register("landmark_matrix_given", o.query("SELECT lm_a, lm_b, d FROM matrix", *_SU, o.MATRIX))(
    lambda s, d: gateway.matrix_from_full(full_of(s, d, "succession"), marks_of(s, d, "succession"))
)


@register("gateway_order_invariance", "SELECT CAST(0 AS BIGINT) AS v, CAST(0 AS BIGINT) AS lm, CAST(0 AS INTEGER) AS d WHERE false")
def _order_invariance(s, d):
    """Entries that differ when the landmarks are taken in reverse order: none."""
    e, r = edges_of(s, d, "users"), marks_of(s, d, "users")
    a, b = index_of(s, d, "users").labels, gateway.build(e, lmk.reordered(r))[0]
    b = cut(b)
    return a.exceptAll(b).union(b.exceptAll(a))


_MANY = (*_given("users", 70), o.full("users"))
register("gateway_two_words", o.query("SELECT v, lm, d FROM labels", *_MANY, o.GATEWAY))(lambda s, d: index_of(s, d, "users", 70).labels)
register(
    "constrained_distance",
    o.query(
        """SELECT p.pair_id, p.s, p.t, l.id AS r, CAST(a.d + b.d AS INTEGER) AS d FROM pairs p JOIN landmarks l ON l.rank < 3
        LEFT JOIN full_d a ON a.lm = l.id AND a.v = p.s LEFT JOIN full_d b ON b.lm = l.id AND b.v = p.t""",
        *_SU, o.pairs(100),
    ),
)(
    lambda s, d: query.constrained(
        pairs_of(s, d, "succession").join(F.broadcast(marks_of(s, d, "succession").filter("rank < 3").select(F.col("id").alias("r")))),
        index_of(s, d, "succession").labels, index_of(s, d, "succession").matrix, marks_of(s, d, "succession"),
    )
)
register("landmark_decode", o.query("SELECT lm AS r, v, d FROM full_d WHERE v NOT IN (SELECT id FROM landmarks)", *_SU))(
    lambda s, d: query.from_landmark(index_of(s, d, "succession").labels, index_of(s, d, "succession").matrix)
)
register(
    "two_hop_query",
    o.query(
        """SELECT p.pair_id, p.s, p.t, CAST(CASE WHEN p.s = p.t THEN 0 ELSE min(a.d + b.d) END AS INTEGER) AS d FROM pairs p
        LEFT JOIN labels a ON a.v = p.s LEFT JOIN labels b ON b.v = p.t AND b.lm = a.lm GROUP BY p.pair_id, p.s, p.t""",
        *_SU, o.GATEWAY, o.pairs(100),
    ),
)(lambda s, d: query.two_hop(pairs_of(s, d, "succession"), index_of(s, d, "succession").labels))
register(
    "triangle_bounds",
    o.query(
        """SELECT p.pair_id, p.s, p.t, CAST(max(abs(a.d - b.d)) AS INTEGER) AS lower, CAST(min(a.d + b.d) AS INTEGER) AS upper FROM pairs p
        LEFT JOIN full_d a ON a.v = p.s LEFT JOIN full_d b ON b.v = p.t AND b.lm = a.lm GROUP BY p.pair_id, p.s, p.t""",
        *_SU, o.pairs(100),
    ),
)(lambda s, d: query.triangle_bounds(pairs_of(s, d, "succession"), full_of(s, d, "succession")))
_CORE_TRUTH = o.reach("core_s", "SELECT DISTINCT s AS id FROM pairs", "core", o.CAP["succession"])
register(
    "core_distance_bounded",
    o.query(
        "SELECT p.pair_id, p.s, p.t, 4 AS ub, CAST(least(4, coalesce(c.d, 4)) AS INTEGER) AS value FROM pairs p LEFT JOIN core_s c ON c.lm = p.s AND c.v = p.t",
        *_given("succession"), o.CORE, o.pairs(100), _CORE_TRUTH,
    ),
)(
    lambda s, d: search.bounded_value(
        index_of(s, d, "succession").core, pairs_of(s, d, "succession").withColumn("ub", F.lit(4))
    ).select("pair_id", "s", "t", "ub", "value")
)
for _b in ("frontier", "alternate"):
    register(
        f"exact_distance_balance_{_b}", o.query("SELECT pair_id, s, t, dist FROM truth", o.edges("users"), o.pairs(100), o.truth("users"))
    )(lambda s, d, b=_b: index_of(s, d, "users").distance(pairs_of(s, d, "users"), b).select("pair_id", "s", "t", "dist"))


def _ends(s, d):
    r = marks_of(s, d, "succession")
    low = r.filter("rank < 5").select(F.col("rank").cast("long").alias("pair_id"), F.col("id").alias("s"))
    mixed = low.join(pairs_of(s, d, "succession").select("pair_id", F.col("t")), "pair_id")
    both = low.join(r.filter("rank >= 5 and rank < 10").select((F.col("rank") - 5).cast("long").alias("pair_id"), F.col("id").alias("t")), "pair_id")
    return mixed.union(both.select(F.col("pair_id") + 10, "s", "t")).union(low.select(F.col("pair_id") + 20, "s", F.col("s").alias("t")))


register(
    "exact_distance_landmark_endpoints",
    o.query(
        """SELECT pair_id, s, t, dist FROM (SELECT p.pair_id, l.id AS s, p.t FROM landmarks l JOIN pairs p ON p.pair_id = l.rank AND l.rank < 5
          UNION ALL SELECT l.rank + 10, l.id, m.id FROM landmarks l JOIN landmarks m ON m.rank = l.rank + 5 WHERE l.rank < 5
          UNION ALL SELECT rank + 20, id, id FROM landmarks WHERE rank < 5) q LEFT JOIN (SELECT lm, v, d AS dist FROM full_d) f ON f.lm = q.s AND f.v = q.t""",
        *_SU, o.pairs(100),
    ),
)(lambda s, d: index_of(s, d, "succession").distance(_ends(s, d)).select("pair_id", "s", "t", "dist"))
register("exact_distance_disconnected", o.query("SELECT pair_id, s, t, dist FROM truth", o.edges("web"), o.pairs(100), o.truth("web")))(
    lambda s, d: index_of(s, d, "web", 3).distance(pairs_of(s, d, "web")).select("pair_id", "s", "t", "dist")
)
for _bits in (8, 32):
    register(
        f"label_pack_{_bits}",
        o.query(
            f"""SELECT v, count(*) AS n_entries, string_agg(upper(lpad(format('{{:x}}', rank), {_bits // 4}, '0')) || upper(lpad(format('{{:x}}', d), 2, '0')), '' ORDER BY rank) AS bytes_hex
            FROM labels JOIN landmarks ON id = lm GROUP BY v""",
            *_SU, o.GATEWAY,
        ),
    )(lambda s, d, b=_bits: codec.pack(index_of(s, d, "succession").labels, marks_of(s, d, "succession"), b).select("v", "n_entries", F.hex("bytes").alias("bytes_hex")))
register("label_unpack", o.query("SELECT v, lm, d FROM labels", *_SU, o.GATEWAY))(
    lambda s, d: codec.unpack(codec.pack(index_of(s, d, "succession").labels, marks_of(s, d, "succession")), marks_of(s, d, "succession"))
)
register("cover_violations", "SELECT CAST(0 AS BIGINT) AS r, CAST(0 AS BIGINT) AS v, CAST(0 AS INTEGER) AS d, CAST(0 AS INTEGER) AS decoded WHERE false")(
    lambda s, d: verify.cover(index_of(s, d, "succession").labels, index_of(s, d, "succession").matrix, full_of(s, d, "succession"), marks_of(s, d, "succession"))
)
register("redundant_entries", "SELECT CAST(0 AS BIGINT) AS v, CAST(0 AS BIGINT) AS lm, CAST(0 AS INTEGER) AS d WHERE false")(
    lambda s, d: verify.redundant(index_of(s, d, "succession").labels, index_of(s, d, "succession").matrix)
)

# baselines ----------------------------------------------------------------------------------------------------

_PRUNED = """pruned AS (SELECT f.v, f.lm, f.d FROM full_d f JOIN landmarks i ON i.id = f.lm WHERE NOT EXISTS (
  SELECT 1 FROM landmarks j JOIN full_d qr ON qr.lm = j.id AND qr.v = f.lm JOIN full_d qv ON qv.lm = j.id AND qv.v = f.v
  WHERE j.rank < i.rank AND qr.d + qv.d <= f.d))"""
_REV = _PRUNED.replace("j.rank < i.rank", "j.rank > i.rank")
_SMALL = 8
for _g, _k in (("example14", K), ("users", _SMALL)):
    _base = (*_given(_g, _k), o.full(_g))
    register(f"pruned_two_hop_{_g}", o.query("SELECT v, lm, d FROM pruned", *_base, _PRUNED))(
        lambda s, d, g=_g, k=_k: two_hop.pruned_two_hop(edges_of(s, d, g), marks_of(s, d, g, k))
    )
    register(f"pruned_two_hop_reversed_{_g}", o.query("SELECT v, lm, d FROM pruned", *_base, _REV))(
        lambda s, d, g=_g, k=_k: two_hop.pruned_two_hop(edges_of(s, d, g), lmk.reordered(marks_of(s, d, g, k)))
    )
    register(f"pruned_cover_{_g}", o.query("SELECT v, lm, d FROM pruned WHERE v NOT IN (SELECT id FROM landmarks)", *_base, _PRUNED))(
        lambda s, d, g=_g, k=_k: two_hop.pruned_cover(edges_of(s, d, g), marks_of(s, d, g, k), index_of(s, d, g, k).matrix)
    )
register("pruned_from_full_succession", o.query("SELECT v, lm, d FROM pruned", *_SU, _PRUNED))(
    lambda s, d: two_hop.pruned_from_full(full_of(s, d, "succession"), marks_of(s, d, "succession"))
)
register("pruned_two_hop_complete", o.query("SELECT p.pair_id, p.s, p.t, p.dist AS d FROM truth p", o.edges("example14"), o.pairs(100), o.truth("example14")))(
    lambda s, d: query.two_hop(pairs_of(s, d, "example14"), cut(two_hop.complete(edges_of(s, d, "example14"))))
)
_ROOTS = 5
_CHOSEN = """deg AS (SELECT src AS id, count(*) AS deg FROM edges GROUP BY src),
chosen AS (SELECT lm, u, row_number() OVER (PARTITION BY lm ORDER BY deg DESC, u) - 1 AS bit FROM (
  SELECT arg_min(l.id, l.rank) AS lm, e.dst AS u FROM landmarks l JOIN edges e ON e.src = l.id WHERE e.dst NOT IN (SELECT id FROM landmarks) GROUP BY e.dst)
  JOIN deg ON id = u)"""
_MASKS = """masks AS (SELECT f.lm, f.v, f.d,
  CAST(coalesce(sum(CASE WHEN n.d = f.d - 1 THEN CAST(1 AS BIGINT) << c.bit ELSE 0 END), 0) AS BIGINT) AS m1,
  CAST(coalesce(sum(CASE WHEN n.d = f.d AND f.d > 0 THEN CAST(1 AS BIGINT) << c.bit ELSE 0 END), 0) AS BIGINT) AS m0
  FROM full_d f LEFT JOIN chosen c ON c.lm = f.lm LEFT JOIN near n ON n.lm = c.u AND n.v = f.v GROUP BY f.lm, f.v, f.d)"""
_MASK_ITEMS = (*_given("users", _ROOTS), o.full("users"), _CHOSEN, o.reach("near", "SELECT u AS id FROM chosen", "edges", o.CAP["users"]), _MASKS)


def masks_of(s, d):
    return _once(s, (d, "masks"), lambda: cut(mask_hybrid.labels(edges_of(s, d, "users"), marks_of(s, d, "users", _ROOTS))))


register("mask_labels", o.query("SELECT lm, v, d, m1, m0 FROM masks", *_MASK_ITEMS))(masks_of)
register(
    "mask_bound",
    o.query(
        """SELECT p.pair_id, p.s, p.t, CAST(CASE WHEN p.s = p.t THEN 0 ELSE min(a.d + b.d - CASE WHEN (a.m1 & b.m1) <> 0 THEN 2
          WHEN (a.m1 & b.m0) <> 0 OR (a.m0 & b.m1) <> 0 THEN 1 ELSE 0 END) END AS INTEGER) AS ub
        FROM pairs p LEFT JOIN masks a ON a.v = p.s LEFT JOIN masks b ON b.v = p.t AND b.lm = a.lm GROUP BY p.pair_id, p.s, p.t""",
        *_MASK_ITEMS, o.pairs(100),
    ),
)(lambda s, d: mask_hybrid.upper_bound(pairs_of(s, d, "users"), masks_of(s, d)))
_TRUTH_USERS = o.query("SELECT pair_id, s, t, dist FROM truth", o.edges("users"), o.pairs(100), o.truth("users"))
register("mask_hybrid_distance", _TRUTH_USERS)(
    lambda s, d: mask_hybrid.distance(edges_of(s, d, "users"), marks_of(s, d, "users", _ROOTS), masks_of(s, d), pairs_of(s, d, "users")).drop("ub")
)
for _g in ("geo", "users"):
    _t = o.query("SELECT pair_id, s, t, dist FROM truth", o.edges(_g), o.pairs(n_pairs(_g)), o.truth(_g))
    register(f"bibfs_distance_{_g}", _t)(lambda s, d, g=_g: online.bidirectional(edges_of(s, d, g), pairs_of(s, d, g)))
    register(f"bfs_distance_{_g}", _t)(lambda s, d, g=_g: online.one_sided(edges_of(s, d, g), pairs_of(s, d, g)))
    register(f"independent_set_distance_{_g}", _t)(lambda s, d, g=_g: independent_set.distance(edges_of(s, d, g), pairs_of(s, d, g)))
register(
    "all_pairs_example",
    o.query("SELECT lm AS s, v AS t, d AS dist FROM r", o.edges("catalog"), o.reach("r", "SELECT DISTINCT src AS id FROM edges", "edges", o.CAP["catalog"])),
)(lambda s, d: full_table.all_pairs(edges_of(s, d, "catalog")))
register(
    "weighted_relax", o.query("SELECT v, CAST(d AS BIGINT) AS d FROM r", o.edges("geo"), o.reach("r", "SELECT CAST(0 AS BIGINT) AS id", "edges", 8))
)(lambda s, d: bfs.relax(edges_of(s, d, "geo").withColumn("w", F.lit(1)), 0))

# measures -----------------------------------------------------------------------------------------------------

_SU_L = (*_SU, o.GATEWAY)
_SU_A = (*_SU, o.pairs(100), o.BOUND, o.truth("succession"))
_COUNTS = "(SELECT count(*) FROM labels) AS entries, (SELECT count(DISTINCT src) FROM edges) - (SELECT count(*) FROM landmarks) AS labelled"
register("als", o.query(f"SELECT entries, labelled, entries / labelled AS als FROM (SELECT {_COUNTS})", *_SU_L))(
    lambda s, d: metrics.als(index_of(s, d, "succession").labels, edges_of(s, d, "succession"), marks_of(s, d, "succession"))
)
register("index_bytes", o.query("SELECT count(*) AS entries, count(*) * 2 AS bytes_8, count(*) * 5 AS bytes_32 FROM labels", *_SU_L))(
    lambda s, d: metrics.index_bytes(index_of(s, d, "succession").labels)
)
register(
    "index_ratio",
    o.query(
        """SELECT e AS entries, e * 2 AS bytes_8, e * 5 AS bytes_32, g AS graph_bytes, e * 2 / g AS ratio_8, e * 5 / g AS ratio_32
        FROM (SELECT (SELECT count(*) FROM labels) AS e, (SELECT CAST(count(*) / 2 * 8 AS BIGINT) FROM edges) AS g)""",
        *_SU_L,
    ),
)(lambda s, d: metrics.index_ratio(index_of(s, d, "succession").labels, edges_of(s, d, "succession")))
_COVERED = "(t.s <> t.t AND t.dist IS NOT NULL AND b.ub IS NOT DISTINCT FROM t.dist)"
for _g in ("geo", "succession", "supply"):
    register(
        f"coverage_{_g}",
        o.query(
            f"""SELECT count(*) AS pairs, CAST(sum(CAST({_COVERED} AS INTEGER)) AS BIGINT) AS covered, avg(CAST({_COVERED} AS INTEGER)) AS coverage
            FROM truth t JOIN bound b ON b.pair_id = t.pair_id""",
            *_given(_g), o.full(_g), o.pairs(n_pairs(_g)), o.BOUND, o.truth(_g),
        ),
    )(lambda s, d, g=_g: metrics.coverage(answers_of(s, d, g)).drop("searched_to_bound"))
    register(f"distance_histogram_{_g}", o.query("SELECT dist, count(*) AS pairs FROM truth GROUP BY dist", o.edges(_g), o.pairs(n_pairs(_g)), o.truth(_g)))(
        lambda s, d, g=_g: metrics.distance_histogram(answers_of(s, d, g))
    )
register(
    "bound_gap",
    o.query("SELECT b.ub - t.dist AS gap, count(*) AS pairs FROM truth t JOIN bound b ON b.pair_id = t.pair_id WHERE t.dist IS NOT NULL GROUP BY 1", *_SU_A),
)(lambda s, d: metrics.bound_gap(answers_of(s, d, "succession")))
register(
    "edges_traversed",
    o.query(
        """SELECT lm, CAST(sum(deg) AS BIGINT) AS edges FROM (SELECT lm, v FROM labels UNION ALL SELECT id, id FROM landmarks)
        JOIN (SELECT src, count(*) AS deg FROM edges GROUP BY src) ON src = v GROUP BY lm""",
        *_SU_L,
    ),
)(lambda s, d: metrics.edges_traversed(edges_of(s, d, "succession"), marks_of(s, d, "succession"), index_of(s, d, "succession").labels))

KS = (10, 20, 30, 40, 50)
_SWEEP = f"""ks AS (SELECT unnest([{', '.join(map(str, KS))}]) AS k),
ranked_full AS (SELECT f.lm, f.v, f.d, l.rank AS lm_rank, m.rank AS v_rank FROM full_d f JOIN landmarks l ON l.id = f.lm LEFT JOIN landmarks m ON m.id = f.v)"""


@register(
    "sweep_size",
    o.query(
        """SELECT CAST(k AS INTEGER) AS k, count(*) AS entries FROM ks JOIN ranked_full f ON f.lm_rank < k AND (f.v_rank IS NULL OR f.v_rank >= k)
        WHERE NOT EXISTS (SELECT 1 FROM ranked_full rq JOIN full_d qv ON qv.lm = rq.v WHERE rq.lm = f.lm AND rq.v_rank < k AND rq.v <> f.lm
          AND qv.v = f.v AND rq.d + qv.d = f.d) GROUP BY k""",
        *_given("users", 50), o.full("users"), _SWEEP,
    ),
)
def _sweep_size(s, d):
    rows = None
    for k in KS:
        one = metrics.entries(index_of(s, d, "users", k).labels).select(F.lit(k).alias("k"), "entries")
        rows = one if rows is None else rows.union(one)
    return rows


@register(
    "sweep_coverage",
    o.query(
        """SELECT CAST(k AS INTEGER) AS k, count(*) AS pairs, CAST(sum(CAST(t.s <> t.t AND ub IS NOT DISTINCT FROM t.dist AND t.dist IS NOT NULL AS INTEGER)) AS BIGINT) AS covered FROM truth t JOIN
        (SELECT k, p.pair_id, min(a.d + b.d) AS ub FROM ks CROSS JOIN pairs p LEFT JOIN ranked_full a ON a.v = p.s AND a.lm_rank < k LEFT JOIN full_d b ON b.v = p.t AND b.lm = a.lm
         GROUP BY k, p.pair_id) u ON u.pair_id = t.pair_id GROUP BY k""",
        *_given("users", 50), o.full("users"), _SWEEP, o.pairs(100), o.truth("users"),
    ),
)
def _sweep_coverage(s, d):
    rows = None
    for k in KS:
        one = metrics.coverage(answers_of(s, d, "users", k)).select(F.lit(k).alias("k"), "pairs", "covered")
        rows = one if rows is None else rows.union(one)
    return rows


def _methods(s, d):
    """(method, kind, lm): every label entry of three methods on one graph."""
    parts = {
        "gateway": index_of(s, d, "succession").labels,
        "pruned": two_hop.pruned_from_full(full_of(s, d, "succession"), marks_of(s, d, "succession")),
        "full": full_of(s, d, "succession").select("v", "lm", "d"),
    }
    out = None
    for name, x in parts.items():
        one = x.join(F.broadcast(marks_of(s, d, "succession").select(F.col("id").alias("v"))), "v", "left_anti").select(F.lit(name).alias("method"), "lm", "d")
        out = one if out is None else out.union(one)
    return out


_METHODS = """methods AS (SELECT 'gateway' AS method, v, lm, d FROM labels UNION ALL SELECT 'pruned', v, lm, d FROM pruned UNION ALL SELECT 'full', v, lm, d FROM full_d),
entries AS (SELECT method, lm, d FROM methods WHERE v NOT IN (SELECT id FROM landmarks))"""
_M = (*_SU_L, _PRUNED, _METHODS)
register(
    "method_size_pivot",
    o.query(
        """SELECT d, count(*) FILTER (method = 'full') AS "full", count(*) FILTER (method = 'gateway') AS gateway, count(*) FILTER (method = 'pruned') AS pruned FROM entries GROUP BY d""", *_M
    ),
)(lambda s, d: _methods(s, d).groupBy("d").pivot("method", ["full", "gateway", "pruned"]).count().na.fill(0))
register("size_rollup", o.query("SELECT method, d, count(*) AS entries FROM entries GROUP BY ROLLUP (method, d)", *_M))(
    lambda s, d: _methods(s, d).rollup("method", "d").agg(F.count("*").alias("entries"))
)


@register("tradeoff")
def _tradeoff(s, d):
    """(graph, n, m, entries, seconds to build): size and build time against network size."""
    import time

    rows = []
    for g in ("geo", "users", "succession"):
        e, r = edges_of(s, d, g), marks_of(s, d, g)
        start = time.time()
        labels = cut(gateway.build(e, r)[0])
        rows.append((g, graph.vertices(e).count(), e.count() // 2, labels.count(), time.time() - start))
    return s.createDataFrame(rows, "graph string, n long, m long, entries long, seconds double")


# applications -------------------------------------------------------------------------------------------------

register(
    "context_rank_topk",
    o.query(
        f"""SELECT v AS page, d, r FROM (SELECT v, d, row_number() OVER (ORDER BY d, v) AS r FROM
        (SELECT v, CAST(min(d) AS INTEGER) AS d FROM near GROUP BY v) WHERE d > 0 AND v < {10 * datasets.UNIT}) WHERE r <= 10""",
        o.edges("web"), o.reach("near", "SELECT id FROM (SELECT DISTINCT src AS id FROM edges ORDER BY id LIMIT 3)", "edges", o.CAP["web"]),
    ),
)(lambda s, d: _context_rank(s, d))


def _context_rank(s, d):
    """The ten pages nearest to the three visited ones."""
    from pyspark.sql import Window

    e = edges_of(s, d, "web")
    visited = graph.vertices(e).orderBy("id").limit(3)
    near = bfs.levels(e, visited).groupBy("v").agg(F.min("d").alias("d")).filter((F.col("d") > 0) & (F.col("v") < 10 * datasets.UNIT))
    top = near.orderBy("d", "v").limit(10)
    return top.select(F.col("v").alias("page"), "d", F.row_number().over(Window.orderBy("d", "v")).cast("long").alias("r"))


register(
    "closeness",
    o.query("SELECT lm AS id, count(*) - 1 AS reached, CAST(sum(d) AS BIGINT) AS total FROM full_d GROUP BY lm", *_given("users", 10), o.full("users")),
)(lambda s, d: full_of(s, d, "users", 10).groupBy(F.col("lm").alias("id")).agg((F.count("*") - 1).alias("reached"), F.sum("d").alias("total")))


def _reading(f):
    """``f`` reads its tables itself: what an earlier query built may be of tables that have changed since."""

    def run(spark, sf_dir):
        _BUILT.clear()
        return f(spark, sf_dir)

    return run


def queries():
    from graphdist import comparison, experiments, relational

    return {name: _reading(f) for name, f in (QUERIES | experiments.QUERIES | relational.QUERIES | comparison.QUERIES).items()}


def oracle_sql():
    from graphdist import comparison, experiments, relational

    return ORACLES | experiments.ORACLES | relational.ORACLES | comparison.ORACLES
