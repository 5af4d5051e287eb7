"""Oracle SQL: the same answers by other means (closed forms and recursive queries on the raw tables).

Depth caps bound the recursions; each is above the largest distance of its graph at the test size.
"""

from __future__ import annotations

from graphdist.datasets import EXAMPLE14, EXAMPLE14_LANDMARKS, UNIT


def _v(kind: int, key: str) -> str:
    return f"({kind * UNIT} + CAST({key} AS BIGINT))"


RAW = {
    "example14": "SELECT * FROM (VALUES " + ", ".join(f"({a}, {b})" for a, b in EXAMPLE14) + ") t(a, b)",
    "geo": f"""SELECT {_v(3, 'c_custkey')} AS a, {_v(2, 'c_nationkey')} AS b FROM customer
      UNION ALL SELECT {_v(4, 's_suppkey')}, {_v(2, 's_nationkey')} FROM supplier
      UNION ALL SELECT {_v(2, 'n_nationkey')}, {_v(1, 'n_regionkey')} FROM nation
      UNION ALL SELECT {_v(1, 'r_regionkey')}, 0 FROM region""",
    "succession": f"""SELECT {_v(3, 'x.o_custkey')} AS a, {_v(3, 'y.o_custkey')} AS b FROM orders x JOIN orders y
      ON y.o_orderkey = x.o_orderkey + 1 WHERE x.o_orderpriority = '1-URGENT'""",
    "basket": f"""SELECT {_v(3, 'o_custkey')} AS a, {_v(5, 'l_partkey')} AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey""",
    "brandhub": f"""SELECT {_v(6, 'l_orderkey')} AS a, {_v(5, 'l_partkey')} AS b FROM lineitem WHERE l_linenumber <= 2
      UNION ALL SELECT {_v(5, 'p_partkey')}, {_v(7, "substr(p_brand, 7)")} FROM part WHERE p_size <= 25""",
    "catalog": f"""SELECT {_v(7, "substr(p_brand, 7)")} AS a, {_v(13, 'p_size')} AS b FROM part""",
    "fragments": f"""SELECT {_v(6, 'l_orderkey')} AS a, {_v(5, 'l_partkey')} AS b FROM lineitem WHERE l_returnflag = 'R' AND l_quantity <= 15""",
    "users": f"""SELECT {_v(8, 'user_id')} AS a, {_v(8, 'nxt')} AS b FROM
      (SELECT user_id, event_type, lead(user_id) OVER (ORDER BY ts, event_id) AS nxt FROM events) WHERE event_type = 'error' AND nxt IS NOT NULL""",
    "web": f"""SELECT {_v(9, 'page_id')} AS a, {_v(10, 'k')} AS b FROM
      (SELECT page_id, dense_rank() OVER (ORDER BY target) AS k FROM
        (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS target FROM pages))""",
    "knn": f"""SELECT {_v(11, 'x')} AS a, {_v(11, 'y')} AS b FROM
      (SELECT p.vec_id AS x, q.vec_id AS y, row_number() OVER (PARTITION BY p.vec_id ORDER BY
         list_cosine_similarity(CAST(p.embedding AS DOUBLE[]), CAST(q.embedding AS DOUBLE[])) DESC, q.vec_id) AS r
       FROM embeddings p JOIN embeddings q ON p.vec_id <> q.vec_id) WHERE r <= 5""",
    "conv_paths": f"""SELECT {_v(12, 'c.conv_id * 1000 + c.turn')} AS a, {_v(12, 'c.conv_id * 1000 + c.turn + 1')} AS b
      FROM conversations c JOIN conversations d ON d.conv_id = c.conv_id AND d.turn = c.turn + 1""",
}
RAW["supply"] = f"""SELECT {_v(6, 'o_orderkey')} AS a, {_v(3, 'o_custkey')} AS b FROM orders UNION ALL {RAW['geo']}
      UNION ALL SELECT {_v(6, 'l_orderkey')}, {_v(4, 'l_suppkey')} FROM lineitem WHERE l_returnflag = 'R' AND l_linenumber = 1"""

CAP = {"example14": 8, "geo": 8, "supply": 12, "succession": 12, "basket": 7, "brandhub": 18, "fragments": 70, "users": 6, "web": 24, "knn": 14, "conv_paths": 12, "catalog": 12}


def edges(g: str) -> str:
    """WITH-items raw, edges."""
    return f"""raw AS ({RAW[g]}),
edges AS (SELECT DISTINCT src, dst FROM (SELECT CAST(a AS BIGINT) AS src, CAST(b AS BIGINT) AS dst FROM raw UNION ALL SELECT b, a FROM raw) WHERE src <> dst)"""


def landmarks(g: str, k: int) -> str:
    if g == "example14":
        rows = ", ".join(f"({n}, {v})" for n, v in enumerate(EXAMPLE14_LANDMARKS))
        return f"landmarks AS (SELECT CAST(rank AS INTEGER) AS rank, CAST(id AS BIGINT) AS id FROM (VALUES {rows}) t(rank, id))"
    return f"""landmarks AS (SELECT CAST(row_number() OVER (ORDER BY deg DESC, id) - 1 AS INTEGER) AS rank, id FROM
  (SELECT src AS id, count(*) AS deg FROM edges GROUP BY src ORDER BY deg DESC, id LIMIT {k}))"""


def reach(name: str, sources: str, table: str, cap: int) -> str:
    """WITH-item: (lm, v, d), distances from ``sources`` (a query of one column id) over an edge table."""
    return f"""{name}_walk(lm, v, d) AS (SELECT id, id, 0 FROM ({sources}) UNION
  SELECT w.lm, e.dst, w.d + 1 FROM {name}_walk w JOIN {table} e ON e.src = w.v WHERE w.d < {cap}),
{name} AS (SELECT lm, v, CAST(min(d) AS INTEGER) AS d FROM {name}_walk GROUP BY lm, v)"""


def full(g: str) -> str:
    return reach("full_d", "SELECT id FROM landmarks", "edges", CAP[g])


GATEWAY = """labels AS (SELECT f.v, f.lm, f.d FROM full_d f WHERE f.v NOT IN (SELECT id FROM landmarks) AND NOT EXISTS (
  SELECT 1 FROM full_d rq JOIN full_d qv ON qv.lm = rq.v WHERE rq.lm = f.lm AND qv.v = f.v AND rq.v <> f.lm
    AND rq.v IN (SELECT id FROM landmarks) AND rq.d + qv.d = f.d))"""
MATRIX = "matrix AS (SELECT lm AS lm_a, v AS lm_b, d FROM full_d WHERE v IN (SELECT id FROM landmarks))"


def pairs(n: int) -> str:
    return f"""ranked AS (SELECT row_number() OVER (ORDER BY id) - 1 AS rank, id FROM (SELECT DISTINCT src AS id FROM edges)),
size AS (SELECT count(*) AS n FROM ranked),
pairs AS (SELECT i AS pair_id, a.id AS s, b.id AS t FROM (SELECT unnest(range({n})) AS i), size
  JOIN ranked a ON a.rank = (i * 7919 + 13) % n JOIN ranked b ON b.rank = (i * 104729 + 57) % n)"""


CORE = "core AS (SELECT src, dst FROM edges WHERE src NOT IN (SELECT id FROM landmarks) AND dst NOT IN (SELECT id FROM landmarks))"
#: The bound is the least way over any landmark (the cover property); 0 for equal ends.
BOUND = """bound AS (SELECT p.pair_id, p.s, p.t, CAST(CASE WHEN p.s = p.t THEN 0 ELSE min(a.d + b.d) END AS INTEGER) AS ub FROM pairs p
  LEFT JOIN full_d a ON a.v = p.s LEFT JOIN full_d b ON b.v = p.t AND b.lm = a.lm GROUP BY p.pair_id, p.s, p.t)"""


def truth(g: str) -> str:
    return reach("from_s", "SELECT DISTINCT s AS id FROM pairs", "edges", CAP[g]) + """,
truth AS (SELECT p.pair_id, p.s, p.t, f.d AS dist FROM pairs p LEFT JOIN from_s f ON f.lm = p.s AND f.v = p.t)"""


def query(select: str, *items: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(items) + "\n" + select
