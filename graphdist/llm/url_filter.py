"""URL filters as a sort-merge range join of canonical host keys, in DataFrame functions only.

A host's key is its labels in reverse order, each closed by ``\\u0001``: ``a.example.net`` -> ``net|example|a|``.
All subdomains of a rule's host then lie in one interval of keys, and such intervals are nested or disjoint.
Keys of urls and rules are sorted together into ranges; a sweep over each range carries, from row to row, the
stack of rules whose interval is open (held with the rule that opened last, its enclosing rules included).
A url pops the entries whose interval ended before its key, and what is left are the rules on its host or a
parent of it; of those whose path is a prefix of its own the longest rule wins (ties: the longer host).

Ranges are dealt by (key, row id), so one hot host is spread over as many ranges as it fills; each range starts
with the last rule of the ranges before it, from a table of one row per range.

Defined cases: a NULL url or one without ``://`` has empty host and path and gets the default verdict unless a
rule has an empty host; repeated rows are judged each; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from graphdist.runtime import materialize

RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
DEFAULT = "allow"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def url_host(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), _UPPER, _LOWER), F.lit(""))


def url_path(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*(/[^?#]*)?", 1), F.lit(""))


def host_key(host: Column) -> Column:
    closed = F.transform(F.reverse(F.split(host, r"\.")), lambda x: F.concat(x, F.lit("\u0001")))
    return F.when(host == "", F.lit("")).otherwise(F.array_join(closed, ""))


def rules_frame(spark: SparkSession, rules=RULES) -> DataFrame:
    rows = F.array(*[F.struct(F.lit(h).alias("host"), F.lit(p).alias("path"), F.lit(v).alias("verdict")) for h, p, v in rules])
    return spark.range(1).select(F.inline(rows))


def _stacks(rules: DataFrame) -> DataFrame:
    """(key, stack): for each rule host the rules open at it, its own and those of the hosts around it."""
    keyed = rules.select(host_key(F.col("host")).alias("key"), F.struct("host", "path", "verdict").alias("rule"))
    own = keyed.groupBy("key").agg(F.collect_set("rule").alias("own"))
    labels = F.split("key", "\u0001")  # the last of them is empty
    prefixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda n: F.array_join(F.concat(F.slice(labels, F.lit(1), n - 1), F.array(F.lit(""))), "\u0001"))
    around = own.select("key", F.explode(prefixes).alias("outer"))
    open_rules = around.join(own.select(F.col("key").alias("outer"), "own"), "outer")
    return open_rules.groupBy("key").agg(F.flatten(F.collect_list("own")).alias("stack"))


def judge_urls(pages: DataFrame, rules: DataFrame, default: str = DEFAULT, url: str = "url") -> DataFrame:
    """``pages`` with host, path, rule (host + path of the winning rule, else NULL) and verdict."""
    names = [c for c in pages.columns if c not in ("host", "path", "rule", "verdict")]
    spark = pages.sparkSession
    stacks = _stacks(rules)
    kind = stacks.schema["stack"].dataType
    urls = pages.select(
        F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"), url_host(F.col(url)).alias("host"), url_path(F.col(url)).alias("path")
    )
    points = urls.select(host_key(F.col("host")).alias("key"), F.monotonically_increasing_id().alias("tie"), F.lit(1).alias("side"), "row", "host", "path", F.lit(None).cast(kind).alias("stack"))
    opens = stacks.select("key", F.expr("-9223372036854775807L - 1L").alias("tie"), F.lit(0).alias("side"), F.lit(None).cast(points.schema["row"].dataType).alias("row"), F.lit(None).cast("string").alias("host"), F.lit(None).cast("string").alias("path"), "stack")
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = materialize(points.unionByName(opens).repartitionByRange(n, "key", "tie").withColumn("range", F.spark_partition_id()), "url-ranges")
    # one row per range: the rule that opened last in it, carried to the ranges after it
    order = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    ends = dealt.groupBy("range").agg(F.max(F.when(F.col("side") == 0, F.struct("key", "stack"))).alias("last"))
    carried = ends.select("range", F.last("last.stack", ignorenulls=True).over(order).alias("before"))
    swept = dealt.withColumn("open", F.last("stack", ignorenulls=True).over(Window.partitionBy("range").orderBy("key", "side", "tie").rowsBetween(Window.unboundedPreceding, 0)))
    met = swept.filter("side = 1").drop("stack").join(carried, "range", "left").withColumn("open", F.coalesce("open", "before"))
    fits = F.filter(
        "open",
        lambda r: (F.col("host").eqNullSafe(r.host) | (r.host == "") | F.endswith(F.col("host"), F.concat(F.lit("."), r.host))) & F.startswith(F.col("path"), r.path),
    )
    ranked = F.transform(fits, lambda r: F.struct((F.length(r.host) + F.length(r.path)).alias("n"), F.length(r.host).alias("m"), F.concat(r.host, r.path).alias("rule"), r.verdict.alias("verdict")))
    best = met.withColumn("best", F.array_max(ranked))
    return best.select(*[F.col(f"row.`{c}`").alias(c) for c in names], "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict"))


def op2_url_filter(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    return judge_urls(pages, rules_frame(spark)).select("page_id", "host", "path", "rule", "verdict")


OP2_SQL = r"""
WITH parts AS (
  SELECT page_id,
    coalesce(translate(regexp_extract(url, '^.*?://([^/?#]*)', 1, 's'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
    coalesce(regexp_extract(url, '^.*?://[^/?#]*(/[^?#]*)?', 1, 's'), '') AS path
  FROM pages),
rules(rhost, rpath, verdict) AS (VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')),
urls AS (SELECT DISTINCT host, path FROM parts),
ranked AS (
  SELECT host, path, rhost || rpath AS rule, verdict,
    row_number() OVER (PARTITION BY host, path ORDER BY length(rhost || rpath) DESC, length(rhost) DESC) AS k
  FROM urls JOIN rules ON (host = rhost OR ends_with(host, '.' || rhost)) AND starts_with(path, rpath))
SELECT p.page_id, p.host, p.path, r.rule, coalesce(r.verdict, 'allow') AS verdict
FROM parts p LEFT JOIN ranked r ON p.host = r.host AND p.path = r.path AND r.k = 1
"""
