"""URL rules: host-suffix and path-prefix expressions matched through short hash prefixes.  Native.

Every URL is expanded into the expressions (host suffix + path prefix) whose label count and path length occur
in some rule, the expressions meet the rules in an equi-join on the first hex digits of a digest, a full digest
comparison confirms, and the longest confirmed rule decides.  The rule list is broadcast only while it has at most
`BROADCAST_RULES` rows (counted first); beyond that the join is left to Spark with skew splitting.

Defined cases: a null URL, or one without `://`, has an empty host and path and no rule; empty rule lists leave the
default verdict; a host may end in a port, which then is part of its last label; equal rules collapse, `block` winning;
repeated rows are judged one by one; other columns of the input are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lower_ascii, table

#: Rules of the query (fixed values): host, path, verdict.
RULES = [
    ("com", "/", "allow"),
    ("example.com", "/en/", "block"),
    ("www.example.com", "/en/", "allow"),
    ("net", "/es/", "block"),
    ("net", "/fr/", "block"),
]
BROADCAST_RULES = 200_000
PREFIX_HEX = 8


def rule_table(rules: DataFrame) -> DataFrame:
    """rules(host, path, verdict) -> one row per distinct rule with digest, short prefix and shape."""
    expr = F.concat("host", "path")
    return (
        rules.where(F.col("host").isNotNull() & F.col("path").isNotNull())
        .groupBy(lower_ascii(F.col("host")).alias("host"), "path")
        .agg(F.max("verdict").alias("verdict"))
        .select(
            expr.alias("rule"),
            "verdict",
            F.size(F.split("host", r"\.")).alias("labels"),
            F.length("path").alias("path_len"),
            F.length(expr).alias("rule_len"),
            F.sha2(F.concat_ws("\n", "host", "path"), 256).alias("digest"),
        )
        .withColumn("short", F.substring("digest", 1, PREFIX_HEX))
    )


def judge_urls(pages: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """One row per row of `pages`: id, host, path, rule (or null), verdict."""
    known = rule_table(rules)
    shapes = [(r["labels"], r["path_len"]) for r in known.select("labels", "path_len").distinct().limit(4097).collect()]
    n_rules = known.count()
    parts = pages.select(
        F.col(id_col),
        lower_ascii(F.coalesce(F.regexp_extract(url_col, r"://([^/?#]*)([^?#]*)", 1), F.lit(""))).alias("host"),
        F.coalesce(F.regexp_extract(url_col, r"://([^/?#]*)([^?#]*)", 2), F.lit("")).alias("path"),
    )
    if not shapes:
        return parts.select(id_col, "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"))
    if len(shapes) > 4096:  # too many shapes to list: every suffix with every prefix
        label_counts, lengths = F.sequence(F.lit(1), F.size(F.split("host", r"\."))), F.sequence(F.lit(0), F.length("path"))
        expressions = F.flatten(F.transform(label_counts, lambda n: F.transform(lengths, lambda m: F.struct(n.alias("n"), m.alias("m")))))
    else:
        expressions = F.array(*[F.struct(F.lit(n).alias("n"), F.lit(m).alias("m")) for n, m in sorted(shapes)])
    fits = F.filter(expressions, lambda x: (x["n"] <= F.size(F.split("host", r"\."))) & (x["m"] <= F.length("path")))
    digests = F.transform(fits, lambda x: F.sha2(F.concat_ws("\n", F.call_function("substring_index", F.col("host"), F.lit("."), -x["n"]), F.left("path", x["m"])), 256))
    probes = (
        parts.withColumn("_row", F.monotonically_increasing_id())
        .select("*", F.explode_outer(digests).alias("_digest"))
        .withColumn("_short", F.substring("_digest", 1, PREFIX_HEX))
    )
    index = known.select("short", "digest", "rule", "rule_len", F.col("verdict").alias("_verdict"), F.col("labels").alias("_labels"))
    if n_rules <= BROADCAST_RULES:
        index = F.broadcast(index)
    hit = F.when(F.col("_digest") == F.col("digest"), F.struct("rule_len", "_labels", "rule", "_verdict"))
    return (
        probes.join(index, F.col("_short") == F.col("short"), "left")
        .groupBy("_row")
        .agg(F.first(id_col).alias(id_col), F.first("host").alias("host"), F.first("path").alias("path"), F.max(hit).alias("_best"))
        .select(id_col, "host", "path", F.col("_best.rule").alias("rule"), F.coalesce("_best._verdict", F.lit(default)).alias("verdict"))
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rules = spark.createDataFrame(RULES, "host string, path string, verdict string")
    return judge_urls(table(spark, sf_dir, "pages"), rules)


SQL = """
WITH parts AS (
  SELECT row_number() OVER () AS rn, page_id,
         translate(coalesce(regexp_extract(url, '://([^/?#]*)([^?#]*)', 1), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         coalesce(regexp_extract(url, '://([^/?#]*)([^?#]*)', 2), '') AS path
  FROM pages),
rules(h, p, v) AS (VALUES ('com','/','allow'), ('example.com','/en/','block'), ('www.example.com','/en/','allow'), ('net','/es/','block'), ('net','/fr/','block')),
best AS (
  SELECT rn, max_by(h || p, length(h || p)) AS rule, max_by(v, length(h || p)) AS v
  FROM parts JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p)
  GROUP BY rn)
SELECT page_id, host, path, rule, coalesce(v, 'allow') AS verdict FROM parts LEFT JOIN best USING (rn)
"""

QUERIES = {"op2_url_filter": query}
ORACLE_SQL = {"op2_url_filter": SQL}
