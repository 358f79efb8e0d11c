"""URL filter: host-suffix and path-prefix expressions looked up by short hash prefixes.

Every url is expanded into the expressions that a rule could be written as; only shapes (labels of the host,
length of the path) that occur among the rules are made. The expressions meet the rules in an equi-join on a
32-bit digest prefix, the full digests confirm it, and the longest rule decides.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from adapterlab.llm.common import ascii_lower

# Fixed values of the task: (host, path, verdict).
TASK_RULES = [
    ("com", "/en/", "block"),
    ("example.com", "/en/7", "allow"),
    ("net", "/de/", "allow"),
    ("example.net", "/de/8", "block"),
    ("org", "/es/", "block"),
]
PREFIX_HEX = 8
BROADCAST_RULES = 100_000


def task_rules(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(TASK_RULES, "host string, path string, verdict string")


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(host) + 1, F.length(rest) + 1), r"^[^?#]*", 0)
    return ascii_lower(host), path


def filter_urls(pages: DataFrame, rules: DataFrame, default: str = "allow", key: str = "page_id", url: str = "url") -> DataFrame:
    """One row (key, host, path, rule, verdict) per row of `pages`.

    Null urls and urls without `://` have an empty host and path and take the default, as does any url that no
    rule fits. Of fitting rules the longest wins (characters of host and path together), ties go to the
    longer host, then to block. Repeated rows stay repeated; other columns are not read.
    """
    rules = rules.where(F.col("host").isNotNull()).select(
        ascii_lower(F.col("host")).alias("r_host"), F.coalesce("path", F.lit("")).alias("r_path"), F.col("verdict").alias("r_verdict")
    ).dropDuplicates()
    shape = F.struct(F.size(F.split("r_host", r"\.")).alias("labels"), F.length("r_path").alias("chars"))
    # Distinct shapes, not rules: labels of a host times lengths of a path.
    shapes = [r["s"] for r in rules.select(shape.alias("s")).distinct().collect()]
    host, path = host_and_path(F.col(url))
    parsed = pages.select(F.col(key), host.alias("host"), path.alias("path"))
    if not shapes:
        return parsed.withColumns({"rule": F.lit(None).cast("string"), "verdict": F.lit(default)})

    wanted = F.array(*[F.struct(F.lit(s["labels"]).alias("labels"), F.lit(s["chars"]).alias("chars")) for s in sorted(shapes)])
    n_labels = F.size(F.split("host", r"\."))
    expressions = (
        parsed.select("host", "path").distinct()
        .withColumn("w", F.explode(wanted))
        .where((n_labels >= F.col("w.labels")) & (F.length("path") >= F.col("w.chars")))
        .select(
            "host", "path",
            F.sha2(F.concat(F.expr("substring_index(host, '.', -w.labels)"), F.expr("substring(path, 1, w.chars)")), 256).alias("digest"),
        )
        .withColumn("prefix", F.substring("digest", 1, PREFIX_HEX))
    )
    table = rules.select(
        F.sha2(F.concat("r_host", "r_path"), 256).alias("r_digest"), F.concat("r_host", "r_path").alias("rule"), F.col("r_verdict"),
        F.length("r_host").alias("host_chars"),
    ).withColumn("prefix", F.substring("r_digest", 1, PREFIX_HEX))
    if rules.count() <= BROADCAST_RULES:
        table = F.broadcast(table)
    order = F.struct(F.length("rule"), F.col("host_chars"), F.col("r_verdict"))
    best = (
        expressions.join(table, "prefix")
        .where(F.col("digest") == F.col("r_digest"))
        .groupBy("host", "path")
        .agg(F.max_by(F.struct("rule", "r_verdict"), order).alias("best"))
    )
    # A key of its own puts an exchange on both sides, so that a page repeated very often is split at run time.
    with_key = lambda df: df.withColumn("k", F.xxhash64("host", "path"))
    best = with_key(best).select(F.col("k").alias("b_k"), F.col("host").alias("b_host"), F.col("path").alias("b_path"), "best")
    return (
        with_key(parsed)
        .join(best, (F.col("k") == F.col("b_k")) & (F.col("host") == F.col("b_host")) & (F.col("path") == F.col("b_path")), "left")
        .select(F.col(key), "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.r_verdict", F.lit(default)).alias("verdict"))
    )


URL_SQL = r"""
WITH parsed AS (
  SELECT page_id,
    CASE WHEN strpos(url, '://') > 0 THEN substring(url, strpos(url, '://') + 3) ELSE '' END AS rest
  FROM pages
), split AS (
  SELECT page_id, regexp_extract(coalesce(rest, ''), '^[^/?#]*') AS raw_host, coalesce(rest, '') AS rest FROM parsed
), parts AS (
  SELECT page_id, translate(raw_host, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(substring(rest, length(raw_host) + 1), '^[^?#]*') AS path
  FROM split
), rules(r_host, r_path, r_verdict) AS (
  VALUES ('com', '/en/', 'block'), ('example.com', '/en/7', 'allow'), ('net', '/de/', 'allow'),
         ('example.net', '/de/8', 'block'), ('org', '/es/', 'block')
), ranked AS (
  SELECT p.page_id, p.host, p.path, r.r_host || r.r_path AS rule, r.r_verdict,
    row_number() OVER (PARTITION BY p.page_id ORDER BY length(r.r_host || r.r_path) DESC NULLS LAST) AS k
  FROM parts p LEFT JOIN rules r
    ON (p.host = r.r_host OR ends_with(p.host, '.' || r.r_host)) AND starts_with(p.path, r.r_path)
)
SELECT page_id, host, path, rule, coalesce(r_verdict, 'allow') AS verdict FROM ranked WHERE k = 1
"""
