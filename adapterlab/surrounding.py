"""Operators around the method, one query each: scans, joins, aggregates, windows, functions, and twins of the streams."""

from __future__ import annotations

import uuid

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from adapterlab import oracles as Q
from adapterlab.functions.tokens import pad_to
from adapterlab.registry import batches, query
from adapterlab.operators import packing as P
from adapterlab.samples import order_microbatches
from adapterlab.session import broadcast_within, shared_dir
from adapterlab.sources.tables import load, register_views
from adapterlab.sources.weights import WeightSource
from adapterlab.streaming import arrivals as A

LEN = "(length(text) + 3) // 4"
docs = lambda s, d: load(s, d, "documents").withColumn("tok_len", F.floor((F.length("text") + 3) / 4).cast("bigint"))
DOCS = f"docs AS (SELECT *, {LEN} AS tok_len FROM documents)"


def add(name: str, sql: str | None, f) -> None:
    query(sql, f"op_{name}")(f)


def round_trip(spark: SparkSession, df: DataFrame, kind: str, **options) -> DataFrame:
    """Written and read back; the folder is the shared one where the cluster names one."""
    path = f"{shared_dir(spark)}/adapterlab-{kind}-{uuid.uuid4().hex}"
    df.write.options(**options).format(kind).save(path)
    return spark.read.schema(df.schema).options(**options).format(kind).load(path)


# Scans, sinks, views
add("scan_pruned", "SELECT doc_id, lang FROM documents", lambda s, d: load(s, d, "documents").select("doc_id", "lang"))
for _kind, _opt in (("csv", {"header": "true"}), ("json", {}), ("orc", {}), ("parquet", {})):
    add(f"round_trip_{_kind}", f"WITH {DOCS} SELECT doc_id, lang, tok_len FROM docs", lambda s, d, k=_kind, o=_opt: round_trip(s, docs(s, d).select("doc_id", "lang", "tok_len"), k, **o))
add("round_trip_text", "SELECT doc_id::VARCHAR || ':' || lang AS value FROM documents", lambda s, d: round_trip(s, load(s, d, "documents").select(F.concat_ws(":", F.col("doc_id").cast("string"), "lang").alias("value")), "text"))
add("partitioned_sink", f"WITH {DOCS} SELECT lang, count(*) AS n, CAST(sum(tok_len) AS BIGINT) AS tokens FROM docs GROUP BY 1", lambda s, d: _partitioned(s, docs(s, d).select("doc_id", "tok_len", "lang")))


def _partitioned(spark, df):
    path = f"{shared_dir(spark)}/adapterlab-partitioned-{uuid.uuid4().hex}"
    df.repartition("lang").sortWithinPartitions("doc_id").write.partitionBy("lang").parquet(path)
    return spark.read.parquet(path).groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum("tok_len").alias("tokens"))


add("manifest", f"{Q.greedy('ffd')} SELECT group_id, gb, bin, count(*) AS n FROM packed GROUP BY 1, 2, 3", lambda s, d: _manifest(s, d))


def _manifest(spark, sf_dir):
    items = P.pack_greedy(batches(spark, sf_dir), Q.C, Q.P)
    lines = items.groupBy("group_id", "gb", "bin").agg(F.to_json(F.struct("group_id", "gb", "bin", F.collect_list("sample_id").alias("ids"))).alias("value")).select("value")
    back = round_trip(spark, lines, "text").select(F.from_json("value", "group_id int, gb bigint, bin int, ids array<bigint>").alias("m"))
    return back.select("m.group_id", "m.gb", "m.bin", F.size("m.ids").cast("bigint").alias("n"))


def _weights(spark, sf_dir):
    spark.dataSource.register(WeightSource)
    return spark.read.format("weight_blocks").option("kind", "w").load()


add("weight_source", "SELECT CAST(i AS INT) AS i, CAST(j AS INT) AS j, (31 * i + 17 * j + 7) % 21 - 10 AS v FROM generate_series(0, 63) t(i), generate_series(0, 31) u(j)", _weights)


def _views(spark, sf_dir):
    register_views(spark, sf_dir, "al_")
    return spark.sql("SELECT lang, count(*) AS n FROM al_documents GROUP BY lang")


add("temp_views", "SELECT lang, count(*) AS n FROM documents GROUP BY 1", _views)

# Projection, filters, cleaning
add("project", "SELECT doc_id, upper(lang) AS lang, n_chars * 2 AS twice FROM documents", lambda s, d: load(s, d, "documents").select("doc_id", F.upper("lang").alias("lang"), (F.col("n_chars") * 2).alias("twice")))
add("filters", """SELECT doc_id, CASE WHEN n_chars > 2000 THEN 'long' ELSE 'short' END AS kind FROM documents WHERE n_chars BETWEEN 100 AND 5000 AND lang IN ('en', 'de') AND text LIKE '%the%'
AND regexp_matches(text, 'th[aeiou]') AND source IS NOT DISTINCT FROM source""", lambda s, d: load(s, d, "documents").where("n_chars BETWEEN 100 AND 5000 AND lang IN ('en', 'de') AND text LIKE '%the%' AND text RLIKE 'th[aeiou]' AND source <=> source")
    .select("doc_id", F.when(F.col("n_chars") > 2000, "long").otherwise("short").alias("kind")))
add("quality_filter", "SELECT d.doc_id FROM documents d JOIN labels l USING (doc_id) WHERE quality = 1 AND toxic = 0", lambda s, d: load(s, d, "documents").select("doc_id").join(load(s, d, "labels").where("quality = 1 AND toxic = 0").select("doc_id"), "doc_id"))
add("exact_dedup", "SELECT min(doc_id) AS doc_id FROM documents GROUP BY md5(text)", lambda s, d: load(s, d, "documents").groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id")).select("doc_id"))
add("decontaminate_words", """WITH wd AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '[ \\t\\n\\r]+'), lambda x: x <> '') AS w FROM documents),
wb AS (SELECT list_filter(regexp_split_to_array(lower(text), '[ \\t\\n\\r]+'), lambda x: x <> '') AS w FROM benchmark),
sd AS (SELECT doc_id, array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT doc_id, w, unnest(generate_series(1, len(w) - 7)) AS i FROM wd)),
sb AS (SELECT DISTINCT array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT w, unnest(generate_series(1, len(w) - 7)) AS i FROM wb))
SELECT doc_id, count(*) AS windows FROM sd WHERE s IN (SELECT s FROM sb) GROUP BY 1""", lambda s, d: _leaks(s, d))


def _leaks(spark, sf_dir, width: int = 8):
    def shingles(name, key):
        w = load(spark, sf_dir, name).select(key, F.filter(F.split(F.lower("text"), r"[ \t\n\r]+"), lambda x: x != "").alias("w")).where(F.size("w") >= width)
        return w.select(key, F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - width + 1), lambda i: F.array_join(F.slice("w", i, width), " "))).alias("s"))

    return shingles("documents", "doc_id").join(shingles("benchmark", "item_id").select("s").distinct(), "s", "left_semi").groupBy("doc_id").agg(F.count(F.lit(1)).alias("windows"))


add("html_to_text", "SELECT page_id, length(trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \\t\\n]+', ' ', 'g'))) AS chars FROM pages",
    lambda s, d: load(s, d, "pages").select("page_id", F.length(F.trim(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), r"[ \t\n]+", " "))).cast("bigint").alias("chars")))
add("split_by_hash", "SELECT doc_id, substr(md5('7-' || doc_id::VARCHAR), 1, 2) < '40' AS held_out FROM documents", lambda s, d: load(s, d, "documents").select("doc_id", (F.substring(F.md5(F.concat(F.lit("7-"), F.col("doc_id").cast("string"))), 1, 2) < "40").alias("held_out")))

# Joins
orders = lambda s, d: load(s, d, "orders").select("o_orderkey", "o_custkey", "o_totalprice")
lines = lambda s, d: load(s, d, "lineitem").select("l_orderkey", "l_quantity", "l_suppkey")
add("broadcast_join", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1", lambda s, d: orders(s, d).join(broadcast_within(load(s, d, "customer").select("c_custkey", "c_mktsegment")), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")))
for _hint in ("merge", "shuffle_hash"):
    add(f"join_{_hint}", "SELECT o_orderkey, CAST(sum(l_quantity) AS BIGINT) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1", lambda s, d, h=_hint: orders(s, d).join(lines(s, d).hint(h), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.sum("l_quantity").cast("bigint").alias("q")))
add("left_join", "SELECT d.doc_id, quality FROM documents d LEFT JOIN labels l USING (doc_id)", lambda s, d: load(s, d, "documents").select("doc_id").join(load(s, d, "labels").select("doc_id", "quality"), "doc_id", "left"))
add("full_join", "SELECT coalesce(d.doc_id, p.page_id) AS id, d.doc_id IS NOT NULL AS in_docs, p.page_id IS NOT NULL AS in_pages FROM documents d FULL JOIN pages p ON d.doc_id = p.page_id * 5", lambda s, d: load(s, d, "documents").select("doc_id").join(load(s, d, "pages").select("page_id"), F.col("doc_id") == F.col("page_id") * 5, "full").select(F.coalesce("doc_id", "page_id").alias("id"), F.col("doc_id").isNotNull().alias("in_docs"), F.col("page_id").isNotNull().alias("in_pages")))
add("semi_join", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)", lambda s, d: load(s, d, "documents").select("doc_id").join(load(s, d, "labels"), "doc_id", "left_semi"))
add("anti_join", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)", lambda s, d: load(s, d, "documents").select("doc_id").join(load(s, d, "labels"), "doc_id", "left_anti"))
add("grid_join", f"""WITH {Q.ORDER_BATCHES.format(n=256)}
SELECT CAST(s AS INT) AS stages, CAST(c AS INT) AS capacity, count(*) AS batches, CAST(sum((tokens + c - 1) // c + s - 1) AS BIGINT) AS slots FROM mbs, (VALUES (1), (2), (4)) a(s), (VALUES (2048), (4096)) b(c) GROUP BY 1, 2""", lambda s, d: _grid_join(s, d))
add("theta_join", "SELECT r.r_regionkey, n.n_nationkey FROM region r JOIN nation n ON n.n_nationkey >= r.r_regionkey * 5 AND n.n_nationkey < r.r_regionkey * 5 + 5", lambda s, d: load(s, d, "region").select("r_regionkey").join(broadcast_within(load(s, d, "nation").select("n_nationkey")), (F.col("n_nationkey") >= F.col("r_regionkey") * 5) & (F.col("n_nationkey") < F.col("r_regionkey") * 5 + 5)))


def _grid_join(spark, sf_dir):
    """Each batch of orders with every setting of a grid: slots of a pipeline that fills, runs and drains."""
    grid = spark.createDataFrame([(1,), (2,), (4,)], "stages int").crossJoin(F.broadcast(spark.createDataFrame([(2048,), (4096,)], "capacity int")))
    met = order_microbatches(spark, sf_dir, 256).crossJoin(F.broadcast(grid))
    return met.groupBy("stages", "capacity").agg(F.count(F.lit(1)).alias("batches"), F.sum(F.expr("(tokens + capacity - 1) div capacity + stages - 1")).alias("slots"))


def _range_join(spark, sf_dir, width: int = 512):
    """Lengths in histogram ranges: ranges are cut to buckets of one width, buckets meet in an equi-join, bounds decide."""
    ranges = spark.createDataFrame([(i, i * 300, i * 300 + 300) for i in range(30)], "bin int, lo bigint, hi bigint")
    cut = ranges.withColumn("bucket", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("hi") - 1) / width))))
    points = docs(spark, sf_dir).select("doc_id", "tok_len", F.floor(F.col("tok_len") / width).alias("bucket"))
    return points.join(F.broadcast(cut), "bucket").where("tok_len >= lo AND tok_len < hi").groupBy("bin").agg(F.count(F.lit(1)).alias("n"))


add("range_join", f"WITH {DOCS}, r AS (SELECT CAST(i AS INT) AS bin, i * 300 AS lo, i * 300 + 300 AS hi FROM generate_series(0, 29) t(i)) SELECT bin, count(*) AS n FROM docs JOIN r ON tok_len >= lo AND tok_len < hi GROUP BY 1", _range_join)
TRACE = """trace AS (SELECT event_id AS id, epoch_us(ts) // 1000000 AS a, epoch_us(ts) // 1000000 + 10 + event_id * 13 % 60 AS b FROM events WHERE ts IS NOT NULL AND event_id IS NOT NULL),
win AS (SELECT w * 3600 AS lo, w * 3600 + 3600 AS hi FROM (SELECT unnest(generate_series(min(a) // 3600, max(b - 1) // 3600)) AS w FROM trace))"""


def _overlap(spark, sf_dir):
    """Seconds that events are under way, by hour; an event begins at its time and lasts 10 to 69 seconds."""
    events = load(spark, sf_dir, "events").where("ts IS NOT NULL AND event_id IS NOT NULL")
    begin = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000)
    trace = events.select("event_id", begin.alias("a")).withColumn("b", F.col("a") + 10 + F.col("event_id") * 13 % 60)
    cut = trace.withColumn("lo", F.explode(F.transform(F.sequence(F.floor(F.col("a") / 3600), F.floor((F.col("b") - 1) / 3600)), lambda w: w * 3600)))
    return cut.groupBy("lo").agg(F.sum(F.least(F.col("b"), F.col("lo") + 3600) - F.greatest("a", "lo")).alias("busy"))


add("interval_overlap", f"WITH {TRACE} SELECT lo, CAST(sum(least(b, hi) - greatest(a, lo)) AS BIGINT) AS busy FROM win JOIN trace ON a < hi AND b > lo GROUP BY 1", _overlap)
add("asof_join", """WITH e AS (SELECT event_id, user_id, epoch_us(ts) AS us, event_type FROM events), c AS (SELECT user_id, us, max(event_id) AS cfg FROM e WHERE event_type = 'signup' GROUP BY 1, 2)
SELECT a.event_id, c.cfg FROM e a ASOF LEFT JOIN c ON a.user_id = c.user_id AND a.us >= c.us WHERE a.event_type = 'purchase'""", lambda s, d: A.latest_configuration(A.events(s, d)))
add("self_join", f"WITH {DOCS} SELECT a.doc_id, b.tok_len - a.tok_len AS step FROM docs a JOIN docs b ON b.doc_id = a.doc_id + 1", lambda s, d: docs(s, d).select("doc_id", "tok_len").alias("a").join(docs(s, d).select((F.col("doc_id") - 1).alias("prev"), F.col("tok_len").alias("next_len")).alias("b"), F.col("doc_id") == F.col("prev")).select("doc_id", (F.col("next_len") - F.col("tok_len")).alias("step")))

# Aggregates
add("hash_aggregate", f"WITH {DOCS} SELECT source, count(*) AS n, CAST(sum(tok_len) AS BIGINT) AS tokens, max(tok_len) AS longest FROM docs GROUP BY 1", lambda s, d: docs(s, d).groupBy("source").agg(F.count(F.lit(1)).alias("n"), F.sum("tok_len").alias("tokens"), F.max("tok_len").alias("longest")))
add("sort_aggregate", f"WITH {DOCS} SELECT source, max_by(doc_id, tok_len * 1000000 + doc_id) AS longest_doc, min_by(doc_id, tok_len * 1000000 + doc_id) AS shortest_doc FROM docs GROUP BY 1", lambda s, d: docs(s, d).groupBy("source").agg(F.expr("max_by(doc_id, tok_len * 1000000 + doc_id)").alias("longest_doc"), F.expr("min_by(doc_id, tok_len * 1000000 + doc_id)").alias("shortest_doc")))
add("distinct_count", "SELECT lang, count(DISTINCT source) AS sources FROM documents GROUP BY 1", lambda s, d: load(s, d, "documents").groupBy("lang").agg(F.count_distinct("source").alias("sources")))
add("distinct_count_approximate", "SELECT true AS close FROM documents LIMIT 1", lambda s, d: load(s, d, "orders").agg((F.abs(F.approx_count_distinct("o_custkey", 0.02) - F.count_distinct("o_custkey")) <= 0.06 * F.count_distinct("o_custkey")).alias("close")))
add("quantiles", f"WITH {DOCS} SELECT lang, quantile_cont(tok_len, 0.25) AS p25, quantile_cont(tok_len, 0.9) AS p90 FROM docs GROUP BY 1", lambda s, d: docs(s, d).groupBy("lang").agg(F.expr("percentile(tok_len, 0.25)").alias("p25"), F.expr("percentile(tok_len, 0.9)").alias("p90")))
add("quantiles_approximate", "SELECT true AS close FROM documents LIMIT 1", lambda s, d: docs(s, d).agg(F.expr("percentile_approx(tok_len, 0.9, 1000) BETWEEN percentile(tok_len, 0.89) AND percentile(tok_len, 0.91)").alias("close")))
add("cube", "SELECT lang, source, grouping_id(lang, source) AS gid, count(*) AS n FROM documents GROUP BY CUBE (lang, source)", lambda s, d: load(s, d, "documents").cube("lang", "source").agg(F.grouping_id().cast("bigint").alias("gid"), F.count(F.lit(1)).alias("n")))
add("grouping_sets", "SELECT n_regionkey, n_nationkey, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY GROUPING SETS ((n_regionkey), (n_nationkey), ())", lambda s, d: _grouping_sets(s, d))


def _grouping_sets(spark, sf_dir):
    register_views(spark, sf_dir, "al_")
    return spark.sql("SELECT n_regionkey, n_nationkey, count(*) AS n FROM al_supplier JOIN al_nation ON s_nationkey = n_nationkey GROUP BY GROUPING SETS ((n_regionkey), (n_nationkey), ())")


add("pivot", "SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'de') AS de FROM documents GROUP BY 1", lambda s, d: load(s, d, "documents").groupBy("source").pivot("lang", ["en", "de"]).agg(F.count(F.lit(1))).na.fill(0))
add("unpivot", "SELECT doc_id, 'quality' AS label, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels", lambda s, d: load(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "label", "value"))
add("filtered_aggregates", "SELECT lang, count(*) FILTER (n_chars > 1000) AS long_docs, bool_and(n_chars > 0) AS all_filled, round(corr(n_chars, doc_id), 6) AS trend FROM documents GROUP BY 1", lambda s, d: load(s, d, "documents").groupBy("lang").agg(F.count_if(F.col("n_chars") > 1000).alias("long_docs"), F.bool_and(F.col("n_chars") > 0).alias("all_filled"), F.round(F.corr("n_chars", "doc_id"), 6).alias("trend")))

# Windows
by_lang = lambda: Window.partitionBy("lang").orderBy("tok_len", "doc_id")
add("ranking", f"""WITH {DOCS} SELECT doc_id, CAST(row_number() OVER w AS INT) AS rn, CAST(rank() OVER (PARTITION BY lang ORDER BY tok_len) AS INT) AS rk, CAST(dense_rank() OVER (PARTITION BY lang ORDER BY tok_len) AS INT) AS dr,
CAST(ntile(4) OVER w AS INT) AS quarter, round(percent_rank() OVER (PARTITION BY lang ORDER BY tok_len), 6) AS pr FROM docs WINDOW w AS (PARTITION BY lang ORDER BY tok_len, doc_id)""", lambda s, d: docs(s, d).select(
    "doc_id", F.row_number().over(by_lang()).alias("rn"), F.rank().over(Window.partitionBy("lang").orderBy("tok_len")).alias("rk"), F.dense_rank().over(Window.partitionBy("lang").orderBy("tok_len")).alias("dr"),
    F.ntile(4).over(by_lang()).alias("quarter"), F.round(F.percent_rank().over(Window.partitionBy("lang").orderBy("tok_len")), 6).alias("pr")))
add("analytic", f"""WITH {DOCS} SELECT doc_id, lag(doc_id) OVER w AS before, lead(doc_id) OVER w AS after, first_value(doc_id) OVER w AS first, nth_value(doc_id, 2) OVER w AS second FROM docs WINDOW w AS (PARTITION BY lang ORDER BY tok_len, doc_id)""", lambda s, d: docs(s, d).select(
    "doc_id", F.lag("doc_id").over(by_lang()).alias("before"), F.lead("doc_id").over(by_lang()).alias("after"), F.first("doc_id").over(by_lang()).alias("first"), F.nth_value("doc_id", 2).over(by_lang()).alias("second")))
add("frames", f"""WITH {DOCS} SELECT doc_id, CAST(sum(tok_len) OVER (PARTITION BY lang ORDER BY doc_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS last3,
count(*) OVER (PARTITION BY lang ORDER BY tok_len RANGE BETWEEN 50 PRECEDING AND 50 FOLLOWING) AS near FROM docs""", lambda s, d: docs(s, d).select(
    "doc_id", F.sum("tok_len").over(Window.partitionBy("lang").orderBy("doc_id").rowsBetween(-2, 0)).alias("last3"), F.count(F.lit(1)).over(Window.partitionBy("lang").orderBy("tok_len").rangeBetween(-50, 50)).alias("near")))
add("sort_limit", f"WITH {DOCS} SELECT doc_id, tok_len FROM docs ORDER BY tok_len DESC, doc_id LIMIT 20 OFFSET 5", lambda s, d: docs(s, d).select("doc_id", "tok_len").orderBy(F.col("tok_len").desc(), "doc_id").offset(5).limit(20))
add("topk_per_key", f"WITH {DOCS} SELECT lang, doc_id FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY tok_len DESC, doc_id) AS k FROM docs) WHERE k <= 3", lambda s, d: docs(s, d).withColumn("k", F.row_number().over(Window.partitionBy("lang").orderBy(F.col("tok_len").desc(), "doc_id"))).where("k <= 3").select("lang", "doc_id"))
add("set_operations", """(SELECT doc_id FROM documents INTERSECT SELECT doc_id FROM labels) UNION ALL (SELECT doc_id FROM documents EXCEPT ALL SELECT page_id FROM pages)""", lambda s, d: load(s, d, "documents").select("doc_id").intersect(load(s, d, "labels").select("doc_id")).unionByName(load(s, d, "documents").select("doc_id").exceptAll(load(s, d, "pages").select(F.col("page_id").alias("doc_id")))))

# Functions
add("strings", "SELECT doc_id, length(text) AS n, lower(substr(text, 1, 5)) AS head, md5(text) AS digest, CAST(len(string_split(text, ' ')) AS BIGINT) AS parts, replace(source, 'src', '#') AS src FROM documents", lambda s, d: load(s, d, "documents").select("doc_id", F.length("text").cast("bigint").alias("n"), F.lower(F.substring("text", 1, 5)).alias("head"), F.md5("text").alias("digest"), F.size(F.split("text", " ")).cast("bigint").alias("parts"), F.replace("source", F.lit("src"), F.lit("#")).alias("src")))
add("dates", "SELECT event_id, epoch_us(date_trunc('hour', ts)) AS hour_us, CAST(dayofmonth(ts) AS INT) AS day, epoch_us(ts + INTERVAL 1 DAY) AS next_us FROM events", lambda s, d: A.events(s, d).select("event_id", F.unix_micros(F.date_trunc("hour", "ts")).alias("hour_us"), F.dayofmonth("ts").alias("day"), F.unix_micros(F.col("ts") + F.expr("INTERVAL 1 DAY")).alias("next_us")))
add("maths", f"WITH {DOCS} SELECT doc_id, {Q.pad('tok_len')} AS padded, CAST(floor(log2(tok_len + 1)) AS BIGINT) AS magnitude, greatest(tok_len, 100) AS least_100, doc_id % 7 AS bucket FROM docs", lambda s, d: docs(s, d).select("doc_id", pad_to(F.col("tok_len"), 64).alias("padded"), F.floor(F.log2(F.col("tok_len") + 1)).alias("magnitude"), F.greatest("tok_len", F.lit(100).cast("bigint")).alias("least_100"), F.pmod("doc_id", F.lit(7)).alias("bucket")))
add("arrays", "SELECT vec_id, CAST(list_sum(list_transform(embedding, lambda v: CAST(floor(v::DOUBLE * 1024) AS BIGINT))) AS BIGINT) AS total, CAST(len(list_filter(embedding, lambda v: v > 0)) AS BIGINT) AS positive FROM embeddings", lambda s, d: load(s, d, "embeddings").select("vec_id", F.aggregate(F.transform("embedding", lambda v: F.floor(v.cast("double") * 1024)), F.lit(0).cast("bigint"), lambda a, b: a + b).alias("total"), F.size(F.filter("embedding", lambda v: v > 0)).cast("bigint").alias("positive")))
add("maps", f"""{Q.greedy('ffd')} SELECT group_id, gb, bin, adapter_id, CAST({Q.pad('sum(tok_len)')} AS BIGINT) AS padded FROM packed GROUP BY 1, 2, 3, 4""", lambda s, d: P.pack_greedy(batches(s, d), Q.C, Q.P).groupBy("group_id", "gb", "bin", "adapter_id").agg(F.sum("tok_len").alias("t")).groupBy("group_id", "gb", "bin")
    .agg(F.map_from_entries(F.collect_list(F.struct("adapter_id", "t"))).alias("m")).select("group_id", "gb", "bin", F.explode(F.transform_values("m", lambda k, v: pad_to(v, 64))).alias("adapter_id", "padded")))
add("json", "SELECT event_id, CAST(props ->> 'k' AS BIGINT) AS k FROM events", lambda s, d: A.events(s, d).select("event_id", F.from_json("props", "k bigint").getField("k").alias("k")))
add("variant", "SELECT event_id, CAST(props ->> 'k' AS BIGINT) AS k FROM events", lambda s, d: A.events(s, d).select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "bigint").alias("k")))
add("decimals", "SELECT o_orderkey, CAST(CAST(o_totalprice AS DECIMAL(18, 2)) * 2 AS DOUBLE) AS twice FROM orders", lambda s, d: load(s, d, "orders").select("o_orderkey", (F.col("o_totalprice").cast("decimal(18,2)") * 2).cast("double").alias("twice")))

# Twins of the streams
add("tumbling", "SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start_us, event_type, count(*) AS n FROM events GROUP BY 1, 2", lambda s, d: A.tumbling(A.events(s, d), "1 hour"))
add("sliding", """SELECT w AS start_us, count(*) AS n FROM (SELECT unnest([epoch_us(time_bucket(INTERVAL 1 HOUR, ts)), epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) - 3600000000]) AS w FROM events) GROUP BY 1""", lambda s, d: A.sliding(A.events(s, d), "2 hours", "1 hour"))
add("session", """WITH e AS (SELECT user_id, epoch_us(ts) AS us FROM events), g AS (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY user_id ORDER BY us) < 7200000000 THEN 0 ELSE 1 END AS fresh FROM e),
n AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY us ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(us) AS start_us, count(*) AS n FROM n GROUP BY user_id, k""", lambda s, d: A.sessions(A.events(s, d), "2 hours"))
add("stream_dedup", "SELECT user_id, event_type, min(event_id) AS event_id FROM events GROUP BY 1, 2", lambda s, d: A.events(s, d).groupBy("user_id", "event_type").agg(F.min("event_id").alias("event_id")))
add("stream_static", "SELECT e.event_type, c_mktsegment, count(*) AS n FROM events e JOIN customer ON user_id = c_custkey GROUP BY 1, 2", lambda s, d: A.with_segment(A.events(s, d), load(s, d, "customer")).groupBy("event_type", "c_mktsegment").agg(F.count(F.lit(1)).alias("n")))
add("interval_join", """SELECT a.event_id AS signup_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY
WHERE a.event_type = 'signup' AND b.event_type = 'purchase'""", lambda s, d: A.signup_to_purchase(A.events(s, d)))
add("filled_batches", """WITH a AS (SELECT user_id % 4 AS tenant, row_number() OVER (PARTITION BY user_id % 4 ORDER BY ts, event_id) - 1 AS rn, event_id % 97 + 1 AS tok_len FROM events)
SELECT tenant, rn // 16 AS batch, count(*) AS n, CAST(sum(tok_len) AS BIGINT) AS tokens FROM a GROUP BY 1, 2""", lambda s, d: A.batches_of(A.job_arrivals(A.events(s, d))))

# User-defined functions


def _dot(spark, sf_dir):
    @F.pandas_udf("bigint")
    def norm(v: pd.Series) -> pd.Series:
        m = np.floor(np.stack(v.to_list()).astype(np.float64) * 1024).astype(np.int64)
        return pd.Series((m * m).sum(axis=1))

    return load(spark, sf_dir, "embeddings").select("vec_id", norm("embedding").alias("norm2"))


add("pandas_scalar", "SELECT vec_id, CAST(list_sum(list_transform(embedding, lambda v: CAST(floor(v::DOUBLE * 1024) * floor(v::DOUBLE * 1024) AS BIGINT))) AS BIGINT) AS norm2 FROM embeddings", _dot)


def _padded_udaf(spark, sf_dir):
    @F.pandas_udf("bigint")
    def load_of(t: pd.Series) -> int:
        return int(-(-t.sum() // 64) * 64)

    return P.pack_greedy(batches(spark, sf_dir), Q.C, Q.P).groupBy("group_id", "gb", "bin", "adapter_id").agg(load_of("tok_len").alias("padded"))


add("pandas_aggregate", f"{Q.greedy('ffd')} SELECT group_id, gb, bin, adapter_id, CAST({Q.pad('sum(tok_len)')} AS BIGINT) AS padded FROM packed GROUP BY 1, 2, 3, 4", _padded_udaf)


def _udtf(spark, sf_dir):
    @F.udtf(returnType="adapter_id string, tile int, n int")
    class Tiles:
        def __init__(self):
            self.key, self.n = None, 0

        def eval(self, row):
            self.key, self.n = row["adapter_id"], self.n + 1

        def terminate(self):
            for t in range(0, self.n, 32):
                yield self.key, t // 32, min(32, self.n - t)

    spark.udtf.register("al_tiles", Tiles)
    load(spark, sf_dir, "embeddings").select(F.concat(F.lit("a"), (F.col("label") % 4).cast("string")).alias("adapter_id"), "vec_id").createOrReplaceTempView("al_x")
    return spark.sql("SELECT * FROM al_tiles(TABLE(al_x) PARTITION BY adapter_id ORDER BY vec_id)")


add("table_function", """WITH r AS (SELECT 'a' || (label % 4)::VARCHAR AS adapter_id, row_number() OVER (PARTITION BY label % 4 ORDER BY vec_id) - 1 AS rn FROM embeddings)
SELECT adapter_id, CAST(rn // 32 AS INT) AS tile, CAST(count(*) AS INT) AS n FROM r GROUP BY 1, 2""", _udtf)


def _cogroup(spark, sf_dir):
    def join(left: pa.Table, right: pa.Table) -> pa.Table:
        key = left.column("lang")[0] if left.num_rows else right.column("m_lang")[0]
        return pa.table({"lang": pa.array([key.as_py()]), "docs": pa.array([left.num_rows]), "labelled": pa.array([right.num_rows])})

    d = load(spark, sf_dir, "documents").select("doc_id", "lang")
    marked = d.join(load(spark, sf_dir, "labels").select("doc_id"), "doc_id", "left_semi").select(F.col("doc_id").alias("m_id"), F.col("lang").alias("m_lang"))
    return d.groupBy("lang").cogroup(marked.groupBy("m_lang")).applyInArrow(join, "lang string, docs bigint, labelled bigint")


add("cogrouped", "SELECT lang, count(*) AS docs, count(*) FILTER (doc_id IN (SELECT doc_id FROM labels)) AS labelled FROM documents GROUP BY 1", _cogroup)


def _map_arrow(spark, sf_dir):
    def run(batches_):
        for b in batches_:
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pc.cast(pc.utf8_length(b.column("text")), pa.int64())], names=["doc_id", "n"])

    return load(spark, sf_dir, "documents").select("doc_id", "text").mapInArrow(run, "doc_id bigint, n bigint")


add("map_partitions", "SELECT doc_id, length(text) AS n FROM documents", _map_arrow)
def _recursive(spark, sf_dir):
    """Next-fit as a recursive query, for inputs known to be small: customers of each nation into bins of 300."""
    sizes = load(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").cast("bigint").alias("k")).agg(F.count(F.lit(1)).alias("t"))
    nations = load(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("bigint").alias("k")).join(sizes, "k", "left")
    nations.select("k", F.coalesce("t", F.lit(0).cast("bigint")).alias("t")).createOrReplaceTempView("al_sizes")
    return spark.sql("""WITH RECURSIVE w(k, bin, used) AS (
      SELECT CAST(-1 AS BIGINT), CAST(0 AS BIGINT), CAST(0 AS BIGINT)
      UNION ALL SELECT s.k, CASE WHEN w.used + s.t > 300 THEN w.bin + 1 ELSE w.bin END, CASE WHEN w.used + s.t > 300 THEN s.t ELSE w.used + s.t END
      FROM w JOIN al_sizes s ON s.k = w.k + 1)
    SELECT k, bin FROM w WHERE k >= 0""")


add("recursive_query", """WITH RECURSIVE s AS (SELECT CAST(n_nationkey AS BIGINT) AS k, (SELECT count(*) FROM customer WHERE c_nationkey = n_nationkey) AS t FROM nation),
w(k, bin, used) AS (SELECT CAST(-1 AS BIGINT), CAST(0 AS BIGINT), CAST(0 AS BIGINT)
UNION ALL SELECT s.k, CASE WHEN w.used + s.t > 300 THEN w.bin + 1 ELSE w.bin END, CASE WHEN w.used + s.t > 300 THEN s.t ELSE w.used + s.t END FROM w JOIN s ON s.k = w.k + 1)
SELECT k, bin FROM w WHERE k >= 0""", _recursive)
