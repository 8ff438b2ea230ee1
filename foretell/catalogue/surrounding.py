"""Surrounding operators of predictive queries, each beside its text for another engine."""

from __future__ import annotations

import uuid

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import draws
from ..operators import relational as R
from ..operators.nearest import nearest
from ..sources.tables import TABLES, shared_dir, table, write
from .registry import entry, r6

Spark = SparkSession


@entry("scan_parquet_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def scan_parquet_counts(spark: Spark, d: str) -> DataFrame:
    out = None
    for t in TABLES:
        one = table(spark, d, t).agg(F.count(F.lit(1)).alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.unionByName(one)
    return out


def _round_trip(kind: str):
    def run(spark: Spark, d: str) -> DataFrame:
        df = table(spark, d, "nation")
        path = f"{shared_dir(spark)}/foretell-{kind}-{uuid.uuid4().hex}"
        write(df, path, kind)
        return spark.read.schema(df.schema).format(kind).load(path)

    return run


for _kind in ("csv", "json", "orc", "parquet"):
    entry(f"roundtrip_{_kind}", "SELECT n_nationkey, n_name, n_regionkey FROM nation")(_round_trip(_kind))


@entry("project_revenue", "SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) AS revenue FROM lineitem")
def project_revenue(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax")), 6).alias("revenue"))


@entry("filter_conjunction", "SELECT count(*) AS n, round(sum(l_extendedprice * l_discount), 2) AS revenue FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01' AND l_shipdate < TIMESTAMP '1998-01-01' AND l_discount BETWEEN 0.02 AND 0.08 AND l_quantity < 24")
def filter_conjunction(spark: Spark, d: str) -> DataFrame:
    df = table(spark, d, "lineitem").filter("l_shipdate >= TIMESTAMP '1997-01-01' AND l_shipdate < TIMESTAMP '1998-01-01' AND l_discount BETWEEN 0.02 AND 0.08 AND l_quantity < 24")
    return df.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(F.col("l_extendedprice") * F.col("l_discount")), 2).alias("revenue"))


@entry("filter_in_like_null", "SELECT source, count(*) AS n FROM documents LEFT JOIN labels USING (doc_id) WHERE lang IN ('en', 'de') AND text LIKE '%th%' AND quality IS NULL GROUP BY source")
def filter_in_like_null(spark: Spark, d: str) -> DataFrame:
    df = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left")
    return df.filter(F.col("lang").isin("en", "de") & F.col("text").like("%th%") & F.col("quality").isNull()).groupBy("source").agg(F.count(F.lit(1)).alias("n"))


@entry("case_bucket", "SELECT CASE WHEN c_acctbal < 0 THEN 'negative' WHEN c_acctbal < 5000 THEN 'small' ELSE 'large' END AS bucket, count(*) AS n FROM customer GROUP BY 1")
def case_bucket(spark: Spark, d: str) -> DataFrame:
    bucket = F.when(F.col("c_acctbal") < 0, "negative").when(F.col("c_acctbal") < 5000, "small").otherwise("large")
    return table(spark, d, "customer").groupBy(bucket.alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


@entry("join_inner_equi", "SELECT doc_id, source, quality, toxic FROM documents JOIN labels USING (doc_id)")
def join_inner_equi(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").select("doc_id", "source", "quality", "toxic")


@entry("join_sortmerge", "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_sortmerge(spark: Spark, d: str) -> DataFrame:
    o, lines = table(spark, d, "orders"), table(spark, d, "lineitem")
    return o.hint("merge").join(lines, o["o_orderkey"] == lines["l_orderkey"]).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@entry("join_broadcast", "SELECT r_name, n_name, count(*) AS suppliers FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")
def join_broadcast(spark: Spark, d: str) -> DataFrame:
    # nation and region have 25 and 5 rows at any scale
    s, n, r = table(spark, d, "supplier"), F.broadcast(table(spark, d, "nation")), F.broadcast(table(spark, d, "region"))
    return s.join(n, F.col("s_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("suppliers"))


@entry("join_left_missing", "SELECT lang, count(*) AS n, count(quality) AS labelled FROM documents LEFT JOIN labels USING (doc_id) GROUP BY lang")
def join_left_missing(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left").groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.count("quality").alias("labelled"))


@entry("join_full", "SELECT d.doc_id IS NOT NULL AS has_text, l.doc_id IS NOT NULL AS has_label, count(*) AS n FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id GROUP BY 1, 2")
def join_full(spark: Spark, d: str) -> DataFrame:
    a, b = table(spark, d, "documents").select(F.col("doc_id").alias("a")), table(spark, d, "labels").select(F.col("doc_id").alias("b"))
    return a.join(b, F.col("a") == F.col("b"), "full").groupBy(F.col("a").isNotNull().alias("has_text"), F.col("b").isNotNull().alias("has_label")).agg(F.count(F.lit(1)).alias("n"))


@entry("join_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left_semi").select("doc_id", "lang")


@entry("join_anti", "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left_anti").select("doc_id", "lang")


@entry("join_cross_models", "SELECT id, round(avg(CASE WHEN a * l_quantity + b * l_extendedprice / 1000 > c THEN 1.0 ELSE 0.0 END), 6) AS share FROM lineitem, (VALUES (1, 1.0, 0.5, 42.0), (2, 1.0, 0.0, 25.0), (3, 0.0, 1.0, 53.0)) AS m(id, a, b, c) GROUP BY id")
def join_cross_models(spark: Spark, d: str) -> DataFrame:
    models = spark.createDataFrame([(1, 1.0, 0.5, 42.0), (2, 1.0, 0.0, 25.0), (3, 0.0, 1.0, 53.0)], "id int, a double, b double, c double")
    hit = F.when(F.expr("a * l_quantity + b * l_extendedprice / 1000 > c"), 1.0).otherwise(0.0)
    return table(spark, d, "lineitem").crossJoin(F.broadcast(models)).groupBy("id").agg(r6(F.avg(hit)).alias("share"))


@entry("join_theta", "SELECT name, count(*) AS n FROM part JOIN (VALUES ('low', 1000.0), ('middle', 1500.0), ('high', 2000.0)) AS t(name, most) ON p_retailprice < most GROUP BY name")
def join_theta(spark: Spark, d: str) -> DataFrame:
    t = spark.createDataFrame([("low", 1000.0), ("middle", 1500.0), ("high", 2000.0)], "name string, most double")
    return table(spark, d, "part").join(F.broadcast(t), F.col("p_retailprice") < F.col("most")).groupBy("name").agg(F.count(F.lit(1)).alias("n"))


@entry("join_range_bucket", "SELECT bucket, count(*) AS n FROM events JOIN (VALUES (0, -1e9, 10.0), (1, 10.0, 50.0), (2, 50.0, 100.0), (3, 100.0, 1e9)) AS b(bucket, lo, hi) ON value >= lo AND value < hi GROUP BY bucket")
def join_range_bucket(spark: Spark, d: str) -> DataFrame:
    b = spark.createDataFrame([(0, -1e9, 10.0), (1, 10.0, 50.0), (2, 50.0, 100.0), (3, 100.0, 1e9)], "bucket int, lo double, hi double")
    return R.range_join(table(spark, d, "events"), "value", b, "lo", "hi").groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


@entry("join_asof", "SELECT p.event_id, p.user_id, max_by(e.value, (e.ts, e.value)) AS last_value FROM events p LEFT JOIN (SELECT * FROM events WHERE event_type <> 'purchase') e ON e.user_id = p.user_id AND e.ts <= p.ts WHERE p.event_type = 'purchase' GROUP BY 1, 2".replace("max_by(e.value, (e.ts, e.value))", "arg_max(e.value, epoch_us(e.ts) * 1000.0 + e.value / 1e6)"))
def join_asof(spark: Spark, d: str) -> DataFrame:
    e = table(spark, d, "events")
    buys = e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts")
    other = e.filter("event_type <> 'purchase'").select("user_id", "ts", F.col("value").alias("last_value"))
    return R.as_of(buys, other, ["user_id"], "ts", "ts", ["last_value"]).select("event_id", "user_id", "last_value")


@entry("join_interval", "SELECT p.event_id, count(*) AS clicks FROM events p JOIN events c ON c.user_id = p.user_id AND c.ts <= p.ts AND CAST(floor(epoch(p.ts)) AS BIGINT) - CAST(floor(epoch(c.ts)) AS BIGINT) < 86400 WHERE p.event_type = 'purchase' AND c.event_type = 'click' GROUP BY 1")
def join_interval(spark: Spark, d: str) -> DataFrame:
    e = table(spark, d, "events")
    buys = e.filter("event_type = 'purchase'").select("event_id", "user_id", F.col("ts").alias("bought"))
    clicks = e.filter("event_type = 'click'").select("user_id", F.col("ts").alias("clicked"))
    return R.interval_join(buys, clicks, "user_id", "bought", "clicked", 86400).groupBy("event_id").agg(F.count(F.lit(1)).alias("clicks"))


@entry("join_lateral", "SELECT o.o_orderpriority, count(*) AS n FROM orders o, LATERAL (SELECT l_linenumber FROM lineitem WHERE l_orderkey = o.o_orderkey AND l_quantity > 45) AS big GROUP BY 1")
def join_lateral(spark: Spark, d: str) -> DataFrame:
    table(spark, d, "orders").createOrReplaceTempView("_lateral_orders")
    table(spark, d, "lineitem").createOrReplaceTempView("_lateral_lines")
    return spark.sql("SELECT o.o_orderpriority, count(*) AS n FROM _lateral_orders o, LATERAL (SELECT l_linenumber FROM _lateral_lines WHERE l_orderkey = o.o_orderkey AND l_quantity > 45) big GROUP BY 1")


@entry("agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_extendedprice), 6) AS price FROM lineitem GROUP BY 1, 2")
def agg_hash(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), r6(F.avg("l_extendedprice")).alias("price"))


@entry("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def agg_distinct(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@entry("agg_sketch")
def agg_sketch(spark: Spark, d: str) -> DataFrame:
    e = table(spark, d, "events")
    return e.groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id", F.lit(14))).alias("users_hll"), F.percentile_approx("value", 0.5, 10000).alias("median"))


@entry("agg_stats", "SELECT round(avg(l_quantity), 6) AS mean, round(stddev_pop(l_quantity), 6) AS deviation, min(l_quantity) AS low, max(l_quantity) AS high, median(l_quantity) AS middle, round(avg(l_tax), 6) AS mean_tax FROM lineitem")
def agg_stats(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "lineitem").agg(r6(F.avg("l_quantity")).alias("mean"), r6(F.stddev_pop("l_quantity")).alias("deviation"), F.min("l_quantity").alias("low"), F.max("l_quantity").alias("high"), F.median("l_quantity").alias("middle"), r6(F.avg("l_tax")).alias("mean_tax"))


@entry("agg_corr_regr", "SELECT round(corr(l_extendedprice, l_quantity), 6) AS correlation, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 4) AS intercept FROM lineitem")
def agg_corr_regr(spark: Spark, d: str) -> DataFrame:
    y, x = F.col("l_extendedprice"), F.col("l_quantity")
    return table(spark, d, "lineitem").agg(r6(F.corr(y, x)).alias("correlation"), F.round(F.regr_slope(y, x), 4).alias("slope"), F.round(F.regr_intercept(y, x), 4).alias("intercept"))


@entry("agg_collect", "SELECT conv_id, array_to_string(list(role ORDER BY turn), ',') AS roles FROM conversations GROUP BY conv_id")
def agg_collect(spark: Spark, d: str) -> DataFrame:
    turns = F.array_sort(F.collect_list(F.struct("turn", "role")))
    return table(spark, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(turns, lambda x: x["role"]), ",").alias("roles"))


@entry("agg_cube_docs", "SELECT lang, source, count(*) AS n, grouping_id(lang, source) AS level FROM documents GROUP BY CUBE (lang, source)")
def agg_cube_docs(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "documents").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))


@entry("agg_rollup_lines", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS quantity FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def agg_rollup_lines(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"))


@entry("agg_grouping_sets", "SELECT lang, source, sum(n_chars) AS chars FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def agg_grouping_sets(spark: Spark, d: str) -> DataFrame:
    table(spark, d, "documents").createOrReplaceTempView("_sets_documents")
    return spark.sql("SELECT lang, source, sum(n_chars) AS chars FROM _sets_documents GROUP BY GROUPING SETS ((lang), (source), ())")


@entry("window_rank", "SELECT source, doc_id, rn, rk, dr FROM (SELECT source, doc_id, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars DESC, doc_id), v AS (PARTITION BY source ORDER BY n_chars DESC)) WHERE rn <= 3")
def window_rank(spark: Spark, d: str) -> DataFrame:
    w, v = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id"), Window.partitionBy("source").orderBy(F.desc("n_chars"))
    return table(spark, d, "documents").select("source", "doc_id", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr")).filter("rn <= 3")


@entry("window_ntile", "SELECT decile, count(*) AS n, round(min(o_totalprice), 2) AS low FROM (SELECT o_totalprice, ntile(10) OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey) AS decile FROM orders) GROUP BY decile")
def window_ntile(spark: Spark, d: str) -> DataFrame:
    w = Window.partitionBy("o_orderpriority").orderBy("o_totalprice", "o_orderkey")
    return table(spark, d, "orders").select("o_totalprice", F.ntile(10).over(w).alias("decile")).groupBy("decile").agg(F.count(F.lit(1)).alias("n"), F.round(F.min("o_totalprice"), 2).alias("low"))


@entry("window_lag", "SELECT event_id, round(value - lag(value) OVER w, 6) AS change, round(lead(value) OVER w, 6) AS following FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def window_lag(spark: Spark, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, d, "events").select("event_id", r6(F.col("value") - F.lag("value").over(w)).alias("change"), r6(F.lead("value").over(w)).alias("following"))


@entry("window_range", "SELECT event_id, count(*) OVER w AS n, round(avg(value) OVER w, 9) AS mean FROM events WINDOW w AS (PARTITION BY event_type ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW)")
def window_range(spark: Spark, d: str) -> DataFrame:
    e = R.trailing(table(spark, d, "events").select("event_id", "event_type", "ts", "value"), "event_type", F.unix_timestamp("ts"), "value", 86400)
    return e.select("event_id", F.col("_n").alias("n"), F.round(F.when(F.col("_values") > 0, F.col("_sum") / F.col("_values")), 9).alias("mean"))


@entry("sort_limit", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 50")
def sort_limit(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(50)


@entry("setop_union_intersect_except", "SELECT 'union' AS op, count(*) AS n FROM (SELECT n_nationkey FROM nation UNION SELECT s_nationkey FROM supplier) UNION ALL SELECT 'intersect', count(*) FROM (SELECT c_nationkey FROM customer INTERSECT SELECT s_nationkey FROM supplier) UNION ALL SELECT 'except_all', count(*) FROM (SELECT c_nationkey FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier)")
def setops(spark: Spark, d: str) -> DataFrame:
    n, s, c = table(spark, d, "nation").select("n_nationkey"), table(spark, d, "supplier").select("s_nationkey"), table(spark, d, "customer").select("c_nationkey")
    count = lambda df, op: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(op).alias("op"), "n")
    return count(n.union(s).distinct(), "union").unionByName(count(c.intersect(s), "intersect")).unionByName(count(c.exceptAll(s), "except_all"))


@entry("str_tokens", "SELECT lang, count(*) AS words, count(DISTINCT w) AS different FROM (SELECT lang, unnest(string_split(lower(text), ' ')) AS w FROM documents) WHERE w <> '' GROUP BY lang")
def str_tokens(spark: Spark, d: str) -> DataFrame:
    words = table(spark, d, "documents").select("lang", F.explode(F.split(F.lower("text"), " ")).alias("w")).filter("w <> ''")
    return words.groupBy("lang").agg(F.count(F.lit(1)).alias("words"), F.countDistinct("w").alias("different"))


@entry("str_hash_slots", "SELECT slot, count(*) AS n FROM (SELECT ('0x' || substr(md5(w), 1, 8))::UBIGINT % 64 AS slot FROM (SELECT unnest(string_split(text, ' ')) AS w FROM documents) WHERE w <> '') GROUP BY slot")
def str_hash_slots(spark: Spark, d: str) -> DataFrame:
    words = table(spark, d, "documents").select(F.explode(F.split("text", " ")).alias("w")).filter("w <> ''")
    slot = F.conv(F.substring(F.md5(F.col("w").cast("binary")), 1, 8), 16, 10).cast("long") % 64
    return words.groupBy(slot.alias("slot")).agg(F.count(F.lit(1)).alias("n"))


@entry("str_stats", "SELECT doc_id, length(text) - length(translate(text, '#$%&*|<>', '')) AS marks, length(text) - length(translate(text, '0123456789', '')) AS digits, round(len(list_distinct(string_split(text, ' '))) / CAST(len(string_split(text, ' ')) AS DOUBLE), 6) AS distinct_share FROM documents")
def str_stats(spark: Spark, d: str) -> DataFrame:
    t = F.col("text")
    return table(spark, d, "documents").select("doc_id", (F.length(t) - F.length(F.translate(t, "#$%&*|<>", ""))).cast("long").alias("marks"), (F.length(t) - F.length(F.translate(t, "0123456789", ""))).cast("long").alias("digits"), r6(F.size(F.array_distinct(F.split(t, " "))) / F.size(F.split(t, " "))).alias("distinct_share"))


@entry("html_strip", "SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS visible FROM pages")
def html_strip(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "pages").select("page_id", F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("visible"))


@entry("url_parts", "SELECT host, count(*) AS n, max(depth) AS depth FROM (SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, length(regexp_extract(url, '://[^/?#]*([^?#]*)', 1)) - length(replace(regexp_extract(url, '://[^/?#]*([^?#]*)', 1), '/', '')) AS depth FROM pages) GROUP BY host")
def url_parts(spark: Spark, d: str) -> DataFrame:
    path = F.regexp_extract("url", "://[^/?#]*([^?#]*)", 1)
    p = table(spark, d, "pages").select(F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"), (F.length(path) - F.length(F.replace(path, F.lit("/"), F.lit("")))).cast("long").alias("depth"))
    return p.groupBy("host").agg(F.count(F.lit(1)).alias("n"), F.max("depth").alias("depth"))


@entry("date_parts", "SELECT hour(ts) AS hour, isodow(ts) % 7 AS weekday, count(*) AS n, min(date_diff('day', DATE '1998-06-01', CAST(ts AS DATE))) AS first_day FROM events GROUP BY 1, 2")
def date_parts(spark: Spark, d: str) -> DataFrame:
    e = table(spark, d, "events").select(F.hour("ts").cast("long").alias("hour"), (F.dayofweek("ts") - 1).cast("long").alias("weekday"), F.datediff("ts", F.lit("1998-06-01").cast("date")).cast("long").alias("day"))
    return e.groupBy("hour", "weekday").agg(F.count(F.lit(1)).alias("n"), F.min("day").alias("first_day"))


@entry("math_link", "SELECT round(avg(1 / (1 + exp(-(l_quantity - 25.5) / 14.4))), 6) AS logistic, round(avg(ln(1 + l_extendedprice)), 6) AS logs, round(avg(least(1.0, greatest(0.0, l_tax * 20))), 6) AS clipped FROM lineitem")
def math_link(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "lineitem").agg(r6(F.avg(1 / (1 + F.exp(-(F.col("l_quantity") - 25.5) / 14.4)))).alias("logistic"), r6(F.avg(F.log1p("l_extendedprice"))).alias("logs"), r6(F.avg(F.least(F.lit(1.0), F.greatest(F.lit(0.0), F.col("l_tax") * 20)))).alias("clipped"))


@entry("array_dot", "SELECT vec_id, round(list_sum(list_transform(generate_series(1, 64), lambda i: CAST(embedding[i] AS DOUBLE) * i / 64.0)), 5) AS dot FROM embeddings")
def array_dot(spark: Spark, d: str) -> DataFrame:
    product = F.zip_with("embedding", F.sequence(F.lit(1), F.lit(64)), lambda v, i: v.cast("double") * i / F.lit(64.0))
    return table(spark, d, "embeddings").select("vec_id", (F.round(F.aggregate(product, F.lit(0.0), lambda a, x: a + x), 5) + 0.0).alias("dot"))


@entry("array_posexplode", "SELECT i - 1 AS pos, round(avg(CAST(embedding[i] AS DOUBLE)), 6) AS mean FROM embeddings, (SELECT unnest(generate_series(1, 64)) AS i) GROUP BY i")
def array_posexplode(spark: Spark, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select(F.posexplode("embedding").alias("pos", "v")).groupBy(F.col("pos").cast("long").alias("pos")).agg(r6(F.avg(F.col("v").cast("double"))).alias("mean"))


@entry("map_build", "SELECT lang, sum(n) AS n, max(CASE WHEN toxic = 1 THEN n END) AS toxic FROM (SELECT lang, toxic, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY 1, 2) GROUP BY lang")
def map_build(spark: Spark, d: str) -> DataFrame:
    n = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").groupBy("lang", "toxic").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("toxic", "n"))).alias("m"))
    return m.select("lang", F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("n"), F.try_element_at("m", F.lit(1)).alias("toxic"))


@entry("json_props", "SELECT event_type, round(avg(CAST(json_extract(props, '$.k') AS DOUBLE)), 6) AS mean_k, max(CAST(json_extract(props, '$.k') AS BIGINT)) AS most FROM events GROUP BY 1")
def json_props(spark: Spark, d: str) -> DataFrame:
    k = F.from_json("props", "k bigint")["k"]
    return table(spark, d, "events").groupBy("event_type").agg(r6(F.avg(k)).alias("mean_k"), F.max(k).alias("most"))


@entry("knn_exact", "SELECT probe, vec_id, rn FROM (SELECT p.vec_id AS probe, e.vec_id, row_number() OVER (PARTITION BY p.vec_id ORDER BY round(list_sum(list_transform(generate_series(1, 64), lambda i: CAST(p.embedding[i] AS DOUBLE) * CAST(e.embedding[i] AS DOUBLE))), 9) DESC, e.vec_id) AS rn FROM (SELECT * FROM embeddings WHERE vec_id % 50 = 0) p, embeddings e WHERE e.vec_id <> p.vec_id) WHERE rn <= 5")
def knn_exact(spark: Spark, d: str) -> DataFrame:
    """The queries of a search are every row whose id is divisible by 50, against all rows."""
    e = table(spark, d, "embeddings")
    return nearest(e, e.filter("vec_id % 50 = 0"), 5)


#: Benchmark windows up to which they are broadcast.
MAX_BROADCAST_WINDOWS = 200_000
_WINDOW_SQL = "list_filter(string_split(lower({}), ' '), lambda w: w <> '')"


@entry("overlap_benchmark", f"""
WITH d AS (SELECT doc_id, {_WINDOW_SQL.format("text")} AS ws FROM documents),
b AS (SELECT item_id, ws, least(10, len(ws)) AS size FROM (SELECT item_id, {_WINDOW_SQL.format("text")} AS ws FROM benchmark) WHERE len(ws) > 0),
bw AS (SELECT DISTINCT item_id, size, array_to_string(ws[i : i + size - 1], ' ') AS w FROM (SELECT *, unnest(generate_series(1, len(ws) - size + 1)) AS i FROM b)),
dw AS (SELECT doc_id, size, array_to_string(ws[i : i + size - 1], ' ') AS w FROM (SELECT doc_id, ws, size, unnest(generate_series(1, len(ws) - size + 1)) AS i FROM d, (SELECT DISTINCT size FROM bw) WHERE len(ws) >= size))
SELECT DISTINCT doc_id, item_id FROM dw JOIN bw USING (size, w)""")
def overlap_benchmark(spark: Spark, d: str) -> DataFrame:
    """Items of which ten consecutive words (or all, of fewer) stand in a document: an equality join of windows."""
    words = F.filter(F.split(F.lower("text"), " "), lambda w: w != "")

    def windows(rows: DataFrame) -> DataFrame:
        each = F.explode(F.sequence(F.lit(1), F.size("ws") - F.col("size") + 1)).alias("i")
        return rows.filter("size > 0 and size(ws) >= size").select("*", each).withColumn("w", F.array_join(F.slice("ws", F.col("i"), F.col("size")), " "))

    items = table(spark, d, "benchmark").select("item_id", words.alias("ws")).withColumn("size", F.least(F.lit(10), F.size("ws")))
    parts = windows(items).select("item_id", "size", "w").distinct()
    # at most ten sizes
    sizes = F.broadcast(parts.select("size").distinct())
    docs = windows(table(spark, d, "documents").select("doc_id", words.alias("ws")).crossJoin(sizes)).select("doc_id", "size", "w")
    parts = F.broadcast(parts) if parts.limit(MAX_BROADCAST_WINDOWS + 1).count() <= MAX_BROADCAST_WINDOWS else parts
    return docs.join(parts, ["size", "w"]).select("doc_id", "item_id").distinct()


@entry("sample_hash", f"SELECT count(*) AS n, round(sum(o_totalprice), 2) AS price FROM orders WHERE {draws.uniform_sql('sample:0', 'o_orderkey')} < 0.1")
def sample_hash(spark: Spark, d: str) -> DataFrame:
    from ..plans.tasks import downsample

    return downsample(table(spark, d, "orders"), "o_orderkey", 0.1).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("price"))


@entry("udf_arrow_score", "SELECT vec_id, round(list_sum(list_transform(generate_series(1, 64), lambda i: CAST(embedding[i] AS DOUBLE) / i)), 5) AS score FROM embeddings")
def udf_arrow_score(spark: Spark, d: str) -> DataFrame:
    @F.pandas_udf("double")
    def dot(v: pd.Series) -> pd.Series:
        w = 1.0 / np.arange(1, 65)
        return pd.Series(np.stack(v.to_numpy()).astype(float) @ w if len(v) else [], dtype=float)

    return table(spark, d, "embeddings").select("vec_id", (F.round(dot("embedding"), 5) + 0.0).alias("score"))


@entry("udaf_confusion", "SELECT quality, toxic, count(*) AS n FROM labels GROUP BY 1, 2")
def udaf_confusion(spark: Spark, d: str) -> DataFrame:
    @F.pandas_udf("long")
    def size(v: pd.Series) -> int:
        return len(v)

    return table(spark, d, "labels").groupBy("quality", "toxic").agg(size("doc_id").alias("n"))


@entry("udtf_grid", "SELECT a.i AS i, b.i AS j, a.i / 3.0 AS u, b.i / 3.0 AS v FROM (VALUES (0), (1), (2), (3)) a(i), (VALUES (0), (1), (2), (3)) b(i)")
def udtf_grid(spark: Spark, d: str) -> DataFrame:
    from pyspark.sql.functions import udtf

    @udtf(returnType="i int, j int, u double, v double")
    class GridPoints:
        def eval(self, n: int):
            for i in range(n):
                for j in range(n):
                    yield i, j, i / (n - 1), j / (n - 1)

    return GridPoints(F.lit(4))
