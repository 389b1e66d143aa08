"""Keys of the relational operators, sources and functions around retrieval. Most are one plan and one SQL text."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..streaming import windows as WN
from .base import Fixture, Registry

key = Registry()
QUERIES, ORACLES = key.queries, key.oracles


def plan(name: str, oracle: str | None, build):
    """build(t): t(name) reads a table."""
    key(oracle, name)(lambda spark, folder: build(Fixture(spark, folder).table))


plan("scan_pruned", "SELECT doc_id, n_chars FROM documents WHERE lang = 'en' AND n_chars > 500", lambda t: t("documents").where("lang = 'en' and n_chars > 500").select("doc_id", "n_chars"))
plan("filter_docs", "SELECT d.doc_id, d.lang FROM documents d JOIN labels l USING (doc_id) WHERE l.quality = 1 AND l.toxic = 0 AND d.source IN ('src0', 'src1', 'src2')", lambda t: t("documents").where(F.col("source").isin("src0", "src1", "src2")).join(t("labels").where("quality = 1 and toxic = 0"), "doc_id").select("doc_id", "lang"))
JOIN_SQL = "SELECT o_orderkey, c_mktsegment, o_orderstatus FROM orders JOIN customer ON o_custkey = c_custkey"
for _name, _hint in (("join_broadcast", "broadcast"), ("join_merge", "merge"), ("join_hash", "shuffle_hash")):
    plan(_name, JOIN_SQL, lambda t, h=_hint: t("orders").join(t("customer").hint(h), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment", "o_orderstatus"))
plan("join_outer", "SELECT n_name, count(s_suppkey) AS suppliers FROM nation LEFT JOIN supplier ON n_nationkey = s_nationkey GROUP BY ALL", lambda t: t("nation").join(t("supplier"), F.col("n_nationkey") == F.col("s_nationkey"), "left").groupBy("n_name").agg(F.count("s_suppkey").alias("suppliers")))
plan("semi_relevant", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)", lambda t: t("documents").join(t("labels").where("quality = 1"), "doc_id", "left_semi").select("doc_id"))
plan("anti_missed", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)", lambda t: t("documents").join(t("labels"), "doc_id", "left_anti").select("doc_id"))
plan("theta_price_band", "SELECT s_suppkey, r_regionkey FROM supplier JOIN region ON s_acctbal > r_regionkey * 2000", lambda t: t("supplier").join(F.broadcast(t("region")), F.col("s_acctbal") > F.col("r_regionkey") * 2000).select("s_suppkey", "r_regionkey"))
plan("range_join_sizes", "SELECT a.doc_id AS a, b.doc_id AS b FROM documents a JOIN documents b ON b.n_chars BETWEEN a.n_chars AND a.n_chars + 5 WHERE a.doc_id < b.doc_id", lambda t: _bands(t("documents").select("doc_id", "n_chars"), 5))
plan("asof_events", "SELECT event_id, prev FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prev FROM events)", lambda t: t("events").select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), True).over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)).alias("prev")))
plan("interval_join_events", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE", lambda t: t("events").select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta")).join(t("events").select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb")), "user_id").where("tb > ta and tb <= ta + interval 30 minutes").select("a", "b"))
plan("agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS quantity, round(avg(l_discount), 6) AS discount FROM lineitem GROUP BY ALL", lambda t: t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount")))
plan("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY ALL", lambda t: t("lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers")))
plan("agg_filter", "SELECT source, count(*) FILTER (WHERE lang = 'en') AS english, count(*) AS n FROM documents GROUP BY ALL", lambda t: t("documents").groupBy("source").agg(F.count(F.when(F.col("lang") == "en", 1)).alias("english"), F.count("*").alias("n")))
plan("agg_minmax_by", "SELECT lang, arg_max(doc_id, (n_chars, doc_id)) AS longest, arg_min(doc_id, (n_chars, doc_id)) AS shortest FROM documents GROUP BY ALL", lambda t: t("documents").groupBy("lang").agg(F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("longest"), F.min_by("doc_id", F.struct("n_chars", "doc_id")).alias("shortest")))
plan("agg_approx", None, lambda t: t("lineitem").agg(F.approx_count_distinct("l_orderkey").alias("orders"), F.percentile_approx("l_quantity", 0.5).alias("median")))
_Q = "(SELECT lang, source, n_chars FROM documents)"
plan("metrics_cube", f"SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM {_Q} GROUP BY CUBE (lang, source)", lambda t: t("documents").cube("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars")))
plan("metrics_rollup", f"SELECT lang, source, count(*) AS n FROM {_Q} GROUP BY ROLLUP (lang, source)", lambda t: t("documents").rollup("lang", "source").agg(F.count("*").alias("n")))
plan("metrics_grouping_sets", f"SELECT lang, source, count(*) AS n FROM {_Q} GROUP BY GROUPING SETS ((lang), (source), ())", lambda t: t("documents").groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count("*").alias("n")))
plan("metrics_pivot", "SELECT source, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'en') AS en FROM documents GROUP BY ALL", lambda t: t("documents").groupBy("source").pivot("lang", ["de", "en"]).agg(F.count(F.lit(1))).fillna(0))


def _w():
    return Window.partitionBy("lang").orderBy("n_chars", "doc_id")


plan("win_rank", "SELECT doc_id, rank() OVER (PARTITION BY lang ORDER BY n_chars) AS r, dense_rank() OVER (PARTITION BY lang ORDER BY n_chars) AS d, row_number() OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS n FROM documents", lambda t: t("documents").select("doc_id", F.rank().over(Window.partitionBy("lang").orderBy("n_chars")).alias("r"), F.dense_rank().over(Window.partitionBy("lang").orderBy("n_chars")).alias("d"), F.row_number().over(_w()).alias("n")))
plan("win_ntile", "SELECT doc_id, ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS q FROM documents", lambda t: t("documents").select("doc_id", F.ntile(4).over(_w()).alias("q")))
plan("win_lag", "SELECT doc_id, lag(doc_id) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS before, lead(doc_id) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS after FROM documents", lambda t: t("documents").select("doc_id", F.lag("doc_id").over(_w()).alias("before"), F.lead("doc_id").over(_w()).alias("after")))
plan("win_running", "SELECT doc_id, CAST(sum(n_chars) OVER (PARTITION BY lang ORDER BY n_chars, doc_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS run FROM documents", lambda t: t("documents").select("doc_id", F.sum("n_chars").over(_w().rowsBetween(Window.unboundedPreceding, 0)).alias("run")))
plan("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS hour FROM events", lambda t: t("events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_timestamp(F.col("ts").cast("timestamp"))).rangeBetween(-3600, 0)).alias("hour")))
plan("topk_global", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20", lambda t: t("documents").select("doc_id", "n_chars").orderBy(F.col("n_chars").desc(), "doc_id").limit(20))
plan("topk_group", "SELECT lang, doc_id FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS n FROM documents) WHERE n <= 3", lambda t: t("documents").withColumn("n", F.row_number().over(Window.partitionBy("lang").orderBy(F.col("n_chars").desc(), "doc_id"))).where("n <= 3").select("lang", "doc_id"))
plan("sort_offset", "SELECT doc_id FROM documents ORDER BY n_chars, doc_id LIMIT 10 OFFSET 5", lambda t: t("documents").orderBy("n_chars", "doc_id").offset(5).limit(10).select("doc_id"))
_A, _B = "SELECT doc_id FROM documents WHERE doc_id % 2 = 0", "SELECT doc_id FROM documents WHERE doc_id % 3 = 0"
plan("set_union", f"{_A} UNION {_B}", lambda t: t("documents").where("doc_id % 2 = 0").select("doc_id").union(t("documents").where("doc_id % 3 = 0").select("doc_id")).distinct())
plan("set_intersect", f"{_A} INTERSECT {_B}", lambda t: t("documents").where("doc_id % 2 = 0").select("doc_id").intersect(t("documents").where("doc_id % 3 = 0").select("doc_id")))
plan("set_except", f"{_A} EXCEPT {_B}", lambda t: t("documents").where("doc_id % 2 = 0").select("doc_id").subtract(t("documents").where("doc_id % 3 = 0").select("doc_id")))
plan("tokenize_docs", "SELECT doc_id, CAST(len(list_filter(regexp_split_to_array(lower(text), '[^a-z]+'), lambda x: x <> '')) AS INTEGER) AS n FROM documents", lambda t: t("documents").select("doc_id", F.size(F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: w != "")).alias("n")))
plan("token_codes", "SELECT w, CAST(concat('0x', substr(md5(w), 1, 8)) AS BIGINT) % 500 AS vec_id FROM (SELECT DISTINCT unnest(list_filter(regexp_split_to_array(lower(text), '[^a-z]+'), lambda x: x <> '')) AS w FROM benchmark)", lambda t: t("benchmark").select(F.explode(F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: w != "")).alias("w")).distinct().select("w", (F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("long") % 500).alias("vec_id")))
plan("html_text", "SELECT page_id, md5(trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \\t\\n]+', ' ', 'g'), ' ')) AS h FROM pages", lambda t: t("pages").select("page_id", F.md5(F.trim(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), "[ \\t\\n]+", " "))).alias("h")))
plan("str_misc", "SELECT c_custkey, upper(c_name) AS u, length(c_name) AS n, substr(c_name, 1, 4) AS s, replace(c_mktsegment, 'A', 'x') AS r FROM customer", lambda t: t("customer").select("c_custkey", F.upper("c_name").alias("u"), F.length("c_name").cast("long").alias("n"), F.substring("c_name", 1, 4).alias("s"), F.replace("c_mktsegment", F.lit("A"), F.lit("x")).alias("r")))
plan("date_features", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofyear(o_orderdate) AS d, quarter(o_orderdate) AS q FROM orders", lambda t: t("orders").select("o_orderkey", *(f("o_orderdate").cast("long").alias(a) for f, a in ((F.year, "y"), (F.month, "m"), (F.dayofyear, "d"), (F.quarter, "q")))))
plan("vec_norm", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 4) AS norm FROM embeddings", lambda t: t("embeddings").select("vec_id", F.round(F.sqrt(F.reduce("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))), 4).alias("norm")))
plan("arrays_guard", "SELECT a.lang, list_has_any(a.s, b.s) AS shared FROM (SELECT lang, list(DISTINCT source) AS s FROM documents GROUP BY ALL) a, (SELECT list(DISTINCT source) AS s FROM documents WHERE lang = 'en') b", lambda t: t("documents").groupBy("lang").agg(F.collect_set("source").alias("s")).join(F.broadcast(t("documents").where("lang = 'en'").agg(F.collect_set("source").alias("e")))).select("lang", F.arrays_overlap("s", "e").alias("shared")))
plan("array_misc", "SELECT vec_id, CAST(len(list_distinct(list_transform(embedding[1:8], lambda x: round(x::DOUBLE, 1)))) AS BIGINT) AS kinds, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS up FROM embeddings", lambda t: t("embeddings").select("vec_id", F.size(F.array_distinct(F.transform(F.slice("embedding", 1, 8), lambda x: F.round(x.cast("double"), 1) + 0.0))).cast("long").alias("kinds"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("up")))
plan("json_props", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events", lambda t: t("events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")))
plan("hash_sample", "SELECT doc_id FROM documents WHERE substr(md5(doc_id::VARCHAR), 1, 1) < '4'", lambda t: t("documents").where(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 1) < "4").select("doc_id"))
plan("sketch_sizes", None, lambda t: t("documents").agg(F.hll_sketch_estimate(F.hll_sketch_agg("source")).alias("sources")))
plan("tumbling_sets", "SELECT user_id, CAST(epoch_us(ts) // 604800000000 AS BIGINT) AS week, count(*) AS n FROM events GROUP BY ALL", lambda t: WN.tumbling(t("events"), 604_800))
plan("sliding_sets", "SELECT user_id, d - k AS start_day, count(*) AS n FROM (SELECT user_id, CAST(epoch_us(ts) // 86400000000 AS BIGINT) AS d FROM events), (SELECT CAST(range AS BIGINT) AS k FROM range(7)) GROUP BY ALL", lambda t: WN.sliding(t("events"), 7))
plan("session_sets", "SELECT user_id, s, count(*) AS n FROM (SELECT user_id, CAST(sum(CASE WHEN gap THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS s FROM (SELECT *, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) >= INTERVAL 12 HOUR, false) AS gap FROM events)) GROUP BY ALL", lambda t: WN.sessions(t("events"), 43_200))


def _bands(d, width):
    """Sizes within `width` above: rows meet in buckets of that width, so each goes to two of them and no pair is made twice."""
    a = d.select(F.col("doc_id").alias("a"), F.col("n_chars").alias("na"), F.explode(F.sequence(F.floor(F.col("n_chars") / width), F.floor((F.col("n_chars") + width) / width))).alias("band"))
    b = d.select(F.col("doc_id").alias("b"), F.col("n_chars").alias("nb"), F.floor(F.col("n_chars") / width).alias("band"))
    return a.join(b, "band").where((F.col("nb") >= F.col("na")) & (F.col("nb") <= F.col("na") + width) & (F.col("a") < F.col("b"))).select("a", "b")
