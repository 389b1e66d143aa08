"""Keys of the measures and of the experiment workloads on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import metrics as E
from ..operators import search as S
from ..operators.contain import contained
from ..operators.exact import exact_topk, top_k
from ..plans.limits import small
from .base import EXACT, Fixture, Registry, chamfer, ctes, top
from .distance_queries import QPAIRS

key = Registry()
QUERIES, ORACLES = key.queries, key.oracles

QRELS = "qrels AS (SELECT DISTINCT query_id, query_id AS set_id FROM qv UNION ALL SELECT DISTINCT query_id, (query_id + 1) % (SELECT count(DISTINCT set_id) FROM vec) FROM qv)"
HITS = f"hits AS MATERIALIZED ({top(chamfer(QPAIRS), 10)})"
PER = "per AS (SELECT query_id, count(rnk) AS found, count(*) AS relevant, min(rnk) AS first FROM qrels LEFT JOIN (SELECT * FROM hits WHERE rnk <= 10) h USING (query_id, set_id) GROUP BY ALL)"


def qrels(f) -> DataFrame:
    q = f.queries.select("query_id").distinct()
    return q.select("query_id", F.col("query_id").alias("set_id")).unionAll(q.select("query_id", ((F.col("query_id") + 1) % f.n_sets()).alias("set_id")))


def coded_hits(f, k=10) -> DataFrame:
    return top_k(S.qch(f.query_codes, f.coded, f.code_sims()), k)


def _measure(name, fold, measure):
    @key(f"WITH {ctes()}, {QRELS}, {HITS}, {PER} SELECT 10 AS k, round(avg({fold}), 6) AS value FROM per", name)
    def run(spark, folder):
        f = Fixture(spark, folder)
        return measure(coded_hits(f), qrels(f), 10)


_measure("recall_at_k", "found / relevant::DOUBLE", E.recall_at_k)
_measure("mrr_at_k", "coalesce(1.0 / first, 0.0)", E.mrr_at_k)
_measure("success_at_k", "CASE WHEN found > 0 THEN 1.0 ELSE 0.0 END", E.success_at_k)


@key(f"WITH {ctes()}, {HITS}, qrels AS (SELECT DISTINCT query_id, query_id AS set_id FROM qv), {PER} SELECT round(avg(found / relevant::DOUBLE), 6) - round(avg(CASE WHEN found > 0 THEN 1.0 ELSE 0.0 END), 6) AS difference FROM per")
def recall_equals_success(spark, folder):
    """With one relevant set for each query, recall and success agree."""
    f = Fixture(spark, folder)
    one = f.queries.select("query_id", F.col("query_id").alias("set_id")).distinct()
    a, b = E.recall_at_k(coded_hits(f), one, 10), E.success_at_k(coded_hits(f), one, 10)
    return a.select(F.col("value").alias("a")).join(small(b.select(F.col("value").alias("b")))).select((F.col("a") - F.col("b")).alias("difference"))


@key(f"WITH {ctes()}, {HITS}, ex AS ({EXACT}), qrels AS (SELECT query_id, set_id FROM ex), {PER} SELECT 10 AS k, round(avg(found / relevant::DOUBLE), 6) AS value FROM per")
def ann_recall(spark, folder):
    f = Fixture(spark, folder)
    return E.ann_recall(coded_hits(f), exact_topk(f.queries, f.vectors, 10), 10)


@key(f"WITH {ctes()}, {HITS}, ex AS ({EXACT}) SELECT count(*) AS candidates, count(*) FILTER (WHERE ex.rnk IS NULL) AS misses, round(count(*) FILTER (WHERE ex.rnk IS NULL) / count(*)::DOUBLE, 6) AS share FROM hits LEFT JOIN ex USING (query_id, set_id)")
def candidate_precision(spark, folder):
    f = Fixture(spark, folder)
    return E.candidate_precision(coded_hits(f), exact_topk(f.queries, f.vectors, 10))


@key("""WITH m AS (SELECT o_orderpriority AS method, (year(o_orderdate) * 12 + month(o_orderdate))::DOUBLE AS cost, count(*) AS n FROM orders GROUP BY ALL),
sweep AS (SELECT method, cost, (sum(n) OVER (PARTITION BY method ORDER BY cost) / sum(n) OVER (PARTITION BY method))::DOUBLE AS quality FROM m),
p AS (SELECT *, lag(cost) OVER w AS c0, lag(quality) OVER w AS q0 FROM sweep WINDOW w AS (PARTITION BY method ORDER BY cost))
SELECT method, round(min(CASE WHEN q0 IS NULL THEN cost ELSE c0 + (0.8::DOUBLE - q0) * (cost - c0) / (quality - q0) END), 6) AS cost FROM p WHERE quality >= 0.8::DOUBLE AND (q0 IS NULL OR q0 < 0.8::DOUBLE) GROUP BY ALL""")
def speedup_at_quality(spark, folder):
    """Orders of each priority as a method's curve: months are its cost, the share of the orders that came by then its quality."""
    from pyspark.sql import Window

    o = Fixture(spark, folder).table("orders").select(F.col("o_orderpriority").alias("method"), (F.year("o_orderdate") * 12 + F.month("o_orderdate")).cast("double").alias("cost"))
    n, by = o.groupBy("method", "cost").agg(F.count("*").alias("n")), Window.partitionBy("method")
    return E.speedup_at_quality(n.select("method", "cost", (F.sum("n").over(by.orderBy("cost")) / F.sum("n").over(by)).alias("quality")), 0.8)


# Workloads: relevance pairs ---------------------------------------------------------------------------------------------------


@key("SELECT item_id AS query_id, doc_id AS set_id FROM benchmark, documents WHERE contains(documents.text, benchmark.text)")
def w1_qrels(spark, folder):
    """Documents that hold a passage."""
    f = Fixture(spark, folder)
    return contained(f.table("documents").select("doc_id", "text"), f.table("benchmark").select("item_id", "text"))


@key("SELECT a.conv_id * 1000 + a.turn AS query_id, b.conv_id * 1000 + b.turn AS set_id FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1 WHERE a.role = 'user' AND b.role = 'assistant'")
def w2_qrels(spark, folder):
    c = Fixture(spark, folder).table("conversations").select("conv_id", "turn", "role")
    nxt = c.where("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("turn").alias("t2"))
    return c.where("role = 'user'").join(nxt, ["conv_id", "turn"]).select((F.col("conv_id") * 1000 + F.col("turn")).alias("query_id"), (F.col("conv_id") * 1000 + F.col("t2")).alias("set_id"))


@key("WITH p AS (SELECT page_id, regexp_extract(url, '^[a-z]+://[^/]*/[^/?#]*') AS site FROM pages) SELECT a.page_id AS query_id, b.page_id AS set_id FROM p a JOIN p b USING (site) WHERE a.page_id % 10 = 0 AND a.page_id <> b.page_id")
def w3_qrels(spark, folder):
    p = Fixture(spark, folder).table("pages").select("page_id", F.regexp_extract("url", "^[a-z]+://[^/]*/[^/?#]*", 0).alias("site"))
    q = p.where("page_id % 10 = 0").select(F.col("page_id").alias("query_id"), "site")
    return p.join(q, "site").where("query_id <> page_id").select("query_id", F.col("page_id").alias("set_id"))


@key("SELECT page_id AS query_id, page_id AS set_id FROM pages")
def w4_qrels(spark, folder):
    return Fixture(spark, folder).table("pages").select(F.col("page_id").alias("query_id"), F.col("page_id").alias("set_id"))


def level(col: str) -> str:
    return f"CAST(concat('0x', substr(md5({col}::VARCHAR), 1, 4)) AS BIGINT)"


@key(f"SELECT part, count(*) AS sets FROM documents, (VALUES (1), (2), (4), (8)) t(part) WHERE {level('doc_id')} * part < 65536 GROUP BY ALL")
def w13_subset_sizes(spark, folder):
    """Nested subsets: N, N/2, N/4, N/8."""
    d = Fixture(spark, folder).table("documents").select("doc_id").withColumn("h", F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 4), 16, 10).cast("long"))
    return d.select(F.explode(F.array(*[F.lit(p) for p in (1, 2, 4, 8)])).alias("part"), "h").where("h * part < 65536").groupBy("part").agg(F.count("*").alias("sets"))


@key(f"SELECT share, count(*) AS pairs FROM documents, (VALUES (5), (10), (20), (40)) t(share) WHERE {level('doc_id')} * 100 < share * 65536 GROUP BY ALL")
def w14_train_samples(spark, folder):
    d = Fixture(spark, folder).table("documents").select("doc_id").withColumn("h", F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 4), 16, 10).cast("long"))
    return d.select(F.explode(F.array(*[F.lit(p) for p in (5, 10, 20, 40)])).alias("share"), "h").where("h * 100 < share * 65536").groupBy("share").agg(F.count("*").alias("pairs"))


@key(f"WITH {ctes()} SELECT r, CAST(count(*) AS BIGINT) AS memberships FROM prof, (VALUES (1), (2), (3), (10)) t(r) WHERE rnk <= r GROUP BY ALL")
def w16_clusters_per_set(spark, folder):
    p = Fixture(spark, folder).profile()
    return p.select(F.explode(F.array(*[F.lit(r) for r in (1, 2, 3, 10)])).alias("r"), "rnk").where("rnk <= r").groupBy("r").agg(F.count("*").alias("memberships"))


@key(f"WITH {ctes()} {EXACT}")
def w17_exact_truth(spark, folder):
    f = Fixture(spark, folder)
    return exact_topk(f.queries, f.vectors, 10)
