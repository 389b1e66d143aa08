"""The experiments' inputs on the given tables: vector sets, queries, relevant pairs, and training queries with their answers.

Texts become sets of token vectors mixed with their neighbours' (sources.tables). A query is a window of its document's tokens with
about a fifth of them left out; it asks for its document and the exact copies. By a hash, four in five queries are for training.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.iterate import cut
from . import tables as T

WINDOW = 16


@dataclass
class WorkSet:
    """fit: the sets that codebooks are fitted on."""

    name: str
    vectors: DataFrame
    queries: DataFrame
    qrels: DataFrame
    train_queries: DataFrame
    train: DataFrame
    fit: DataFrame


def _windows(token_ids: DataFrame, extra: DataFrame | None = None) -> DataFrame:
    """WINDOW tokens of each set that has half as many again, from a place that a hash gives, a fifth of them left out."""
    n = token_ids.groupBy("set_id").agg(F.count("*").alias("n")).where(F.col("n") >= WINDOW * 3 // 2)
    at = token_ids.join(n, "set_id").withColumn("from", F.pmod(F.xxhash64("set_id"), F.col("n") - WINDOW + 1))
    at = at.where((F.col("vec_no") >= F.col("from")) & (F.col("vec_no") < F.col("from") + WINDOW) & (F.pmod(F.xxhash64("set_id", "vec_no"), F.lit(5)) != 0))
    at = at.select("set_id", "vec_no", "vec_id")
    return at if extra is None else at.unionAll(extra.join(at.select("set_id").distinct(), "set_id", "left_semi"))


def _is_train(key: str):
    return F.pmod(F.xxhash64(F.col(key), F.lit(7)), F.lit(5)) != 0


def _work(name: str, sets: DataFrame, windows: DataFrame, qrels: DataFrame, vocab: DataFrame, may_train, may_ask, fit: DataFrame | None) -> WorkSet:
    vectors, asked = cut(T.mixed_vectors(sets, vocab)), cut(T.mixed_vectors(windows, vocab).withColumnRenamed("set_id", "query_id"))
    qrels = cut(qrels.join(asked.select("query_id").distinct(), "query_id", "left_semi").select("query_id", "set_id").distinct())
    pick = lambda df, ok: cut(df.where(ok))
    train = pick(qrels.where(F.col("query_id") == F.col("set_id")), _is_train("query_id") & may_train)
    return WorkSet(name, vectors, pick(asked, ~_is_train("query_id") & may_ask), pick(qrels, ~_is_train("query_id") & may_ask), pick(asked, _is_train("query_id") & may_train), train, vectors if fit is None else cut(vectors.join(fit, "set_id", "left_semi")))


def document_sets(spark: SparkSession, folder: str, name: str = "w1", most: int = 48) -> WorkSet:
    """w1: all documents. w2: codebooks, cutoff and shortcuts from the documents of one language, queries from the others."""
    docs = T.read_table(spark, folder, "documents", ["doc_id", "text", "lang"])
    vocab = T.vocabulary(spark, folder)
    ids = cut(T.token_sets(docs, "doc_id", "text", vocab.count(), most))
    same = docs.select("doc_id", F.md5("text").alias("h"))
    qrels = same.select(F.col("doc_id").alias("query_id"), "h").join(same.select(F.col("doc_id").alias("set_id"), "h"), "h").join(ids.select("set_id").distinct(), "set_id", "left_semi")
    if name == "w1":
        return _work(name, ids, _windows(ids), qrels, vocab, F.lit(True), F.lit(True), None)
    lang = cut(docs.select(F.col("doc_id").alias("set_id"), (F.col("lang") == "en").alias("en")))
    w = _work(name, ids, _windows(ids), qrels, vocab, F.lit(True), F.lit(True), lang.where("en").select("set_id"))
    by = lang.withColumnRenamed("set_id", "query_id")
    keep = lambda df, en: cut(df.join(by.where("en" if en else "not en").select("query_id"), "query_id", "left_semi"))
    return WorkSet(name, w.vectors, keep(w.queries, False), keep(w.qrels, False), keep(w.train_queries, True), keep(w.train, True), w.fit)


def page_sets(spark: SparkSession, folder: str, name: str = "w3", most: int = 40) -> WorkSet:
    """Two kinds of vectors in a set: tokens of a page's visible text and of its address, in different halves of the vocabulary. A query
    is a window of the text with the address. w3: relevant are the pages of the same host and first path segment. w4: the page itself."""
    pages = T.read_table(spark, folder, "pages", ["page_id", "url", "html"])
    vocab = T.vocabulary(spark, folder)
    half = max(1, vocab.count() // 2)
    seen = F.regexp_replace(F.regexp_replace("html", "(?is)<(script|style)[^>]*>.*?</\\1>|<!--.*?-->", " "), "<[^>]*>", " ")
    site = F.regexp_extract("url", "^[A-Za-z]+://[^/]*/[^/?#]*", 0)
    rows = pages.select(F.col("page_id").alias("set_id"), seen.alias("text"), site.alias("site"))
    text = T.token_sets(rows, "set_id", "text", half, most)
    link = T.token_sets(rows, "set_id", "site", half).select("set_id", (F.col("vec_no") + 1000).alias("vec_no"), (F.col("vec_id") + half).alias("vec_id"))
    ids = cut(text.unionAll(link))
    if name == "w3":
        qrels = rows.select(F.col("set_id").alias("query_id"), "site").join(rows.select("set_id", "site"), "site")
    else:
        qrels = rows.select(F.col("set_id").alias("query_id"), "set_id")
    return _work(name, ids, _windows(ids.where("vec_no < 1000"), ids.where("vec_no >= 1000")), qrels, vocab, F.lit(True), F.lit(True), None)


def work_set(spark: SparkSession, folder: str, name: str) -> WorkSet:
    return (document_sets if name in ("w1", "w2") else page_sets)(spark, folder, name)


def subset(work: WorkSet, parts: int, of: str = "sets") -> WorkSet:
    """One in `parts` of the sets (with the queries that have an answer left), or of each set's vectors; nested by hash thresholds."""
    if of == "sets":
        ok = lambda c: F.conv(F.substring(F.md5(F.col(c).cast("string")), 1, 4), 16, 10).cast("long") * parts < 65536
        vectors, qrels, train = work.vectors.where(ok("set_id")), work.qrels.where(ok("set_id")), work.train.where(ok("set_id"))
        keep = lambda df, pairs: df.join(pairs.select("query_id").distinct(), "query_id", "left_semi")
        return WorkSet(work.name, cut(vectors), cut(keep(work.queries, qrels)), cut(qrels), cut(keep(work.train_queries, train)), cut(train), cut(work.fit.where(ok("set_id"))))
    place = Window.partitionBy("set_id").orderBy(F.md5(F.concat_ws("-", F.col("set_id").cast("string"), F.col("vec_no").cast("string"))), "vec_no")
    thin = lambda df: cut(df.withColumn("_n", F.row_number().over(place)).withColumn("_m", F.count("*").over(Window.partitionBy("set_id"))).where(F.col("_n") <= F.ceil(F.col("_m") / parts)).drop("_n", "_m"))
    return WorkSet(work.name, thin(work.vectors), work.queries, work.qrels, work.train_queries, work.train, thin(work.fit))
