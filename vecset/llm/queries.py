"""The queries of this subpackage: each applies its operator to its whole table."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

RULES = [("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/")]
END_OF_TEXT = 50256


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import jaccard_join

    return jaccard_join.join(table(spark, sf_dir, "documents"), percent=75, words=5)


def op2_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import url_filter

    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    return url_filter.judge(pages, RULES, url_filter.labels_by_number(pages, table(spark, sf_dir, "labels")))


def op3_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import vectors

    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return vectors.nearest(rows, rows.where("vec_id % 20 = 0"), k=20)


def op4_near_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import vectors

    return vectors.near_duplicates(table(spark, sf_dir, "embeddings"), 0.98)


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import suffix_dedup

    return suffix_dedup.report(table(spark, sf_dir, "documents"), width=400)


def op6_token_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import token_files

    segments = token_files.write_segments(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), end_id=0)
    return token_files.read_documents(segments)


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import token_files

    flat = token_files.write_flat(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), END_OF_TEXT)
    return token_files.count_tokens(flat, END_OF_TEXT).select("doc_id", "file", "ordinal", "start", "n_tokens")


def op8_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import bpe

    return bpe.round_trip(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import packing

    return packing.pack_documents(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), 2048, end_id=0)


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import quality

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = quality.fit(docs, table(spark, sf_dir, "labels"))
    out = quality.score(docs, model)
    return out.select("doc_id", F.coalesce(quality.held_out("doc_id"), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


QUERIES = {f.__name__: f for f in (op1_jaccard_join, op2_url_filter, op3_nearest, op4_near_vectors, op5_suffix_dedup, op6_token_ids, op7_token_counts, op8_byte_bpe, op9_packing, op10_quality)}
ORACLES: dict[str, str] = {}
