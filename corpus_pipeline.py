"""A corpus from raw documents to packed sequences: rejects low quality, keeps one of each group of near copies, cuts repeated
passages, packs what is left. Each stage's result is written as Parquet and read again as the next one's documents."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecset import shipping
from vecset.llm import jaccard_join, packing, quality, suffix_dedup
from vecset.llm.common import written

#: SQL can't express the classifier's fit or the tokenizer; tests hold each stage against brute force.
ORACLE_SQL = None


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the documents that score at least 0.5. A null or empty text is scored like others (all features zero); ties with 0.5
    stay; rows that repeat are scored alike; very long texts go whole; an empty table gives an empty one; other columns pass as they
    are, whatever their names."""
    shipping.ship(spark)
    model = quality.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality.kept_documents(docs, model)


def ngram_jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the least doc_id of each group of documents that link at a similarity of 0.75. Null, empty and wordless texts link with
    nothing and stay; rows that repeat (same doc_id and text) become one; rows with a null doc_id stay; very long texts go whole; an
    empty table gives an empty one; other columns pass as they are, whatever their names."""
    shipping.ship(spark)
    return jaccard_join.one_of_each(docs, percent=75, words=5)


def suffix_array_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes every byte of a 400-byte string that also starts elsewhere. n_chars follows the text; emptied documents stay as rows.
    Null and empty texts stay as they are; of rows that repeat, each loses what the other has; very long texts go whole, in parts that
    overlap; an empty table gives an empty one; other columns pass as they are, whatever their names."""
    shipping.ship(spark)
    out = suffix_dedup.cleaned(docs, width=400)
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset). A null or empty text is one end id; rows that repeat are packed
    as often as they come; a text of over 2048 ids is cut; pieces of equal length are told apart by the order they are read in; an
    empty table gives an empty one; other columns are not read."""
    shipping.ship(spark)
    return packing.pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), 2048, end_id=0)


STAGES = [("quality_classifier", quality_classifier), ("ngram_jaccard_join", ngram_jaccard_join), ("suffix_array_dedup", suffix_array_dedup), ("best_fit_packing", best_fit_packing)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
