"""Inputs as vector sets. Long form: (set_id, vec_no, v); see functions.distance for fixed point."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.distance import fixed_point
from ..plans.limits import TooLarge, driver_table


def read_table(spark: SparkSession, folder: str, name: str, columns: list[str] | None = None, where: str | None = None, fmt: str = "parquet") -> DataFrame:
    df = spark.read.format(fmt).load(f"{folder}/{name}.{fmt}")
    df = df.where(where) if where else df
    return df.select(*columns) if columns else df


def chunk_vectors(spark: SparkSession, folder: str, m: int = 4) -> DataFrame:
    """Every m embeddings in a row are a set, in fixed point."""
    e = read_table(spark, folder, "embeddings", ["vec_id", "embedding"])
    return e.select(F.expr(f"vec_id div {m}").alias("set_id"), (F.col("vec_id") % m).cast("int").alias("vec_no"), fixed_point(F.col("embedding")).alias("v"))


def chunk_queries(vectors: DataFrame, every: int = 10) -> DataFrame:
    return vectors.where(F.col("set_id") % every == 0).select(F.col("set_id").alias("query_id"), "vec_no", "v")


def vocabulary(spark: SparkSession, folder: str) -> DataFrame:
    """(vec_id, v): the embeddings as token vectors."""
    return read_table(spark, folder, "embeddings", ["vec_id", "embedding"]).select("vec_id", fixed_point(F.col("embedding")).alias("v"))


def words(text):
    """Lower-cased runs of letters, in order."""
    return F.filter(F.split(F.lower(text), "[^a-z]+"), lambda w: w != "")


def tokens(df: DataFrame, key: str, text: str, most: int | None = None) -> DataFrame:
    """(set_id, vec_no, token): lower-cased runs of letters, the first `most` where given."""
    found = F.slice(words(F.col(text)), 1, most) if most else words(F.col(text))
    return df.select(F.col(key).alias("set_id"), F.posexplode(found).alias("vec_no", "token"))


def token_sets(df: DataFrame, key: str, text: str, n_vec: int, most: int | None = None) -> DataFrame:
    """(set_id, vec_no, vec_id): a token's vector is the one that the head of its md5 names."""
    t = tokens(df, key, text, most)
    return t.select("set_id", "vec_no", (F.conv(F.substring(F.md5("token"), 1, 8), 16, 10).cast("long") % n_vec).alias("vec_id"))


def context_vectors(sets: DataFrame, vocab: DataFrame, weight: float = 0.25) -> DataFrame:
    """Token vectors mixed with their neighbours' and normalised: (set_id, vec_no, vec array<double>)."""
    v = sets.join(vocab.select("vec_id", F.transform("v", lambda x: x / 1000.0).alias("x")), "vec_id")
    w = Window.partitionBy("set_id").orderBy("vec_no")
    none = F.transform("x", lambda x: F.lit(0.0))
    mixed = v.select("set_id", "vec_no", F.zip_with(F.zip_with("x", F.coalesce(F.lag("x").over(w), none), lambda a, b: a + weight * b), F.coalesce(F.lead("x").over(w), none), lambda a, b: a + weight * b).alias("y"))
    norm = F.sqrt(F.reduce("y", F.lit(0.0), lambda s, x: s + x * x))
    return mixed.select("set_id", "vec_no", F.transform("y", lambda x: x / F.greatest(norm, F.lit(1e-12))).alias("vec"))


def mixed_vectors(sets: DataFrame, vocab: DataFrame, weight: float = 0.25) -> DataFrame:
    """context_vectors in fixed point: (set_id, vec_no int, v). Each task has the vocabulary as a matrix and mixes whole sets by array
    steps, in the same order of sums; with a vocabulary that no task should hold, the same by joins."""
    try:
        book = driver_table(vocab.select("vec_id", "v").orderBy("vec_id"))
    except TooLarge:
        return context_vectors(sets, vocab, weight).select("set_id", F.col("vec_no").cast("int").alias("vec_no"), fixed_point(F.col("vec")).alias("v"))
    names = book.column("vec_id").to_numpy()
    held = sets.sparkSession.sparkContext.broadcast((names, np.array(book.column("v").to_pylist(), np.int64).reshape(len(names), -1)))
    lists = sets.groupBy("set_id").agg(F.sort_array(F.collect_list(F.struct(F.col("vec_no").cast("int").alias("vec_no"), F.col("vec_id").cast("long").alias("vec_id")))).alias("t"))

    def run(batches):
        names, vectors = held.value
        for whole in batches:
            for batch in (whole.slice(i, 64) for i in range(0, whole.num_rows, 64)):
                lists = batch.column("t")
                row = np.repeat(np.arange(batch.num_rows), lists.value_lengths().to_numpy().astype(np.int64))
                no, vec = (lists.flatten().field(k).to_numpy(zero_copy_only=False) for k in (0, 1))
                at = np.minimum(np.searchsorted(names, vec), max(len(names) - 1, 0))
                there = names[at] == vec if len(names) else np.zeros(len(vec), bool)
                row, no, x = row[there], no[there], vectors[at[there]] / 1000.0 if len(names) else np.zeros((0, 1))
                if not len(row):
                    continue
                back, ahead = np.zeros_like(x), np.zeros_like(x)
                same = (row[1:] == row[:-1])[:, None]
                back[1:], ahead[:-1] = np.where(same, x[:-1], 0), np.where(same, x[1:], 0)
                y, total = x + weight * back + weight * ahead, np.zeros(len(x))
                for k in range(y.shape[1]):
                    total += y[:, k] * y[:, k]
                y = y / np.maximum(np.sqrt(total), 1e-12)[:, None] * 1000
                size = np.trunc(np.abs(y))
                v = (np.sign(y) * (size + (np.abs(y) - size >= 0.5))).astype(np.int64)  # halves go away from zero, as Spark's do
                v = pa.ListArray.from_arrays(pa.array(np.arange(0, v.size + 1, v.shape[1], dtype=np.int32)), pa.array(v.ravel()))
                yield pa.RecordBatch.from_arrays([batch.column("set_id").take(pa.array(row)), pa.array(no.astype(np.int32)), v], names=["set_id", "vec_no", "v"])

    return lists.mapInArrow(run, f"set_id {dict(sets.dtypes)['set_id']}, vec_no int, v array<long>")


def order_sets(spark: SparkSession, folder: str) -> DataFrame:
    """A set for each order, a vector of scaled numbers for each line."""
    line = read_table(spark, folder, "lineitem")
    by = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate")
    parts = [F.col("l_quantity") * 20, F.col("l_extendedprice") / 100, F.col("l_discount") * 10000, F.col("l_tax") * 10000]
    return line.select(F.col("l_orderkey").alias("set_id"), (F.row_number().over(by) - 1).alias("vec_no"), F.array(*[F.round(p).cast("long") for p in parts]).alias("v"))


def validate_sets(vectors: DataFrame, width: int) -> DataFrame:
    """(set_id, problem): vectors of another width, null components, no length."""
    bad = F.when(F.size("v") != width, "width").when(F.exists("v", lambda x: x.isNull()), "null").when(F.forall("v", lambda x: x == 0), "zero")
    return vectors.select("set_id", bad.alias("problem")).where("problem is not null")
