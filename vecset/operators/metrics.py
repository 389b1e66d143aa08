"""Measures of result lists (query_id, set_id, rnk) against relevant pairs (query_id, set_id). Averages go over all queries that have
a relevant set; one without hits counts 0."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _per_query(hits: DataFrame, qrels: DataFrame, k: int) -> DataFrame:
    first = hits.where(F.col("rnk") <= k).groupBy("query_id", "set_id").agg(F.min("rnk").alias("rnk"))
    both = qrels.select("query_id", "set_id").distinct().join(first, ["query_id", "set_id"], "left")
    return both.groupBy("query_id").agg(F.count("rnk").alias("found"), F.count("*").alias("relevant"), F.min("rnk").alias("first"))


def recall_at_k(hits: DataFrame, qrels: DataFrame, k: int) -> DataFrame:
    return _per_query(hits, qrels, k).agg(F.lit(k).alias("k"), F.round(F.avg(F.col("found") / F.col("relevant")), 6).alias("value"))


def mrr_at_k(hits: DataFrame, qrels: DataFrame, k: int) -> DataFrame:
    return _per_query(hits, qrels, k).agg(F.lit(k).alias("k"), F.round(F.avg(F.coalesce(1.0 / F.col("first"), F.lit(0.0))), 6).alias("value"))


def success_at_k(hits: DataFrame, qrels: DataFrame, k: int) -> DataFrame:
    return _per_query(hits, qrels, k).agg(F.lit(k).alias("k"), F.round(F.avg((F.col("found") > 0).cast("double")), 6).alias("value"))


def ann_recall(hits: DataFrame, exact_hits: DataFrame, k: int) -> DataFrame:
    return recall_at_k(hits, exact_hits.where(F.col("rnk") <= k), k)


def candidate_precision(cands: DataFrame, exact_hits: DataFrame) -> DataFrame:
    """(candidates, misses, share): candidates that are not in the final exact list."""
    c = cands.select("query_id", "set_id").distinct()
    miss = c.join(exact_hits.select("query_id", "set_id"), ["query_id", "set_id"], "left_anti")
    return c.agg(F.count("*").alias("candidates")).join(F.broadcast(miss.agg(F.count("*").alias("misses")))).select("candidates", "misses", F.round(F.col("misses") / F.col("candidates"), 6).alias("share"))


def cluster_population(membership: DataFrame) -> DataFrame:
    n = membership.groupBy("cluster_id").agg(F.count("*").alias("n"))
    return n.agg(F.min("n").alias("least"), F.percentile("n", F.lit(0.5)).alias("middle"), F.max("n").alias("most"), F.count("*").alias("clusters"))


def speedup_at_quality(sweep: DataFrame, level: float) -> DataFrame:
    """(method, cost): cost at which a method's curve (method, cost, quality) first reaches the level, by straight lines between points."""
    from pyspark.sql import Window

    w = Window.partitionBy("method").orderBy("cost")
    pairs = sweep.select("method", "cost", "quality", F.lag("cost").over(w).alias("c0"), F.lag("quality").over(w).alias("q0"))
    on = F.when(F.col("q0").isNull(), F.col("cost")).otherwise(F.col("c0") + (level - F.col("q0")) * (F.col("cost") - F.col("c0")) / (F.col("quality") - F.col("q0")))
    reach = pairs.where((F.col("quality") >= level) & (F.col("q0").isNull() | (F.col("q0") < level)))
    return reach.groupBy("method").agg(F.round(F.min(on), 6).alias("cost"))


def latency(search, repeats: int = 10) -> float:
    """Mean seconds of a batch of queries over `repeats` runs, results thrown away."""
    import time

    took = []
    for _ in range(repeats):
        began = time.time()
        search().write.format("noop").mode("overwrite").save()
        took.append(time.time() - began)
    return sum(took) / len(took)


def stored_bytes(df: DataFrame) -> int:
    """Bytes of a table as Parquet."""
    from .iterate import shared

    spark = df.sparkSession
    path = shared(spark, "size")
    df.write.parquet(path)
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    files = p.getFileSystem(spark._jsc.hadoopConfiguration())
    size = files.getContentSummary(p).getLength()
    files.delete(p, True)
    return size
