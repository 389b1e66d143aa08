"""Set-level clustering: codebooks, codes, tf-idf profiles, memberships and their adaptive cutoff."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import dot
from ..plans.limits import driver_table, small


def seed_codebook(vectors: DataFrame, k: int, key: str = "vec_id") -> DataFrame:
    """(code, center): the first k vectors by md5 of their id."""
    w = Window.orderBy(F.md5(F.col(key).cast("string")), key)
    first = vectors.select(key, "v").orderBy(F.md5(F.col(key).cast("string")), key).limit(k)
    return first.select((F.row_number().over(w) - 1).cast("int").alias("code"), F.col("v").alias("center"))


def fit_kmeans(vectors: DataFrame, k: int, share: float = 1.0, seed: int = 42, iters: int = 10, weight: str | None = None) -> DataFrame:
    """(code, center array<double>) by spherical k-means on a hash sample of the vectors (set_id, vec_no, v)."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    part = vectors.where(F.pmod(F.xxhash64("set_id", "vec_no"), F.lit(10_000)) < int(share * 10_000))
    data = part.select(array_to_vector(F.transform("v", lambda x: x.cast("double"))).alias("features"), *([weight] if weight else []))
    kind = KMeans(k=k, seed=seed, maxIter=iters, distanceMeasure="cosine", **({"weightCol": weight} if weight else {}))
    centers = kind.fit(data).clusterCenters()
    return vectors.sparkSession.createDataFrame([(i, [float(x) for x in c]) for i, c in enumerate(centers)], "code int, center array<double>")


def lloyd_step(vectors: DataFrame, codebook: DataFrame) -> DataFrame:
    """(code, pos, total, n): component sums of each code's vectors; the new centre is total / n. Each task sums its own vectors, so a
    row for each code and component leaves it."""

    def run(batches):
        total, n = {}, {}
        for batch in batches:
            if not batch.num_rows:
                continue
            own = batch.column("code").to_numpy()
            x = batch.column("v").flatten().to_numpy().reshape(batch.num_rows, -1)
            order = np.argsort(own, kind="stable")
            codes, start = np.unique(own[order], return_index=True)
            for c, t, k in zip(codes.tolist(), np.add.reduceat(x[order], start, axis=0), np.diff([*start, len(own)]), strict=True):
                total[c], n[c] = total.get(c, 0) + t, n.get(c, 0) + int(k)
        for c, t in total.items():
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(t), c, np.int32)), pa.array(np.arange(len(t), dtype=np.int32)), pa.array(t), pa.array(np.full(len(t), n[c]))], names=["code", "pos", "total", "n"])

    part = assign_codes(vectors, codebook).select("code", "v").mapInArrow(run, "code int, pos int, total long, n long")
    return part.groupBy("code", "pos").agg(F.sum("total").alias("total"), F.sum("n").alias("n"))


def assign_codes(vectors: DataFrame, codebook: DataFrame) -> DataFrame:
    """vectors with their nearest code (largest inner product, ties to the smaller code). A map: the codebook, of a checked size,
    goes to each task as a matrix; a larger one is assigned level by level through its parents."""
    book = driver_table(codebook.orderBy("code"))
    centers = np.array(book.column("center").to_pylist(), np.float64).T
    codes = book.column("code").to_numpy().astype(np.int32)
    schema = vectors.select("*", F.lit(0).alias("code")).schema

    def run(batches):
        for batch in batches:
            col = batch.column("v")
            x = col.flatten().to_numpy().astype(np.float64).reshape(batch.num_rows, -1) if batch.num_rows else np.zeros((0, len(centers)))
            best = [np.argmax(x[s : s + 4096] @ centers, axis=1) for s in range(0, len(x), 4096)]
            got = codes[np.concatenate(best)] if best else np.zeros(0, np.int32)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(got)], names=[*batch.schema.names, "code"])

    return vectors.mapInArrow(run, schema)


def fine_parents(fine: DataFrame, coarse: DataFrame) -> DataFrame:
    """(code, cluster_id): the coarse centroid nearest to each fine one."""
    near = fine.select("code", "center").join(small(coarse.select(F.col("code").alias("cluster_id"), F.col("center").alias("_c"))))
    return near.groupBy("code").agg(F.min_by("cluster_id", F.struct(-dot("center", "_c"), F.col("cluster_id"))).alias("cluster_id"))


def bags(coded: DataFrame) -> DataFrame:
    """(set_id, code, cnt): a set as a bag of fine codes."""
    return coded.groupBy("set_id", "code").agg(F.count("*").alias("cnt"))


def term_counts(assigned: DataFrame) -> DataFrame:
    """(set_id, cluster_id, tf)."""
    return assigned.groupBy("set_id", "cluster_id").agg(F.count("*").alias("tf"))


def inverse_counts(tf: DataFrame, n_sets: int) -> DataFrame:
    """(cluster_id, df, idf), idf = ln(N / (1 + df)) as it stands, so it may be negative."""
    return tf.groupBy("cluster_id").agg(F.count("*").alias("df")).withColumn("idf", F.round(F.log(F.lit(float(n_sets)) / (1.0 + F.col("df"))), 6))


def profile(tf: DataFrame, idf: DataFrame) -> DataFrame:
    """(set_id, cluster_id, tf, score, rnk) by falling score, then tf, then cluster."""
    scored = tf.join(small(idf), "cluster_id").withColumn("score", F.round(F.col("tf") * F.col("idf"), 6))
    w = Window.partitionBy("set_id").orderBy(F.col("score").desc(), F.col("tf").desc(), "cluster_id")
    return scored.select("set_id", "cluster_id", "tf", "score", F.row_number().over(w).alias("rnk"))


def top_clusters(profiles: DataFrame, r: int) -> DataFrame:
    return profiles.where(F.col("rnk") <= r).select("set_id", "cluster_id", "rnk")


def cutoff_labels(train: DataFrame, profiles: DataFrame, routed: DataFrame, r_max: int = 10) -> DataFrame:
    """(query_id, set_id, r): rank of the first of the answer's clusters that the query is routed to, at most r_max."""
    hit = train.join(profiles, "set_id").join(routed, ["query_id", "cluster_id"], "left_semi").groupBy("query_id", "set_id").agg(F.min("rnk").alias("first"))
    return train.join(hit, ["query_id", "set_id"], "left").select("query_id", "set_id", F.least(F.lit(r_max), F.coalesce("first", F.lit(r_max))).cast("int").alias("r"))


def cutoff_features(profiles: DataFrame, r_max: int = 10) -> DataFrame:
    """(set_id, scores array<double> of r_max entries, zero padded, m)."""
    top = profiles.groupBy("set_id").agg(F.array_sort(F.collect_list(F.when(F.col("rnk") <= r_max, F.struct("rnk", "score")))).alias("e"), F.sum("tf").alias("m"))
    scores = F.transform("e", lambda x: x["score"])
    return top.select("set_id", F.slice(F.concat(scores, F.array_repeat(F.lit(0.0), r_max)), 1, r_max).alias("scores"), "m")


def fit_cutoff(labels: DataFrame, features: DataFrame, depth: int = 5):
    """A decision tree that tells r from a set's profile."""
    from pyspark.ml.classification import DecisionTreeClassifier

    return DecisionTreeClassifier(featuresCol="features", labelCol="r", maxDepth=depth, seed=42).fit(labels.join(_vector(features), "set_id").select("features", F.col("r").cast("double").alias("r")))


def _vector(features: DataFrame) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    return features.select("set_id", array_to_vector(F.concat("scores", F.array(F.col("m").cast("double")))).alias("features"))


def adaptive_clusters(model, profiles: DataFrame, features: DataFrame) -> DataFrame:
    """(set_id, cluster_id, rnk) with each set's own cutoff."""
    r = model.transform(_vector(features)).select("set_id", F.greatest(F.lit(1), F.col("prediction").cast("int")).alias("r"))
    return profiles.join(r, "set_id").where("rnk <= r").select("set_id", "cluster_id", "rnk")


def thin(profiled: DataFrame, keep: int) -> DataFrame:
    """Of (set_id, vec_no, idf) the `keep` vectors of each set whose clusters are rarest."""
    w = Window.partitionBy("set_id").orderBy(F.col("idf").desc(), "vec_no")
    return profiled.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= keep).drop("_r")


def codebook_sizes(n_vectors: int, per_cluster: int = 10_000) -> tuple[int, int]:
    """k1: the power of two at or below 16 sqrt(n); k2: one coarse cluster for per_cluster vectors, from 8 to k1 / 4."""
    k1 = 2 ** math.floor(math.log2(16 * math.sqrt(n_vectors)))
    return k1, int(min(max(8, n_vectors // per_cluster), max(8, k1 // 4)))
