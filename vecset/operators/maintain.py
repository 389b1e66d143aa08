"""Changes of a standing index: inserts, lazy deletes, later pruning, statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.limits import small
from . import clusters as C
from . import graph as G


def insert_membership(coded: DataFrame, parents: DataFrame, idf: DataFrame, r: int) -> DataFrame:
    """Clusters of new sets through the parents of their fine codes, ranked by the standing statistics."""
    tf = C.term_counts(coded.join(small(parents), "code"))
    return C.top_clusters(C.profile(tf, idf.select("cluster_id", "df", "idf")), r)


def insert_edges(cand: DataFrame, old: DataFrame, new: DataFrame, coded: DataFrame, codebook: DataFrame, f: int, most: int) -> DataFrame:
    """The adjacency with new sets: only clusters that get one are built again; the others keep their half-edges."""
    touched = new.select("cluster_id").distinct()
    members = old.unionAll(new)
    again = G.local_edges(members.join(small(touched), "cluster_id", "left_semi"), coded, codebook, f)
    kept = cand.join(small(touched.withColumnRenamed("cluster_id", "via")), "via", "left_anti").select("src", "dst", "dist", "via")
    return G.merge_bridges(kept.unionAll(again), members, most)


def active(hits: DataFrame, tombstones: DataFrame) -> DataFrame:
    return hits.join(small(tombstones), "set_id", "left_anti").select("query_id", "set_id", "score")


def vacuum(edges: DataFrame, tombstones: DataFrame, most: int) -> DataFrame:
    """(src, dst, dist) without deleted sets; neighbours on both sides of one are linked at the length of the way through it."""
    gone = tombstones.select("set_id")
    off = lambda df, end: df.join(small(gone.withColumnRenamed("set_id", end)), end, "left_anti")
    alive = off(off(edges, "src"), "dst").select("src", "dst", "dist")
    into = off(edges, "src").join(small(gone.withColumnRenamed("set_id", "dst")), "dst", "left_semi").select("src", F.col("dst").alias("via_"), F.col("dist").alias("d0"))
    out = off(edges, "dst").join(small(gone.withColumnRenamed("set_id", "src")), "src", "left_semi").select(F.col("src").alias("via_"), "dst", F.col("dist").alias("d1"))
    detour = into.join(out, "via_").where("src <> dst").select("src", "dst", (F.col("d0") + F.col("d1")).alias("dist"))
    return G.trim_degree(alive.unionAll(detour).groupBy("src", "dst").agg(F.min("dist").alias("dist")), most)


def merge_idf(old_tf: DataFrame, new_tf: DataFrame, n_sets: int) -> DataFrame:
    """Document frequencies of both parts, added; no old set is read again once its counts are kept."""
    count = lambda tf: tf.groupBy("cluster_id").agg(F.count("*").alias("df"))
    df = count(old_tf).unionAll(count(new_tf)).groupBy("cluster_id").agg(F.sum("df").alias("df"))
    return df.withColumn("idf", F.round(F.log(F.lit(float(n_sets)) / (1.0 + F.col("df"))), 6))
