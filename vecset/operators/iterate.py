"""Cutting lineage in loops."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def checkpoint_dir(spark: SparkSession) -> str:
    """The folder that spark.checkpoint.dir names; a new one only where none is set and there is one machine (tests)."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and sc.master.split("[")[0] != "local":
            raise ValueError("spark.checkpoint.dir is unset: a cluster's machines have no other folder in common")
        sc.setCheckpointDir(named or f"file://{tempfile.mkdtemp(prefix='vecset-')}")
    return sc._jsc.sc().getCheckpointDir().get()


def shared(spark: SparkSession, name: str) -> str:
    """A new path in that folder."""
    return f"{checkpoint_dir(spark)}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """A reliable checkpoint."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint()


def stored(df: DataFrame, name: str) -> DataFrame:
    """df as Parquet in that folder, computed once; a checkpoint computes its last stage twice."""
    path = shared(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def dropped(df: DataFrame) -> None:
    """Deletes what stored() wrote for df, which no later plan reads."""
    jvm, conf = df.sparkSession._jvm, df.sparkSession._jsc.hadoopConfiguration()
    for f in df.inputFiles()[:1]:
        path = jvm.org.apache.hadoop.fs.Path(f).getParent()
        path.getFileSystem(conf).delete(path, True)


def components(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """(set_id, component): least id reachable. Labels of neighbours and of labels spread until none changes."""
    both = cut(edges.select(F.col("src").alias("a"), F.col("dst").alias("b")).unionAll(edges.select(F.col("dst").alias("a"), F.col("src").alias("b"))).distinct())
    label = cut(nodes.select("set_id", F.col("set_id").alias("component")))
    while True:
        near = both.join(label, both.b == label.set_id).groupBy("a").agg(F.min("component").alias("near"))
        step = label.join(near, label.set_id == near.a, "left").select("set_id", F.least("component", "near").alias("c"))
        jump = step.select(F.col("set_id").alias("c"), F.col("c").alias("cc"))
        new = cut(step.join(jump, "c", "left").select("set_id", F.least("c", "cc").alias("component")))
        changed = new.join(label.withColumnRenamed("component", "old"), "set_id").where("component <> old").limit(1).count()
        label = new
        if not changed:
            return label
