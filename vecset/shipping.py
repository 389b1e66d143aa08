"""Python workers need this package: it goes to them as a zip file unless PYTHONPATH already has it."""

from __future__ import annotations

import functools
import os
import tempfile
import zipfile
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
_done: set[str] = set()


def ship(spark: SparkSession) -> None:
    app = spark.sparkContext.applicationId
    if app in _done or ROOT in map(os.path.abspath, filter(None, os.environ.get("PYTHONPATH", "").split(":"))):
        return
    with tempfile.NamedTemporaryFile(suffix=".zip", delete=False) as f, zipfile.ZipFile(f, "w") as z:
        for folder, _, names in os.walk(os.path.join(ROOT, "vecset")):
            for name in names:
                if name.endswith(".py"):
                    path = os.path.join(folder, name)
                    z.write(path, os.path.relpath(path, ROOT))
    spark.sparkContext.addPyFile(f.name)
    _done.add(app)


def shipped(query: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    @functools.wraps(query)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return query(spark, sf_dir)

    return run
