"""The scores as SQL functions: vs_chamfer, vs_emd over Arrow batches, vs_tokens as a table function; vector sums in two steps."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _matrices(column: pa.Array) -> list[np.ndarray]:
    """A column of lists of vectors as matrices."""
    n, flat = column.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64), column.flatten()
    x = flat.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(flat), -1) if len(flat) else np.zeros((0, 1))
    return np.split(x, np.cumsum(n)[:-1]) if len(n) else []


def _chamfer(q: pa.Array, p: pa.Array) -> pa.Array:
    return pa.array([int((a @ b.T).max(axis=1).sum()) if len(a) and len(b) else None for a, b in zip(_matrices(q), _matrices(p), strict=True)], pa.int64())


def _emd(q: pa.Array, p: pa.Array) -> pa.Array:
    from .transport import emd

    out = []
    for a, b in zip(_matrices(q), _matrices(p), strict=True):
        out.append(emd(np.sqrt(np.maximum(((a[:, None] - b[None]) ** 2).sum(axis=2), 0))) if len(a) and len(b) else None)
    return pa.array(out, pa.float64())


class Tokens:
    """Lower-case runs of letters, with their places. A null text has none."""

    def eval(self, text: str):
        import re

        for i, w in enumerate(w for w in re.split("[^a-z]+", (text or "").lower()) if w):
            yield i, w


def register(spark: SparkSession) -> None:
    """vs_chamfer(q, p): sum of best inner products of two arrays of fixed-point vectors. vs_emd(q, p): earth mover's distance under l2.
    vs_tokens(text): (place, token)."""
    spark.udf.register("vs_chamfer", F.arrow_udf(_chamfer, "long"))
    spark.udf.register("vs_emd", F.arrow_udf(_emd, "double"))
    spark.udtf.register("vs_tokens", F.udtf(Tokens, returnType="place int, token string"))


def vector_sums(vectors: DataFrame, key: str) -> DataFrame:
    """(key, n, total array<long>): sums of the vectors v of each key."""
    kind = dict(vectors.dtypes)[key]

    def run(batches):
        total, n = {}, {}
        for batch in batches:
            if not batch.num_rows:
                continue
            x = batch.column("v").flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            names, at = np.unique(np.array(batch.column(key).to_pylist(), object).astype(str), return_inverse=True)
            own = batch.column(key).to_pylist()
            first = {a: own[i] for i, a in reversed(list(enumerate(at.tolist())))}
            for j in range(len(names)):
                total[first[j]] = total.get(first[j], 0) + x[at == j].sum(axis=0)
                n[first[j]] = n.get(first[j], 0) + int((at == j).sum())
        for name, t in total.items():
            yield pa.RecordBatch.from_pydict({key: [name] * len(t), "pos": list(range(len(t))), "x": t.tolist(), "n": [n[name]] * len(t)}, schema=schema)

    types = {"int": pa.int32(), "bigint": pa.int64(), "string": pa.string()}
    schema = pa.schema([(key, types[kind]), ("pos", pa.int32()), ("x", pa.int64()), ("n", pa.int64())])
    part = vectors.select(key, "v").mapInArrow(run, f"{key} {kind}, pos int, x long, n long")
    sums = part.groupBy(key, "pos").agg(F.sum("x").alias("x"), F.sum("n").alias("n"))
    return sums.groupBy(key).agg(F.max("n").alias("n"), F.transform(F.array_sort(F.collect_list(F.struct("pos", "x"))), lambda p: p["x"]).alias("total"))
