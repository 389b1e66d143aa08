"""Exact retrieval: the k sets of largest Chamfer score."""

from __future__ import annotations

from itertools import permutations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import chamfer, pair_nearness
from ..plans.limits import driver_table


def nested(vectors: DataFrame) -> DataFrame:
    """(set_id, vecs array<array>): one row for each set."""
    return vectors.groupBy("set_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("vec_no", "v"))), lambda x: x["v"]).alias("vecs"))


def top_k(scores: DataFrame, k: int, order: str = "score", descending: bool = True) -> DataFrame:
    """(query_id, set_id, score, rnk) with ties to the smaller set_id; Spark keeps k rows a query before it shuffles."""
    w = Window.partitionBy("query_id").orderBy(F.col(order).desc() if descending else F.col(order).asc(), "set_id")
    return scores.withColumn("rnk", F.row_number().over(w)).where(F.col("rnk") <= k)


#: Inner products that a task holds at once.
CELLS = 1 << 21


class _Asked:
    """A stated query set, of a checked size, for every task: vectors in a row, and where each query's begin."""

    def __init__(self, queries: DataFrame):
        asked = driver_table(queries.select("query_id", "vec_no", "v").orderBy("query_id", "vec_no"))
        self.q = asked.column("v").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(asked.num_rows, -1) if asked.num_rows else np.zeros((0, 1))
        ids = asked.column("query_id").to_numpy()
        self.heads = np.flatnonzero(np.concatenate(([True], ids[1:] != ids[:-1]))) if len(ids) else np.zeros(0, int)
        self.names, self.ends = ids[self.heads], np.append(self.heads, len(ids))

    def parts(self, most: int):
        """Ranges of queries that have up to `most` vectors, or one query."""
        lo = 0
        while lo < len(self.names):
            hi = max(lo + 1, int(np.searchsorted(self.ends, self.ends[lo] + most, "right")) - 1)
            yield lo, hi
            lo = hi


def _sets(batch: pa.RecordBatch, column: str = "vecs"):
    """(vectors of all sets in a row, number of each set's vectors)."""
    col = batch.column(column)
    n, flat = col.value_lengths().to_numpy().astype(np.int64), col.flatten()
    return flat.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(flat), -1) if len(flat) else np.zeros((0, 1)), n


def _scored(asked: _Asked, batch: pa.RecordBatch, ground: str, sets: int, rows: int, read=_sets):
    """(first query, last, first set, last, scores of these queries and sets) in blocks of up to `sets` sets and `rows` scores."""
    x, n = read(batch)
    size = (x * x).sum(axis=1)
    starts = np.concatenate(([0], np.cumsum(n)))
    for lo in range(0, len(n), sets):
        hi = min(lo + sets, len(n))
        y, cut = x[starts[lo] : starts[hi]], starts[lo:hi] - starts[lo]
        for a, b in asked.parts(max(1, min(CELLS // max(1, len(y)), rows // (hi - lo)))):
            q = asked.q[asked.ends[a] : asked.ends[b]]
            dots = q @ y.T
            if ground != "cosine":
                dots = 2 * dots - (q * q).sum(axis=1)[:, None] - size[starts[lo] : starts[hi]][None, :]
            best = np.maximum.reduceat(dots, cut, axis=1)
            yield a, b, lo, hi, np.add.reduceat(best, asked.heads[a:b] - asked.ends[a], axis=0)


def _firsts(score: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Columns of the k largest of each row, ties to the smaller id. ids are sorted; scores are whole numbers."""
    m = len(ids)
    if m <= k or np.abs(score).max() * m >= 1 << 62:
        return np.lexsort((np.broadcast_to(ids, score.shape), -score), axis=1)[:, :k]
    return np.argpartition(score.astype(np.int64) * -m + np.arange(m), k - 1, axis=1)[:, :k]


def exact_topk(queries: DataFrame, vectors: DataFrame, k: int, ground: str = "cosine") -> DataFrame:
    """Every set is scored against every query, in blocks of a bounded number of products, however many ask: a stated query set, of a
    checked size, goes to each task; a task keeps the k best of each block of sets. Fixed-point scores are whole numbers below 2^53,
    so doubles carry them exactly."""
    return sets_topk(queries, nested(vectors), k, ground)


def sets_topk(queries: DataFrame, sets: DataFrame, k: int, ground: str = "cosine", read=_sets) -> DataFrame:
    """exact_topk over sets (set_id, ...) in one row each. read: a batch of them -> (vectors of all sets in a row, number of each set's)."""
    asked = _Asked(queries)

    def run(batches):
        for batch in batches:
            batch = pa.RecordBatch.from_struct_array(batch.to_struct_array().take(pa.array(np.argsort(batch.column("set_id").to_numpy(), kind="stable"))))
            ids = batch.column("set_id").to_numpy()
            for a, b, lo, hi, score in _scored(asked, batch, ground, 2048, CELLS, read):
                order = _firsts(score, ids[lo:hi], k)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(asked.names[a:b], order.shape[1])), pa.array(ids[lo:hi][order].ravel()), pa.array(np.take_along_axis(score, order, 1).ravel().astype(np.int64))], names=["query_id", "set_id", "score"])

    return top_k(sets.mapInArrow(run, "query_id long, set_id long, score long"), k)


def irregular(vectors: DataFrame, width: int) -> bool:
    """Whether some v is null, holds a null or is of another width."""
    odd = F.coalesce((F.size("v") != width) | F.exists("v", lambda x: x.isNull()), F.lit(True))
    return vectors.where(odd).limit(1).count() > 0


def all_scores(queries: DataFrame, vectors: DataFrame, ground: str = "cosine", mean: bool = False) -> DataFrame:
    """(query_id, set_id, score) of every query and set: the sum, or the mean, of the best matches, by matrix products in blocks. Where a
    vector is null, holds a null or is of another width, the relational plan answers instead."""
    width = vectors.select(F.size("v").alias("n")).first()
    if width is None or irregular(vectors, width["n"]):
        return chamfer(pair_nearness(queries, vectors, ground), "mean" if mean else "sum")
    asked = _Asked(queries)

    def run(batches):
        for batch in batches:
            ids = batch.column("set_id").to_numpy()
            for a, b, lo, hi, score in _scored(asked, batch, ground, 1024, 1 << 17):
                if mean:
                    score = score / np.diff(asked.ends[a : b + 1])[:, None]
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(asked.names[a:b], hi - lo)), pa.array(np.tile(ids[lo:hi], b - a)), pa.array(score.ravel() if mean else score.ravel().astype(np.int64))], names=["query_id", "set_id", "score"])

    return nested(vectors).mapInArrow(run, f"query_id long, set_id long, score {'double' if mean else 'long'}")


def matched(sets: DataFrame, m: int, name: str, centers: np.ndarray | None = None, unit: int = 1_000_000, every: int = 10) -> DataFrame:
    """(a, b, name): earth mover's distance of all pairs a < b of sets of m vectors, a a multiple of `every`, under cost unit - inner product.
    Weights are equal, so it is the cheapest of the m! matchings over m. sets: (set_id, vecs), or codes of centers in place of vectors."""
    asked = driver_table(sets.where(F.col("set_id") % every == 0))
    orders = list(permutations(range(m)))

    def shaped(batch):
        if centers is None:
            return _sets(batch)[0].reshape(batch.num_rows, m, -1)
        return centers[batch.column("vecs").flatten().to_numpy().reshape(batch.num_rows, m)].astype(np.float64)

    names = asked.column("set_id").to_numpy()
    own = shaped(asked.combine_chunks().to_batches()[0]) if len(names) else None

    def run(batches):
        for batch in batches:
            if not batch.num_rows or not len(names):
                continue
            y, ids = shaped(batch), batch.column("set_id").to_numpy()
            for lo in range(0, len(ids), 512):
                z = y[lo : lo + 512]
                step = max(1, (1 << 17) // len(z))
                for a in range(0, len(names), step):
                    x = own[a : a + step]
                    cost = unit - (x.reshape(-1, x.shape[2]) @ z.reshape(-1, z.shape[2]).T).reshape(len(x), m, len(z), m)
                    least = None
                    for o in orders:
                        total = sum(cost[:, i, :, j] for i, j in enumerate(o))
                        least = total if least is None else np.minimum(least, total)
                    i, j = np.nonzero(names[a : a + step, None] < ids[None, lo : lo + 512])
                    yield pa.RecordBatch.from_arrays([pa.array(names[a : a + step][i]), pa.array(ids[lo : lo + 512][j]), pa.array(np.round(least[i, j] / m, 6))], names=["a", "b", name])

    return sets.mapInArrow(run, f"a long, b long, {name} double")


def vector_topk(queries: DataFrame, vectors: DataFrame, k: int, ground: str = "l2") -> DataFrame:
    """Single vectors: (query_id, set_id, score, rnk)."""
    return exact_topk(queries, vectors, k, ground)
