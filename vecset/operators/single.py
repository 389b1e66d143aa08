"""Single vectors: product quantization, a proximity graph over vectors and its beam search. Sets folded to one vector use it, and so
do codebooks whose centres are to be visited nearest first."""

from __future__ import annotations

from heapq import heapify, heappop, heappush, heapreplace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.limits import driver_table
from .clusters import fit_kmeans


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """A list column of equal lengths, as rows."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1) if len(column) else np.zeros((0, 1))


class Quantizer:
    """Codebooks of the stretches of a vector: centres of shape (parts, codes, stretch)."""

    def __init__(self, centers: np.ndarray):
        self.centers = centers

    @classmethod
    def fit(cls, vectors: DataFrame, parts: int = 8, codes: int = 256, fit_rows: int = 20_000, seed: int = 42, iters: int = 8) -> "Quantizer":
        """k-means in each stretch over a hash sample of at most fit_rows vectors (a parameter). vectors: (set_id, v)."""
        some = driver_table(vectors.orderBy(F.xxhash64("set_id"), "set_id").limit(fit_rows).select("v"))
        x = matrix(some.column("v"))
        x = np.pad(x, ((0, 0), (0, -x.shape[1] % parts)))
        draw, out = np.random.default_rng(seed), []
        for y in np.split(x, parts, axis=1):
            c = y[draw.permutation(len(y))[:codes]].copy()
            for _ in range(iters):
                own = np.argmin((c * c).sum(axis=1) - 2 * y @ c.T, axis=1)
                n, total = np.bincount(own, minlength=len(c)), np.zeros_like(c)
                np.add.at(total, own, y)
                c = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], c)
            out.append(c)
        return cls(np.stack(out))

    def _cut(self, x: np.ndarray) -> list[np.ndarray]:
        parts, _, step = self.centers.shape
        return np.split(np.pad(x, ((0, 0), (0, parts * step - x.shape[1]))), parts, axis=1)

    def encode(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.argmin((c * c).sum(axis=1) - 2 * y @ c.T, axis=1) for y, c in zip(self._cut(x), self.centers, strict=True)], axis=1).astype(np.uint16)

    def tables(self, q: np.ndarray) -> np.ndarray:
        """(queries, parts, codes): inner products with every centre."""
        return np.stack([y @ c.T for y, c in zip(self._cut(q), self.centers, strict=True)], axis=1)


def encoded(vectors: DataFrame, quantizer: Quantizer) -> DataFrame:
    """(set_id, codes array<int>)."""

    def run(batches):
        for batch in batches:
            codes = quantizer.encode(matrix(batch.column("v")))
            yield pa.RecordBatch.from_arrays([batch.column("set_id"), pa.array(codes.astype(np.int32).tolist(), pa.list_(pa.int32()))], names=["set_id", "codes"])

    return vectors.select("set_id", "v").mapInArrow(run, "set_id long, codes array<int>")


def vector_graph(vectors: DataFrame, degree: int = 24, list_rows: int = 512, copies: int = 3, seed: int = 42) -> DataFrame:
    """(src, dst, s): each vector's `degree` nearest by inner product among those that share one of its `copies` nearest lists, both
    ways, cut to 2 * degree. Lists are about list_rows long; a list is dealt in blocks, so none is held whole."""
    n = vectors.count()
    lists = max(1, n // list_rows)
    if lists > 1:
        book = driver_table(fit_kmeans(vectors.select("set_id", F.lit(0).alias("vec_no"), "v"), lists, min(1.0, 200_000 / n), seed, 5))
        centers = matrix(book.column("center"))
    else:
        centers, copies = np.zeros((1, len(vectors.first()["v"]))), 1

    def place(batches):
        for batch in batches:
            x = matrix(batch.column("v"))
            near = np.argsort(-(x @ centers.T), axis=1, kind="stable")[:, :copies].astype(np.int32)
            took = batch.take(pa.array(np.repeat(np.arange(len(x)), near.shape[1])))
            yield pa.RecordBatch.from_arrays([pa.array(near.ravel()), took.column("set_id"), took.column("v")], names=["list", "set_id", "v"])

    placed = vectors.select("set_id", F.transform("v", lambda x: x.cast("double")).alias("v")).mapInArrow(place, "list int, set_id long, v array<double>")
    size = placed.groupBy("list").agg(F.ceil(F.count("*") / F.lit(4 * list_rows)).cast("int").alias("blocks"))
    placed = placed.join(F.broadcast(size), "list").withColumn("own", F.pmod(F.xxhash64("set_id"), F.col("blocks")).cast("int"))  # at most n / list_rows rows
    each = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    both = placed.select("list", "set_id", "v", F.col("own").alias("a"), each.alias("b"), F.lit(True).alias("asks")).unionAll(placed.select("list", "set_id", "v", each.alias("a"), F.col("own").alias("b"), F.lit(False).alias("asks")))

    def link(group: pa.Table) -> pa.Table:
        asks = np.array(group.column("asks").to_pylist(), bool)
        ids, x = group.column("set_id").to_numpy(), matrix(group.column("v"))
        one, two = np.flatnonzero(asks), np.flatnonzero(~asks)
        out = [np.zeros((3, 0))]
        for a in range(0, len(one), 256):
            dots = x[one[a : a + 256]] @ x[two].T
            dots[ids[one[a : a + 256]][:, None] == ids[two][None, :]] = -np.inf
            most = min(degree, len(two))
            top = np.argpartition(-dots, most - 1, axis=1)[:, :most]
            s = np.take_along_axis(dots, top, 1).ravel()
            out.append(np.stack((np.repeat(ids[one[a : a + 256]], most), ids[two][top].ravel(), s))[:, np.isfinite(s)])
        src, dst, s = np.concatenate(out, axis=1)
        return pa.table([pa.array(src.astype(np.int64)), pa.array(dst.astype(np.int64)), pa.array(s)], names=["src", "dst", "s"])

    half = both.groupBy("list", "a", "b").applyInArrow(link, "src long, dst long, s double")
    best = Window.partitionBy("src").orderBy(F.col("s").desc(), "dst")
    near = half.groupBy("src", "dst").agg(F.max("s").alias("s")).withColumn("_n", F.row_number().over(best)).where(F.col("_n") <= degree).drop("_n")
    back = near.unionAll(near.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "s")).groupBy("src", "dst").agg(F.max("s").alias("s"))
    return back.withColumn("_n", F.row_number().over(best)).where(F.col("_n") <= 2 * degree).drop("_n")


def _walk(near, scores, entries: list[int], ef: int) -> tuple[list[tuple[float, int]], int]:
    """Best-first: ([(score, point)], best first, points scored). Ends when the best that waits is worse than the ef-th found."""
    seen = dict(zip(entries, scores(entries), strict=True))
    queue, best = [(-s, p) for p, s in seen.items()], sorted(seen.values(), reverse=True)[:ef]
    heapify(queue)
    heapify(best)
    while queue:
        first, p = heappop(queue)
        if len(best) >= ef and -first < best[0]:
            break
        new = [v for v in near[p].tolist() if v not in seen]
        for v, s in zip(new, scores(new) if new else (), strict=True):
            seen[v] = s
            heappush(queue, (-s, v))
            if len(best) < ef:
                heappush(best, s)
            elif s > best[0]:
                heapreplace(best, s)
    return sorted(((s, p) for p, s in seen.items()), key=lambda x: (-x[0], x[1]))[:ef], len(seen)


def walk_topk(queries: DataFrame, codes: DataFrame, graph: DataFrame, quantizer: Quantizer, k: int, ef: int, entries: int = 8) -> DataFrame:
    """(query_id, set_id, score, rnk, scored): beam search of the graph by inner products with the quantized vectors, looked up in a
    table for each query. queries: (query_id, v). Graph and codes are of a checked size; the queries are dealt out."""
    from .search import Runs

    table = driver_table(codes)
    ids = table.column("set_id").to_numpy()
    order = np.argsort(ids)
    ids, held_codes = ids[order], matrix(table.column("codes")).astype(np.int64)[order]
    near = Runs(driver_table(graph.select("src", "dst")), "src", "dst")
    start = ids[:: max(1, len(ids) // entries)][:entries].tolist()
    held = queries.sparkSession.sparkContext.broadcast((ids, held_codes, near, quantizer))

    def run(batches):
        ids, held_codes, near, quantizer = held.value
        parts = np.arange(held_codes.shape[1])
        for batch in batches:
            out = []
            for q, t in zip(batch.column("query_id").to_pylist(), quantizer.tables(matrix(batch.column("v"))), strict=True):
                scores = lambda points, t=t: t[parts, held_codes[np.searchsorted(ids, points)]].sum(axis=1).tolist()
                hits, scored = _walk(near, scores, start, ef)
                out += [(q, p, s, i + 1, scored) for i, (s, p) in enumerate(hits[:k])]
            yield pa.RecordBatch.from_arrays([pa.array([o[c] for o in out], kind) for c, kind in enumerate((pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64()))], names=["query_id", "set_id", "score", "rnk", "scored"])

    return queries.select("query_id", "v").mapInArrow(run, "query_id long, set_id long, score double, rnk long, scored long")


def nearest_codes(queries: DataFrame, codebook: DataFrame, graph: DataFrame, ef: int) -> DataFrame:
    """(query_id, q_no, code, s): the ef codes that a walk of the graph over the centres finds for each query vector."""
    from .search import Runs

    book = driver_table(codebook.orderBy("code"))
    near = Runs(driver_table(graph.select("src", "dst")), "src", "dst")
    codes, centers = book.column("code").to_numpy().astype(np.int64), matrix(book.column("center"))
    held = queries.sparkSession.sparkContext.broadcast((codes, centers, near))

    def run(batches):
        codes, centers, near = held.value
        start = codes[:: max(1, len(codes) // 8)][:8].tolist()
        for batch in batches:
            out = []
            for q, v, x in zip(batch.column("query_id").to_pylist(), batch.column("vec_no").to_pylist(), matrix(batch.column("v")), strict=True):
                hits, _ = _walk(near, lambda points, x=x: (centers[np.searchsorted(codes, points)] @ x).tolist(), start, ef)
                out += [(q, v, p, int(s)) for s, p in hits]
            yield pa.RecordBatch.from_arrays([pa.array([o[c] for o in out], kind) for c, kind in enumerate((pa.int64(), pa.int32(), pa.int32(), pa.int64()))], names=["query_id", "q_no", "code", "s"])

    return queries.select("query_id", "vec_no", "v").mapInArrow(run, "query_id long, q_no int, code int, s long")
