"""The methods that the set graph is compared with."""

from __future__ import annotations

from dataclasses import dataclass
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import chamfer, dot, squared_l2
from ..plans.limits import driver_table, small
from .exact import exact_topk, irregular, nested, sets_topk, top_k
from .iterate import cut
from .search import code_scores, pair_scores, rerank
from .single import Quantizer, encoded, matrix, nearest_codes, vector_graph, walk_topk


def pooled_candidates(queries: DataFrame, vectors: DataFrame, lists: DataFrame, codebook: DataFrame, per_vec_k: int, nprobe: int) -> DataFrame:
    """(query_id, set_id): owners of each query vector's nearest single vectors in the nprobe nearest lists. lists: vectors with code.
    A task scores its vectors of a list against the query vectors that probe it, and keeps the per_vec_k best of each."""
    probed = driver_table(probe(queries, codebook, nprobe).select("code", "query_id", "q_no").orderBy("code"))
    asked = driver_table(queries.select("query_id", "vec_no", "v"))
    place = {k: i for i, k in enumerate(zip(asked.column("query_id").to_pylist(), asked.column("vec_no").to_pylist(), strict=True))}
    x, who = np.array(asked.column("v").to_pylist(), np.float64), np.array(list(place), np.int64).reshape(-1, 2)
    by: dict[int, list[int]] = {}
    for code, q, n in zip(*(probed.column(c).to_pylist() for c in ("code", "query_id", "q_no")), strict=True):
        by.setdefault(code, []).append(place[q, n])
    held = queries.sparkSession.sparkContext.broadcast((x, who, {c: np.array(rows) for c, rows in by.items()}))

    def run(batches):
        x, who, by = held.value
        for batch in batches:
            codes, y = batch.column("code").to_numpy(), matrix(batch.column("v"))
            sets, no = batch.column("set_id").to_numpy(), batch.column("vec_no").to_numpy().astype(np.int64)
            for code in np.unique(codes):
                rows = by.get(int(code))
                if rows is None:
                    continue
                at = np.flatnonzero(codes == code)
                at = at[np.lexsort((no[at], sets[at]))]
                s = x[rows] @ y[at].T
                top = np.argsort(-s, axis=1, kind="stable")[:, :per_vec_k]
                asks = np.repeat(rows, top.shape[1])
                yield pa.RecordBatch.from_arrays([pa.array(who[asks, 0]), pa.array(who[asks, 1]), pa.array(sets[at][top].ravel()), pa.array(no[at][top].ravel()), pa.array(np.take_along_axis(s, top, 1).ravel().astype(np.int64))], names=["query_id", "q_no", "set_id", "vec_no", "s"])

    near = lists.select("set_id", "vec_no", "v", "code").mapInArrow(run, "query_id long, q_no long, set_id long, vec_no long, s long")
    w = Window.partitionBy("query_id", "q_no").orderBy(F.col("s").desc(), "set_id", "vec_no")
    return near.withColumn("_n", F.row_number().over(w)).where(F.col("_n") <= per_vec_k).select("query_id", "set_id").distinct()


def probe(queries: DataFrame, codebook: DataFrame, nprobe: int) -> DataFrame:
    """(query_id, q_no, code, s): the nprobe codes nearest to each query vector."""
    return code_scores(queries, codebook, nprobe)


def rounded(x: np.ndarray) -> np.ndarray:
    """To whole numbers, halves away from zero, as SQL rounds."""
    return (np.sign(x) * np.floor(np.abs(x) + 0.5)).astype(np.int64)


def _each_set(vectors: DataFrame, key: str, schema: str, f) -> DataFrame:
    """f(key column, vectors of all sets in a row, where each set begins) -> record batch, over batches of whole sets."""

    def run(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                col = part.column("vecs")
                n = col.value_lengths().to_numpy().astype(np.int64)
                yield f(part.column("set_id"), matrix(col.flatten()), np.cumsum(n) - n, n)

    return nested(vectors.select(F.col(key).alias("set_id"), "vec_no", "v")).mapInArrow(run, schema)


def mean_vectors(vectors: DataFrame, key: str = "set_id") -> DataFrame:
    """(key, v): component means, rounded to fixed point."""

    def mean(ids, x, start, n):
        return pa.RecordBatch.from_arrays([ids, pa.array(list(rounded(np.add.reduceat(x, start, axis=0) / n[:, None])), pa.list_(pa.int64()))], names=[key, "v"])

    return _each_set(vectors, key, f"{key} long, v array<long>", mean)


def mean_single(queries: DataFrame, vectors: DataFrame, k: int) -> DataFrame:
    q = mean_vectors(queries, "query_id").withColumn("vec_no", F.lit(0))
    return exact_topk(q, mean_vectors(vectors).withColumn("vec_no", F.lit(0)), k)


def posting_lists(coded: DataFrame) -> DataFrame:
    """(code, set_id): a set stands under every code of its vectors, once."""
    return coded.select("code", "set_id").distinct()


def posting_candidates(queries: DataFrame, coded: DataFrame, codebook: DataFrame, nprobe: int, least: int, ndocs: int) -> DataFrame:
    """(query_id, set_id, score, rnk): sets of the probed lists, scored by the query's own code scores; those below `least` count 0."""
    cand = posting_lists(coded).join(small(probe(queries, codebook, nprobe).select("query_id", "code").distinct()), "code").select("query_id", "set_id").distinct()
    centres = codebook.select("code", F.col("center").alias("v"))
    decoded = posting_lists(coded).join(small(centres), "code").select("set_id", F.col("code").alias("vec_no"), "v")
    return top_k(pair_scores(cand, queries, decoded, least=least), ndocs)


def residual_codes(coded: DataFrame, codebook: DataFrame, edges: list[int]) -> DataFrame:
    """(set_id, vec_no, code, bits array<int>): each component less the centre's, as the number of `edges` at or below it."""
    c = codebook.select("code", F.col("center").alias("_c"))
    bucket = lambda x: sum((F.when(x >= e, 1).otherwise(0) for e in edges), F.lit(0))
    return coded.join(small(c), "code").select("set_id", "vec_no", "code", F.transform(F.zip_with("v", "_c", lambda x, y: x - y), bucket).alias("bits"))


def planes(tables: int, bits: int, width: int, seed: str) -> np.ndarray:
    """(tables * bits, width) of +1 and -1 from md5 names, the same in every engine."""
    sign = lambda t, b, i: 1.0 if md5(f"{seed}-{t}-{b}-{i}".encode(), usedforsecurity=False).hexdigest()[0] < "8" else -1.0
    return np.array([[sign(t, b, i) for i in range(width)] for t in range(tables) for b in range(bits)])


def sides(x: np.ndarray, normals: np.ndarray, bits: int) -> np.ndarray:
    """(vectors, tables): the sides of each table's hyperplanes as one number; one matrix product."""
    return ((x @ normals.T >= 0).reshape(len(x), -1, bits) << np.arange(bits)).sum(axis=2)


def plane_codes(vectors: DataFrame, keys: list[str], tables: int, bits: int, seed: str) -> DataFrame:
    """(keys, t, code): for each of `tables` the sides of `bits` random hyperplanes, as one number. A map."""
    normals = planes(tables, bits, len(vectors.select("v").first()["v"]), seed)

    def run(batches):
        for batch in batches:
            got = sides(matrix(batch.column("v")), normals, bits)
            took = batch.select(keys).take(pa.array(np.repeat(np.arange(len(got)), tables)))
            yield pa.RecordBatch.from_arrays([*took.columns, pa.array(np.tile(np.arange(tables), len(got))), pa.array(got.ravel().astype(np.int64))], names=[*keys, "t", "code"])

    kinds = dict(vectors.dtypes)
    return vectors.select(*keys, "v").mapInArrow(run, ", ".join(f"{k} {kinds[k]}" for k in keys) + ", t long, code long")


def lsh_sketch(queries: DataFrame, vectors: DataFrame, k: int, tables: int = 64, bits: int = 7) -> DataFrame:
    """Score: for each query vector the largest number of colliding tables of any of the set's vectors, summed. Every set is scanned,
    codes against codes; sets without a collision are no hits."""
    asked = driver_table(queries.select("query_id", "vec_no", "v").orderBy("query_id", "vec_no"))
    normals = planes(tables, bits, len(vectors.select("v").first()["v"]), "h")
    q_ids, q = asked.column("query_id").to_numpy(), sides(matrix(asked.column("v")), normals, bits).astype(np.uint16)
    heads = np.flatnonzero(np.concatenate(([True], q_ids[1:] != q_ids[:-1]))) if len(q_ids) else np.zeros(0, int)

    def scan(ids, x, start, n):
        p, same = sides(x, normals, bits).astype(np.uint16), np.zeros((len(q), len(x)), np.uint16)
        for t in range(tables):
            same += q[:, t, None] == p[None, :, t]
        score = np.add.reduceat(np.maximum.reduceat(same, start, axis=1).astype(np.int64), heads, axis=0)
        ids = ids.to_numpy()
        order = np.lexsort((np.broadcast_to(ids, score.shape), -score), axis=1)[:, :k]
        best = np.take_along_axis(score, order, 1).ravel()
        hit = best > 0
        return pa.RecordBatch.from_arrays([pa.array(np.repeat(q_ids[heads], order.shape[1])[hit]), pa.array(ids[order].ravel()[hit]), pa.array(best[hit])], names=["query_id", "set_id", "score"])

    return top_k(_each_set(vectors, "set_id", "query_id long, set_id long, score long", scan), k)


def fde_vectors(vectors: DataFrame, key: str, reps: int, planes_: int, fold: str, proj: int | None = None, seed: str = "f") -> DataFrame:
    """(key, v array<long>): a set folded to one vector of reps * 2^planes buckets. A query sums the vectors of a bucket; a set averages
    them, and its empty buckets take the average of the nearest bucket that is not (fewest bits apart, then least code). proj: buckets
    are projected to so many dimensions by random signs."""
    width = len(vectors.select("v").first()["v"])
    normals, cells = planes(reps, planes_, width, seed), 1 << planes_
    apart = np.bitwise_count(np.arange(cells)[:, None] ^ np.arange(cells)[None, :]).astype(np.int64) * cells + np.arange(cells)[None, :]
    down = None if proj is None else planes(reps, proj, width, seed + "p").reshape(reps, proj, width)

    def fold_sets(ids, x, start, n):
        code, own = sides(x, normals, planes_), np.repeat(np.arange(len(n)), n)
        out = []
        for t in range(reps):
            at = own * cells + code[:, t]
            count, total = np.bincount(at, minlength=len(n) * cells), np.zeros((len(n) * cells, width))
            np.add.at(total, at, x)
            if fold == "mean":
                total = rounded(total / np.maximum(count, 1)[:, None]).reshape(len(n), cells, width)
                reach = np.where((count > 0).reshape(len(n), 1, cells), apart[None], 1 << 30).argmin(axis=2)
                total = np.take_along_axis(total, reach[:, :, None], 1)
            total = total.reshape(len(n), cells, width)
            out.append(total.reshape(len(n), -1) if down is None else rounded(total @ down[t].T / np.sqrt(proj)).reshape(len(n), -1))
        v = np.concatenate(out, axis=1).astype(np.int64)
        return pa.RecordBatch.from_arrays([ids, pa.array(list(v), pa.list_(pa.int64()))], names=[key, "v"])

    return _each_set(vectors, key, f"{key} long, v array<long>", fold_sets)


def fde_encode(vectors: DataFrame, key: str, reps: int, planes_: int, fold: str, seed: str = "f") -> DataFrame:
    """(key, t, code, pos, x): fde_vectors in long form, every bucket of a set."""
    width = len(vectors.select("v").first()["v"])
    rows = fde_vectors(vectors, key, reps, planes_, fold, None, seed).select(key, F.posexplode("v").alias("at", "x"))
    cell = F.expr(f"at div {width}")
    return rows.select(key, F.expr(f"at div {width << planes_}").alias("t"), (cell % (1 << planes_)).alias("code"), (F.col("at") % width).cast("int").alias("pos"), "x")


def fde_single(queries: DataFrame, vectors: DataFrame, k: int, reps: int = 20, planes_: int = 5, proj: int | None = None) -> DataFrame:
    """Exact scan of the folded vectors."""
    q = fde_vectors(queries, "query_id", reps, planes_, "sum", proj).withColumn("vec_no", F.lit(0))
    return exact_topk(q, fde_vectors(vectors, "set_id", reps, planes_, "mean", proj).withColumn("vec_no", F.lit(0)), k)


@dataclass
class FoldedIndex:
    """Folded vectors as product codes, and a graph over them."""

    codes: DataFrame
    graph: DataFrame
    quantizer: Quantizer
    reps: int
    planes: int
    proj: int | None

    def search(self, queries: DataFrame, k: int, ef: int) -> DataFrame:
        return walk_topk(fde_vectors(queries, "query_id", self.reps, self.planes, "sum", self.proj), self.codes, self.graph, self.quantizer, k, ef)


def build_folded(vectors: DataFrame, reps: int = 20, planes_: int = 5, proj: int | None = 32, parts: int = 8, codes: int = 256, degree: int = 24) -> FoldedIndex:
    folded = cut(fde_vectors(vectors, "set_id", reps, planes_, "mean", proj))
    quantizer = Quantizer.fit(folded, parts, codes)
    return FoldedIndex(cut(encoded(folded, quantizer)), cut(vector_graph(folded, degree)), quantizer, reps, planes_, proj)


def centroid_graph(codebook: DataFrame, degree: int) -> DataFrame:
    """(src, dst, s, rnk): the codes nearest to each code."""
    other = codebook.select(F.col("code").alias("dst"), F.col("center").alias("_c"))
    pairs = codebook.select(F.col("code").alias("src"), "center").join(small(other)).where("src <> dst").select("src", "dst", dot("center", "_c").alias("s"))
    w = Window.partitionBy("src").orderBy(F.col("s").desc(), "dst")
    return pairs.withColumn("rnk", F.row_number().over(w)).where(F.col("rnk") <= degree)


def incremental_candidates(queries: DataFrame, coded: DataFrame, codebook: DataFrame, budget: int) -> DataFrame:
    """(query_id, set_id, score): each query vector visits codes nearest first; a list is read while what came before is below budget.
    The score sums the best code of each query vector among the lists it read."""
    order = code_scores(queries, codebook)
    sizes = posting_lists(coded).groupBy("code").agg(F.count("*").alias("n"))
    w = Window.partitionBy("query_id", "q_no").orderBy(F.col("s").desc(), "code").rowsBetween(Window.unboundedPreceding, -1)
    read = order.join(small(sizes), "code").withColumn("before", F.coalesce(F.sum("n").over(w), F.lit(0))).where(F.col("before") < budget)
    return chamfer(posting_lists(coded).join(small(read), "code").select("query_id", "q_no", "set_id", "s"))


def walked_candidates(queries: DataFrame, coded: DataFrame, codebook: DataFrame, graph: DataFrame, budget: int, ef: int) -> DataFrame:
    """incremental_candidates with the codes that a walk of the graph over the centres comes to, in its order, in place of a sort of all."""
    sizes = posting_lists(coded).groupBy("code").agg(F.count("*").alias("n"))
    w = Window.partitionBy("query_id", "q_no").orderBy(F.col("s").desc(), "code").rowsBetween(Window.unboundedPreceding, -1)
    read = nearest_codes(queries, codebook, graph, ef).join(small(sizes), "code").withColumn("before", F.coalesce(F.sum("n").over(w), F.lit(0))).where(F.col("before") < budget)
    return chamfer(posting_lists(coded).join(small(read), "code").select("query_id", "q_no", "set_id", "s"))


def residual_scores(queries: DataFrame, cands: DataFrame, packed: DataFrame, codebook: DataFrame, edges: list[int]) -> DataFrame:
    """(query_id, set_id, score): candidates by their decompressed vectors, centre plus the middle of each component's bucket. packed:
    residual_codes; the outer buckets count as wide as their neighbours. Raw vectors are not read."""
    step = edges[1] - edges[0] if len(edges) > 1 else 100
    middle = [edges[0] - step // 2, *[(a + b) // 2 for a, b in zip(edges[:-1], edges[1:], strict=True)], edges[-1] + step // 2]
    level = F.array(*[F.lit(int(m)) for m in middle])
    c = codebook.select("code", F.col("center").alias("_c"))
    some = packed.join(small(cands.select("set_id").distinct()), "set_id", "left_semi").join(small(c), "code")
    v = some.select("set_id", "vec_no", F.zip_with("_c", "bits", lambda x, b: x + F.element_at(level, b + 1)).alias("v"))
    return pair_scores(cands, queries, v)


def _stretches(parts: int, width: int):
    step = width // parts
    return lambda c: F.explode(F.array(*[F.struct(F.lit(i).alias("part"), F.slice(c, i * step + 1, step).alias("x")) for i in range(parts)]))


def pq_encode(vectors: DataFrame, codebook: DataFrame, parts: int, width: int, keys: tuple[str, ...] = ("set_id", "vec_no")) -> DataFrame:
    """(keys, part, code): nearest sub-centre in each of `parts` stretches of the vector, ties to the smaller code. A map: the codebook,
    of a checked size, goes to each task. Where a vector is null, holds a null or is of another width, the relational plan answers
    instead."""
    if width % parts or irregular(vectors, width) or irregular(codebook.withColumnRenamed("center", "v"), width):
        cut_ = _stretches(parts, width)
        v = vectors.select(*keys, cut_(F.col("v")).alias("p")).select(*keys, "p.part", "p.x")
        c = codebook.select("code", cut_(F.col("center")).alias("p")).select("code", "p.part", F.col("p.x").alias("y"))
        return v.join(small(c), "part").groupBy(*keys, "part").agg(F.min_by("code", F.struct(squared_l2("x", "y"), F.col("code"))).alias("code"))
    book = driver_table(codebook.select("code", "center").orderBy("code"))
    quantizer, codes = Quantizer(np.stack(np.split(matrix(book.column("center")), parts, axis=1))), book.column("code").to_numpy().astype(np.int32)
    schema = vectors.select(*keys, F.lit(0).alias("part"), F.lit(0).alias("code")).schema

    def run(batches):
        for batch in batches:
            own = codes[quantizer.encode(matrix(batch.column("v")))] if batch.num_rows and len(codes) else np.zeros((0, parts), np.int32)
            at = pa.array(np.repeat(np.arange(len(own)), parts))
            yield pa.RecordBatch.from_arrays([*(batch.column(k).take(at) for k in keys), pa.array(np.tile(np.arange(parts, dtype=np.int32), len(own))), pa.array(own.ravel())], names=[*keys, "part", "code"])

    return vectors.select(*keys, "v").mapInArrow(run, schema)


def pq_topk(queries: DataFrame, encoded: DataFrame, codebook: DataFrame, parts: int, width: int, k: int) -> DataFrame:
    """Single vectors by the inner product with their decoded sub-centres. Codes alone are grouped by set; a task decodes its sets and
    scores them against all queries by matrix products in blocks, so no pair of vectors is a row. Where a query vector or a centre is
    irregular, look-ups in a table for each query vector and part answer instead."""
    if width % parts or irregular(queries, width) or irregular(codebook.withColumnRenamed("center", "v"), width):
        cut_ = _stretches(parts, width)
        c = codebook.select("code", cut_(F.col("center")).alias("p")).select("code", "p.part", F.col("p.x").alias("y"))
        q = queries.select("query_id", F.col("vec_no").alias("q_no"), cut_(F.col("v")).alias("p")).select("query_id", "q_no", "p.part", "p.x")
        table = q.join(small(c), "part").select("query_id", "q_no", "part", "code", dot("x", "y").alias("s"))
        s = encoded.join(small(table), ["part", "code"]).groupBy("query_id", "q_no", "set_id", "vec_no").agg(F.sum("s").alias("s"))
        return top_k(chamfer(s), k)
    book = driver_table(codebook.select("code", "center").orderBy("code"))
    names, centers = book.column("code").to_numpy(), matrix(book.column("center")).reshape(book.num_rows, parts, -1)

    def decoded(batch):
        flat, n = batch.column("codes").flatten(), batch.column("codes").value_lengths().to_numpy().astype(np.int64) // parts
        own = np.searchsorted(names, flat.to_numpy()).reshape(-1, parts)
        return np.concatenate([centers[own[:, i], i] for i in range(parts)], axis=1), n

    codes = F.transform(F.array_sort(F.collect_list(F.struct("vec_no", "part", "code"))), lambda x: x["code"])
    spark = encoded.sparkSession  # codes are few bytes for many products: a stated number of tasks is not merged by size
    tasks = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    return sets_topk(queries, encoded.repartition(tasks, "set_id").groupBy("set_id").agg(codes.alias("codes")), k, read=decoded)


def refine(cands: DataFrame, queries: DataFrame, vectors: DataFrame, k: int) -> DataFrame:
    return rerank(cands, queries, vectors, k)
