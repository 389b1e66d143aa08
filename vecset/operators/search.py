"""Cluster-guided search of the graph: routing, entries, beam search (kernel and supersteps), re-ranking."""

from __future__ import annotations

from heapq import heapify, heappop, heappush, heapreplace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import chamfer, dot
from ..plans.limits import MOST_ROWS, driver_table, small
from .exact import nested, top_k
from .graph import Codebook
from .iterate import cut, dropped, stored


def centroid_scores(queries: DataFrame, coarse: DataFrame, most: int | None = None) -> DataFrame:
    """(query_id, vec_no, cluster_id, score), of the `most` best of each vector or of all."""
    return code_scores(queries, coarse, most).select("query_id", F.col("q_no").alias("vec_no"), F.col("code").alias("cluster_id"), F.col("s").alias("score"))


def query_clusters(scores: DataFrame, t: int = 4) -> DataFrame:
    """(query_id, cluster_id): union over a query's vectors of their t best clusters."""
    w = Window.partitionBy("query_id", "vec_no").orderBy(F.col("score").desc(), "cluster_id")
    return scores.withColumn("_n", F.row_number().over(w)).where(F.col("_n") <= t).select("query_id", "cluster_id").distinct()


def entry_points(routed: DataFrame, membership: DataFrame) -> DataFrame:
    """(query_id, cluster_id, set_id): of each cluster the member with the least md5."""
    first = membership.groupBy("cluster_id").agg(F.min_by("set_id", F.struct(F.md5(F.col("set_id").cast("string")), F.col("set_id"))).alias("set_id"))
    return routed.join(small(first), "cluster_id").select("query_id", "cluster_id", "set_id")


def qch(query_codes: DataFrame, set_codes: DataFrame, code_sims: DataFrame) -> DataFrame:
    """(query_id, set_id, score): for each query vector's code the best of the set's codes, summed. code_sims: (a, b, s)."""
    sims = code_sims.select(F.col("a").alias("q_code"), F.col("b").alias("code"), "s")
    q = query_codes.select("query_id", F.col("vec_no").alias("q_no"), F.col("code").alias("q_code"))
    pairs = set_codes.select("set_id", "code").distinct().join(small(q.join(sims, "q_code")), "code")
    return chamfer(pairs)


def reachable(entries: DataFrame, edges: DataFrame, membership: DataFrame | None, routed: DataFrame | None) -> DataFrame:
    """(query_id, set_id) that a search without limit comes to, in as many rounds as that takes. With membership and routed: through
    sets of the query's clusters alone."""
    step = edges.select("src", "dst").distinct()
    if membership is not None:
        allowed = cut(routed.join(membership.select("set_id", "cluster_id"), "cluster_id").select("query_id", F.col("set_id")).distinct())
    seen = front = cut(entries.select("query_id", "set_id").distinct())
    while True:
        new = front.join(step, front.set_id == step.src).select("query_id", F.col("dst").alias("set_id")).distinct()
        if membership is not None:
            new = new.join(allowed, ["query_id", "set_id"], "left_semi")
        front = cut(new.join(seen, ["query_id", "set_id"], "left_anti"))
        if not front.limit(1).count():
            return seen
        seen = cut(seen.unionAll(front))


def qch_of(pairs: DataFrame, query_codes: DataFrame, set_codes: DataFrame, code_sims: DataFrame) -> DataFrame:
    """qch of the given (query_id, set_id) pairs alone: only their codes are joined."""
    sims = code_sims.select(F.col("a").alias("q_code"), F.col("b").alias("code"), "s")
    q = query_codes.select("query_id", F.col("vec_no").alias("q_no"), F.col("code").alias("q_code"))
    codes = pairs.select("query_id", "set_id").join(set_codes.select("set_id", "code").distinct(), "set_id")
    return chamfer(codes.join(small(q.join(sims, "q_code")), ["query_id", "code"]))


def search_exhaustive(entries, edges, membership, routed, query_codes, set_codes, code_sims, k: int) -> DataFrame:
    """Top k by quantized Chamfer of all that is reachable under the cluster guard: what a beam without limit returns. Only what was
    reached is scored."""
    return top_k(qch_of(reachable(entries, edges, membership, routed), query_codes, set_codes, code_sims), k)


def superstep(state: DataFrame, edges: DataFrame, allowed: DataFrame, scores: DataFrame, ef: int) -> DataFrame:
    """One round of the search: (query_id, path, set_id, score, expanded). scores: (query_id, set_id, score), larger is nearer, or a
    function that gives them for (query_id, set_id) pairs, so that only new neighbours are scored.

    Each path takes its best unexpanded entry, unless the results are full and it is worse than the worst of them. Its neighbours
    in the query's clusters that nobody saw are scored; one that several paths reach is the least path's. The ef best stay, with all
    that were expanded as marks.
    """
    best = Window.partitionBy("query_id", "path").orderBy(F.col("score").desc(), "set_id")
    rank = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "set_id")
    ranked = state.withColumn("place", F.row_number().over(rank))
    worst = ranked.where(F.col("place") == ef).select("query_id", F.col("score").alias("worst"))
    pick = ranked.where("expanded = 0").withColumn("_n", F.row_number().over(best)).where("_n = 1").join(worst, "query_id", "left").where("worst is null or score >= worst")
    near = pick.join(edges.select(F.col("src").alias("set_id"), "dst").distinct(), "set_id").groupBy("query_id", F.col("dst").alias("set_id")).agg(F.min("path").alias("path"))
    near = near.join(allowed, ["query_id", "set_id"], "left_semi").join(state.select("query_id", "set_id"), ["query_id", "set_id"], "left_anti")
    scored = scores(near) if callable(scores) else scores
    new = near.join(scored, ["query_id", "set_id"]).select("query_id", "path", "set_id", "score", F.lit(0).alias("expanded"))
    done = pick.select("query_id", "set_id", F.lit(1).alias("_d"))
    old = state.join(done, ["query_id", "set_id"], "left").select("query_id", "path", "set_id", "score", F.greatest("expanded", F.coalesce("_d", F.lit(0))).alias("expanded"))
    both = old.unionAll(new).withColumn("place", F.row_number().over(rank))
    return both.where((F.col("place") <= ef) | (F.col("expanded") == 1)).drop("place")


STATE = "query_id long, asks array<long>, inside array<long>, sets array<long>, scores array<long>, paths array<long>, expanded array<boolean>, picks array<struct<path: long, set_id: long>>"


def search_frontier(entries, edges, membership, routed, query_codes, set_codes, code_sims, k: int, ef: int) -> DataFrame:
    """Beam search by supersteps, for indexes that no task holds whole: ends when a round expands nothing, however many it takes.

    A query's state is one row: what it holds, and what its paths expand next. Each vertex is one row with its neighbours, their codes
    and clusters. A round is one join of picks and vertices, whose rows go back to their queries; there superstep's rules are
    followed. Code similarities go to each task as a matrix; beyond driver_table's size search_by_joins stands in, with the same result.
    """
    if code_sims.limit(MOST_ROWS + 1).count() > MOST_ROWS:
        return search_by_joins(entries, edges, membership, routed, query_codes, set_codes, code_sims, k, ef)
    long = lambda c: F.col(c).cast("long").alias(c)
    sims = driver_table(code_sims.groupBy(long("a"), long("b")).agg(F.max("s").cast("long").alias("s")))
    a, b = (np.unique(sims.column(c).to_numpy()) for c in ("a", "b"))
    none = np.iinfo(np.int64).min  # where a pair has no similarity
    matrix = np.full((len(a), len(b)), none)
    matrix[np.searchsorted(a, sims.column("a").to_numpy()), np.searchsorted(b, sims.column("b").to_numpy())] = sims.column("s").to_numpy()
    held = entries.sparkSession.sparkContext.broadcast((dict(zip(a.tolist(), range(len(a)))), dict(zip(b.tolist(), range(len(b)))), matrix))

    codes = set_codes.select(long("set_id"), long("code")).groupBy("set_id").agg(F.collect_set("code").alias("codes"))
    clusters = membership.select(long("set_id"), long("cluster_id")).groupBy("set_id").agg(F.collect_set("cluster_id").alias("clusters"))
    sets = stored(codes.join(clusters, "set_id"), "sets")
    node = F.struct("set_id", "codes", "clusters")
    near = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("set_id")).distinct().join(sets, "set_id")
    near = stored(near.groupBy("src").agg(F.collect_list(node).alias("near")).withColumnRenamed("src", "set_id"), "near")
    asks = query_codes.select(long("query_id"), long("code")).groupBy("query_id").agg(F.collect_list("code").alias("asks"))
    inside = routed.select(long("query_id"), long("cluster_id")).groupBy("query_id").agg(F.collect_set("cluster_id").alias("inside"))
    first = entries.select(long("query_id"), F.col("cluster_id").cast("long").alias("path"), long("set_id")).join(sets, "set_id").withColumn("near", F.array(node))
    found = lambda df: df.groupBy("query_id").agg(F.collect_list(F.struct("path", "near")).alias("found"))
    fields = [f for f in STATE.split(", ") if f.split()[0] in ("sets", "scores", "paths", "expanded")]
    empty = [F.array().cast(f.split()[1]).alias(f.split()[0]) for f in fields]
    state = asks.join(inside, "query_id").select("*", *empty, F.array().cast("array<struct<path: long, set_id: long>>").alias("picks")).join(found(first), "query_id")

    def scored(asks: list[int], fresh: dict) -> dict:
        """Scores of the new sets, of those that have one."""
        row_of, place_of, matrix = held.value
        rows, n = np.unique(np.array([row_of[c] for c in asks if c in row_of], np.int64), return_counts=True)
        places = {s: [place_of[c] for c in codes if c in place_of] for s, (_, codes) in fresh.items()}
        names = [s for s, at in places.items() if at]
        if not len(rows) or not names:
            return {}
        size = np.array([len(places[s]) for s in names])
        best = np.maximum.reduceat(matrix[rows][:, np.concatenate([places[s] for s in names])], np.cumsum(size) - size, axis=1)
        has = best > none
        total = (np.where(has, best, 0) * n[:, None]).sum(axis=0)
        return {s: t for s, t, ok in zip(names, total.tolist(), has.any(axis=0).tolist(), strict=True) if ok}

    def step(begins: bool):
        def run(batches):
            for batch in batches:
                out = []
                for r in batch.to_pylist():
                    got, picks = r.pop("found"), r["picks"]
                    if begins or picks:
                        held_ = {s: [v, p, e] for s, v, p, e in zip(r["sets"], r["scores"], r["paths"], r["expanded"], strict=True)}
                        for p in picks:
                            held_[p["set_id"]][2] = True
                        may, fresh = set(r["inside"]), {}
                        for g in got or []:
                            for x in g["near"]:
                                s = x["set_id"]
                                if s in fresh:
                                    fresh[s][0] = min(fresh[s][0], g["path"])
                                elif s not in held_ and not may.isdisjoint(x["clusters"]):
                                    fresh[s] = [g["path"], x["codes"]]
                        for s, v in scored(r["asks"], fresh).items():
                            held_[s] = [v, fresh[s][0], False]
                        rank = sorted(held_.items(), key=lambda x: (-x[1][0], x[0]))
                        if not begins:
                            rank = [x for i, x in enumerate(rank) if i < ef or x[1][2]]
                        worst, taken = rank[ef - 1][1][0] if len(rank) >= ef else None, {}
                        for s, (v, p, e) in rank:
                            if not e and p not in taken:
                                taken[p] = (s, v)
                        r |= {"sets": [s for s, _ in rank], "picks": [{"path": p, "set_id": s} for p, (s, v) in taken.items() if worst is None or v >= worst]}
                        r |= {name: [x[1][i] for x in rank] for i, name in enumerate(("scores", "paths", "expanded"))}
                    out.append(r)
                yield pa.RecordBatch.from_pylist(out, schema=STATE_ARROW)

        return run

    state = stored(state.mapInArrow(step(True), STATE), "state")
    while not state.where("size(picks) > 0").isEmpty():
        picks = state.select("query_id", F.explode("picks").alias("p")).select("query_id", "p.path", "p.set_id")
        new = stored(state.join(found(picks.join(near, "set_id")), "query_id", "left").mapInArrow(step(False), STATE), "state")
        dropped(state)
        state = new
    out = state.select("query_id", F.explode(F.arrays_zip("sets", "scores")).alias("x")).select("query_id", F.col("x.sets").alias("set_id"), F.col("x.scores").alias("score"))
    return top_k(out, k)


_LONGS = pa.list_(pa.int64())
STATE_ARROW = pa.schema([("query_id", pa.int64()), *((c, _LONGS) for c in ("asks", "inside", "sets", "scores", "paths")), ("expanded", pa.list_(pa.bool_())), ("picks", pa.list_(pa.struct([("path", pa.int64()), ("set_id", pa.int64())])))])


def search_by_joins(entries, edges, membership, routed, query_codes, set_codes, code_sims, k: int, ef: int) -> DataFrame:
    """The same by superstep, where every part is a table of rows: some ten joins a round, but nothing of any size goes to all tasks."""
    allowed = cut(routed.join(membership.select("set_id", "cluster_id"), "cluster_id").select("query_id", "set_id").distinct())
    first = entries.join(allowed, ["query_id", "set_id"], "left_semi")

    def scores(pairs: DataFrame) -> DataFrame:
        return qch_of(pairs, query_codes, set_codes, code_sims)

    state = first.join(scores(first.select("query_id", "set_id").distinct()), ["query_id", "set_id"]).groupBy("query_id", "set_id", "score").agg(F.min("cluster_id").alias("path"))
    state, last = cut(state.select("query_id", "path", "set_id", "score", F.lit(0).alias("expanded"))), -1
    while True:
        state = cut(superstep(state, edges, allowed, scores, ef))
        done = state.agg(F.sum("expanded")).first()[0] or 0
        if done == last:
            return top_k(state.select("query_id", "set_id", "score"), k)
        last = done


def spread(df: DataFrame, rounds: int = 4) -> DataFrame:
    """Few bytes that are much work: dealt out to all cores, where Spark would put them into one task for their size."""
    return df.repartition(rounds * df.sparkSession.sparkContext.defaultParallelism)


class Runs:
    """Rows (key, value) as runs: the values of a key by one look-up."""

    def __init__(self, table: pa.Table, key: str, value: str):
        keys, values = table.column(key).to_numpy(), table.column(value).to_numpy()
        order = np.lexsort((values, keys))
        self.keys, start = np.unique(keys[order], return_index=True)
        self.values, self.start = values[order], np.append(start, len(keys))
        self.at = {k: i for i, k in enumerate(self.keys.tolist())}

    @classmethod
    def packed(cls, df: DataFrame, key: str, value: str) -> "Runs":
        """The same of a DataFrame, each pair once. The driver has a row for each key, and its values in a list of their own type."""
        table = driver_table(df.groupBy(key).agg(F.sort_array(F.collect_set(value)).alias(value)))
        keys, lists, out = table.column(key).to_numpy(), table.column(value).combine_chunks(), cls.__new__(cls)
        lists = lists.take(pa.array(np.argsort(keys)))
        out.keys, out.values = np.sort(keys), lists.flatten().to_numpy()
        out.start = np.append(0, np.cumsum(lists.value_lengths().to_numpy().astype(np.int64)))
        out.at = {k: i for i, k in enumerate(out.keys.tolist())}
        return out

    def __getitem__(self, key: int) -> np.ndarray:
        i = self.at.get(key)
        return self.values[:0] if i is None else self.values[self.start[i] : self.start[i + 1]]

    def all(self, keys: list[int]) -> tuple[np.ndarray, np.ndarray]:
        """(values of all these keys in a row, where each key's begin); every key has some."""
        parts = [self[k] for k in keys]
        n = np.array([len(p) for p in parts])
        return np.concatenate(parts), np.cumsum(n) - n


def search_kernel(queries: DataFrame, routed: DataFrame, entries: DataFrame, edges: DataFrame, membership: DataFrame, coded: DataFrame, codebook: DataFrame, k: int, ef: int, multi_path: bool = True, guard: bool = True) -> DataFrame:
    """(query_id, set_id, score, rnk, scored, hops, guarded): the beam search of an index of a checked size, which each task holds
    (one broadcast for all its queries); the queries are dealt out. One queue for each entry (or one for all), a shared result list
    and shared marks; a queue ends when its best is worse than the worst result. queries: (query_id, codes)."""
    book = Codebook(codebook)
    near, own, bag = Runs.packed(edges, "src", "dst"), Runs.packed(membership, "set_id", "cluster_id"), Runs.packed(coded, "set_id", "code")
    held = queries.sparkSession.sparkContext.broadcast((book.centers, near, own, bag))
    asked = queries.join(routed.groupBy("query_id").agg(F.collect_set("cluster_id").alias("clusters")), "query_id")
    asked = asked.join(entries.groupBy("query_id").agg(F.array_sort(F.collect_set("set_id")).alias("entries")), "query_id")
    asked = spread(asked)

    def one(codes, clusters, entries):
        centers, near, own, bag = held.value
        names, n = np.unique(np.array(codes), return_counts=True)
        sims, n = (centers[names] @ centers.T), n[:, None]

        def scores(sets: list[int]) -> list[int]:
            flat, start = bag.all(sets)
            return (n * np.maximum.reduceat(sims[:, flat], start, axis=1)).sum(axis=0).astype(np.int64).tolist()

        seen = dict(zip(entries, scores(entries), strict=True))
        queues = [[(-seen[s], s)] for s in entries] if multi_path else [sorted((-seen[s], s) for s in entries)]
        best = sorted(seen.values(), reverse=True)[:ef]  # the ef best scores so far, as a heap with the worst first
        heapify(best)
        hops = guarded = 0
        live = [q for q in queues if q]
        while live:
            for queue in live:
                first, s = heappop(queue)
                if len(best) == ef and -first < best[0]:
                    queue.clear()
                    continue
                hops += 1
                new = [v for v in near[s].tolist() if v not in seen]
                if guard:
                    inside = [v for v in new if not clusters.isdisjoint(own[v].tolist())]
                    guarded += len(new) - len(inside)
                    new = inside
                for v, score in zip(new, scores(new) if new else (), strict=True):
                    seen[v] = score
                    heappush(queue, (-score, v))
                    if len(best) < ef:
                        heappush(best, score)
                    elif score > best[0]:
                        heapreplace(best, score)
            live = [q for q in live if q]
        top = sorted(seen.items(), key=lambda x: (-x[1], x[0]))[: min(ef, k)]
        return top, len(seen), hops, guarded

    def run(batches):
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                hits, scored, hops, guarded = one(r["codes"], set(r["clusters"]), r["entries"])
                out += [(r["query_id"], s, v, i + 1, scored, hops, guarded) for i, (s, v) in enumerate(hits)]
            yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], pa.int64()) for i in range(7)], names=["query_id", "set_id", "score", "rnk", "scored", "hops", "guarded"])

    return asked.select("query_id", "codes", "clusters", "entries").mapInArrow(run, "query_id long, set_id long, score long, rnk long, scored long, hops long, guarded long")


def pair_scores(cands: DataFrame, queries: DataFrame, vectors: DataFrame, ground: str = "cosine", least: int | None = None) -> DataFrame:
    """(query_id, set_id, score): Chamfer scores of the given pairs. Only the candidates' vectors are read; they meet by set with the
    queries that ask for them, whose vectors, a stated set of a checked size, each task has. A matrix product for each pair. least: products count by what they have above it."""
    asked = driver_table(queries.select("query_id", "vec_no", "v").orderBy("query_id", "vec_no"))
    ids = asked.column("query_id").to_numpy()
    x = np.array(asked.column("v").to_pylist(), np.float64)
    names, start = np.unique(ids, return_index=True)
    held = queries.sparkSession.sparkContext.broadcast(dict(zip(names.tolist(), np.split(x, start[1:]), strict=True)) if len(ids) else {})
    by = cands.select("query_id", "set_id").distinct().groupBy("set_id").agg(F.collect_list("query_id").alias("asks"))
    rows = nested(vectors.join(small(by.select("set_id")), "set_id", "left_semi")).join(by, "set_id")

    def run(batches):
        for batch in batches:
            col, out = batch.column("vecs"), []
            n, flat = col.value_lengths().to_numpy().astype(np.int64), col.flatten()
            y = flat.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(flat), -1) if len(flat) else np.zeros((0, 1))
            for i, p, asks in zip(batch.column("set_id").to_pylist(), np.split(y, np.cumsum(n)[:-1]) if len(n) else [], batch.column("asks").to_pylist(), strict=True):
                for q in asks:
                    if (v := held.value.get(q)) is None:
                        continue
                    dots = v @ p.T
                    if ground != "cosine":
                        dots = 2 * dots - (v * v).sum(axis=1)[:, None] - (p * p).sum(axis=1)[None, :]
                    best = dots.max(axis=1)
                    out.append((q, i, int((best if least is None else np.maximum(best - least, 0)).sum())))
            yield pa.RecordBatch.from_arrays([pa.array([o[c] for o in out], pa.int64()) for c in range(3)], names=["query_id", "set_id", "score"])

    return rows.select("set_id", "vecs", "asks").mapInArrow(run, "query_id long, set_id long, score long")


def rerank(cands: DataFrame, queries: DataFrame, vectors: DataFrame, k: int, ground: str = "cosine") -> DataFrame:
    """Exact Chamfer of (query_id, set_id) candidates."""
    return top_k(pair_scores(cands, queries, vectors, ground), k)


def code_scores(queries: DataFrame, codebook: DataFrame, most: int | None = None) -> DataFrame:
    """(query_id, q_no, code, s): inner products of query vectors and centres, of the `most` nearest or of all. A map by matrix
    products; the codebook is of a checked size."""
    book = driver_table(codebook.select("code", "center").orderBy("code"))
    codes, centers = book.column("code").to_numpy().astype(np.int32), np.array(book.column("center").to_pylist(), np.float64)

    def run(batches):
        for batch in batches:
            col = batch.column("v")
            for lo in range(0, batch.num_rows, 1024):
                x = col.slice(lo, 1024).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, centers.shape[1])
                s = x @ centers.T
                at = np.argsort(-s, axis=1, kind="stable")[:, : most or s.shape[1]]
                took = batch.slice(lo, 1024).take(pa.array(np.repeat(np.arange(len(x)), at.shape[1])))
                yield pa.RecordBatch.from_arrays([took.column("query_id"), took.column("vec_no"), pa.array(codes[at.ravel()]), pa.array(np.take_along_axis(s, at, 1).ravel().astype(np.int64))], names=["query_id", "q_no", "code", "s"])

    kinds = dict(queries.dtypes)
    return queries.select("query_id", "vec_no", "v").mapInArrow(run, f"query_id {kinds['query_id']}, q_no {kinds['vec_no']}, code int, s long")
