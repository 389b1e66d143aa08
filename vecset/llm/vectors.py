"""Embedding operators: near-duplicates over graphs per shard, and nearest neighbours over balanced posting lists.

Cases of both: vectors that are null, all zero, of another length than most, or hold null or non-finite components take no part;
identical vectors are one point with many rows; a vec_id is meant to be unique: of rows that share one and differ in vector each goes by
its own vector, and vectors with the same least vec_id share their links; an empty table gives an empty one; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import written
from .components import components
from .hnsw import Graph


def _takes_part(vec: str, key: str) -> Column:
    """Never null."""
    v = F.col(vec).cast("array<double>")
    fine = v.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists(v, lambda x: x != 0.0)
    return F.coalesce(fine, F.lit(False)) & F.col(key).isNotNull()


def sound(vectors: DataFrame, vec: str = "embedding", key: str = "vec_id", *more: str) -> DataFrame:
    """(vec_id, vec array<double>, more) of the vectors that take part."""
    return vectors.where(_takes_part(vec, key)).select(F.col(key).cast("long").alias("vec_id"), F.col(vec).cast("array<double>").alias("vec"), *more)


def _matrix(column: pa.Array) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt((x * x).sum(axis=1))[:, None]


# Near-duplicates --------------------------------------------------------------------------------------------------------------


def _scan(q: np.ndarray, x: np.ndarray, least: float) -> tuple[np.ndarray, np.ndarray]:
    """(query, point) pairs with inner product >= least, by brute force."""
    x, parts = x.astype(np.float64).T, [np.zeros((2, 0), np.int64)]
    for a in range(0, len(q), 512):
        i, j = np.nonzero(q[a : a + 512] @ x >= least)
        parts.append(np.stack((i + a, j)))
    return tuple(np.concatenate(parts, axis=1))


def _planted(x: np.ndarray, cos: float) -> np.ndarray:
    """A vector at that cosine from each of the unit vectors x, in a drawn direction."""
    x = _unit(x.astype(np.float64))
    side = np.random.default_rng(11).normal(size=x.shape)
    side -= (side * x).sum(axis=1)[:, None] * x
    size = np.sqrt((side * side).sum(axis=1))[:, None]
    return _unit(cos * x + np.sqrt(max(0.0, 1 - cos * cos)) * np.where(size > 1e-9, side / np.maximum(size, 1e-9), 0))


def _search(graph: Graph, q: np.ndarray, own: np.ndarray | None, least: float, beam: int, audit: int, recall: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, point) pairs with inner product >= least, and the queries that have as many as the beam holds: those are to be compared
    with every point, a block at a time. The beam doubles until it finds `recall` both of `audit` points from vectors planted at the
    least nearness that counts, so that there is always something to find, and of the pairs that brute force gives for `audit` of the
    queries, a point's pair with itself left out. Points that no link leads to are compared with every query."""
    sample = np.unique(np.linspace(0, len(q) - 1, min(audit, len(q))).astype(int))
    truth = q[sample] @ graph.x.astype(np.float64).T >= least
    if own is not None:
        truth[np.arange(len(sample)), own[sample]] = False
    goal = np.unique(np.linspace(0, len(graph.x) - 1, min(audit, len(graph.x))).astype(int))
    probes, lost = _planted(graph.x[goal], min(1.0, least + 1e-5)), graph.lost()
    strays = np.isin(goal, lost)
    while True:
        if beam >= len(graph.x):
            return *np.zeros((2, 0), np.int64), np.arange(len(q))
        ids, sims = graph.search(probes, beam)
        if ((ids == goal[:, None]).any(axis=1) | (sims[:, -1] >= least) | strays).sum() < recall * len(goal):
            beam *= 2
            continue
        ids, sims = graph.search(q, beam, own)
        hit = (sims >= least) & (ids >= 0)
        over = np.flatnonzero(hit[:, -1])
        hit[over] = False
        rest = np.setdiff1d(np.arange(len(q)), over)
        r, c = np.nonzero(hit)
        stray = _scan(q[rest], graph.x[lost], least)
        r, c = np.concatenate((r, rest[stray[0]])), np.concatenate((ids[r, c], lost[stray[1]]))
        seen = np.zeros(truth.shape, bool)
        seen[np.isin(sample, over)] = True
        at = np.full(len(q), -1)
        at[sample] = np.arange(len(sample))
        keep = at[r] >= 0
        seen[at[r[keep]], c[keep]] = True
        if (seen & truth).sum() >= recall * truth.sum():
            return r, c, over
        beam *= 2


def _found(graph: Graph, q: np.ndarray, own: np.ndarray | None, least: float, beam: int, audit: int, recall: float) -> tuple[np.ndarray, np.ndarray]:
    """All (query, point) pairs with inner product >= least, in memory: for small graphs."""
    r, c, over = _search(graph, q, own, least, beam, audit, recall)
    full = _scan(q[over], graph.x, least)
    return np.concatenate((r, over[full[0]])), np.concatenate((c, full[1]))


class _Union:
    """Least reachable number, for links that come in blocks."""

    def __init__(self, n: int):
        self.root = np.arange(n)

    def add(self, u: np.ndarray, v: np.ndarray) -> None:
        while True:
            a, b = self.root[u], self.root[v]
            live = a != b
            if not live.any():
                return
            u, v, a, b = u[live], v[live], a[live], b[live]
            np.minimum.at(self.root, np.maximum(a, b), np.minimum(a, b))
            while not np.array_equal(new := self.root[self.root], self.root):
                self.root = new


def _linked(x: np.ndarray, y: np.ndarray | None, one: Graph, two: Graph, weight_x: np.ndarray, weight_y: np.ndarray, least: float, beam: int, audit: int, recall: float) -> tuple[np.ndarray, np.ndarray, _Union]:
    """(links of each x, links of each y, union over x and y) of the pairs of unit vectors with cosine >= least; y None: pairs within x.

    Pairs that the graphs give are few for each vector. A vector near to more than a beam holds is compared with all others, in blocks
    whose pairs are added up and joined at once, so a group of thousands of near vectors takes a block's memory."""
    slack, same = least - 1e-5, y is None  # float32 search; the cosine below is in double precision
    y = x if same else y
    r, c, over_x = _search(two, x, np.arange(len(x)) if same else None, slack, beam, audit, recall)
    if same:
        r, c, over_y = np.minimum(r, c)[r != c], np.maximum(r, c)[r != c], over_x
    else:
        k, l, over_y = _search(one, y, None, slack, beam, audit, recall)
        r, c = np.concatenate((r, l)), np.concatenate((c, k))
    links_x, links_y, union = np.zeros(len(x), np.int64), np.zeros(len(y), np.int64), _Union(len(x) + (0 if same else len(y)))
    shift = 0 if same else len(x)
    whole_x, whole_y = np.isin(np.arange(len(x)), over_x), np.isin(np.arange(len(y)), over_y)
    code = np.unique(r.astype(np.int64) * len(y) + c)
    r, c = code // len(y), code % len(y)
    few = ~(whole_x[r] | whole_y[c])  # the rest comes with the blocks
    r, c = r[few], c[few]
    cos = np.concatenate([np.zeros(0), *((x[r[s : s + 65536]] * y[c[s : s + 65536]]).sum(axis=1) for s in range(0, len(r), 65536))])
    r, c = r[cos >= least], c[cos >= least]
    np.add.at(links_x, r, weight_y[c])
    np.add.at(links_x if same else links_y, c, weight_x[r])
    union.add(r, c + shift)

    def blocks(p: np.ndarray, over: np.ndarray, q: np.ndarray):
        """(vectors, whether each of q is linked to them)."""
        step = max(1, (1 << 20) // max(1, len(q)))
        for s in range(0, len(over), step):
            some = over[s : s + step]
            dots = p[some] @ q.T
            hit = dots >= least
            i, j = np.nonzero(np.abs(dots - least) < 1e-9)
            hit[i, j] = (p[some[i]] * q[j]).sum(axis=1) >= least
            yield some, hit

    for some, hit in blocks(x, over_x, y):
        if same:
            hit[np.arange(len(some)), some] = False
        links_x[some] += hit @ weight_y
        other = weight_x[some] @ hit
        links_y += np.where(whole_y, 0, other)
        i, j = np.nonzero(hit)
        union.add(some[i], j + shift)
    if same:
        return links_x + links_y, links_y, union
    for some, hit in blocks(y, over_y, x):
        links_y[some] += hit @ weight_x
        links_x += np.where(whole_x, 0, weight_y[some] @ hit)
        i, j = np.nonzero(hit)
        union.add(j, some[i] + shift)
    return links_x, links_y, union


def near_duplicates(vectors: DataFrame, least: float = 0.98, shard_rows: int = 8192, beam: int = 32, audit: int = 128, recall: float = 0.995, vec: str = "embedding", key: str = "vec_id", label: str = "label") -> DataFrame:
    """(vec_id, n_links, component_id, kept): rows are compared within a label. A label's points are dealt to shards of about
    shard_rows; each shard has a graph, and every pair of shards is searched in both directions."""
    rows = sound(vectors.where(F.col(label).isNotNull()), vec, key, F.col(label).alias("label"))
    classes = rows.groupBy("label", "vec").agg(F.min("vec_id").alias("point"), F.count("*").alias("copies"))
    classes = written(classes, "classes")
    shards = classes.groupBy("label").agg(F.ceil(F.count("*") / F.lit(shard_rows)).cast("int").alias("shards"))
    dealt = classes.join(shards, "label").withColumn("shard", F.pmod(F.xxhash64("point"), F.col("shards")).cast("int"))

    def build(group: pa.Table) -> pa.Table:
        group = group.sort_by("point")
        graph = Graph(_unit(_matrix(group.column("vec"))))
        pick = lambda name: group.column(name)[:1]
        return pa.table([pick("label").cast(pa.string()), pick("shard"), pa.array([graph.parts()], pa.list_(pa.binary())), pa.array([_matrix(group.column("vec")).tobytes()]), pa.array([group.column("point").to_numpy().tobytes()]), pa.array([group.column("copies").to_numpy().tobytes()])], names=["label", "shard", "graph", "vec", "points", "copies"])

    keyed = dealt.select(F.col("label").cast("string").alias("label"), "shard", F.size("vec").alias("width"), "vec", "point", "copies")
    graphs = written(keyed.groupBy("label", "shard", "width").applyInArrow(build, "label string, shard int, graph array<binary>, vec binary, points binary, copies binary"), "graphs")
    a, b = (graphs.select(F.col("label"), *(F.col(c).alias(f"{c}_{side}") for c in ("shard", "graph", "vec", "points", "copies"))) for side in "ab")
    jobs = a.join(b, "label").where("shard_a <= shard_b").repartition(F.col("label"), F.col("shard_a"), F.col("shard_b"))

    def compare(batches):
        for batch in batches:
            for r in batch.to_pylist():
                one, two = Graph.of(r["graph_a"]), Graph.of(r["graph_b"])
                if one.x.shape[1] != two.x.shape[1]:
                    continue
                same = r["shard_a"] == r["shard_b"]
                x, y = (_unit(np.frombuffer(r[f"vec_{s}"], np.float64).reshape(-1, one.x.shape[1])) for s in "ab")
                p, q = (np.frombuffer(r[f"points_{s}"], np.int64) for s in "ab")
                m, n = (np.frombuffer(r[f"copies_{s}"], np.int64) for s in "ab")
                links_x, links_y, union = _linked(x, None if same else y, one, two, m, n, least, beam, audit, recall)
                points, links = (p, links_x) if same else (np.concatenate((p, q)), np.concatenate((links_x, links_y)))
                at = np.flatnonzero(links)
                nodes, root, links = points[at], points[union.root[at]], links[at]
                yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(root), pa.array(links)], names=["a", "b", "n"])

    found = written(jobs.mapInArrow(compare, "a long, b long, n long"), "found")
    parts = components(found.select("a", "b"))
    counts = found.groupBy("a").agg(F.sum("n").alias("n"))
    points = classes.select("label", "vec", "point", "copies").join(counts.withColumnRenamed("a", "point"), "point", "left").join(parts.withColumnRenamed("node", "point"), "point", "left")
    points = points.select("label", "vec", (F.col("copies") - 1 + F.coalesce("n", F.lit(0))).alias("links"), F.coalesce("component", "point").alias("component"))
    member = rows.join(points, ["label", "vec"]).select("vec_id", "links", "component")
    alone = vectors.where(~_takes_part(vec, key) | F.col(label).isNull()).select(F.col(key).cast("long").alias("vec_id"), F.lit(0).cast("long").alias("links"), F.col(key).cast("long").alias("component"))
    out = member.unionAll(alone)
    return out.select("vec_id", F.col("links").cast("long").alias("n_links"), F.col("component").alias("component_id"), (F.col("component") == F.col("vec_id")).alias("kept"))


# Nearest neighbours -----------------------------------------------------------------------------------------------------------


def balanced_centroids(x: np.ndarray, k: int, rounds: int = 12, seed: int = 5) -> np.ndarray:
    """Lloyd's rounds with a price on crowded clusters: what a cluster has above its share makes it farther for the next points."""
    draw = np.random.default_rng(seed)
    centre, price = x[draw.permutation(len(x))[:k]].copy(), np.zeros(min(k, len(x)))
    for _ in range(rounds):
        own = np.argmin(((centre * centre).sum(axis=1) - 2 * x @ centre.T) + price, axis=1)
        n = np.bincount(own, minlength=len(centre))
        sums = np.zeros_like(centre)
        np.add.at(sums, own, x)
        centre = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], x[draw.integers(len(x), size=len(centre))])
        price += 0.1 * np.var(x) * x.shape[1] * (n / (len(x) / len(centre)) - 1).clip(-1, 1)
    return centre


class Lists:
    """Centroids with a graph over them. Nearness to a centroid is the distance; the graph works on lifted unit vectors, whose inner
    products have the order of the distances."""

    def __init__(self, centre: np.ndarray, beam: int):
        self.centre, self.beam = centre, beam
        size = (centre * centre).sum(axis=1)
        # -|c|^2/2 as one more coordinate keeps the order of distances; one further makes all of one length
        lifted = np.concatenate((centre, -size[:, None] / 2), axis=1)
        length = (lifted * lifted).sum(axis=1)
        lifted = np.concatenate((lifted, np.sqrt(np.maximum(length.max() - length, 0))[:, None]), axis=1)
        self.graph = Graph(lifted / max(np.sqrt(length.max()), 1e-12), degree=16, beam=64)

    def near(self, x: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and distances of the `most` nearest centroids that a beam of twice as many finds, nearest first; -1 padded."""
        most = min(most, len(self.centre))
        ask = np.concatenate((x, np.ones((len(x), 1)), np.zeros((len(x), 1))), axis=1)
        ask /= np.sqrt((ask * ask).sum(axis=1))[:, None]
        ids = self.graph.search(ask, max(2 * most, self.beam))[0]
        d = np.sqrt(np.maximum((x * x).sum(axis=1)[:, None] + (self.centre * self.centre).sum(axis=1)[ids] - 2 * np.einsum("qd,qkd->qk", x, self.centre[ids]), 0))
        d[ids < 0] = np.inf
        order = np.argsort(d, axis=1, kind="stable")[:, :most]
        return np.take_along_axis(ids, order, 1), np.take_along_axis(d, order, 1)


#: Queries that a scan holds at once; of more, each part is a scan of its own.
QUERIES_AT_ONCE = 200_000


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 20, list_rows: int = 512, sample: int = 20_000, replicas: int = 3, boundary: float = 1.05, recall: float = 0.97, audit: int = 64, vec: str = "embedding", key: str = "vec_id", at_once: int = QUERIES_AT_ONCE) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k rows of largest inner product, but itself.

    Centroids are fitted on at most `sample` rows (a parameter), every row is indexed: in the list of its nearest centroid, and of
    up to `replicas` - 1 more whose distance is within `boundary` times that. A query reads the lists whose centroid's distance is
    within a ratio of its nearest one's; the ratio is what brings the true neighbours of `audit` queries to `recall`.

    A list is many blocks, one or more of each task that placed rows; they are written once, in the vectors' own width, and neither
    they nor the queries are shuffled: a scan's tasks hold the queries and tell for each block which of them read its list.
    """
    rows, asked = sound(vectors, vec, key), sound(queries, vec, key)
    n, width = rows.agg(F.count("*"), F.mode(F.size("vec"))).first()
    spark = vectors.sparkSession
    if not n:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    rows, asked = (d.where(F.size("vec") == width) for d in (rows, asked))
    fitted = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).toArrow()
    n_lists = max(1, min(-(-n // list_rows), fitted.num_rows // 16))
    lists = Lists(balanced_centroids(_matrix(fitted.column("vec")), n_lists), 32)
    del fitted
    narrow = np.float32 if dict(vectors.dtypes)[vec] == "array<float>" else np.float64

    def place(batches):
        """Blocks of one list each, from some batches at a time."""
        held, n_held = [], 0

        def blocks():
            own, ids, x = (np.concatenate([h[c] for h in held]) for c in range(3))
            order = np.argsort(own, kind="stable")
            own = own[order]
            cut = np.concatenate(([0], np.flatnonzero(np.diff(own)) + 1, [len(own)]))
            for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
                some = order[a:b]
                yield pa.RecordBatch.from_arrays([pa.array([int(own[a])], pa.int32()), pa.array([ids[some].tobytes()]), pa.array([x[some].tobytes()])], names=["list", "ids", "vecs"])

        for batch in batches:
            for s in range(0, batch.num_rows, 2048):
                part = batch.slice(s, 2048)
                x = _matrix(part.column("vec"))
                ids, d = lists.near(x, replicas)
                keep = (ids >= 0) & (d <= boundary * d[:, :1])
                keep[:, 0] = True
                r, c = np.nonzero(keep)
                held.append((ids[r, c], part.column("vec_id").to_numpy()[r], x[r].astype(narrow)))
                n_held += len(r)
                if n_held * width > 1 << 23:
                    yield from blocks()
                    held, n_held = [], 0
        if held:
            yield from blocks()

    postings = written(rows.mapInArrow(place, "list int, ids binary, vecs binary"), "postings")
    ratio = _ratio(rows, asked, lists, k, replicas, boundary, recall, audit)
    parts = max(1, -(-asked.count() // at_once))
    hits = None
    for i in range(parts):
        got = _scanned(postings, asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(parts)) == i), lists, ratio, k, width, narrow)
        hits = got if hits is None else hits.unionAll(got)
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return hits.distinct().withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def _scanned(postings: DataFrame, asked: DataFrame, lists: Lists, ratio: float, k: int, width: int, narrow: type, cells: int = 1 << 18) -> DataFrame:
    """(query_id, vec_id, score): the k best that each task found for each query in the blocks of the lists that it reads."""
    some = asked.select("vec_id", "vec").toArrow()
    names, q = some.column("vec_id").to_numpy(), _matrix(some.column("vec")).astype(narrow)
    del some
    centre = lists.centre
    reach = np.concatenate([np.zeros(0), *(ratio * lists.near(q[s : s + 4096].astype(np.float64), 1)[1][:, 0] for s in range(0, len(q), 4096))])
    sent = postings.sparkSession.sparkContext.broadcast((names, q, reach))

    def scan(batches):
        names, q, reach = sent.value
        if not len(names):
            return
        q = q.astype(np.float64)
        size = (q * q).sum(axis=1)
        least, most = np.full(len(q), -np.inf), max(400_000, len(q) * k)
        best, held, n_held = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)), [], 0

        def merged():
            """The k best of each query, ties to the smaller vec_id; from now on only what may be among them is held."""
            i, v, s = (np.concatenate([h[c] for h in (best, *held)]) for c in range(3))
            order = np.lexsort((v, -s, i))
            i, v, s = i[order], v[order], s[order]
            new = np.concatenate(([True], (i[1:] != i[:-1]) | (v[1:] != v[:-1]) | (s[1:] != s[:-1])))[: len(i)]  # replicas
            i, v, s = i[new], v[new], s[new]
            first = np.concatenate(([True], i[1:] != i[:-1]))[: len(i)]
            rank = np.arange(len(i)) - np.maximum.accumulate(np.where(first, np.arange(len(i)), 0))
            last = rank == k - 1
            least[i[last]] = s[last]
            return i[rank < k], v[rank < k], s[rank < k]

        for batch in batches:
            for own, ids, vecs in zip(batch.column("list").to_pylist(), batch.column("ids"), batch.column("vecs"), strict=True):
                c = centre[own]
                reads = np.flatnonzero(np.sqrt(np.maximum(size - 2 * q @ c + c @ c, 0)) <= reach)
                ids, x = np.frombuffer(ids.as_buffer(), np.int64), np.frombuffer(vecs.as_buffer(), narrow).reshape(-1, width).astype(np.float64)
                slack = 1e-12 * np.sqrt((x * x).sum(axis=1).max())
                step = max(1, cells // len(ids))
                for a in range(0, len(reads), step):
                    at = reads[a : a + step]
                    i, j = np.nonzero(q[at] @ x.T >= (least[at] - slack * np.sqrt(size[at]))[:, None])
                    i = at[i]
                    other = names[i] != ids[j]
                    i, j = i[other], j[other]
                    held += [(i[b : b + 8192], ids[j[b : b + 8192]], (q[i[b : b + 8192]] * x[j[b : b + 8192]]).sum(axis=1)) for b in range(0, len(i), 8192)]
                    n_held += len(i)
                    if n_held > most:
                        best, held, n_held = merged(), [], 0
        best = merged()
        for a in range(0, len(best[0]), 65536):
            i, v, s = (b[a : a + 65536] for b in best)
            yield pa.RecordBatch.from_arrays([pa.array(names[i]), pa.array(v), pa.array(s)], names=["query_id", "vec_id", "score"])

    return postings.mapInArrow(scan, "query_id long, vec_id long, score double")


def brute_force(rows: DataFrame, q_ids: np.ndarray, q: np.ndarray, k: int) -> DataFrame:
    """(query_id, vec_id, vec, score): the k nearest of a bounded set of queries in every batch of rows; the best of them are the true ones."""

    def run(batches):
        for batch in batches:
            v, ids = _matrix(batch.column("vec")), batch.column("vec_id").to_numpy()
            if not len(ids):
                continue
            dots = q @ v.T
            dots[q_ids[:, None] == ids[None, :]] = -np.inf
            most = min(k, len(ids))
            top = np.argpartition(-dots, most - 1, axis=1)[:, :most]
            r, c = np.repeat(np.arange(len(q)), most), top.ravel()
            fine = np.isfinite(dots[r, c])
            took = batch.take(pa.array(c[fine]))
            yield pa.RecordBatch.from_arrays([pa.array(q_ids[r[fine]]), took.column("vec_id"), took.column("vec"), pa.array(dots[r[fine], c[fine]])], names=["query_id", "vec_id", "vec", "score"])

    found = rows.mapInArrow(run, "query_id long, vec_id long, vec array<double>, score double")
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def _ratio(rows: DataFrame, asked: DataFrame, lists: Lists, k: int, replicas: int, boundary: float, recall: float, audit: int) -> float:
    """The ratio at which the lists that are read hold `recall` of the true neighbours of the audited queries."""
    some = asked.orderBy(F.xxhash64("vec_id"), "vec_id").limit(audit).toArrow()
    if not some.num_rows:
        return 1.0
    q_ids, q = some.column("vec_id").to_numpy(), _matrix(some.column("vec"))
    true = brute_force(rows, q_ids, q, k).select("query_id", "vec").toArrow()
    if not true.num_rows:
        return 1.0
    at, d = lists.near(_matrix(true.column("vec")), replicas)
    own = (at >= 0) & (d <= boundary * d[:, :1])
    own[:, 0] = True
    order = np.argsort(q_ids)
    x = q[order][np.searchsorted(q_ids[order], true.column("query_id").to_numpy())]
    to = np.sqrt(np.maximum(((x[:, None, :] - lists.centre[at]) ** 2).sum(axis=2), 0))
    to[~own] = np.inf
    base = lists.near(x, 1)[1][:, 0]
    return float(np.quantile(to.min(axis=1) / np.maximum(base, 1e-12), recall, method="higher")) + 1e-9
