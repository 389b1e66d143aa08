"""The proximity graph over sets: edges inside clusters, bridges at shared members, shortcuts from training pairs."""

from __future__ import annotations

import itertools
from heapq import heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.transport import emd, entropic_filled
from ..plans.limits import driver_table, small
from .iterate import cut

UNIT = 1_000_000  # of fixed-point inner products
MOST_COUNTS = 1 << 22  # sets times codes that a task counts in a matrix; beyond, set by set


class Codebook:
    """Code distances in fixed point: UNIT less the inner product. A block of the codes in use is made for each cluster."""

    def __init__(self, codebook: DataFrame):
        book = driver_table(codebook.orderBy("code"))
        self.centers = np.array(book.column("center").to_pylist(), np.float64)

    def block(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        seen, at = np.unique(codes, return_inverse=True)
        c = self.centers[seen]
        return UNIT - c @ c.T, at


def set_distances(one: np.ndarray, others: list[np.ndarray], block: np.ndarray, edge: str, cut: float = np.inf, solver: str = "exact") -> np.ndarray:
    """From a set's codes to others'. qemd: earth mover's on codes; pairs whose lower bound is above cut keep the bound. qch: mean of minima."""
    if not others:
        return np.zeros(0)
    to, back = Bags(others).one_sided(one, block)
    if edge == "qch":
        return to
    out = np.maximum(to, back)
    at = np.flatnonzero(out <= cut)
    out[at] = _transports(one, [others[k] for k in at], block, solver)
    return out


def _transports(one: np.ndarray, others: list[np.ndarray], block: np.ndarray, solver: str) -> np.ndarray:
    """Earth mover's distances. exact: a flow for each pair; sinkhorn: all pairs at once, close from above."""
    if len(one) == 2 and all(len(o) == 2 for o in others):
        c = block[np.ix_(one, np.concatenate(others))].reshape(2, -1, 2) if others else np.zeros((2, 0, 2))
        return np.minimum(c[0, :, 0] + c[1, :, 1], c[0, :, 1] + c[1, :, 0]) / 2
    a, ca = np.unique(one, return_counts=True)
    bags = [np.unique(o, return_counts=True) for o in others]
    if solver == "exact":
        return np.array([emd(block[np.ix_(a, b)], ca, cb) for b, cb in bags])
    codes, weight = _padded(bags)
    return _entropic_from(a, ca / ca.sum(), codes, weight, block)


def _padded(bags: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """(codes, shares) of sets as rows of one length; places beyond a set's own repeat its first code and weigh 0."""
    width = max((len(b) for b, _ in bags), default=1)
    codes, weight = np.zeros((len(bags), width), np.int64), np.zeros((len(bags), width))
    for k, (b, cb) in enumerate(bags):
        codes[k], codes[k, : len(b)], weight[k, : len(b)] = b[0], b, cb / cb.sum()
    return codes, weight


def _entropic_from(a: np.ndarray, share: np.ndarray, codes: np.ndarray, weight: np.ndarray, block: np.ndarray, most: float = np.inf) -> np.ndarray:
    cost = block[a][:, codes].transpose(1, 0, 2)
    return entropic_filled(np.ascontiguousarray(cost), np.broadcast_to(share, (len(codes), len(a))), weight, most=most)


class Bags:
    """Sets as runs of codes in one array: distances from one set to all of them by a few array steps."""

    def __init__(self, sets: list[np.ndarray]):
        self.sets, self.flat = sets, np.concatenate(sets)
        self.size = np.array([len(c) for c in sets])
        self.start = np.cumsum(self.size) - self.size
        self._rows = None

    def one_sided(self, one: np.ndarray, block: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(mean over one's codes of the nearest in each set, mean over each set's codes of the nearest in one)."""
        codes, n = np.unique(one, return_counts=True)
        rows = block[codes]
        to = np.zeros(len(self.sets))
        for row, w in zip(rows, n, strict=True):
            to += w * np.minimum.reduceat(row[self.flat], self.start)
        return to / len(one), np.add.reduceat(rows.min(axis=0)[self.flat], self.start) / self.size

    def counts(self, codes: int) -> np.ndarray:
        """How often each set has each code."""
        own = np.repeat(np.arange(len(self.sets)), self.size)
        return np.bincount(own * codes + self.flat, minlength=len(self.sets) * codes).reshape(-1, codes).astype(np.float64)

    def least(self, block: np.ndarray) -> np.ndarray:
        """Each set's nearest code to each code of the block."""
        return np.stack([np.minimum.reduceat(row[self.flat], self.start) for row in block], axis=1)

    def all_one_sided(self, others: "Bags", block: np.ndarray, step: int = 256):
        """one_sided from each of these sets to all the others, by matrix products of counts and least distances."""
        n, near = others.counts(len(block)), others.least(block)
        mine, own = (n, near) if self is others else (self.counts(len(block)), self.least(block))
        for a in range(0, len(self.sets), step):
            to = mine[a : a + step] @ near.T / self.size[a : a + step, None]
            yield from zip(to, own[a : a + step] @ n.T / others.size, strict=True)

    def all_overlaps(self, others: "Bags", block: np.ndarray, step: int = 256):
        """Lower bounds of the earth mover's distance from each of these sets to all the others, no less than one_sided's: a code may
        stay at itself with the share that both sets have, and what is left goes to the nearest other code. The larger of both ways."""
        far, own = block.copy(), np.diag(block)
        np.fill_diagonal(far, np.inf)

        def parts(bags: "Bags") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            near = bags.least(far)
            near = np.where(np.isfinite(near), near, own)  # a set's only code: it has room for all
            return bags.counts(len(block)) / bags.size[:, None], near, np.minimum(own - near, 0)

        share, near, gain = parts(others)
        mine = (share, near, gain) if self is others else parts(self)
        share_by, gain_by = np.ascontiguousarray(share.T), np.ascontiguousarray(gain.T)
        for lo in range(0, len(self.sets), step):
            to, back = mine[0][lo : lo + step] @ near.T, mine[1][lo : lo + step] @ share_by
            for i in range(len(to)):
                has = np.flatnonzero(mine[0][lo + i])
                both = np.minimum(mine[0][lo + i, has, None], share_by[has])
                yield np.maximum(to[i] + np.einsum("ij,ij->j", both, gain_by[has]), back[i] + mine[2][lo + i, has] @ both)

    def padded(self, block: np.ndarray) -> tuple:
        """_padded of all sets, the shares and the block in single precision too, made once."""
        if self._rows is None or self._rows[0] is not block:
            codes, weight = _padded([np.unique(s, return_counts=True) for s in self.sets])
            self._rows = block, codes, weight, weight.astype(np.float32), block.astype(np.float32)
        return self._rows[1:]

    def nearest(self, one: np.ndarray, block: np.ndarray, f: int, edge: str, ids: np.ndarray, skip: int, solver: str = "exact", low: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(places, distances) of the f nearest sets, ties to the smaller id, without place `skip`. Distances are had in the order of
        their lower bounds, until a bound is above the f-th distance found. low: lower bounds, where they are known."""
        if edge == "qch":
            d = low if low is not None else self.one_sided(one, block)[0]
        else:
            low = np.maximum(*self.one_sided(one, block)) if low is None else low
            order = np.argsort(low, kind="stable")
            order = order[order != skip]
            solve = lambda some, most: _transports(one, [self.sets[j] for j in some], block, solver)
            if solver == "exact" or len(one) <= 2:
                d = _until(low, order, f, solve, 1e-6)
            else:
                a, n = np.unique(one, return_counts=True)
                codes, weight, light, half = self.padded(block)
                cut_ = lambda some, w: _narrow(codes[some], w[some])
                slack = 1e-4 * np.abs(block).max()  # many times what single precision and its rounds can be off, with a thousandth of the f-th
                rough = _until(low, order, f, lambda some, most: _entropic_from(a, (n / n.sum()).astype(np.float32), *cut_(some, light), half, most), slack)
                d = np.full(len(low), np.inf)
                near = np.flatnonzero(rough <= _limit(rough[np.isfinite(rough)], f, slack))
                near = near[np.isfinite(rough[near])]
                if len(near):
                    d[near] = np.concatenate([_entropic_from(a, n / n.sum(), *cut_(near[k : k + 64], weight), block) for k in range(0, len(near), 64)])
        order = np.lexsort((ids, d))
        order = order[(order != skip) & np.isfinite(d[order])][:f]
        return order, d[order]


def _limit(d: np.ndarray, f: int, slack: float) -> float:
    """The f-th least distance with room for what it may be off; no limit while there are no more than f."""
    if len(d) <= f:
        return np.inf
    worst = np.partition(d, f - 1)[f - 1]
    return worst + slack + (1e-3 * abs(worst) if slack > 1 else 0)


def _until(low: np.ndarray, order: np.ndarray, f: int, solve, slack: float) -> np.ndarray:
    """Distances by solve(places, limit) in the order of their lower bounds, until a bound is above the limit; the others are infinite."""
    d, most, at = np.full(len(low), np.inf), np.inf, 0
    while at < len(order):
        some = order[at : at + (96 if at else 32)]
        at += len(some)
        some = some[low[some] <= most]
        if not len(some):
            break
        d[some] = solve(some, most)
        most = _limit(d[order[:at]], f, slack)
    return d


def _narrow(codes: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Without the columns that weigh nothing in any row."""
    width = int((weight > 0).sum(axis=1).max())
    return codes[:, :width], weight[:, :width]


def local_edges(members: DataFrame, coded: DataFrame, codebook: DataFrame, f: int = 24, edge: str = "qemd", mode: str = "exact", beam: int = 80, block_sets: int = 4096, solver: str = "exact", ask_sets: int = 512) -> DataFrame:
    """(src, dst, dist, via): each member of a cluster and its f nearest others there. members: (set_id, cluster_id); coded: (set_id, code).

    solver: exact flows, or sinkhorn, close from above and many times faster for sets of tens of vectors.
    exact: a cluster is dealt in blocks of about block_sets members, each pair of blocks is compared by one task, and the f nearest of
    each member over all blocks stay: a cluster of any size gives the same edges, and no task holds it whole. About ask_sets members
    of a block ask in one task, so that a large cluster's work is not one task's.
    incremental: members go in by md5 order; each searches the part that stands, as a best-first walk of `beam`. The walk needs the
    part it walks; where a cluster has more than block_sets members, its blocks are walked each by itself and by the exact way across.
    """
    book = Codebook(codebook)
    sets = coded.groupBy("set_id").agg(F.sort_array(F.collect_list("code")).alias("codes"))
    rows = members.select("set_id", "cluster_id").distinct().join(sets, "set_id")
    size = members.select("set_id", "cluster_id").distinct().groupBy("cluster_id").agg(F.count("*").alias("n"))
    size = size.withColumn("blocks", F.ceil(F.col("n") / F.lit(block_sets)).cast("int"))
    size = size.withColumn("slices", F.ceil(F.col("n") / F.col("blocks") / F.lit(ask_sets)).cast("int")).drop("n")
    size = cut(size.withColumn("whole", F.lit(1) if mode == "incremental" else F.col("slices")))
    rows = rows.join(small(size), "cluster_id").withColumn("own", F.pmod(F.xxhash64("set_id"), F.col("blocks")).cast("int"))
    each = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    mine = lambda n: F.pmod(F.xxhash64("set_id", F.lit(1)), F.col(n)).cast("int")
    held = ["cluster_id", "set_id", "codes"]
    among = rows.select(*held, F.col("own").alias("a"), F.col("own").alias("b"), each("whole").alias("part"), mine("whole").alias("_own"))
    among = among.select(*held, "a", "b", "part", (F.col("part") == F.col("_own")).alias("asks"))
    apart = rows.where("blocks > 1").withColumn("other", each("blocks")).where("other <> own")
    left = apart.select(*held, F.col("own").alias("a"), F.col("other").alias("b"), mine("slices").alias("part"), F.lit(True).alias("asks"))
    right = apart.select(*held, F.col("other").alias("a"), F.col("own").alias("b"), each("slices").alias("part"), F.lit(False).alias("asks"))
    tasks = int(size.agg(F.sum(F.col("blocks") * (F.col("whole") + (F.col("blocks") - 1) * F.col("slices")))).first()[0] or 1)

    def build(group: pa.Table) -> pa.Table:
        group = group.sort_by("set_id")
        ids, asks = group.column("set_id").to_numpy(), np.array(group.column("asks").to_pylist(), bool)
        codes = [np.array(c) for c in group.column("codes").to_pylist()]
        block, at = book.block(np.concatenate(codes))
        sets_ = np.split(at, np.cumsum([len(c) for c in codes])[:-1])
        same = group.column("a")[0].as_py() == group.column("b")[0].as_py()
        if same and mode == "incremental":
            found = _inserted(ids, sets_, block, f, edge, beam, solver)
        else:
            there = np.arange(len(ids)) if same else np.flatnonzero(~asks)
            bags, names = Bags([sets_[j] for j in there]) if len(there) else None, ids[there]
            found = []
            asking = np.flatnonzero(asks) if len(there) else []
            known = itertools.repeat(None)
            if len(asking) and len(sets_) * len(block) <= MOST_COUNTS:
                own = bags if same and asks.all() else Bags([sets_[i] for i in asking])
                known = (to for to, _ in own.all_one_sided(bags, block)) if edge == "qch" else own.all_overlaps(bags, block)
            for i, low in zip(asking, known):
                place, d = bags.nearest(sets_[i], block, f, edge, names, i if same else -1, solver, low)
                found.append((ids[i], names[place], d))
        n = [len(x[1]) for x in found]
        src = np.repeat([x[0] for x in found], n).astype(np.int64) if found else np.zeros(0, np.int64)
        dst, dist = (np.concatenate([x[k] for x in found]) if found else np.zeros(0) for k in (1, 2))
        via = group.column("cluster_id")[0].as_py()
        return pa.table([pa.array(src), pa.array(dst.astype(np.int64)), pa.array(dist.astype(np.float64)), pa.array([via] * len(src), pa.int32())], names=["src", "dst", "dist", "via"])

    by = ["cluster_id", "a", "b", "part"]
    found = among.unionAll(left).unionAll(right).repartition(min(max(tasks, 1), 2000), *by).groupBy(*by).applyInArrow(build, "src long, dst long, dist double, via int")
    best = Window.partitionBy("via", "src").orderBy("dist", "dst")
    return found.withColumn("_n", F.row_number().over(best)).where(F.col("_n") <= f).drop("_n")


def linked_edges(fresh: DataFrame, members: DataFrame, coded: DataFrame, codebook: DataFrame, f: int, edge: str = "qemd", block_sets: int = 4096, solver: str = "exact") -> DataFrame:
    """(src, dst, dist, via): each new set and its f nearest members, old or new, of its clusters. A task compares the new sets of a
    cluster with one block of its members."""
    book = Codebook(codebook)
    sets = coded.groupBy("set_id").agg(F.sort_array(F.collect_list("code")).alias("codes"))
    size = members.groupBy("cluster_id").agg(F.ceil(F.count("*") / F.lit(block_sets)).cast("int").alias("blocks"))
    there = members.select("set_id", "cluster_id").join(sets, "set_id").join(small(size), "cluster_id")
    there = there.select("cluster_id", "set_id", "codes", F.pmod(F.xxhash64("set_id"), F.col("blocks")).cast("int").alias("part"), F.lit(False).alias("asks"))
    new = fresh.select("set_id", "cluster_id").join(sets, "set_id").join(small(size), "cluster_id")
    new = new.select("cluster_id", "set_id", "codes", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("part"), F.lit(True).alias("asks"))

    def build(group: pa.Table) -> pa.Table:
        group = group.sort_by("set_id")
        ids, asks = group.column("set_id").to_numpy(), np.array(group.column("asks").to_pylist(), bool)
        codes = [np.array(c) for c in group.column("codes").to_pylist()]
        block, at = book.block(np.concatenate(codes))
        sets_, old = np.split(at, np.cumsum([len(c) for c in codes])[:-1]), np.flatnonzero(~asks)
        out = []
        bags, names = Bags([sets_[j] for j in old]) if len(old) else None, ids[old]
        for i in np.flatnonzero(asks) if len(old) else []:
            own = np.flatnonzero(names == ids[i])
            place, d = bags.nearest(sets_[i], block, f, edge, names, int(own[0]) if len(own) else -1, solver)
            out += zip([ids[i]] * len(d), names[place].tolist(), d.tolist(), strict=True)
        via = group.column("cluster_id")[0].as_py()
        return pa.table([pa.array([o[0] for o in out], pa.int64()), pa.array([o[1] for o in out], pa.int64()), pa.array([o[2] for o in out], pa.float64()), pa.array([via] * len(out), pa.int32())], names=["src", "dst", "dist", "via"])

    found = new.unionAll(there).groupBy("cluster_id", "part").applyInArrow(build, "src long, dst long, dist double, via int")
    best = Window.partitionBy("via", "src").orderBy("dist", "dst")
    return found.withColumn("_n", F.row_number().over(best)).where(F.col("_n") <= f).drop("_n")


def _inserted(ids: np.ndarray, sets_: list[np.ndarray], block: np.ndarray, f: int, edge: str, beam: int, solver: str = "exact") -> list[tuple]:
    """One after the other: each new set walks the graph so far and is linked both ways to the f nearest that it met; the farthest
    link of a vertex that gets too many is dropped."""
    near: dict[int, dict[int, float]] = {}
    for i in _md5_order(ids):
        found: dict[int, float] = {}
        if near:
            start = next(iter(near))
            found[start] = float(set_distances(sets_[i], [sets_[start]], block, edge, np.inf, solver)[0])
            todo, best = [(found[start], ids[start], start)], [-found[start]]
            while todo:
                d, _, u = heappop(todo)
                worst = -best[0] if len(best) >= beam else np.inf
                if d > worst:
                    break
                new = [v for v in near[u] if v not in found]
                for v, dv in zip(new, set_distances(sets_[i], [sets_[v] for v in new], block, edge, worst, solver), strict=True):
                    found[v] = float(dv)
                    heappush(todo, (found[v], ids[v], v))
                    heappush(best, -found[v])
                    if len(best) > beam:
                        heappop(best)
        near[i] = {}
        for v, d in sorted(found.items(), key=lambda x: (x[1], ids[x[0]]))[:f]:
            near[i][v] = near[v][i] = d
            if len(near[v]) > f:
                del near[v][max(near[v], key=lambda x: (near[v][x], ids[x]))]
    return [(ids[i], ids[np.array(list(links), int)], np.array(list(links.values()))) for i, links in near.items() if links]


def _md5_order(ids: np.ndarray) -> list[int]:
    import hashlib

    return sorted(range(len(ids)), key=lambda i: hashlib.md5(str(ids[i]).encode()).hexdigest())  # noqa: S324


def mirrored(cand: DataFrame) -> DataFrame:
    """Both directions of each half-edge, once, with the least cluster that gave it."""
    back = cand.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist", "via")
    return cand.select("src", "dst", "dist", "via").unionAll(back).groupBy("src", "dst").agg(F.min("dist").alias("dist"), F.min("via").alias("via"))


def merge_bridges(cand: DataFrame, membership: DataFrame, most: int, mode: str = "reserve") -> DataFrame:
    """(src, dst, dist, via, reserved): at most `most` neighbours; under reserve the nearest of each of the vertex's own clusters
    comes before any other. Order-independent, so a rerun gives the same graph."""
    pairs = mirrored(cand)
    if mode == "reserve":
        own = membership.select(F.col("set_id").alias("src"), "cluster_id", "rnk")
        theirs = membership.select(F.col("set_id").alias("dst"), "cluster_id")
        near = Window.partitionBy("src", "cluster_id").orderBy("dist", "dst")
        held = pairs.join(own, "src").join(theirs, ["dst", "cluster_id"]).withColumn("_n", F.row_number().over(near)).where("_n = 1")
        held = held.groupBy("src", "dst").agg(F.min("rnk").alias("best"))
        pairs = pairs.join(held, ["src", "dst"], "left")
    else:
        pairs = pairs.withColumn("best", F.lit(None).cast("int"))
    first = Window.partitionBy("src").orderBy(F.coalesce("best", F.lit(1 << 30)), "dist", "dst")
    kept = pairs.withColumn("_n", F.row_number().over(first)).where(F.col("_n") <= most)
    return kept.select("src", "dst", "dist", "via", F.col("best").isNotNull().cast("int").alias("reserved"))


def merge_bridges_in_turn(cand: DataFrame, membership: DataFrame, most: int) -> DataFrame:
    """The order-dependent variant: the `most` nearest first, then for each cluster that is missing the farthest kept one gives way."""
    pairs = mirrored(cand).join(membership.groupBy("set_id").agg(F.collect_set("cluster_id").alias("theirs")).withColumnRenamed("set_id", "dst"), "dst")
    pairs = pairs.join(membership.groupBy("set_id").agg(F.sort_array(F.collect_set("cluster_id")).alias("own")).withColumnRenamed("set_id", "src"), "src")

    def merge(group: pa.Table) -> pa.Table:
        rows = sorted(group.to_pylist(), key=lambda r: (r["dist"], r["dst"]))
        kept, rest = rows[:most], rows[most:]
        for cluster in rows[0]["own"]:
            if not any(cluster in r["theirs"] for r in kept):
                for r in rest:
                    if cluster in r["theirs"]:
                        kept = sorted([*kept[: most - 1], r], key=lambda x: (x["dist"], x["dst"]))
                        break
        return pa.table({c: pa.array([r[c] for r in kept]) for c in ("src", "dst", "dist", "via")}, schema=pa.schema([("src", pa.int64()), ("dst", pa.int64()), ("dist", pa.float64()), ("via", pa.int32())]))

    return pairs.groupBy("src").applyInArrow(merge, "src long, dst long, dist double, via int")


def trim_degree(edges: DataFrame, most: int, symmetric: bool = False) -> DataFrame:
    """The `most` nearest of each vertex; symmetric: an edge stays only if both its halves do."""
    w = Window.partitionBy("src").orderBy("dist", "dst")
    kept = edges.withColumn("_n", F.row_number().over(w)).where(F.col("_n") <= most).drop("_n")
    if symmetric:
        kept = kept.join(kept.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"], "left_semi")
    return kept


def shortcut_candidates(hits: DataFrame, train: DataFrame, edges: DataFrame, depth: int = 10) -> DataFrame:
    """(u, v): top hit and answer of training pairs whose answer is not among the first `depth` hits, not yet linked."""
    first = hits.where("rnk <= %d" % depth)
    missed = train.join(first.select("query_id", "set_id"), ["query_id", "set_id"], "left_anti")
    pairs = missed.join(first.where("rnk = 1").select("query_id", F.col("set_id").alias("top")), "query_id").where("top <> set_id")
    pairs = pairs.select(F.least("top", "set_id").alias("u"), F.greatest("top", "set_id").alias("v")).distinct()
    linked = edges.select(F.least("src", "dst").alias("u"), F.greatest("src", "dst").alias("v")).distinct()
    return pairs.join(linked, ["u", "v"], "left_anti")


def admit_shortcuts(pairs: DataFrame, edges: DataFrame, most: int) -> DataFrame:
    """(u, v) of pairs that find room at both ends: among a vertex's candidates, in md5 order, those within its spare degree."""
    degree = edges.groupBy("src").agg(F.count("*").alias("degree"))
    spare = lambda end: degree.select(F.col("src").alias(end), F.col("degree").alias(f"d_{end}"))
    ends = pairs.select("u", "v", F.md5(F.concat_ws("-", F.col("u").cast("string"), F.col("v").cast("string"))).alias("h"))
    half = ends.select(F.col("u").alias("x"), "u", "v", "h").unionAll(ends.select(F.col("v").alias("x"), "u", "v", "h"))
    rank = half.withColumn("n", F.row_number().over(Window.partitionBy("x").orderBy("h", "u", "v")))
    fits = rank.join(spare("x"), "x", "left").where(F.col("n") <= most - F.coalesce("d_x", F.lit(0)))
    return fits.groupBy("u", "v").agg(F.count("*").alias("ends")).where("ends = 2").select("u", "v")


def stitch(components: DataFrame, means: DataFrame) -> DataFrame:
    """(src, dst, component): for each component but the largest, its pair of nearest sets inside and outside. components: (set_id,
    component); means: (set_id, v). The sets of the smaller components are few and go to every task."""
    size = components.groupBy("component").agg(F.count("*").alias("n"))
    largest = size.orderBy(F.col("n").desc(), "component").limit(1).select("component")
    inside = components.join(small(largest), "component", "left_anti").join(means, "set_id").select(F.col("set_id").alias("src"), "component", F.col("v").alias("_v"))
    table = driver_table(inside)
    if not table.num_rows:
        return components.sparkSession.createDataFrame([], "src long, dst long, component long")
    ids, own = table.column("src").to_numpy(), table.column("component").to_numpy()
    x = np.array(table.column("_v").to_pylist(), np.float64)

    def run(batches):
        for batch in batches:
            y, there, part = np.array(batch.column("v").to_pylist(), np.float64), batch.column("set_id").to_numpy(), batch.column("component").to_numpy()
            if not len(there):
                continue
            s = np.where(own[:, None] == part[None, :], -np.inf, x @ y.T)
            best = s.argmax(axis=1)
            at = np.flatnonzero(np.isfinite(s[np.arange(len(x)), best]))
            yield pa.RecordBatch.from_arrays([pa.array(ids[at]), pa.array(there[best[at]]), pa.array(own[at]), pa.array(s[at, best[at]])], names=["src", "dst", "component", "s"])

    found = means.join(components, "set_id").select("set_id", "v", "component").mapInArrow(run, "src long, dst long, component long, s double")
    return found.groupBy("component").agg(F.max_by(F.struct("src", "dst"), F.struct("s", -F.col("src"), -F.col("dst"))).alias("p")).select("p.src", "p.dst", "component")
