"""Near-duplicate sets of tokens by prefixes of rare tokens."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.limits import driver_table, small
from .iterate import components, shared

#: Counts that order the tokens, each of the tokens whose hashes share its bits; pairs that a task makes at once; bytes of a check's group.
COUNTS, PAIRS, UNIT = 1 << 20, 1 << 18, 2 << 20
PREFIX = "token long, id long, n int, pos int, prev long, s0 long, s1 long, s2 long, s3 long"


def _kept(df: DataFrame, name: str) -> DataFrame:
    path = shared(df.sparkSession, name)
    df.write.option("parquet.block.size", 16 << 20).parquet(path)
    return df.sparkSession.read.parquet(path)


def _least(n, percent: int):
    """Tokens that sets of up to n have to share."""
    return -(-percent * n // 100)


def _ragged(start: np.ndarray, n: np.ndarray) -> np.ndarray:
    """start[0], ..., start[0] + n[0] - 1, start[1], ..."""
    return np.arange(n.sum()) + np.repeat(start - np.cumsum(n) + n, n)


def _parts(batches, most: int = 512):
    for batch in batches:
        for lo in range(0, batch.num_rows, most):
            yield batch.slice(lo, most)


def _flat(batch: pa.RecordBatch):
    col = batch.column("hs")
    return batch.column("set_id").to_numpy(), col.flatten().to_numpy(), col.value_lengths().to_numpy().astype(np.int64)


def _counted(batches):
    total = np.zeros(COUNTS, np.int64)
    for batch in _parts(batches):
        total += np.bincount(_flat(batch)[1] & (COUNTS - 1), minlength=COUNTS)
    at = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["place", "n"])


def _sketches(hs: np.ndarray, n: np.ndarray) -> np.ndarray:
    """(sets, 4): 256 parities. Two sets differ in at least as many tokens as these differ in bits."""
    bit = np.uint64(1) << (hs.view(np.uint64) >> np.uint64(56) & np.uint64(63))
    word = hs.view(np.uint64) >> np.uint64(62)
    return np.stack([np.bitwise_xor.reduceat(np.where(word == w, bit, np.uint64(0)), np.cumsum(n) - n) for w in range(4)], axis=1)


def _prefixes(held, percent: int):
    def run(batches):
        counts = held.value
        for batch in _parts(batches):
            ids, hs, n = _flat(batch)
            row, often = np.repeat(np.arange(len(n)), n), counts[hs & (COUNTS - 1)]
            hs, often = (x[np.lexsort((hs, often, row))] for x in (hs, often))
            start, pos, sketch = np.cumsum(n) - n, _ragged(np.ones(len(n), np.int64), n), _sketches(hs, n)
            at = np.flatnonzero((pos <= np.repeat(n - _least(n, percent) + 1, n)) & (often > 1))
            own = row[at]
            prev = pa.array(hs[np.maximum(at - 1, 0)], mask=at == start[own])
            yield pa.RecordBatch.from_arrays([pa.array(hs[at]), pa.array(ids[own]), pa.array(n[own].astype(np.int32)), pa.array(pos[at].astype(np.int32)), prev, *(pa.array(sketch[own, w].view(np.int64)) for w in range(4))], names=[c.split()[0] for c in PREFIX.split(", ")])

    return run


def _meetings(percent: int):
    """Rows in the order of their tokens -> (a, b), a < b: pairs of one token that may be near. A pair that also shares the token before
    has met there."""

    def pairs(t: dict, i: np.ndarray, j: np.ndarray):
        least = _least(np.maximum(t["n"][i], t["n"][j]), percent)
        ok = (np.minimum(t["n"][i], t["n"][j]) >= least) & (1 + np.minimum(t["n"][i] - t["pos"][i], t["n"][j] - t["pos"][j]) >= least)
        ok &= ~((t["prev"][i] == t["prev"][j]) & (t["pos"][i] > 1) & (t["pos"][j] > 1))
        i, j, least = i[ok], j[ok], least[ok]
        apart = sum(np.bitwise_count(t[f"s{w}"][i] ^ t[f"s{w}"][j]).astype(np.int64) for w in range(4))
        ok = apart <= t["n"][i] + t["n"][j] - 2 * least
        a, b = t["id"][i[ok]], t["id"][j[ok]]
        return pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], names=["a", "b"])

    def met(table: pa.Table):
        t = {c: table.column(c).fill_null(0).to_numpy().astype(np.int64) for c in table.column_names}
        t |= {f"s{w}": t[f"s{w}"].view(np.uint64) for w in range(4)}
        new = np.concatenate(([True], t["token"][1:] != t["token"][:-1])) if len(t["token"]) else np.zeros(0, bool)
        end = np.append(np.flatnonzero(new)[1:], len(new))[np.cumsum(new) - 1] if len(new) else np.zeros(0, int)
        after = end - np.arange(len(end)) - 1  # rows of the same token that follow
        upto, lo = np.cumsum(after), 0
        while lo < len(after):
            hi = max(lo + 1, int(np.searchsorted(upto, (upto[lo - 1] if lo else 0) + PAIRS, "right")))
            n = after[lo:hi]
            if n.sum():
                yield pairs(t, np.repeat(np.arange(lo, hi), n), _ragged(np.arange(lo, hi) + 1, n))
            lo = hi

    def run(batches):
        rest: list[pa.RecordBatch] = []  # rows whose token may go on in the next batch
        for batch in batches:
            if not batch.num_rows:
                continue
            token = batch.column("token").to_numpy()
            last = int(np.searchsorted(token == token[-1], True))
            if last or (rest and rest[0].column("token")[0].as_py() != token[0]):
                yield from met(pa.Table.from_batches([*rest, batch.slice(0, last)]))
                rest = []
            rest.append(batch.slice(last))
        if rest:
            yield from met(pa.Table.from_batches(rest))

    return run


def _wide_sketches(batches):
    """As many parities as a set has tokens, rounded up to a power of two: a fraction of the set's bytes."""
    for batch in _parts(batches, 256):
        ids, hs, n = _flat(batch)
        wide = 1 << np.maximum(6, np.ceil(np.log2(n)).astype(np.int64))
        at = np.concatenate(([0], np.cumsum(wide)))
        odd = np.bincount(np.repeat(at[:-1], n) + (hs.view(np.uint64) >> np.uint64(20)).astype(np.int64) % np.repeat(wide, n), minlength=at[-1]) & 1
        packed = np.packbits(odd.astype(np.uint8)).tobytes()
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(n), pa.array([packed[i:j] for i, j in zip((at[:-1] // 8).tolist(), (at[1:] // 8).tolist(), strict=True)], pa.binary())], names=["set_id", "n", "sketch"])


def _still_near(percent: int):
    """Pairs whose parities don't rule them out; the longer row of parities is folded to the shorter."""

    def folded(rows: list[bytes], wide: int) -> np.ndarray:
        x = np.frombuffer(b"".join(rows), np.uint64).reshape(len(rows), -1)
        while 8 * x.shape[1] > wide:
            x = x[:, : x.shape[1] // 2] ^ x[:, x.shape[1] // 2 :]
        return x

    def run(batches):
        for batch in _parts(batches, 1024):
            one, two = (np.array(batch.column(c).to_pylist(), object) for c in ("sa", "sb"))
            na, nb = (batch.column(c).to_numpy() for c in ("na", "nb"))
            la, lb = (np.array([len(x) for x in side]) for side in (one, two))
            apart = np.zeros(len(na), np.int64)
            for wa, wb in set(zip(la.tolist(), lb.tolist(), strict=True)):
                at = np.flatnonzero((la == wa) & (lb == wb))
                bits = folded(one[at].tolist(), min(wa, wb)) ^ folded(two[at].tolist(), min(wa, wb))
                apart[at] = np.bitwise_count(bits).sum(axis=1)
            yield batch.select(["a", "b"]).filter(pa.array(apart <= na + nb - 2 * _least(np.maximum(na, nb), percent)))

    return run


def _checked(percent: int):
    """One unit's sets and pairs -> the pairs that are near."""

    def run(key, sets: pa.Table, pairs: pa.Table) -> pa.Table:
        ids, first = np.unique(sets.column("set_id").to_numpy(), return_index=True)
        batch = sets.take(pa.array(first)).combine_chunks().to_batches()[0] if len(ids) else None
        _, hs, n = _flat(batch)
        del batch
        names = np.unique(hs)
        token = np.searchsorted(names, hs).astype(np.int32)
        start, mark = np.cumsum(n) - n, np.zeros(len(names), np.int32)
        a, b = (np.searchsorted(ids, pairs.column(c).to_numpy()) for c in "ab")
        order = np.argsort(a, kind="stable")
        a, b = a[order], b[order]
        step = max(1, PAIRS // int(n.max()))
        near, bounds = np.zeros(len(a), bool), np.append(np.flatnonzero(np.concatenate(([True], a[1:] != a[:-1]))), len(a))
        for lo, hi in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            own = token[start[a[lo]] : start[a[lo]] + n[a[lo]]]
            mark[own] = 1
            for at in range(lo, hi, step):
                other = b[at : min(at + step, hi)]
                shared_ = np.add.reduceat(mark[token[_ragged(start[other], n[other])]], np.cumsum(n[other]) - n[other])
                near[at : at + len(other)] = 100 * shared_.astype(np.int64) >= percent * np.maximum(n[a[lo]], n[other])
            mark[own] = 0
        return pa.table({"a": ids[a[near]], "b": ids[b[near]]})

    return run


def near_sets(sets: DataFrame, percent: int = 90, block_sets: int = 8192) -> tuple[DataFrame, DataFrame]:
    """Classes (set_id, rep) of sets of equal tokens, each with its least set_id, and pairs (a, b), a < b, of representatives that share
    at least `percent` of the larger one's distinct tokens. sets: (set_id, words array<string>), one row a set; null and empty ones
    are in no class. Tokens are told apart by 64-bit hashes.

    Near sets share a token among the first n - ceil(percent n) + 1 of each in any order of the tokens; this one is by counts that several
    rare tokens may share. Only those prefixes are dealt out, each row with 256 parities of its set, which rule most other pairs out;
    more parities, by the sets' sizes, do so for large sets. Pairs left are checked on whole sets, which go once to the group that their links join; a group of over block_sets sets goes as
    pairs of blocks.
    """
    hs = sets.select(F.col("set_id").cast("long").alias("set_id"), F.array_sort(F.array_distinct(F.transform("words", lambda w: F.xxhash64(w)))).alias("hs"))
    hs = _kept(hs.where(F.size("hs") > 0), "hashes")  # 8 bytes a token: splitting the texts again for each step costs more
    spark = sets.sparkSession
    keys = hs.select("set_id", F.xxhash64("hs").alias("k1"), F.xxhash64(F.lit(7), "hs").alias("k2"), F.size("hs").alias("n"))
    keys = _kept(keys, "keys")
    classes = _kept(keys.join(keys.groupBy("k1", "k2", "n").agg(F.min("set_id").alias("rep")), ["k1", "k2", "n"]).select("set_id", "rep"), "classes")
    of_reps = hs.join(small(classes.where("set_id <> rep").select("set_id")), "set_id", "left_anti")

    counted = driver_table(hs.mapInArrow(_counted, "place long, n long").groupBy("place").agg(F.sum("n").alias("n")))
    counts = np.zeros(COUNTS, np.int64)
    counts[counted.column("place").to_numpy()] = counted.column("n").to_numpy()
    held = spark.sparkContext.broadcast(counts)
    rows = of_reps.mapInArrow(_prefixes(held, percent), PREFIX)
    met = rows.repartition("token").sortWithinPartitions("token").mapInArrow(_meetings(percent), "a long, b long")
    met = _kept(met.distinct(), "met")
    ends = lambda: met.select(F.col("a").alias("set_id")).unionAll(met.select(F.col("b").alias("set_id"))).distinct()
    sketches = _kept(hs.join(small(ends()), "set_id", "left_semi").mapInArrow(_wide_sketches, "set_id long, n long, sketch binary"), "sketches")
    side = lambda x: sketches.select(F.col("set_id").alias(x), F.col("n").alias(f"n{x}"), F.col("sketch").alias(f"s{x}"))
    met = _kept(met.join(side("a"), "a").join(side("b"), "b").mapInArrow(_still_near(percent), "a long, b long"), "left")

    group = components(met.select(F.col("a").alias("src"), F.col("b").alias("dst")), ends())
    place = F.row_number().over(Window.partitionBy("component").orderBy("set_id")) - 1
    members = _kept(group.withColumn("block", F.floor(place / block_sets)), "members")
    side = lambda x: members.select(F.col("set_id").alias(x), F.col("component").alias("c"), F.col("block").alias(f"_{x}"))
    dealt = _kept(met.join(side("a"), "a").join(side("b").drop("c"), "b"), "dealt")
    blocks = dealt.select("c", "_a", "_b").distinct()
    tiles = _kept(blocks.select("c", F.explode(F.array_distinct(F.array("_a", "_b"))).alias("block"), "_a", "_b"), "tiles")
    wanted = _kept(hs.join(small(members), "set_id"), "wanted")
    units = max(1, -(-int(wanted.agg(F.coalesce(F.sum(8 * F.size("hs")), F.lit(0))).first()[0]) // UNIT))
    unit = F.pmod(F.xxhash64("c", "_a", "_b"), F.lit(units))
    arrays = wanted.withColumnRenamed("component", "c").join(small(tiles), ["c", "block"]).select(unit.alias("unit"), "set_id", "hs")
    pairs = arrays.groupBy("unit").cogroup(dealt.select(unit.alias("unit"), "a", "b").groupBy("unit")).applyInArrow(_checked(percent), "a long, b long")
    return classes, pairs


def near_token_sets(tokens: DataFrame, percent: int = 90) -> DataFrame:
    """(a, b), a < b: sets that share at least `percent` of the larger one's distinct tokens, copies spelled out. tokens: (set_id, token)."""
    classes, pairs = near_sets(tokens.groupBy("set_id").agg(F.collect_set("token").alias("words")), percent)
    pairs = pairs.unionAll(classes.select(F.col("rep").alias("a"), F.col("rep").alias("b")).distinct())
    side = lambda x, y: classes.select(F.col("rep").alias(x), F.col("set_id").alias(y))
    out = pairs.join(side("a", "x"), "a").join(side("b", "y"), "b")
    return out.where((F.col("a") != F.col("b")) | (F.col("x") < F.col("y"))).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
