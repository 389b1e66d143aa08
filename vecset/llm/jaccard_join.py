"""N-gram Jaccard join by adaptive multi-match prefixes.

A document's set is that of its 5-word shingles, in a fixed order: rare shingles first, then by hash. Of two sets that are similar
enough, any two prefixes of n - ceil(t n) + l shingles share at least l. A longer prefix costs more postings but asks for more
matches before a pair is verified; each document takes the l that costs least by the document frequencies of its own shingles. A
pair needs as many matches as the smaller l of its two documents, inside the prefixes that its two sizes leave.

1. Shingles are hashed and dealt by hash; each bucket counts document frequencies and sends back those that two documents share.
   Shingles of one document alone take the first places of its prefix but need no posting, and a document with fewer than t n
   shared shingles has no partner at all.
2. Documents with equal sets are one class, and its least document stands for it.
3. Postings of the prefixes meet by shingle. Three rounds compare each document with one pivot of each of its shingles (the most
   central, the least, a random one) and join what is similar into components. What is left to compare are documents of different components that share enough postings, so a group
   of thousands of near copies is never paired with itself.
4. Links give components; each class member has its class's.

Cases: null or empty texts and texts without words have an empty set and no links; with one to four words the whole sequence is the
one shingle; repeated rows are copies; an empty table gives an empty one; other columns are not read; very long texts go whole.
Shingles are told apart by 64 bits of a hash, sets by 64 bits and their size. A bucket of shingles is counted in one task: their
number follows the size of the texts. The postings of one shingle take 8 bytes a document in the bucket that counts it.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import column_bytes, drop_written, free, fresh, ids_of, mix64, null_again, nothing_kept, pieces_of, texts, written
from .components import components
from .suffix_kernel import BASE, UNBASE, powers

_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32
_SPACE = np.zeros(256, bool)
_SPACE[[32, *range(9, 14)]] = True


def shingles(flat: np.ndarray, off: np.ndarray, words: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """(text, hash) of the distinct shingles of each text, sorted by both."""
    n = len(flat)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    ink = ~_SPACE[flat]
    edge = np.zeros(n + 1, bool)
    edge[off] = True
    start = np.flatnonzero(ink & (edge[:-1] | np.concatenate(([True], ~ink[:-1]))))
    end = np.flatnonzero(ink & (edge[1:] | np.concatenate((~ink[1:], [True])))) + 1
    text = np.searchsorted(off, start, "right") - 1
    with np.errstate(over="ignore"):
        total = np.zeros(n + 1, np.uint64)
        np.cumsum((_FOLD[flat].astype(np.uint64) + np.uint64(1)) * powers(BASE, n), out=total[1:])
        word = mix64((total[end] - total[start]) * powers(UNBASE, n + 1)[start])
        factor = powers(0xD1B54A32D192ED03, words + 1)[1:]
        count = np.bincount(text, minlength=len(off) - 1)
        inside = np.arange(len(word)) + words <= np.cumsum(count)[text] if len(word) else np.zeros(0, bool)
        at = np.flatnonzero(inside)
        full = sum((word[at + k] * factor[k] for k in range(words)), np.zeros(len(at), np.uint64))
        few = np.flatnonzero((count > 0) & (count < words))
        first = (np.cumsum(count) - count)[few]
        short = np.full(len(few), 0x5851F42D4C957F2D, np.uint64)
        for k in range(words - 1):
            has = count[few] > k
            short[has] += word[first[has] + k] * factor[k]
        t, h = np.concatenate((text[at], few)), mix64(np.concatenate((full, short)))
    order = np.lexsort((h, t))
    t, h = t[order], h[order]
    new = np.concatenate(([True], (t[1:] != t[:-1]) | (h[1:] != h[:-1]))) if len(t) else np.zeros(0, bool)
    return t[new], h[new]


#: Bytes of text whose shingles one bucket counts.
BUCKET_BYTES = 32 << 20


def bucket_bits(rows: DataFrame) -> int:
    """Bits of the hash that name a bucket: 8 at least, more where the texts ask for more buckets of BUCKET_BYTES."""
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    return min(22, max(8, (-(-size // BUCKET_BYTES) - 1).bit_length()))


def _coded(h: np.ndarray, t: np.ndarray) -> bytes:
    """Hashes without their top byte, which a bucket knows, and the documents they come from, in order: 8 bytes for each pair, and 4
    for each run of 256 documents."""
    runs = np.bincount(t >> 8).astype(np.uint32)
    return b"".join((h.astype(np.uint32).tobytes(), (h >> np.uint64(32)).astype(np.uint16).tobytes(), (h >> np.uint64(48)).astype(np.uint8).tobytes(), t.astype(np.uint8).tobytes(), runs.tobytes(), np.uint32(len(runs)).tobytes()))


def _uncoded(blob: bytes, top: int) -> tuple[np.ndarray, np.ndarray]:
    k = int(np.frombuffer(blob, np.uint32, 1, len(blob) - 4)[0])
    m = (len(blob) - 4 - 4 * k) // 8
    low, mid, high, t = (np.frombuffer(blob, kind, m, at * m) for kind, at in ((np.uint32, 0), (np.uint16, 4), (np.uint8, 6), (np.uint8, 7)))
    run = np.repeat(np.arange(k, dtype=np.uint16), np.frombuffer(blob[8 * m : 8 * m + 4 * k], np.uint32))
    return low | mid.astype(np.uint64) << np.uint64(32) | high.astype(np.uint64) << np.uint64(48) | np.uint64(top) << np.uint64(56), t | run << np.uint16(8)


SHARED = "doc long, n long, sig long, tokens binary, rarity binary"


def shared_sets(docs: DataFrame, threshold: float, words: int, flush: int = 1 << 20) -> DataFrame:
    """(doc, n, sig, tokens, rarity): the shingles of each document that another has too, rare ones first, and 8 log2 of their
    document frequency. tokens is null where they are too few for any partner."""
    bits = bucket_bits(docs)

    def ask(batches):
        nothing_kept()
        part, k, held, size, n_docs = TaskContext.get().partitionId(), 0, [], 0, 0

        def out():
            t, h = np.concatenate([x[0] for x in held]), np.concatenate([x[1] for x in held])
            bucket = (h >> np.uint64(64 - bits)).astype(np.uint16 if bits <= 16 else np.uint32)
            order = np.argsort(bucket, kind="stable")
            named, start = np.unique(bucket[order], return_index=True)
            t, h = t[order].astype(np.uint16), h[order]
            name = (part << 24) + k
            blobs = [_coded(h[a:b], t[a:b]) for a, b in zip(start, np.append(start, len(h))[1:], strict=True)]
            head = b"".join(np.concatenate([x[c] for x in held]).tobytes() for c in (2, 3, 4))
            buckets = [*named.tolist(), name % (1 << bits)]
            return pa.RecordBatch.from_arrays([pa.array(buckets, pa.int32()), pa.array([name] * len(buckets), pa.int64()), pa.array([*blobs, None], pa.binary()), pa.array([None] * len(named) + [head], pa.binary())], names=["bucket", "flush", "blob", "head"])

        for batch in batches:
            for piece in pieces_of(batch, 1 << 18):
                for s in range(0, piece.num_rows, 1 << 14):
                    some = piece.slice(s, 1 << 14)
                    t, h = shingles(*column_bytes(some.column("text")), words)
                    if held and (size + len(h) > flush or n_docs + some.num_rows > 1 << 16):
                        yield out()
                        held, size, n_docs, k = [], 0, 0, k + 1
                    n = np.bincount(t, minlength=some.num_rows)
                    sums = np.zeros(some.num_rows, np.uint64)
                    with np.errstate(over="ignore"):
                        np.add.at(sums, t, mix64(h ^ np.uint64(0xA5A5A5A5A5A5A5A5)))
                    held.append((t + n_docs, h, ids_of(some.column("doc_id")), n, sums.view(np.int64)))
                    size, n_docs = size + len(h), n_docs + some.num_rows
        if held:
            yield out()

    def count(group: pa.Table) -> pa.Table:
        nothing_kept()
        blobs, flushes, bucket = group.column("blob").to_pylist(), group.column("flush").to_numpy(), group.column("bucket")[0].as_py()
        data = [i for i, b in enumerate(blobs) if b is not None]
        parts = [(np.zeros(0, np.uint64), np.zeros(0, np.uint16)), *(_uncoded(blobs[i], bucket >> (bits - 8)) for i in data)]
        h, t = (np.concatenate([p[c] for p in parts]) for c in range(2))
        own = np.repeat(np.array(data, np.int64), [len(p[0]) for p in parts[1:]])
        del parts
        order = np.argsort(h, kind="stable")
        new = np.concatenate(([True], h[order][1:] != h[order][:-1])) if len(h) else np.zeros(0, bool)
        group_of = np.cumsum(new) - 1
        df = np.bincount(group_of)[group_of] if len(h) else np.zeros(0, np.int64)
        keep = order[df > 1]
        rarity = np.minimum(np.ceil(8 * np.log2(np.maximum(df[df > 1], 1))), 255).astype(np.uint8)
        back = np.argsort(keep, kind="stable")
        keep, rarity = keep[back], rarity[back]
        edge = np.searchsorted(own[keep], [*data, len(blobs)])
        out = [h[k].tobytes() + t[k].tobytes() + rarity[a:b].tobytes() for a, b in zip(edge[:-1], edge[1:], strict=True) for k in [keep[a:b]]]
        heads = [i for i, b in enumerate(blobs) if b is None]
        return pa.table([pa.array(flushes[data + heads]), pa.array(out + [None] * len(heads), pa.binary()), pa.array([None] * len(data) + [group.column("head")[i].as_py() for i in heads], pa.binary())], names=["flush", "blob", "head"])

    def gather(group: pa.Table) -> pa.Table:
        nothing_kept()
        head = next(h for h in group.column("head").to_pylist() if h is not None)
        m = len(head) // 24
        ids, n, sig = (np.frombuffer(head, np.int64, m, 8 * m * k) for k in range(3))
        blobs = [b for b in group.column("blob").to_pylist() if b]
        sizes = [len(b) // 11 for b in blobs]
        h, t, rarity = (np.concatenate([np.zeros(0, kind), *(np.frombuffer(b, kind, s, at * s) for b, s in zip(blobs, sizes, strict=True))]) for kind, at in ((np.uint64, 0), (np.uint16, 8), (np.uint8, 10)))
        c = np.bincount(t, minlength=m)
        order = np.lexsort((h, rarity, t))
        h, rarity, end = h[order], rarity[order], np.cumsum(c)
        fit = (c >= threshold * n - 1e-9) & (n > 0)
        cut = lambda x: pa.array([x[e - k : e].tobytes() if f else None for e, k, f in zip(end.tolist(), c.tolist(), fit.tolist(), strict=True)], pa.binary())
        return pa.table([pa.array(ids), pa.array(n), pa.array(sig), cut(h), cut(rarity)], names=["doc", "n", "sig", "tokens", "rarity"])

    counted = docs.mapInArrow(ask, "bucket int, flush long, blob binary, head binary").groupBy("bucket").applyInArrow(count, "flush long, blob binary, head binary")
    return written(counted.groupBy("flush").applyInArrow(gather, SHARED), "sets")


def choose_l(rarity: np.ndarray, n: int, base: int, weight: float = 0.25, most: int = 8) -> int:
    """The l of least cost. base: shared shingles in the prefix for l = 1. A posting costs one; a candidate weight for each shared
    shingle that its verification reads. At most (sum of document frequencies) / l documents match l times."""
    df = 2.0 ** (rarity[: base + most - 1] / 8)
    sums = np.cumsum(df)
    best, cost = 1, np.inf
    for l in range(1, min(most, len(rarity) - base + 1) + 1):  # noqa: E741
        p = base + l - 1
        c = p + sums[p - 1] / l * weight * len(rarity) if p else 0.0
        if c < cost:
            best, cost = l, c
    return best


def prefixes(reps: DataFrame, percent: int) -> DataFrame:
    """(token, doc, n, l, pos, central): the postings of each document's prefix. pos: place in the document's order; central: mean
    rarity of its set, higher where the set is made of what many have."""

    def run(batches):
        for batch in batches:
            out = []
            for doc, n, tokens, rarity in zip(*(batch.column(c).to_pylist() for c in ("doc", "n", "tokens", "rarity")), strict=True):
                h, rare = np.frombuffer(tokens, np.int64), np.frombuffer(rarity, np.uint8)
                base = n - -(-percent * n // 100) + 1 - (n - len(h))
                if base > 0:
                    l = choose_l(rare, n, base)  # noqa: E741
                    mine = h[: base + l - 1]
                    k = len(mine)
                    out.append((mine, np.full(k, doc), np.full(k, n), np.full(k, l, np.int32), n - len(h) + np.arange(k), np.full(k, 64 * rare.sum(dtype=np.int64) // n)))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([o[k] for o in out])) for k in range(6)], names=["token", "doc", "n", "l", "pos", "central"])

    return reps.mapInArrow(run, "token long, doc long, n long, l int, pos long, central long")


MARKS = tuple(f"m{k}" for k in range(8))


def marks(reps: DataFrame) -> DataFrame:
    """(doc, c, m0 to m7): c is how many shingles of a document another has too; bit b of m0 to m7 is the parity of those with hash
    b modulo 512. Two sets differ in as many of these shingles at least as their marks differ in bits."""

    def run(batches):
        for batch in batches:
            held = [np.frombuffer(t, np.uint64) for t in batch.column("tokens").to_pylist()]
            bits = np.zeros((len(held), 512), np.uint8)
            for row, h in zip(bits, held, strict=True):
                row[:] = np.bincount((h & np.uint64(511)).astype(np.int64), minlength=512) & 1
            words = np.packbits(bits, axis=1).view(np.int64).reshape(len(held), 8)
            yield pa.RecordBatch.from_arrays([batch.column("doc"), pa.array([len(h) for h in held], pa.int64()), *(pa.array(np.ascontiguousarray(words[:, k])) for k in range(8))], names=["doc", "c", *MARKS])

    return reps.select("doc", "tokens").mapInArrow(run, "doc long, c long, " + ", ".join(f"{m} long" for m in MARKS))


def matched(own: DataFrame, percent: int, held_pairs: int = 500_000) -> DataFrame:
    """(a, b, matches, least): pairs of different parts and how many postings they share inside their prefixes, summed in each task
    before they are dealt. own: (token, doc, n, l, pos, part) and the marks. A task goes through its shingles in order; of one shingle
    it holds the postings (120 bytes each) and crosses them in blocks. Pairs whose marks differ in too many bits for the overlap that
    their sizes need can't be links and are left out; no other pair is."""
    both = 100 + percent
    names = ("token", "doc", "n", "l", "pos", "part", "c", *MARKS)

    def near(need, c, m, x, y, a, b):
        """Whether c_x + c_y - (bits that differ) leaves room for twice the overlap that the pair needs."""
        ok = np.zeros(len(a), bool)
        for s in range(0, len(a), 1 << 15):
            i, j = x.start + a[s : s + (1 << 15)], y.start + b[s : s + (1 << 15)]
            apart = sum(np.bitwise_count((w[i] ^ w[j]).view(np.uint64)).astype(np.int64) for w in m)
            ok[s : s + (1 << 15)] = c[i] + c[j] - apart >= 2 * need[s : s + (1 << 15)]
        return ok

    def run(batches):
        nothing_kept()
        held, n_held, rest = [], 0, None

        def cross(rows):
            nonlocal n_held
            token, doc, n, l, pos, part, c, *m = rows
            edge = np.flatnonzero(np.concatenate(([True], token[1:] != token[:-1], [True])))
            for s, e in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
                for i in range(s, e, 1024):
                    for j in range(i, e, 4096):
                        x, y = slice(i, min(i + 1024, e)), slice(j, min(j + 4096, e))
                        least = np.minimum(l[x, None], l[None, y])
                        need = (percent * (n[x, None] + n[None, y]) + both - 1) // both
                        room = least - need
                        ok = (part[x, None] != part[None, y]) & (pos[x, None] < n[x, None] + room) & (pos[None, y] < n[None, y] + room)
                        ok &= np.arange(i, x.stop)[:, None] < np.arange(j, y.stop)[None, :]
                        a, b = np.nonzero(ok)
                        fit = near(need[a, b], c, m, x, y, a, b)
                        a, b = a[fit], b[fit]
                        if len(a):
                            held.append((np.minimum(doc[x][a], doc[y][b]), np.maximum(doc[x][a], doc[y][b]), np.ones(len(a), np.int64), least[a, b].astype(np.int64)))
                            n_held += len(a)
                            if n_held > held_pairs:
                                fold()
                                if n_held > held_pairs // 2:
                                    yield out()

        def fold():
            nonlocal held, n_held
            a, b, times, l = (np.concatenate([h[k] for h in held]) for k in range(4))
            order = np.lexsort((b, a))
            a, b, times, l = a[order], b[order], times[order], l[order]
            first = np.flatnonzero(np.concatenate(([True], (a[1:] != a[:-1]) | (b[1:] != b[:-1]))))
            held = [(a[first], b[first], np.add.reduceat(times, first), np.minimum.reduceat(l, first))]
            n_held = len(first)

        def out():
            nonlocal held, n_held
            batch = pa.RecordBatch.from_arrays([pa.array(c) for c in held[0]], names=["a", "b", "matches", "least"])
            held, n_held = [], 0
            return batch

        for batch in batches:
            rows = [batch.column(c).to_numpy().astype(np.int64) for c in names]
            rows = rows if rest is None else [np.concatenate(p) for p in zip(rest, rows, strict=True)]
            last = int(np.searchsorted(rows[0], rows[0][-1], "left")) if len(rows[0]) else 0
            rest = [r[last:] for r in rows]
            if last:
                yield from cross([r[:last] for r in rows])
        if rest is not None and len(rest[0]):
            yield from cross(rest)
        if held:
            fold()
            yield out()

    dealt = own.select(*names).repartition(F.col("token")).sortWithinPartitions("token")
    return dealt.mapInArrow(run, "a long, b long, matches long, least long")


def verified(pairs: DataFrame, reps: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets are similar enough."""

    def run(batches):
        for batch in batches:
            hit = []
            for na, nb, x, y in zip(*(batch.column(c).to_pylist() for c in ("na", "nb", "ta", "tb")), strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                both = np.sort(np.concatenate((x, y)))
                shared = int((both[1:] == both[:-1]).sum())
                hit.append(100 * shared >= percent * (na + nb - shared))
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(hit, pa.bool_()))

    one = reps.select(F.col("doc").alias("a"), F.col("n").alias("na"), F.col("tokens").alias("ta"))
    two = reps.select(F.col("doc").alias("b"), F.col("n").alias("nb"), F.col("tokens").alias("tb"))
    return pairs.join(one, "a").join(two, "b").select("a", "b", "na", "nb", "ta", "tb").mapInArrow(run, "a long, b long")


def join(docs: DataFrame, percent: int = 75, words: int = 5, pivot_rounds: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id): documents link when 100 * intersection >= percent * union."""
    return _join(docs, percent, words, pivot_rounds, id_col, text_col)[0]


def _join(docs: DataFrame, percent: int = 75, words: int = 5, pivot_rounds: int = 3, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, list[DataFrame]]:
    """join's result, and the written tables that nothing needs once that result is written."""
    rows = texts(docs, id_col, text_col)
    sets = shared_sets(rows, percent / 100, words)
    free(docs)
    classes = sets.where("tokens is not null").groupBy("n", "sig").agg(F.min("doc").alias("doc"), F.min_by("tokens", "doc").alias("tokens"), F.min_by("rarity", "doc").alias("rarity"))
    reps = written(classes, "reps")
    slim = written(sets.select("doc", "n", "sig"), "sizes")
    drop_written(sets)
    del classes
    free(docs)
    postings = written(prefixes(reps, percent), "postings")
    both = 100 + percent

    def inside(a: str, b: str) -> "F.Column":
        """Whether a token lies in both prefixes of this very pair: n - overlap + l, for the overlap that two sets of these sizes need."""
        overlap = F.expr(f"({percent} * (n_{a} + n_{b}) + {both - 1}) div {both}")
        least = F.least(f"l_{a}", f"l_{b}")
        return (F.col(f"pos_{a}") < F.col(f"n_{a}") - overlap + least) & (F.col(f"pos_{b}") < F.col(f"n_{b}") - overlap + least)

    def side(df: DataFrame, name: str) -> DataFrame:
        return df.select("token", *(F.col(c).alias(f"{c}_{name}") for c in ("doc", "n", "l", "pos", "part")))

    stars = None
    own = postings.withColumn("part", F.col("doc"))
    for r in range(pivot_rounds):
        first = (-F.col("central"), F.col("doc"), F.xxhash64("doc", F.lit(r)))[min(r, 2)]
        pivot = own.groupBy("token").agg(F.min(F.struct(first.alias("first"), "doc", "n", "l", "pos", "part")).alias("p"), F.min("part").alias("low"), F.max("part").alias("high")).where("low < high").select("token", "p.*")
        pairs = side(own, "a").join(side(pivot, "b"), "token").where((F.col("part_a") != F.col("part_b")) & inside("a", "b"))
        pairs = pairs.select(F.least("doc_a", "doc_b").alias("a"), F.greatest("doc_a", "doc_b").alias("b")).distinct()
        found = verified(pairs, reps, percent)
        parts = components(found if stars is None else stars.unionAll(found)).select(F.col("node").alias("doc"), F.col("component").alias("part"))
        stars = parts.where("doc <> part").select(F.col("doc").alias("a"), F.col("part").alias("b"))  # all links so far, as reach
        old, own = own, written(postings.join(parts, "doc", "left").withColumn("part", F.coalesce("part", "doc")), "own")
        if r:
            drop_written(old)
        del pivot, pairs, found
        free(docs)  # each round's shuffles
    mixed = own.groupBy("token").agg(F.min("part").alias("low"), F.max("part").alias("high")).where("low < high").select("token")
    old, own = own, written(own.join(mixed, "token"), "mixed")
    if pivot_rounds:
        drop_written(old)
        drop_written(postings)
    pairs = matched(own.join(marks(reps), "doc"), percent).groupBy("a", "b").agg(F.sum("matches").alias("matches"), F.min("least").alias("least")).where("matches >= least").select("a", "b")
    found = verified(pairs, reps, percent)
    parts = components(found if stars is None else stars.unionAll(found))
    named = reps.select("n", "sig", "doc").join(parts.withColumnRenamed("node", "doc"), "doc", "left").select("n", "sig", F.coalesce("component", "doc").alias("component"))
    out = slim.join(named, ["n", "sig"], "left")
    out = out.select(F.col("doc").alias("doc_id"), F.col("n").alias("n_shingles"), F.coalesce("component", "doc").alias("component_id"))
    return null_again(out, "doc_id", "component_id"), [slim, reps, own]


def one_of_each(docs: DataFrame, **options) -> DataFrame:
    """docs without those that link to a group whose least doc_id is another; of repeated rows with one doc_id and a set, one stays."""
    groups, spent = _join(docs, **options)
    groups = written(groups, "groups")
    for table in spent:  # before the documents are dealt
        drop_written(table)
    free(docs)
    keep = groups.where("doc_id is null or doc_id = component_id").select("doc_id").dropDuplicates(["doc_id"])
    name = fresh(docs, "_n")
    order = Window.partitionBy("doc_id", F.xxhash64(F.coalesce("text", F.lit("")))).orderBy(F.lit(0))
    kept = docs.join(keep.where("doc_id is not null"), "doc_id", "left_semi")
    once = kept.withColumn(name, F.row_number().over(order)).where(F.col(name) == 1).drop(name)
    return once.select(*docs.columns).unionAll(docs.where("doc_id is null"))
