"""Quality classifier by Bradley-Terry pairwise ranking.

A document's score is linear in features of its text: shares of byte classes and square roots of hashed byte-pair frequencies. Of a
pair with one better and one worse document, the better wins with the logistic of the score difference; weights follow from that
loss over all such pairs. The threshold is the quantile of the scores at the share of rejected labels.

All labelled documents that are not held out take part. Their counts are written once; each step of the fit is a pass over them that
returns sums. The loss of all pairs needs no pair: its slope at a document follows from its score and the distribution of the other
class's scores (in 4,096 bins), and its curvature is bounded by a quarter of the mean outer product of the pairs' differences, which
follows from both classes' moments. The threshold is exact.

Cases: null and empty texts get all-zero features and a score like others; null labels are left out, of repeated ones the lowest
counts; without labels of both kinds every document scores 0.5 and is kept; repeated rows stay; an empty table gives an empty one.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from .common import column_bytes, drop_written, fresh, nothing_kept, pieces_of, small_batches, written

PAIRS = 1024
#: Bytes and rows of text that a task turns to features at once.
PIECE, ROWS = 1 << 18, 512
_CLASS = np.full(256, 6, np.int64)
for _k, _bytes in enumerate((range(97, 123), range(65, 91), range(48, 58), (9, 32), (10, 13), range(128, 256))):
    _CLASS[list(_bytes)] = _k
N_CLASS = 7
WIDTH = PAIRS + N_CLASS + N_CLASS * N_CLASS + 1


def byte_counts(flat: np.ndarray, off: np.ndarray, block: int = 1 << 18) -> np.ndarray:
    """A row for each text: counts of hashed byte pairs, byte classes, pairs of classes. Goes through the bytes a block at a time, so
    that a very long text takes no more memory than others."""
    n = len(off) - 1
    one, two, both = (np.zeros((n, w), np.int64) for w in (N_CLASS, PAIRS, N_CLASS * N_CLASS))
    for a in range(0, len(flat), block):
        b = min(a + block, len(flat))
        lo, hi = int(np.searchsorted(off, a, "right")) - 1, int(np.searchsorted(off, b, "left"))  # texts that have bytes here
        m = hi - lo
        doc = np.repeat(np.arange(m), np.diff(np.clip(off[lo : hi + 1], a, b)))
        part = flat[a : b + 1]
        kind = _CLASS[part]
        one[lo:hi] += np.bincount(doc * N_CLASS + kind[: b - a], minlength=m * N_CLASS).reshape(m, -1)
        inner = np.ones(b - a, bool)  # bytes with a next one in their text
        last = off[lo + 1 : hi + 1] - 1 - a
        inner[last[(last >= 0) & (last < b - a)]] = False
        at = np.flatnonzero(inner)
        code = (part[at].astype(np.int64) * 31 + part[at + 1]) % PAIRS
        two[lo:hi] += np.bincount(doc[at] * PAIRS + code, minlength=m * PAIRS).reshape(m, -1)
        both[lo:hi] += np.bincount(doc[at] * N_CLASS**2 + kind[at] * N_CLASS + kind[at + 1], minlength=m * N_CLASS**2).reshape(m, -1)
    return np.concatenate((two, one, both), axis=1)


def scaled(counts: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Features of counts and lengths."""
    out = np.zeros((len(size), WIDTH), np.float32)
    by = np.maximum(size, 1)[:, None]
    out[:, :PAIRS] = np.sqrt(counts[:, :PAIRS] / by)
    out[:, PAIRS:-1] = 2 * np.sqrt(counts[:, PAIRS:] / by)
    out[:, -1] = np.log1p(size) / 10
    return out


def features(flat: np.ndarray, off: np.ndarray, block: int = 1 << 18) -> np.ndarray:
    """A row for each text: hashed byte pairs, byte classes, pairs of classes, length."""
    return scaled(byte_counts(flat, off, block), np.diff(off))


@dataclass
class Ranker:
    weights: np.ndarray
    threshold: float
    scale: float

    def score(self, x: np.ndarray) -> np.ndarray:
        """From 0 to 1; 0.5 at the threshold."""
        return 1 / (1 + np.exp(-np.clip((x.astype(np.float64) @ self.weights - self.threshold) * self.scale, -40, 40)))


class _Sums:
    """What a pass adds up over blocks (x, y) of features and labels; passes of several tasks are added on the driver."""

    @staticmethod
    def moments(blocks):
        """Of either class: n, sum, sum of outer products."""
        n, total, outer = np.zeros(2), np.zeros((2, WIDTH)), np.zeros((2, WIDTH, WIDTH), np.float32)
        for x, y in blocks:
            for k in (0, 1):
                z = x[y == k]
                n[k] += len(z)
                total[k] += z.sum(axis=0, dtype=np.float64)
                outer[k] += z.T @ z
        return n, total, outer

    @staticmethod
    def histogram(blocks, w, low, high, bins):
        """Rows of either class by score; what lies outside goes to the last bin of that side."""
        out = np.zeros((2, bins))
        for x, y in blocks:
            at = _bin(x.astype(np.float64) @ w, low, high, bins)
            for k in (0, 1):
                out[k] += np.bincount(at[y == k], minlength=bins)
        return (out,)

    @staticmethod
    def slope(blocks, w, low, high, pull):
        """Sum of features, each row by the pull of its class and bin."""
        out = np.zeros(WIDTH)
        for x, y in blocks:
            x = x.astype(np.float64)
            out += pull[y, _bin(x @ w, low, high, pull.shape[1])] @ x
        return (out,)

    @staticmethod
    def range(blocks, w):
        """Least and largest score, negated so that both are maxima."""
        out = np.full(2, -np.inf)
        for x, _ in blocks:
            s = x.astype(np.float64) @ w
            out = np.maximum(out, (-s.min(), s.max()))
        return (out,)


def _bin(s: np.ndarray, low: float, high: float, bins: int) -> np.ndarray:
    return np.clip((s - low) * (bins / max(high - low, 1e-300)), 0, bins - 1).astype(np.int64)


def _fitted(run, between, rounds: int, ridge: float, bins: int = 4096) -> Ranker:
    """run(name, *arguments): the arrays of that pass for each task. between(w, low, high): the sorted scores from low to high."""
    n, total, outer = np.zeros(2), np.zeros((2, WIDTH)), np.zeros((2, WIDTH, WIDTH))
    for part in run("moments"):
        n, total = n + part[0], total + part[1]
        outer += part[2]
    if not n.all():
        return Ranker(np.zeros(WIDTH), 0.0, 1.0)
    mean, outer = total / n[:, None], outer / n[:, None, None]
    cross = np.outer(mean[0], mean[1])
    bound = (outer[0] + outer[1] - cross - cross.T) / 4 + ridge * np.eye(WIDTH)
    ends = lambda w: (np.array([-1.0, 1.0]) * np.max([p[0] for p in run("range", w)], axis=0)).tolist()
    w = _solved(bound, (mean[1] - mean[0]) / 2)
    for _ in range(rounds):
        low, high = ends(w)
        share = sum(p[0] for p in run("histogram", w, low, high, bins)) / n[:, None]
        step = (high - low) / bins
        far = step * np.arange(1 - bins, bins)
        loses = 1 / (1 + np.exp(np.clip(-far, -40, 40)))  # chance that the worse one wins, by how far it is above
        pull = np.stack((_convolved(share[1], loses) / n[0], -_convolved(share[0], loses[::-1]) / n[1]))
        w = w - _solved(bound, sum(p[0] for p in run("slope", w, low, high, pull)) + ridge * w)
    w = np.round(w, 6)  # the same however sums came
    low, high = ends(w)
    share = np.cumsum(sum(p[0] for p in run("histogram", w, low, high, bins)).sum(axis=0)).astype(np.int64)
    rank = [int(n[0]) - 1, min(int(n[0]), int(n.sum()) - 1)]  # of the two scores that the threshold lies between
    a, b = (int(np.searchsorted(share, r, "right")) for r in rank)
    got = between(w, low, high, bins, a, b)
    before = int(share[a - 1]) if a else 0
    return Ranker(w, float((got[rank[0] - before] + got[rank[1] - before]) / 2), 1.0)


def _solved(matrix: np.ndarray, right: np.ndarray, rounds: int = 1000) -> np.ndarray:
    """By conjugate gradients, scaled by the diagonal: the matrix is positive definite."""
    x, r, scale = np.zeros(len(right)), right.copy(), 1 / np.diag(matrix)
    p = z = scale * r
    for _ in range(rounds):
        q, was = matrix @ p, r @ z
        if was <= 1e-16 * (right @ (scale * right)):
            break
        step = was / (p @ q)
        x, r = x + step * p, r - step * q
        z = scale * r
        p = z + (r @ z / was) * p
    return x


def _convolved(share: np.ndarray, loses: np.ndarray) -> np.ndarray:
    """out[a] = sum over b of share[b] loses[a - b + len - 1]."""
    m = len(share)
    size = 4 * m
    return np.fft.irfft(np.fft.rfft(share, size) * np.fft.rfft(loses, size), size)[m - 1 : 2 * m - 1]


def fit_pairs(better: np.ndarray, worse: np.ndarray, share_worse: float, rounds: int = 4, ridge: float = 1e-4) -> Ranker:
    """The fit of features in memory; the threshold is the quantile at share_worse, classes weighted by it."""
    x, y = np.concatenate((worse, better)), np.repeat((0, 1), (len(worse), len(better)))

    def between(w, low, high, bins, a, b):
        s = x.astype(np.float64) @ w
        at = _bin(s, low, high, bins)
        return np.sort(s[(at >= a) & (at <= b)])

    model = _fitted(lambda name, *more: [getattr(_Sums, name)(iter([(x, y)]), *more)], between, rounds, ridge)
    if not len(better) or not len(worse):
        return model
    raw = x.astype(np.float64) @ model.weights
    mass = np.where(y == 0, share_worse / len(worse), (1 - share_worse) / len(better))
    order = np.argsort(raw, kind="stable")
    k = int(np.searchsorted(np.cumsum(mass[order]), share_worse - 1e-12))
    low, high = raw[order[min(k, len(raw) - 1)]], raw[order[min(k + 1, len(raw) - 1)]]
    return Ranker(model.weights, float((low + high) / 2), 1.0)


def held_out(doc_id) -> "F.Column":
    return F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(3)) == 1


COUNTS = "y int, size long, counts binary, at binary, more binary"


def _counted(batches):
    """A byte for each count; counts of 255 and more stand beside, with their places."""
    for batch in batches:
        for part in pieces_of(batch, PIECE, most_rows=ROWS):
            flat, off = column_bytes(part.column("text"))
            counts = byte_counts(flat, off)
            at, more = [], []
            for r in counts:
                high = np.flatnonzero(r >= 255)
                at.append(high.astype(np.int32).tobytes())
                more.append(r[high].tobytes())
            low = np.minimum(counts, 255).astype(np.uint8)
            yield pa.RecordBatch.from_arrays([part.column("y"), pa.array(np.diff(off)), pa.array([r.tobytes() for r in low], pa.binary()), pa.array(at, pa.binary()), pa.array(more, pa.binary())], names=["y", "size", "counts", "at", "more"])


def _blocks(batches):
    """(features, labels) of rows of counts."""
    for batch in batches:
        for s in range(0, batch.num_rows, ROWS):
            part = batch.slice(s, ROWS)
            counts = column_bytes(part.column("counts"))[0].reshape(part.num_rows, -1).astype(np.int64)
            at, off = column_bytes(part.column("at"))
            more = column_bytes(part.column("more"))[0]
            counts[np.repeat(np.arange(part.num_rows), np.diff(off) // 4), np.frombuffer(at.tobytes(), np.int32)] = np.frombuffer(more.tobytes(), np.int64)
            yield scaled(counts, part.column("size").to_numpy()), part.column("y").to_numpy()


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", rounds: int = 4, ridge: float = 1e-4) -> Ranker:
    """Learns from all labelled rows that are not held out."""
    from vecset.plans.limits import small

    small_batches(docs)
    known = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min(label).cast("int").alias("y"))
    known = known.where(~F.coalesce(held_out("doc_id"), F.lit(False)) & F.col("y").isin(0, 1))
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    own = own.where(~F.coalesce(held_out("doc_id"), F.lit(False)))
    rows = written(own.join(small(known), "doc_id").select("y", "text").mapInArrow(_counted, COUNTS), "counts")
    table = rows.coalesce(max(8, rows.count() // 500_000))  # a pass's sums are some megabytes for each task

    def run(name, *more):
        def add(batches):
            sums = getattr(_Sums, name)(_blocks(batches), *more)
            yield pa.RecordBatch.from_arrays([pa.array([np.ascontiguousarray(a).tobytes()], pa.binary()) for a in sums], names=[f"c{i}" for i in range(len(sums))])

        names, shapes, kinds = PASSES[name](more)
        got = table.mapInArrow(add, ", ".join(f"{c} binary" for c in names)).toArrow()
        for i in range(got.num_rows):
            yield tuple(np.frombuffer(got.column(c)[i].as_buffer(), kind).reshape(shape) for c, shape, kind in zip(names, shapes, kinds, strict=True))

    def between(w, low, high, bins, a, b):
        def pick(batches):
            for x, _ in _blocks(batches):
                s = x.astype(np.float64) @ w
                at = _bin(s, low, high, bins)
                got, n = np.unique(s[(at >= a) & (at <= b)], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(got), pa.array(n)], names=["s", "n"])

        # bins hold the two scores at the threshold and their like: some thousandths of the labels, equal ones once
        got = table.mapInArrow(pick, "s double, n long").where("s is not null").groupBy("s").agg(F.sum("n").alias("n")).where("n > 0").toArrow()
        s, n = got.column("s").to_numpy(), got.column("n").to_numpy()
        order = np.argsort(s)
        return np.repeat(s[order], n[order])

    model = _fitted(run, between, rounds, ridge)
    drop_written(rows)
    return model


#: Columns, shapes and kinds of each pass's sums.
PASSES = {
    "moments": lambda more: (["c0", "c1", "c2"], [(2,), (2, WIDTH), (2, WIDTH, WIDTH)], [np.float64, np.float64, np.float32]),
    "range": lambda more: (["c0"], [(2,)], [np.float64]),
    "histogram": lambda more: (["c0"], [(2, more[3])], [np.float64]),
    "slope": lambda more: (["c0"], [(WIDTH,)], [np.float64]),
}


def score(docs: DataFrame, model: Ranker, text_col: str = "text", name: str = "score") -> DataFrame:
    """docs with the score beside its own columns, in one pass and without a shuffle. A column of docs of that name is replaced."""
    small_batches(docs)
    docs = docs.drop(name)
    schema = StructType([*docs.schema.fields, StructField(name, DoubleType())])

    def run(batches):
        nothing_kept()
        for batch in batches:
            text = batch.schema.get_field_index(text_col)
            for part in pieces_of(batch, PIECE, text_col, ROWS):
                s = model.score(features(*column_bytes(part.column(text))))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(s)], names=[*part.schema.names, name])

    return docs.mapInArrow(run, schema)


def kept_documents(docs: DataFrame, model: Ranker, least: float = 0.5, text_col: str = "text") -> DataFrame:
    """The rows of docs that score at least `least`, with docs' own columns whatever their names."""
    name = fresh(docs, "_score")
    return score(docs, model, text_col, name).where(F.col(name) >= least).select(*docs.columns)
