"""Suffix-array dedup: removes every byte that a string of `width` bytes covers which also starts elsewhere in the corpus.

1. Every window of `width` bytes belongs to an owner: its gram with the least hash. Equal windows have equal owners at the same
   place, so only windows of equal owners need to meet. Neighbouring windows of one owner are a segment.
2. Owners that come once are done. Equal segments are a class; a class with copies is repeated in all its windows, and one member
   stands for it.
3. The representatives of owners with several classes go to tasks by owner. Each task leaves out windows whose bytes around the owner
   come in one class alone, joins the rest to one text and sorts its suffixes in two stages; neighbours that share `width` bytes are
   repeated windows. An owner with more than `hot_classes` classes
   is compared by window hashes instead, which spread over all tasks.
4. The windows' spans go back to their documents.

Cases: a null or empty text has nothing to remove; a text shorter than width neither; repeated rows (same doc_id) are separate texts,
so both go; an empty table gives an empty one; matches never cross documents; very long texts are cut into overlapping parts.
Equality of segments in step 2 and of windows of hot owners is that of 64-bit hashes.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import NO_ID, column_bytes, free, fresh, nothing_kept, pieces_of, small_batches, written
from .suffix_kernel import may_repeat, owners, repeated_windows

#: Bytes of text that a kernel takes at once, and of a long text's parts.
PIECE, PART = 1 << 16, 1 << 20


def keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(doc, tag, text): tag tells rows of one doc_id with different texts apart."""
    small_batches(docs)
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("doc"), F.crc32(text.cast("binary")).alias("tag"), text.alias("text"))


def _segments(width: int):
    def run(batches):
        nothing_kept()
        for batch in batches:
            for part in pieces_of(batch, PIECE):
                flat, off = column_bytes(part.column("text"))
                if len(flat) > 2 * PART:  # one long text, in parts that share width - 1 bytes
                    cuts = [(a, min(a + PART + width - 1, len(flat))) for a in range(0, max(1, len(flat) - width + 1), PART)]
                else:
                    cuts = [(0, len(flat))]
                for a, b in cuts:
                    t, h, rel, s, e, w = owners(flat[a:b], off if len(cuts) == 1 else np.array([0, b - a]), width)
                    took = part.select(["doc", "tag"]).take(pa.array(t))  # not the text, which would be copied for each of its segments
                    yield pa.RecordBatch.from_arrays([took.column("doc"), took.column("tag"), pa.array(h), pa.array(w), pa.array(rel.astype(np.int32)), pa.array(s + a), pa.array(e + a)], names=["doc", "tag", "h", "w", "rel", "s", "e"])

    return run


SEGMENT = "doc long, tag long, h long, w long, rel int, s long, e long"


def spans(docs: DataFrame, width: int = 400, unit_bytes: int = 1 << 20, hot_classes: int = 12_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc, tag, spans array<struct<lo, hi>>): byte ranges that repeated strings cover, overlapping and unsorted."""
    rows = keyed(docs, id_col, text_col)
    segments = written(rows.mapInArrow(_segments(width), SEGMENT), "segments")
    # tasks count first: an owner or a segment with very many copies is a row for each task
    owner = Window.partitionBy("h")
    counts = segments.groupBy("h", "w").agg(F.count("*").alias("copies"))
    kinds = counts.withColumns({"n": F.sum("copies").over(owner), "several": F.count("*").over(owner) > 1}).where("n > 1").drop("n")
    kinds = written(kinds, "kinds")  # so that the join's shuffle is its own, and a segment with very many rows can be split
    live = written(segments.join(kinds, ["h", "w"]), "live")
    free(segments)
    classes = live.groupBy("h", "w", "several", "copies").agg(F.min(F.struct("doc", "tag", "s", "e", "rel")).alias("rep"))
    classes = written(classes.select("h", "w", "several", "copies", "rep.*"), "classes")
    copied = live.where("copies > 1").select("doc", "tag", F.col("s").alias("lo"), (F.col("e") + width).alias("hi"))

    kinds = classes.where("several").groupBy("h").agg(F.count("*").alias("k"), F.sum(F.col("e") - F.col("s") + width).alias("bytes"))
    total, most = kinds.agg(F.coalesce(F.sum("bytes"), F.lit(0)), F.coalesce(F.max("k"), F.lit(0))).first()
    units = max(1, -(-total // unit_bytes))
    met = classes.where("several").join(kinds.select("h", (F.col("k") > hot_classes).alias("hot")), "h")
    asked = met.groupBy("doc", "tag").agg(F.collect_list(F.struct("h", "s", "e", "rel", "copies", "hot")).alias("asked"))

    def fetch(batches):
        for batch in batches:
            text, off = column_bytes(batch.column("text"))
            asks = batch.column("asked")
            n = asks.value_lengths().to_numpy().astype(np.int64)
            flat = asks.flatten()
            field = lambda k: flat.field(k).to_numpy(zero_copy_only=False)
            row = np.repeat(np.arange(batch.num_rows), n)
            a, b = off[row] + field(1), off[row] + field(2) + width
            for lo in range(0, len(row), 4096):
                cut = [text[i:j].tobytes() for i, j in zip(a[lo : lo + 4096].tolist(), b[lo : lo + 4096].tolist(), strict=True)]
                took = batch.select(["doc", "tag"]).take(pa.array(row[lo : lo + 4096]))
                part = flat.slice(lo, 4096)
                yield pa.RecordBatch.from_arrays([*took.columns, *part.flatten(), pa.array(cut, pa.binary())], names=["doc", "tag", "h", "s", "e", "rel", "copies", "hot", "bytes"])

    fetched = rows.join(asked, ["doc", "tag"]).mapInArrow(fetch, "doc long, tag long, h long, s long, e long, rel int, copies long, hot boolean, bytes binary")
    fetched = fetched.withColumn("unit", F.pmod(F.xxhash64("h"), F.lit(units)))
    if most > hot_classes:
        fetched = written(fetched, "fetched")

    def sort(group: pa.Table) -> pa.Table:
        nothing_kept()
        data = [np.frombuffer(b, np.uint8) for b in group.column("bytes").to_pylist()]
        copies = group.column("copies").to_numpy()
        own, first, end = may_repeat(data, group.column("h").to_numpy(), group.column("rel").to_numpy().astype(np.int64), copies, width)
        marks = repeated_windows([data[i][a : b - 1 + width] for i, a, b in zip(own, first, end, strict=True)], copies[own], width)
        runs = []
        for m, i, a in zip(marks, own, first, strict=True):
            edge = np.flatnonzero(np.diff(np.concatenate(([0], m.view(np.int8), [0])))) if copies[i] == 1 else np.zeros(0, np.int64)
            runs.append(edge.reshape(-1, 2) + a)
        n = np.array([len(r) for r in runs], np.int64)
        edges = np.concatenate(runs) if len(runs) else np.zeros((0, 2), np.int64)
        took = group.select(["doc", "tag", "s"]).take(pa.array(np.repeat(own, n)))
        s = took.column("s").to_numpy()
        return pa.table([took.column("doc"), took.column("tag"), pa.array(s + edges[:, 0]), pa.array(s + edges[:, 1] - 1 + width)], names=["doc", "tag", "lo", "hi"])

    sorted_ = fetched.where("not hot").groupBy("unit").applyInArrow(sort, "doc long, tag long, lo long, hi long")
    out = copied.unionAll(sorted_)
    if most > hot_classes:
        out = out.unionAll(_hot(fetched.where("hot"), width))
    # spans of one document that copies gave come in order; each task joins them before they are dealt
    return written(out.groupBy("doc", "tag").agg(F.collect_list(F.struct("lo", "hi")).alias("spans")), "spans")


def _hot(fetched: DataFrame, width: int) -> DataFrame:
    """Windows of owners with very many classes: a row for each window and its hash; equal ones are counted, tasks first."""
    from .suffix_kernel import BASE, UNBASE, mix64, powers

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                x = np.frombuffer(batch.column("bytes")[i].as_py(), np.uint8)
                with np.errstate(over="ignore"):
                    total = np.concatenate((np.zeros(1, np.uint64), np.cumsum((x.astype(np.uint64) + np.uint64(1)) * powers(BASE, len(x)))))
                    got = mix64((total[width:] - total[:-width]) * powers(UNBASE, len(x) + 1 - width))
                took = batch.slice(i, 1).select(["doc", "tag", "h", "s", "rel", "copies"]).take(pa.array(np.zeros(len(got), np.int64)))
                at = np.arange(len(got))
                yield pa.RecordBatch.from_arrays([*took.columns[:3], pa.array(took.column("s").to_numpy() + at), pa.array(took.column("rel").to_numpy() - at), took.column("copies"), pa.array(got.view(np.int64))], names=["doc", "tag", "h", "p", "rel", "copies", "fp"])

    windows = written(fetched.mapInArrow(run, "doc long, tag long, h long, p long, rel long, copies long, fp long"), "windows")
    many = windows.groupBy("h", "rel", "fp").agg(F.sum("copies").alias("n")).where("n > 1").select("h", "rel", "fp")
    return windows.where("copies = 1").join(many, ["h", "rel", "fp"]).select("doc", "tag", F.col("p").alias("lo"), (F.col("p") + width).alias("hi"))


def _merged(column: pa.Array, i: int) -> list[tuple[int, int]]:
    """The spans of row i as maximal runs, in order."""
    row = column[i].values
    if row is None or not len(row):
        return []
    lo, hi = row.field(0).to_numpy(), row.field(1).to_numpy()
    order = np.argsort(lo, kind="stable")
    lo, hi = lo[order], np.maximum.accumulate(hi[order])
    new = np.concatenate(([True], lo[1:] > hi[:-1]))
    last = np.concatenate((new[1:], [True]))
    return list(zip(lo[new].tolist(), hi[last].tolist(), strict=True))


def _joined(docs: DataFrame, found: DataFrame, id_col: str, text_col: str) -> tuple[DataFrame, str]:
    """docs with the spans found in them, and the name of that column, which docs don't have."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    doc, tag, name = (fresh(docs, c) for c in ("_doc", "_tag", "_spans"))
    keyed_ = docs.withColumns({doc: F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)), tag: F.crc32(text.cast("binary"))})
    return keyed_.join(found.select(F.col("doc").alias(doc), F.col("tag").alias(tag), F.col("spans").alias(name)), [doc, tag], "left").select(*docs.columns, name), name


def report(docs: DataFrame, width: int = 400, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256)."""

    def run(batches):
        for batch in batches:
            for part in pieces_of(batch, 4 << 20, "text"):
                raw, off = column_bytes(part.column("text"))
                out = []
                for i in range(part.num_rows):
                    data, at, sha, gone, runs = raw[off[i] : off[i + 1]], 0, hashlib.sha256(), 0, _merged(part.column(name), i)
                    for a, b in runs:
                        sha.update(data[at:a])
                        at, gone = b, gone + b - a
                    sha.update(data[at:])
                    out.append((len(data), gone, len(runs), sha.hexdigest()))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *(pa.array([o[k] for o in out], pa.int64() if k < 3 else pa.string()) for k in range(4))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    found = spans(docs, width, id_col=id_col, text_col=text_col, **options)
    free(docs)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    joined, name = _joined(rows, found, "doc_id", "text")
    return joined.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def cleaned(docs: DataFrame, width: int = 400, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """docs with the kept bytes as text. Bytes of a character that a cut goes through become U+FFFD. No row is lost; null texts stay."""
    found = spans(docs, width, id_col=id_col, text_col=text_col, **options)
    free(docs)
    joined, name = _joined(docs, found, id_col, text_col)

    def run(batches):
        for batch in batches:
            for part in pieces_of(batch, 4 << 20, text_col):
                raw, off = column_bytes(part.column(text_col))
                texts = part.column(text_col).to_pylist()
                for i in range(part.num_rows):
                    if runs := _merged(part.column(name), i):
                        data, keep, at = raw[off[i] : off[i + 1]], [], 0
                        for a, b in runs:
                            keep.append(data[at:a].tobytes())
                            at = b
                        texts[i] = (b"".join(keep) + data[at:].tobytes()).decode("utf-8", errors="replace")
                names = [c for c in part.schema.names if c != name]
                yield pa.RecordBatch.from_arrays([pa.array(texts, pa.string()) if c == text_col else part.column(c) for c in names], names=names)

    return joined.mapInArrow(run, docs.schema)
