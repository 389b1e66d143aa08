"""Best-fit packing over all pieces at once, by classes of length.

Which sequences best fit makes, longest piece first, depends only on how many pieces there are of each length, and there are no more
lengths than ids in a sequence. So the pieces are written and counted by length, best fit runs over the counts, a whole run of equal
pieces or of equal sequences at a step, and each piece finds its sequence by its number among those of its length. No piece is left
out, no sequence is closed while a piece of any task fits, and no task holds more than item_rows pieces.

Cases: a null or empty text is its end id alone; repeated rows are packed as often as they come; an empty table gives an empty one;
a document longer than a sequence is cut, its first piece taking the remainder.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ids_of, null_again, pieces_of, ranges, texts, written
from .tokens import json_encoder

FIELDS = ["doc_id", "piece", "start", "length", "crc"]
PIECE_SCHEMA = "doc_id long, piece int, start long, length int, crc long"


def best_fit(sizes: list[int], counts: list[int], capacity: int) -> np.ndarray:
    """Rows (size, nth, bin, each, offset), by size and nth: from the nth item of a size on, bins from that one on take `each` items,
    the first of them at offset. Longest first, each item to the bin with the least room that takes it. Sizes from 1 to capacity.

    Bins of equal room wait as ranges of numbers. A bin that an item goes to has the least room for the next of that size too.
    """
    steps, rooms, waiting, bins = [], [], {}, 0
    for size, left in sorted(zip(sizes, counts, strict=True), reverse=True):
        nth = 0
        while left:
            at = bisect_left(rooms, size)
            if at < len(rooms):
                room = rooms[at]
                first, n = waiting[room].pop()
                if not waiting[room]:
                    del waiting[room], rooms[at]
            else:
                room, first, n = capacity, bins, -(-left // (capacity // size))
                bins += n
            each = room // size
            took = min(left, n * each)
            full, rest = divmod(took, each)
            steps.append((size, nth, first, each, capacity - room))
            nth, left = nth + took, left - took
            part = int(rest > 0)
            for more, start, many in ((room - each * size, first, full), (room - rest * size, first + full, part), (room, first + full + part, n - full - part)):
                if more and many:
                    if more not in waiting:
                        waiting[more] = []
                        insort(rooms, more)
                    waiting[more].append((start, many))
    return np.array(sorted(steps), np.int64).reshape(-1, 5)


def _cut(path: str, capacity: int, end_id: int):
    """Batches of (doc_id, text) to batches of pieces."""

    def run(batches):
        encoder = json_encoder(path)
        for batch in batches:
            for part in pieces_of(batch, 1 << 20):
                flat, lens = encoder.encode(part.column("text").to_pylist())
                flat = np.insert(flat, np.cumsum(lens), end_id).astype("<u4")
                lens = lens + 1
                n = -(-lens // capacity)
                k = ranges(np.zeros(len(n)), n)
                size, first = np.repeat(lens, n), np.repeat(lens - (n - 1) * capacity, n)
                start = np.where(k == 0, 0, first + (k - 1) * capacity)
                length = np.where(k == 0, np.minimum(first, size), capacity)
                at = np.repeat(np.cumsum(lens) - lens, n) + start
                crc = np.fromiter((zlib.crc32(flat[a : a + m]) for a, m in zip(at, length, strict=True)), np.int64, len(at))
                ids = np.repeat(ids_of(part.column("doc_id")), n)
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(k.astype(np.int32)), pa.array(start), pa.array(length.astype(np.int32)), pa.array(crc)], names=FIELDS)

    return run


def cut_pieces(docs: DataFrame, path: str, capacity: int, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, piece, start, length, crc): the pieces of every document."""
    return texts(docs, id_col, text_col).mapInArrow(_cut(path, capacity, end_id), PIECE_SCHEMA)


def _number(item_rows: int = 200_000):
    """Batches of pieces to the same with their block and their number among the block's pieces of their length."""

    def numbered(held: list[pa.RecordBatch], block: int):
        table = pa.Table.from_batches(held)
        length = table.column("length").to_numpy()
        order = np.argsort(length, kind="stable")
        n = np.unique(length, return_counts=True)[1]
        nth = np.empty(len(length), np.int64)
        nth[order] = ranges(np.zeros(len(n)), n)
        yield from table.append_column("block", pa.array(np.full(len(nth), block))).append_column("nth", pa.array(nth)).to_batches()

    def run(batches):
        task, k, held, size = TaskContext.get().partitionId(), 0, [], 0
        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            if size >= item_rows:
                yield from numbered(held, (task << 32) + k)
                held, size, k = [], 0, k + 1
        if size:
            yield from numbered(held, (task << 32) + k)

    return run


ITEM_SCHEMA = f"{PIECE_SCHEMA}, block long, nth long"


def pack(pieces: DataFrame, capacity: int = 2048, item_rows: int = 200_000) -> DataFrame:
    """(doc_id, piece, start, length, crc, sequence_id, offset) of pieces of 1 to capacity ids."""
    return _placed(pieces.mapInArrow(_number(item_rows), ITEM_SCHEMA), capacity)


def _placed(items: DataFrame, capacity: int) -> DataFrame:
    items = written(items, "pieces")
    counts = written(items.groupBy("block", "length").agg(F.count("*").alias("n")), "counts")
    total = counts.groupBy("length").agg(F.sum("n").alias("n")).toArrow()
    plan = best_fit(total.column("length").to_pylist(), total.column("n").to_pylist(), capacity)
    before = Window.partitionBy("length").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("block", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))

    def place(batches):
        wide = int(plan[:, 1].max(initial=0)).bit_length()
        keys = (plan[:, 0] << wide) + plan[:, 1]
        for b in batches:
            length = b.column("length").to_numpy().astype(np.int64)
            nth = b.column("base").to_numpy() + b.column("nth").to_numpy()
            # the last step of a length may hold numbers with more bits than any step's first
            at = np.searchsorted(keys, (length << wide) + np.minimum(nth, (1 << wide) - 1), "right") - 1
            _, first, start, each, offset = plan[at].T
            k = nth - first
            yield pa.RecordBatch.from_arrays([*(b.column(f) for f in FIELDS), pa.array(start + k // each), pa.array(offset + k % each * length)], names=[*FIELDS, "sequence_id", "offset"])

    return items.join(base, ["block", "length"]).select(*FIELDS, "nth", "base").mapInArrow(place, f"{PIECE_SCHEMA}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, path: str, capacity: int = 2048, end_id: int = 0, **options) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset)."""
    cut, number = _cut(path, capacity, end_id), _number(**options)
    items = texts(docs, "doc_id", "text").mapInArrow(lambda batches: number(cut(batches)), ITEM_SCHEMA)  # one worker a task, not two
    out = null_again(_placed(items, capacity), "doc_id")
    return out.select("doc_id", "piece", "start", F.col("length").cast("long").alias("length"), F.col("crc").alias("ids_crc32"), "sequence_id", "offset")
