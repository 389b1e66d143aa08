"""Token-ID output in directly addressable codes.

An id is cut into chunks of 8 bits, lowest first. Level k holds chunk k of every id that has one, and a bitmap that tells which of
them go on to level k + 1. A directory of running counts for each 512 bits gives the rank of a bit, and with it the place of an
id's next chunk. So any id of a segment is read by a look-up in each of its levels; nothing is decoded block by block.

A segment is a row of a Parquet table: documents stand in ascending doc_id order, within a segment and over segments.

Cases: a null or empty text is one end id; repeated doc_ids keep their rows, next to each other; an empty table gives an empty
table; other columns of docs are not read. A null doc_id sorts first and stays null.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ids_of, null_again, pieces_of, texts, written
from .tokens import json_encoder

CHUNK_BITS, RANK_BITS = 8, 512
SEGMENT_SCHEMA = "part int, segment int, first_doc long, n_docs long, n_tokens long, doc_ids binary, doc_starts binary, levels array<binary>, bitmaps array<binary>, ranks array<binary>"


def pack(ids: np.ndarray) -> tuple[list[np.ndarray], list[np.ndarray], list[np.ndarray]]:
    """Levels, bitmaps and rank directories of the ids."""
    levels, bitmaps, ranks, rest = [], [], [], np.asarray(ids)
    rest = rest if rest.dtype == np.uint32 else rest.astype(np.uint64)
    while True:
        more = rest >= (1 << CHUNK_BITS)
        levels.append(rest.astype(np.uint8))  # the lowest chunk
        if not more.any():
            return levels, bitmaps, ranks
        words = np.packbits(more, bitorder="little")
        words = np.concatenate((words, np.zeros(-len(words) % (RANK_BITS // 8), np.uint8)))
        count = np.bitwise_count(words.reshape(-1, RANK_BITS // 8)).sum(axis=1)
        bitmaps.append(words)
        ranks.append((np.cumsum(count) - count).astype(np.uint32))
        rest = rest[more] >> rest.dtype.type(CHUNK_BITS)


class Segment:
    """Random access to the ids of a segment."""

    def __init__(self, levels: list, bitmaps: list, ranks: list):
        read = lambda parts, kind: [np.frombuffer(p, kind) for p in parts]
        self.levels, self.bitmaps, self.ranks = read(levels, np.uint8), read(bitmaps, np.uint8), read(ranks, np.uint32)

    def rank(self, level: int, at: np.ndarray) -> np.ndarray:
        """Set bits of the level's bitmap before each position."""
        words, row, byte = self.bitmaps[level].reshape(-1, RANK_BITS // 8), at // RANK_BITS, at % RANK_BITS // 8
        some, back = (row, np.arange(len(at))) if len(at) < len(words) else (np.arange(len(words)), row)
        count = np.bitwise_count(words[some])  # of the rows that are asked for; the directory has what came before each
        inside = np.cumsum(count, axis=1, dtype=np.uint16) - count
        return self.ranks[level][row].astype(np.int64) + inside[back, byte] + np.bitwise_count(words[row, byte] & ((1 << (at % 8)) - 1).astype(np.uint8))

    def read(self, lo: int, hi: int) -> np.ndarray:
        """The ids of positions lo to hi, that one not included. A level's chunks of a run are a run: the directory tells where it begins."""
        out, live = self.levels[0][lo:hi].astype(np.uint32), np.arange(max(hi - lo, 0))
        for k, bitmap in enumerate(self.bitmaps):
            if not len(live):
                break
            on = np.flatnonzero(np.unpackbits(bitmap[lo >> 3 : (hi + 7) >> 3], bitorder="little")[lo & 7 : (lo & 7) + hi - lo])
            live, lo = live[on], int(self.rank(k, np.array([lo]))[0])
            hi = lo + len(on)
            out[live] |= self.levels[k + 1][lo:hi].astype(np.uint32) << np.uint32(CHUNK_BITS * (k + 1))
        return out

    def get(self, at) -> np.ndarray:
        """The ids at these positions."""
        at = np.atleast_1d(np.asarray(at, np.int64))
        out, live = self.levels[0][at].astype(np.uint32), np.arange(len(at))
        for k in range(len(self.bitmaps)):
            on = (self.bitmaps[k][at >> 3] >> (at & 7).astype(np.uint8)) & 1
            keep = np.flatnonzero(on)
            live, at = live[keep], self.rank(k, at[keep])
            out[live] |= self.levels[k + 1][at].astype(np.uint32) << np.uint32(CHUNK_BITS * (k + 1))
        return out


def write_segments(docs: DataFrame, path: str, end_id: int = 0, segment_tokens: int = 1_000_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The table of segments, written to the shared folder. path: of the tokenizer's file."""
    rows = texts(docs, id_col, text_col).repartitionByRange(F.col("doc_id")).sortWithinPartitions("doc_id")

    def encode(batches):
        encoder, part, held, size, n = json_encoder(path), TaskContext.get().partitionId(), [], 0, 0

        def flush():
            nonlocal held, size, n
            ids, lens, flat = np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held]), np.concatenate([h[2] for h in held])
            levels, bitmaps, ranks = pack(flat)
            first = ids[0] if len(ids) else 0
            row = [part, n, int(first), len(ids), len(flat), ids.tobytes(), (np.cumsum(lens) - lens).tobytes(), *([x.tobytes() for x in kind] for kind in (levels, bitmaps, ranks))]
            held, size, n = [], 0, n + 1
            return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, KINDS, strict=True)], names=NAMES)

        for batch in batches:
            for piece in pieces_of(batch, 1 << 20):
                flat, lens = encoder.encode(piece.column("text").to_pylist())
                ends = np.cumsum(lens)
                flat = np.insert(flat, ends, end_id)
                held.append((ids_of(piece.column("doc_id")), lens + 1, flat))
                size += len(flat)
                if size >= segment_tokens:
                    yield flush()
        if held:
            yield flush()

    return written(rows.mapInArrow(encode, SEGMENT_SCHEMA), "segments")


NAMES = [c.split()[0] for c in SEGMENT_SCHEMA.split(", ")]
KINDS = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.list_(pa.binary()), pa.list_(pa.binary()), pa.list_(pa.binary())]


def with_starts(segments: DataFrame) -> DataFrame:
    """Adds base: the ids of all segments before. The totals of the written parts, of which there are as many as tasks, are summed
    in their order; within a part, a window sums its segments. The bases, a row for each segment, are broadcast if they are small."""
    from pyspark.sql import Window

    from vecset.plans.limits import small

    parts = segments.groupBy("part").agg(F.min("first_doc").alias("low"), F.sum("n_tokens").alias("total"))
    order = Window.orderBy("low", "part").rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.select("part", F.coalesce(F.sum("total").over(order), F.lit(0)).alias("part_base"))
    inside = Window.partitionBy("part").orderBy("segment").rowsBetween(Window.unboundedPreceding, -1)
    base = segments.select("part", "segment", F.coalesce(F.sum("n_tokens").over(inside), F.lit(0)).alias("inside")).join(parts, "part")
    base = written(base.select("part", "segment", (F.col("part_base") + F.col("inside")).alias("base")), "bases")
    return segments.join(small(base), ["part", "segment"])


def read_documents(segments: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, from the files."""

    def decode(batches):
        for batch in batches:
            for row in batch.to_pylist():
                ids, starts = np.frombuffer(row["doc_ids"], np.int64), np.frombuffer(row["doc_starts"], np.int64)
                ends = np.append(starts[1:], row["n_tokens"])
                segment = Segment(row["levels"], row["bitmaps"], row["ranks"])
                tokens = segment.read(0, row["n_tokens"]).astype("<u4", copy=False)
                crc = np.fromiter((zlib.crc32(tokens[a:b]) for a, b in zip(starts, ends, strict=True)), np.int64, len(ids))
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(starts + row["base"]), pa.array(ends - starts), pa.array(crc)], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return null_again(with_starts(segments).mapInArrow(decode, "doc_id long, start long, n_tokens long, ids_crc32 long"), "doc_id")


def token_at(segments: DataFrame, positions: DataFrame) -> DataFrame:
    """(position, token) for each asked position, counted over the whole corpus: only the segments that hold one are read. The bounds
    of the segments, 32 bytes for each, go to every task; beyond 2M segments that is refused."""
    from vecset.plans.limits import driver_table

    bounds = with_starts(segments.select("part", "segment", "first_doc", "n_tokens")).select("part", "segment", "base", (F.col("base") + F.col("n_tokens")).alias("upto"))
    bounds = positions.sparkSession.createDataFrame(driver_table(bounds))
    asked = positions.select(F.col("position").cast("long").alias("position"))
    hit = asked.join(F.broadcast(bounds), (F.col("position") >= F.col("base")) & (F.col("position") < F.col("upto")))
    wanted = hit.groupBy("part", "segment").agg(F.collect_list(F.col("position")).alias("asked"), F.first("base").alias("base"))

    def look(batches):
        for batch in batches:
            for row in batch.to_pylist():
                at = np.array(row["asked"], np.int64)
                got = Segment(row["levels"], row["bitmaps"], row["ranks"]).get(at - row["base"])
                yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(got.astype(np.int64))], names=["position", "token"])

    return segments.join(wanted, ["part", "segment"]).mapInArrow(look, "position long, token long")


# Flat files and their token counts ------------------------------------------------------------------------------------------

FLAT_SCHEMA = "file int, block int, width int, tokens binary, doc_ids binary"


def write_flat(docs: DataFrame, path: str, end_id: int, block_tokens: int = 1 << 19, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Flat token files: per task one run of 16-bit ids (32-bit ones if the vocabulary asks for it), cut into blocks of equal size
    wherever that falls; documents end with end_id and have no index. Each block tells the bytes of an id. The names of the documents, in order, go beside the last block."""
    kind = np.uint16 if max(end_id, json_encoder(path).tokenizer.get_vocab_size(with_added_tokens=True)) < 1 << 16 else np.uint32

    def encode(batches):
        encoder, file, block, held, size, names = json_encoder(path), TaskContext.get().partitionId(), 0, [], 0, []
        row = lambda tokens, ids: pa.RecordBatch.from_arrays([pa.array([file], pa.int32()), pa.array([block], pa.int32()), pa.array([kind().itemsize], pa.int32()), pa.array([tokens.tobytes()]), pa.array([ids], pa.binary())], names=["file", "block", "width", "tokens", "doc_ids"])
        for batch in batches:
            for piece in pieces_of(batch, 1 << 20):
                flat, lens = encoder.encode(piece.column("text").to_pylist())
                held.append(np.insert(flat, np.cumsum(lens), end_id).astype(kind))
                names.append(ids_of(piece.column("doc_id")))
                size += len(held[-1])
                if size >= block_tokens:
                    run = np.concatenate(held)
                    for a in range(0, size - block_tokens + 1, block_tokens):
                        yield row(run[a : a + block_tokens], None)
                        block += 1
                    held, size = [run[size - size % block_tokens :]], size % block_tokens
        if names:
            yield row(np.concatenate(held), np.concatenate(names).tobytes())

    return written(texts(docs, id_col, text_col).mapInArrow(encode, FLAT_SCHEMA), "flat")


def count_tokens(flat: DataFrame, end_id: int) -> DataFrame:
    """(file, ordinal, doc_id, start, n_tokens) of each document of flat token files, its end id counted.

    Each block is searched for end ids on its own. Then a prefix scan over a file's blocks carries how many documents and tokens
    came before and where the last end stood, which gives the length of a document that began in an earlier block.
    """
    from pyspark.sql import Window

    def search(batches):
        for batch in batches:
            blobs = [np.frombuffer(b, np.uint16 if w == 2 else np.uint32) for b, w in zip(batch.column("tokens").to_pylist(), batch.column("width").to_pylist(), strict=True)]
            ends = [np.flatnonzero(b == end_id).astype(np.int32) for b in blobs]
            yield pa.RecordBatch.from_arrays(
                [batch.column("file"), batch.column("block"), pa.array([len(b) for b in blobs], pa.int64()), pa.array([len(e) for e in ends], pa.int64()), pa.array([int(e[-1]) if len(e) else None for e in ends], pa.int64()), pa.array([e.tobytes() for e in ends]), batch.column("doc_ids")],
                names=["file", "block", "n", "n_ends", "last", "ends", "doc_ids"],
            )

    found = flat.mapInArrow(search, "file int, block int, n long, n_ends long, last long, ends binary, doc_ids binary")
    before = Window.partitionBy("file").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    scan = found.drop("doc_ids").withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0)))
    scan = scan.withColumns({"ordinal": F.coalesce(F.sum("n_ends").over(before), F.lit(0)), "open": F.coalesce(F.max(F.col("base") + F.col("last")).over(before), F.lit(-1))})
    names = found.where("doc_ids is not null").select("file", "doc_ids")

    def rows(batches):
        for batch in batches:
            for r in batch.to_pylist():
                at = np.frombuffer(r["ends"], np.int32).astype(np.int64) + r["base"]
                prev = np.concatenate(([r["open"]], at[:-1]))[: len(at)]
                k = r["ordinal"] + np.arange(len(at))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), r["file"], np.int32)), pa.array(k), pa.array(np.frombuffer(r["doc_ids"], np.int64)[k]), pa.array(prev + 1), pa.array(at - prev)], names=["file", "ordinal", "doc_id", "start", "n_tokens"])

    return null_again(scan.where("n_ends > 0").join(names, "file").mapInArrow(rows, "file int, ordinal long, doc_id long, start long, n_tokens long"), "doc_id")
