"""Byte-level BPE encoding and decoding of a column, by the tokenizers library over Arrow batches.

The rank file gives the vocabulary; each byte has a printable character, and the merges follow from the ranks. The library splits
the text by the caller's pattern. Decoding reads the table of those characters backwards. Where the pattern
allows it, texts are cut at spaces first and each chunk is encoded once (tokens.py). Tests hold the ids against a second
library that merges by ranks.

Cases: null and empty texts have no ids; very long ones go whole; repeated rows stay; an empty table gives an empty one.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pieces_of, texts
from .tokens import ByteTable, rank_encoder


def encode(docs: DataFrame, path: str, pattern: str, offsets: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids array<int>), with offsets the n + 1 byte offsets of the ids."""

    def run(batches):
        encoder, table = rank_encoder(path, pattern)
        for batch in batches:
            for piece in pieces_of(batch, 1 << 20):
                flat, lens = encoder.encode(piece.column("text").to_pylist())
                at = np.concatenate(([0], np.cumsum(lens))).astype(np.int32)
                out = [piece.column("doc_id"), pa.ListArray.from_arrays(pa.array(at), pa.array(flat.astype(np.int32)))]
                if offsets:
                    each = [table.byte_offsets(flat[a:b]) for a, b in zip(at[:-1], at[1:], strict=True)]
                    out.append(pa.array(each, pa.list_(pa.int64())))
                yield pa.RecordBatch.from_arrays(out, names=["doc_id", "ids", "offsets"][: len(out)])

    return texts(docs, id_col, text_col).mapInArrow(run, "doc_id long, ids array<int>" + (", offsets array<long>" if offsets else ""))


def decode(ids: DataFrame, path: str, pattern: str) -> DataFrame:
    """(doc_id, bytes, text) of (doc_id, ids). Bytes that are no whole character become U+FFFD in the text alone. Null ids: empty."""

    def run(batches):
        _, table = rank_encoder(path, pattern)
        for batch in batches:
            raw = [table.decode(np.array(x or [], np.int64)) for x in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(raw, pa.binary()), pa.array([r.decode("utf-8", errors="replace") for r in raw])], names=["doc_id", "bytes", "text"])

    return ids.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("ids").cast("array<long>").alias("ids")).mapInArrow(run, "doc_id long, bytes binary, text string")


def round_trip(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): ids and decoded bytes are hashed where they are made, none is shipped."""

    def run(batches):
        encoder, table = rank_encoder(path, pattern)
        for batch in batches:
            for piece in pieces_of(batch, 1 << 20):
                flat, lens = encoder.encode(piece.column("text").to_pylist())
                at = np.concatenate(([0], np.cumsum(lens)))
                shas = [[], []]
                for out, kind in zip(shas, (table.decimal, table.token), strict=True):
                    joined = ByteTable.join(kind, flat.astype(np.int64))
                    ends = np.concatenate(([0], np.cumsum(kind[2][flat])))[at]
                    cut = 1 if kind is table.decimal else 0
                    out += [hashlib.sha256(joined[a : max(a, b - cut)]).hexdigest() for a, b in zip(ends[:-1], ends[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array(lens), pa.array(shas[0]), pa.array(shas[1])], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return texts(docs, id_col, text_col).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
