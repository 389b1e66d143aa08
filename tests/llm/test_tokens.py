"""Token operators against brute force."""

import functools
import hashlib
import random
import zlib

import numpy as np
import public_tokenizers as P
import pytest
from pyspark.sql import functions as F

from vecset.llm import bpe, packing, token_files
from vecset.llm.tokens import Encoder, load_json, read_ranks

JSON, RANKS = P.path("byte_bpe_50k.json"), P.path("byte_bpe_50k.tiktoken")
SCHEMA = "doc_id long, text string, part string, start int, n_tokens string"


def odd_texts() -> list:
    draw = random.Random(3)
    signs = [" ", "  ", "\n", "\t", "a", "Bc", "é", " ", "1", "!", "'s", " ", "x,y", "世", "<|endoftext|>", " "]
    return [None, "", " ", "\n\n", "word " * 6000, "same text", "same text"] + ["".join(draw.choices(signs, k=draw.randint(0, 14))) for _ in range(150)]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i * 3, t, "x", 1, "y") for i, t in enumerate(odd_texts())]
    random.Random(1).shuffle(rows)
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


@functools.cache
def tokenizer():
    return load_json(JSON)


def ids_of(text):
    return tokenizer().encode(text or "", add_special_tokens=False).ids


def test_encoder_prunes_and_still_agrees():
    encoder, texts = Encoder(load_json(JSON), most=40), odd_texts()
    for _ in range(2):
        for k in range(0, len(texts), 9):
            flat, n = encoder.encode(texts[k : k + 9])
            assert flat.tolist() == [i for t in texts[k : k + 9] for i in ids_of(t)]


def test_segments_hold_every_id(docs):
    segments = token_files.write_segments(docs, JSON, segment_tokens=500)
    got = {r["doc_id"]: r for r in token_files.read_documents(segments).collect()}
    start = 0
    for r in sorted(docs.collect()):
        ids = [*ids_of(r["text"]), 0]
        assert (got[r["doc_id"]]["start"], got[r["doc_id"]]["n_tokens"]) == (start, len(ids))
        assert got[r["doc_id"]]["ids_crc32"] == zlib.crc32(np.array(ids, "<u4").tobytes())
        start += len(ids)
    flat = [i for r in sorted(docs.collect()) for i in [*ids_of(r["text"]), 0]]
    asked = [0, 5, start - 1, start // 2]
    at = token_files.token_at(segments, docs.sparkSession.createDataFrame([(p,) for p in asked], "position long"))
    assert {r["position"]: r["token"] for r in at.collect()} == {p: flat[p] for p in asked}


@pytest.mark.parametrize("high", [200, 50_000, 1 << 31])
def test_runs_of_a_segment(high):
    """A run is read from where the directory says that it begins in each level; 32-bit and 64-bit ids are packed alike."""
    ids = np.random.default_rng(high).integers(0, high, size=5000) >> np.random.default_rng(1).integers(0, 20, size=5000)
    parts = token_files.pack(ids)
    assert all(np.array_equal(x, y) for a, b in zip(parts, token_files.pack(ids.astype(np.uint32)), strict=True) for x, y in zip(a, b, strict=True))
    segment = token_files.Segment(*parts)
    for lo, hi in ((0, 5000), (0, 0), (1, 2), (511, 513), (777, 4097), (4999, 5000)):
        assert segment.read(lo, hi).tolist() == ids[lo:hi].tolist() == segment.get(np.arange(lo, hi)).tolist()



def test_codes_of_every_width():
    ids = np.array([0, 255, 256, 65535, 65536, 1 << 24, (1 << 32) - 1, 7] * 300)
    segment = token_files.Segment(*token_files.pack(ids))
    assert segment.get(np.arange(len(ids))).tolist() == ids.tolist()
    assert [int(segment.get(i)[0]) for i in range(60)] == ids[:60].tolist()


@pytest.mark.parametrize("block", [64, 1 << 19])
def test_counts_over_blocks(docs, block):
    flat = token_files.write_flat(docs, JSON, 50256, block_tokens=block)
    got = {r["doc_id"]: r["n_tokens"] for r in token_files.count_tokens(flat, 50256).collect()}
    assert got == {r["doc_id"]: len(ids_of(r["text"])) + 1 for r in docs.collect()}


def test_rank_round_trip(docs):
    import tiktoken

    plain = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=read_ranks(RANKS), special_tokens={})
    got = {r["doc_id"]: r for r in bpe.round_trip(docs, RANKS, P.PATTERN).collect()}
    decoded = {r["doc_id"]: r for r in bpe.decode(bpe.encode(docs, RANKS, P.PATTERN), RANKS, P.PATTERN).collect()}
    for r in docs.collect():
        ids, raw = plain.encode_ordinary(r["text"] or ""), (r["text"] or "").encode()
        assert got[r["doc_id"]]["n_tokens"] == len(ids)
        assert got[r["doc_id"]]["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert got[r["doc_id"]]["decoded_sha256"] == hashlib.sha256(raw).hexdigest()
        assert bytes(decoded[r["doc_id"]]["bytes"]) == raw and decoded[r["doc_id"]]["text"] == (r["text"] or "")


@pytest.mark.parametrize("rows", [40, 200_000])
def test_packing_is_whole_and_tight(docs, rows):
    got = packing.pack_documents(docs, JSON, 128, item_rows=rows).collect()
    by_doc, by_bin = {}, {}
    for r in got:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_bin.setdefault(r["sequence_id"], []).append(r)
    total = 0
    for r in docs.collect():
        ids, pieces = [*ids_of(r["text"]), 0], sorted(by_doc[r["doc_id"]], key=lambda x: x["piece"])
        total += len(ids)
        assert [p["start"] for p in pieces] == [sum(p["length"] for p in pieces[:k]) for k in range(len(pieces))]
        assert all(zlib.crc32(np.array(ids[p["start"] : p["start"] + p["length"]], "<u4").tobytes()) == p["ids_crc32"] for p in pieces)
        assert sum(p["length"] for p in pieces) == len(ids) and len(pieces) == -(-len(ids) // 128)
    for pieces in by_bin.values():
        pieces.sort(key=lambda x: x["offset"])
        assert [p["offset"] for p in pieces] == [sum(p["length"] for p in pieces[:k]) for k in range(len(pieces))]
        assert sum(p["length"] for p in pieces) <= 128
    assert len(by_bin) <= -(-total // 128) + 2


def best_fit_bins(sizes, capacity):
    """Sequences of best fit, longest first, one piece at a time."""
    rooms = []
    for size in sorted(sizes, reverse=True):
        fits = [r for r in rooms if r >= size]
        if fits:
            rooms.remove(min(fits))
        rooms.append((min(fits) if fits else capacity) - size)
    return len(rooms)


def test_best_fit_by_classes_is_best_fit():
    draw = np.random.default_rng(3)
    for capacity in (1, 7, 64, 200):
        for _ in range(20):
            sizes = draw.integers(1, capacity + 1, size=int(draw.integers(1, 300))) // draw.integers(1, 4) + 1
            sizes = np.minimum(sizes, capacity)
            names, n = np.unique(sizes, return_counts=True)
            plan = packing.best_fit(names.tolist(), n.tolist(), capacity)
            spans = {}
            for size, many in zip(names.tolist(), n.tolist(), strict=True):
                for k in range(many):
                    _, first, start, each, offset = max((r for r in plan.tolist() if r[0] == size and r[1] <= k), key=lambda r: r[1])
                    spans.setdefault(start + (k - first) // each, []).append((offset + (k - first) % each * size, size))
            for span in spans.values():
                span.sort()
                assert [a for a, _ in span] == [sum(m for _, m in span[:i]) for i in range(len(span))] and sum(m for _, m in span) <= capacity
            assert sorted(spans) == list(range(best_fit_bins(sizes.tolist(), capacity)))


def test_all_half_empty_sequences_meet_all_short_pieces(spark):
    """One task makes 6,000 half-empty sequences, another has the 6,000 pieces that fill them."""
    rows = [(i, 0, 0, 70, 0) for i in range(6000)] + [(6000 + i, 0, 0, 30, 0) for i in range(6000)]
    pieces = spark.createDataFrame(rows, "doc_id long, piece int, start long, length int, crc long").coalesce(2)
    got = packing.pack(pieces, 100).groupBy("sequence_id").agg(F.sum("length").alias("n"), F.min("offset").alias("a"), F.max("offset").alias("b"))
    assert {tuple(r) for r in got.select("n", "a", "b").distinct().collect()} == {(100, 0, 70)} and got.count() == 6000


def test_empty_tables(spark):
    none = spark.createDataFrame([], SCHEMA)
    assert token_files.read_documents(token_files.write_segments(none, JSON)).count() == 0
    assert token_files.count_tokens(token_files.write_flat(none, JSON, 50256), 50256).count() == 0
    assert bpe.round_trip(none, RANKS, P.PATTERN).count() == 0
    assert packing.pack_documents(none, JSON).count() == 0


def test_null_ids(spark):
    one = spark.createDataFrame([(None, "a b"), (None, None), (4, "c")], "doc_id long, text string")
    assert sorted(str(r["doc_id"]) for r in packing.pack_documents(one, JSON).collect()) == ["4", "None", "None"]
    assert {r["start"] for r in token_files.read_documents(token_files.write_segments(one, JSON)).collect()} <= {0, 1, 3, 4}
    assert one.select(F.count("*")).first()[0] == 3
