"""Suffix-array dedup against brute force."""

import hashlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from vecset.llm import suffix_dedup
from vecset.llm.suffix_kernel import common_prefix_reaches, may_repeat, owners, suffix_array


@pytest.mark.parametrize("kind", range(4))
def test_two_stage_order(kind):
    draw = np.random.default_rng(kind)
    text = draw.integers(97, 97 + [2, 4, 26, 1][kind], size=900).astype(np.uint8)
    if kind == 2:
        text[300:600] = text[:300]
    order = suffix_array(text, 1000)
    raw = text.tobytes()
    assert order.tolist() == sorted(range(len(raw)), key=lambda i: raw[i:])
    reach = common_prefix_reaches(text, order, 100)
    assert reach[1:].tolist() == [raw[a : a + 100].ljust(100, b"\0") == raw[b : b + 100].ljust(100, b"\0") for a, b in zip(order[:-1], order[1:], strict=True)]


def brute(texts, width):
    raws = [(t or "").encode() for t in texts]
    seen = Counter(r[i : i + width] for r in raws for i in range(len(r) - width + 1))
    out = []
    for r in raws:
        gone = np.zeros(len(r), bool)
        for i in range(len(r) - width + 1):
            if seen[r[i : i + width]] > 1:
                gone[i : i + width] = True
        edge = np.diff(np.concatenate(([0], gone.view(np.int8), [0])))
        out.append((len(r), int(gone.sum()), int((edge == 1).sum()), hashlib.sha256(np.frombuffer(r, np.uint8)[~gone].tobytes()).hexdigest()))
    return out


def corpus():
    draw = np.random.default_rng(8)
    words = ["".join(map(chr, draw.integers(97, 123, size=draw.integers(2, 8)))) + ("é" if draw.random() < 0.1 else "") for _ in range(300)]
    make = lambda n: " ".join(draw.choice(words, size=n))
    passage, base = make(40), make(200)
    texts = [None, "", "short", make(100), base, base, base[:500] + "X" + base[500:], passage, "z" * 900, "ab" * 400]
    texts += [make(int(draw.integers(0, 60))) + " " + passage + " " + make(int(draw.integers(0, 60))) for _ in range(40)]
    texts += [passage[:120] + make(30) + passage[100:] for _ in range(10)] + [base[: int(k)] for k in draw.integers(50, 900, size=12)]
    return texts


@pytest.mark.parametrize(("width", "hot", "unit"), [(100, 12_000, 1 << 20), (100, 3, 2000), (400, 12_000, 1 << 20), (60, 12_000, 3000)])
def test_report(spark, width, hot, unit):
    texts = corpus()
    df = spark.createDataFrame([(i, t, 5, "q") for i, t in enumerate(texts)], "doc_id long, text string, doc int, tag string").repartition(3)
    got = {r[0]: tuple(r[1:]) for r in suffix_dedup.report(df, width, hot_classes=hot, unit_bytes=unit).collect()}
    assert [got[i] for i in range(len(texts))] == brute(texts, width)


def test_cleaned_keeps_rows_and_columns(spark):
    same = "one passage that comes twice " * 20
    df = spark.createDataFrame([(1, same, "a"), (1, same, "a"), (None, None, "b"), (2, "alone", "c")], "doc_id long, text string, lang string")
    got = suffix_dedup.cleaned(df, 100)
    assert got.columns == df.columns
    assert sorted((str(r[0]), r[1], r[2]) for r in got.collect()) == [("1", "", "a"), ("1", "", "a"), ("2", "alone", "c"), ("None", None, "b")]


def test_empty(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert suffix_dedup.report(none).count() == 0


def test_segments_hold_no_copies_of_the_text():
    """A text of 400,000 bytes has some thousand segments; a copy of it for each would be over a gigabyte."""
    text = np.random.default_rng(3).integers(97, 123, size=400_000).astype(np.uint8).tobytes().decode()
    batch = pa.RecordBatch.from_arrays([pa.array([1]), pa.array([2]), pa.array([text])], names=["doc", "tag", "text"])
    usual, pool = pa.default_memory_pool(), pa.proxy_memory_pool(pa.default_memory_pool())
    pa.set_memory_pool(pool)
    try:
        n = sum(b.num_rows for b in suffix_dedup._segments(400)([batch]))
    finally:
        pa.set_memory_pool(usual)
    assert n > 1000 and pool.max_memory() < 32 << 20


@pytest.mark.parametrize("width", [100, 60, 40])
def test_windows_left_out_come_once(width):
    raws = [(t or "").encode() for t in corpus()]
    off = np.cumsum([0, *map(len, raws)])
    text, h, rel, first, last, _ = owners(np.frombuffer(b"".join(raws), np.uint8), off, width)
    runs = may_repeat([np.frombuffer(raws[t][a : b + width], np.uint8) for t, a, b in zip(text, first, last, strict=True)], h, rel, np.ones(len(h), np.int64), width)
    found = {(int(text[i]), int(first[i]) + j) for i, a, b in zip(*runs, strict=True) for j in range(a, b)}
    seen = Counter(r[i : i + width] for r in raws for i in range(len(r) - width + 1))
    every = {(k, i): seen[r[i : i + width]] > 1 for k, r in enumerate(raws) for i in range(len(r) - width + 1)}
    # copies inside one text that overlap have one segment each, and none is lost; what comes once is mostly left out
    assert {w for w, again in every.items() if again} <= found
    assert len(found) < sum(every.values()) + 0.5 * (len(every) - sum(every.values()))
