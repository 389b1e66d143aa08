"""Clashing names, dense groups, repeated ids, other patterns and widths."""

import numpy as np
import public_tokenizers as P
import pytest

from vecset.llm import bpe, jaccard_join, quality, suffix_dedup, token_files
from vecset.llm import vectors as V
from vecset.llm.tokens import Encoder, from_ranks, load_json, may_cut, read_ranks

from .test_jaccard import brute as join_brute

RANKS = P.path("byte_bpe_50k.tiktoken")


def test_clashing_names(spark):
    text = "one two three four five six seven " * 20
    schema = "doc_id long, text string, _n int, _N_ string, _doc string, _tag int, _spans string, _score string, score int"
    df = spark.createDataFrame([(i, t, i, "a", "b", 7, "c", "d", 9) for i, t in enumerate([text, text, "other words here", None, ""])], schema)
    labels = spark.createDataFrame([(0, 1), (1, 0)], "doc_id long, quality int")
    kept = quality.kept_documents(df, quality.fit(df, labels), 0.0)
    one = jaccard_join.one_of_each(df)
    cut = suffix_dedup.cleaned(df, 100)
    assert kept.columns == one.columns == cut.columns == df.columns
    assert sorted(map(str, kept.collect())) == sorted(map(str, df.collect()))
    assert sorted(r["doc_id"] for r in one.collect()) == [0, 2, 3, 4]
    assert {r["doc_id"]: (r["text"], r["_n"], r["_spans"], r["score"]) for r in cut.collect()}[1] == ("", 1, "c", 9)
    assert quality.score(df, quality.fit(df, labels)).schema["score"].dataType.simpleString() == "double"


def test_features_by_blocks():
    draw = np.random.default_rng(1)
    lens = draw.integers(0, 300, size=40) * draw.integers(0, 2, size=40)
    off = np.concatenate(([0], np.cumsum(lens)))
    flat = draw.integers(32, 127, size=off[-1]).astype(np.uint8)
    assert np.array_equal(quality.features(flat, off), quality.features(flat, off, block=37))
    for i in range(40):
        one = quality.features(flat[off[i] : off[i + 1]], np.array([0, lens[i]]))
        assert np.array_equal(one[0], quality.features(flat, off)[i])


@pytest.mark.parametrize("same", [True, False])
def test_dense_groups_by_blocks(same):
    """Groups of hundreds of near vectors beside sparse pairs and strangers, against all pairs."""
    draw = np.random.default_rng(6)
    centre = draw.normal(size=(2, 16))
    make = lambda n, c: centre[c] + draw.normal(size=(n, 16)) * 0.08
    x = V._unit(np.concatenate((make(300, 0), draw.normal(size=(200, 16)), make(5, 1))))
    y = V._unit(np.concatenate((make(150, 0), draw.normal(size=(100, 16)), make(4, 1))))
    m, n = draw.integers(1, 4, size=len(x)), draw.integers(1, 4, size=len(x) if same else len(y))
    if same:
        n = m
    links_x, links_y, union = V._linked(x, None if same else y, V.Graph(x), V.Graph(x if same else y), m, n, 0.98, 32, 128, 0.995)
    z = x if same else y
    hit = x @ z.T >= 0.98
    if same:
        np.fill_diagonal(hit, False)
        assert np.array_equal(links_x, hit @ m)
    else:
        assert np.array_equal(links_x, hit @ n) and np.array_equal(links_y, m @ hit)
    low = np.arange(len(x) + (0 if same else len(y)))
    i, j = np.nonzero(hit)
    j = j + (0 if same else len(x))
    for _ in range(20):
        np.minimum.at(low, i, low[j])
        np.minimum.at(low, j, low[i])
    assert hit.sum() > 10_000 and np.array_equal(union.root, low)


def test_repeated_ids(spark):
    """Both vectors of vec_id 1 have it as their least, and share their links."""
    rows = [(1, [1.0, 0.0], 0), (1, [0.0, 1.0], 0), (2, [1.0, 0.01], 0), (3, None, 0), (3, [0.0, 1.0], None)]
    got = V.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int"), 0.98)
    assert sorted(map(tuple, got.collect())) == [(1, 1, 1, True), (1, 1, 1, True), (2, 1, 1, False), (3, 0, 3, True), (3, 0, 3, True)]


@pytest.mark.parametrize("pattern", [P.PATTERN, r" ?[^\s]+|\s+", r"\s*\S+|\s+", r"\p{L}+|[^\p{L}]+"])
def test_other_patterns(pattern):
    import tiktoken

    ranks = read_ranks(RANKS)
    plain = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    encoder = Encoder(from_ranks(ranks, pattern))
    assert encoder.cuts == (pattern == P.PATTERN)
    texts = ["", "Some words, (and marks)!  two  spaces\n\nlines\tand 'quotes' it's 123abc.", "aaaa aaaaaaaaa ====---- \n x", "é世界 naïve... end "]
    flat, n = encoder.encode(texts)
    assert flat.tolist() == [i for t in texts for i in plain.encode_ordinary(t)] and n.tolist() == [len(plain.encode_ordinary(t)) for t in texts]


def test_json_vocabulary_allows_cuts():
    assert may_cut(load_json(P.path("byte_bpe_50k.json")))


def test_byte_offsets_and_split_characters(spark):
    docs = spark.createDataFrame([(1, "é世 x")], "doc_id long, text string")
    row = bpe.encode(docs, RANKS, P.PATTERN, offsets=True).first()
    assert row["offsets"][0] == 0 and row["offsets"][-1] == len("é世 x".encode()) and len(row["offsets"]) == len(row["ids"]) + 1


def test_more_buckets_give_the_same_links(spark, monkeypatch):
    draw = np.random.default_rng(5)
    base = [" ".join(draw.choice(400, size=60).astype(str)) for _ in range(30)]
    texts = base + [b + " tail" for b in base[:10]] + ["a b", "", None]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    monkeypatch.setattr(jaccard_join, "BUCKET_BYTES", 4)
    assert jaccard_join.bucket_bits(jaccard_join.texts(df)) > 10
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.join(df).collect()}
    assert got == join_brute(list(enumerate(texts)))


def test_codes_keep_64_bits():
    draw = np.random.default_rng(9)
    t = np.sort(draw.integers(0, 1000, size=500)).astype(np.uint16)
    h = draw.integers(0, 1 << 56, size=500, dtype=np.uint64) | np.uint64(0xAB << 56)
    back, doc = jaccard_join._uncoded(jaccard_join._coded(h, t), 0xAB)
    assert np.array_equal(back, h) and np.array_equal(doc, t)


def test_blocks_tell_the_bytes_of_an_id(spark):
    docs = spark.createDataFrame([(1, "a b c"), (2, ""), (3, "word " * 50)], "doc_id long, text string")
    flat = token_files.write_flat(docs, P.path("byte_bpe_50k.json"), 70_000, block_tokens=16)
    assert {r["width"] for r in flat.collect()} == {4}
    got = {r["doc_id"]: r["n_tokens"] for r in token_files.count_tokens(flat, 70_000).collect()}
    t = load_json(P.path("byte_bpe_50k.json"))
    assert got == {r["doc_id"]: len(t.encode(r["text"]).ids) + 1 for r in docs.collect()}
