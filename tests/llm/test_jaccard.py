"""The n-gram Jaccard join against brute force."""

import re

import numpy as np
import pytest

from vecset.llm import jaccard_join
from vecset.llm.common import column_bytes


def word_sets(text, words=5):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[i : i + words]) for i in range(len(w) - words + 1)} or ({tuple(w)} if w else set())


def brute(rows):
    sets = [(i, word_sets(t)) for i, t in rows]
    low = {i: i for i, _ in rows}
    links = [(a, b) for k, (a, x) in enumerate(sets) for b, y in sets[k + 1 :] if x and y and 100 * len(x & y) >= 75 * len(x | y)]
    changed = True
    while changed:
        changed = False
        for a, b in links:
            m = min(low[a], low[b])
            changed |= low[a] != m or low[b] != m
            low[a] = low[b] = m
    return {i: (len(s), low[i]) for i, s in sets}


def corpus(seed):
    draw = np.random.default_rng(seed)
    words = [f"w{k}" for k in range(4000)]
    make = lambda n: list(draw.choice(words, size=n))
    texts = [None, "", "  \n", "one two", "One TWO", "a b c d", "a b c d e", "É x y z ü É", "é x y z ü é"]
    line = make(20)
    for _ in range(25):
        base = make(int(draw.integers(5, 120)))
        for _ in range(int(draw.integers(1, 6))):
            edit = list(base)
            for _ in range(int(draw.integers(0, 6))):
                edit[int(draw.integers(0, len(edit)))] = str(draw.choice(words))
            texts.append(" ".join(edit if draw.random() < 0.7 else line + edit))
    hot = make(60)
    for _ in range(60):
        edit = list(hot)
        edit[int(draw.integers(0, 60))] = str(draw.choice(words))
        texts += [" ".join(edit), " ".join(edit).upper()]
    chain = make(80)
    texts += [" ".join(chain[k : k + 60]) for k in range(0, 21, 2)]
    order = draw.permutation(len(texts))
    return [(int(k) * 2, texts[k]) for k in order]


@pytest.mark.parametrize("seed", [1, 2])
def test_join(spark, seed):
    rows = corpus(seed)
    df = spark.createDataFrame([(i, t, 3, "x") for i, t in rows], "doc_id long, text string, n int, token string").repartition(4)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.join(df).collect()}
    assert got == brute(rows)


def test_bound_of_marks_loses_no_link(spark):
    """Without pivots every pair passes the bound by marks."""
    rows = corpus(3)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.join(df, pivot_rounds=0).collect()}
    assert got == brute(rows)


def test_shingles_count():
    import pyarrow as pa

    texts = ["a b c d e f", "", "x", "a\x0bb\x1cc d e A B C D E", "q " * 3000]
    t, _ = jaccard_join.shingles(*column_bytes(pa.array(texts)))
    assert np.bincount(t, minlength=5).tolist() == [len(word_sets(x)) for x in texts]


def test_repeats_nulls_and_empty(spark):
    df = spark.createDataFrame([(1, "a b c d e f"), (1, "a b c d e f"), (None, "a b c"), (2, None)], "doc_id long, text string")
    assert sorted(map(str, (tuple(r) for r in jaccard_join.join(df).collect()))) == sorted(map(str, [(1, 2, 1), (1, 2, 1), (None, 1, None), (2, 0, 2)]))
    kept = jaccard_join.one_of_each(df)
    assert kept.columns == df.columns and sorted(str(r["doc_id"]) for r in kept.collect()) == ["1", "2", "None"]
    assert jaccard_join.join(df.where("doc_id > 9")).count() == 0
