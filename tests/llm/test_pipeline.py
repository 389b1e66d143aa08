"""The quality classifier, URL filter and pipeline."""

import numpy as np
import public_tokenizers as P
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from vecset.llm import quality, url_filter
from vecset.llm.queries import RULES
from vecset.llm.tokens import load_json

from .test_jaccard import brute as join_brute
from .test_suffix import brute as cut_brute

SF = "/root/testdata/sf0.001"


def test_ranker_orders_pairs():
    draw = np.random.default_rng(1)
    good = draw.normal(1, 1, size=(200, quality.WIDTH)).astype(np.float32) * 0.1
    bad = draw.normal(0, 1, size=(50, quality.WIDTH)).astype(np.float32) * 0.1
    model = quality.fit_pairs(good, bad, 0.2)
    assert model.score(good).mean() > 0.7 > 0.3 > model.score(bad).mean()


def test_quality_held_out(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    out = quality.score(docs.select("doc_id", "text"), quality.fit(docs, labels)).where(quality.held_out("doc_id"))
    rows = out.join(labels, "doc_id").select("quality", "score").collect()
    assert len(rows) > 50 and np.mean([(r["score"] >= 0.5) == r["quality"] for r in rows]) > 0.95


def test_quality_cases(spark):
    docs = spark.createDataFrame([(1, None, 0.1), (2, "", 0.2), (2, "", 0.2), (None, "x" * 100000, 0.3)], "doc_id long, text string, score_ double")
    labels = spark.createDataFrame([(1, None), (2, 1)], "doc_id long, quality int")
    got = quality.score(docs, quality.fit(docs, labels)).collect()
    assert len(got) == 4 and all(r["score"] == 0.5 for r in got)
    assert quality.score(docs.where("doc_id = 9"), quality.fit(docs, labels)).count() == 0


def url_brute(url):
    host = path = ""
    if url and "://" in url:
        rest = url.split("://", 1)[1]
        cut = min((rest.find(c) for c in "/?#" if c in rest), default=len(rest))
        host, path = rest[:cut], rest[cut:]
        host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
        path = path[: min((path.find(c) for c in "?#" if c in path), default=len(path))]
    best = (None, None)
    for said, rule in sorted(RULES, key=lambda r: len(r[1])):
        h, _, p = rule.partition("/")
        if (host == h or host.endswith("." + h)) and path.startswith("/" + p):
            best = (rule, said)
    return host, path, *best


def test_url_parts_and_rules(spark):
    urls = [None, "", "no scheme", "http://A.Example.NET/en/1?x=/y", "https://example.net", "ftp://x.net#f/", "http://www.example.com/de/7/", "://q.org/fr/", "http://É.ORG/fr/a#b", "http://badnet/", "a://b://c.net/d", "http://h.org/fr?/", "http://x.example.com/a\nb/1"]
    df = spark.createDataFrame([(i, u, "p") for i, u in enumerate(urls)] + [(3, urls[3], "p")], "page_id long, url string, path string")
    got = url_filter.judge(df, RULES).collect()
    assert len(got) == len(urls) + 1
    for r in got:
        host, path, rule, said = url_brute(urls[r["page_id"]])
        assert (r["host"], r["path"], r["rule"], r["verdict"]) == (host, path, rule, said or "allow")


def test_url_templates(spark):
    rows = [(i, f"http://h.com/{'spam' if i % 2 else 'news'}/{'abc'[i % 3]}{i}x/p{i}", int(i % 2 == 1)) for i in range(400)]
    rows += [(1000 + i, f"http://h.com/t/{chr(97 + i % 26)}{chr(97 + i // 26)}.html", 0) for i in range(200)]
    df = spark.createDataFrame(rows, "page_id long, url string, bad int")
    got = {r["page_id"]: r for r in url_filter.judge(df.select("page_id", "url"), RULES, df.select("page_id", "bad").where("page_id % 3 = 0")).collect()}
    assert {got[i]["verdict"] for i in range(1, 400, 2)} == {"block"} and {got[i]["verdict"] for i in range(0, 400, 2)} == {"allow"}
    assert len({got[1000 + i]["template"] for i in range(200)}) == 1
    assert url_filter.judge(df.where("page_id < 0").select("page_id", "url"), RULES).count() == 0


def test_url_templates_of_deep_paths(spark):
    """Good and bad branches part at the fifth segment."""
    df = spark.createDataFrame([(i, f"http://h.com/a/b/c/d/{'spam' if i % 2 else 'news'}/p{i}", i % 2) for i in range(200)], "page_id long, url string, bad int")
    got = {r["page_id"]: r["verdict"] for r in url_filter.judge(df.select("page_id", "url"), RULES, df.select("page_id", "bad")).collect()}
    assert got == {i: "block" if i % 2 else "allow" for i in range(200)}


@pytest.fixture(scope="module")
def stages(spark):
    docs, out = spark.read.parquet(f"{SF}/documents.parquet"), []
    for _, stage in corpus_pipeline.STAGES:
        after = stage(spark, docs, SF).cache()
        out.append((docs, after))
        docs = after
    return out


def test_stages_against_brute_force(stages):
    names = stages[0][0].columns
    assert all(after.columns == names for _, after in stages[:-1])
    kept = {r["doc_id"] for r in stages[0][1].collect()}
    assert kept and kept < {r["doc_id"] for r in stages[0][0].collect()}
    before = [(r["doc_id"], r["text"]) for r in stages[1][0].collect()]
    assert {r["doc_id"] for r in stages[1][1].collect()} == {i for i, (_, low) in join_brute(before).items() if i == low}
    before = {r["doc_id"]: r["text"] for r in stages[2][0].collect()}
    want = dict(zip(before, cut_brute(list(before.values()), 400), strict=True))
    after = {r["doc_id"]: r for r in stages[2][1].collect()}
    assert after.keys() == before.keys()
    for i, r in after.items():
        n, gone, _, _ = want[i]
        assert (r["text"] == before[i]) == (gone == 0) and r["n_chars"] == len(r["text"])
        assert len(r["text"].replace("\ufffd", "").encode()) <= n - gone
    tokens = load_json(P.path("byte_bpe_50k.json"))
    n = {r["doc_id"]: r["n"] for r in stages[3][1].groupBy("doc_id").agg(F.sum("length").alias("n")).collect()}
    assert n == {i: len(tokens.encode(r["text"], add_special_tokens=False).ids) + 1 for i, r in after.items()}


def test_run(spark, stages):
    got = corpus_pipeline.run(spark, SF)
    assert got.columns == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
    assert got.select("doc_id", "piece", "length", "ids_crc32").exceptAll(stages[3][1].select("doc_id", "piece", "length", "ids_crc32")).count() == 0


def test_quality_learns_from_all_labels(spark):
    """A class of 3,400 documents of which 40 are of another kind: a sample of 3,000 of them may miss what tells these from good ones."""
    draw = np.random.default_rng(5)
    text = lambda letters: "".join(draw.choice(list(letters), 60))
    rows = [(i, text("abcdefgh") if i % 85 else text("uvwxyz"), 0) for i in range(3400)] + [(i, text("ijklmnop"), 1) for i in range(3400, 4000)]
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string").repartition(5)
    labels = spark.createDataFrame([(r[0], r[2]) for r in rows], "doc_id long, quality int")
    seen, fitted = [], quality._fitted
    quality._fitted = lambda run, *more: (seen.extend(run("moments")), fitted(run, *more))[1]
    try:
        model = quality.fit(docs, labels)
    finally:
        quality._fitted = fitted
    own = labels.where(~quality.held_out("doc_id")).groupBy("quality").count().collect()
    assert sum(s[0] for s in seen).tolist() == [r["count"] for r in sorted(own)]
    got = quality.score(docs, model).join(labels, "doc_id").collect()
    assert np.mean([(r["score"] >= 0.5) == r["quality"] for r in got]) > 0.99
    texts = [r[1].encode() for r in rows if r[0] % 3 == 0]
    x = quality.features(np.frombuffer(b"".join(texts), np.uint8), np.arange(len(texts) + 1) * 60)
    y = np.array([r[2] for r in rows if r[0] % 3 == 0])
    one, two = (quality.fit_pairs(x[y == 1][o], x[y == 0], float((y == 0).mean())) for o in (slice(None), slice(None, None, -1)))
    assert np.allclose(one.weights, two.weights, atol=1e-5) and abs(one.threshold - two.threshold) < 1e-4
