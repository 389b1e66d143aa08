"""The built index, its search, the baselines and the derived tasks: invariants and brute force."""

import itertools
import os
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecset.functions import sql as Q
from vecset.functions import transport
from vecset.operators import baselines as B
from vecset.operators import graph as G
from vecset.operators import index as I
from vecset.operators import search as S
from vecset.operators import single
from vecset.operators.contain import contained
from vecset.operators.exact import exact_topk, top_k
from vecset.operators.iterate import shared
from vecset.operators.near import near_sets, near_token_sets
from vecset.operators.search import Runs
from vecset.queries import study_queries
from vecset.sources.worksets import subset, work_set

SF = "/root/testdata/sf0.001"
CONFIG = I.IndexConfig(k1=64, k2=16, degree=8, t=1, iterations=3, solver="sinkhorn", sample=100)
slow = pytest.mark.skipif(not os.environ.get("FULL"), reason="FULL=1 runs it: many small jobs")
rows = lambda df, *cols: sorted(map(tuple, df.select(*cols).collect()))


@pytest.fixture(scope="module")
def work(spark):
    return work_set(spark, SF, "w1")


@pytest.fixture(scope="module")
def books(work):
    return I.fit_codebooks(work.fit, CONFIG)


@pytest.fixture(scope="module")
def index(work, books):
    return I.build_index(work.vectors, CONFIG, work.train_queries, work.train, books)


def test_parts_fit_together(work, index):
    norms = [np.linalg.norm(r["center"]) for r in index.fine.collect()]
    assert len(norms) <= 64 and all(990 < n < 1010 for n in norms)
    sets = {r["set_id"] for r in work.vectors.select("set_id").distinct().collect()}
    assert {r["set_id"] for r in index.membership.collect()} == sets
    edges = index.edges.collect()
    own = [(r["src"], r["dst"]) for r in edges if r["kind"] != "shortcut"]
    cuts = [(r["src"], r["dst"]) for r in edges if r["kind"] == "shortcut"]
    assert len(set(own)) == len(own) and not set(own) & set(cuts) and all(a != b for a, b in own + cuts)
    assert cuts and {(b, a) for a, b in cuts} == set(cuts)
    for limit, pairs in ((8, own), (10, own + cuts)):
        assert max(len(list(g)) for _, g in itertools.groupby(sorted(a for a, _ in pairs))) <= limit


def test_sequential_build_gives_the_same_graph(index):
    one = I.local_graphs(index.membership, index.codes, index.fine, CONFIG)
    two = I.local_graphs(index.membership, index.codes, index.fine, replace(CONFIG, build_mode="sequential"))
    assert rows(one, "src", "dst", "via") == rows(two, "src", "dst", "via")


@pytest.mark.parametrize("edge", ["qch", "qemd"])
def test_blocks_lose_no_neighbour(index, edge):
    some = index.membership.where("cluster_id < 4")
    build = lambda n: G.local_edges(some, index.codes, index.fine, 5, edge, solver="sinkhorn", block_sets=n)
    assert rows(build(10**6), "src", "dst", "via") == rows(build(7), "src", "dst", "via")


def test_kernel_deals_its_queries_out(work, index):
    """Queries are few bytes; before, Spark put those of a whole work set into one task."""
    hits = index.search(work.queries, 5, 10, engine="kernel")
    assert hits.rdd.getNumPartitions() >= work.queries.sparkSession.sparkContext.defaultParallelism


def test_local_graphs_are_made_once(work, books, monkeypatch):
    """The merge reads the half-edges twice: they come from a table, not from the flows; before, all flows were had twice."""
    plans, real = [], G.merge_bridges
    monkeypatch.setattr(G, "merge_bridges", lambda cand, *more: (plans.append(cand._jdf.queryExecution().toString()), real(cand, *more))[1])
    built = I.build_index(work.vectors, replace(CONFIG, shortcuts=False), codebooks=books)
    assert built.edges.count() and len(plans) == 1 and "InArrow" not in plans[0]


def test_routes_need_no_row_for_every_cluster(work, index):
    """Each vector's t best clusters come out of the product; before, a row for each vector and cluster did."""
    for t in (1, 3):
        want = S.query_clusters(S.centroid_scores(work.queries, index.coarse), t)
        assert rows(index.route(work.queries, t), "query_id", "cluster_id") == rows(want, "query_id", "cluster_id")
    assert S.centroid_scores(work.queries, index.coarse, 3).count() == 3 * work.queries.count()


@slow
def test_engines_agree(work, index):
    """With a beam above all sets both engines return all that can be reached; with a finite one, what either finds is scored alike."""
    few = work.queries.join(work.qrels.select("query_id").distinct().orderBy("query_id").limit(2), "query_id", "left_semi")
    for ef in (10**6, 6):
        kernel, frontier = (rows(index.search(few, 5, ef, engine=e), "query_id", "set_id", "score") for e in ("kernel", "frontier"))
        if ef > 6:
            assert kernel == frontier
        else:
            score = {r[:2]: r[2] for r in frontier}
            assert len({r[0] for r in kernel}) == len({r[0] for r in frontier}) and all(score.get(r[:2], r[2]) == r[2] for r in kernel)


def test_guided_search_scores_a_part(work, index):
    n = work.vectors.select("set_id").distinct().count()
    hits = index.search(work.queries, 10, 20)
    assert hits.groupBy("query_id").agg(F.max("scored").alias("s")).agg(F.avg("s")).first()[0] < n / 2
    free = index.search(work.queries, 10, 20, guard=False)
    assert free.agg(F.max("guarded")).first()[0] == 0 and hits.agg(F.max("guarded")).first()[0] > 0


def test_more_codes_than_rows_of_a_driver_table_go_by_the_kernel(work, index, monkeypatch):
    """The documents of 0.1 GB have over two million codes; the supersteps are slow there and count no scored sets."""
    from vecset.plans import limits

    n = index.codes.agg(F.count("*").alias("codes"), F.countDistinct("set_id").alias("sets")).first()
    monkeypatch.setattr(limits, "MOST_ROWS", n["sets"])
    assert n["codes"] > n["sets"]
    hits = index.search(work.queries, 5, 10)
    assert {"scored", "hops", "guarded"} <= set(hits.columns)
    monkeypatch.undo()
    assert rows(hits, "query_id", "set_id", "rnk") == rows(index.search(work.queries, 5, 10, engine="kernel"), "query_id", "set_id", "rnk")


def test_mixed_vectors_are_the_context_vectors(spark, monkeypatch):
    """The array steps give what the joins give, gaps and tokens without a vector included; both ways stand behind one name."""
    from vecset.plans import limits
    from vecset.sources import tables as T

    def refuse(df):
        raise limits.TooLarge

    vocab = T.vocabulary(spark, SF).where("vec_id % 7 <> 3")
    docs = T.read_table(spark, SF, "documents", ["doc_id", "text"])
    ids = T.token_sets(docs, "doc_id", "text", 500, 24).where("vec_no % 5 <> 2").cache()
    fast = T.mixed_vectors(ids, vocab)
    assert "MapInArrow" in fast._jdf.queryExecution().toString()
    got = rows(fast, "set_id", "vec_no", "v")
    monkeypatch.setattr(T, "driver_table", refuse)
    slow_way = T.mixed_vectors(ids, vocab)
    assert fast.dtypes == slow_way.dtypes and got == rows(slow_way, "set_id", "vec_no", "v") and len(got) > 1000
    assert T.mixed_vectors(ids.where("set_id < 0"), vocab).count() == 0


def test_packed_runs_are_the_runs(spark):
    pairs = [(5, 2), (1, 9), (5, 1), (5, 2), (3, 4), (1, 7)]
    df = spark.createDataFrame(pairs, "k long, v int")
    one, two = Runs(df.distinct().toArrow(), "k", "v"), Runs.packed(df, "k", "v")
    assert all(one[k].tolist() == two[k].tolist() for k in (1, 2, 3, 5)) and [x.tolist() for x in one.all([5, 1])] == [x.tolist() for x in two.all([5, 1])]
    assert Runs.packed(df.where("k > 9"), "k", "v")[1].tolist() == []


def test_written_index_is_the_index(spark, work, index):
    path = shared(spark, "t")
    I.write_index(index, path)
    back = I.read_index(spark, path, CONFIG)
    assert rows(back.search(work.queries, 5, 30), "query_id", "set_id", "rnk") == rows(index.search(work.queries, 5, 30), "query_id", "set_id", "rnk")
    size = {r["part"]: r["bytes"] for r in I.index_size(spark, path).collect()}
    assert set(size) == set(I.PARTS) and all(v > 0 for v in size.values()) and "v" not in back.codes.columns


def test_inserted_sets_are_found(work, books):
    late = work.train.orderBy("set_id").limit(12).select("set_id")
    old = I.build_index(work.vectors.join(late, "set_id", "left_anti"), replace(CONFIG, cutoff="fixed", shortcuts=False), None, None, books)
    new = work.vectors.join(late, "set_id", "left_semi")
    grown = I.insert_sets(old, new)
    asked = new.withColumnRenamed("set_id", "query_id")
    hits = grown.topk(asked, work.vectors, 1, 10**6, 20)
    assert sum(r["query_id"] == r["set_id"] for r in hits.collect()) >= 10


@slow
def test_every_switch_of_the_ablation_changes_something(spark, work, monkeypatch):
    part = subset(work, 2)
    monkeypatch.setattr(study_queries, "CONFIG", replace(CONFIG, k1=32, k2=8, iterations=2))
    monkeypatch.setattr(study_queries, "work_set", lambda *_: part)
    out, made = study_queries.ablation(spark, SF, "w1", (10,))
    full = made["full"]
    kinds = lambda i: {r[0] for r in i.edges.groupBy("kind").count().collect()}
    assert kinds(full) == {"bridge", "near", "shortcut"} and kinds(made["no_bridges"]) == {"near", "shortcut"} and kinds(made["no_shortcuts"]) == {"bridge", "near"} and kinds(made["all_off"]) == {"near"}
    assert made["fixed_three"].membership.count() > full.membership.count() and made["one_queue"] is full
    pairs = lambda i: set(rows(i.edges.where("kind <> 'shortcut'"), "src", "dst"))
    assert pairs(made["no_transport_edges"]) != pairs(full)
    cost = {(r[2], r[5]): r[6] for r in out}
    assert cost["one_queue", "scored"] != cost["full", "scored"]
    assert {r[2] for r in out} == set(study_queries.VARIANTS)


def test_entropic_is_close_from_above():
    draw = np.random.default_rng(3)
    cost = draw.random((20, 6, 5))
    a, b = draw.integers(1, 4, size=(20, 6)), draw.integers(0, 3, size=(20, 5))
    b[:, 0] += 1
    got = transport.entropic(cost, a / a.sum(axis=1)[:, None], b / b.sum(axis=1)[:, None])
    for c, x, y, g in zip(cost, a, b, got, strict=True):
        want = transport.emd(c[:, y > 0], x, y[y > 0])
        assert want - 1e-9 <= g <= want * 1.25 + 1e-3


def test_settings_share_what_is_the_same(work, index, monkeypatch):
    """Two settings that differ in the sample of shortcuts, and one that comes twice: one build, and its shortcuts are a build's."""
    made, rows_ = [], []
    bare = replace(index, edges=index.edges.where("kind <> 'shortcut'"), seconds={"graph": 1.0})
    monkeypatch.setattr(study_queries, "work_set", lambda *_: work)
    monkeypatch.setattr(study_queries, "fit_codebooks", lambda *_: (index.fine, index.coarse))
    monkeypatch.setattr(study_queries, "built", lambda w, config, books: made.append(config) or bare)
    monkeypatch.setattr(study_queries, "searched", lambda i, *_: rows_.append(i) or [("w", "w1", "m", "p", 10, "x", 0.0)])
    same = lambda w: w
    study_queries.rebuilt(work.vectors.sparkSession, "", "x", [("a", same, CONFIG), ("b", same, replace(CONFIG, sample=5)), ("c", same, CONFIG)])
    assert len(made) == 1 and not made[0].shortcuts and rows_[2] is rows_[0] and set(rows_[0].seconds) == {"graph", "shortcuts"}
    assert rows(rows_[0].edges, "src", "dst", "kind") == rows(index.edges, "src", "dst", "kind")
    assert rows_[1].config.sample == 5 and rows_[1].edges.count() <= rows_[0].edges.count()


def test_bounds_of_all_sets_at_once():
    """The matrix products give what one set after the other gives, to the last bit where costs are whole numbers."""
    draw = np.random.default_rng(5)
    c = draw.integers(-1000, 1000, size=(40, 6)).astype(np.float64)
    some, others = (G.Bags([draw.integers(0, 40, size=draw.integers(1, 9)) for _ in range(n)]) for n in (300, 70))
    block = G.UNIT - c @ c.T
    for a, b in ((some, others), (some, some), (others, some)):
        for one, (to, back) in zip(a.sets, a.all_one_sided(b, block, 64), strict=True):
            want = b.one_sided(one, block)
            assert (to == want[0]).all() and (back == want[1]).all()


def _sets(draw, n, codes=60):
    c = draw.normal(size=(codes, 12))
    c = np.round(c / np.linalg.norm(c, axis=1)[:, None] * 1000)
    return G.Bags([draw.integers(0, codes, size=draw.integers(1, 30)) for _ in range(n)]), G.UNIT - c @ c.T


def test_overlap_bounds_stand_between_one_sided_ones_and_the_distance():
    bags, block = _sets(np.random.default_rng(8), 12)
    for one, low in zip(bags.sets, bags.all_overlaps(bags, block, 16), strict=True):
        assert (low >= np.maximum(*bags.one_sided(one, block)) - 1e-6).all()
        assert (low <= G._transports(one, bags.sets, block, "exact") + 1e-6).all()


def test_few_flows_find_the_same_neighbours(monkeypatch):
    """The nearest by bounds, in single precision and then in full, are those of all distances in full; few of these are had."""
    bags, block = _sets(np.random.default_rng(9), 600)
    solved, real = [], G.entropic_filled
    monkeypatch.setattr(G, "entropic_filled", lambda cost, *a, **b: (solved.append((cost.dtype, len(cost))), real(cost, *a, **b))[1])
    lows = bags.all_overlaps(bags, block)
    for i, low in zip(range(8), lows):
        if len(bags.sets[i]) <= 2:
            continue
        d = np.concatenate([G._transports(bags.sets[i], [s], block, "sinkhorn") for s in bags.sets])
        d[i] = np.inf
        solved.clear()
        place, got = bags.nearest(bags.sets[i], block, 6, "qemd", np.arange(600), i, "sinkhorn", low)
        assert place.tolist() == np.lexsort((np.arange(600), d))[:6].tolist() and np.allclose(got, d[place], atol=1e-6)
        assert sum(n for kind, n in solved if kind == np.float64) < 30 and sum(n for _, n in solved) < 600


@pytest.mark.parametrize("edge", ["qemd", "qch"])
def test_a_large_cluster_is_the_work_of_many_tasks(work, index, edge):
    """Members of a block that ask in several tasks have the same neighbours; before, a block was one task."""
    some = index.membership.select("set_id", F.lit(0).alias("cluster_id")).distinct()
    build = lambda **how: rows(G.local_edges(some, index.codes, index.fine, 5, edge, solver="sinkhorn", **how), "src", "dst", "via")
    assert build(ask_sets=20) == build() == build(ask_sets=15, block_sets=90)


def test_sets_of_one_code_that_is_too_long_are_near():
    """A code whose square is above one costs less than nothing to itself: no NaN, and copies are the nearest."""
    block = np.array([[-400.0, 900_000.0], [900_000.0, -3.0]])
    for solver in ("exact", "sinkhorn"):
        place, d = G.Bags([np.array([0] * n) for n in (1, 3, 4)] + [np.array([1, 1, 1])]).nearest(np.array([0, 0, 0]), block, 3, "qemd", np.arange(4), -1, solver)
        assert place.tolist() == [0, 1, 2] and d.tolist() == [-400.0] * 3
    assert transport.emd([[-400.0]], solver="sinkhorn") == -400.0
    assert abs(transport.emd([[-400.0, 5.0], [5.0, -300.0]]) + 350) < 1e-9



def test_pair_scores_by_hand(spark):
    q = spark.createDataFrame([(1, 0, [1, 0]), (1, 1, [0, 2]), (2, 0, [1, 1])], "query_id long, vec_no int, v array<long>")
    v = spark.createDataFrame([(7, 0, [3, 1]), (7, 1, [0, 5]), (8, 0, [-1, -1])], "set_id long, vec_no int, v array<long>")
    pairs = spark.createDataFrame([(1, 7), (1, 8), (2, 8), (1, 7)], "query_id long, set_id long")
    assert rows(S.pair_scores(pairs, q, v), "query_id", "set_id", "score") == [(1, 7, 13), (1, 8, -3), (2, 8, -2)]
    assert rows(S.pair_scores(pairs, q, v, least=0), "query_id", "set_id", "score") == [(1, 7, 13), (1, 8, 0), (2, 8, 0)]


def test_folded_graph_and_residuals_find_the_exact_best(work, index):
    """Both are followed by exact scores: what counts is that the best is among the candidates, and that residuals come nearer to the
    exact scores than centres alone."""
    truth = {(r["query_id"], r["set_id"]) for r in exact_topk(work.queries, work.vectors, 1).collect()}
    folded = B.build_folded(work.vectors, 4, 3, 16, 16, 32, 8)
    found = {tuple(r) for r in folded.search(work.queries, 20, 60).select("query_id", "set_id").collect()}
    assert len(truth & found) >= 0.9 * len(truth)
    coded = work.vectors.join(index.codes, ["set_id", "vec_no"])
    cands = B.posting_candidates(work.queries, coded, index.fine, 4, 100_000, 50)
    packed = B.residual_codes(coded, index.fine, study_queries.EDGES)
    close = B.residual_scores(work.queries, cands, packed, index.fine, study_queries.EDGES)
    held = {tuple(r) for r in top_k(close, 20).select("query_id", "set_id").collect()}
    assert len(truth & held) >= 0.9 * len(truth)
    exact = {r[:2]: r[2] for r in rows(S.pair_scores(cands, work.queries, work.vectors), "query_id", "set_id", "score")}
    centres = coded.join(index.fine, "code").select("set_id", "vec_no", F.col("center").alias("v"))
    off = lambda df: np.mean([abs(exact[r[:2]] - r[2]) for r in rows(df, "query_id", "set_id", "score")])
    assert off(close) < off(S.pair_scores(cands, work.queries, centres))


def test_walk_over_centres_finds_the_nearest(work, index):
    graph = single.vector_graph(index.fine.select(F.col("code").cast("long").alias("set_id"), F.col("center").alias("v")), 8)
    walked = set(rows(single.nearest_codes(work.queries, index.fine, graph, 12), "query_id", "q_no", "code"))
    want = rows(B.probe(work.queries, index.fine, 4), "query_id", "q_no", "code")
    assert sum(w in walked for w in want) >= 0.95 * len(want)


def test_pq_topk_makes_no_row_for_a_pair_of_vectors(spark):
    draw = np.random.default_rng(5)
    x, book = draw.integers(-3, 4, (41, 8)), draw.integers(-3, 4, (5, 8))
    names = [2, 3, 7, 8, 20]
    vectors = spark.createDataFrame([(i // 3, i % 3, v.tolist()) for i, v in enumerate(x)], "set_id long, vec_no int, v array<long>")
    codebook = spark.createDataFrame([(c, v.tolist()) for c, v in zip(names, book)], "code int, center array<long>")
    coded = B.pq_encode(vectors, codebook, 4, 8)
    own = [[int(np.argmin(((book[:, 2 * p : 2 * p + 2] - v[2 * p : 2 * p + 2]) ** 2).sum(axis=1))) for p in range(4)] for v in x]
    assert rows(coded, "set_id", "vec_no", "part", "code") == sorted((i // 3, i % 3, p, names[c]) for i, o in enumerate(own) for p, c in enumerate(o))
    found = B.pq_topk(vectors.where("set_id < 4").withColumnRenamed("set_id", "query_id"), coded, codebook, 4, 8, 5)
    seen = np.array([np.concatenate([book[c, 2 * p : 2 * p + 2] for p, c in enumerate(o)]) for o in own])
    want = []
    for q in range(4):
        score = [(-int((x[3 * q : 3 * q + 3] @ seen[3 * s : 3 * s + 3].T).max(axis=1).sum()), s) for s in range(14)]
        want += [(q, s, -v, i + 1) for i, (v, s) in enumerate(sorted(score)[:5])]
    assert rows(found, "query_id", "set_id", "score", "rnk") == sorted(want)
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
    # a vector with a null takes the relational plan
    holed = vectors.unionAll(spark.createDataFrame([(99, 0, [None] * 8)], "set_id long, vec_no int, v array<long>"))
    assert {c for s, _, _, c in rows(B.pq_encode(holed, codebook, 4, 8), "set_id", "vec_no", "part", "code") if s == 99} == {2}


def test_near_token_sets(spark):
    draw = np.random.default_rng(2)
    base = [f"w{i}" for i in range(30)]
    sets = {i: base[: 30 - i % 4] + [f"x{i % 7}"] for i in range(25)} | {100 + i: list(draw.choice(200, 20).astype(str)) for i in range(20)} | {200: [], 201: ["one"], 202: ["one"]}
    df = spark.createDataFrame([(i, t) for i, s in sets.items() for t in s], "set_id long, token string")
    bags = {i: set(s) for i, s in sets.items() if s}
    want = sorted((a, b) for a, b in itertools.combinations(sorted(bags), 2) if 100 * len(bags[a] & bags[b]) >= 90 * max(len(bags[a]), len(bags[b])))
    assert want and rows(near_token_sets(df, 90), "a", "b") == want


@pytest.mark.parametrize("block_sets", [3, 8192])
def test_near_sets_keeps_copies_as_classes(spark, block_sets):
    draw = np.random.default_rng(3)
    base = [f"w{i}" for i in range(40)]
    bags = {i: set(base) for i in range(300)} | {300 + i: set(base) - {base[i]} | {f"y{i % 5}"} for i in range(40)} | {500 + i: set(draw.choice(90, 30).astype(str)) for i in range(20)}
    data = [(i, list(b)) for i, b in bags.items()] + [(900, []), (901, None), (902, ["one"])]
    classes, pairs = near_sets(spark.createDataFrame(data, "set_id long, words array<string>"), 90, block_sets)
    reps = {}
    for i, b in sorted((bags | {902: {"one"}}).items()):
        reps.setdefault(frozenset(b), i)
    assert rows(classes, "set_id", "rep") == sorted((i, reps[frozenset(b)]) for i, b in (bags | {902: {"one"}}).items())
    want = sorted((i, j) for (a, i), (b, j) in itertools.combinations(reps.items(), 2) if 100 * len(a & b) >= 90 * max(len(a), len(b)))
    assert len(want) > 700 and rows(pairs, "a", "b") == want


def test_contained(spark):
    texts = spark.createDataFrame([(1, "abcabc"), (2, None), (3, "xbc"), (4, "")], "id long, text string")
    asked = spark.createDataFrame([(10, "bc"), (11, "abc"), (12, "bc"), (13, ""), (14, None), (15, "q")], "item long, text string")
    assert rows(contained(texts, asked), "query_id", "set_id") == [(10, 1), (10, 3), (11, 1), (12, 1), (12, 3)]
    assert contained(texts, asked.where("item > 99")).count() == 0


def test_stitch(spark):
    parts = spark.createDataFrame([(1, 1), (2, 1), (3, 1), (5, 5), (6, 5), (9, 9)], "set_id long, component long")
    means = spark.createDataFrame([(1, [10, 0]), (2, [0, 10]), (3, [-9, 0]), (5, [1, 9]), (6, [0, -1]), (9, [-5, 0])], "set_id long, v array<long>")
    assert rows(G.stitch(parts, means), "src", "dst", "component") == [(5, 2, 5), (9, 3, 9)]
    assert G.stitch(parts.where("component = 1"), means).count() == 0


def test_sql_functions(spark):
    Q.register(spark)
    one = spark.sql("SELECT vs_chamfer(array(array(1L, 0L), array(0L, 1L)), array(array(2L, 1L), array(0L, 5L))) AS s, vs_emd(array(array(0L, 0L)), array(array(3L, 4L))) AS d").first()
    assert one["s"] == 7 and abs(one["d"] - 5) < 1e-9
    assert spark.sql("SELECT collect_list(token) AS t FROM vs_tokens('An X-y')").first()["t"] == ["an", "x", "y"]


def test_subsets_nest(work):
    small, large = (rows(subset(work, p).vectors.select("set_id").distinct(), "set_id") for p in (4, 2))
    assert set(small) < set(large)
    thin = subset(work, 4, "vectors").vectors.groupBy("set_id").count().agg(F.max("count")).first()[0]
    assert thin == 12


def test_stream_inserts(spark, tmp_path):
    from vecset.streaming.windows import stream_inserts

    spark.createDataFrame([(1, 0, [1, 2]), (2, 0, [3, 4])], "set_id long, vec_no int, v array<long>").write.parquet(str(tmp_path / "in"))
    stream, seen = spark.readStream.schema("set_id long, vec_no int, v array<long>").parquet(str(tmp_path / "in")), []
    query = stream_inserts(stream, lambda batch, epoch: seen.append((epoch, batch.count())), str(tmp_path / "cp"))
    query.awaitTermination(60)
    assert sum(n for _, n in seen) == 2
