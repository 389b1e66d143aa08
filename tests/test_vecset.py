"""The engine against DuckDB, brute force and its own invariants. FULL=1 runs every key that has an oracle."""

import itertools
import os
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from tests.compare import connect, difference
from vecset.functions import distance as D
from vecset.functions import transport
from vecset.operators import clusters as C
from vecset.operators import exact as X
from vecset.operators import graph as G
from vecset.operators import iterate
from vecset.operators import metrics as E
from vecset.operators import search as S
from vecset.plans import limits
from vecset.registry import ORACLES, QUERIES
from vecset.streaming import windows as W

SF = "/root/testdata/sf0.001"
SOME = ["chamfer_pairs", "exact_topk", "emd_m3", "assign_fine", "cluster_profile", "cutoff_labels", "bridge_merge", "superstep_once", "posting_topk", "lsh_sketch_topk", "fde_topk", "pq_adc_topk", "mrr_at_k", "metrics_cube", "session_sets"]


@pytest.mark.parametrize("name", sorted(ORACLES) if os.environ.get("FULL") else SOME)
def test_oracle(spark, name):
    assert difference(spark, connect(SF), QUERIES[name], ORACLES[name], SF) is None


def test_registry():
    assert set(entry.oracle_sql()) <= set(entry.queries()) and len(ORACLES) > 100


@pytest.mark.parametrize("m", [1, 2, 3, 4, 5])
def test_transport_is_the_best_permutation(m):
    draw = np.random.default_rng(m)
    for _ in range(20):
        cost = draw.random((m, m))
        best = min(sum(cost[i, p[i]] for i in range(m)) for p in itertools.permutations(range(m))) / m
        got, plan = transport.emd_plan(cost)
        assert abs(got - best) < 1e-9 and np.allclose(plan.sum(axis=0), 1 / m) and np.allclose(plan.sum(axis=1), 1 / m)
        assert transport.emd(cost, solver="relaxed") <= got + 1e-12 <= transport.emd(cost, solver="greedy") + 1e-9
        assert transport.emd(cost, solver="sinkhorn") >= got - 1e-9


def test_transport_of_bags_equals_that_of_copies():
    draw = np.random.default_rng(5)
    cost, a, b = draw.random((3, 2)), np.array([1, 3, 2]), np.array([2, 1])
    full = np.repeat(np.repeat(cost, a, axis=0), b, axis=1)
    assert abs(transport.emd(cost, a, b) - transport.emd(full)) < 1e-9
    assert abs(transport.emd(cost, a, b) - transport.emd(cost.T, b, a)) < 1e-9


def test_bounds_and_triangle():
    draw = np.random.default_rng(6)
    unit = lambda n: (x := draw.normal(size=(n, 6))) / np.linalg.norm(x, axis=1)[:, None]
    dist = lambda x, y: np.linalg.norm(x[:, None] - y[None], axis=2)
    above = 0
    for _ in range(50):
        x, y, z = unit(4), unit(3), unit(5)
        e = transport.emd(dist(x, y))
        assert dist(x, y).min(axis=1).mean() <= e + 1e-9 and transport.mean_vector_bound(x, y) <= e + 1e-9
        assert transport.emd(dist(x, z)) <= e + transport.emd(dist(y, z)) + 1e-9
        above += dist(x, y).min(axis=1).sum() > e
    assert above == 50  # the sum form is no lower bound
    a = np.array([[1, 0], [np.sqrt(0.5), np.sqrt(0.5)], [0, 1]])
    assert (1 - a @ a.T)[0, 2] > (1 - a @ a.T)[0, 1] + (1 - a @ a.T)[1, 2]  # cosine is no metric


def test_code_sizes():
    assert [C.codebook_sizes(n)[0] for n in (597_000_000, 339_000_000, 14_000_000, 9_700_000)] == [262144, 262144, 32768, 32768]


@pytest.fixture(scope="module")
def index(spark):
    from vecset.queries.graph_queries import Index

    return Index(spark, SF)


def test_graph_invariants(index):
    rows = index.adj.collect()
    assert all(r["src"] != r["dst"] for r in rows)
    own = {}
    for r in index.mem.collect():
        own.setdefault(r["set_id"], set()).add(r["cluster_id"])
    cand = {}
    for r in G.mirrored(index.cand).collect():
        cand.setdefault(r["src"], []).append(r["dst"])
    kept = {}
    for r in rows:
        kept.setdefault(r["src"], []).append(r["dst"])
    for v, near in kept.items():
        assert len(near) == len(set(near)) <= 6
        for c in own[v]:
            if any(c in own[x] for x in cand[v]):
                assert any(c in own[x] for x in near)
    assert index.adj.exceptAll(G.merge_bridges(index.cand.repartition(7), index.mem, 6)).count() == 0


def test_engines_agree_without_limit(index):
    """ef above all sets: the kernel returns what reachability gives. (test_search_example runs the supersteps.)"""
    routed, entries = index.routing(8)
    want = S.search_exhaustive(entries, index.adj, index.mem, routed, index.query_codes, index.codes, index.code_sims(), 5).select("query_id", "set_id", "score")
    kernel = index.kernel(k=5, ef=1000, t=8).select("query_id", "set_id", "score")
    assert want.exceptAll(kernel).count() == 0 and kernel.exceptAll(want).count() == 0


def test_search_frontier_runs_to_its_end(spark, monkeypatch):
    """The registered key on a chain of eight sets in two clusters, which takes more than four rounds: with ef above all sets the
    supersteps return what reachability gives."""
    from vecset.queries import graph_queries

    class Chain:
        def __init__(self, *_):
            links = [(a, a + 1) for a in range(7)]
            self.adj = spark.createDataFrame([p for a, b in links for p in ((a, b), (b, a))], "src long, dst long")
            self.mem = spark.createDataFrame([(s, int(s > 5)) for s in range(8)] + [(5, 1)], "set_id long, cluster_id int")
            self.codes = spark.createDataFrame([(s, s) for s in range(8)], "set_id long, code int")
            self.query_codes = spark.createDataFrame([(1, 0, 0), (1, 1, 7), (2, 0, 5)], "query_id long, vec_no int, code int")

        def code_sims(self):
            return spark.createDataFrame([(a, b, (a * 5 + b * 11) % 17 + b) for a in (0, 5, 7) for b in range(8)], "a int, b int, s long")

        def routing(self, t=1):
            return spark.createDataFrame([(1, 0), (1, 1), (2, 0)], "query_id long, cluster_id int"), spark.createDataFrame([(1, 0, 0), (2, 0, 0)], "query_id long, cluster_id int, set_id long")

    monkeypatch.setattr(graph_queries, "Index", Chain)
    f = Chain()
    routed, entries = f.routing()
    want = S.search_exhaustive(entries, f.adj, f.mem, routed, f.query_codes, f.codes, f.code_sims(), 10)
    rows = lambda d: sorted(map(tuple, d.select("query_id", "set_id", "score", "rnk").collect()))
    got = rows(QUERIES["search_frontier"](spark, SF))
    assert got == rows(want) and {q: sum(r[0] == q for r in got) for q in (1, 2)} == {1: 8, 2: 6}


@pytest.mark.parametrize("ef", [3])
def test_search_frontier_follows_the_supersteps(index, ef):
    """One row a query, or every part a table: the same sets and scores, ties and full beams included."""
    routed, entries = index.routing(2)
    parts = entries, index.adj, index.mem, routed.where("query_id < 60"), index.query_codes.where("query_id < 60"), index.codes, index.code_sims()
    rows = lambda d: sorted(map(tuple, d.select("query_id", "set_id", "score", "rnk").collect()))
    got = rows(S.search_frontier(*parts, 10, ef))
    assert got and got == rows(S.search_by_joins(*parts, 10, ef))


def test_probing_all_postings_is_exact(index):
    from vecset.operators import baselines as B

    q, v = index.queries, index.vectors
    got = B.refine(B.posting_candidates(q, index.coded, index.fine, 64, -(10**9), 10**6), q, v, 5).select("query_id", "set_id", "score")
    assert X.exact_topk(q, v, 5).select("query_id", "set_id", "score").exceptAll(got).count() == 0


def test_search_example(spark):
    """Each customer's walk again in plain Python, on the orders of the table."""
    chains = {}
    for r in sorted(spark.read.parquet(f"{SF}/orders.parquet").collect(), key=lambda r: (r["o_orderdate"], r["o_orderkey"])):
        chains.setdefault(r["o_custkey"], {}).setdefault(r["o_orderstatus"], []).append((r["o_orderkey"], int(float(r["o_totalprice"]) + 0.5)))
    want = []
    for customer, by in chains.items():
        score = {k: v for status in "FO" for k, v in by.get(status, [])}
        links = {(x[i][0], x[i + 1][0]) for x in by.values() for i in range(len(x) - 1)}
        if len(by.get("F", [])) > 1 and by.get("O"):
            links.add((by["F"][1][0], by["O"][-1][0]))
        links |= {(b, a) for a, b in links}
        state = {by[s][0][0]: (path, 0) for path, s in enumerate("FO") if s in by}
        for _ in range(5):
            place = sorted(state, key=lambda s: (-score[s], s))
            picked = [next((s for s in place if state[s] == (path, 0)), None) for path in (0, 1)]
            picked = [s for s in picked if s is not None and (len(place) < 2 or score[s] >= score[place[1]])]
            fresh = {}
            for s in picked:
                for a, b in links:
                    if a == s and b in score and b not in state:
                        fresh[b] = min(fresh.get(b, 9), state[s][0])
            state = {s: (p, 1 if s in picked else e) for s, (p, e) in state.items()} | {s: (p, 0) for s, p in fresh.items()}
            place = sorted(state, key=lambda s: (-score[s], s))
            state = {s: state[s] for i, s in enumerate(place) if i < 2 or state[s][1]}
        want += [(customer, s, score[s], i + 1) for i, s in enumerate(sorted(state, key=lambda s: (-score[s], s))[:2])]
    got = [tuple(r) for r in QUERIES["search_example"](spark, SF).select("query_id", "set_id", "score", "rnk").collect()]
    assert len(want) > 100 and sorted(got) == sorted(want)


def test_supersteps_by_hand(spark):
    """A toy graph of eight sets, ef = 2: entry points lie in two clusters, a shortcut (1-6) leads from one to the other."""
    links = [(0, 1), (1, 2), (3, 4), (4, 5), (1, 6), (6, 7)]
    edges = spark.createDataFrame([p for a, b in links for p in ((a, b), (b, a))], "src long, dst long")
    allowed = spark.createDataFrame([(9, s) for s in (0, 1, 3, 4, 6, 7)], "query_id long, set_id long")
    scores = spark.createDataFrame([(9, s, v) for s, v in enumerate([10, 30, 99, 5, 20, 99, 60, 80])], "query_id long, set_id long, score long")
    state = spark.createDataFrame([(9, 0, 0, 10, 0), (9, 1, 3, 5, 0)], "query_id long, path int, set_id long, score long, expanded int")
    for _ in range(5):
        state = iterate.cut(S.superstep(state, edges, allowed, scores, 2))
    got = X.top_k(state.select("query_id", "set_id", "score"), 2).orderBy("rnk").collect()
    assert [(r["set_id"], r["score"]) for r in got] == [(7, 80), (6, 60)]


def test_measures_by_hand(spark):
    hits = spark.createDataFrame([(1, 5, 1), (1, 6, 2), (2, 9, 1)], "query_id long, set_id long, rnk int")
    rel = spark.createDataFrame([(1, 6), (1, 7), (2, 1), (3, 4)], "query_id long, set_id long")
    value = lambda f: f(hits, rel, 10).first()["value"]
    assert (value(E.recall_at_k), value(E.mrr_at_k), value(E.success_at_k)) == (round(0.5 / 3, 6), round(0.5 / 3, 6), round(1 / 3, 6))


def test_stream_equals_batch(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.orderBy("ts").repartition(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    name = f"sets{int(time.time())}"
    q = W.stream_tumbling(stream).writeStream.format("memory").outputMode("complete").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = spark.table(name).agg(F.count("*"), F.sum("n")).first()
    want = W.tumbling(events, 604_800).agg(F.count("*"), F.sum("n")).first()
    assert tuple(got) == tuple(want)


def test_late_events_are_dropped(spark, tmp_path):
    rows = [(1, "2024-01-10 00:00:00", 1), (2, "2024-03-01 00:00:00", 1)]
    frame = lambda r: spark.createDataFrame(r, "event_id long, ts string, user_id long").withColumn("ts", F.to_timestamp("ts"))
    for k, r in enumerate([rows, [(3, "2024-01-01 00:00:00", 1), (4, "2024-06-01 00:00:00", 1)], [(5, "2024-09-01 00:00:00", 1)]]):
        frame(r).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        stream = spark.readStream.schema(frame(r).schema).parquet(str(tmp_path / "in"))
        q = W.stream_sessions(stream).writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "cp")).outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination(120)
        assert k >= 0
    starts = {str(r["w"]["start"])[:10] for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert "2024-01-10" in starts and "2024-01-01" not in starts


def test_plans(spark):
    text = QUERIES["scan_pruned"](spark, SF)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(lang)" in text and "html" not in text
    text = QUERIES["topk_group"](spark, SF)._jdf.queryExecution().toString()
    assert "WindowGroupLimit" in text
    with pytest.raises(limits.TooLarge):
        limits.driver_table(spark.range(100), most_rows=10)


def test_components_and_nested_score(spark, index):
    edges = spark.createDataFrame([(1, 2), (2, 3), (7, 8)], "src long, dst long")
    got = {r["set_id"]: r["component"] for r in iterate.components(edges, spark.range(10).withColumnRenamed("id", "set_id")).collect()}
    assert got == {0: 0, 1: 1, 2: 1, 3: 1, 4: 4, 5: 5, 6: 6, 7: 7, 8: 7, 9: 9}
    one = spark.createDataFrame([([[1, 0], [0, 1]], [[2, 1], [0, 5]])], "q array<array<long>>, p array<array<long>>")
    assert one.select(D.chamfer_nested("q", "p").alias("s")).first()["s"] == 7


def _drawn(spark, sets, seed):
    """Small whole numbers, so that scores tie; sets of one to three vectors."""
    draw = np.random.default_rng(seed)
    return [(s, j, draw.integers(-2, 3, 4).tolist()) for s in range(sets) for j in range(1 + s % 3)]


@pytest.mark.parametrize("ground", ["cosine", "l2"])
def test_exact_topk_in_blocks(spark, monkeypatch, ground):
    """However few products a task may hold, every set asks every set; ties go to the smaller one."""
    from vecset.operators import exact

    monkeypatch.setattr(exact, "CELLS", 64)
    rows = _drawn(spark, 90, 3)
    v = spark.createDataFrame(rows, "set_id long, vec_no int, v array<long>").repartition(3)
    x = {s: np.array([r[2] for r in rows if r[0] == s]) for s in range(90)}
    near = lambda a, b: a @ b.T if ground == "cosine" else -((a[:, None] - b[None]) ** 2).sum(axis=2)
    want = {q: sorted((-int(near(x[q], x[s]).max(axis=1).sum()), s) for s in x)[:7] for q in x}
    got = {}
    for r in exact.exact_topk(v.withColumnRenamed("set_id", "query_id"), v, 7, ground).orderBy("query_id", "rnk").collect():
        got.setdefault(r["query_id"], []).append((-r["score"], r["set_id"]))
    assert got == want


@pytest.mark.parametrize("odd", [None, [1, None, 2, 3]])
def test_all_scores(spark, odd):
    from vecset.functions import distance as D
    from vecset.operators.exact import all_scores

    v = spark.createDataFrame([*_drawn(spark, 40, 5), (41, 0, odd or [1, 1, 1, 1])], "set_id long, vec_no int, v array<long>")
    q = v.where("set_id % 10 = 0").withColumnRenamed("set_id", "query_id")
    for mean in (False, True):
        got = all_scores(q, v, "cosine", mean)
        assert ("CartesianProduct" in got._jdf.queryExecution().toString() or "NestedLoop" in got._jdf.queryExecution().toString()) == (odd is not None)
        assert sorted(map(str, got.collect())) == sorted(map(str, D.chamfer(D.pair_nearness(q, v), "mean" if mean else "sum").collect()))


def test_matchings_are_transport(spark):
    """With equal weights the cheapest matching is the earth mover's distance; codes stand for their centres, also repeated ones."""
    from vecset.functions import transport
    from vecset.operators.exact import matched

    draw = np.random.default_rng(6)
    centers = draw.integers(-900, 900, size=(5, 8))
    codes = draw.integers(0, 5, size=(23, 4))
    plain = matched(spark.createDataFrame([(i, centers[c].tolist()) for i, c in enumerate(codes)], "set_id long, vecs array<array<long>>"), 4, "emd").collect()
    coded = matched(spark.createDataFrame([(i, c.tolist()) for i, c in enumerate(codes)], "set_id long, vecs array<int>").repartition(3), 4, "emd", centers).collect()
    want = {(a, b): round(transport.emd(1_000_000.0 - centers[codes[a]] @ centers[codes[b]].T), 6) for a in (0, 10, 20) for b in range(a + 1, 23)}
    assert {(r["a"], r["b"]): r["emd"] for r in plain} == pytest.approx(want) and sorted(plain) == sorted(coded)


@pytest.mark.parametrize("name", ["chamfer_example", "membership_example", "codebook_size", "speedup_at_quality"])
def test_examples_read_a_table(spark, name):
    assert "parquet" in QUERIES[name](spark, SF)._jdf.queryExecution().executedPlan().toString().lower()
    assert difference(spark, connect(SF), QUERIES[name], ORACLES[name], SF) is None
