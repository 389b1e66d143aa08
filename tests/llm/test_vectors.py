"""Embedding operators against brute force."""

import numpy as np
import pytest

from vecset.llm import vectors as V
from vecset.llm.components import components

SCHEMA = "vec_id long, embedding array<double>, label int, vec string, score int, n double"


@pytest.fixture(scope="module")
def table(spark):
    draw = np.random.default_rng(4)
    x = draw.normal(size=(700, 16))
    x[100:160] = x[100] + draw.normal(size=(60, 16)) * 0.12  # a dense group
    x[200:230] = x[200]  # copies
    x[300:340:2] = x[301:341:2] * 1.5 + draw.normal(size=(20, 16)) * 0.01
    rows = [(i, v.tolist(), None if i % 50 == 7 else i % 3, "a", 1, 0.5) for i, v in enumerate(x)]
    rows += [(1000, None, 1, "a", 1, 0.5), (1001, [0.0] * 16, 1, "a", 1, 0.5), (1002, [float("nan")] * 16, 1, "a", 1, 0.5), (1003, [None] + [1.0] * 15, 1, "a", 1, 0.5), (1020, [], 1, "a", 1, 0.5)]
    return rows, spark.createDataFrame(rows, SCHEMA).repartition(3)


def sound(rows):
    return [r for r in rows if r[1] and all(v is not None and np.isfinite(v) for v in r[1]) and any(r[1])]


def reach(nodes, links):
    low = {v: v for v in nodes}
    while True:
        was = dict(low)
        for a, b in links:
            low[a] = low[b] = min(low[a], low[b])
        if was == low:
            return low


def test_components(spark):
    draw = np.random.default_rng(2)
    links = [(int(a), int(b)) for a, b in draw.integers(0, 400, size=(260, 2))] + [(1000 + i, 1001 + i) for i in range(40)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(links, "a long, b long").repartition(5)).collect()}
    want = reach({v for p in links if p[0] != p[1] for v in p}, links)
    assert got == want


@pytest.mark.parametrize("shard_rows", [8192, 60])
def test_near_duplicates(table, shard_rows):
    rows, df = table
    got = {r["vec_id"]: r for r in V.near_duplicates(df, 0.98, shard_rows=shard_rows).collect()}
    ok = [r for r in sound(rows) if r[2] is not None]
    x = np.array([r[1] for r in ok])
    x /= np.linalg.norm(x, axis=1)[:, None]
    i, j = np.nonzero(np.triu((x @ x.T >= 0.98), 1) & (np.array([r[2] for r in ok])[:, None] == np.array([r[2] for r in ok])[None]))
    links = [(ok[a][0], ok[b][0]) for a, b in zip(i, j, strict=True)]
    low = reach([r[0] for r in rows], links)
    degree = {r[0]: 0 for r in rows}
    for a, b in links:
        degree[a] += 1
        degree[b] += 1
    assert len(got) == len(rows)
    assert {k: (r["n_links"], r["component_id"], r["kept"]) for k, r in got.items()} == {k: (degree[k], low[k], low[k] == k) for k in low}


@pytest.mark.parametrize("fault", ["no links", "narrow beams"])
def test_audit_without_true_pairs(fault):
    """One near pair, and none of an audited query: a graph that finds nothing must not pass the audit."""
    draw = np.random.default_rng(8)
    x, q = (V._unit(draw.normal(size=(600, 16))) for _ in range(2))
    q[303] = V._unit(x[[77]] + 0.01 * draw.normal(size=16))[0]
    graph = V.Graph(x)
    if fault == "no links":
        for links in graph.links:
            links[:] = -1
    else:
        search = graph.search
        graph.search = lambda q, beam, own=None: search(q, beam, own) if beam >= 64 else (np.full((len(q), beam), -1), np.full((len(q), beam), -3.0, np.float32))
    want = set(zip(*np.nonzero(q @ x.T >= 0.98), strict=True))
    assert want == {(303, 77)} and 303 not in np.linspace(0, 599, 128).astype(int)
    assert set(zip(*V._found(graph, q, None, 0.98, 32, 128, 0.995), strict=True)) == want


def test_nearest(table):
    rows, df = table
    got = {}
    for r in V.nearest(df, df.where("vec_id % 20 = 0"), list_rows=32).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    ok = sound(rows)
    ids, x = np.array([r[0] for r in ok]), np.array([r[1] for r in ok])
    hit = total = 0
    for q in range(0, 700, 20):
        s = (x * x[ids == q][0]).sum(axis=1)
        want = [ids[k] for k in np.lexsort((ids, -s)) if ids[k] != q][:20]
        mine = sorted(got[q])
        assert [r for r, _, _ in mine] == list(range(1, 21))
        assert all(abs(sc - s[ids == v][0]) < 1e-12 for _, v, sc in mine) and mine == sorted(mine, key=lambda m: (-m[2], m[1]))
        hit += len(set(want) & {v for _, v, _ in mine})
        total += 20
    assert hit / total >= 0.9 and set(got) == set(range(0, 700, 20))


def test_empty(spark):
    none = spark.createDataFrame([], SCHEMA)
    assert V.near_duplicates(none).count() == 0 and V.nearest(none, none).count() == 0


def test_nearest_shuffles_no_vectors(table):
    """Lists and queries are written once and dealt to no join; queries in several parts give the same rows."""
    _, df = table
    asked = df.where("vec_id % 20 = 0")
    whole, parts = V.nearest(df, asked, k=5, list_rows=40), V.nearest(df, asked, k=5, list_rows=40, at_once=7)
    plan = whole._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Repartition" not in plan
    assert sorted(map(tuple, whole.collect())) == sorted(map(tuple, parts.collect()))
