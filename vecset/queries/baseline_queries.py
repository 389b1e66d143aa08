"""Keys of the competing methods."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import graph as G
from ..operators.exact import top_k
from .base import K1, PAIRS, Fixture, Registry, chamfer, ctes, dot, sq, top

key = Registry()
QUERIES, ORACLES = key.queries, key.oracles


def probed(n: int) -> str:
    return f"probed AS MATERIALIZED (SELECT query_id, q_no, code, s FROM (SELECT query_id, vec_no AS q_no, code, {dot('v', 'center')} AS s, row_number() OVER (PARTITION BY query_id, vec_no ORDER BY {dot('v', 'center')} DESC, code) AS n FROM qv, fine) WHERE n <= {n})"


POOLED = f"pooled AS (SELECT DISTINCT query_id, set_id FROM (SELECT p.query_id, c.set_id, row_number() OVER (PARTITION BY p.query_id, p.q_no ORDER BY {dot('qv.v', 'c.v')} DESC, c.set_id, c.vec_no) AS n FROM probed p JOIN qv ON qv.query_id = p.query_id AND qv.vec_no = p.q_no JOIN coded c ON c.code = p.code) WHERE n <= 5)"


def _pooled(f):
    return B.pooled_candidates(f.queries, f.vectors, f.coded, f.fine, 5, 8)


@key(f"WITH {ctes()}, {probed(8)}, {POOLED} SELECT * FROM pooled")
def pooled_candidates(spark, folder):
    return _pooled(Fixture(spark, folder))


@key(f"WITH {ctes()}, {probed(8)}, {POOLED} {top('SELECT p.* FROM (' + chamfer(PAIRS) + ') p JOIN pooled USING (query_id, set_id)', 10)}")
def pooled_topk(spark, folder):
    f = Fixture(spark, folder)
    return B.refine(_pooled(f), f.queries, f.vectors, 10)


@key()
def pooled_lsh(spark, folder):
    """Single vectors by the library's random projections."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    f = Fixture(spark, folder)
    x = f.vectors.select("set_id", "vec_no", array_to_vector(F.transform("v", lambda e: e / 1000.0)).alias("x"))
    model = BucketedRandomProjectionLSH(inputCol="x", outputCol="h", bucketLength=1.0, numHashTables=4, seed=42).fit(x)
    q = x.where("set_id % 10 = 0")
    near = model.approxSimilarityJoin(q, x, 1.2, "dist")
    return near.select(F.col("datasetA.set_id").alias("query_id"), F.col("datasetB.set_id").alias("set_id")).distinct()


MEAN = """means AS MATERIALIZED (SELECT set_id, list(x ORDER BY i) AS v FROM (SELECT set_id, i, CAST(round(sum(v[i])::DOUBLE / count(*)) AS BIGINT) AS x FROM vec, range(1, 65) r(i) GROUP BY ALL) GROUP BY ALL)"""


@key(f"WITH {ctes()}, {MEAN} {top('SELECT q.set_id AS query_id, p.set_id, ' + dot('q.v', 'p.v') + ' AS score FROM means q, means p WHERE q.set_id % 10 = 0', 10)}")
def mean_single_topk(spark, folder):
    f = Fixture(spark, folder)
    return B.mean_single(f.queries, f.vectors, 10)


@key(f"""WITH {ctes(2)}, n2 AS (SELECT set_id, list(code ORDER BY code) AS cs FROM coded GROUP BY ALL), d AS MATERIALIZED (SELECT a, b, 1000000 - s AS d FROM sims),
g AS (SELECT p.set_id AS src, q.set_id AS dst, (least(d1.d, d2.d) + least(d3.d, d4.d)) / 2.0 AS dist FROM n2 p JOIN n2 q ON p.set_id <> q.set_id JOIN d d1 ON d1.a = p.cs[1] AND d1.b = q.cs[1] JOIN d d2 ON d2.a = p.cs[1] AND d2.b = q.cs[2] JOIN d d3 ON d3.a = p.cs[2] AND d3.b = q.cs[1] JOIN d d4 ON d4.a = p.cs[2] AND d4.b = q.cs[2])
SELECT src, dst, dist FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS n FROM g) WHERE n <= 4""")
def plain_graph_knn(spark, folder):
    return _plain(Fixture(spark, folder, 2)).select("src", "dst", "dist")


def _plain(f):
    one = f.vectors.select("set_id").distinct().withColumn("cluster_id", F.lit(0))
    return G.local_edges(one, f.coded, f.fine, 4, edge="qch")


@key()
def plain_graph_topk(spark, folder):
    """No clusters, no bridges, one entry, one queue."""
    from ..operators import iterate
    from ..operators import search as S

    f = Fixture(spark, folder, 2)
    edges = iterate.cut(G.trim_degree(G.mirrored(_plain(f)), 24))
    member = f.vectors.select("set_id").distinct().withColumn("cluster_id", F.lit(0))
    q = f.query_codes.groupBy("query_id").agg(F.sort_array(F.collect_list("code")).alias("codes"))
    routed = q.select("query_id", F.lit(0).alias("cluster_id"))
    hits = S.search_kernel(q, routed, S.entry_points(routed, member), edges, member, f.coded, f.fine, 20, 40, multi_path=False, guard=False)
    return S.rerank(hits, f.queries, f.vectors, 10)


@key(f"WITH {ctes()} SELECT DISTINCT code, set_id FROM coded")
def posting_lists(spark, folder):
    return B.posting_lists(Fixture(spark, folder).coded)


LEAST = 100_000
CANDS = f"pl AS (SELECT DISTINCT code, set_id FROM coded), pc AS (SELECT DISTINCT query_id, set_id FROM probed JOIN pl USING (code)), tab AS (SELECT query_id, vec_no AS q_no, code, greatest({dot('v', 'center')} - {LEAST}, 0) AS s FROM qv, fine), posted AS MATERIALIZED ({top(chamfer('SELECT pc.query_id, q_no, pc.set_id, s FROM pc JOIN pl USING (set_id) JOIN tab ON tab.query_id = pc.query_id AND tab.code = pl.code'), 30)})"


def _posted(f):
    return B.posting_candidates(f.queries, f.coded, f.fine, 4, LEAST, 30)


@key(f"WITH {ctes()}, {probed(4)}, {CANDS} SELECT * FROM posted")
def posting_candidates(spark, folder):
    return _posted(Fixture(spark, folder))


@key(f"WITH {ctes()}, {probed(4)}, {CANDS} {top('SELECT p.* FROM (' + chamfer(PAIRS) + ') p JOIN posted USING (query_id, set_id)', 10).replace('SELECT p.*', 'SELECT p.query_id, p.set_id, p.score')}")
def posting_topk(spark, folder):
    f = Fixture(spark, folder)
    return B.refine(_posted(f), f.queries, f.vectors, 10)


@key(f"WITH {ctes()} SELECT set_id, vec_no, code, array_to_string(list_transform(list_zip(v, center), lambda p: (CASE WHEN p[1] - p[2] >= -100 THEN 1 ELSE 0 END) + (CASE WHEN p[1] - p[2] >= 0 THEN 1 ELSE 0 END) + (CASE WHEN p[1] - p[2] >= 100 THEN 1 ELSE 0 END)), '') AS bits FROM coded JOIN fine USING (code)")
def residual_codes(spark, folder):
    f = Fixture(spark, folder)
    return B.residual_codes(f.coded, f.fine, [-100, 0, 100]).select("set_id", "vec_no", "code", F.array_join(F.transform("bits", lambda b: b.cast("string")), "").alias("bits"))


def planes(tables: int, bits: int, seed: str) -> str:
    return f"""pl{seed} AS MATERIALIZED (SELECT t, b, list(CASE WHEN substr(md5('{seed}-' || t || '-' || b || '-' || i), 1, 1) < '8' THEN 1 ELSE -1 END ORDER BY i) AS sg FROM range({tables}) x(t), range({bits}) y(b), range(64) z(i) GROUP BY ALL),
sk{seed} AS MATERIALIZED (SELECT set_id, vec_no, t, CAST(sum(CASE WHEN {dot('v', 'sg')} >= 0 THEN pow(2, b) ELSE 0 END) AS BIGINT) AS code FROM vec, pl{seed} GROUP BY ALL)"""


@key(f"WITH {ctes()}, {planes(6, 4, 'h')} SELECT * FROM skh")
def lsh_codes(spark, folder):
    return B.plane_codes(Fixture(spark, folder).vectors, ["set_id", "vec_no"], 6, 4, "h")


@key(f"WITH {ctes()}, {planes(6, 4, 'h')} {top(chamfer('SELECT q.set_id AS query_id, q.vec_no AS q_no, p.set_id, p.vec_no, count(*) AS s FROM skh q JOIN skh p ON q.t = p.t AND q.code = p.code WHERE q.set_id % 10 = 0 GROUP BY ALL'), 10)}")
def lsh_sketch_topk(spark, folder):
    f = Fixture(spark, folder)
    return B.lsh_sketch(f.queries, f.vectors, 10, 6, 4)


FDE = f"""{planes(3, 2, 'f')}, cell AS MATERIALIZED (SELECT set_id, t, s.code, i - 1 AS pos, CAST(sum(v[i]) AS BIGINT) AS total, CAST(round(sum(v[i])::DOUBLE / count(*)) AS BIGINT) AS mean FROM vec JOIN skf s USING (set_id, vec_no), range(1, 65) r(i) GROUP BY ALL),
have AS (SELECT DISTINCT set_id, t, code FROM cell), fill AS (SELECT set_id, t, want, code FROM (SELECT h.set_id, h.t, w.want, h.code, row_number() OVER (PARTITION BY h.set_id, h.t, w.want ORDER BY bit_count(xor(w.want, h.code)), h.code) AS n FROM have h, range(4) w(want)) WHERE n = 1),
enc AS MATERIALIZED (SELECT fill.set_id, fill.t, want AS code, pos, mean AS x FROM fill JOIN cell USING (set_id, t, code))"""


@key(f"WITH {ctes()}, {FDE} SELECT set_id, t, code, CAST(pos AS INTEGER) AS pos, x FROM enc")
def fde_encode(spark, folder):
    return B.fde_encode(Fixture(spark, folder).vectors, "set_id", 3, 2, "mean")


@key(f"WITH {ctes()}, {FDE} {top('SELECT q.set_id AS query_id, e.set_id, CAST(sum(q.total * e.x) AS BIGINT) AS score FROM cell q JOIN enc e USING (t, code, pos) WHERE q.set_id % 10 = 0 GROUP BY ALL'.replace('JOIN enc e USING (t, code, pos)', 'JOIN enc e ON e.t = q.t AND e.code = q.code AND e.pos = q.pos'), 10)}")
def fde_topk(spark, folder):
    f = Fixture(spark, folder)
    return B.fde_single(f.queries, f.vectors, 10, 3, 2)


@key(f"WITH {ctes()} SELECT a AS src, b AS dst, s, rnk FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY s DESC, b) AS rnk FROM sims WHERE a <> b) WHERE rnk <= 4")
def centroid_knn_graph(spark, folder):
    return B.centroid_graph(Fixture(spark, folder).fine, 4)


INC = f"""{probed(K1)}, pl AS (SELECT DISTINCT code, set_id FROM coded), sz AS (SELECT code, count(*) AS n FROM pl GROUP BY ALL),
rd AS (SELECT * FROM (SELECT p.*, coalesce(sum(n) OVER (PARTITION BY query_id, q_no ORDER BY s DESC, code ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM probed p JOIN sz USING (code)) WHERE before < 20),
inc AS MATERIALIZED ({chamfer('SELECT query_id, q_no, set_id, s FROM rd JOIN pl USING (code)')})"""


@key(f"WITH {ctes()}, {INC} SELECT * FROM inc")
def incremental_candidates(spark, folder):
    f = Fixture(spark, folder)
    return B.incremental_candidates(f.queries, f.coded, f.fine, 20)


@key(f"WITH {ctes()}, {INC} {top('SELECT p.query_id, p.set_id, p.score FROM (' + chamfer(PAIRS) + ') p JOIN (' + top('SELECT * FROM inc', 20) + ') c ON c.query_id = p.query_id AND c.set_id = p.set_id', 10)}")
def centroid_graph_topk(spark, folder):
    f = Fixture(spark, folder)
    return B.refine(top_k(B.incremental_candidates(f.queries, f.coded, f.fine, 20), 20), f.queries, f.vectors, 10)


PQ = f"pq AS MATERIALIZED (SELECT set_id, vec_no, part, code FROM (SELECT set_id, vec_no, part, code, row_number() OVER (PARTITION BY set_id, vec_no, part ORDER BY {sq('v[part * 16 + 1 : part * 16 + 16]', 'center[part * 16 + 1 : part * 16 + 16]')}, code) AS n FROM vec, (SELECT * FROM fine WHERE code < 16), (SELECT CAST(range AS INTEGER) AS part FROM range(4))) WHERE n = 1)"


@key(f"WITH {ctes()}, {PQ} SELECT * FROM pq")
def pq_encode(spark, folder):
    f = Fixture(spark, folder)
    return B.pq_encode(f.vectors, f.fine.where("code < 16"), 4, 64)


@key(f"WITH {ctes()}, {PQ} {top(chamfer('SELECT query_id, qv.vec_no AS q_no, pq.set_id, pq.vec_no, sum(' + dot('qv.v[part * 16 + 1 : part * 16 + 16]', 'center[part * 16 + 1 : part * 16 + 16]') + ') AS s FROM qv, pq JOIN fine USING (code) GROUP BY ALL'), 10)}")
def pq_adc_topk(spark, folder):
    f = Fixture(spark, folder)
    book = f.fine.where("code < 16")
    return B.pq_topk(f.queries, B.pq_encode(f.vectors, book, 4, 64), book, 4, 64, 10)


@key()
def fde_pq_graph(spark, folder):
    """Folded vectors as product codes, a graph over them, its beam search, then exact scores of 30."""
    f = Fixture(spark, folder)
    return B.refine(B.build_folded(f.vectors, 4, 2, 16, 8, 32, 8).search(f.queries, 30, 60), f.queries, f.vectors, 10)


@key()
def posting_residual_topk(spark, folder):
    """Candidates of the probed lists scored by their decompressed vectors, then exactly."""
    from ..operators.exact import top_k

    f = Fixture(spark, folder)
    packed = B.residual_codes(f.coded, f.fine, [-120, -40, 40, 120])
    return B.refine(top_k(B.residual_scores(f.queries, _posted(f), packed, f.fine, [-120, -40, 40, 120]), 20), f.queries, f.vectors, 10)


@key()
def centroid_graph_walk(spark, folder):
    """Codes in the order of a walk of the graph over the centres; their lists up to the budget; then exact scores."""
    from ..operators.exact import top_k
    from ..operators.single import vector_graph

    f = Fixture(spark, folder)
    graph = vector_graph(f.fine.select(F.col("code").cast("long").alias("set_id"), F.col("center").alias("v")), 8)
    return B.refine(top_k(B.walked_candidates(f.queries, f.coded, f.fine, graph, 20, 32), 20), f.queries, f.vectors, 10)


