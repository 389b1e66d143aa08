"""Keys of distances and scores."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import functions as F

from ..functions import distance as D
from ..functions import transport
from ..operators import exact as X
from ..operators import search as S
from ..operators.graph import Codebook
from ..plans.limits import small
from .base import EXACT, PAIRS, Fixture, Registry, chamfer, ctes, dot, sq, top

key = Registry()
QUERIES, ORACLES = key.queries, key.oracles
TWO = "a.vec_id AS a, b.vec_id AS b"
REAL = "list_transform(list_zip(a.embedding, b.embedding), lambda p: p[1]::DOUBLE * p[2]::DOUBLE)"


def _two(spark, folder):
    e = Fixture(spark, folder).table("embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    asked = e.where("vec_id % 20 = 0").select(F.col("vec_id").alias("a"), F.col("v").alias("va"))
    return e.select(F.col("vec_id").alias("b"), F.col("v").alias("vb")).join(small(asked))


def _ground(kind, sql):
    oracle = f"SELECT {TWO}, round({sql}, 9) AS dist FROM embeddings a, embeddings b WHERE a.vec_id % 20 = 0"
    key(oracle, f"ground_{kind}")(lambda spark, folder: _two(spark, folder).select("a", "b", F.round(D.ground_dist("va", "vb", kind), 9).alias("dist")))


_D = "list_inner_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[])"
_ground("cosine", f"1.0 - {_D}")
_ground("chord", f"sqrt(greatest(0.0, 2.0 - 2.0 * {_D}))")
_ground("l2", "list_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[])")


@key(f"WITH {ctes()} {chamfer(PAIRS)}")
def chamfer_pairs(spark, folder):
    f = Fixture(spark, folder)
    return X.all_scores(f.queries, f.vectors)


@key(f"WITH {ctes()} SELECT query_id, set_id, sum(best) / count(*)::DOUBLE AS score FROM (SELECT query_id, q_no, set_id, max(s) AS best FROM ({PAIRS}) GROUP BY ALL) GROUP BY ALL")
def chamfer_mean(spark, folder):
    f = Fixture(spark, folder)
    return X.all_scores(f.queries, f.vectors, mean=True)


PAIRS_L2 = f"SELECT query_id, qv.vec_no AS q_no, set_id, -{sq('qv.v', 'vec.v')} AS s FROM qv, vec"


@key(f"WITH {ctes()} {chamfer(PAIRS_L2)}")
def chamfer_l2(spark, folder):
    f = Fixture(spark, folder)
    return X.all_scores(f.queries, f.vectors, "l2")


@key(f"WITH {ctes()} {chamfer(PAIRS)}")
def chamfer_hof(spark, folder):
    f = Fixture(spark, folder)
    return X.all_scores(f.queries, f.vectors)


@key(f"WITH {ctes()} {chamfer('SELECT x.set_id AS query_id, x.vec_no AS q_no, y.set_id, ' + dot('x.v', 'y.v') + ' AS s FROM vec x JOIN vec y ON y.set_id = x.set_id + 1')}")
def chamfer_example(spark, folder):
    """The score of each set with the next one, from a table of pairs."""
    v = Fixture(spark, folder).vectors
    nxt = v.select((F.col("set_id") - 1).alias("query_id"), "set_id", "vec_no", "v")
    pairs = v.select(F.col("set_id").alias("query_id"), F.col("vec_no").alias("q_no"), F.col("v").alias("q")).join(nxt, "query_id")
    return D.chamfer(pairs.select("query_id", "q_no", "set_id", "vec_no", D.dot("q", "v").alias("s")))


@key(f"WITH {ctes()} {EXACT}")
def exact_topk(spark, folder):
    f = Fixture(spark, folder)
    return X.exact_topk(f.queries, f.vectors, 10)


@key(f"WITH {ctes()} {top(chamfer(PAIRS_L2), 10)}")
def exact_topk_l2(spark, folder):
    f = Fixture(spark, folder)
    return X.exact_topk(f.queries, f.vectors, 10, "l2")


@key(f"WITH {ctes(1)} {top('SELECT query_id, set_id, -' + sq('qv.v', 'vec.v') + ' AS score FROM qv, vec', 5)}")
def vector_topk(spark, folder):
    f = Fixture(spark, folder, 1)
    return X.vector_topk(f.queries, f.vectors, 5)


def _costs(spark, folder, m):
    """(a, b, c): costs 1e6 - inner product of pairs of sets of m vectors, c row by row; a is a query set, b above it. Short sets go."""
    f = Fixture(spark, folder, m)
    n = X.nested(f.vectors).where(F.size("vecs") == m)
    a, b = n.where("set_id % 10 = 0").select(F.col("set_id").alias("a"), F.col("vecs").alias("va")), n.select(F.col("set_id").alias("b"), F.col("vecs").alias("vb"))
    return b.join(small(a)).where("a < b").select("a", "b", F.flatten(F.transform("va", lambda x: F.transform("vb", lambda y: 1_000_000 - D.dot(x, y)))).alias("c"))


def _cost_sql(m):
    cells = ", ".join(f"1000000 - {dot(f'va[{i}]', f'vb[{j}]')}" for i in range(1, m + 1) for j in range(1, m + 1))
    return f"""WITH {ctes(m)}, n AS (SELECT set_id, list(v ORDER BY vec_no) AS vs FROM vec GROUP BY ALL HAVING count(*) = {m}),
costs AS (SELECT a.set_id AS a, b.set_id AS b, a.vs AS va, b.vs AS vb FROM n a, n b WHERE a.set_id % 10 = 0 AND a.set_id < b.set_id),
c AS (SELECT a, b, [{cells}] AS c FROM costs)"""


def _solved(costs, m, solver):
    """(a, b, emd) of (a, b, c)."""

    def run(batches):
        for batch in batches:
            c = batch.column("c").flatten().to_numpy().reshape(-1, m, m)
            got = [round(transport.emd(x, solver=solver), 6) for x in c]
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), pa.array(got, pa.float64())], names=["a", "b", "emd"])

    return costs.mapInArrow(run, "a long, b long, emd double")


def _emd(m, best):
    def run(spark, folder):
        cell = lambda i, j: F.col("c")[i * m + j]
        if m == 1:
            return _costs(spark, folder, m).select("a", "b", cell(0, 0).cast("double").alias("emd"))
        return X.matched(X.nested(Fixture(spark, folder, m).vectors).where(F.size("vecs") == m), m, "emd")

    key(best and f"{_cost_sql(m)} SELECT a, b, round({best}, 6) AS emd FROM c", f"emd_m{m}" if m < 4 else "emd_general")(run)


_emd(1, "c[1]::DOUBLE")
_emd(2, "least(c[1] + c[4], c[2] + c[3]) / 2.0")
_emd(3, "least(c[1]+c[5]+c[9], c[1]+c[6]+c[8], c[2]+c[4]+c[9], c[2]+c[6]+c[7], c[3]+c[4]+c[8], c[3]+c[5]+c[7]) / 3.0")
_emd(4, None)


@key(f"{_cost_sql(3)} SELECT a, b, round(greatest(least(c[1],c[2],c[3]) + least(c[4],c[5],c[6]) + least(c[7],c[8],c[9]), least(c[1],c[4],c[7]) + least(c[2],c[5],c[8]) + least(c[3],c[6],c[9])) / 3.0, 6) AS emd FROM c")
def emd_relaxed_lb(spark, folder):
    return _solved(_costs(spark, folder, 3), 3, "relaxed")


@key(f"""WITH {ctes(2)}, s AS (SELECT x.set_id, list(x.v[i] + y.v[i] ORDER BY i) AS v FROM vec x, vec y, range(1, 65) r(i) WHERE x.set_id = y.set_id AND x.vec_no = 0 AND y.vec_no = 1 GROUP BY ALL)
SELECT a.set_id AS a, b.set_id AS b, {sq('a.v', 'b.v')} AS squared FROM s a, s b WHERE a.set_id % 10 = 0 AND a.set_id < b.set_id""")
def emd_meanvec_lb(spark, folder):
    """Squared l2 of the sums of two vectors: four times the squared distance of the means."""
    f = Fixture(spark, folder, 2)
    s = X.nested(f.vectors).where(F.size("vecs") == 2).select("set_id", F.zip_with(F.col("vecs")[0], F.col("vecs")[1], lambda x, y: x + y).alias("v"))
    a = s.where("set_id % 10 = 0").select(F.col("set_id").alias("a"), F.col("v").alias("va"))
    return s.withColumnRenamed("set_id", "b").join(small(a)).where("a < b").select("a", "b", D.squared_l2("va", "v").alias("squared"))


@key(f"{_cost_sql(2)} SELECT count(*) AS n, count(*) FILTER (WHERE least(c[1],c[2]) + least(c[3],c[4]) > least(c[1]+c[4], c[2]+c[3])) AS violations, min(least(c[1]+c[4], c[2]+c[3]) - least(c[1],c[2]) - least(c[3],c[4])) AS least_slack FROM c")
def bound_check(spark, folder):
    """The mean Chamfer distance never exceeds the earth mover's distance (both times 2)."""
    c = [F.col("c")[i] for i in range(4)]
    emd, ch = F.least(c[0] + c[3], c[1] + c[2]), F.least(c[0], c[1]) + F.least(c[2], c[3])
    return _costs(spark, folder, 2).agg(F.count("*").alias("n"), F.count(F.when(ch > emd, 1)).alias("violations"), F.min(emd - ch).alias("least_slack"))


def _qemd(f, m):
    codes = f.coded.groupBy("set_id").agg(F.sort_array(F.collect_list(F.struct("vec_no", "code"))).alias("cs")).where(F.size("cs") == m)
    return codes.select("set_id", F.transform("cs", lambda x: x["code"]).alias("vecs"))


@key(f"""WITH {ctes(2)}, n AS MATERIALIZED (SELECT set_id, list(code ORDER BY vec_no) AS cs FROM coded GROUP BY ALL HAVING count(*) = 2), d AS MATERIALIZED (SELECT a, b, 1000000 - s AS d FROM sims),
pr AS MATERIALIZED (SELECT x.set_id AS a, y.set_id AS b, x.cs[1] AS c1, x.cs[2] AS c2, y.cs[1] AS e1, y.cs[2] AS e2 FROM (SELECT * FROM n WHERE set_id % 10 = 0) x, n y WHERE x.set_id < y.set_id)
SELECT pr.a, pr.b, least(p.d + q.d, r.d + t.d) / 2.0 AS qemd FROM pr JOIN d p ON p.a = c1 AND p.b = e1 JOIN d q ON q.a = c2 AND q.b = e2 JOIN d r ON r.a = c1 AND r.b = e2 JOIN d t ON t.a = c2 AND t.b = e1""")
def qemd_m2(spark, folder):
    f = Fixture(spark, folder, 2)
    return X.matched(_qemd(f, 2), 2, "qemd", Codebook(f.fine).centers)


@key()
def qemd_pairs(spark, folder):
    """Quantized earth mover's distance of bags of codes of four vectors."""
    f = Fixture(spark, folder, 4)
    return X.matched(_qemd(f, 4), 4, "qemd", Codebook(f.fine).centers)


QPAIRS = "SELECT query_id, q.vec_no AS q_no, c.set_id, s FROM qcoded q JOIN sims ON q.code = sims.a JOIN (SELECT DISTINCT set_id, code FROM coded) c ON c.code = sims.b"


@key(f"WITH {ctes()} {chamfer(QPAIRS)}")
def qch_pairs(spark, folder):
    f = Fixture(spark, folder)
    return S.qch(f.query_codes, f.coded, f.code_sims())


@key(f"WITH {ctes()} {top(chamfer(QPAIRS), 10)}")
def qch_topk(spark, folder):
    f = Fixture(spark, folder)
    return X.top_k(S.qch(f.query_codes, f.coded, f.code_sims()), 10)


@key(f"WITH {ctes()} {chamfer('SELECT query_id, qv.vec_no AS q_no, c.set_id, ' + dot('qv.v', 'fine.center') + ' AS s FROM qv, fine JOIN (SELECT DISTINCT set_id, code FROM coded) c ON c.code = fine.code')}")
def qch_asym_pairs(spark, folder):
    f = Fixture(spark, folder)
    table = f.queries.join(small(f.fine)).select("query_id", F.col("vec_no").alias("q_no"), "code", D.dot("v", "center").alias("s"))
    return D.chamfer(f.coded.select("set_id", "code").distinct().join(small(table), "code"))


@key(f"WITH {ctes()} SELECT set_id, CAST(sum(1000000 - {dot('v', 'center')}) AS BIGINT) AS total, count(*) AS m FROM coded JOIN fine USING (code) GROUP BY ALL")
def quant_error(spark, folder):
    f = Fixture(spark, folder)
    return f.coded.join(small(f.fine), "code").groupBy("set_id").agg(F.sum(1_000_000 - D.dot("v", "center")).alias("total"), F.count("*").alias("m"))


@key(f"WITH {ctes()} SELECT query_id, vec_no, cluster_id, {dot('v', 'center')} AS score FROM qv, coarse")
def centroid_scores(spark, folder):
    f = Fixture(spark, folder)
    return S.centroid_scores(f.queries, f.coarse)


@key(f"WITH {ctes()} SELECT a, b, 1000000 - s AS dist FROM sims")
def code_dist(spark, folder):
    return Fixture(spark, folder).code_sims().select("a", "b", (1_000_000 - F.col("s")).alias("dist"))


