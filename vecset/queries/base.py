"""What the query modules share: registration, fixtures, and the same fixtures as DuckDB common table expressions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import clusters as C
from ..sources import tables as T
from ..plans.limits import small

K1, K2, M = 64, 8, 4


class Registry:
    def __init__(self):
        self.queries, self.oracles = {}, {}

    def __call__(self, oracle: str | None = None, name: str | None = None):
        def add(f):
            key = name or f.__name__
            self.queries[key] = f
            if oracle:
                self.oracles[key] = oracle
            return f

        return add


class Fixture:
    """The inputs of one query on one scale directory."""

    def __init__(self, spark: SparkSession, folder: str, m: int = M):
        self.spark, self.folder, self.m = spark, folder, m
        self.vectors = T.chunk_vectors(spark, folder, m)
        self.queries = T.chunk_queries(self.vectors)
        self.vocab = T.vocabulary(spark, folder)

    def table(self, name: str) -> DataFrame:
        return T.read_table(self.spark, self.folder, name)

    @property
    def fine(self) -> DataFrame:
        return C.seed_codebook(self.vocab, K1)

    @property
    def coarse(self) -> DataFrame:
        return C.seed_codebook(self.vocab, K2)

    @property
    def coded(self) -> DataFrame:
        return C.assign_codes(self.vectors, self.fine)

    @property
    def query_codes(self) -> DataFrame:
        return C.assign_codes(self.queries, self.fine)

    @property
    def assigned(self) -> DataFrame:
        return C.assign_codes(self.vectors, self.coarse).withColumnRenamed("code", "cluster_id")

    def n_sets(self) -> int:
        return self.vectors.select("set_id").distinct().count()

    def profile(self) -> DataFrame:
        tf = C.term_counts(self.assigned)
        return C.profile(tf, C.inverse_counts(tf, self.n_sets()))

    def membership(self, r: int = 2) -> DataFrame:
        return C.top_clusters(self.profile(), r)

    def code_sims(self) -> DataFrame:
        from ..functions.distance import dot

        other = self.fine.select(F.col("code").alias("b"), F.col("center").alias("_c"))
        return self.fine.select(F.col("code").alias("a"), "center").join(small(other)).select("a", "b", dot("center", "_c").alias("s"))


def fp(v: str) -> str:
    return f"list_transform({v}, lambda x: CAST(round(x::DOUBLE * 1000) AS BIGINT))"


def dot(a: str, b: str) -> str:
    return f"CAST(list_inner_product({a}::DOUBLE[], {b}::DOUBLE[]) AS BIGINT)"


def sq(a: str, b: str) -> str:
    return f"CAST(list_sum(list_transform(list_zip({a}, {b}), lambda p: (p[1] - p[2]) * (p[1] - p[2]))) AS BIGINT)"


def ctes(m: int = M) -> str:
    """vec, qv (queries), fine, coarse, coded, qcoded, assigned, tf, idf, prof, mem; each reads what stands before it."""
    return f"""
vec AS (SELECT vec_id // {m} AS set_id, CAST(vec_id % {m} AS INTEGER) AS vec_no, {fp('embedding')} AS v FROM embeddings),
qv AS (SELECT set_id AS query_id, vec_no, v FROM vec WHERE set_id % 10 = 0),
seed AS (SELECT CAST(row_number() OVER (ORDER BY md5(vec_id::VARCHAR), vec_id) - 1 AS INTEGER) AS code, {fp('embedding')} AS center FROM embeddings),
fine AS MATERIALIZED (SELECT * FROM seed WHERE code < {K1}),
coarse AS MATERIALIZED (SELECT code AS cluster_id, center FROM seed WHERE code < {K2}),
coded AS MATERIALIZED (SELECT set_id, vec_no, v, code FROM (SELECT set_id, vec_no, v, code, row_number() OVER (PARTITION BY set_id, vec_no ORDER BY {dot('v', 'center')} DESC, code) AS n FROM vec, fine) WHERE n = 1),
qcoded AS (SELECT set_id AS query_id, vec_no, v, code FROM coded WHERE set_id % 10 = 0),
assigned AS MATERIALIZED (SELECT set_id, vec_no, v, cluster_id FROM (SELECT set_id, vec_no, v, cluster_id, row_number() OVER (PARTITION BY set_id, vec_no ORDER BY {dot('v', 'center')} DESC, cluster_id) AS n FROM vec, coarse) WHERE n = 1),
tf AS (SELECT set_id, cluster_id, count(*) AS tf FROM assigned GROUP BY ALL),
idf AS (SELECT cluster_id, count(*) AS df, round(ln((SELECT count(DISTINCT set_id) FROM vec)::DOUBLE / (1.0 + count(*))), 6) AS idf FROM tf GROUP BY ALL),
prof0 AS (SELECT set_id, cluster_id, tf, round(tf * idf, 6) AS score FROM tf JOIN idf USING (cluster_id)),
prof AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY set_id ORDER BY score DESC, tf DESC, cluster_id) AS rnk FROM prof0),
mem AS MATERIALIZED (SELECT set_id, cluster_id, rnk FROM prof WHERE rnk <= 2),
sims AS MATERIALIZED (SELECT a.code AS a, b.code AS b, {dot('a.center', 'b.center')} AS s FROM fine a, fine b)"""


def top(scores: str, k: int) -> str:
    return f"SELECT query_id, set_id, score, rnk FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, set_id) AS rnk FROM ({scores})) WHERE rnk <= {k}"


def chamfer(pairs: str) -> str:
    """pairs: query_id, q_no, set_id, s."""
    return f"SELECT query_id, set_id, CAST(sum(best) AS BIGINT) AS score FROM (SELECT query_id, q_no, set_id, max(s) AS best FROM ({pairs}) GROUP BY ALL) GROUP BY ALL"


PAIRS = f"SELECT query_id, qv.vec_no AS q_no, set_id, {dot('qv.v', 'vec.v')} AS s FROM qv, vec"
EXACT = top(chamfer(PAIRS), 10)
