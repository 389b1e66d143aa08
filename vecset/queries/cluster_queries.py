"""Keys of set-level clustering."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import clusters as C
from ..operators import search as S
from ..plans.limits import small
from .base import Fixture, Registry, ctes, dot

key = Registry()
QUERIES, ORACLES = key.queries, key.oracles


@key()
def kmeans_fit(spark, folder):
    f = Fixture(spark, folder)
    return C.fit_kmeans(f.vectors, 16, iters=4).select("code", F.size("center").alias("width"))


def _lloyd(table, code):
    return f"WITH {ctes()} SELECT {code} AS code, CAST(i - 1 AS INTEGER) AS pos, CAST(sum(v[i]) AS BIGINT) AS total, count(*) AS n FROM {table}, range(1, 65) r(i) GROUP BY ALL"


@key(_lloyd("coded", "code"))
def lloyd_step(spark, folder):
    f = Fixture(spark, folder)
    return C.lloyd_step(f.vectors, f.fine)


@key(f"""WITH {ctes()}, par AS (SELECT code, center, cluster_id FROM (SELECT fine.code, fine.center, cluster_id, row_number() OVER (PARTITION BY fine.code ORDER BY {dot('fine.center', 'coarse.center')} DESC, cluster_id) AS n FROM fine, coarse) WHERE n = 1)
SELECT cluster_id AS code, CAST(i - 1 AS INTEGER) AS pos, CAST(sum(center[i]) AS BIGINT) AS total, count(*) AS n FROM par, range(1, 65) r(i) GROUP BY ALL""")
def coarse_lloyd_step(spark, folder):
    f = Fixture(spark, folder)
    return C.lloyd_step(f.fine.select(F.col("code").alias("fine"), F.col("center").alias("v")), f.coarse)


@key(f"WITH {ctes()} SELECT set_id, vec_no, code FROM coded")
def assign_fine(spark, folder):
    return Fixture(spark, folder).coded.select("set_id", "vec_no", "code")


@key(f"WITH {ctes()} SELECT set_id, vec_no, cluster_id FROM assigned")
def assign_coarse(spark, folder):
    return Fixture(spark, folder).assigned.select("set_id", "vec_no", "cluster_id")


PARENT = f"par AS (SELECT code, cluster_id FROM (SELECT fine.code, cluster_id, row_number() OVER (PARTITION BY fine.code ORDER BY {dot('fine.center', 'coarse.center')} DESC, cluster_id) AS n FROM fine, coarse) WHERE n = 1)"


@key(f"WITH {ctes()}, {PARENT} SELECT set_id, vec_no, par.cluster_id FROM coded JOIN par USING (code)")
def assign_coarse_via_fine(spark, folder):
    f = Fixture(spark, folder)
    return f.coded.join(small(C.fine_parents(f.fine, f.coarse)), "code").select("set_id", "vec_no", "cluster_id")


@key(f"WITH {ctes()} SELECT DISTINCT set_id, cluster_id FROM assigned")
def naive_membership(spark, folder):
    return Fixture(spark, folder).assigned.select("set_id", "cluster_id").distinct()


@key(f"WITH {ctes()} SELECT * FROM tf")
def cluster_tf(spark, folder):
    return C.term_counts(Fixture(spark, folder).assigned)


@key(f"WITH {ctes()} SELECT * FROM idf")
def cluster_idf(spark, folder):
    f = Fixture(spark, folder)
    return C.inverse_counts(C.term_counts(f.assigned), f.n_sets())


@key(f"WITH {ctes()} SELECT * FROM prof")
def cluster_profile(spark, folder):
    return Fixture(spark, folder).profile()


@key(f"WITH {ctes()} SELECT * FROM mem")
def membership_top_r(spark, folder):
    return Fixture(spark, folder).membership()


@key("""WITH assigned AS (SELECT l_orderkey AS set_id, CAST(l_suppkey % 8 AS INTEGER) AS cluster_id FROM lineitem),
tf AS (SELECT set_id, cluster_id, count(*) AS tf FROM assigned GROUP BY ALL),
idf AS (SELECT cluster_id, round(ln((SELECT count(DISTINCT set_id) FROM tf)::DOUBLE / (1.0 + count(*))), 6) AS idf FROM tf GROUP BY ALL),
prof AS (SELECT set_id, cluster_id, row_number() OVER (PARTITION BY set_id ORDER BY round(tf * idf, 6) DESC, tf DESC, cluster_id) AS rnk FROM tf JOIN idf USING (cluster_id))
SELECT set_id, cluster_id, rnk FROM prof WHERE rnk <= 2""")
def membership_example(spark, folder):
    """Orders as sets, their lines in eight clusters of suppliers: the two clusters of highest score stay."""
    lines = Fixture(spark, folder).table("lineitem").select(F.col("l_orderkey").alias("set_id"), (F.col("l_suppkey") % 8).cast("int").alias("cluster_id"))
    tf = C.term_counts(lines)
    return C.top_clusters(C.profile(tf, C.inverse_counts(tf, lines.select("set_id").distinct().count())), 2)


TRAIN = "train AS (SELECT DISTINCT query_id, (query_id * 7 + 3) % (SELECT count(DISTINCT set_id) FROM vec) AS set_id FROM qv)"
ROUTED = f"routed AS (SELECT DISTINCT query_id, cluster_id FROM (SELECT query_id, cluster_id, row_number() OVER (PARTITION BY query_id, vec_no ORDER BY {dot('v', 'center')} DESC, cluster_id) AS n FROM qv, coarse) WHERE n <= 2)"


def train(f):
    return f.queries.select("query_id").distinct().withColumn("set_id", (F.col("query_id") * 7 + 3) % f.n_sets())


@key(f"WITH {ctes()}, {TRAIN}, {ROUTED} SELECT train.query_id, train.set_id, CAST(least(10, coalesce(min(prof.rnk) FILTER (WHERE routed.cluster_id IS NOT NULL), 10)) AS INTEGER) AS r FROM train LEFT JOIN prof USING (set_id) LEFT JOIN routed ON routed.query_id = train.query_id AND routed.cluster_id = prof.cluster_id GROUP BY ALL")
def cutoff_labels(spark, folder):
    f = Fixture(spark, folder)
    return C.cutoff_labels(train(f), f.profile(), S.query_clusters(S.centroid_scores(f.queries, f.coarse), 2))


@key(f"WITH {ctes()} SELECT set_id, array_to_string(list_transform(list_concat(list(score ORDER BY rnk), [0.0, 0.0, 0.0, 0.0])[1:4], lambda x: CAST(round(x * 1000000) AS BIGINT)), ',') AS scores, CAST(sum(tf) AS BIGINT) AS m FROM prof GROUP BY ALL")
def cutoff_features(spark, folder):
    x = C.cutoff_features(Fixture(spark, folder).profile(), 4)
    return x.select("set_id", F.array_join(F.transform("scores", lambda s: F.round(s * 1_000_000).cast("long").cast("string")), ",").alias("scores"), "m")


@key()
def adaptive_membership(spark, folder):
    f = Fixture(spark, folder)
    p, x = f.profile(), C.cutoff_features(f.profile(), 4)
    labels = C.cutoff_labels(train(f), p, S.query_clusters(S.centroid_scores(f.queries, f.coarse), 2), 4)
    return C.adaptive_clusters(C.fit_cutoff(labels, x), p, x)


@key(f"""WITH {ctes()}, {PARENT} SELECT 'fine' AS kind, round(avg(n), 6) AS clusters FROM (SELECT count(DISTINCT code) AS n FROM coded GROUP BY set_id) UNION ALL SELECT 'coarse', round(avg(n), 6) FROM (SELECT count(*) AS n FROM tf GROUP BY set_id) UNION ALL SELECT 'pruned', round(avg(n), 6) FROM (SELECT count(*) AS n FROM mem GROUP BY set_id)""")
def avg_clusters_per_set(spark, folder):
    f = Fixture(spark, folder)
    mean = lambda kind, df: df.groupBy("set_id").agg(F.count("*").alias("n")).agg(F.lit(kind).alias("kind"), F.round(F.avg("n"), 6).alias("clusters"))
    return mean("fine", f.coded.select("set_id", "code").distinct()).unionAll(mean("coarse", f.assigned.select("set_id", "cluster_id").distinct())).unionAll(mean("pruned", f.membership()))


@key(f"WITH {ctes()} SELECT set_id, vec_no, idf FROM (SELECT set_id, vec_no, idf, row_number() OVER (PARTITION BY set_id ORDER BY idf DESC, vec_no) AS n FROM assigned JOIN idf USING (cluster_id)) WHERE n <= 2")
def thin_sets(spark, folder):
    f = Fixture(spark, folder)
    idf = C.inverse_counts(C.term_counts(f.assigned), f.n_sets())
    return C.thin(f.assigned.join(small(idf), "cluster_id").select("set_id", "vec_no", "idf"), 2)


@key("SELECT l_suppkey AS part, count(*) AS n, CAST(pow(2, floor(log2(16 * sqrt(count(*))))) AS BIGINT) AS k1 FROM lineitem GROUP BY ALL")
def codebook_size(spark, folder):
    """Fine codes for a codebook of each supplier's lines, by their number."""
    n = Fixture(spark, folder).table("lineitem").groupBy(F.col("l_suppkey").alias("part")).agg(F.count("*").alias("n"))
    return n.withColumn("k1", F.udf(lambda m: C.codebook_sizes(m)[0], "long")("n"))
