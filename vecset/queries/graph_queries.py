"""Keys of the graph, of search and of index maintenance. Sets of two vectors: in 250 sets at sf0.01 some are in two clusters."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import clusters as C
from ..operators import graph as G
from ..operators import iterate
from ..operators import maintain as MT
from ..operators import metrics as E
from ..operators import search as S
from ..operators.exact import top_k
from ..plans.limits import small
from .base import Fixture, Registry, chamfer, ctes, dot, top
from .cluster_queries import PARENT
from .distance_queries import QPAIRS

key = Registry()
QUERIES, ORACLES = key.queries, key.oracles
NEAR, MOST = 3, 6

CAND = f"""n2 AS (SELECT set_id, list(code ORDER BY code) AS cs FROM coded GROUP BY ALL), d AS MATERIALIZED (SELECT a, b, 1000000 - s AS d FROM sims),
pairs AS (SELECT x.cluster_id AS via, x.set_id AS src, y.set_id AS dst, p.cs AS ca, q.cs AS cb FROM mem x JOIN mem y ON x.cluster_id = y.cluster_id AND x.set_id <> y.set_id JOIN n2 p ON p.set_id = x.set_id JOIN n2 q ON q.set_id = y.set_id),
dists AS (SELECT via, src, dst, least(d1.d + d4.d, d2.d + d3.d) / 2.0 AS dist FROM pairs JOIN d d1 ON d1.a = ca[1] AND d1.b = cb[1] JOIN d d2 ON d2.a = ca[1] AND d2.b = cb[2] JOIN d d3 ON d3.a = ca[2] AND d3.b = cb[1] JOIN d d4 ON d4.a = ca[2] AND d4.b = cb[2]),
cand AS MATERIALIZED (SELECT src, dst, dist, via FROM (SELECT *, row_number() OVER (PARTITION BY via, src ORDER BY dist, dst) AS n FROM dists) WHERE n <= {NEAR})"""
MIRROR = "mir AS MATERIALIZED (SELECT src, dst, min(dist) AS dist, min(via) AS via FROM (SELECT src, dst, dist, via FROM cand UNION ALL SELECT dst, src, dist, via FROM cand) GROUP BY ALL)"
HELD = """held AS (SELECT src, dst, min(rnk) AS best FROM (SELECT mir.src, mir.dst, o.rnk, row_number() OVER (PARTITION BY mir.src, o.cluster_id ORDER BY mir.dist, mir.dst) AS n FROM mir JOIN mem o ON o.set_id = mir.src JOIN mem t ON t.set_id = mir.dst AND t.cluster_id = o.cluster_id) WHERE n = 1 GROUP BY ALL)"""


def adj(name: str = "adj", most: int = MOST, held: bool = True) -> str:
    join, best = ("LEFT JOIN held USING (src, dst)", "best") if held else ("", "NULL::BIGINT")
    return f"{name} AS MATERIALIZED (SELECT src, dst, dist, via, CAST(best IS NOT NULL AS INTEGER) AS reserved FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY coalesce(best, 1073741824), dist, dst) AS n FROM (SELECT mir.*, {best} AS best FROM mir {join})) WHERE n <= {most})"


GRAPH = f"{ctes(2)}, {CAND}, {MIRROR}, {HELD}, {adj()}"
ROUTE = f"routed AS MATERIALIZED (SELECT DISTINCT query_id, cluster_id FROM (SELECT query_id, cluster_id, row_number() OVER (PARTITION BY query_id, vec_no ORDER BY {dot('v', 'center')} DESC, cluster_id) AS n FROM qv, coarse) WHERE n <= 1)"
ENTRY = "entry AS MATERIALIZED (SELECT query_id, cluster_id, arg_min(set_id, (md5(set_id::VARCHAR), set_id)) AS set_id FROM routed JOIN mem USING (cluster_id) GROUP BY ALL)"
REACH = "reach AS (SELECT DISTINCT query_id, set_id FROM entry UNION SELECT reach.query_id, dst FROM reach JOIN adj ON src = reach.set_id JOIN mem ON mem.set_id = dst JOIN routed ON routed.query_id = reach.query_id AND routed.cluster_id = mem.cluster_id)"
FREE = "reach AS (SELECT DISTINCT query_id, set_id FROM entry UNION SELECT reach.query_id, dst FROM reach JOIN adj ON src = reach.set_id)"


class Index(Fixture):
    """The whole index over sets of two vectors, its parts checkpointed."""

    def __init__(self, spark, folder, mode="reserve", edge="qemd", build="exact"):
        super().__init__(spark, folder, 2)
        self.mem = iterate.cut(self.membership())
        self.codes = iterate.cut(self.coded)
        self.cand = iterate.cut(G.local_edges(self.mem, self.codes, self.fine, NEAR, edge, build))
        self.adj = iterate.cut(G.merge_bridges(self.cand, self.mem, MOST, mode))

    def routing(self, t=1):
        routed = iterate.cut(S.query_clusters(S.centroid_scores(self.queries, self.coarse), t))
        return routed, iterate.cut(S.entry_points(routed, self.mem))

    def kernel(self, k=10, ef=20, t=2, **options):
        routed, entries = self.routing(t)
        q = self.query_codes.groupBy("query_id").agg(F.sort_array(F.collect_list("code")).alias("codes"))
        return S.search_kernel(q, routed, entries, self.adj, self.mem, self.codes, self.fine, k, ef, **options)


@key(f"WITH {ctes(2)}, {CAND} SELECT * FROM cand")
def local_knn_exact(spark, folder):
    return Index(spark, folder).cand


@key()
def local_graph(spark, folder):
    return Index(spark, folder, build="incremental").cand


@key(f"WITH {ctes(2)}, {CAND}, {MIRROR} SELECT src, dst, dist, via FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS n FROM mir) WHERE n <= 4")
def degree_trim(spark, folder):
    return G.trim_degree(G.mirrored(Index(spark, folder).cand), 4)


@key(f"WITH {GRAPH} SELECT * FROM adj")
def bridge_merge(spark, folder):
    return Index(spark, folder).adj


@key(f"WITH {ctes(2)}, {CAND}, {MIRROR}, {adj('adj', MOST, False)} SELECT * FROM adj")
def bridge_off(spark, folder):
    return Index(spark, folder, "off").adj


@key()
def bridge_replace(spark, folder):
    f = Index(spark, folder)
    return G.merge_bridges_in_turn(f.cand, f.mem, MOST)


@key(f"WITH {GRAPH} SELECT count(*) AS vertices, count(*) FILTER (WHERE n > {MOST}) AS over FROM (SELECT src, count(*) AS n FROM adj GROUP BY ALL)")
def graph_unique_vertices(spark, folder):
    return Index(spark, folder).adj.groupBy("src").agg(F.count("*").alias("n")).agg(F.count("*").alias("vertices"), F.count(F.when(F.col("n") > MOST, 1)).alias("over"))


@key(f"WITH {GRAPH} SELECT degree, count(*) AS n FROM (SELECT src, count(*) AS degree FROM adj GROUP BY ALL) GROUP BY ALL")
def degree_histogram(spark, folder):
    return Index(spark, folder).adj.groupBy("src").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("n"))


@key(f"WITH {ctes(2)} SELECT clusters, count(*) AS n FROM (SELECT set_id, count(*) AS clusters FROM mem GROUP BY ALL) GROUP BY ALL")
def bridge_count(spark, folder):
    return Fixture(spark, folder, 2).membership().groupBy("set_id").agg(F.count("*").alias("clusters")).groupBy("clusters").agg(F.count("*").alias("n"))


@key(f"WITH RECURSIVE {GRAPH}, und AS (SELECT src AS a, dst AS b FROM adj UNION SELECT dst, src FROM adj), walk AS (SELECT DISTINCT set_id, set_id AS other FROM mem UNION SELECT walk.set_id, b FROM walk JOIN und ON a = walk.other) SELECT set_id, min(other) AS component FROM walk GROUP BY ALL")
def components(spark, folder):
    f = Index(spark, folder)
    return iterate.components(f.adj, f.mem.select("set_id").distinct())


@key()
def stitch_edges(spark, folder):
    """One edge from each component but the largest to its nearest set outside, by the sets' mean vectors."""
    from ..operators.baselines import mean_vectors

    f = Index(spark, folder)
    return G.stitch(iterate.components(f.adj, f.mem.select("set_id").distinct()), mean_vectors(f.vectors))


@key(f"WITH {ctes(2)}, {ROUTE} SELECT * FROM routed")
def query_clusters(spark, folder):
    f = Fixture(spark, folder, 2)
    return S.query_clusters(S.centroid_scores(f.queries, f.coarse), 1)


@key(f"WITH {ctes(2)}, {ROUTE}, {ENTRY} SELECT query_id, cluster_id, set_id FROM entry")
def entry_points(spark, folder):
    f = Fixture(spark, folder, 2)
    return S.entry_points(S.query_clusters(S.centroid_scores(f.queries, f.coarse), 1), f.membership())


@key(f"WITH RECURSIVE {GRAPH}, {ROUTE}, {ENTRY}, {REACH} {top('SELECT p.* FROM (' + chamfer(QPAIRS) + ') p JOIN reach USING (query_id, set_id)', 10)}")
def search_exhaustive(spark, folder):
    f = Index(spark, folder)
    routed, entries = f.routing()
    return S.search_exhaustive(entries, f.adj, f.mem, routed, f.query_codes, f.codes, f.code_sims(), 10)


@key(f"WITH RECURSIVE {GRAPH}, {ROUTE}, {ENTRY}, {FREE} SELECT query_id, set_id FROM reach")
def reach_no_guard(spark, folder):
    f = Index(spark, folder)
    return S.reachable(f.routing()[1], f.adj, None, None)


@key(f"WITH RECURSIVE {GRAPH}, {ROUTE}, {ENTRY}, {REACH} SELECT query_id, set_id FROM reach")
def reach_recursive(spark, folder):
    f = Index(spark, folder)
    routed, entries = f.routing()
    return S.reachable(entries, f.adj, f.mem, routed)


@key()
def search_topk(spark, folder):
    """Kernel engine, then exact re-ranking of 20 candidates."""
    f = Index(spark, folder)
    return S.rerank(f.kernel(k=20, ef=40), f.queries, f.vectors, 10)


@key()
def search_frontier(spark, folder):
    f = Index(spark, folder)
    routed, entries = f.routing(2)
    return S.search_frontier(entries, f.adj, f.mem, routed, f.query_codes, f.codes, f.code_sims(), 10, 20)


@key()
def search_single_queue(spark, folder):
    return Index(spark, folder).kernel(multi_path=False).select("query_id", "set_id", "score", "rnk")


@key()
def search_cost(spark, folder):
    return Index(spark, folder).kernel().groupBy("query_id").agg(F.max("scored").alias("scored"), F.max("hops").alias("hops"), F.max("guarded").alias("guarded"))


@key(f"""WITH {GRAPH}, {ROUTE}, {ENTRY}, sc AS MATERIALIZED ({chamfer(QPAIRS)}), st AS (SELECT e.query_id, e.set_id, score, min(cluster_id) AS path FROM entry e JOIN sc USING (query_id, set_id) GROUP BY ALL),
pick AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY query_id, path ORDER BY score DESC, set_id) AS n FROM st) WHERE n = 1),
new AS (SELECT pick.query_id, min(path) AS path, dst AS set_id FROM pick JOIN adj ON src = pick.set_id WHERE EXISTS (SELECT 1 FROM mem JOIN routed USING (cluster_id) WHERE mem.set_id = dst AND routed.query_id = pick.query_id) AND NOT EXISTS (SELECT 1 FROM st WHERE st.query_id = pick.query_id AND st.set_id = dst) GROUP BY ALL),
merged AS (SELECT query_id, path, set_id, score, CAST(EXISTS (SELECT 1 FROM pick WHERE pick.query_id = st.query_id AND pick.set_id = st.set_id) AS INTEGER) AS expanded FROM st UNION ALL SELECT query_id, path, set_id, score, 0 FROM new JOIN sc USING (query_id, set_id))
SELECT query_id, path, set_id, score, expanded FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, set_id) AS place FROM merged) WHERE place <= 5 OR expanded = 1""")
def superstep_once(spark, folder):
    f = Index(spark, folder)
    routed, entries = f.routing()
    scores = S.qch(f.query_codes, f.codes, f.code_sims())
    state = entries.join(scores, ["query_id", "set_id"]).groupBy("query_id", "set_id", "score").agg(F.min("cluster_id").alias("path"))
    allowed = routed.join(f.mem, "cluster_id").select("query_id", "set_id").distinct()
    return S.superstep(state.select("query_id", "path", "set_id", "score", F.lit(0).alias("expanded")), f.adj, allowed, scores, 5)


@key(f"WITH {ctes(2)} {top('SELECT p.* FROM (' + chamfer('SELECT query_id, qv.vec_no AS q_no, set_id, ' + dot('qv.v', 'vec.v') + ' AS s FROM qv, vec') + ') p JOIN (' + top(chamfer(QPAIRS), 20) + ') c USING (query_id, set_id)', 10)}")
def rerank_topk(spark, folder):
    f = Fixture(spark, folder, 2)
    return S.rerank(top_k(S.qch(f.query_codes, f.coded, f.code_sims()), 20), f.queries, f.vectors, 10)


@key()
def search_example(spark, folder):
    """Five rounds with ef = 2 for each customer over its orders, scored by their price. Orders of one status are a cluster and a chain
    by date; entry points are the first finished and the first open order, other clusters are pruned, and a shortcut leads from the
    second finished order to the last open one."""
    o = Fixture(spark, folder).table("orders").where("o_custkey is not null and o_orderkey is not null and o_totalprice is not null")
    by = Window.partitionBy("o_custkey", "o_orderstatus").orderBy("o_orderdate", "o_orderkey")
    o = o.select(F.col("o_custkey").alias("query_id"), F.col("o_orderkey").alias("set_id"), F.col("o_orderstatus").alias("cluster"), F.round("o_totalprice").cast("long").alias("score"), F.row_number().over(by).alias("n"), F.lead("o_orderkey").over(by).alias("next"))
    o = iterate.cut(o)
    ends = o.groupBy("query_id").agg(F.max(F.when((F.col("cluster") == "F") & (F.col("n") == 2), F.col("set_id"))).alias("a"), F.max(F.when((F.col("cluster") == "O") & F.col("next").isNull(), F.col("set_id"))).alias("b"))
    links = o.select(F.col("set_id").alias("a"), F.col("next").alias("b")).unionAll(ends.select("a", "b")).where("a is not null and b is not null")
    edges = iterate.cut(links.select(F.col("a").alias("src"), F.col("b").alias("dst")).unionAll(links.select("b", "a")))
    inside = o.where("cluster in ('F', 'O')")
    state = inside.where("n = 1").select("query_id", F.when(F.col("cluster") == "F", 0).otherwise(1).alias("path"), "set_id", "score", F.lit(0).alias("expanded"))
    for _ in range(5):
        state = iterate.cut(S.superstep(state, edges, inside.select("query_id", "set_id"), inside.select("query_id", "set_id", "score"), 2))
    return top_k(state.select("query_id", "set_id", "score"), 2)


TRAIN = "train AS (SELECT DISTINCT query_id, (query_id * 7 + 3) % (SELECT count(DISTINCT set_id) FROM vec) AS set_id FROM qv)"
HITS = f"hits AS MATERIALIZED ({top(chamfer(QPAIRS), 10)})"
SHORT = "short AS (SELECT DISTINCT least(h.set_id, t.set_id) AS u, greatest(h.set_id, t.set_id) AS v FROM train t JOIN hits h ON h.query_id = t.query_id AND h.rnk = 1 WHERE h.set_id <> t.set_id AND NOT EXISTS (SELECT 1 FROM hits x WHERE x.query_id = t.query_id AND x.set_id = t.set_id)), fresh AS MATERIALIZED (SELECT u, v FROM short WHERE NOT EXISTS (SELECT 1 FROM adj WHERE (src = u AND dst = v) OR (src = v AND dst = u)))"


def _shortcuts(spark, folder):
    f = Index(spark, folder)
    hits = top_k(S.qch(f.query_codes, f.codes, f.code_sims()), 10)
    train = f.queries.select("query_id").distinct().withColumn("set_id", (F.col("query_id") * 7 + 3) % f.n_sets())
    return f, G.shortcut_candidates(hits, train, f.adj)


@key(f"WITH {GRAPH}, {TRAIN}, {HITS}, {SHORT} SELECT u, v FROM fresh")
def shortcut_candidates(spark, folder):
    return _shortcuts(spark, folder)[1]


@key(f"""WITH {GRAPH}, {TRAIN}, {HITS}, {SHORT}, deg AS (SELECT src, count(*) AS n FROM adj GROUP BY ALL), half AS (SELECT u AS x, u, v FROM fresh UNION ALL SELECT v, u, v FROM fresh),
rk AS (SELECT *, row_number() OVER (PARTITION BY x ORDER BY md5(u::VARCHAR || '-' || v::VARCHAR), u, v) AS n FROM half)
SELECT u, v FROM rk LEFT JOIN deg ON deg.src = x WHERE rk.n <= {MOST + 2} - coalesce(deg.n, 0) GROUP BY ALL HAVING count(*) = 2""")
def shortcut_edges(spark, folder):
    f, pairs = _shortcuts(spark, folder)
    return G.admit_shortcuts(pairs, f.adj, MOST + 2)


@key()
def shortcut_coverage(spark, folder):
    """(sample, pairs, shortcuts): nested samples of the training pairs of the documents, and the edges that searching for them gives."""
    from dataclasses import replace

    from ..operators.index import sampled_pairs, with_shortcuts
    from .study_queries import CONFIG, built, work_set

    work, rows = work_set(spark, folder, "w1"), []
    index = built(work, replace(CONFIG, shortcuts=False))
    for percent in (5, 10, 20, 40):
        tried = replace(index, config=replace(CONFIG, sample=percent))
        rows.append((percent, sampled_pairs(work.train, percent).count(), with_shortcuts(tried, work.train_queries, work.train).where("kind = 'shortcut'").count() // 2))
    return spark.createDataFrame(rows, "sample int, pairs long, shortcuts long")


@key()
def index_summary(spark, folder):
    f = Index(spark, folder)
    return f.adj.agg(F.count("*").alias("edges"), F.countDistinct("src").alias("vertices"), F.sum("reserved").alias("reserved"), F.max("dist").alias("longest"))


@key(f"WITH {ctes(2)}, {PARENT}, t AS (SELECT set_id, cluster_id, count(*) AS tf FROM coded JOIN par USING (code) WHERE set_id % 5 = 0 GROUP BY ALL), p AS (SELECT set_id, cluster_id, row_number() OVER (PARTITION BY set_id ORDER BY round(t.tf * idf, 6) DESC, t.tf DESC, cluster_id) AS rnk FROM t JOIN idf USING (cluster_id)) SELECT set_id, cluster_id, rnk FROM p WHERE rnk <= 2")
def insert_membership(spark, folder):
    """Every fifth set as if it were new: clusters through its fine codes, pruned by the statistics that stand."""
    f = Fixture(spark, folder, 2)
    idf = C.inverse_counts(C.term_counts(f.assigned), f.n_sets())
    return MT.insert_membership(f.coded.where("set_id % 5 = 0"), C.fine_parents(f.fine, f.coarse), idf, 2)


@key()
def insert_graph(spark, folder):
    f = Index(spark, folder)
    old, new = f.mem.where("set_id % 5 <> 0"), f.mem.where("set_id % 5 = 0")
    kept = f.cand.where("src % 5 <> 0 and dst % 5 <> 0")
    return MT.insert_edges(kept, old, new, f.codes, f.fine, NEAR, MOST)


@key(f"WITH RECURSIVE {GRAPH}, {ROUTE}, {ENTRY}, {REACH} {top('SELECT p.* FROM (' + chamfer(QPAIRS) + ') p JOIN reach USING (query_id, set_id) WHERE set_id % 7 <> 0', 10)}")
def search_after_delete(spark, folder):
    """Deleted sets are still walked through; they leave the result before it is cut to k."""
    f = Index(spark, folder)
    routed, entries = f.routing()
    reach = S.reachable(entries, f.adj, f.mem, routed)
    scores = S.qch(f.query_codes, f.codes, f.code_sims()).join(reach, ["query_id", "set_id"], "left_semi")
    gone = f.mem.select("set_id").distinct().where("set_id % 7 = 0")
    return top_k(MT.active(scores, gone), 10)


@key(f"""WITH {GRAPH}, gone AS (SELECT DISTINCT set_id FROM mem WHERE set_id % 7 = 0), alive AS (SELECT src, dst, dist FROM adj WHERE src % 7 <> 0 AND dst % 7 <> 0),
detour AS (SELECT a.src, b.dst, a.dist + b.dist AS dist FROM adj a JOIN adj b ON a.dst = b.src WHERE a.dst % 7 = 0 AND a.src % 7 <> 0 AND b.dst % 7 <> 0 AND a.src <> b.dst),
allp AS (SELECT src, dst, min(dist) AS dist FROM (SELECT * FROM alive UNION ALL SELECT * FROM detour) GROUP BY ALL)
SELECT src, dst, dist FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS n FROM allp) WHERE n <= {MOST}""")
def vacuum_edges(spark, folder):
    f = Index(spark, folder)
    return MT.vacuum(f.adj, f.mem.select("set_id").distinct().where("set_id % 7 = 0"), MOST)


@key(f"WITH {ctes(2)} SELECT cluster_id, count(*) AS df, round(ln((SELECT count(DISTINCT set_id) FROM vec)::DOUBLE / (1.0 + count(*))), 6) AS idf FROM tf GROUP BY ALL")
def idf_after_insert(spark, folder):
    """Counts of the old sets and of the new ones add up."""
    f = Fixture(spark, folder, 2)
    tf = C.term_counts(f.assigned)
    return MT.merge_idf(tf.where("set_id % 5 <> 0"), tf.where("set_id % 5 = 0"), f.n_sets())


@key(f"WITH {ctes(2)}, n AS (SELECT cluster_id, count(*) AS n FROM mem GROUP BY ALL) SELECT min(n) AS least, median(n) AS middle, max(n) AS most, count(*) AS clusters FROM n")
def cluster_population(spark, folder):
    return E.cluster_population(Fixture(spark, folder, 2).membership())


