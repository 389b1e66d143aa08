"""Keys of the experiments: every method on the four work sets, built once and searched apart from its building.

Rows are (workload, dataset, method, param, k, metric, value). Qualities are measured against the work sets' relevant pairs, costs as
sets scored and seconds of a batch of queries. Times differ from run to run, so these keys have no SQL; tests hold what must hold.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import clusters as C
from ..operators import graph as G
from ..operators import metrics as E
from ..operators import search as S
from ..operators.exact import exact_topk, top_k
from ..operators.index import IndexConfig, SetIndex, build_index, fit_codebooks, with_shortcuts
from ..operators.iterate import cut
from ..operators.single import vector_graph
from ..sources.worksets import WorkSet, subset, work_set
from .base import Registry

key = Registry()
QUERIES, ORACLES = key.queries, key.oracles

SCHEMA = "workload string, dataset string, method string, param string, k int, metric string, value double"
#: For work sets of some thousand sets; the sizing rule of codebook_sizes is meant for millions of vectors.
CONFIG = IndexConfig(k1=256, k2=64, degree=12, t=1, iterations=4, solver="sinkhorn")
EDGES = [-120, -40, 40, 120]


@dataclass
class Method:
    """search(k) gives hits (query_id, set_id, score, rnk); tables: what a search reads, raw vectors left out."""

    search: Callable[[int], DataFrame]
    tables: list[DataFrame]
    seconds: float


def built(work: WorkSet, config: IndexConfig = CONFIG, codebooks=None) -> SetIndex:
    if codebooks is None:
        codebooks = fit_codebooks(work.fit, config)
    return build_index(work.vectors, config, work.train_queries, work.train, codebooks)


def method(name: str, work: WorkSet, index: SetIndex) -> Method:
    """The method's index, built, and its search. All but brute and mean_single re-rank 4 k candidates by exact scores. Codebooks are
    shared, and counted in no method's time."""
    q, v, began = work.queries, work.vectors, time.time()
    fine, done = index.fine, lambda *tables: [cut(t) for t in tables]
    coded = cut(C.assign_codes(v, fine)) if name in ("centroid_postings", "centroid_graph", "pooled", "plain_graph") else None
    refine = lambda cands, k: S.rerank(cands, q, v, k)
    if name == "brute":
        return Method(lambda k: exact_topk(q, v, k), [], 0.0)
    if name == "mean_single":
        tables = done(B.mean_vectors(v).withColumn("vec_no", F.lit(0)))
        search = lambda k: exact_topk(B.mean_vectors(q, "query_id").withColumn("vec_no", F.lit(0)), tables[0], k)
    elif name == "pooled":
        tables = done(coded.select("set_id", "vec_no", "code"))
        search = lambda k: refine(B.pooled_candidates(q, v, coded, fine, 2 * k, 8), k)
    elif name == "centroid_postings":
        tables = done(B.posting_lists(coded), B.residual_codes(coded, fine, EDGES))
        search = lambda k: refine(top_k(B.residual_scores(q, B.posting_candidates(q, coded, fine, 4, 100_000, 16 * k), tables[1], fine, EDGES), 4 * k), k)
    elif name == "lsh_sketch":
        tables = done(B.plane_codes(v, ["set_id", "vec_no"], 32, 5, "h"))
        search = lambda k: refine(B.lsh_sketch(q, v, 4 * k, 32, 5), k)
    elif name == "fde_pq_graph":
        folded = B.build_folded(v, 6, 3, 16, 24, 64, index.config.degree)
        tables = [folded.codes, folded.graph]
        search = lambda k: refine(folded.search(q, 4 * k, 16 * k), k)
    elif name == "centroid_graph":
        graph = vector_graph(fine.select(F.col("code").cast("long").alias("set_id"), F.col("center").alias("v")), index.config.degree)
        tables = done(graph, B.posting_lists(coded))
        search = lambda k: refine(top_k(B.walked_candidates(q, coded, fine, tables[0], 16 * k, 32), 4 * k), k)
    elif name == "plain_graph":
        one = v.select("set_id").distinct().withColumn("cluster_id", F.lit(0))
        d = index.config.degree
        tables = done(G.trim_degree(G.mirrored(G.local_edges(one, coded, fine, d, edge="qch")), d), one, coded.select("set_id", "code"))
        bags = C.assign_codes(q, fine).groupBy("query_id").agg(F.sort_array(F.collect_list("code")).alias("codes"))
        routed = cut(bags.select("query_id", F.lit(0).alias("cluster_id")))
        search = lambda k: refine(S.search_kernel(bags, routed, S.entry_points(routed, tables[1]), tables[0], tables[1], tables[2], fine, 4 * k, 10 * k, multi_path=False, guard=False), k)
    elif name == "set_graph":
        search, tables = (lambda k: index.topk(q, v, k, 10 * k, 4 * k)), [index.edges, index.membership, index.codes, index.entries]
        return Method(search, tables, sum(s for stage, s in index.seconds.items() if stage != "codebooks"))
    else:
        raise ValueError(name)
    return Method(search, tables, time.time() - began)


METHODS = ("brute", "mean_single", "pooled", "centroid_postings", "lsh_sketch", "fde_pq_graph", "centroid_graph", "plain_graph", "set_graph")


def qualities(hits: DataFrame, qrels: DataFrame, k: int) -> dict[str, float]:
    return {name: f(hits, qrels, k).first()["value"] or 0.0 for name, f in (("recall", E.recall_at_k), ("success", E.success_at_k), ("mrr", E.mrr_at_k))}


def measured(rows: list, head: tuple, search: Callable[[], DataFrame], qrels: DataFrame, k: int, repeats: int = 1) -> None:
    """Adds the qualities and the mean seconds of `repeats` runs."""
    hits = cut(search())
    rows += [(*head, k, name, float(x)) for name, x in qualities(hits, qrels, k).items()]
    rows.append((*head, k, "seconds", E.latency(search, repeats)))


def overview(spark, folder, dataset: str, ks=(10, 100), names=METHODS, repeats: int = 1) -> DataFrame:
    work, rows = work_set(spark, folder, dataset), []
    index = built(work)
    for name in names:
        m = method(name, work, index)
        for k in ks:
            measured(rows, ("overview", dataset, name, ""), lambda m=m, k=k: m.search(k), work.qrels, k, repeats)
    return spark.createDataFrame(rows, SCHEMA)


def _overview(dataset: str) -> None:
    @key(None, f"w5_overview_{dataset}")
    def run(spark, folder):
        return overview(spark, folder, dataset, (10,))


for _d in ("w1", "w2", "w3", "w4"):
    _overview(_d)


@key()
def w6_vary_k(spark, folder):
    """k = 1, 10, 100 with beams that grow."""
    return overview(spark, folder, "w1", (1, 10, 100), ("centroid_postings", "fde_pq_graph", "set_graph")).withColumn("workload", F.lit("vary_k"))


def sweep(spark, folder, workload: str, settings, dataset: str = "w1", k: int = 10) -> DataFrame:
    """settings: (param, value, search(index, work) -> hits with scored), on one index."""
    work, rows = work_set(spark, folder, dataset), []
    index = built(work)
    n = work.vectors.select("set_id").distinct().count()
    for param, value, search in settings:
        hits = cut(search(index, work))
        head = (workload, dataset, "set_graph", f"{param}={value}", k)
        rows += [(*head, name, float(x)) for name, x in qualities(S.rerank(hits, work.queries, work.vectors, k), work.qrels, k).items()]
        scored = hits.groupBy("query_id").agg(F.max("scored").alias("s")).agg(F.avg("s")).first()[0] or 0.0
        rows += [(*head, "scored", float(scored)), (*head, "scored_share", float(scored) / max(n, 1))]
    return spark.createDataFrame(rows, SCHEMA)


@key()
def w7_curve(spark, folder):
    return sweep(spark, folder, "curve", [("ef", v, lambda i, w, v=v: i.search(w.queries, min(v, 40), v)) for v in (10, 20, 40, 80, 160)])


@key()
def w10_vary_t(spark, folder):
    return sweep(spark, folder, "vary_t", [("t", v, lambda i, w, v=v: i.search(w.queries, 40, 60, v)) for v in (1, 2, 4, 8)])


@key()
def w11_vary_rerank(spark, folder):
    return sweep(spark, folder, "vary_rerank", [("rerank_k", v, lambda i, w, v=v: i.search(w.queries, v, 80)) for v in (10, 20, 40, 80)])


@key()
def tradeoff_curve(spark, folder):
    """(method, cost, quality): sets scored against MRR of the graph, with and without its cluster guard, by beam."""
    out = None
    for guard in (True, False):
        rows = sweep(spark, folder, "curve", [("ef", v, lambda i, w, v=v, g=guard: i.search(w.queries, 10, v, guard=g)) for v in (10, 40, 120)])
        part = rows.groupBy("param").agg(F.max(F.when(F.col("metric") == "scored", F.col("value"))).alias("cost"), F.max(F.when(F.col("metric") == "mrr", F.col("value"))).alias("quality")).select(F.lit("guided" if guard else "unguided").alias("method"), "cost", "quality")
        out = part if out is None else out.unionAll(part)
    return out


@key()
def w8_index_cost(spark, folder):
    """Seconds to build, after the shared codebooks, and bytes of what a search reads."""
    rows = []
    for dataset in ("w1", "w3"):
        work = work_set(spark, folder, dataset)
        index = built(work)
        rows += [("index_cost", dataset, "set_graph", stage, 0, "stage_seconds", float(s)) for stage, s in index.seconds.items()]
        for name in METHODS[1:]:
            m = method(name, work, index)
            rows += [("index_cost", dataset, name, "", 0, "seconds", float(m.seconds)), ("index_cost", dataset, name, "", 0, "bytes", float(sum(E.stored_bytes(t) for t in m.tables)))]
    return spark.createDataFrame(rows, SCHEMA)


#: variant -> (changes of the build, changes of the search)
VARIANTS = {
    "full": ({}, {}),
    "no_transport_edges": ({"edge": "qch"}, {}),
    "one_queue": ({}, {"multi_path": False}),
    "fixed_three": ({"cutoff": "fixed", "r": 3}, {}),
    "no_bridges": ({"bridge_mode": "off"}, {}),
    "no_shortcuts": ({"shortcuts": False}, {}),
    "all_off": ({"edge": "qch", "cutoff": "fixed", "r": 3, "bridge_mode": "off", "shortcuts": False}, {"multi_path": False}),
}


def ablation(spark, folder, dataset: str = "w1", efs=(10, 20, 40, 80), k: int = 10, variants=tuple(VARIANTS)):
    """Rows of every variant and beam, and the indexes by variant (one build serves variants that differ in the search alone)."""
    work, rows, made = work_set(spark, folder, dataset), [], {}
    books = fit_codebooks(work.fit, CONFIG)
    for variant in variants:
        build, search = VARIANTS[variant]
        name = tuple(sorted(build.items()))
        if name not in made:
            made[name] = built(work, replace(CONFIG, **build), books)
        for ef in efs:
            hits = cut(made[name].search(work.queries, k, ef, **search))
            head = ("ablation", dataset, variant, f"ef={ef}", k)
            rows += [(*head, metric, float(x)) for metric, x in qualities(S.rerank(hits, work.queries, work.vectors, k), work.qrels, k).items()]
            per = hits.groupBy("query_id").agg(F.max("scored").alias("s"), F.max("hops").alias("h")).agg(F.avg("s"), F.avg("h")).first()
            rows += [(*head, "scored", float(per[0] or 0)), (*head, "hops", float(per[1] or 0))]
    return rows, {v: made[tuple(sorted(VARIANTS[v][0].items()))] for v in variants}


@key()
def w9_ablation(spark, folder):
    """Every switch by itself and all together, over beams, so that costs can be read at equal quality (speedup_at_quality)."""
    return spark.createDataFrame(ablation(spark, folder)[0], SCHEMA)


def searched(index: SetIndex, work: WorkSet, head: tuple, ef: int) -> list:
    """Qualities and costs of an index."""
    hits = cut(index.search(work.queries, 40, ef))
    rows = [(*head, metric, float(x)) for metric, x in qualities(S.rerank(hits, work.queries, work.vectors, head[-1]), work.qrels, head[-1]).items()]
    return [*rows, (*head, "scored", float(hits.groupBy("query_id").agg(F.max("scored").alias("s")).agg(F.avg("s")).first()[0] or 0)), (*head, "build_seconds", float(sum(index.seconds.values()))), (*head, "sets", float(index.codes.select("set_id").distinct().count())), (*head, "shortcuts", float(index.edges.where("kind = 'shortcut'").count() // 2))]


def rebuilt(spark, folder, workload: str, settings, dataset: str = "w1", k: int = 10, ef: int = 60) -> DataFrame:
    """settings: (param, work set of the whole one, configuration); each is built and searched. What is the same for the whole set in
    several settings is made once: codebooks, which count in no build's time; all but the shortcuts; or all."""
    whole, rows, books, bare, made = work_set(spark, folder, dataset), [], {}, {}, {}
    shares = [replace(config, shortcuts=False, sample=0) for _, _, config in settings]
    for (param, change, config), share in zip(settings, shares, strict=True):
        work = change(whole)
        if work is not whole:
            index = built(work, config)
        elif config in made:
            index = made[config]
        else:
            fitted = (config.k1, config.k2, config.fit_rows, config.iterations, config.seed)
            if fitted not in books:
                books[fitted] = fit_codebooks(whole.fit, config)
            if shares.count(share) == 1 or not config.shortcuts:
                index = built(whole, config, books[fitted])
            else:
                if share not in bare:
                    bare[share] = built(whole, share, books[fitted])
                began = time.time()
                index = replace(bare[share], config=config)
                edges = cut(with_shortcuts(index, whole.train_queries, whole.train))
                index = replace(index, edges=edges, seconds=index.seconds | {"shortcuts": time.time() - began})
            made[config] = index
        rows += searched(index, work, (workload, dataset, "set_graph", param, k), ef)
    return spark.createDataFrame(rows, SCHEMA)


@key()
def w12_vary_degree(spark, folder):
    return rebuilt(spark, folder, "vary_degree", [(f"M={m} ef_construction={e}", lambda w: w, replace(CONFIG, degree=m, ef_construction=e, local="incremental")) for m, e in ((8, 24), (24, 80), (48, 200))])


@key()
def w13_scalability(spark, folder):
    """An eighth, a quarter, half and all of the sets; then of each set's vectors."""
    by = [(f"{of}/{p}", lambda w, p=p, of=of: subset(w, p, of) if p > 1 else w, CONFIG) for of in ("sets", "vectors") for p in (8, 4, 2, 1)]
    return rebuilt(spark, folder, "scalability", by)


@key()
def w14_shortcut_share(spark, folder):
    return rebuilt(spark, folder, "shortcut_share", [(f"sample={p}", lambda w: w, replace(CONFIG, sample=p)) for p in (5, 10, 20, 40)])


@key()
def w15_vary_codebook(spark, folder):
    return rebuilt(spark, folder, "vary_codebook", [(f"k1={k1}", lambda w: w, replace(CONFIG, k1=k1)) for k1 in (128, 256, 512)])


@key()
def index_size(spark, folder):
    """Bytes of each part of the index as written; raw vectors are no part of it."""
    from ..operators import index as I
    from ..operators.iterate import shared

    path = shared(spark, "index")
    I.write_index(built(work_set(spark, folder, "w1")), path)
    return I.index_size(spark, path)


@key()
def insert_index(spark, folder):
    """Quality and links after a tenth of the sets came in later, beside those of one build."""
    work, rows = work_set(spark, folder, "w1"), []
    whole = built(work)
    from ..operators import index as I

    late = F.pmod(F.xxhash64("set_id", F.lit(3)), F.lit(10)) == 0
    early = replace(work, vectors=cut(work.vectors.where(~late)), train=cut(work.train.where(~late)))
    grown = I.insert_sets(built(early, CONFIG, (whole.fine, whole.coarse)), cut(work.vectors.where(late)))
    for name, index in (("one_build", whole), ("inserted", grown)):
        hits = S.rerank(index.search(work.queries, 40, 60), work.queries, work.vectors, 10)
        rows += [("insert", "w1", name, "", 10, metric, float(x)) for metric, x in qualities(hits, work.qrels, 10).items()]
        rows.append(("insert", "w1", name, "", 10, "edges", float(index.edges.count())))
    return spark.createDataFrame(rows, SCHEMA)
