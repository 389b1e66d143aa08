"""The whole index: codebooks, pruned memberships with a cutoff of each set's own, the bridged graph, shortcuts from training pairs.

Every part is a table of its own and none holds a raw vector, so a search reads codes and adjacency and re-ranking alone reads vectors.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.distance import fixed_point
from ..plans.limits import small
from . import clusters as C
from . import graph as G
from . import search as S
from .iterate import cut, dropped, stored

PARTS = ("fine", "coarse", "parents", "codes", "idf", "membership", "edges", "entries")


@dataclass(frozen=True)
class IndexConfig:
    """k1, k2: None for what codebook_sizes says. cutoff: tree (each set's own number of clusters, learnt from training pairs) or
    fixed. sample: per cent of the training pairs that give shortcuts."""

    k1: int | None = None
    k2: int | None = None
    fit_rows: int = 200_000
    iterations: int = 10
    cutoff: str = "tree"
    r: int = 3
    r_max: int = 10
    degree: int = 24
    ef_construction: int = 80
    local: str = "exact"
    edge: str = "qemd"
    solver: str = "exact"
    bridge_mode: str = "reserve"
    build_mode: str = "parallel"
    shortcuts: bool = True
    sample: int = 20
    f_prime: int = 10
    t: int = 4
    seed: int = 42


@dataclass
class SetIndex:
    config: IndexConfig
    fine: DataFrame
    coarse: DataFrame
    parents: DataFrame
    codes: DataFrame
    idf: DataFrame
    profiles: DataFrame
    membership: DataFrame
    edges: DataFrame
    entries: DataFrame
    seconds: dict = field(default_factory=dict)

    def route(self, queries: DataFrame, t: int | None = None) -> DataFrame:
        t = t or self.config.t
        return S.query_clusters(S.centroid_scores(queries, self.coarse, t), t)

    def search(self, queries: DataFrame, k: int, ef: int, t: int | None = None, multi_path: bool = True, guard: bool = True, engine: str | None = None) -> DataFrame:
        """(query_id, set_id, score, rnk, ...) by quantized scores. engine None: the kernel while the index is of a size that a task
        can hold, supersteps beyond it."""
        from ..plans.limits import engine_for

        routed = cut(self.route(queries, t))
        entries = routed.join(small(self.entries), "cluster_id").select("query_id", "cluster_id", "set_id")
        coded = C.assign_codes(queries, self.fine)
        if (engine or engine_for(self.edges, self.codes)) == "kernel":
            bags = coded.groupBy("query_id").agg(F.sort_array(F.collect_list("code")).alias("codes"))
            return S.search_kernel(bags, routed, entries, self.edges, self.membership, self.codes, self.fine, k, ef, multi_path, guard)
        used = coded.select(F.col("code").alias("a")).distinct().join(self.fine.select(F.col("code").alias("a"), "center"), "a")
        other = self.fine.select(F.col("code").alias("b"), F.col("center").alias("_c"))
        sims = used.join(small(other)).select("a", "b", S.dot("center", "_c").alias("s"))
        return S.search_frontier(entries, self.edges, self.membership, routed, cut(coded.drop("v")), self.codes, cut(sims), k, ef)

    def topk(self, queries: DataFrame, vectors: DataFrame, k: int, ef: int, rerank_k: int, **options) -> DataFrame:
        return S.rerank(self.search(queries, rerank_k, max(ef, rerank_k), **options), queries, vectors, k)


def _unit(codebook: DataFrame) -> DataFrame:
    """Centres at length one, in fixed point."""
    norm = F.sqrt(F.reduce("center", F.lit(0.0), lambda s, x: s + x * x))
    return codebook.select(F.col("code").cast("int").alias("code"), fixed_point(F.transform("center", lambda x: x / F.greatest(norm, F.lit(1e-12)))).alias("center"))


def fit_codebooks(vectors: DataFrame, config: IndexConfig) -> tuple[DataFrame, DataFrame]:
    """(fine, coarse): k-means over a hash sample of at most about fit_rows vectors; k-means over the fine centres, each weighted by
    the sampled vectors that are nearest to it."""
    n = vectors.count()
    k1, k2 = C.codebook_sizes(max(n, 1))
    k1, k2 = config.k1 or min(k1, max(8, n // 8)), config.k2 or k2
    share = min(1.0, config.fit_rows / max(n, 1))
    part = vectors.where(F.pmod(F.xxhash64("set_id", "vec_no"), F.lit(10_000)) < int(share * 10_000)) if share < 1 else vectors
    fine = cut(_unit(C.fit_kmeans(part, k1, 1.0, config.seed, config.iterations)))
    weight = C.assign_codes(part.select("set_id", "vec_no", "v"), fine).groupBy("code").agg(F.count("*").cast("double").alias("w"))
    heavy = fine.join(small(weight), "code").select(F.col("code").alias("set_id"), F.lit(0).alias("vec_no"), F.col("center").alias("v"), "w")
    return fine, cut(_unit(C.fit_kmeans(heavy, k2, 1.0, config.seed, config.iterations, "w")))


def local_graphs(membership: DataFrame, codes: DataFrame, fine: DataFrame, config: IndexConfig) -> DataFrame:
    """Half-edges of all clusters. sequential: a job for each cluster, one after the other; it gives the same edges."""
    build = lambda members: G.local_edges(members, codes, fine, config.degree, config.edge, config.local, config.ef_construction, solver=config.solver)
    if config.build_mode == "parallel":
        return build(membership)
    parts = [cut(build(membership.where(F.col("cluster_id") == r["cluster_id"]))) for r in membership.select("cluster_id").distinct().orderBy("cluster_id").collect()]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionAll(p)
    return out


def sampled_pairs(train: DataFrame, percent: int) -> DataFrame:
    """Nested samples: a pair that is in one of a smaller share is in all of a larger one."""
    return train.where(F.conv(F.substring(F.md5(F.concat_ws("-", F.col("query_id").cast("string"), F.col("set_id").cast("string"))), 1, 4), 16, 10).cast("long") * 100 < 65536 * percent)


def build_index(vectors: DataFrame, config: IndexConfig = IndexConfig(), train_queries: DataFrame | None = None, train: DataFrame | None = None, codebooks: tuple[DataFrame, DataFrame] | None = None) -> SetIndex:
    """vectors: (set_id, vec_no, v). train_queries: (query_id, vec_no, v) and train: (query_id, set_id) give the cutoff tree and the
    shortcuts; without them every set has the r best clusters and the graph no shortcuts. codebooks: fitted elsewhere."""
    seconds, began = {}, time.time()

    def done(stage: str) -> None:
        nonlocal began
        seconds[stage], began = time.time() - began, time.time()

    fine, coarse = codebooks or fit_codebooks(vectors, config)
    parents = cut(C.fine_parents(fine, coarse))
    done("codebooks")
    codes = cut(C.assign_codes(vectors.select("set_id", "vec_no", "v"), fine).select("set_id", "vec_no", "code"))
    tf = C.term_counts(codes.join(small(parents), "code"))
    idf = cut(C.inverse_counts(tf, codes.select("set_id").distinct().count()))
    profiles = cut(C.profile(tf, idf))
    done("profiles")
    routed = cut(S.query_clusters(S.centroid_scores(train_queries, coarse, config.t), config.t)) if train is not None else None
    membership = C.top_clusters(profiles, config.r)
    if config.cutoff == "tree" and train is not None and not train.isEmpty():
        features = cut(C.cutoff_features(profiles, config.r_max))
        model = C.fit_cutoff(C.cutoff_labels(train, profiles, routed, config.r_max), features)
        membership = C.adaptive_clusters(model, profiles, features)
    membership = cut(membership)
    done("membership")
    local = stored(local_graphs(membership, codes, fine, config), "local")  # the merge reads it twice
    edges = cut(G.merge_bridges(local, membership, config.degree, config.bridge_mode))
    dropped(local)
    edges = cut(edges.select("src", "dst", "dist", F.when(F.col("reserved") == 1, "bridge").otherwise("near").alias("kind")))
    done("graph")
    first = cut(membership.groupBy("cluster_id").agg(F.min_by("set_id", F.struct(F.md5(F.col("set_id").cast("string")), F.col("set_id"))).alias("set_id")))
    index = SetIndex(config, fine, coarse, parents, codes, idf, profiles, membership, edges, first, seconds)
    if config.shortcuts and train is not None:
        index.edges = cut(with_shortcuts(index, train_queries, train))
    done("shortcuts")
    return index


def with_shortcuts(index: SetIndex, train_queries: DataFrame, train: DataFrame) -> DataFrame:
    """The edges and those that tie a training query's first hit to its answer, where a search of the graph itself missed the answer
    and both ends have room."""
    config = index.config
    some = cut(sampled_pairs(train, config.sample))
    asked = train_queries.join(small(some.select("query_id").distinct()), "query_id", "left_semi")
    hits = cut(index.search(asked, config.f_prime, max(40, config.f_prime)).select("query_id", "set_id", "score", "rnk"))
    pairs = G.admit_shortcuts(G.shortcut_candidates(hits, some, index.edges, config.f_prime), index.edges, config.degree + config.degree // 4)
    both = pairs.select(F.col("u").alias("src"), F.col("v").alias("dst")).unionAll(pairs.select(F.col("v").alias("src"), F.col("u").alias("dst")))
    return index.edges.unionAll(both.select("src", "dst", F.lit(None).cast("double").alias("dist"), F.lit("shortcut").alias("kind")))


def write_index(index: SetIndex, path: str) -> None:
    """A folder of Parquet tables. Memberships and edges are laid out by what a search looks up."""
    for name in PARTS:
        df, out = getattr(index, name), f"{path}/{name}"
        if name == "membership":
            df.repartition("cluster_id").sortWithinPartitions("cluster_id", "set_id").write.mode("overwrite").partitionBy("cluster_id").parquet(out)
        elif name in ("edges", "codes"):
            by = "src" if name == "edges" else "set_id"
            df.repartitionByRange(by).sortWithinPartitions(by).write.mode("overwrite").parquet(out)
        else:
            df.write.mode("overwrite").parquet(out)


def read_index(spark: SparkSession, path: str, config: IndexConfig = IndexConfig()) -> SetIndex:
    parts = {name: spark.read.parquet(f"{path}/{name}") for name in PARTS}
    parts["membership"] = parts["membership"].select("set_id", F.col("cluster_id").cast("int").alias("cluster_id"), "rnk")
    return SetIndex(config, profiles=None, **parts)


def index_size(spark: SparkSession, path: str) -> DataFrame:
    """(part, bytes) on disk, raw vectors excluded since the index has none."""
    jvm, rows = spark._jvm, []
    for name in PARTS:
        p = jvm.org.apache.hadoop.fs.Path(f"{path}/{name}")
        rows.append((name, p.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(p).getLength()))
    return spark.createDataFrame(rows, "part string, bytes long")


def insert_sets(index: SetIndex, vectors: DataFrame) -> SetIndex:
    """The index with new sets: codes by the standing codebooks, clusters through the fine codes' parents and the standing statistics,
    and links to the nearest members of those clusters. Old sets are compared with new ones alone, never with each other again."""
    config = index.config
    codes = cut(C.assign_codes(vectors.select("set_id", "vec_no", "v"), index.fine).select("set_id", "vec_no", "code"))
    tf = C.term_counts(codes.join(small(index.parents), "code"))
    fresh = cut(C.top_clusters(C.profile(tf, index.idf), config.r))
    members = cut(index.membership.select("set_id", "cluster_id", "rnk").unionAll(fresh))
    all_codes = cut(index.codes.unionAll(codes))
    touched = members.join(small(fresh.select("cluster_id").distinct()), "cluster_id", "left_semi")
    found = cut(G.linked_edges(fresh, touched, all_codes, index.fine, config.degree, config.edge, solver=config.solver))
    old = index.edges.where("kind <> 'shortcut'").select("src", "dst", "dist", F.lit(-1).alias("via"))
    merged = G.merge_bridges(old.unionAll(found), members, config.degree, config.bridge_mode)
    edges = merged.select("src", "dst", "dist", F.when(F.col("reserved") == 1, "bridge").otherwise("near").alias("kind")).unionAll(index.edges.where("kind = 'shortcut'"))
    first = members.groupBy("cluster_id").agg(F.min_by("set_id", F.struct(F.md5(F.col("set_id").cast("string")), F.col("set_id"))).alias("set_id"))
    return SetIndex(config, index.fine, index.coarse, index.parents, all_codes, index.idf, None, members, cut(edges), cut(first), dict(index.seconds))
