"""Ground distances and set scores as columns and relational plans.

Vectors are arrays of doubles, or of longs in fixed point (components times SCALE, rounded), where sums are exact in any order.
Distance form: smaller is nearer. Similarities are inner products of unit vectors.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.limits import small

SCALE = 1000


def fixed_point(v: Column) -> Column:
    return F.transform(v, lambda x: F.round(x.cast("double") * SCALE).cast("long"))


def dot(a: Column | str, b: Column | str) -> Column:
    """Inner product; keeps longs exact."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return F.reduce(F.zip_with(a, b, lambda x, y: x * y), F.lit(0).cast("long"), lambda s, x: s + x)


def dot_real(a: Column | str, b: Column | str) -> Column:
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return F.reduce(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def squared_l2(a: Column | str, b: Column | str) -> Column:
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return F.reduce(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0).cast("long"), lambda s, x: s + x)


def ground_dist(a: Column | str, b: Column | str, ground: str = "cosine") -> Column:
    """cosine: 1 - inner product (unit vectors); l2; chord: sqrt(2 - 2 inner product), a metric of the same order."""
    if ground == "cosine":
        return 1.0 - dot_real(a, b)
    if ground == "chord":
        return F.sqrt(F.greatest(F.lit(0.0), 2.0 - 2.0 * dot_real(a, b)))
    if ground == "l2":
        a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
        return F.sqrt(F.reduce(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    raise ValueError(f"unknown ground distance {ground}")


def nearness(a: Column | str, b: Column | str, ground: str) -> Column:
    """Fixed-point nearness, larger is nearer: inner product, or minus the squared distance."""
    return dot(a, b) if ground == "cosine" else -squared_l2(a, b)


def pair_nearness(queries: DataFrame, vectors: DataFrame, ground: str = "cosine") -> DataFrame:
    """(query_id, q_no, set_id, vec_no, s) for all vector pairs. The queries are a stated set: they go to every block of vectors."""
    q = queries.select("query_id", F.col("vec_no").alias("q_no"), F.col("v").alias("_q"))
    return vectors.join(small(q)).select("query_id", "q_no", "set_id", "vec_no", nearness("_q", "v", ground).alias("s"))


def chamfer(pairs: DataFrame, agg: str = "sum") -> DataFrame:
    """(query_id, set_id, score): for each query vector its best match in the set, summed or averaged."""
    best = pairs.groupBy("query_id", "set_id", "q_no").agg(F.max("s").alias("best"))
    fold = F.sum("best") if agg == "sum" else F.sum("best") / F.count("*")
    return best.groupBy("query_id", "set_id").agg(fold.alias("score"))


def chamfer_nested(q: Column | str, p: Column | str) -> Column:
    """The same on nested arrays, with higher-order functions alone."""
    q, p = (F.col(x) if isinstance(x, str) else x for x in (q, p))
    return F.reduce(F.transform(q, lambda a: F.array_max(F.transform(p, lambda b: dot(a, b)))), F.lit(0).cast("long"), lambda s, x: s + x)
