"""Size checks before anything small goes to the driver or to every task, and the choice of plans that follows."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MOST_ROWS = 2_000_000
MOST_BYTES = 256 << 20


class TooLarge(ValueError):
    pass


def driver_table(df: DataFrame, most_rows: int = MOST_ROWS) -> pa.Table:
    """A bounded table (queries, codebooks) as Arrow on the driver. Larger ones are refused: split the queries into blocks."""
    table = df.limit(most_rows + 1).toArrow()
    if table.num_rows > most_rows or table.nbytes > MOST_BYTES:
        raise TooLarge(f"{table.num_rows} rows, {table.nbytes} bytes: more than a task should hold")
    return table


def small(df: DataFrame, most_bytes: int = 64 << 20, most_rows: int = 100_000) -> DataFrame:
    """df with a broadcast hint if its estimated size is within most_bytes, or, where Spark has no estimate (a table made from rows of
    the driver, say), if it has at most most_rows; else as it is, for a shuffled join."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    if size > 1 << 50 and df.limit(most_rows + 1).count() <= most_rows:
        size = 0
    return F.broadcast(df) if size <= most_bytes else df


def distance_tier(k1: int, most_table: int = 4096) -> str:
    """How code distances are had: a table of all pairs, or a matrix of the centroids in each task."""
    return "table" if k1 <= most_table else "matrix"


def search_engine(index_bytes: int, n_queries: int) -> str:
    """kernel: the whole index in each task, queries dealt out; frontier: supersteps of joins."""
    return "kernel" if index_bytes <= MOST_BYTES else "frontier"


def engine_for(edges: DataFrame, codes: DataFrame) -> str:
    """search_engine by the bytes that a task would hold: 16 for an edge, 8 for a set's code, which come as a list for each set; there
    may be no more sets than rows that driver_table takes."""
    n = codes.agg(F.count("*").alias("codes"), F.countDistinct("set_id").alias("sets")).first()
    return search_engine(16 * edges.count() + 8 * n["codes"] if n["sets"] <= MOST_ROWS else 1 << 62, 0)
