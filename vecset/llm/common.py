"""Shared plumbing: written tables in the cluster's shared folder, Arrow helpers, clean inputs."""

from __future__ import annotations

import ctypes
import functools
import os
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a new one where it is unset (tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise ValueError("spark.checkpoint.dir is unset: a cluster's machines have no other folder in common")
        found = f"file://{tempfile.mkdtemp(prefix='shared-')}"
        spark.conf.set("spark.checkpoint.dir", found)
    return found.rstrip("/")


def written(df: DataFrame, name: str) -> DataFrame:
    """Cuts the lineage: writes df as Parquet into the shared folder and reads it back."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop_written(df: DataFrame) -> None:
    """Deletes the folder of a table that written() returned and that no later plan reads."""
    spark = df.sparkSession
    for f in df.inputFiles()[:1]:
        path = spark._jvm.org.apache.hadoop.fs.Path(f).getParent()
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


#: Bytes of rows that Spark hands to a Python worker at once. Its own bound is 10,000 rows, which is 34 MB of common documents.
BATCH_BYTES = 4 << 20


def small_batches(df: DataFrame) -> None:
    """Holds the Arrow batches of the session's plans to BATCH_BYTES from here on; a smaller bound stays."""
    conf, name = df.sparkSession.conf, "spark.sql.execution.arrow.maxBytesPerBatch"
    held = str(conf.get(name))
    if not held.isdigit() or int(held) > BATCH_BYTES:
        conf.set(name, str(BATCH_BYTES))


def texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id long, text string not null); a null text is empty. Other columns are left out."""
    small_batches(docs)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))


def binaries(parts: list) -> pa.Array:
    return pa.array([np.ascontiguousarray(p).tobytes() for p in parts], type=pa.binary())


def column_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string or binary column in one array, and n + 1 offsets into it. Nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    flat = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return flat, off - off[0]


def pieces_of(batch: pa.RecordBatch, most_bytes: int, column: str = "text", most_rows: int = 1 << 20):
    """Slices of a batch that hold most_bytes of text each, or one row: bounds the memory of what follows."""
    _, off = column_bytes(batch.column(column))
    lo = 0
    while lo < batch.num_rows:
        hi = min(max(lo + 1, int(np.searchsorted(off, off[lo] + most_bytes, "right")) - 1), lo + most_rows)
        yield batch.slice(lo, hi - lo)
        lo = hi


def ranges(starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """Concatenation of arange(start, start + len)."""
    lens = np.asarray(lens, np.int64)
    ends = np.cumsum(lens)
    return np.repeat(np.asarray(starts, np.int64) - (ends - lens), lens) + np.arange(ends[-1] if len(ends) else 0)


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: spreads every input bit over the output."""
    x = x.astype(np.uint64, copy=True)
    with np.errstate(over="ignore"):
        x ^= x >> np.uint64(31)
        x *= np.uint64(0x7FB5D329728EA185)
        x ^= x >> np.uint64(27)
        x *= np.uint64(0x81DADEF4BC2DD44D)
        x ^= x >> np.uint64(33)
    return x


#: Stands for a null id inside Arrow kernels.
NO_ID = -(1 << 63)


def ids_of(column: pa.Array) -> np.ndarray:
    return (column.fill_null(NO_ID) if column.null_count else column).to_numpy(zero_copy_only=False).astype(np.int64)


def null_again(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.when(F.col(c) != NO_ID, F.col(c)) for c in columns})


_kept: dict = {}


def kept(name: tuple, make):
    """What a worker process keeps from task to task, one thing at a time: a task of another operator frees what the last one kept."""
    if name not in _kept:
        nothing_kept()
        _kept[name] = make()
    return _kept[name]


def nothing_kept() -> None:
    """Frees what an earlier task of this worker process kept, and gives the memory that it freed back to the machine."""
    _kept.clear()
    pa.default_memory_pool().release_unused()
    libc = _libc()
    if libc:
        libc.malloc_trim(0)


@functools.cache
def _libc():
    """The C library where it has these calls. From now on arrays of a megabyte and more are mapped by themselves, so that freeing them
    frees memory; else the library keeps up to tens of megabytes of each kind."""
    try:
        libc = ctypes.CDLL(None)
        libc.mallopt(-3, 1 << 20)
        libc.malloc_trim  # noqa: B018
    except (OSError, AttributeError):
        return None
    return libc


def fresh(df: DataFrame, name: str) -> str:
    """A column name that df doesn't have, whatever the case of its letters."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def free(df: DataFrame) -> None:
    """Lets Spark delete the shuffle files of plans that are no longer referenced."""
    import gc

    gc.collect()
    df.sparkSession._jvm.System.gc()
