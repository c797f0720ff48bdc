"""Scratch tables, batches and small helpers shared by the operators of this folder."""

from __future__ import annotations

import atexit
import ctypes
import shutil
import tempfile
import threading
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space that separates words: space, tab, line feed, vertical tab, form feed, return.
WHITE = r"[\x20\x09-\x0D]+"

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

_own_scratch: dict[str, str] = {}
_mine = threading.local()


def _staged() -> list[str]:
    """Tables that this thread has staged; queries in other threads keep theirs."""
    if not hasattr(_mine, "tables"):
        _mine.tables = []
    return _mine.tables


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where it is unset and Spark runs in one JVM, a temporary folder does; on a cluster
    that would be a machine-local folder, so there it is an error.
    """
    shared = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if shared:
        return shared.rstrip("/")
    if spark.sparkContext.master.partition("[")[0] != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    app = spark.sparkContext.applicationId
    if app not in _own_scratch:
        _own_scratch[app] = tempfile.mkdtemp(prefix="veilstat-")
        atexit.register(shutil.rmtree, _own_scratch[app], ignore_errors=True)
    return _own_scratch[app]


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/{name}-{uuid.uuid4().hex}"
    # The table stands for the plan from here on: its shuffle files can go with the write.
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(_CLEANUP, before)
    _staged().append(path.removeprefix("file://"))
    return spark.read.schema(df.schema).parquet(path)


def staged_tables() -> int:
    """How many tables are staged just now; a mark for :func:`drop_staged`."""
    return len(_staged())


def drop_staged(spark: SparkSession, mark: int = 0, keep: DataFrame | None = None) -> None:
    """Delete the tables staged since ``mark``, but for the one that ``keep`` reads."""
    files = [] if keep is None else keep.inputFiles()
    tables = _staged()
    kept = [p for p in tables[mark:] if any(p in f for f in files)]
    hadoop = spark._jvm.org.apache.hadoop.fs
    for name in tables[mark:]:
        if name not in kept:
            path = hadoop.Path(name)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    tables[mark:] = kept


def small_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Keep Arrow batches of whole texts small; a run-time setting, read when a stage starts."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))


def tidy() -> None:
    """Give memory that a finished task held back to the system: Python workers live on."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library frees by itself
        pass


def texts_of(column) -> pa.Array:
    """A text column with nulls as empty strings."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return pc.fill_null(column, "")


def raw_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all rows end to end, and the row offsets (rows + 1 of them), without copies."""
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    if data is None:
        return np.zeros(0, np.uint8), offs - offs[0]
    return np.frombuffer(data, dtype=np.uint8)[offs[0] : offs[-1]], offs - offs[0]


def slices(offsets: np.ndarray, most: int = 1 << 20) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``most`` bytes each, or of one longer row."""
    at, n = 0, len(offsets) - 1
    while at < n:
        end = int(np.searchsorted(offsets, offsets[at] + most, side="right")) - 1
        end = min(max(end, at + 1), n)
        yield at, end
        at = end


def text_slices(batch: pa.RecordBatch, text: str = "text") -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """(rows, their bytes, their offsets) for pieces of a batch of about 1 MB of text."""
    column = texts_of(batch.column(text))
    data, offs = raw_bytes(column)
    for a, b in slices(offs):
        yield batch.slice(a, b - a), data[offs[a] : offs[b]], offs[a : b + 1] - offs[a]


#: Rows of ids or fingerprints that are broadcast at most: tens of MB, whatever the corpus.
BROADCAST_ROWS = 200_000


def sized(df: DataFrame, hint: str | None = "shuffle_hash", most: int = BROADCAST_ROWS) -> DataFrame:
    """A narrow side of a join: broadcast when a count shows that it is small, else shuffled.

    Give a staged table, as it is counted first (up to the bound).
    """
    if df.limit(most + 1).count() <= most:
        return F.broadcast(df)
    return df.hint(hint) if hint else df


def only(df: DataFrame, *names: str) -> DataFrame:
    """Just these columns, whatever others there are."""
    return df.select(*[F.col(f"`{n}`") for n in names])
