"""Shared pieces: word splitting on UTF-8 bytes, Arrow blocks and checkpoints.

Words are split on bytes, not on ``str``: ``bytes.lower`` and ``bytes.split``
touch ASCII only, which is what the word rules of this subpackage ask for, and
they run at C speed.
"""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import threading
import zlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text bytes that a Python worker handles at a time.
BLOCK_BYTES = 8 << 20


def _alnum_table() -> bytes:
    out = bytearray(range(256))
    for b in range(128):
        ch = chr(b)
        out[b] = ord(ch.lower()) if ch.isalnum() else 0x20
    return bytes(out)


_ALNUM = _alnum_table()


def alnum_words(data: bytes) -> list[bytes]:
    """Lower-cased runs of ASCII letters, digits and non-ASCII characters."""
    return data.translate(_ALNUM).split()


def space_words(data: bytes) -> list[bytes]:
    """Lower-cased (A-Z only) runs between ASCII white space."""
    return data.lower().split()


def doc_hash(doc_id: Column) -> Column:
    """CRC-32 of the id's decimal text; null ids count as the empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")))


def py_doc_hash(doc_id) -> int:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode())


def texts(column: pa.Array | pa.ChunkedArray) -> list[bytes]:
    """UTF-8 bytes of a string column; null becomes the empty text."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return [b"" if t is None else t for t in column.cast(kind).to_pylist()]


def blocks(batches: Iterable[pa.RecordBatch], column: str = "text", limit: int = BLOCK_BYTES) -> Iterator[pa.RecordBatch]:
    """Cuts and joins batches so that each holds about ``limit`` bytes of text (one row at least)."""
    held, size = [], 0
    for batch in batches:
        if not batch.num_rows:
            continue
        lengths = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_pylist()
        start = 0
        for i, n in enumerate(lengths):
            if size and size + n > limit:
                if i > start:
                    held.append(batch.slice(start, i - start))
                yield _joined(held)
                pa.default_memory_pool().release_unused()
                held, size, start = [], 0, i
            size += n
        held.append(batch.slice(start))
    if held:
        yield _joined(held)
    del held
    _trim()


def _trim() -> None:
    """Gives freed memory back: a worker that waits for its next task shouldn't hold the last one's peak."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError, OSError):  # glibc only
        ctypes.CDLL(None).malloc_trim(0)


def keep_heap() -> None:
    """Has a worker that makes many arrays of some MB keep their memory for the next ones, up to 64 MB."""
    with contextlib.suppress(AttributeError, OSError):  # glibc only
        libc = ctypes.CDLL(None)
        libc.mallopt(-3, 32 << 20)  # M_MMAP_THRESHOLD
        libc.mallopt(-1, 64 << 20)  # M_TRIM_THRESHOLD


def _joined(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
    return parts[0] if len(parts) == 1 else pa.concat_batches(parts)


_checkpoint_lock = threading.Lock()


def shared_folder(spark: SparkSession) -> str:
    """The reliable checkpoint folder of the session, which all executors reach.

    A cluster names it in ``spark.checkpoint.dir``.  Only a local session that
    names none gets a temporary one; anywhere else that is an error.
    """
    sc = spark.sparkContext
    with _checkpoint_lock:
        if not sc._jsc.sc().getCheckpointDir().isDefined():
            named = sc.getConf().get("spark.checkpoint.dir")
            if not named and not sc.master.startswith("local"):
                raise ValueError("spark.checkpoint.dir must name a folder that all executors reach")
            sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="llm-checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def checkpointed(df: DataFrame) -> DataFrame:
    """Cuts the lineage through the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


def drop_checkpoint(df: DataFrame) -> None:
    """Deletes what ``checkpointed`` wrote for a frame that nothing reads any more."""
    plan = df._jdf.queryExecution().logical()
    if plan.getClass().getSimpleName() == "LogicalRDD":
        path = plan.rdd().getCheckpointFile()
        if path.isDefined():
            remove_folder(df.sparkSession, path.get())


def remove_folder(spark: SparkSession, path: str) -> None:
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(conf).delete(target, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def free_names(columns: Iterable[str], *stems: str) -> list[str]:
    """Names that neither the columns nor each other take."""
    taken, out = list(columns), []
    for stem in stems:
        out.append(free_name([*taken, *out], stem))
    return out


def free_name(columns: Iterable[str], stem: str) -> str:
    """A column name that is not taken (Spark compares names without case)."""
    taken, name = {c.lower() for c in columns}, f"_{stem}"
    while name.lower() in taken:
        name = f"_{name}"
    return name
