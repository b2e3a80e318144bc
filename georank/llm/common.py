"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import os
import tempfile
import time
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SPACES = " \t\n\x0b\x0c\r"
MASK = (1 << 64) - 1


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words(text: Column) -> Column:
    """Runs of characters other than 0x20 and 0x09-0x0D; null text has none."""
    return F.array_remove(F.split(F.translate(F.coalesce(text, F.lit("")), "\t\n\x0b\x0c\r", "     "), " "), "")


def n_words(text: Column) -> Column:
    return F.size(words(text)).cast("long")


def id_crc(doc_id: Column) -> Column:
    """crc32 of the id as decimal text; a null id counts as the empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary"))


def _shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that the session names. Where it names none, a local session takes a temporary one, a cluster its warehouse."""
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        own = os.path.join(tempfile.gettempdir(), "checkpoints", str(os.getpid())) if sc.master.startswith("local[") or sc.master == "local" else f"{spark.conf.get('spark.sql.warehouse.dir')}/checkpoints"
        sc.setCheckpointDir(folder or own)
    return sc._jsc.sc().getCheckpointDir().get()


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut lineage through the shared checkpoint folder (set here only where the session has none)."""
    _shared_folder(df.sparkSession)
    out = df.checkpoint()
    rested(df.sparkSession)
    return out


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder that all executors and the driver reach."""
    return f"{_shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


_CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def stored(df: DataFrame, name: str = "step") -> DataFrame:
    """df as Parquet in the shared folder, reread. The shuffle files behind it go as soon as it is written."""
    spark = df.sparkSession
    path, before = shared_path(spark, name), spark.conf.get(_CLEAN, None)
    spark.conf.set(_CLEAN, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.unset(_CLEAN) if before is None else spark.conf.set(_CLEAN, before)
    rested(spark)
    out = spark.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


#: Seconds between two collections of the driver's garbage, and when the last one was.
REST = 5
_rested = [0.0]


def rested(spark: SparkSession) -> None:
    """Let the driver's JVM give memory back between steps: many small plans leave garbage that its heap grows by, and freed memory outside the heap that its C library keeps."""
    if time.monotonic() - _rested[0] < REST:
        return
    jvm, new = spark._jvm, spark.sparkContext._gateway.new_array
    jvm.System.gc()
    kind, types, args = jvm.java.lang.Class.forName, new(jvm.java.lang.Class, 4), new(jvm.java.lang.Object, 4)
    for i, name in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
        types[i] = kind(name)
    try:
        args[0], args[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        kind("javax.management.MBeanServer").getMethod("invoke", types).invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), args)
    except Py4JJavaError:  # a JVM without this command
        pass
    _rested[0] = time.monotonic()


def dropped(*steps: DataFrame | None) -> None:
    """Delete what `stored` has written, once its successors stand."""
    for df in steps:
        if df is not None:
            spark = df.sparkSession
            at = spark._jvm.org.apache.hadoop.fs.Path(df.stored_at)
            at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def sliced(batches, column: str, most: int = 2 << 20):
    """Record batches cut so that the column's text has `most` bytes, or is one row."""
    for batch in batches:
        if not batch.num_rows:
            continue
        col = batch.column(batch.schema.get_field_index(column))
        size = pc.fill_null(pc.binary_length(col), 0).to_numpy(zero_copy_only=False)
        total, at = np.cumsum(size), 0
        while at < batch.num_rows:
            base = total[at - 1] if at else 0
            end = max(at + 1, int(np.searchsorted(total, base + most, "right")))
            yield batch.slice(at, end - at)
            at = end
    released()


def released() -> None:
    """Give a worker's freed memory back to the system: workers outlive their tasks, and the next stage's tasks get them."""
    _POWERS.clear()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # a C library without it
        pass


def text_bytes(col) -> tuple[np.ndarray, np.ndarray]:
    """The column's UTF-8 bytes in one array, and each row's offset (nulls are empty)."""
    col = pc.fill_null(col, "" if pa.types.is_string(col.type) or pa.types.is_large_string(col.type) else b"")
    kind = np.int64 if pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type) else np.int32
    _, offsets, data = col.buffers()
    off = np.frombuffer(offsets, kind)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    data = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None and off[-1] > off[0] else np.zeros(0, np.uint8)
    return data, off - off[0]


_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 9, 10, 11, 12, 13]] = True
_BYTE = np.random.default_rng(20240229).integers(1, MASK, 256, dtype=np.uint64) | np.uint64(1)
_ROOTS = (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93)
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def lowered(data: np.ndarray) -> np.ndarray:
    return _LOWER[data]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads all bits."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _powers(root: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    have = _POWERS.get(root)
    if have is None or len(have[0]) < n:
        n = max(n, 1 << 16)

        def run(base: int) -> np.ndarray:
            out = np.empty(n, np.uint64)
            out[0] = 1
            k, b = 1, base
            while k < n:  # doubling: powers [0,k) times base^k
                m = min(k, n - k)
                out[k : k + m] = out[:m] * np.uint64(b)
                b = b * b & MASK
                k += m
            return out

        have = _POWERS[root] = run(root), run(pow(root, -1, 1 << 64))
    return have


class Hasher:
    """64-bit hashes of any substring of `data` by prefix sums, all at once."""

    def __init__(self, data: np.ndarray, which: int = 0):
        self.inverse = _powers(_ROOTS[which], len(data) + 1)[1]
        self.sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(_BYTE[data] * _powers(_ROOTS[which], len(data) + 1)[0][: len(data)], out=self.sums[1:])

    def __call__(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * self.inverse[start] + (end - start).astype(np.uint64))


def word_spans(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of words; the index of each row's first word (rows + 1 entries)."""
    full = off[:-1] < off[1:]
    word = ~_SPACE[data]
    first, last = word.copy(), word.copy()
    first[1:] &= ~word[:-1]
    last[:-1] &= ~word[1:]
    first[off[:-1][full]] = word[off[:-1][full]]
    last[off[1:][full] - 1] = word[off[1:][full] - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, off)
