"""Helpers shared by the training-data operators."""

from __future__ import annotations

import contextlib
import ctypes
import functools
import gc
import sys
import tempfile
import uuid

import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

#: ASCII letters that the contracts fold; other letters keep their case.
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()

#: White space of the word rule ``[^\x20\x09-\x0D]+``.
BLANKS = " \t\n\x0b\x0c\r"

_LIBC = ctypes.CDLL("libc.so.6") if sys.platform == "linux" and hasattr(ctypes.CDLL(None), "malloc_trim") else None

#: A small side is broadcast only below this many (estimated) bytes.
BROADCAST_BYTES = 32 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def workspace(spark: SparkSession) -> str:
    """Folder shared by driver and executors, as the session names it; where none is set, a temporary one in local mode, an error on a cluster."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isDefined():
            return held.get()
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="hyperembed-")
        spark.sparkContext.setCheckpointDir(base)
    return base


def new_folder(spark: SparkSession, label: str) -> str:
    return f"{workspace(spark)}/llm-{label}-{uuid.uuid4().hex}"


def stash(df: DataFrame, label: str) -> DataFrame:
    """Write to the shared folder and read back: cuts lineage, survives lost executors."""
    path = new_folder(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def maybe_broadcast(df: DataFrame, row_bytes: int, limit: int = BROADCAST_BYTES) -> DataFrame:
    """Broadcast hint when a count proves that `df` fits in `limit` bytes; otherwise leave the choice to Spark."""
    return F.broadcast(df) if df.count() * row_bytes <= limit else df


def block_bits(df: DataFrame, least: int = 8, most: int = 20, block_bytes: int = 4 << 20) -> int:
    """Bits of a block number such that a block stands for about `block_bytes` of the input, by the planner's estimate of its size."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return max(least, min(most, (size // block_bytes).bit_length()))


def fold_case(c: Column) -> Column:
    """Lower-case A-Z only; null counts as empty."""
    return F.translate(F.coalesce(c, F.lit("")), UPPER, LOWER)


def packed(df: DataFrame, text: str, ident: str) -> DataFrame:
    """`_row` holds every input column, so that internal names cannot clash with the caller's."""
    return df.select(F.struct("*").alias("_row"), F.col(ident).alias("_id"), F.col(text).alias("_text"))


@contextlib.contextmanager
def without_cycles():
    """Large caches of small objects and no reference cycles: the cycle collector would only walk over them, again and again."""
    was = gc.isenabled()
    gc.disable()
    try:
        yield
    finally:
        if was:
            gc.enable()


def give_back() -> None:
    """Return free memory of this Python worker to the system; workers live on, and what one stage held must not weigh on the next."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    if _LIBC is not None:
        _LIBC.malloc_trim(0)


#: Caches (of `functools.cache`) that outlive a task in a Python worker.
HELD: list = []


def drop_held(keeps=None) -> None:
    """Empty the caches of other operators in this worker: a pipeline's next stages run in the same workers."""
    for cache in HELD:
        if cache is not keeps:
            cache.cache_clear()


def give_back_executors(spark: SparkSession) -> None:
    """Let the heaps of the executors shrink to what is in use; a heap that one stage has filled would weigh on the next."""
    tasks = 2 * spark.sparkContext.defaultParallelism
    spark.range(0, tasks, 1, tasks).select(F.expr("reflect('java.lang.System', 'gc')").alias("done")).collect()


def give_back_driver(spark: SparkSession) -> None:
    """The same for the driver: its Python and its JVM, whose compiler and heap keep what the last stage has freed."""
    give_back()
    gateway = spark.sparkContext._gateway
    jvm = gateway.jvm
    jvm.java.lang.System.gc()
    with contextlib.suppress(Py4JError):  # JVMs without this command keep their native memory
        name = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        server = jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer()
        server.invoke(name, "systemTrimNativeHeap", gateway.new_array(jvm.java.lang.Object, 0), gateway.new_array(jvm.java.lang.String, 0))


def tidy(run, keeps=None):
    """A function over batches that gives memory back when its task ends. Of what other tasks have left in the worker, only the cache `keeps` stays."""

    @functools.wraps(run)
    def tidied(batches):
        drop_held(keeps)
        try:
            yield from run(batches)
        finally:
            give_back()

    return tidied


def bounded_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Long texts make Arrow batches of the default 10,000 rows too large for small executors; a smaller setting of the session stays."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if int(spark.conf.get(key)) > rows:
        spark.conf.set(key, str(rows))
