"""Helpers that the training-data operators share: table reading, shared storage, bounded Arrow batches."""

from __future__ import annotations

import atexit
import contextlib
import functools
import os
import shutil
import tempfile
import uuid

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ARROW_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"
#: Rows of an Arrow batch of texts; most rows of narrow columns that are broadcast.
BATCH_ROWS, BROADCAST_ROWS = 256, 250_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One input table, read by Spark only, so any store Spark knows will do."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bounded_batches(spark: SparkSession) -> None:
    """Arrow batches of at most BATCH_ROWS rows: long texts then stay within a Python worker's memory.

    One value for all operators, as the plans they return run later, so the order of calls does not matter; a smaller setting of the
    caller stays.
    """
    now = int(spark.conf.get(ARROW_ROWS))
    if not 0 < now <= BATCH_ROWS:
        spark.conf.set(ARROW_ROWS, str(BATCH_ROWS))


@contextlib.contextmanager
def batches_of(spark: SparkSession, rows: int):
    """Other batches while a step runs that is written at once."""
    before = spark.conf.get(ARROW_ROWS)
    spark.conf.set(ARROW_ROWS, str(rows))
    try:
        yield
    finally:
        spark.conf.set(ARROW_ROWS, before)


def if_small(df: DataFrame) -> DataFrame:
    """df, marked for broadcast if it has at most BROADCAST_ROWS rows; df should be a saved table of a few narrow columns."""
    return F.broadcast(df) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


def gathered(df: DataFrame) -> DataFrame:
    """A saved table of a few narrow columns, read by one task if it has at most BROADCAST_ROWS rows: grouping it then needs no shuffle."""
    return df.coalesce(1) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a temporary one in local mode where that is unset."""
    set_dir = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if set_dir:
        return set_dir.rstrip("/")
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get().rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    made = tempfile.mkdtemp(prefix="groupsearch-")
    atexit.register(shutil.rmtree, made, ignore_errors=True)
    spark.sparkContext.setCheckpointDir(f"file://{made}")
    return f"file://{made}"


class Workspace:
    """Intermediate tables of one operator call, as Parquet in the shared folder.

    A saved table cuts the lineage: a lost executor costs only the tasks it was running. ``drop`` deletes a table that no later
    step reads; what the returned DataFrame still reads stays until the caller's job is over and it calls ``clear_workspaces``.
    """

    made: list[Workspace] = []

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
        Workspace.made.append(self)

    def save(self, df: DataFrame, name: str) -> DataFrame:
        df.write.mode("overwrite").option("compression", "zstd").parquet(f"{self.path}/{name}")
        relieve_driver(self.spark)
        return self.spark.read.schema(df.schema).parquet(f"{self.path}/{name}")

    def drop(self, *names: str) -> None:
        jvm = self.spark.sparkContext._jvm
        for name in names:
            path = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
            path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)

    def delete(self) -> None:
        self.drop("")

    def release(self) -> None:
        """Lets Spark delete shuffle files of finished steps now rather than at the next collection of the driver's garbage."""
        import gc
        import time

        for _ in range(2):  # one collection finds them, the next follows what the first set free
            gc.collect()
            self.spark.sparkContext._jvm.System.gc()
            time.sleep(0.7)


def clear_workspaces(*keep: Workspace) -> None:
    """Deletes what operators have saved so far but for some workspaces; results that were not written elsewhere are lost with it."""
    for work in [w for w in Workspace.made if w not in keep]:
        work.delete()
        Workspace.made.remove(work)


def filesystem(uri: str):
    """A file system that driver and executors can use without Spark, and the path in it."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


def give_back() -> None:
    """Returns freed memory of this Python worker to the system: workers are reused, and freed arrays stay with them otherwise."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # where the C library is another one
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def relieve_driver(spark: SparkSession) -> None:
    """Returns memory that finished steps have freed in the driver's JVM: its C heap, which compiling hundreds of plans leaves in
    pieces, to the system; garbage of the Java heap once over a third of that heap is in use, as a collection takes a moment."""
    jvm = spark.sparkContext._jvm
    runtime = jvm.java.lang.Runtime.getRuntime()
    if (runtime.totalMemory() - runtime.freeMemory()) * 3 > runtime.maxMemory():
        jvm.System.gc()
    with contextlib.suppress(Py4JError):  # a JVM without that command
        _trim_native_heap(spark)


def _trim_native_heap(spark: SparkSession) -> str:
    """The JVM's own command; its server's class is hidden from py4j, so it is called by the public interface."""
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway
    types, values = gateway.new_array(jvm.java.lang.Class, 4), gateway.new_array(jvm.java.lang.Object, 4)
    for i, kind in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
        types[i] = jvm.java.lang.Class.forName(kind)
    values[0], values[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
    invoke = jvm.java.lang.Class.forName("javax.management.MBeanServerConnection").getMethod("invoke", types)
    return invoke.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), values)


def tidy(run):
    """A map over batches that leaves its worker's memory as it found it."""

    @functools.wraps(run)
    def tidied(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return tidied


def ascii_lower(col):
    """A-Z to a-z, other letters unchanged."""
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def vocabulary(name: str) -> str:
    """Path of an installed public tokenizer file."""
    import public_tokenizers

    return public_tokenizers.path(name)


os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
