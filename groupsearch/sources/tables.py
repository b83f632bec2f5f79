"""Reading tables and vectors, checking them, and the index on disk."""

from __future__ import annotations

import atexit
import contextlib
import functools
import gc
import itertools
import json
import re
import shutil
import tempfile
import time
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

VECTORS = T.StructType([T.StructField("vec_id", T.LongType()), T.StructField("vec", T.ArrayType(T.DoubleType()))])
REPS = T.StructType(
    [
        T.StructField("unit_id", T.LongType()),
        T.StructField("rep", T.ArrayType(T.DoubleType())),
        T.StructField("n_members", T.LongType()),
        T.StructField("rep_norm2", T.DoubleType()),
    ]
)
#: Most rows and bytes of a side that is broadcast.
BROADCAST_ROWS, BROADCAST_BYTES = 1_000_000, 200 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a temporary one in local mode where that is unset."""
    known = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if known:
        return known.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    made = tempfile.mkdtemp(prefix="groupsearch-")
    atexit.register(shutil.rmtree, made, ignore_errors=True)
    return f"file://{made}"


def save(df: DataFrame, name: str) -> tuple[DataFrame, str]:
    """(df read again, its folder) from a new folder in the shared one: cuts the lineage and keeps rows out of the driver."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path), path


def drop(spark: SparkSession, path: str) -> None:
    """Deletes a folder that no later step reads."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def saved_folder(df: DataFrame, name: str = r"\w+") -> str | None:
    """The folder that save made, by name, if the frame reads just this one; what is derived from saved rows reads it too."""
    at = {f.rpartition("/")[0] for f in df.inputFiles()}
    return at.pop() if len(at) == 1 and re.search(rf"/{name}-[0-9a-f]{{32}}$", next(iter(at))) else None


def release(spark: SparkSession) -> None:
    """Lets Spark delete shuffle files and broadcasts of finished steps now rather than when the driver next collects its garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


@contextlib.contextmanager
def batches_of(spark: SparkSession, rows: int):
    """Arrow batches of at most so many rows while wide rows are met; what runs inside must be computed at once."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, min(rows, int(before)) if int(before) > 0 else rows)
    try:
        yield
    finally:
        spark.conf.set(name, before)


def now(df: DataFrame) -> DataFrame:
    """A small result, computed now: its shuffles and caches need not last until the whole plan runs."""
    out = df.sparkSession.createDataFrame(df.collect(), df.schema)
    release(df.sparkSession)
    return out


def _store(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else f"file://{path}")


def stored_files(path: str) -> list[str]:
    """Parquet files of a folder and those inside it, as paths from the folder on; none if it is not there."""
    from pyarrow import fs

    store, root = _store(path)
    return sorted(f.path[len(root.rstrip("/")) + 1 :] for f in store.get_file_info(fs.FileSelector(root, allow_not_found=True, recursive=True)) if f.path.endswith(".parquet"))


def stored_blocks(path: str, rows: int, columns: list[str] | None = None):
    """Arrow batches of the Parquet files of a folder that executors share, or of one file, for use inside a task."""
    import pyarrow.parquet as pq
    from pyarrow import fs

    store, root = _store(path)
    files = [root] if root.endswith(".parquet") else sorted(f.path for f in store.get_file_info(fs.FileSelector(root)) if f.path.endswith(".parquet"))
    for f in files:
        with store.open_input_file(f) as source:
            yield from pq.ParquetFile(source).iter_batches(rows, columns=columns)


def store_file(path: str, table) -> None:
    """Writes a Parquet file in a folder that executors share, from a task; what a task that is run again writes takes its place."""
    import pyarrow.parquet as pq

    store, at = _store(path)
    store.create_dir(at.rpartition("/")[0])
    part = f"{at}-{uuid.uuid4().hex}"
    with store.open_output_stream(part) as out:
        pq.write_table(table, out)
    store.move(part, at)


def store_matrix(path: str, name: str) -> None:
    """Appends the vectors of a folder's Parquet files, in the order of their names, to files of plain numbers beside it: {name}.ids, {name}.rows."""
    from ..functions import kernels

    store, root = _store(path)
    at = root.rpartition("/")[0]
    with store.open_output_stream(f"{at}/{name}.ids") as ids, store.open_output_stream(f"{at}/{name}.rows") as rows:
        for b in stored_blocks(path, 4096):
            ids.write(b.column("vec_id").to_numpy().tobytes())
            rows.write(kernels.matrix(b.column("vec")).tobytes())


def open_matrix(path: str):
    """(ids, matrix) of store_matrix's files for use inside a task: pages of the file, read as they are needed, not memory of the task.

    A folder that is not a local one is copied to the task's temporary folder first.
    """
    import numpy as np
    from pyarrow import fs

    store, root = _store(path)
    with store.open_input_stream(f"{root}.ids") as f:
        ids = np.frombuffer(f.read(), np.int64)
    if isinstance(store, fs.LocalFileSystem):
        return ids, np.memmap(f"{root}.rows", np.float64, "r").reshape(len(ids), -1)
    with tempfile.TemporaryFile() as copy:
        with store.open_input_stream(f"{root}.rows") as f:
            shutil.copyfileobj(f, copy, 1 << 22)
        copy.flush()
        return ids, np.memmap(copy, np.float64, "r").reshape(len(ids), -1)


def stored_groups(path: str, rows: int):
    """(unit_id, vec_id, vec) blocks of members stored with whole, sorted units in a file; a unit is never cut, whatever the rows asked for."""
    import numpy as np
    import pyarrow as pa

    from ..functions import kernels

    held, last = [], None
    for block in itertools.chain(stored_blocks(path, rows), [None]):
        units = block.column("unit_id").to_numpy() if block is not None else None
        if block is not None and not len(units):
            continue
        # a new block that starts with another unit closes what is held
        if held and (block is None or units[0] != last):
            t = pa.Table.from_batches(held)
            yield t.column("unit_id").to_numpy(), t.column("vec_id").to_numpy(), kernels.matrix(t.column("vec"))
            held = []
        if block is not None:
            cut = int(np.searchsorted(units, units[-1])) if not held else 0
            if cut:
                part = block.slice(0, cut)
                yield part.column("unit_id").to_numpy(), part.column("vec_id").to_numpy(), kernels.matrix(part.column("vec"))
            held.append(block.slice(cut))
            last = units[-1]


def tidy(run):
    """A map over batches that gives its worker's freed memory back when it is done: workers are reused, several stand side by side."""

    @functools.wraps(run)
    def tidied(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return tidied


def give_back() -> None:
    """Returns freed memory of this Python process to the system."""
    import ctypes

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # where the C library is another one
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def load_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def load_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, vec (array<double>) of the embeddings."""
    return load_table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("vec"))


def invalid_reason(vec: Column, d: int) -> Column:
    """Why a vector can't be indexed, or null."""
    return (
        F.when(vec.isNull(), "null")
        .when(F.size(vec) != d, "length")
        .when(F.exists(vec, lambda x: x.isNull()), "null_element")
        .when(F.exists(vec, lambda x: F.isnan(x) | (F.abs(x) == float("inf"))), "not_finite")
        .when(F.aggregate(vec, F.lit(0.0), lambda s, x: s + x * x) == 0, "zero")
    )


def validate_vectors(df: DataFrame, d: int, vec: str = "vec") -> tuple[DataFrame, DataFrame]:
    """(rows that can be indexed, rejects with a reason). Both read the same scan; nothing is shuffled."""
    marked = df.withColumn("reason", invalid_reason(F.col(vec), d))
    return marked.where("reason is null").drop("reason"), marked.where("reason is not null").select("vec_id", "reason")


def read_text_vectors(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    """Vectors written as "[0.1, ...]" in CSV (vec_id, vec) or as JSON rows."""
    if fmt == "json":
        return spark.read.schema(VECTORS).json(path)
    raw = spark.read.schema("vec_id bigint, vec string").option("quote", '"').csv(path)
    return raw.select("vec_id", F.from_json("vec", "array<double>").alias("vec"))


def read_vectors(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    return spark.read.schema(VECTORS).format(fmt).load(path)


def write_index(reps: DataFrame, members: DataFrame, meta: dict, path: str, mode: str = "overwrite") -> None:
    """Members by batch_id, sorted by unit_id so that row groups of other units are skipped; representatives apart; meta as JSON."""
    spark = members.sparkSession
    members.repartition("batch_id").sortWithinPartitions("batch_id", "unit_id").write.mode(mode).partitionBy("batch_id").parquet(f"{path}/members")
    reps.write.mode(mode).parquet(f"{path}/reps")
    row = [(int(time.time() * 1e6), json.dumps(meta))]
    spark.createDataFrame(row, "version bigint, meta string").coalesce(1).write.mode("append").json(f"{path}/meta")


def read_index(spark: SparkSession, path: str, version: int | None = None) -> tuple[DataFrame, DataFrame, dict]:
    """(representatives, members, meta); with a version, the meta as of it."""
    meta = spark.read.schema("version bigint, meta string").json(f"{path}/meta")
    if version is not None:
        meta = meta.where(F.col("version") <= version)
    last = meta.orderBy(F.desc("version")).limit(1).collect()
    return spark.read.parquet(f"{path}/reps"), spark.read.parquet(f"{path}/members"), json.loads(last[0].meta) if last else {}


def write_bucketed(members: DataFrame, table: str, buckets: int) -> None:
    """Members as a table bucketed by unit: verification then joins without shuffling them."""
    members.write.mode("overwrite").bucketBy(buckets, "unit_id").sortBy("unit_id").saveAsTable(table)
