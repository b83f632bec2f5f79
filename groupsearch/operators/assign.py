"""Assignment of vectors to units: random, by arrival, by key, spherical k-means whole or in independent batches."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels
from ..sources import tables
from ..sources.tables import BROADCAST_BYTES
from .represent import representatives, solved

#: Rows of a batch, members of a unit; rows, and bytes of vectors, that one task clusters in memory (which changes no result), if it is
#: one of several, and if it is the only one.
BATCH, PER_UNIT = 10_000, 10
ONE_TASK, TASK_BYTES = 20_000, 48 << 20
ALONE, ALONE_BYTES = 60_000, 112 << 20
#: Bytes of centroids that pass through the driver; more are stored, and tasks read them. Rows met by so many stored centroids at a time.
DRIVER_BYTES, CHUNK, BLOCK = 8 << 20, 4096, 512
#: Bytes of vectors that one task assigns to stored centroids at a time.
PIECE_BYTES = 16 << 20


def units_for(n: int, ratio: float = 0.1) -> int:
    return max(1, -(-int(n * ratio * 1000) // 1000)) if n else 1


def assign_random(vectors: DataFrame, unit_size: int, n: int | None = None, seed: int = 0, mode: str = "hash", batch: int = 100_000) -> DataFrame:
    """vectors with unit_id and batch_id.

    "hash": unit by a seeded hash of the id, no shuffle, sizes vary. "modulo": by the id itself. "exact": units of just unit_size,
    ranked by hash inside hashed batches, so no window spans all rows; the last unit of a batch may be short. n: number of vectors.
    """
    if mode == "exact":
        n = vectors.count() if n is None else n
        batches = max(1, round(n / batch))
        per = -(-n // batches) * 4 // unit_size + 1  # room for units of a batch, so that ids never meet
        h = F.xxhash64(F.col("vec_id"), F.lit(seed))
        placed = vectors.withColumn("batch_id", F.pmod(h, F.lit(batches)))
        rank = F.row_number().over(Window.partitionBy("batch_id").orderBy(F.xxhash64(F.col("vec_id"), F.lit(seed + 1)), "vec_id"))
        return placed.withColumn("unit_id", F.col("batch_id") * per + F.floor((rank - 1) / unit_size))
    n = vectors.count() if n is None else n
    units = max(1, -(-n // unit_size))
    key = F.col("vec_id") if mode == "modulo" else F.xxhash64(F.col("vec_id"), F.lit(seed))
    return vectors.withColumn("unit_id", F.pmod(key, F.lit(units)).cast("bigint")).withColumn("batch_id", F.lit(0).cast("bigint"))


def assign_arrival(arrivals: DataFrame, unit_size: int, lanes: int = 1, order: tuple[str, ...] = ("ts", "event_id")) -> DataFrame:
    """Consecutive arrivals fill a unit, lane by lane; lane = id modulo lanes keeps a window to a part of the rows."""
    lane = F.pmod(F.col(order[-1]), F.lit(lanes))
    rank = F.row_number().over(Window.partitionBy("lane").orderBy(*order))
    return arrivals.withColumn("lane", lane).withColumn("unit_id", F.floor((rank - 1) / unit_size) * lanes + F.col("lane"))


def assign_by_key(vectors: DataFrame, column: str) -> DataFrame:
    """Units by a column: ids in the order of its values (few, broadcast)."""
    keys = vectors.select(column).distinct().withColumn("unit_id", (F.dense_rank().over(Window.orderBy(column)) - 1).cast("bigint"))
    return vectors.join(F.broadcast(keys), column).withColumn("batch_id", F.lit(0).cast("bigint"))


def nearest_unit(vectors: DataFrame, unit_ids: np.ndarray, centroids: np.ndarray) -> DataFrame:
    """vectors with the unit whose centroid has the largest product. Centroids are broadcast: their size is checked."""
    if centroids.nbytes > BROADCAST_BYTES:
        raise ValueError("too many centroids to broadcast; cluster in batches")
    shared = vectors.sparkSession.sparkContext.broadcast((unit_ids, centroids))
    names = ["vec_id", "vec"]

    def run(batches):
        ids, c = shared.value
        for b in batches:
            own = kernels.best_units(kernels.matrix(b.column(1)), c) if b.num_rows else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(ids[own], pa.int64())], [*names, "unit_id"])

    return vectors.select(*names).mapInArrow(run, "vec_id bigint, vec array<double>, unit_id bigint")


def nearest_stored(vectors: DataFrame, path: str, normalize: bool = False, euclidean: bool = False) -> DataFrame:
    """vectors with the unit whose stored representative (unit_id, rep) has the largest product, or the least distance; ties to the smaller.

    Tasks read the representatives from the shared folder, block by block, so their number is bounded by no process's memory.
    """
    names = ["vec_id", "vec"]

    @tables.tidy
    def run(batches):
        for whole in batches:
            for i in range(0, whole.num_rows, CHUNK):
                b = whole.slice(i, CHUNK)
                near = kernels.Nearest(kernels.matrix(b.column(1)))
                for c, ids in centroid_blocks(path, normalize):
                    near.add(c, ids, less=(c**2).sum(1) / 2 if euclidean else None)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(near.unit)], [*names, "unit_id"])

    return vectors.select(*names).mapInArrow(run, "vec_id bigint, vec array<double>, unit_id bigint")


def centroid_blocks(path: str, normalize: bool = False):
    """(representatives, units) of a stored folder, for use inside a task."""
    for block in tables.stored_blocks(path, BLOCK):
        c, ids = kernels.matrix(block.column("rep")), block.column("unit_id").to_numpy()
        if normalize:
            size = np.linalg.norm(c, axis=1, keepdims=True)
            c = c / np.where(size > 0, size, 1)
        yield c, ids


def starting_rows(vectors: DataFrame, units: int, start: str = "random", seed: int = 0) -> DataFrame:
    """unit_id, rep: the rows of smallest id or seeded hash, just so many, named by their ids.

    The bound is found by counting rows by the first bits of what orders them, so no task sorts them all.
    """
    h = F.xxhash64("vec_id", F.lit(seed)) if start == "random" else F.col("vec_id").cast("bigint")
    keyed = vectors.select("vec_id", h.alias("h"))
    low, high = keyed.agg(F.min("h"), F.max("h")).first()
    shift = max(0, ((high or 0) - (low or 0)).bit_length() - 14)
    b = F.floor((F.col("h").cast("decimal(20,0)") - F.lit(low or 0).cast("decimal(20,0)")) / F.lit(1 << shift).cast("decimal(20,0)")).cast("bigint")
    counts = sorted(keyed.groupBy(b.alias("b")).count().collect())
    seen, last = 0, None
    for last, n in counts:  # at most 2**14
        if seen + n >= units:
            break
        seen += n
    edge = keyed.where(b == last).orderBy("h", "vec_id").limit(max(0, units - seen)).agg(F.max(F.struct("h", "vec_id"))).first()[0] if counts else None
    rows = vectors.select(F.col("vec_id").alias("unit_id"), F.col("vec").alias("rep"), h.alias("h"))
    if edge is None:
        return rows.limit(0).drop("h")
    return rows.where((F.col("h") < edge.h) | ((F.col("h") == edge.h) & (F.col("unit_id") <= edge.vec_id))).drop("h")


def _starting_rows_of_batches(vectors: DataFrame, per_unit: int, seed: int, room: int) -> DataFrame:
    """batch_id, unit_id, rep: the rows of smallest seeded hash of each batch, one for so many of its rows, numbered by rising id."""
    keyed = vectors.select("batch_id", "vec_id", F.xxhash64("vec_id", F.lit(seed)).alias("h"))
    place = F.row_number().over(Window.partitionBy("batch_id").orderBy("h", "vec_id"))
    n = F.greatest(F.lit(1), F.floor(F.count("*").over(Window.partitionBy("batch_id")) / per_unit))
    first = keyed.select("batch_id", "vec_id", place.alias("place"), n.alias("n")).where("place <= n")
    number = F.row_number().over(Window.partitionBy("batch_id").orderBy("vec_id")) - 1
    named = first.select("batch_id", "vec_id", (F.col("batch_id") * room + number).alias("unit_id"))
    return vectors.join(named, ["batch_id", "vec_id"]).select("batch_id", "unit_id", F.col("vec").alias("rep"))


def stored_kmeans(vectors: DataFrame, units: int, rep: str, normalize: bool, start: str, max_iter: int, seed: int, per_unit: int = 0, batches: int = 0, room: int = 0) -> DataFrame:
    """spherical_kmeans with vectors and centroids in the shared folder: no process holds them all, the driver none.

    With batches the rows of each batch_id are clustered by themselves, all in the same rounds, and several batches' units are numbered as in
    batch_spherical_kmeans; else units are named by the ids of their first rows.

    A task assigns a stored piece of the vectors and writes each row's unit, product and bound on the products of all others (see
    kernels.Nearest). A round solves and meets again only units whose members changed. Rounds end when no row moves.
    """
    spark = vectors.sparkSession
    base = f"{tables.shared_dir(spark)}/kmeans-{uuid.uuid4().hex}"
    one = vectors.select(F.size("vec")).first()
    if one is None:
        return vectors.select("vec_id", "vec", F.lit(0).cast("bigint").alias("unit_id"), *(["batch_id"] if batches else []))
    rows = max(256, min(8192, PIECE_BYTES // (8 * max(one[0], 1))))
    if batches == 1:
        vectors.select("vec_id", "vec").write.option("maxRecordsPerFile", rows).parquet(f"{base}/pieces/batch_id=0")
    elif batches:
        salt = max(1, -(-room // 2 // rows))
        dealt = vectors.select("vec_id", "vec", "batch_id").repartition(batches * salt, "batch_id", F.pmod(F.xxhash64("vec_id", F.lit(seed + 1)), F.lit(salt)))
        dealt.write.option("maxRecordsPerFile", rows).partitionBy("batch_id").parquet(f"{base}/pieces")
    else:
        vectors.select("vec_id", "vec").write.option("maxRecordsPerFile", rows).parquet(f"{base}/pieces")
    pieces = tables.stored_files(f"{base}/pieces")
    held = spark.read.parquet(f"{base}/pieces").withColumn("batch_id", F.col("batch_id").cast("bigint") if batches else F.lit(0).cast("bigint"))

    def store(reps: DataFrame, name: str) -> None:
        reps = reps.select("unit_id", "rep", (F.floor(F.col("unit_id") / room) if batches > 1 else F.lit(0)).alias("batch_id"))
        reps.write.partitionBy("batch_id").parquet(f"{base}/{name}")

    def units_of(piece: str, name: str, normalized: bool, columns: list[str] | None = None):
        path = f"{base}/{name}/{piece.split('/')[0] if batches else 'batch_id=0'}"
        if not tables.stored_files(path):
            return
        if columns:
            yield from (b.column(0).to_numpy() for b in tables.stored_blocks(path, 1 << 16, columns))
        else:
            yield from centroid_blocks(path, normalized)

    def state(i: int, r: int):
        return tuple(np.concatenate([b.column(k).to_numpy() for b in tables.stored_blocks(f"{base}/state-{r}/{i}.parquet", 1 << 16)]) for k in range(3))

    def vecs(i: int):
        return np.concatenate([kernels.matrix(b.column("vec")) for b in tables.stored_blocks(f"{base}/pieces/{pieces[i]}", 4096, ["vec"])])

    def over(work, schema: str) -> DataFrame:
        @tables.tidy
        def run(batches):
            for i in [i for b in batches for i in b.column(0).to_pylist()]:
                yield from work(i)

        return spark.range(0, len(pieces), 1, len(pieces)).mapInArrow(run, schema)

    def assign(r: int):
        def work(i: int):
            x, old = vecs(i), state(i, r - 1) if r else None
            changed = np.sort(np.concatenate([np.zeros(0, np.int64), *units_of(pieces[i], f"new-{r}", False, ["unit_id"])]))
            normal = normalize and r > 0
            near = kernels.nearest_again(x, old, changed, lambda: units_of(pieces[i], f"new-{r}", normal), lambda: units_of(pieces[i], f"kept-{r}", normal))
            tables.store_file(f"{base}/state-{r}/{i}.parquet", pa.table([near.unit, near.best, near.bound], names=["unit_id", "best", "bound"]))
            moved = near.unit != old[0] if old else np.ones(len(x), bool)
            yield pa.RecordBatch.from_arrays([pa.array(np.union1d(near.unit[moved], old[0][moved] if old else near.unit))], ["unit_id"])

        return work

    def members_of(r: int):
        def work(i: int):
            unit = state(i, r)[0]
            touched = np.sort(np.concatenate([np.zeros(0, np.int64), *(b.column(0).to_numpy() for b in tables.stored_blocks(f"{base}/touched-{r}", 1 << 16))]))
            mine = np.flatnonzero(np.isin(unit, touched))
            x, unit = vecs(i)[mine], unit[mine]
            if rep == "sum":  # partial sums of the piece
                unit, at = np.unique(unit, return_inverse=True)
                x = kernels.unit_reps(x, at, len(unit), "sum")[0]
            for j in range(0, len(unit), 2048):
                yield pa.RecordBatch.from_arrays([pa.array(unit[j : j + 2048]), kernels.vectors_column(x[j : j + 2048])], ["unit_id", "vec"])

        return work

    if batches > 1:
        store(_starting_rows_of_batches(held, per_unit, seed, room), "new-0")
    else:
        store(starting_rows(held, units, start, seed), "new-0")
    for r in range(max_iter):
        touched = over(assign(r), "unit_id bigint").distinct()
        touched.write.parquet(f"{base}/touched-{r}")
        touched = spark.read.parquet(f"{base}/touched-{r}")
        if r:
            for name in (f"state-{r - 1}", f"touched-{r - 1}"):
                tables.drop(spark, f"{base}/{name}")
        if r + 1 == max_iter or touched.isEmpty():
            break
        store(solved(over(members_of(r), "unit_id bigint, vec array<double>"), rep), f"new-{r + 1}")
        if r:  # units of the start without members go
            parts = [spark.read.schema("unit_id bigint, rep array<double>").parquet(f"{base}/{name}-{r}/*") for name in ("new", "kept") if tables.stored_files(f"{base}/{name}-{r}")]
            store(parts[0].unionByName(parts[1]).join(touched, "unit_id", "left_anti") if len(parts) > 1 else parts[0].join(touched, "unit_id", "left_anti"), f"kept-{r + 1}")
        for name in (f"new-{r}", f"kept-{r}"):
            tables.drop(spark, f"{base}/{name}")
        tables.release(spark)

    def rows_of(i: int):
        unit, at = state(i, r)[0], 0
        for b in tables.stored_blocks(f"{base}/pieces/{pieces[i]}", 2048, ["vec_id", "vec"]):
            k = slice(at, at + b.num_rows)
            at += b.num_rows
            batch = [pa.array(np.full(b.num_rows, int(pieces[i].split("/")[0].partition("=")[2]), np.int64))] if batches else []
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), b.column("vec"), pa.array(unit[k]), *batch], ["vec_id", "vec", "unit_id", *(["batch_id"] if batches else [])])

    assigned, _ = tables.save(over(rows_of, "vec_id bigint, vec array<double>, unit_id bigint" + (", batch_id bigint" if batches else "")), "assigned")
    tables.drop(spark, base)
    tables.release(spark)
    return assigned


def spherical_kmeans(
    vectors: DataFrame, units: int, rep: str = "sum", normalize: bool = False, start: str = "first", max_iter: int = 12, seed: int = 0, d: int = 64, folder: str | None = None
) -> DataFrame:
    """vec_id, vec, unit_id after spherical k-means over all vectors.

    start: "first" takes the vectors of smallest id, "random" the smallest by a seeded hash. Units without members drop out. Rounds
    end when no vector moves. Centroids of up to DRIVER_BYTES are broadcast each round, more are stored (see stored_kmeans). With a
    folder every round of the former is written there, which cuts the lineage; else each plan is one round long, as a round depends on
    the last only through its centroids.
    """
    if units * d * 8 > DRIVER_BYTES:
        return stored_kmeans(vectors, units, rep, normalize, start, max_iter, seed)
    order = [F.col("vec_id")] if start == "first" else [F.xxhash64("vec_id", F.lit(seed)), F.col("vec_id")]
    first = vectors.orderBy(*order).limit(units).select("vec").collect()
    c = np.array([r.vec for r in first], float).reshape(len(first), -1)
    ids = np.arange(len(c))
    d = c.shape[1] if len(c) else d
    if not len(c):
        return vectors.select("vec_id", "vec", F.lit(0).cast("bigint").alias("unit_id"))
    last = None
    assigned = vectors
    for i in range(max_iter):
        assigned = nearest_unit(vectors, ids, c)
        if folder:
            path = f"{folder}/kmeans-{uuid.uuid4().hex}-{i}"
            assigned.write.parquet(path)
            assigned = vectors.sparkSession.read.parquet(path)
        if i + 1 == max_iter:
            break
        reps = representatives(assigned, rep, d).orderBy("unit_id").collect()  # as many as units, checked by nearest_unit
        c, ids = np.array([r.rep for r in reps], float), np.array([r.unit_id for r in reps])
        if normalize:
            size = np.linalg.norm(c, axis=1, keepdims=True)
            c = c / np.where(size > 0, size, 1)
        if last is not None and last.shape == c.shape and np.allclose(last, c, atol=1e-12):
            break
        last = c
    return assigned


def fits_task(vectors: DataFrame, n: int, alone: bool = False) -> bool:
    """Whether one task clusters so many of the vectors in memory."""
    if n > (ALONE if alone else ONE_TASK):
        return False
    if n <= 1000:
        return True
    first = vectors.select(F.size("vec")).first()
    return first is None or n * 8 * first[0] <= (ALONE_BYTES if alone else TASK_BYTES)


def batch_spherical_kmeans(
    vectors: DataFrame, batch_size: int = BATCH, per_unit: int = PER_UNIT, rep: str = "pinv", normalize: bool = True, seed: int = 0, max_iter: int = 12, n: int | None = None, empty: str = "drop"
) -> DataFrame:
    """vec_id, vec, unit_id, batch_id: random batches, each clustered by itself.

    A batch has about batch_size rows (its hash decides, whatever the values); its clustering starts from its rows of smallest hash.
    Batches that fit a task take one shuffle and no rounds on the driver; larger ones go round by round over all tasks, to the same
    units (see stored_kmeans; only empty="drop"). Units of different batches never share ids.
    """
    n = vectors.count() if n is None else n
    batches = max(1, round(n / batch_size))
    room = -(-n // batches) * 2  # more units than any batch has
    h = F.xxhash64(F.col("vec_id"), F.lit(seed))
    placed = vectors.select("vec_id", "vec", F.pmod(h, F.lit(batches)).alias("batch_id"))
    if empty == "drop" and not fits_task(vectors, -(-n // batches), batches == 1):
        return stored_kmeans(placed, max(1, n // per_unit), rep, normalize, "random", max_iter, seed, per_unit, batches, room)

    def cluster(key, table):
        table = table.sort_by("vec_id")
        v, batch = kernels.matrix(table.column("vec")), key[0].as_py()
        start = np.sort(np.lexsort((table.column("vec_id").to_numpy(), table.column("h").to_numpy()))[: max(1, len(v) // per_unit)])
        own, _ = kernels.spherical_lloyd(v, len(start), rep, normalize, seed, max_iter, empty, start)
        units = pa.array(own + batch * room, pa.int64())
        return pa.table([table.column("vec_id"), table.column("vec"), units, pa.array([batch] * len(v), pa.int64())], names=["vec_id", "vec", "unit_id", "batch_id"])

    return placed.withColumn("h", h).groupBy("batch_id").applyInArrow(cluster, "vec_id bigint, vec array<double>, unit_id bigint, batch_id bigint")


def append_batch(spark, path: str, new: DataFrame, batch_id: int, **options) -> None:
    """Clusters new vectors by themselves, in batches of bounded size, and adds them to an index on disk.

    What is there stays untouched, a repeat overwrites itself.
    """
    from .represent import pinv_representatives

    members = batch_spherical_kmeans(new, **options)
    members = members.withColumn("unit_id", F.col("unit_id") + F.lit(batch_id << 40)).withColumn("batch_id", F.lit(batch_id).cast("bigint"))
    target = f"{path}/members/batch_id={batch_id}"
    members.drop("batch_id").sortWithinPartitions("unit_id").write.mode("overwrite").parquet(target)
    stored = spark.read.parquet(target)
    pinv_representatives(stored).write.mode("overwrite").parquet(f"{path}/reps/batch={batch_id}")
