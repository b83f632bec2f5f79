"""What two-stage search is compared with: mini-batch k-means, inverted cells, a tuned forest, filter-and-refine, hashing."""

from __future__ import annotations

import heapq
import itertools
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import kernels
from ..functions.vectors import dot
from ..sources import tables
from .assign import fits_task, nearest_stored, starting_rows, stored_kmeans
from .represent import sum_representatives
from .search import Index, bounded_broadcast, query_blocks, rank_hits, search

#: Most rows that centroids are fitted on in one task; more are met step by step by all tasks, to the same centroids. Vectors of a
#: tree's node that are met at a time.
FIT_ROWS, FOREST_ROWS = 60_000, 8192


def _fit_rows(table: pa.Table, units: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(rows by id, which of them start as centroids, which of them each step draws), as starting_rows and stored_minibatch take them."""
    table = table.sort_by("vec_id")
    start = np.sort(np.lexsort((table.column("vec_id").to_numpy(), table.column("h").to_numpy()))[:units])
    drawn = np.array(table.column("drawn").to_pylist(), bool)
    return kernels.matrix(table.column("vec")), start, drawn


def _fitted(vectors: DataFrame, units: int, seed: int, drawn: list, fit) -> str:
    """Folder of the centroids that fit(rows, start, drawn) finds in one task that holds all rows."""

    def run(key, table):
        c = fit(*_fit_rows(table, units))
        return pa.table([pa.array(np.arange(len(c))), kernels.vectors_column(c)], names=["unit_id", "rep"])

    rows = vectors.select("vec_id", "vec", F.xxhash64("vec_id", F.lit(seed)).alias("h"), F.array(*drawn).alias("drawn"), F.lit(0).alias("all"))
    return tables.save(rows.groupBy("all").applyInArrow(run, "unit_id bigint, rep array<double>"), "centroids")[1]


def _fits(vectors: DataFrame, n: int) -> bool:
    return n <= FIT_ROWS and fits_task(vectors, n, True)


def minibatch_index(vectors: DataFrame, units: int, batch: int = 10_000, steps: int = 50, seed: int = 0) -> Index:
    """Cells of mini-batch k-means: centroids from seeded batches of all rows, then every vector to its best unit-norm centroid."""
    n = vectors.count()
    if not _fits(vectors, n):
        return cell_index(vectors, stored_minibatch(vectors, n, units, batch, steps, seed))
    return cell_index(vectors, _fitted(vectors, units, seed, [_drawn(n, batch, step, seed) for step in range(steps)], kernels.minibatch_kmeans))


def _drawn(n: int, batch: int, step: int, seed: int):
    """Whether a step draws a row: a hash decides, for about ``batch`` of n."""
    return F.pmod(F.xxhash64("vec_id", F.lit(seed), F.lit(step)), F.lit(1 << 30)) < int(batch / max(n, 1) * (1 << 30))


def stored_minibatch(vectors: DataFrame, n: int, units: int, batch: int, steps: int, seed: int) -> str:
    """Folder of the centroids of mini-batch k-means over all tasks: a step's rows are drawn by a hash, about ``batch`` of n.

    Moving a centre to its rows one by one, by a rate of one over its count, leaves the mean of all its rows: sums do in one step.
    """
    spark = vectors.sparkSession
    state, path = tables.save(starting_rows(vectors, units, "random", seed).withColumn("n", F.lit(0).cast("bigint")), "centroids")
    d = vectors.select(F.size("vec")).first()[0]
    for step in range(steps):
        drawn = vectors.where(_drawn(n, batch, step, seed))
        sums = sum_representatives(nearest_stored(drawn, path, euclidean=True), d=d).select("unit_id", F.col("rep").alias("total"), F.col("n_members").alias("m"))
        c = F.transform(F.arrays_zip("rep", "total"), lambda x: x["rep"] + (x["total"] - F.col("m") * x["rep"]) / (F.col("n") + F.col("m")))
        grown = state.join(sums, "unit_id", "left").select("unit_id", F.coalesce(c, "rep").alias("rep"), (F.col("n") + F.coalesce("m", F.lit(0))).alias("n"))
        state, new = tables.save(grown, "centroids")
        tables.drop(spark, path)
        path = new
        if step % 5 == 4:
            tables.release(spark)
    return path


def cell_index(vectors: DataFrame, path: str) -> Index:
    """An index of cells around stored centroids (unit_id, rep), scaled to unit length; cells without members are left out."""
    reps = vectors.sparkSession.read.parquet(path).select("unit_id", "rep")
    size = F.sqrt(F.aggregate("rep", F.lit(0.0), lambda s, x: s + x * x))
    reps = reps.withColumn("size", size).select("unit_id", F.transform("rep", lambda x: x / F.when(F.col("size") > 0, F.col("size")).otherwise(1.0)).alias("rep"), F.lit(1.0).alias("rep_norm2"))
    members, folder = tables.save(nearest_stored(vectors, path, normalize=True), "cells")
    sizes = members.groupBy("unit_id").agg(F.count("*").alias("n_members"))
    return Index(reps.join(sizes, "unit_id"), members, {"rep": "centroid", "folder": folder})


def ivf_index(vectors: DataFrame, units: int, max_iter: int = 10, seed: int = 0) -> Index:
    """A plain inverted partition: unit-norm mean centroids by k-means, the nearest cells are opened."""
    n = vectors.count()
    if not _fits(vectors, n):
        own = stored_kmeans(vectors, units, "sum", True, "random", max_iter, seed)
        d = vectors.select(F.size("vec")).first()[0]
        out = cell_index(vectors, tables.save(sum_representatives(own, d=d).select("unit_id", "rep"), "centroids")[1])  # sums lie where means do
        tables.drop(vectors.sparkSession, tables.saved_folder(own))
        return out

    def fit(x, start, _):
        own, sums = kernels.spherical_lloyd(x, len(start), "sum", True, seed, max_iter, start=start)
        return kernels.unit_reps(x, own, len(sums), "sum")[0]

    return cell_index(vectors, _fitted(vectors, units, seed, [F.lit(True)], fit))


def ivf_search(index: Index, queries: DataFrame, cells: int, k: int | None = None, min_sim: float | None = None) -> DataFrame:
    return search(index, queries, top_units=cells, k=k, min_sim=min_sim)


def _parts(rows: np.ndarray) -> list[np.ndarray]:
    return [rows[i : i + FOREST_ROWS] for i in range(0, len(rows), FOREST_ROWS)]


def _spread(v: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Mean and variance of every component, some rows at a time."""
    mean = sum(v[part].sum(0) for part in _parts(rows)) / len(rows)
    return mean, sum(((v[part] - mean) ** 2).sum(0) for part in _parts(rows)) / len(rows)


def _children(v: np.ndarray, rows: np.ndarray, branch: int, seed: int, rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """kernels.spherical_lloyd on some rows, by unit-norm sums, some rows at a time."""
    centres = v[rows[np.random.default_rng(seed).permutation(len(rows))[:branch]]].copy()
    own = np.full(len(rows), -1)
    for _ in range(rounds):
        got, total, size = [], np.zeros_like(centres), np.zeros(len(centres), np.int64)
        for part in _parts(rows):
            x = np.asarray(v[part])
            near = kernels.Nearest(x)
            near.add(centres, np.arange(len(centres)))
            sums, n = kernels.unit_reps(x, near.unit, len(centres), "sum")
            got.append(near.unit)
            total += sums
            size += n
        new = np.concatenate(got)
        if (new == own).all():
            break
        held = size > 0
        length = np.linalg.norm(total[held], axis=1, keepdims=True)
        centres, own = total[held] / np.where(length > 0, length, 1), (np.cumsum(held) - 1)[new]
    return own, centres


class Tree:
    """A randomised k-d tree: splits at the mean of one of the five widest coordinates, so trees of a forest differ."""

    def __init__(self, v: np.ndarray, leaf: int, rng: np.random.Generator):
        self.v = v
        self.split: list[tuple[int, float, int, int] | np.ndarray] = []
        stack: list[tuple[np.ndarray, int, int]] = [(np.arange(len(v)), -1, 0)]
        while stack:
            rows, parent, side = stack.pop()
            at = len(self.split)
            if parent >= 0:
                axis, cut, *kids = self.split[parent]
                kids[side] = at
                self.split[parent] = (axis, cut, *kids)
            mean, spread = _spread(v, rows) if len(rows) > leaf else (None, np.zeros(1))
            if not spread.any():
                self.split.append(rows)
                continue
            axis = int(rng.choice(np.argsort(spread)[-5:]))
            cut = float(mean[axis])
            left = np.concatenate([v[part, axis] < cut for part in _parts(rows)])
            if not left.any() or left.all():
                self.split.append(rows)
                continue
            self.split.append((axis, cut, -1, -1))
            stack += [(rows[~left], at, 1), (rows[left], at, 0)]


class ClusterTree:
    """A hierarchical k-means tree: every inner node splits its rows by a few spherical k-means rounds into ``branch`` children."""

    def __init__(self, v: np.ndarray, leaf: int, rng: np.random.Generator, branch: int = 8):
        self.split: list[tuple[np.ndarray, list[int]] | np.ndarray] = [np.arange(len(v))]
        stack = [0]
        while stack:
            at = stack.pop()
            rows = self.split[at]
            if len(rows) <= max(leaf, branch):
                continue
            own, centres = _children(v, rows, branch, int(rng.integers(1 << 30)), 5)
            if len(centres) < 2:
                continue
            kids = list(range(len(self.split), len(self.split) + len(centres)))
            self.split += [rows[own == j] for j in range(len(centres))]
            self.split[at] = (centres, kids)
            stack += kids


def cluster_query(trees: list[ClusterTree], q: np.ndarray, checks: int) -> np.ndarray:
    """Rows met by best-bin-first search, the centre with the largest product first."""
    return next(cluster_rows(trees, q, [checks]))


def cluster_rows(trees: list[ClusterTree], q: np.ndarray, limits: list[int]) -> Iterator[np.ndarray]:
    """The same at each of several rising numbers of checks, in one search: a shorter search is the beginning of a longer one."""
    heap = [(0.0, t, 0) for t in range(len(trees))]
    seen: set[int] = set()
    for checks in limits:
        while heap and len(seen) < checks:
            _, t, at = heapq.heappop(heap)
            node = trees[t].split[at]
            while isinstance(node, tuple):
                s = (node[0] @ q).tolist()
                best = s.index(max(s))
                for j, kid in enumerate(node[1]):
                    if j != best:
                        heapq.heappush(heap, (-s[j], t, kid))
                node = trees[t].split[node[1][best]]
            seen.update(node.tolist())
        yield np.fromiter(sorted(seen), np.int64)


def forest_query(trees: list[Tree], q: np.ndarray, checks: int) -> np.ndarray:
    """Rows met by best-bin-first search over all trees until so many were checked."""
    return next(forest_rows(trees, q, [checks]))


def forest_rows(trees: list[Tree], q: np.ndarray, limits: list[int]) -> Iterator[np.ndarray]:
    """The same at each of several rising numbers of checks, in one search."""
    heap = [(0.0, t, 0) for t in range(len(trees))]
    seen: set[int] = set()
    q = q.tolist()
    for checks in limits:
        while heap and len(seen) < checks:
            miss, t, at = heapq.heappop(heap)
            split = trees[t].split
            node = split[at]
            while isinstance(node, tuple):
                axis, cut, left, right = node
                gap = q[axis] - cut
                near, far = (left, right) if gap < 0 else (right, left)
                heapq.heappush(heap, (miss + gap * gap, t, far))
                node = split[near]
            seen.update(node.tolist())
        yield np.fromiter(sorted(seen), np.int64)


def forest_ann(vectors: DataFrame, queries: DataFrame, trees: int = 4, leaf: int = 16, checks: int = 256, k: int = 10, parts: int | None = None, seed: int = 0, algorithm: str = "kd") -> DataFrame:
    """query_id, vec_id, sim, hit_rank, checked: a forest over all vectors, or one for each of several parts, built and searched where it lies.

    part_checked: distances computed for the query in the part. Parts are dealt by a hash of the id, and a task holds one; the
    queries are one block (see search.query_blocks).
    """
    parts = parts or 1
    (_, shared), *more = query_blocks(queries)
    if more:
        raise ValueError("more than a block of queries")

    def run(key, table):
        table = table.sort_by("vec_id")
        ids, v = table.column("vec_id").to_numpy(), kernels.matrix(table.column("vec"))
        make, ask = (Tree, forest_query) if algorithm == "kd" else (ClusterTree, cluster_query)
        forest = [make(v, leaf, np.random.default_rng([seed, t])) for t in range(trees)]
        out = []
        for query, q in zip(*shared.value, strict=True):
            rows = ask(forest, q, checks)
            s = v[rows] @ q
            best = np.lexsort((ids[rows], -s))[:k]
            out += [(int(query), int(ids[rows[i]]), float(s[i]), len(rows)) for i in best]
        kinds = [pa.int64(), pa.int64(), pa.float64(), pa.int64()]
        return pa.table([pa.array([r[i] for r in out], kind) for i, kind in enumerate(kinds)], names=["query_id", "vec_id", "sim", "part_checked"])

    placed = vectors.select("vec_id", "vec", F.pmod(F.xxhash64("vec_id"), F.lit(parts)).alias("part"))
    hits = placed.groupBy("part").applyInArrow(run, "query_id bigint, vec_id bigint, sim double, part_checked bigint")
    return rank_hits(hits, k)


@dataclass
class Tuned:
    trees: int
    checks: int
    precision: float
    ratio: float
    cost: float
    leaf: int = 16
    algorithm: str = "kd"


#: Trees, checks, sizes of leaves and algorithms that are tried.
GRID = ((1, 4, 8), (32, 128, 512, 2048), (16,), ("kd",))


def tune_forest(
    vectors: DataFrame, queries: DataFrame, truth: DataFrame, n: int, target_precision: float = 0.95, build_weight: float = 0.01, memory_weight: float = 0.0, k: int = 1, grid=GRID
) -> list[Tuned]:
    """Every grid point with its precision against the truth's best hit, and weighted cost; the first meets the target at least cost."""
    out = []
    want = truth.where("hit_rank = 1").select("query_id", F.col("vec_id").alias("best"))
    hits, path = forest_grid(vectors, queries, n, grid)
    first = hits.groupBy("place", "query_id").agg(F.min(F.struct((-F.col("sim")).alias("s"), "vec_id", "part_checked")).alias("h"))
    got = first.join(want, "query_id").groupBy("place").agg(F.avg((F.col("h.vec_id") == F.col("best")).cast("int")).alias("p"), F.avg("h.part_checked").alias("c"))
    found = {r.place: r for r in got.collect()}
    tables.drop(vectors.sparkSession, path)
    for place, (trees, checks, leaf, algorithm) in enumerate(itertools.product(*grid)):
        row = found[place]
        ratio = row.c / n
        out.append(Tuned(trees, checks, row.p, ratio, ratio + build_weight * trees + memory_weight * trees, leaf, algorithm))
    return sorted(out, key=lambda t: (t.precision < target_precision, t.cost))


def forest_grid(vectors: DataFrame, queries: DataFrame, n: int, grid, seed: int = 0) -> tuple[DataFrame, str]:
    """place, query_id, vec_id, sim, part_checked: the best hit of each query at every grid point, numbered as by itertools.product;
    and the folder of the vectors, which the caller drops.

    One forest over all vectors, however many they are: a task builds each tree of one leaf size and algorithm once, on vectors that
    stay in a file of the shared folder. Forests of fewer trees are its first ones, and searches with fewer checks the beginnings of
    the longest.
    """
    spark = vectors.sparkSession
    (_, shared), *more = query_blocks(queries)
    if more:
        raise ValueError("more than a block of queries")
    path = f"{tables.shared_dir(spark)}/forest-{uuid.uuid4().hex}"
    vectors.select("vec_id", "vec").orderBy("vec_id").write.parquet(f"{path}/sorted")
    spark.range(0, 1, 1, 1).mapInArrow(lambda batches: _as_matrix(batches, f"{path}/sorted"), "id bigint").count()
    tables.drop(spark, f"{path}/sorted")
    sizes, limits, leaves, algorithms = grid
    places = {point: i for i, point in enumerate(itertools.product(*grid))}
    jobs = list(itertools.product(algorithms, leaves))
    rising = sorted(limits)
    names, kinds = ["place", "query_id", "vec_id", "sim", "part_checked"], [pa.int32(), pa.int64(), pa.int64(), pa.float64(), pa.int64()]

    @tables.tidy
    def run(batches):
        for algorithm, leaf in [jobs[i] for b in batches for i in b.column(0).to_pylist()]:
            ids, v = tables.open_matrix(f"{path}/matrix")
            make, ask = (Tree, forest_rows) if algorithm == "kd" else (ClusterTree, cluster_rows)
            forest = [make(v, leaf, np.random.default_rng([seed, t])) for t in range(max(sizes))]
            out = []
            for query, q in zip(*shared.value, strict=True):
                for trees in sizes:
                    for checks, rows in zip(rising, ask(forest[:trees], q, [min(c, n) for c in rising]), strict=True):
                        s = v[rows] @ q
                        best = np.lexsort((ids[rows], -s))[0]
                        out.append((places[trees, checks, leaf, algorithm], int(query), int(ids[rows[best]]), float(s[best]), len(rows)))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], kind) for i, kind in enumerate(kinds)], names)

    asked = spark.range(0, len(jobs), 1, len(jobs))
    return asked.mapInArrow(run, "place int, query_id bigint, vec_id bigint, sim double, part_checked bigint"), path


def _as_matrix(batches, path: str):
    for b in batches:
        if b.num_rows:
            tables.store_matrix(path, "matrix")
        yield b


def filter_refine_search(vectors: DataFrame, queries: DataFrame, alpha0: float, bits: int = 4) -> DataFrame:
    """Range search in two stages: products of quantised components bound the true one, only pairs whose upper bound passes are computed."""
    step = 2.0 / (1 << bits)
    cell = F.transform("vec", lambda x: F.floor((x + 1) / step).cast("double"))
    coded = vectors.withColumn("low", F.transform(cell, lambda c: c * step - 1))
    asked = bounded_broadcast(queries.select("query_id", "qvec"))
    # a component lies in [low, low + step]: the end that its query component's sign favours bounds the product
    upper = F.aggregate(F.zip_with("low", "qvec", lambda lo, q: F.when(q >= 0, q * (lo + step)).otherwise(q * lo)), F.lit(0.0), lambda s, x: s + x)
    likely = coded.join(asked, upper >= alpha0)
    return likely.select("query_id", "vec_id", dot("vec", "qvec").alias("sim")).where(F.col("sim") >= alpha0)


def lsh_search(vectors: DataFrame, queries: DataFrame, alpha0: float, tables: int = 8, width: float = 0.5, seed: int = 0) -> DataFrame:
    """Range search by bucketed random projections; unit vectors of product alpha0 lie sqrt(2 - 2 alpha0) apart."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    a = vectors.select("vec_id", array_to_vector("vec").alias("features"))
    b = queries.select("query_id", array_to_vector("qvec").alias("features"))
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=width, numHashTables=tables, seed=seed).fit(a)
    pairs = model.approxSimilarityJoin(a, b, (2 - 2 * alpha0) ** 0.5 + 1e-9, "dist")
    return pairs.select(F.col("datasetB.query_id").alias("query_id"), F.col("datasetA.vec_id").alias("vec_id"), (1 - F.col("dist") ** 2 / 2).alias("sim"))
