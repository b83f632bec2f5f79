"""Exact top-k inner-product search: a ball tree for each shard, searched by branch and bound.

A node keeps its centre and radius, so no member scores above <query, centre> + |query| radius. Each query visits first the child
with the larger bound, and a node is left out for every query whose k-th score so far already exceeds it. The k-th scores are
shared: shards are searched in waves, and each wave starts from the k-th scores of all shards before it.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Workspace, bounded_batches, filesystem, tidy

LEAF = 256
#: Queries in one block, rows of a shard, and the share of the shards that each wave ends with.
QUERY_BLOCK, SHARD_ROWS, WAVES = 4096, 65536, (1 / 16, 1 / 4, 1)
_EXACT = float(1 << 53)


class BallTree:
    """Nodes over rows of a matrix, split at the median of the widest coordinate; ids break ties, so the tree is reproducible."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, leaf: int = LEAF):
        self.nodes: list[tuple] = []
        self.evaluated = 0
        order = np.argsort(ids, kind="stable")
        self.ids, self.vectors = ids[order], vectors[order]
        place = np.arange(len(ids))
        stack = [(place, -1)]
        while stack:
            rows, parent = stack.pop()
            at = len(self.nodes)
            v = self.vectors[rows]
            centre = v.mean(0)
            radius = float(np.sqrt(((v - centre) ** 2).sum(1).max()))
            self.nodes.append([centre, radius, None, None])
            if parent >= 0:
                self.nodes[parent][2].append(at)
            if len(rows) <= leaf or radius == 0:
                self.nodes[at][3] = np.sort(rows)
                continue
            self.nodes[at][2] = []
            axis = int(np.argmax(v.max(0) - v.min(0)))
            by = np.argsort(v[:, axis], kind="stable")
            half = len(rows) // 2
            stack += [(rows[by[half:]], at), (rows[by[:half]], at)]

    def search(self, query_ids: np.ndarray, queries: np.ndarray, floor: np.ndarray, k: int):
        """Lists of (query row, id, score): per query the k best by (score, then smaller id), but none below its floor.

        evaluated counts the products with vectors that were computed.
        """
        n = len(queries)
        score = np.full((n, k), -np.inf)
        found = np.full((n, k), np.iinfo(np.int64).max)
        norm = np.sqrt((queries**2).sum(1))
        kth = floor.astype(float).copy()

        def bound(at, active):
            node = self.nodes[at]
            exact = queries[active] @ node[0] + norm[active] * node[1]
            return exact + 1e-9 * (np.abs(exact) + norm[active] * (node[1] + np.abs(node[0]).max()) + 1)

        def visit(at, active, upper):
            open_ = upper >= kth[active]
            active = active[open_]
            if not len(active):
                return
            node = self.nodes[at]
            if node[3] is not None:
                compare(node, active)
                return
            left, right = node[2]
            low, high = bound(left, active), bound(right, active)
            first = low >= high  # these visit the left child first, the others the right one
            visit(left, active[first], low[first])
            visit(right, active[~first], high[~first])
            visit(right, active[first], high[first])
            visit(left, active[~first], low[~first])

        def compare(node, active):
            rows = node[3]
            if not node[1] and len(rows) > k:  # of equal vectors the k smallest ids, and one more for each that is a query's own
                own = np.isin(self.ids[rows], query_ids[active])
                rows = rows[np.cumsum(~own) <= k]
            ids = self.ids[rows]
            s = queries[active] @ self.vectors[rows].T
            self.evaluated += s.size
            s[query_ids[active][:, None] == ids[None, :]] = -np.inf
            if len(rows) > 4 * k:  # those that can be among the k best, ties included
                part = -np.partition(-s, k - 1, axis=1)[:, k - 1]
                keep = s >= np.maximum(part, kth[active])[:, None]
                hit = keep.any(1)
                active, s, keep = active[hit], s[hit], keep[hit]
                if not len(active):
                    return
                s = np.where(keep, s, -np.inf)
            all_s = np.concatenate([score[active], s], 1)
            all_i = np.concatenate([found[active], np.broadcast_to(ids, s.shape)], 1)
            order = np.lexsort((all_i, -all_s), axis=1)[:, :k]
            score[active] = np.take_along_axis(all_s, order, 1)
            found[active] = np.take_along_axis(all_i, order, 1)
            kth[active] = np.maximum(kth[active], score[active][:, k - 1])

        everyone = np.arange(n)
        if len(self.ids):
            visit(0, everyone, bound(0, everyone))
        ok = np.isfinite(score) & (score >= floor[:, None])
        at = np.nonzero(ok)
        return at[0], found[at], score[at]


def integer_vectors(df: DataFrame, id_col: str, vec_col: str, scale: int = 256) -> DataFrame:
    """vec_id and v, floor(scale * x) of each component in double; rows with a null id or vector, or null or non-finite components, go."""
    x = F.col(vec_col)
    bad = F.exists(x, lambda e: e.isNull() | F.isnan(e.cast("double")) | (F.abs(e.cast("double")) == F.lit(float("inf"))))
    ok = df.where(F.col(id_col).isNotNull() & x.isNotNull()).where(~bad)
    return ok.select(F.col(id_col).cast("bigint").alias("vec_id"), F.transform(x, lambda e: F.floor(e.cast("double") * F.lit(scale)).cast("double")).alias("v"))


def _by_width(vectors: pa.ChunkedArray, *columns: pa.ChunkedArray):
    """(width, matrix, columns) of the vectors of each length: vectors of unequal length have no inner product."""
    widths = pc.list_value_length(vectors).to_numpy()
    for width in np.unique(widths):
        if width:
            at = pa.array(np.flatnonzero(widths == width))
            flat = pa.concat_arrays([c.flatten() for c in vectors.take(at).chunks])
            yield int(width), flat.to_numpy(zero_copy_only=False).reshape(len(at), -1), *(c.take(at).to_numpy() for c in columns)


def _query_blocks(folder: str):
    """The saved blocks of queries, one file at a time."""
    import pyarrow.parquet as pq
    from pyarrow import fs

    store, root = filesystem(folder)
    for info in sorted(store.get_file_info(fs.FileSelector(root)), key=lambda i: i.path):
        if info.path.endswith(".parquet"):
            with store.open_input_file(info.path) as f:
                table = pq.read_table(f)
            if table.num_rows:
                yield table


def exact_top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, block: int = QUERY_BLOCK) -> DataFrame:
    """The k highest integer inner products of each query: query_id, rank, vec_id, score; ties go to the smaller vec_id.

    Both inputs: vec_id, v (see integer_vectors). A query meets every row but those with its own id. Rows repeated with one id and
    vector count once; unequal vectors with one id are rows, and queries, of their own. Fewer than k others give fewer rows, empty
    tables give none; vectors of unequal length, or of none, do not meet. Scores must stay below 2**53, else it raises.

    Rows are dealt by a hash of id and vector into shards of about SHARD_ROWS, so equal vectors spread. A task builds the tree of its
    shard once and reads the queries block by block from the shared folder, so neither it nor the driver holds more than a block.
    Shards are searched in three waves; the k-th scores so far are written with the queries for the next one, and only scores that
    reach them leave a task.
    """
    spark = vectors.sparkSession
    bounded_batches(spark)
    work = Workspace(spark, "topk")
    rows = work.save(vectors.select("vec_id", "v").distinct(), "rows")
    asked = work.save(queries.select("vec_id", "v").distinct().withColumn("query", F.monotonically_increasing_id()), "queries")
    n_rows, n_queries = rows.count(), asked.count()
    blocks = max(1, -(-n_queries // block))
    shards = max(1, min(-(-n_rows // 4096), max(spark.sparkContext.defaultParallelism, -(-n_rows // SHARD_ROWS))))
    dealt = rows.withColumn("shard", F.pmod(F.xxhash64("vec_id", "v"), F.lit(shards)).cast("int"))
    best = spark.createDataFrame([], "query bigint, query_id bigint, vec_id bigint, score bigint")
    first = 0
    for wave, share in enumerate(WAVES):
        last = max(first, round(shards * share))
        if last == first:
            continue
        kth = best.groupBy("query").agg(F.min("score").alias("floor"), F.count("*").alias("n")).where(F.col("n") == k).select("query", "floor")
        ready = asked.join(kth, "query", "left").repartitionById(blocks, F.pmod(F.xxhash64("query"), F.lit(blocks)).cast("int"))
        work.save(ready.select("query", "vec_id", F.col("floor").cast("double").alias("floor"), "v"), f"asked-{wave}")
        folder = f"{work.path}/asked-{wave}"

        @tidy
        def run(batches, folder=folder):
            batches = [b for b in batches if b.num_rows]  # a shard, of bounded rows
            if not batches:
                return
            table = pa.Table.from_batches(batches)
            trees = {}
            for width, matrix, ids in _by_width(table.column("v"), table.column("vec_id")):
                trees[width] = BallTree(ids, matrix), float(np.abs(matrix).max())
            for asked in _query_blocks(folder):
                for width, q, query, ids, floor in _by_width(asked.column("v"), asked.column("query"), asked.column("vec_id"), asked.column("floor")):
                    if width not in trees:
                        continue
                    tree, largest = trees[width]
                    if largest * np.abs(q).max() * width >= _EXACT:
                        raise ValueError("inner products beyond 2**53")
                    at, found, score = tree.search(ids, q, np.where(np.isnan(floor), -np.inf, floor), k)
                    columns = [query[at], ids[at], found, score.astype(np.int64)]
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["query", "query_id", "vec_id", "score"])

        mine = dealt.where((F.col("shard") >= first) & (F.col("shard") < last)).withColumn("task", F.col("shard") - first)
        hits = mine.repartitionById(last - first, "task").select("vec_id", "v").mapInArrow(run, "query bigint, query_id bigint, vec_id bigint, score bigint")
        order = Window.partitionBy("query").orderBy(F.desc("score"), "vec_id")
        ranked = best.unionByName(hits).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
        best, first = work.save(ranked.drop("rank"), f"best-{wave}"), last
    order = Window.partitionBy("query").orderBy(F.desc("score"), "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).select("query_id", "rank", "vec_id", "score")
