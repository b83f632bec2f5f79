"""Connected components of a distributed edge table by alternating large-star and small-star steps; of few edges in one task."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Workspace, tidy

#: Edges that one task joins up.
FEW_EDGES = 250_000


def _large(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v"))).distinct()


@tidy
def _join_up(batches):
    """node, root of all edges in the batches: a forest whose trees are joined by their least nodes."""
    above: dict[int, int] = {}

    def root(x: int) -> int:
        while (y := above.get(x, x)) != x:
            z = above.get(y, y)
            above[x] = z
            x = z
        return x

    for b in batches:
        for u, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            u, v = root(u), root(v)
            if u != v:
                above[max(u, v)] = min(u, v)
    nodes = list(above)
    yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array([root(x) for x in nodes], pa.int64())], ["node", "root"])


def connected_components(edges: DataFrame, work: Workspace, most: int = 60) -> DataFrame:
    """node, root for every node of edges (bigint columns u, v; loops and repeats allowed) but the roots: the smallest nodes reachable.

    At most FEW_EDGES edges are joined up by one task. Of more, each round is written to the shared folder, so plans stay short and lost executors cost one round at most. Rounds grow with
    the logarithm of the longest path. Both steps reduce to minima by key, combined before they are shuffled.
    """
    now = work.save(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges-0")
    if now.limit(FEW_EDGES + 1).count() <= FEW_EDGES:
        out = work.save(now.coalesce(1).mapInArrow(_join_up, "node bigint, root bigint"), "roots")
        work.drop("edges-0")
        return out
    seen = None
    for i in range(1, most + 1):
        step = work.save(_small(_large(now)), f"edges-{i}")
        work.drop(f"edges-{i - 1}")
        now = step
        mark = now.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0))).first()
        if mark == seen or not mark[0]:
            break
        seen = mark
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
