"""Streams of arriving vectors: windows of arrivals, units that fill as items come, index batches, live search."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import kernels
from ..operators.assign import batch_spherical_kmeans
from ..operators.represent import pinv_representatives

ARRIVALS = "event_id bigint, ts timestamp, vec_id bigint, vec array<double>"


def arrivals_of(events: DataFrame, vectors: DataFrame, n: int) -> DataFrame:
    """event_id, ts, vec_id, vec: event i brings vector i modulo n. The vectors' side is the small one of a shuffle or broadcast join."""
    placed = events.select("event_id", "ts", F.pmod("event_id", F.lit(n)).alias("vec_id"))
    return placed.join(vectors.select("vec_id", "vec"), "vec_id").select("event_id", "ts", "vec_id", "vec")


def read_arrivals(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    return spark.readStream.schema(ARRIVALS).option("maxFilesPerTrigger", files).parquet(path)


def clean(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Late rows beyond the delay go, repeats of an event within it too."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def tumbling_arrivals(df: DataFrame, width: str) -> DataFrame:
    return df.groupBy(F.window("ts", width).alias("w")).agg(F.count("*").alias("arrivals")).select(F.col("w.start").alias("start"), "arrivals")


def sliding_arrivals(df: DataFrame, width: str, slide: str) -> DataFrame:
    return df.groupBy(F.window("ts", width, slide).alias("w")).agg(F.count("*").alias("arrivals")).select(F.col("w.start").alias("start"), "arrivals")


def session_arrivals(df: DataFrame, gap: str, key: str = "user_id") -> DataFrame:
    out = df.groupBy(key, F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("arrivals"))
    return out.select(key, F.col("w.start").alias("start"), "arrivals")


def with_lane(df: DataFrame, lanes: int) -> DataFrame:
    """lane = hash of the vector's id: state spreads over lanes, and runs of near copies break up."""
    return df.withColumn("lane", F.pmod(F.xxhash64("vec_id"), F.lit(lanes)))


SEALED = "unit_id bigint, lane bigint, n_members bigint, rep array<double>, rep_norm2 double, member_ids array<bigint>"


def fill_units(stream: DataFrame, unit_size: int, lanes: int = 8, kind: str = "pinv") -> DataFrame:
    """Sealed units: arrivals of a lane fill a unit in order of event_id within each trigger; a full unit is emitted and leaves the state.

    State of a lane: number of units so far and the members of the open one, at most unit_size vectors.
    """

    def step(key, frames, state: GroupState):
        (lane,) = key
        count, ids, flat = state.get if state.exists else (0, [], [])
        ids, flat = list(ids), list(flat)
        rows = pd.concat(list(frames)).sort_values("event_id")
        out = []
        for vec_id, vec in zip(rows["vec_id"], rows["vec"], strict=True):
            ids.append(int(vec_id))
            flat.extend(float(x) for x in vec)
            if len(ids) == unit_size:
                m = kernels.representative(np.array(flat).reshape(unit_size, -1), kind)
                out.append((count * lanes + int(lane), int(lane), unit_size, m.tolist(), float(m @ m), ids))
                count, ids, flat = count + 1, [], []
        state.update((count, ids, flat))
        yield pd.DataFrame(out, columns=["unit_id", "lane", "n_members", "rep", "rep_norm2", "member_ids"])

    keyed = with_lane(stream, lanes).groupBy("lane")
    return keyed.applyInPandasWithState(step, SEALED, "count bigint, ids array<bigint>, flat array<double>", "append", GroupStateTimeout.NoTimeout)


def batch_cluster_sink(path: str, per_unit: int = 10, rep: str = "pinv", seed: int = 0):
    """A foreachBatch function: clusters each micro-batch by itself and writes it under its epoch, so a repeated epoch overwrites itself."""

    def sink(batch: DataFrame, epoch: int) -> None:
        members = batch_spherical_kmeans(batch.select("vec_id", "vec").dropDuplicates(["vec_id"]), 10_000, per_unit, rep, True, seed)
        members = members.withColumn("unit_id", F.col("unit_id") + F.lit(epoch << 40)).drop("batch_id")
        members.write.mode("overwrite").parquet(f"{path}/members/batch_id={epoch}")
        stored = batch.sparkSession.read.parquet(f"{path}/members/batch_id={epoch}")
        pinv_representatives(stored).write.mode("overwrite").parquet(f"{path}/reps/batch_id={epoch}")

    return sink


def live_search(reps: DataFrame, members: DataFrame, arriving: DataFrame, tau: float, alpha0: float) -> DataFrame:
    """Arrivals as queries against an index: a stream-static join when arriving is a stream.

    The representatives are the static side of a theta join and are broadcast: at most BROADCAST_ROWS. Larger indexes take the
    arrivals of a foreachBatch as queries of search.search().
    """
    from ..functions.vectors import dot
    from ..operators.search import bounded_broadcast

    queries = arriving.select(F.col("event_id").alias("query_id"), F.col("vec").alias("qvec"))
    positives = queries.join(bounded_broadcast(reps.select("unit_id", "rep")), dot("rep", "qvec") > tau)
    pairs = positives.join(members.select("unit_id", "vec_id", "vec"), "unit_id")
    return pairs.select("query_id", "vec_id", dot("vec", "qvec").alias("sim")).where(F.col("sim") >= alpha0)


def interval_join(left: DataFrame, right: DataFrame, within: str) -> DataFrame:
    """Pairs of arrivals of one vector, the right within a time after the left; both may be streams with watermarks."""
    a = left.select(F.col("event_id").alias("left_event"), F.col("ts").alias("left_ts"), F.col("vec_id").alias("left_vec"))
    b = right.select(F.col("event_id").alias("right_event"), F.col("ts").alias("right_ts"), F.col("vec_id").alias("right_vec"))
    near = (F.col("left_vec") == F.col("right_vec")) & (F.col("right_ts") > F.col("left_ts")) & (F.col("right_ts") <= F.col("left_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, near).select("left_event", "right_event", "left_vec")

