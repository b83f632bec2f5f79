"""Index on disk, streams against their batch twins, and the plans that large inputs depend on."""

from __future__ import annotations

import io
from contextlib import redirect_stdout

import numpy as np
from pyspark.sql import functions as F

from groupsearch.functions import udtf
from groupsearch.operators import assign, search
from groupsearch.plans import queries as q
from groupsearch.sources import tables
from groupsearch.streaming import arrivals

from .conftest import SMALL


def plan(df) -> str:
    out = io.StringIO()
    with redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def test_index_on_disk(spark, tmp_path):
    index = q.pinv_index(spark, SMALL)
    tables.write_index(index.reps, index.members, {"d": 64, "rep": "pinv"}, str(tmp_path))
    reps, members, meta = tables.read_index(spark, str(tmp_path))
    assert meta == {"d": 64, "rep": "pinv"} and reps.count() == 50 and members.count() == 500
    new = q.vectors(spark, SMALL).where("vec_id < 100").withColumn("vec_id", F.col("vec_id") + 10_000)
    assign.append_batch(spark, str(tmp_path), new, 7)
    assign.append_batch(spark, str(tmp_path), new, 7)  # again: overwrites itself
    _, members, _ = tables.read_index(spark, str(tmp_path))
    assert members.count() == 600 and members.where("batch_id = 7").count() == 100


def test_text_vectors(spark, tmp_path):
    q.vectors(spark, SMALL).limit(5).select("vec_id", F.to_json("vec").alias("vec")).coalesce(1).write.option("quote", '"').csv(f"{tmp_path}/csv")
    assert tables.read_text_vectors(spark, f"{tmp_path}/csv").where("size(vec) = 64").count() == 5


def test_rejects(spark):
    rows = [(1, None), (2, [0.0, 0.0]), (3, [1.0]), (4, [1.0, float("nan")]), (5, [1.0, None]), (6, [1.0, 0.0])]
    ok, bad = tables.validate_vectors(spark.createDataFrame(rows, "vec_id bigint, vec array<double>"), 2)
    assert [r.vec_id for r in ok.collect()] == [6]
    assert {r.vec_id: r.reason for r in bad.collect()} == {1: "null", 2: "zero", 3: "length", 4: "not_finite", 5: "null_element"}


def _arrivals(spark, tmp_path, n=200):
    v = q.vectors(spark, SMALL)
    e = tables.load_table(spark, SMALL, "events").where(f"event_id < {n}").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    rows = arrivals.arrivals_of(e, v, 500)
    for i in range(4):
        rows.where(f"event_id between {i * n // 4} and {(i + 1) * n // 4 - 1}").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    return arrivals.read_arrivals(spark, f"{tmp_path}/in", files=1), rows


def test_stream_fills_units_and_survives_a_restart(spark, tmp_path):
    stream, rows = _arrivals(spark, tmp_path)
    for _ in range(2):  # the second start finds nothing new
        sealed = arrivals.fill_units(stream, 10, lanes=2)
        run = sealed.writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/state").trigger(availableNow=True).start()
        run.awaitTermination()
    units = spark.read.parquet(f"{tmp_path}/out").collect()
    x = {r.vec_id: np.array(r.vec) for r in rows.collect()}
    lanes = {r.lane: r.n for r in arrivals.with_lane(rows, 2).groupBy("lane").agg(F.count("*").alias("n")).collect()}
    assert len(units) == sum(n // 10 for n in lanes.values())
    for u in units:
        assert len(u.member_ids) == u.n_members == 10
        assert max(abs(x[i] @ np.array(u.rep) - 1) for i in u.member_ids) < 1e-8
    assert len({i for u in units for i in u.member_ids}) == 10 * len(units)


def test_stream_windows_equal_their_batch_twins(spark, tmp_path):
    stream, rows = _arrivals(spark, tmp_path)
    counted = arrivals.tumbling_arrivals(arrivals.clean(stream, "40 days"), "1 hour")
    run = counted.writeStream.format("memory").queryName("arrivals_by_hour").outputMode("complete").trigger(availableNow=True).start()
    run.awaitTermination()
    got = {(r.start, r.arrivals) for r in spark.table("arrivals_by_hour").collect()}
    assert got == {(r.start, r.arrivals) for r in arrivals.tumbling_arrivals(rows, "1 hour").collect()}


def test_batches_of_a_stream_are_clustered(spark, tmp_path):
    stream, rows = _arrivals(spark, tmp_path)
    run = stream.writeStream.foreachBatch(arrivals.batch_cluster_sink(f"{tmp_path}/index")).option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
    run.awaitTermination()
    members = spark.read.parquet(f"{tmp_path}/index/members")
    assert members.count() == 200 and members.select("batch_id").distinct().count() == 4
    reps = spark.read.parquet(f"{tmp_path}/index/reps")
    hits = arrivals.live_search(reps, members, rows, 0.9, 0.99)
    assert hits.where("vec_id = query_id").count() == 200
    pairs = arrivals.interval_join(rows, rows, "60 days")
    assert pairs.where("left_event >= right_event").count() == 0


def test_sql_functions(spark):
    udtf.register(spark)
    q.members(spark, SMALL).createOrReplaceTempView("m")
    got = spark.sql("SELECT unit_id, pinv_rep(vec) AS rep FROM m GROUP BY unit_id").collect()
    want = {r.unit_id: r.rep for r in q.pinv_index(spark, SMALL).reps.collect()}
    assert all(np.allclose(r.rep, want[r.unit_id]) for r in got)


def test_plans(spark):
    native = plan(q.probe_native(spark, SMALL))
    assert "BroadcastNestedLoopJoin" in native and "CartesianProduct" not in native
    sums = plan(q.rep_sum(spark, SMALL))
    assert sums.count("Exchange") <= 2 and "partial_sum" in sums
    clustered = plan(assign.batch_spherical_kmeans(q.vectors(spark, SMALL), 100, n=500))
    assert clustered.count("hashpartitioning") == 1
    assert "WindowGroupLimit" in plan(q.probe_top_units(spark, SMALL))
    scan = plan(search.verify(spark.createDataFrame([(1, 1)], "query_id bigint, unit_id bigint"), q.members(spark, SMALL), q.stated(spark, SMALL)))
    assert "CartesianProduct" not in scan and "label" not in scan
