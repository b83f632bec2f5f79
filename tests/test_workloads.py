"""Orderings and rates that the methods must show on the given tables."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from groupsearch.functions import features, kernels, theory
from groupsearch.operators import assign, baselines, codes, metrics, represent, search
from groupsearch.plans import queries as q
from groupsearch.plans import workloads as w

from .conftest import MEDIUM, SMALL


def test_no_threshold_opens_all_and_a_high_one_nothing(spark):
    index, asked = q.sum_index(spark, SMALL), q.stated(spark, SMALL)
    n = q.vectors(spark, SMALL).count()
    costs = metrics.query_cost(search.probe(index.reps, asked, -1e9), index.reps, asked).collect()
    assert all(r.ops == r.n_units + n for r in costs)
    hits = search.search(index, asked, tau=-1e9, min_sim=0.3).select("query_id", "vec_id")
    exact = search.exhaustive_search(q.vectors(spark, SMALL), asked, alpha0=0.3).select("query_id", "vec_id")
    assert hits.exceptAll(exact).count() == exact.exceptAll(hits).count() == 0
    costs = metrics.query_cost(search.probe(index.reps, asked, 1e9), index.reps, asked).collect()
    assert len(costs) == asked.count() and all(r.ops == r.n_units and r.n_opened == 0 for r in costs)
    at = [search.search(index, asked, tau=t).count() for t in (0.2, 0.5, 0.9)]
    assert at == sorted(at, reverse=True)


def test_rates_follow_the_model(spark):
    for r in w.roc_planted(spark, MEDIUM).collect():
        assert r.pfp == pytest.approx(r.pfp_model, abs=0.03)
        assert r.pfn == pytest.approx(r.pfn_model, abs=0.06)


def test_pinv_beats_sum_on_random_units_at_high_similarity(spark):
    rows = {(r.kind, r.alpha, r.tau): r for r in w.roc_planted(spark, MEDIUM).collect()}
    assert rows["pinv", 0.9, 0.41].pfn < rows["sum", 0.9, 0.41].pfn
    assert rows["pinv", 0.7, 0.41].pfn < rows["sum", 0.7, 0.41].pfn


def test_imbalance_orderings(spark):
    delta = {(r.family, r.method): r.delta for r in w.imbalance_variants(spark, MEDIUM).collect()}
    for family in ("documents", "conversations", "baskets"):
        assert delta[family, "full-pinv"] < delta[family, "full-sum"]
        assert delta[family, "full-pinv_norm"] <= delta[family, "full-sum_norm"]
        assert 1 <= delta[family, "full-pinv_norm"] < delta[family, "minibatch"]


def test_clustered_units_beat_random_and_batches_lie_between(spark):
    rows = {(r.method, r.opened): r for r in w.batch_assignment(spark, MEDIUM).collect()}
    for k in (1, 5):
        assert rows["random-pinv", k].recall < rows["batch-pinv_norm", k].recall < rows["full-pinv_norm", k].recall + 1e-9


def test_cost_varies_less_with_pinv(spark):
    rows = {r.method: r for r in w.cost_spread(spark, MEDIUM).collect()}
    assert rows["full-pinv"].ratio_std < rows["full-sum"].ratio_std


def test_large_units_are_poor_in_streams(spark):
    rows = {(r.n, r.kind): r for r in w.streaming_sizes(spark, MEDIUM).collect()}
    assert rows[10, "pinv"].ratio < rows[10, "sum"].ratio  # cheaper at its threshold
    assert rows[500, "sum"].ratio > 0.9 and rows[500, "pinv"].ratio > 0.9
    assert all(rows[n, "pinv"].recall >= 0.7 for n in (10, 20))


def test_simulated_caps_follow_the_model(spark):
    for r in w.cap_simulation(spark, SMALL).collect():
        assert r.mean_s1 == pytest.approx(r.e1, rel=0.06, abs=0.03)
        if r.kind == "sum":
            assert r.var_s0 == pytest.approx(r.v0, rel=0.3)
        else:  # the model bounds the norm from below
            assert r.var_s0 > 0.7 * r.v0


def test_low_intrinsic_dimension_costs_more_than_modelled(spark):
    rows = {r.family: r for r in w.low_dimension(spark, MEDIUM).collect()}
    assert rows["trigrams"].effective_d < 10 < 50 < rows["embeddings"].effective_d
    assert rows["trigrams"].ratio > 2 * rows["trigrams"].ratio_model
    assert rows["embeddings"].ratio == pytest.approx(rows["embeddings"].ratio_model, rel=0.15)


def test_dense_and_native_probes_agree(spark):
    a = {(r.query_id, r.unit_id): r.score for r in q.probe_threshold(spark, SMALL).collect()}
    b = {(r.query_id, r.unit_id): r.score for r in q.probe_native(spark, SMALL).collect()}
    assert a == b and a


def test_online_and_batch_representatives_agree(spark):
    a = {r.unit_id: r.rep_norm2 for r in w.rep_online(spark, SMALL).collect()}
    b = {r.unit_id: r.rep_norm2 for r in q.pinv_index(spark, SMALL).reps.collect()}
    assert all(a[u] == pytest.approx(b[u], abs=1e-6) for u in b)


def test_wide_sums_take_the_arrow_path(spark):
    rng = np.random.default_rng(0)
    x = rng.standard_normal((40, 200))
    df = spark.createDataFrame([(i, i % 3, v.tolist()) for i, v in enumerate(x)], "vec_id bigint, unit_id bigint, vec array<double>")
    for r in represent.sum_representatives(df, d=200).collect():
        assert np.allclose(r.rep, x[r.unit_id :: 3].sum(0)) and r.n_members == len(x[r.unit_id :: 3])


def test_units_grow_by_appending(spark):
    base = q.members(spark, SMALL)
    old, new = base.where("vec_id % 2 = 0"), base.where("vec_id % 2 = 1")
    grown = {r.unit_id: r for r in represent.append_to_units(represent.sum_representatives(old), new).collect()}
    for r in represent.sum_representatives(base).collect():
        assert np.allclose(grown[r.unit_id].rep, r.rep) and grown[r.unit_id].n_members == r.n_members


def test_exact_units_have_their_size(spark):
    sizes = [r["count"] for r in assign.assign_random(q.vectors(spark, SMALL), 16, mode="exact", batch=200).groupBy("unit_id").count().collect()]
    assert sum(sizes) == 500 and sizes.count(16) >= len(sizes) - 3 and max(sizes) == 16


def test_empty_tables_and_odd_sizes(spark):
    none = q.vectors(spark, SMALL).limit(0)
    placed = none.withColumn("unit_id", F.lit(0).cast("bigint"))
    index = search.Index(represent.sum_representatives(placed), placed)
    assert search.search(index, q.stated(spark, SMALL), tau=0.1).count() == 0
    assert search.search(q.sum_index(spark, SMALL), q.stated(spark, SMALL).limit(0), tau=0.1).count() == 0
    assert assign.batch_spherical_kmeans(none).count() == 0
    many = search.search(q.sum_index(spark, SMALL), q.stated(spark, SMALL), top_units=1000, k=1000)
    assert many.groupBy("query_id").count().agg(F.min("count")).first()[0] == 500


def test_distances_of_codes_are_products_of_signs(spark):
    coded = codes.encode(q.vectors(spark, SMALL).limit(2), 64).collect()
    a, b = (np.where(np.array(r.vec) >= 0, 1, -1) for r in coded)
    differing = sum(int(x ^ y).bit_count() for x, y in zip(coded[0].code, coded[1].code, strict=True))
    assert a @ b == 64 - 2 * differing


def test_average_precision_by_hand(spark):
    hits = spark.createDataFrame([(1, 10, 1), (1, 11, 2), (1, 12, 3)], "query_id bigint, vec_id bigint, hit_rank int")
    truth = spark.createDataFrame([(1, 10), (1, 12), (1, 99)], "query_id bigint, vec_id bigint")
    assert metrics.average_precision(hits, truth).first().ap == pytest.approx((1 + 2 / 3) / 3)


def test_imbalance_and_cost_by_hand(spark):
    rows = [(u,) for u, n in ((1, 3), (2, 1), (3, 2), (4, 4)) for _ in range(n)]
    got = metrics.imbalance(spark.createDataFrame(rows, "unit_id bigint"), 4).first()
    assert got.delta == pytest.approx(1.2) and got.var_size == pytest.approx(1.25)
    reps = spark.createDataFrame([(1, 3), (2, 1), (3, 2), (4, 4)], "unit_id bigint, n_members bigint")
    positives = spark.createDataFrame([(7, 1), (7, 3)], "query_id bigint, unit_id bigint")
    asked = spark.createDataFrame([(7,), (8,)], "query_id bigint")
    costs = {r.query_id: r for r in metrics.complexity_ratio(metrics.query_cost(positives, reps, asked), 10).collect()}
    assert (costs[7].ops, costs[7].ratio, costs[8].ops) == (9, 0.9, 4)


def test_generators(spark):
    x = kernels.matrix(features.sphere(spark, 500, 32, 3).orderBy("vec_id").toArrow().column("vec"))
    again = kernels.matrix(features.sphere(spark, 500, 32, 3).repartition(7).orderBy("vec_id").toArrow().column("vec"))
    assert np.allclose(np.linalg.norm(x, axis=1), 1) and np.allclose(x, again)
    c = kernels.matrix(features.cap(spark, 500, 32, 0.5, 3).toArrow().column("vec"))
    assert c[:, 0].min() >= 0.5 and c[:, 0].mean() == pytest.approx(theory.cap_moment(1, 0.5, 32), abs=0.01)


def test_pairs_of_the_join_are_found_from_either_side(spark):
    v = q.vectors(spark, SMALL)
    index, x = q.sum_index(spark, SMALL), kernels.matrix(v.orderBy("vec_id").toArrow().column("vec"))
    unit = {r.vec_id: r.unit_id for r in index.members.collect()}
    reps = {r.unit_id: np.array(r.rep) for r in index.reps.collect()}
    true = [(i, j) for i in range(500) for j in range(i + 1, 500) if x[i] @ x[j] >= 0.35]
    want = {(i, j) for i, j in true if reps[unit[j]] @ x[i] > 0.3 or reps[unit[i]] @ x[j] > 0.3}
    got = {(r.left_id, r.right_id) for r in search.similarity_join(v, index, 0.35, 0.3).collect()}
    assert got == want and len(want) > 0.8 * len(true)


def test_blocks_of_queries_change_nothing(spark, monkeypatch):
    index, asked = q.sum_index(spark, SMALL), q.planted(spark, SMALL)
    whole = sorted(map(tuple, search.search(index, asked, tau=0.5, min_sim=0.3).select("query_id", "vec_id", "hit_rank").collect()))
    monkeypatch.setattr(search, "BLOCK_BYTES", 64 * 64 * 8)
    monkeypatch.setattr(search, "TILE", 4096)
    monkeypatch.setattr(search, "LIST", 3)
    assert len(list(search.query_blocks(asked))) == 8
    assert sorted(map(tuple, search.search(index, asked, tau=0.5, min_sim=0.3).select("query_id", "vec_id", "hit_rank").collect())) == whole
    top = search.exhaustive_search(q.vectors(spark, SMALL), asked, k=3).collect()
    x = kernels.matrix(q.vectors(spark, SMALL).orderBy("vec_id").toArrow().column("vec"))
    y = {r.query_id: np.array(r.qvec) for r in asked.collect()}
    assert len(top) == 1500 and all(np.argsort(-(x @ y[r.query_id]), kind="stable")[r.hit_rank - 1] == r.vec_id for r in top)


def test_stacked_solves_equal_single_ones():
    rng = np.random.default_rng(2)
    v, own = rng.standard_normal((300, 16)), rng.integers(0, 40, 300)
    v[5] = v[4]
    own[4] = own[5]
    own[own == 7] = 8  # one unit is empty, one larger than the dimension
    own[:20] = 3
    for kind in ("sum", "pinv"):
        reps, size = kernels.unit_reps(v, own, 40, kind)
        for j in range(40):
            want = kernels.representative(v[own == j], kind) if size[j] else np.zeros(16)
            assert np.allclose(reps[j], want, atol=1e-7)


def test_measured_cost_of_clustered_units_follows_the_model(spark):
    for r in w.cost_cap_measured(spark, SMALL).collect():
        if r.kind == "sum":
            assert r.ratio == pytest.approx(r.ratio_model, rel=0.12, abs=0.01)
        else:  # the model bounds the norm from below, and so the cost
            assert 0.93 * r.ratio_model < r.ratio < 1.4 * r.ratio_model + 0.02


def test_rates_on_generated_vectors_follow_the_model(spark):
    for r in w.roc_sphere(spark, SMALL).collect():
        assert r.pfp == pytest.approx(r.pfp_model, abs=0.02) and r.pfn == pytest.approx(r.pfn_model, abs=0.04)


def test_batches_are_better_balanced_than_mini_batches(spark):
    rows = {r.method: r for r in w.minibatch_imbalance(spark, MEDIUM).collect()}
    assert rows["batch-pinv_norm"].delta_mean < rows["batch-sum_norm"].delta_mean < rows["minibatch"].delta_mean
    assert rows["minibatch"].delta_sd > rows["batch-pinv_norm"].delta_sd and rows["minibatch"].runs == 5
    cost = {r.method: r for r in w.positive_units_protocol(spark, MEDIUM).collect()}
    assert cost["batch-pinv_norm"].ratio_mean < cost["minibatch"].ratio_mean and cost["batch-pinv_norm"].ratio_std < cost["minibatch"].ratio_std


def test_codes_lose_little_and_more_symmetrically(spark):
    rows = {(r.kind, r.way, r.tau): r for r in w.sign_documents(spark, MEDIUM).collect()}
    for kind in ("sum", "pinv"):
        for way in ("real", "asymmetric", "symmetric"):
            curve = [rows[kind, way, t] for t in sorted(w.SIGN_TAUS)]
            assert all(a.recall >= b.recall and a.ratio >= b.ratio for a, b in zip(curve, curve[1:], strict=False))
        assert rows[kind, "real", 0.2].recall >= 0.7


#: Workloads that no other test calls, but for the long ones.
REST = """rep_pinv_degenerate rep_ridge gram_spectrum mp_moments kl_sum kl_pinv cost_curve_cap capacity plans kmeans_pinv kmeans_pinv_norm
batch_kmeans batch_kmeans_full cost_histograms vector_normalisation pca_variance baseline_forest baseline_ivf baseline_lsh two_level
roc_families random_and_clustered minibatch_comparison large_protocol distractors same_conversation pca_search other_features""".split()


@pytest.mark.parametrize("name", REST)
def test_rows_make_sense(spark, name):
    rows = w.queries()[name](spark, SMALL).toPandas()
    assert len(rows)
    for column in rows.columns:
        if column in ("recall", "pfp", "tpr", "share", "p_match", "precision", "auc", "map"):
            assert rows[column].dropna().between(0, 1 + 1e-9).all(), column
        if column in ("ratio", "ratio_mean", "cost_ratio"):
            assert (rows[column] > 0).all() and (rows[column] < 2.01).all(), column
    if {"opened", "recall", "method"} <= set(rows.columns):
        rest = [c for c in rows.columns if c not in ("opened", "recall", "ratio_mean", "ratio_std")]
        for _, curve in rows.groupby(rest):
            curve = curve.sort_values("opened")
            assert curve.recall.is_monotonic_increasing and curve.ratio_mean.is_monotonic_increasing
    if name == "rep_pinv_degenerate":  # copies contradict nothing
        assert (rows.worst < 1e-6).mean() > 0.5
    if name == "gram_spectrum":
        assert abs(rows.share.sum() - 1) < 0.25 and abs(rows.model.sum() - 1) < 0.01
    if name == "kl_sum":
        assert (rows.kl >= 0).all()
    if name == "cost_curve_cap":  # the optimum moves to larger units as the similarity grows
        best = rows[(rows.eta == 0) & (rows.kind == "pinv")].sort_values("cost_ratio").groupby("alpha0").n.first()
        assert best.is_monotonic_increasing and best.iloc[0] < best.iloc[-1]
    if name == "capacity":
        assert all(g.sort_values("d").n.is_monotonic_increasing for _, g in rows.groupby("kind"))
    if name == "two_level":
        assert (rows.ops > 0).all()


def _partition(df):
    units: dict = {}
    for r in df.select("vec_id", "unit_id").collect():
        units.setdefault(r.unit_id, set()).add(r.vec_id)
    return {frozenset(u) for u in units.values()}


@pytest.mark.parametrize("kind, normalize", [("sum", True), ("pinv", False)])
def test_stored_centroids_cluster_as_broadcast_ones(spark, monkeypatch, kind, normalize):
    v = q.vectors(spark, SMALL)
    want = _partition(assign.spherical_kmeans(v, 50, kind, normalize, "random", 4, 3, q.D))
    monkeypatch.setattr(assign, "DRIVER_BYTES", 0)
    monkeypatch.setattr(assign, "BLOCK", 7)
    monkeypatch.setattr(assign, "nearest_unit", None)  # no centroid passes through the driver
    assert _partition(assign.spherical_kmeans(v, 50, kind, normalize, "random", 4, 3, q.D)) == want


def test_mini_batches_of_all_rows_in_tasks(spark, monkeypatch):
    v = q.vectors(spark, SMALL)
    monkeypatch.setattr(baselines, "FIT_ROWS", 0)
    monkeypatch.setattr(baselines, "_fit_rows", None)  # no row passes through the driver
    monkeypatch.setattr(assign, "DRIVER_BYTES", 0)
    path = baselines.stored_minibatch(v, 500, 20, 100, 3, 1)
    x = {r.vec_id: np.array(r.vec) for r in v.collect()}
    c = {r.unit_id: np.array(r.rep) for r in assign.starting_rows(v, 20, "random", 1).collect()}
    assert len(c) == 20
    count = dict.fromkeys(c, 0)
    for step in range(3):
        drawn = [r.vec_id for r in v.where(F.pmod(F.xxhash64("vec_id", F.lit(1), F.lit(step)), F.lit(1 << 30)) < int(0.2 * (1 << 30))).collect()]
        own = {i: min(c, key=lambda u: (((c[u] - x[i]) ** 2).sum(), u)) for i in drawn}
        for i, u in own.items():
            count[u] += 1
            c[u] = c[u] + (x[i] - c[u]) / count[u]
    got = {r.unit_id: r for r in spark.read.parquet(path).collect()}
    assert all(np.allclose(got[u].rep, c[u]) and got[u].n == count[u] for u in c)
    for index in (baselines.minibatch_index(v, 20, 100, 3, 1), baselines.ivf_index(v, 20, 3)):
        assert index.members.count() == index.reps.agg(F.sum("n_members")).first()[0] == 500


def test_curves_need_no_table_of_matches(spark):
    v = q.vectors(spark, SMALL)
    asked = features.every_50th(v)
    truth, index = w._truth(v, asked, 0.3).cache(), w.index_of(v, "random-sum", 500, q.D)
    every = search.count_matches(v, asked, 0.3)
    assert every == truth.count() > 0
    assert w.curve_by_units(index, asked, 0.3, 500, every=every).collect() == w.curve_by_units(index, asked, truth, 500).collect()


@pytest.mark.parametrize("name", "cap_moments cap_simulation capacity cost_cap_measured cost_curve cost_curve_cap cost_optimum kl_pinv kl_sum mp_moments plans roc_theory".split())
def test_model_is_asked_about_the_table(spark, tmp_path, name):
    """Other vectors in the table give other rows: what the model is asked about is read from it."""
    from groupsearch.plans import registry

    e = spark.read.parquet(f"{SMALL}/embeddings.parquet")
    flat = F.transform("embedding", lambda x, i: (F.when(i < 32, x).otherwise(x * 0.05)).cast("float"))
    e.withColumn("embedding", flat).write.parquet(f"{tmp_path}/embeddings.parquet")
    run = registry.queries()[name]
    a, b = (sorted(map(str, run(spark, str(sf)).collect())) for sf in (SMALL, tmp_path))
    assert a and len(a) == len(b) and a != b


def test_rates_and_summaries_need_no_pairs(spark, monkeypatch):
    index, asked = q.sum_index(spark, SMALL), q.planted(spark, SMALL)
    own = index.members.select(F.col("vec_id").alias("query_id"), F.col("unit_id").alias("own"))
    s = q.labelled_scores(spark, SMALL).cache()
    want = {r.related: r for r in s.groupBy("related").agg(F.count("*").alias("n"), F.percentile("score", 0.5).alias("median"), F.max_by("unit_id", "score").alias("best")).collect()}
    rates = {r.tau: r for r in metrics.error_rates(s, [0.21, 0.61]).collect()}
    monkeypatch.setattr(search, "query_blocks", None)  # no block of queries passes through the driver
    for r in search.own_summary(index.reps, asked.join(own, "query_id")).collect():
        assert (r.n, r.best_unit) == (want[r.related].n, want[r.related].best) and r.median == pytest.approx(want[r.related].median, abs=1e-12)
    for r in search.own_rates(index.reps, asked.join(own, "query_id"), [0.21, 0.61]).collect():
        assert (r.pfp, r.pfn) == (pytest.approx(rates[r.tau].pfp), pytest.approx(rates[r.tau].pfn))
    w.roc_planted(spark, SMALL)


@pytest.mark.parametrize("rows", [3, 4096])
def test_units_near_a_query_are_counted_without_pairs(spark, monkeypatch, rows):
    v = q.vectors(spark, SMALL)
    # bounds apart from one: a query is a member of its own unit, whose score is one but for rounding
    asked, placed = features.every_50th(v), q.members(spark, SMALL)
    monkeypatch.setattr(search, "SLICE", rows)
    got = {(r.alpha0, r.tau): r for a in (0.2, 0.3) for r in metrics.roc_of_counts(search.near_counts(placed, asked, "pinv", (0.2, 0.3), -0.537, 1.519, 20).where(F.col("alpha0") == a).drop("alpha0"), -0.537, 1.519, 20).withColumn("alpha0", F.lit(a)).collect()}
    monkeypatch.undo()
    scores, truth = search.probe(q.pinv_index(spark, SMALL).reps, asked), w._truth(v, asked, 0.2).cache()
    for a in (0.2, 0.3):
        held = truth.where(F.col("sim") >= a).join(placed.select("vec_id", "unit_id"), "vec_id").select("query_id", "unit_id", F.lit(True).alias("r")).distinct()
        s = scores.join(held, ["query_id", "unit_id"], "left").select("score", F.coalesce("r", F.lit(False)).alias("related"))
        for r in metrics.roc(s, -0.537, 1.519, 20).collect():
            assert (got[a, r.tau].pfp, got[a, r.tau].tpr) == (pytest.approx(r.pfp), pytest.approx(r.tpr))


def _embedded(spark, n=500, d=64):
    """Index of the table's vectors, queries, and all of them as arrays, some rows copied."""
    v = q.vectors(spark, SMALL)
    v = v.unionByName(v.where("vec_id % 5 = 0").select((F.col("vec_id") + 10_000).alias("vec_id"), "vec"))
    x = {r.vec_id: np.array(r.vec) for r in v.collect()}
    placed = assign.assign_random(v, 10, len(x)).select("vec_id", "vec", "unit_id")
    index = search.build_index(placed, "sum", d)
    unit, reps = {r.vec_id: r.unit_id for r in placed.collect()}, {r.unit_id: np.array(r.rep) for r in index.reps.collect()}
    asked = features.every_50th(v)
    ranked = {i: sorted(reps, key=lambda u, i=i: (-(reps[u] @ x[i]), u)) for i in x if i % 50 == 0}
    return index, asked, x, {(i, k): [j for j in x if unit[j] in ranked[i][:k]] for i in ranked for k in (1, 7, 30)} | {(i, 0): list(x) for i in ranked}


def test_best_others_need_no_table_of_hits(spark, monkeypatch):
    index, asked, x, held = _embedded(spark)
    for name in ("verify", "score_pairs", "query_blocks"):
        monkeypatch.setattr(search, name, None)
    monkeypatch.setattr(search, "SLICE", 100)
    got: dict = {}
    for r in search.best_others(index, asked, [1, 7, 30], 4).collect():
        got.setdefault((r.query_id, r.opened), []).append(r.vec_id)
    for (i, k), members in held.items():
        want = sorted((round(-(x[i] @ x[j]), 9), j) for j in members if j != i)[:4]
        assert sorted((round(-(x[i] @ x[j]), 9), j) for j in got.get((i, k), [])) == want
    assert w.same_conversation(spark, SMALL).count() >= 3


def _precision(order, matches):
    found = [r for r, j in enumerate(order, 1) if j in matches]
    return sum(n / r for n, r in enumerate(found, 1)) / len(matches)


@pytest.mark.parametrize("k", [3, 200])
def test_precision_needs_no_table_of_hits(spark, monkeypatch, k):
    index, asked, x, held = _embedded(spark)
    for name in ("verify", "score_pairs", "query_blocks"):
        monkeypatch.setattr(search, name, None)
    monkeypatch.setattr(search, "SLICE", 100)
    listed = {i: {j for j in x if j % 7 == i % 7} - {i} for i in {i for i, _ in held} - {50}}
    truth = spark.createDataFrame([(i, j) for i, js in listed.items() for j in js], "query_id bigint, vec_id bigint")
    near = {(r.query_id, r.opened): r.ap for r in search.near_precision(index, asked, [1, 7, 30], 0.25, k).collect()}
    other = {(r.query_id, r.opened): r for r in search.listed_precision(index, asked, [1, 7, 30], truth, k).collect()}
    for (i, opened), members in held.items():
        order = sorted(members, key=lambda j, i=i: (round(-(x[i] @ x[j]), 9), j))
        order = order if opened else order[:k]
        matches = {j for j in x if x[i] @ x[j] >= 0.25} - {i}
        assert near.get((i, opened)) == (pytest.approx(_precision([j for j in order if j != i], matches)) if matches else None)
        assert other[i, opened].ap == (pytest.approx(_precision(order, listed[i])) if i != 50 else None)
        assert other[i, opened].verified == (len(members) + index.reps.count() if opened else 0)


def test_items_are_found_in_one_pass_over_a_text(spark):
    long = "".join(chr(97 + i * i % 23) for i in range(40))
    docs = spark.createDataFrame([(1, "x" * 100_000 + long + "y"), (2, long[:30]), (3, "short"), (4, ""), (5, None), (6, "a short one")], "doc_id bigint, text string").repartition(3)
    items = spark.createDataFrame([(1, long), (2, long[:25]), (3, "short"), (4, ""), (5, None), (6, long[:24] + "?")], "item_id bigint, text string")
    plan = features.containing_texts(docs, items)
    assert "Generate" not in plan._jdf.queryExecution().toString()  # no row for each place of a text
    assert sorted(map(tuple, plan.collect())) == [(1, 1), (1, 2), (2, 2), (3, 3), (4, 4)]


def test_curves_of_codes_need_no_table_of_scores(spark, monkeypatch):
    v = q.vectors(spark, SMALL)
    asked, placed, taus = features.every_50th(v), q.members(spark, SMALL), [0.1, 0.3, 0.55]
    truth, want = w._truth(v, asked, 0.3), {}
    for kind in ("sum", "pinv"):
        plain, coded = search.build_index(placed, kind, q.D), codes.sign_index(placed, kind, q.D)
        for way, scores in (("real", search.probe(plain.reps, asked)), ("asymmetric", codes.sign_scores(coded, asked)), ("symmetric", codes.sign_scores(coded, asked, True))):
            want |= {(kind, way, r.tau): r for r in metrics.quality_cost_curve(scores, plain.reps, placed, truth, asked, 500, taus).collect()}
    lone = placed.withColumn("unit_id", F.col("vec_id"))
    alone = codes.sign_index(lone, "sum", q.D)
    want |= {("none", "scan", r.tau): r for r in metrics.quality_cost_curve(codes.sign_scores(alone, asked, True), alone.reps, lone, truth, asked, 500, taus).collect()}
    for name in ("score_pairs", "verify", "representatives"):
        monkeypatch.setattr(codes, name, None)
    got = codes.curve_counts(placed, asked, 0.3, q.D, taus).collect()
    assert len(got) == len(want) == 21
    for r in got:
        x = want[r.kind, r.way, r.tau]
        assert r["all"] == truth.count() > 0 and r.found / r["all"] == pytest.approx(x.recall)
        assert r.way == "scan" or (r.opened / 10 + 50) / 500 == pytest.approx(x.ratio_mean)


@pytest.mark.parametrize("held", [0, 1 << 30])
def test_a_task_sums_its_scores_up(spark, monkeypatch, held):
    index, asked = q.sum_index(spark, SMALL), q.planted(spark, SMALL)
    own = index.members.select(F.col("vec_id").alias("query_id"), F.col("unit_id").alias("own"))
    s = q.labelled_scores(spark, SMALL).cache()
    want = {r.related: r for r in s.groupBy("related").agg(F.count("*").alias("n"), F.percentile("score", 0.5).alias("median"), F.stddev_samp("score").alias("sd"), F.min("score").alias("least"), F.max_by("unit_id", "score").alias("best")).collect()}
    monkeypatch.setattr(search, "BINS", 8)
    monkeypatch.setattr(search, "HELD", held)
    monkeypatch.setattr(search, "SLICE", 16)
    rows, scores = [], search.own_scores
    monkeypatch.setattr(search, "own_scores", lambda *a: rows.append(scores(*a)) or rows[-1])
    for r in search.own_summary(index.reps, asked.join(own, "query_id")).collect():
        assert (r.n, r.best_unit, r.median, r.least) == (want[r.related].n, want[r.related].best, pytest.approx(want[r.related].median, abs=1e-12), pytest.approx(want[r.related].least))
        assert r.sd == pytest.approx(want[r.related].sd)
    assert len(rows) == (3 if held == 0 else 2)


def test_summary_shuffles_no_queries(spark, monkeypatch, tmp_path):
    """Units follow from ids; only where ids repeat, queries meet every row of theirs by a join."""
    e = spark.read.parquet(f"{SMALL}/embeddings.parquet")
    e.unionByName(e.where("vec_id < 3")).write.parquet(f"{tmp_path}/embeddings.parquet")
    asked, summed = [], search.own_summary
    monkeypatch.setattr(search, "own_summary", lambda reps, queries: asked.append(queries) or summed(reps, queries))
    for sf in (SMALL, str(tmp_path)):
        got = {r.related: r for r in q.score_summary(spark, sf).collect()}
        want = q.labelled_scores(spark, sf).groupBy("related").agg(F.count("*").alias("n"), F.round(F.avg("score"), 6).alias("mean"), F.max_by("unit_id", "score").alias("best")).collect()
        assert {(r.related, r.n, r.best_unit) for r in got.values()} == {(r.related, r.n, r.best) for r in want}
        assert all(got[r.related].mean == pytest.approx(r.mean, abs=2e-6) for r in want)
    assert [("Join" in x._jdf.queryExecution().optimizedPlan().toString()) for x in asked] == [False, True]


def test_a_forest_is_built_and_searched_once_for_its_grid(spark, monkeypatch):
    """The same numbers as a forest of its own for each grid point, from one job a grid, over several parts."""
    monkeypatch.setattr(baselines, "FOREST_ROWS", 150)
    v, asked = q.vectors(spark, SMALL).cache(), q.stated(spark, SMALL, 0.7).cache()
    n, truth = v.count(), search.exhaustive_search(v, asked, k=1).cache()
    grid = ((1, 3), (16, 64, 5000), (4, 16), ("kd", "kmeans"))
    want = {r.query_id: r.vec_id for r in truth.collect()}
    expected = {}
    for trees, checks, leaf, algorithm in [(1, 16, 4, "kd"), (3, 64, 16, "kd"), (1, 5000, 16, "kd"), (3, 16, 4, "kmeans"), (1, 64, 16, "kmeans")]:
        hits = [r for r in baselines.forest_ann(v, asked, trees, leaf, min(checks, n), 1, algorithm=algorithm).collect() if r.hit_rank == 1]
        expected[trees, checks, leaf, algorithm] = np.mean([r.vec_id == want[r.query_id] for r in hits]), np.mean([r.part_checked for r in hits]) / n
    monkeypatch.setattr(baselines, "forest_ann", None)
    tuned = baselines.tune_forest(v, asked, truth, n, grid=grid)
    assert len(tuned) == 24
    got = {(t.trees, t.checks, t.leaf, t.algorithm): (t.precision, t.ratio) for t in tuned}
    for point, numbers in expected.items():
        assert got[point] == pytest.approx(numbers, abs=1e-12)


@pytest.mark.parametrize("method", ["full-sum", "full-sum_norm", "full-pinv", "full-pinv_norm", "batch-pinv_norm", "minibatch", "ivf"])
def test_units_do_not_depend_on_where_rows_are_clustered(spark, monkeypatch, method):
    """Rows that fit a task or process and rows met round by round over all tasks get the same units."""
    v = w.document_vectors(spark, SMALL).cache()
    n = v.count()
    want = _partition(w.index_of(v, method, n, 256, 3).members)
    monkeypatch.setattr(assign, "fits_task", lambda vectors, n, alone=False: False)
    monkeypatch.setattr(baselines, "FIT_ROWS", 0)
    monkeypatch.setattr(assign, "PIECE_BYTES", 0)
    index = w.index_of(v, method, n, 256, 3)
    assert len(want) > 5 and _partition(index.members) == want


def test_batches_are_as_large_as_asked(spark, monkeypatch):
    """A batch of more rows than a task takes is neither cut nor made into several."""
    sizes = []
    monkeypatch.setattr(assign, "BATCH", 20)
    monkeypatch.setattr(assign, "batch_spherical_kmeans", lambda v, size, *rest, **options: sizes.append(size) or v.withColumn("unit_id", F.lit(0)))
    v = q.vectors(spark, SMALL)
    for method, batch in (("batch-pinv_norm", None), ("batch-pinv_norm", 30), ("full-pinv_norm", None)):
        w.index_of(v, method, 500, q.D, batch=batch)
    assert sizes == [125, 30, 500]


def test_a_forest_stands_on_all_vectors(spark, monkeypatch):
    """Rows met at a time change neither the trees nor what is checked; a search with 16 checks ends at the leaf that reaches them."""
    v, asked = q.vectors(spark, SMALL).cache(), q.stated(spark, SMALL, 0.7).cache()
    n, truth = v.count(), search.exhaustive_search(v, asked, k=1).cache()
    grid = ((1, 3), (16, 64), (4,), ("kd", "kmeans"))
    want = baselines.tune_forest(v, asked, truth, n, grid=grid)
    monkeypatch.setattr(baselines, "FOREST_ROWS", 150)
    assert baselines.tune_forest(v, asked, truth, n, grid=grid) == want
    hits, path = baselines.forest_grid(v, asked, n, grid)
    assert hits.count() == 8 * asked.count()
    x = np.array([r.vec for r in v.orderBy("vec_id").collect()])
    trees = [baselines.Tree(x, 4, np.random.default_rng([0, t])) for t in range(3)]
    monkeypatch.setattr(baselines, "FOREST_ROWS", 8192)
    whole = [baselines.Tree(x, 4, np.random.default_rng([0, t])) for t in range(3)]
    some = asked.orderBy("query_id").limit(20).collect()
    got = {r.query_id: r.part_checked for r in hits.where("place = 4").collect()}  # 3 trees, 16 checks, kd
    for r in some:
        rows = baselines.forest_query(whole, np.array(r.qvec), 16)
        assert got[r.query_id] == len(rows) and (rows == baselines.forest_query(trees, np.array(r.qvec), 16)).all()
