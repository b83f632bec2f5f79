"""Registered queries that have a SQL twin in oracle.py, by name. Outputs are flat rows with rounded numbers."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import features as ft
from ..functions import theory
from ..functions import vectors as vx
from ..operators import assign, baselines, codes, metrics, reduce, represent, search
from ..sources import tables
from ..streaming import arrivals

D = 64
ALPHA, TAU = 0.9, 0.5
UNIT = 10


def r6(c):
    return F.round(c, 6)


def _flat(df: DataFrame, keys: list[str], vec: str) -> DataFrame:
    """One row a component: keys, pos (from 0), value."""
    return df.select(*keys, F.posexplode(vec).alias("pos", "x")).select(*keys, "pos", r6("x").alias("value"))


def vectors(spark, sf) -> DataFrame:
    return tables.load_vectors(spark, sf)


def members(spark, sf, unit_size: int = UNIT) -> DataFrame:
    return assign.assign_random(vectors(spark, sf), unit_size, mode="modulo")


def sum_index(spark, sf) -> search.Index:
    return search.build_index(members(spark, sf), "sum", D)


def pinv_index(spark, sf) -> search.Index:
    return search.build_index(members(spark, sf), "pinv", D)


def planted(spark, sf, alpha: float = ALPHA) -> DataFrame:
    return ft.plant_queries(vectors(spark, sf), alpha)


def stated(spark, sf, alpha: float = ALPHA) -> DataFrame:
    """Planted queries of the rows whose id is divisible by 50: the query set of searches."""
    return planted(spark, sf, alpha).where(F.col("query_id") % 50 == 0)


# representatives -------------------------------------------------------------------------------------------------------------


def rep_sum(spark, sf):
    return _flat(sum_index(spark, sf).reps, ["unit_id", "n_members"], "rep")


def rep_sum_norm(spark, sf):
    return _flat(represent.normalize_representatives(sum_index(spark, sf).reps), ["unit_id", "n_members"], "rep")


def rep_pinv_pairs(spark, sf):
    pairs = vectors(spark, sf).withColumn("unit_id", F.floor(F.col("vec_id") / 2))
    return _flat(represent.pinv_representatives(pairs), ["unit_id", "n_members"], "rep")


def rep_pinv(spark, sf):
    return _flat(pinv_index(spark, sf).reps, ["unit_id", "n_members"], "rep")


def rep_norms(spark, sf):
    return represent.unit_diagnostics(members(spark, sf)).select("unit_id", "n", r6("norm2_sum").alias("norm2_sum"), r6("norm2_pinv").alias("norm2_pinv"), r6("trace").alias("trace"))


def power_norm(spark, sf):
    return _flat(vx.power_normalize(vectors(spark, sf), 0.5), ["vec_id"], "vec")


def normalize_vectors(spark, sf):
    return _flat(vx.normalize(vectors(spark, sf)), ["vec_id"], "vec")


def pinv_constraint(spark, sf):
    index = pinv_index(spark, sf)
    kept = index.members.join(index.reps, "unit_id").select("unit_id", (F.abs(vx.dot("vec", "rep") - 1) < 1e-6).cast("int").alias("ok"))
    return kept.groupBy("unit_id").agg(F.count("*").alias("n"), F.sum("ok").alias("satisfied"))


# analytic model ----------------------------------------------------------------------------------------------------------------


def h0_variance(spark, sf):
    return sum_index(spark, sf).reps.select("unit_id", r6(F.col("rep_norm2") / D).alias("variance"))


CDF_S = [i / 20 for i in range(-20, 21)]
CDF_D = [8, 64, 128]


def score_cdf_grid(spark, sf):
    rows = [(d, s, round(theory.score_cdf(s, 1.0, d), 6)) for d in CDF_D for s in CDF_S]
    return spark.createDataFrame(rows, "d int, s double, cdf double")


def score_pdf_grid(spark, sf):
    rows = [(d, s, round(theory.score_pdf(s, 1.0, d), 6)) for d in CDF_D for s in CDF_S]
    return spark.createDataFrame(rows, "d int, s double, pdf double")


ROC_ALPHAS = [0.5, 0.6, 0.7, 0.8, 0.9]
ROC_TAUS = [i / 10 for i in range(-5, 16)]


def dimensions(spark, sf, components: tuple[int, ...] = (D,)) -> list[int]:
    """Dimension of the table's vectors, and of their first components, as the model needs it: that of evenly spread vectors with as
    large squared products, rounded. Tasks add up second moments of the whole table; one block a task reaches the driver."""
    rows, _, xx = reduce.moments(vectors(spark, sf))
    if not rows:
        return list(components)
    return [int(np.floor(np.trace(m) ** 2 / (m**2).sum() + 0.5)) for m in (xx[:k, :k] / rows for k in components)]


def roc_theory(spark, sf):
    """Modelled rates of units of UNIT members in the table's dimension."""
    rows, (d,) = [], dimensions(spark, sf)
    for kind in ("sum", "pinv"):
        for a in ROC_ALPHAS:
            for t in ROC_TAUS:
                fp, fn = theory.error_rates(kind, t, UNIT, d, a)
                rows.append((kind, a, t, round(fp, 6), round(1 - fn, 6)))
    return spark.createDataFrame(rows, "kind string, alpha double, tau double, pfp double, tpr double")


COST_D, COST_EPS = 1000, 0.01


def thresholds(spark, sf):
    rows = [(k, a, n, round(theory.threshold(k, n, COST_D, a, COST_EPS), 6)) for k in ("sum", "pinv") for a in ROC_ALPHAS for n in range(1, 101)]
    return spark.createDataFrame(rows, "kind string, alpha0 double, n int, tau double")


def cost_curve(spark, sf):
    """Expected cost by unit size in the table's dimension; minimum-norm units as large as it open always."""
    (d,) = dimensions(spark, sf)
    rows = [(k, a, n, round(theory.expected_cost_ratio(k, n, d, a, COST_EPS), 6)) for k in ("sum", "pinv") for a in ROC_ALPHAS for n in range(1, 101)]
    return spark.createDataFrame(rows, "kind string, alpha0 double, n int, cost_ratio double")


def cost_optimum(spark, sf):
    curve = cost_curve(spark, sf)
    best = curve.groupBy("kind", "alpha0").agg(F.min(F.struct("cost_ratio", "n")).alias("b"))
    return best.select("kind", "alpha0", F.col("b.n").alias("n"), F.col("b.cost_ratio").alias("cost_ratio"))


def unit_thresholds(spark, sf):
    return search.with_unit_thresholds(sum_index(spark, sf).reps, D, ALPHA, 0.05, "sum").select("unit_id", r6("tau").alias("tau"))


CAP_ETAS = [-0.5, -0.2, 0.0, 0.2, 0.4, 0.6]


CAP_DIMS = [16, 64]


def cap_moments(spark, sf):
    """Moments of the cosine to an axis of the table's vectors on a cap, measured over all axes, beside those of the model.

    Fewer components are a vector's first ones: those of an evenly spread vector are evenly spread.
    """
    v, both = vectors(spark, sf), None
    for d in CAP_DIMS:
        part = v.select(F.slice("vec", 1, d).alias("vec")).where(vx.norm2("vec") > 0).select(F.explode(F.transform("vec", lambda x: x / vx.norm("vec"))).alias("c"))
        found = part.select("c", F.explode(F.array(*[F.lit(e) for e in CAP_ETAS])).alias("eta")).where("c > eta")
        found = found.groupBy("eta").agg(F.count("*").alias("n"), r6(F.avg("c")).alias("mu1"), r6(F.avg(F.col("c") * F.col("c"))).alias("mu2")).withColumn("d", F.lit(d))
        both = found if both is None else both.unionByName(found)
    model = [(d, e, round(theory.cap_moment(1, e, d), 6), round(theory.cap_moment(2, e, d), 6)) for d in CAP_DIMS for e in CAP_ETAS]
    model = spark.createDataFrame(model, "d int, eta double, mu1_model double, mu2_model double")
    return model.join(both, ["d", "eta"], "left").select("d", "eta", F.coalesce("n", F.lit(0)).alias("n"), "mu1", "mu2", "mu1_model", "mu2_model")


# assignment ------------------------------------------------------------------------------------------------------------------


def assign_random(spark, sf):
    return members(spark, sf).select("vec_id", "unit_id")


def _events(spark, sf):
    return tables.load_table(spark, sf, "events")


def assign_arrival(spark, sf):
    return assign.assign_arrival(_events(spark, sf).select("event_id", "ts"), 50, lanes=8).select("event_id", "unit_id")


def assign_label(spark, sf):
    e = tables.load_table(spark, sf, "embeddings", ["vec_id", "label"])
    return assign.assign_by_key(e, "label").select("vec_id", "unit_id")


KMEANS_UNITS = 20


def _kmeans(spark, sf, normalize):
    out = assign.spherical_kmeans(vectors(spark, sf), KMEANS_UNITS, "sum", normalize, "first", max_iter=3, d=D)
    return out.select("vec_id", "unit_id")


def kmeans_sum(spark, sf):
    return _kmeans(spark, sf, False)


def kmeans_sum_norm(spark, sf):
    return _kmeans(spark, sf, True)


# search ----------------------------------------------------------------------------------------------------------------------


def index_build(spark, sf):
    index = sum_index(spark, sf)
    sizes = index.members.groupBy("unit_id").agg(F.min("vec_id").alias("first_vec"), F.max("vec_id").alias("last_vec"))
    return index.reps.join(sizes, "unit_id").select("unit_id", "n_members", r6("rep_norm2").alias("rep_norm2"), "first_vec", "last_vec")


def probe_scores(spark, sf):
    return search.probe(sum_index(spark, sf).reps, stated(spark, sf)).select("query_id", "unit_id", r6("score").alias("score"))


def probe_native(spark, sf):
    return search.probe_native(sum_index(spark, sf).reps, stated(spark, sf), TAU).select("query_id", "unit_id", r6("score").alias("score"))


def probe_threshold(spark, sf):
    return search.probe(sum_index(spark, sf).reps, stated(spark, sf), TAU).select("query_id", "unit_id", r6("score").alias("score"))


def probe_unit_tau(spark, sf):
    reps = search.with_unit_thresholds(sum_index(spark, sf).reps, D, ALPHA, 0.05, "sum")
    return search.probe(reps, stated(spark, sf), "tau").select("query_id", "unit_id", r6("score").alias("score"))


def probe_top_units(spark, sf):
    return search.select_units(sum_index(spark, sf).reps, stated(spark, sf), top_units=7).select("query_id", "unit_id", "unit_rank", r6("score").alias("score"))


def search_threshold(spark, sf):
    return search.search(sum_index(spark, sf), stated(spark, sf), tau=TAU).select("query_id", "vec_id", r6("sim").alias("sim"), "hit_rank")


def search_range(spark, sf):
    return search.search(sum_index(spark, sf), stated(spark, sf), tau=TAU, min_sim=0.3).select("query_id", "vec_id", r6("sim").alias("sim"))


def search_topk(spark, sf):
    return search.search(sum_index(spark, sf), stated(spark, sf), top_units=7, k=4).select("query_id", "vec_id", r6("sim").alias("sim"), "hit_rank")


def unit_thresholds_pinv(spark, sf):
    return search.with_unit_thresholds(pinv_index(spark, sf).reps, D, ALPHA, 0.05, "pinv").select("unit_id", r6("tau").alias("tau"))


def rep_append(spark, sf):
    """Units of the even ids, then the odd ids appended."""
    both = members(spark, sf)
    old, new = both.where("vec_id % 2 = 0"), both.where("vec_id % 2 = 1")
    grown = represent.append_to_pinv_units(represent.pinv_representatives(old), old, new)
    return grown.select("unit_id", "n_members", r6("rep_norm2").alias("rep_norm2"))


def membership(spark, sf):
    return search.membership_test(sum_index(spark, sf).reps, stated(spark, sf), 0.7)


def similarity_join(spark, sf):
    """Pairs of cosine 0.35 or more. The method may miss some: on the given tables it finds 83 to 86 % of them at this threshold."""
    return search.similarity_join(vectors(spark, sf), sum_index(spark, sf), 0.35, 0.3).select("left_id", "right_id", r6("sim").alias("sim"))


def filtered_search(spark, sf):
    """Members keep their label, so the condition is pushed to their scan."""
    labelled = tables.load_table(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("vec"), "label")
    index = search.Index(sum_index(spark, sf).reps, assign.assign_random(labelled, UNIT, mode="modulo"))
    return search.search(index, stated(spark, sf), tau=TAU, where=F.col("label") == 3).select("query_id", "vec_id", r6("sim").alias("sim"))


def exact_range(spark, sf):
    return search.exhaustive_search(vectors(spark, sf), stated(spark, sf), alpha0=0.3).select("query_id", "vec_id", r6("sim").alias("sim"))


def exact_topk(spark, sf):
    return search.exhaustive_search(vectors(spark, sf), stated(spark, sf), k=10).select("query_id", "vec_id", r6("sim").alias("sim"), "hit_rank")


def baseline_filter_refine(spark, sf):
    return baselines.filter_refine_search(vectors(spark, sf), stated(spark, sf), 0.3).select("query_id", "vec_id", r6("sim").alias("sim"))


def no_miss_copy(spark, sf):
    """Copies as queries are never missed by pinv units at any threshold below one."""
    index, queries = pinv_index(spark, sf), planted(spark, sf, 1.0)
    opened = search.probe(index.reps, queries, 0.999).join(index.members.select("unit_id", F.col("vec_id").alias("query_id")), ["unit_id", "query_id"])
    return opened.agg(F.count("*").alias("found")).crossJoin(queries.agg(F.count("*").alias("queries"))).select("queries", (F.col("queries") - F.col("found")).alias("misses"))


# reduction and codes -----------------------------------------------------------------------------------------------------------


def second_moment(spark, sf):
    return reduce.second_moment(vectors(spark, sf), D).select("i", "j", r6("value").alias("value"))


def sign_codes(spark, sf):
    return codes.encode(vectors(spark, sf), D).select("vec_id", F.posexplode("code").alias("word", "code"))


def hamming_topk(spark, sf):
    coded = codes.encode(vectors(spark, sf), D)
    asked = codes.encode(stated(spark, sf), D, "qvec")
    return codes.hamming_search(coded, asked, D, 10)


SIGN_TAU = 0.35


def search_sign_asym(spark, sf):
    return codes.search_signs(codes.sign_index(members(spark, sf), "sum", D), stated(spark, sf), SIGN_TAU).select("query_id", "vec_id", r6("sim").alias("sim"))


def search_sign_sym(spark, sf):
    return codes.search_signs(codes.sign_index(members(spark, sf), "sum", D), stated(spark, sf), SIGN_TAU, symmetric=True).select("query_id", "vec_id", r6("sim").alias("sim"))


# measures ----------------------------------------------------------------------------------------------------------------------


def _costs(spark, sf, tau=TAU):
    index, queries = sum_index(spark, sf), stated(spark, sf)
    return metrics.query_cost(search.probe(index.reps, queries, tau), index.reps, queries)


def query_cost(spark, sf):
    return _costs(spark, sf)


def complexity_ratio(spark, sf):
    n = vectors(spark, sf).count()
    return metrics.complexity_ratio(_costs(spark, sf), n).select("query_id", "ops", r6("ratio").alias("ratio"), r6("speedup").alias("speedup"), "saved")


def cost_histogram(spark, sf):
    return metrics.cost_histogram(metrics.complexity_ratio(_costs(spark, sf), vectors(spark, sf).count()), 20)


def cost_h0(spark, sf):
    """Cost of queries that have nothing to do with the database: one vector in ten is held out."""
    base, unrelated = ft.holdout(vectors(spark, sf))
    index = search.build_index(base.withColumn("unit_id", F.floor(F.col("vec_id") / 10)), "sum", D)
    costs = metrics.query_cost(search.probe(index.reps, unrelated, TAU), index.reps, unrelated)
    summary = metrics.cost_summary(metrics.complexity_ratio(costs, base.count()))
    return summary.select("queries", r6("ratio_mean").alias("ratio_mean"), r6("ratio_std").alias("ratio_std"))


def labelled_scores(spark, sf, kind: str = "sum", alpha: float = ALPHA):
    """query_id, unit_id, score, related of every planted query against every unit."""
    index = sum_index(spark, sf) if kind == "sum" else pinv_index(spark, sf)
    own = index.members.select(F.col("vec_id").alias("query_id"), F.col("unit_id").alias("own"))
    scores = search.probe(index.reps, planted(spark, sf, alpha))
    return scores.join(own, "query_id").select("query_id", "unit_id", "score", (F.col("unit_id") == F.col("own")).alias("related"))


RATE_TAUS = [0.21, 0.41, 0.61, 0.81]


def error_rates(spark, sf):
    return metrics.error_rates(labelled_scores(spark, sf), RATE_TAUS).select("tau", r6("pfp").alias("pfp"), r6("pfn").alias("pfn"))


def roc_empirical(spark, sf):
    return metrics.roc(labelled_scores(spark, sf), -1.5, 2.5, 40).select(r6("tau").alias("tau"), r6("pfp").alias("pfp"), r6("tpr").alias("tpr"))


def kl_empirical(spark, sf):
    return metrics.kl_empirical(labelled_scores(spark, sf)).select(*[r6(c).alias(c) for c in ("mean1", "var1", "mean0", "var0", "kl")])


def score_summary(spark, sf):
    """Scores of every planted query against every unit, reduced in the tasks: no pair leaves them."""
    index, asked = sum_index(spark, sf), planted(spark, sf)
    if index.members.groupBy("vec_id").count().where("count > 1").isEmpty():  # the unit follows from the id, so vectors need no shuffle
        asked = assign.assign_random(asked.withColumnRenamed("query_id", "vec_id"), UNIT, mode="modulo").where("vec_id is not null")
        asked = asked.select("qvec", F.col("unit_id").alias("own"))
    else:
        asked = asked.join(index.members.select(F.col("vec_id").alias("query_id"), F.col("unit_id").alias("own")), "query_id")
    out = search.own_summary(index.reps, asked)
    return out.select("related", "n", *[r6(c).alias(c) for c in ("mean", "sd", "least", "most", "median")], "units", "best_unit")


def _truth(spark, sf, alpha0=0.3):
    return search.exhaustive_search(vectors(spark, sf), stated(spark, sf), alpha0=alpha0).select("query_id", "vec_id", "sim")


def _hits(spark, sf):
    return search.search(sum_index(spark, sf), stated(spark, sf), tau=TAU, min_sim=0.3)


def recall_at_alpha(spark, sf):
    out = metrics.precision_recall(_hits(spark, sf), _truth(spark, sf))
    return out.select("n_hits", "n_truth", "n_correct", r6("precision").alias("precision"), r6("recall").alias("recall"))


def _label_truth(spark, sf):
    e = tables.load_table(spark, sf, "embeddings", ["vec_id", "label"])
    q = e.where(F.col("vec_id") % 50 == 0).select(F.col("vec_id").alias("query_id"), "label")
    return e.join(F.broadcast(q), "label").where("query_id <> vec_id").select("query_id", "vec_id")


def _ranked(spark, sf):
    hits = search.search(sum_index(spark, sf), ft.every_50th(vectors(spark, sf)), top_units=7)
    return search.rank_hits(hits.where("query_id <> vec_id").drop("hit_rank"))


def map_score(spark, sf):
    return metrics.mean_average_precision(_ranked(spark, sf), _label_truth(spark, sf)).select(r6("map").alias("map"), "queries")


def recall4(spark, sf):
    return metrics.mean_correct_at(_ranked(spark, sf), _label_truth(spark, sf), ft.every_50th(vectors(spark, sf)), 4).select(r6("correct").alias("correct"), "queries")


def _matches(spark, sf):
    index, queries = sum_index(spark, sf), stated(spark, sf)
    return metrics.unit_matches(search.rank_units(search.probe(index.reps, queries)), index.members, _truth(spark, sf))


def match_by_rank(spark, sf):
    return metrics.match_probability_by_rank(_matches(spark, sf)).select("unit_rank", r6("p_match").alias("p_match"))


def matches_given_pos(spark, sf):
    return metrics.matches_given_positive_by_rank(_matches(spark, sf)).select("unit_rank", r6("avg_matches").alias("avg_matches"))


def imbalance(spark, sf):
    return metrics.imbalance(_kmeans(spark, sf, True), KMEANS_UNITS).select("n", "units", r6("delta").alias("delta"), r6("var_size").alias("var_size"))


def _imbalances(spark, sf):
    named = [("plain", _kmeans(spark, sf, False)), ("norm", _kmeans(spark, sf, True)), ("random", assign_random(spark, sf))]
    out = None
    for variant, a in named:
        part = metrics.imbalance(a, KMEANS_UNITS if variant != "random" else None).select(F.lit("embeddings").alias("dataset"), F.lit(variant).alias("variant"), r6("delta").alias("delta"))
        out = part if out is None else out.unionByName(part)
    return out


def imbalance_pivot(spark, sf):
    return metrics.pivot_by_kind(_imbalances(spark, sf), "dataset", "variant", ["plain", "norm", "random"], "delta")


def quality_cost_curve(spark, sf):
    index, queries = sum_index(spark, sf), stated(spark, sf)
    out = metrics.quality_cost_curve(search.probe(index.reps, queries), index.reps, index.members, _truth(spark, sf), queries, vectors(spark, sf).count(), [0.11, 0.31, 0.51, 0.71, 0.91])
    return out.select("tau", r6("ratio_mean").alias("ratio_mean"), r6("recall").alias("recall"))


def truth_filter(spark, sf):
    return metrics.filter_queries(_truth(spark, sf).where("query_id <> vec_id"), 1, 1000)


def build_cost(spark, sf):
    n = vectors(spark, sf).count()
    m = max(1, -(-n // UNIT))
    rows = [("random", 0), ("full", metrics.build_cost(n, m, 12)), ("batch_100", metrics.build_cost(n, m, 12, 100))]
    return spark.createDataFrame(rows, "method string, ops bigint")


def index_overhead(spark, sf):
    index = sum_index(spark, sf)
    return metrics.index_overhead(index.reps, index.members).select("rep_numbers", "member_numbers", r6("overhead").alias("overhead"))


def score_gaps(spark, sf):
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "unit_id")
    ranked = search.rank_units(search.probe(sum_index(spark, sf).reps, stated(spark, sf)))
    return ranked.select("query_id", "unit_rank", r6(F.lag("score").over(w) - F.col("score")).alias("gap"), F.ntile(4).over(w).alias("quarter"))


def metrics_rollup(spark, sf):
    return _cube_input(spark, sf).rollup("label", "half").agg(r6(F.avg("ratio")).alias("avg_ratio"), F.count("*").alias("cnt"))


def metrics_cube(spark, sf):
    return _cube_input(spark, sf).cube("label", "half").agg(r6(F.avg("ratio")).alias("avg_ratio"), F.count("*").alias("cnt"))


def _cube_input(spark, sf):
    n = vectors(spark, sf).count()
    labels = tables.load_table(spark, sf, "embeddings", [F.col("vec_id").alias("query_id"), "label"])
    half = (F.col("query_id") % 100 >= 50).cast("int").alias("half")
    return metrics.complexity_ratio(_costs(spark, sf), n).join(labels, "query_id").select("label", half, "ratio")


# operators around --------------------------------------------------------------------------------------------------------------


def scan_embeddings(spark, sf):
    e = tables.load_table(spark, sf, "embeddings", ["vec_id", "label"])
    return e.groupBy("label").agg(F.count("*").alias("n"), F.min("vec_id").alias("first_id"))


def reject_invalid(spark, sf):
    """Broken on purpose: rows of four remainders get a null, zero, short or not finite vector."""
    v, r = F.col("vec"), F.col("vec_id") % 20
    broken = (
        F.when(r == 1, F.lit(None).cast("array<double>"))
        .when(r == 2, F.transform(v, lambda x: x * 0))
        .when(r == 3, F.slice(v, 1, D - 1))
        .when(r == 4, F.transform(v, lambda x, i: F.when(i == 5, F.lit(float("nan"))).otherwise(x)))
        .otherwise(v)
    )
    _, rejects = tables.validate_vectors(vectors(spark, sf).withColumn("vec", broken), D)
    return rejects


def queries_without_hit(spark, sf):
    return stated(spark, sf, 0.6).select("query_id").join(search.search(sum_index(spark, sf), stated(spark, sf, 0.6), tau=0.9, min_sim=0.5), "query_id", "left_anti")


def asof_index_version(spark, sf):
    """The index version in force at each event: versions appear every 1000 events; latest one not after the event."""
    e = _events(spark, sf).select("event_id", "ts", F.date_trunc("hour", "ts").alias("h"))
    versions = e.where(F.col("event_id") % 1000 == 0).select(F.col("event_id").alias("version"), F.col("ts").alias("vts"))
    per_hour = versions.groupBy(F.date_trunc("hour", "vts").alias("h")).agg(F.max(F.struct("vts", "version")).alias("last"))
    hours = e.select("h").distinct().join(per_hour, "h", "left")
    carried = hours.withColumn("before", F.max("last").over(Window.orderBy("h").rowsBetween(Window.unboundedPreceding, -1)))  # one row an hour
    same = F.max(F.when(F.col("event_id") % 1000 == 0, F.struct(F.col("ts").alias("vts"), F.col("event_id").alias("version")))).over(Window.partitionBy("h").orderBy("ts", "event_id"))
    out = e.withColumn("inside", same).join(carried.select("h", "before"), "h")
    return out.select("event_id", F.coalesce("inside", "before")["version"].alias("version"))


def _two_hit_sets(spark, sf):
    a = search.search(sum_index(spark, sf), stated(spark, sf), tau=TAU, min_sim=0.25).select("query_id", "vec_id")
    b = search.search(sum_index(spark, sf), stated(spark, sf), top_units=7, min_sim=0.25).select("query_id", "vec_id")
    return a, b


def hits_intersect(spark, sf):
    a, b = _two_hit_sets(spark, sf)
    return a.intersect(b)


def hits_except(spark, sf):
    a, b = _two_hit_sets(spark, sf)
    return a.exceptAll(b)


def dot_self(spark, sf):
    return vectors(spark, sf).select("vec_id", r6(vx.dot("vec", "vec")).alias("norm2"), r6(vx.norm("vec")).alias("norm"))


def cosine_pairs(spark, sf):
    v = vectors(spark, sf)
    w = v.select((F.col("vec_id") - 1).alias("vec_id"), F.col("vec").alias("other"))
    return v.join(w, "vec_id").select("vec_id", r6(vx.cosine("vec", "other")).alias("cosine"))


def sql_dot(spark, sf):
    vx.register_sql(spark)
    vectors(spark, sf).createOrReplaceTempView("groupsearch_vectors")
    return spark.sql("SELECT a.vec_id, round(vec_dot(a.vec, b.vec), 6) AS product, round(vec_norm(a.vec), 6) AS norm FROM groupsearch_vectors a JOIN groupsearch_vectors b ON a.vec_id = b.vec_id - 1")


def hash_features(spark, sf):
    docs = tables.load_table(spark, sf, "documents", ["doc_id", "text"])
    return ft.hash_weights(docs, "doc_id", F.col("text"), 256)


def user_profiles(spark, sf):
    return ft.user_profiles(_events(spark, sf))


def props_k(spark, sf):
    return _events(spark, sf).groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count("*").alias("n"), r6(F.sum("value")).alias("total"))


def _micros(df: DataFrame, *keys):
    us = F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01', cast(start AS timestamp_ntz))")
    return df.select(*keys, us.alias("start_us"), "arrivals")


def tumbling_arrivals(spark, sf):
    return _micros(arrivals.tumbling_arrivals(_events(spark, sf), "1 hour"))


def sliding_arrivals(spark, sf):
    return _micros(arrivals.sliding_arrivals(_events(spark, sf), "2 hours", "1 hour"))


def session_arrivals(spark, sf):
    return _micros(arrivals.session_arrivals(_events(spark, sf), "6 hours"), "user_id")


def roc_documents(spark, sf):
    """ROC on document vectors: a unit is related if it holds a document of cosine 0.9 or more, the query's own document apart.

    Document vectors are hashed words; the documents asked for are those with an id divisible by 50.
    """
    docs = tables.load_table(spark, sf, "documents", ["doc_id", "text"])
    v = ft.hash_vectors(docs.withColumn("text", F.array_join(ft.tokens(F.col("text")), " ")), "doc_id", "text", 256)
    m = v.withColumn("unit_id", F.pmod("vec_id", F.lit(100)))
    q = ft.every_50th(v)
    reps = represent.sum_representatives(m, d=256)
    truth = search.exhaustive_search(v, q, alpha0=0.9).where("query_id <> vec_id").select("query_id", "vec_id")
    related = truth.join(m.select("vec_id", "unit_id"), "vec_id").select("query_id", "unit_id", F.lit(True).alias("r")).distinct()
    scores = search.probe(reps, q).join(related, ["query_id", "unit_id"], "left").select("score", F.coalesce("r", F.lit(False)).alias("related"))
    return metrics.error_rates(scores, [2.05, 4.05, 6.05, 8.05]).select("tau", r6("pfp").alias("pfp"), r6(1 - F.col("pfn")).alias("tpr"))


NAMES = """rep_sum rep_sum_norm rep_pinv_pairs rep_pinv rep_norms power_norm normalize_vectors pinv_constraint h0_variance score_cdf_grid
score_pdf_grid roc_theory thresholds cost_curve cost_optimum unit_thresholds cap_moments assign_random assign_arrival assign_label
kmeans_sum kmeans_sum_norm index_build probe_scores probe_native probe_threshold probe_unit_tau probe_top_units search_threshold
search_range search_topk membership unit_thresholds_pinv rep_append similarity_join filtered_search exact_range exact_topk baseline_filter_refine no_miss_copy
second_moment sign_codes hamming_topk search_sign_asym search_sign_sym query_cost complexity_ratio cost_histogram cost_h0 error_rates
roc_empirical roc_documents kl_empirical score_summary recall_at_alpha map_score recall4 match_by_rank matches_given_pos imbalance
imbalance_pivot quality_cost_curve truth_filter build_cost index_overhead score_gaps metrics_rollup metrics_cube scan_embeddings
reject_invalid queries_without_hit asof_index_version hits_intersect hits_except dot_self cosine_pairs sql_dot hash_features
user_profiles props_k tumbling_arrivals sliding_arrivals session_arrivals""".split()


def queries() -> dict:
    return {n: globals()[n] for n in NAMES}
