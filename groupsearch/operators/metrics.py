"""Cost and accuracy measures over probes, hits and truth."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def query_cost(positives: DataFrame, reps: DataFrame, queries: DataFrame) -> DataFrame:
    """query_id, n_units, n_opened, n_verified, ops: vector operations of each query, all units probed and opened ones scanned.

    A query that opens nothing still probes: queries are the outer side.
    """
    opened = positives.join(reps.select("unit_id", "n_members"), "unit_id").groupBy("query_id").agg(F.count("*").alias("n_opened"), F.sum("n_members").alias("n_verified"))
    units = reps.agg(F.count("*").alias("n_units"))
    out = queries.select("query_id").join(opened, "query_id", "left").crossJoin(F.broadcast(units))
    zero = F.lit(0).cast("bigint")
    return out.select("query_id", "n_units", F.coalesce("n_opened", zero).alias("n_opened"), F.coalesce("n_verified", zero).alias("n_verified")).withColumn("ops", F.col("n_units") + F.col("n_verified"))


def complexity_ratio(costs: DataFrame, n: int) -> DataFrame:
    """costs with ratio (operations over an exhaustive scan's), speedup and saved operations."""
    return costs.withColumn("ratio", F.col("ops") / n).withColumn("speedup", F.lit(n) / F.col("ops")).withColumn("saved", F.lit(n).cast("bigint") - F.col("ops"))


def cost_summary(ratios: DataFrame, by: list[str] | None = None) -> DataFrame:
    return ratios.groupBy(*(by or [])).agg(F.avg("ratio").alias("ratio_mean"), F.stddev_pop("ratio").alias("ratio_std"), F.count("*").alias("queries"))


def cost_histogram(ratios: DataFrame, bins: int = 20, top: float = 1.0) -> DataFrame:
    """bin, cnt: bins of equal width up to ``top``, numbered from 1; larger ratios in bin bins + 1."""
    return ratios.groupBy(F.expr(f"width_bucket(ratio, 0D, {float(top)}D, {bins})").alias("bin")).agg(F.count("*").alias("cnt"))


def error_rates(scores: DataFrame, taus: list[float]) -> DataFrame:
    """tau, pfp, pfn from scores (score, related), every threshold in one pass."""
    tau = F.explode(F.array(*[F.lit(float(t)) for t in taus])).alias("tau")
    rows = scores.select("score", "related", tau)
    return rows.groupBy("tau").agg(
        F.avg(F.when(~F.col("related"), (F.col("score") > F.col("tau")).cast("int"))).alias("pfp"),
        F.avg(F.when(F.col("related"), (F.col("score") <= F.col("tau")).cast("int"))).alias("pfn"),
    )


def roc(scores: DataFrame, lo: float, hi: float, bins: int) -> DataFrame:
    """tau, pfp, tpr at bins + 1 thresholds: scores are counted by bin once, then cumulated from above; ties to tau are negative."""
    # bin b holds scores in (lo + (b - 1) width, lo + b width]; 0 and bins + 1 hold the rest
    b = F.greatest(F.lit(0), F.least(F.lit(bins + 1), F.ceil((F.col("score") - lo) / ((hi - lo) / bins)))).cast("int")
    counts = scores.groupBy(b.alias("b")).agg(F.sum(F.col("related").cast("int")).alias("p"), F.sum((~F.col("related")).cast("int")).alias("n"))
    return roc_of_counts(counts, lo, hi, bins)


def roc_of_counts(counts: DataFrame, lo: float, hi: float, bins: int) -> DataFrame:
    """The same from related (p) and unrelated (n) scores counted by bin b."""
    width = (hi - lo) / bins
    grid = counts.sparkSession.range(0, bins + 2).select(F.col("id").cast("int").alias("b")).join(counts, "b", "left").na.fill(0, ["p", "n"])
    above = Window.orderBy(F.desc("b")).rowsBetween(Window.unboundedPreceding, -1)  # over the bins
    every = Window.orderBy(F.desc("b")).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    out = grid.select("b", F.try_divide(F.coalesce(F.sum("n").over(above), F.lit(0)), F.sum("n").over(every)).alias("pfp"), F.try_divide(F.coalesce(F.sum("p").over(above), F.lit(0)), F.sum("p").over(every)).alias("tpr"))
    return out.where(F.col("b") <= bins).select((F.lit(lo) + F.col("b") * width).alias("tau"), "pfp", "tpr")


def auc(curve: DataFrame) -> DataFrame:
    """Area under a curve of (pfp, tpr) by trapezia, closed at both corners."""
    w = Window.orderBy("pfp", "tpr")
    step = curve.select("pfp", "tpr", F.lag("pfp", 1, 0.0).over(w).alias("x"), F.lag("tpr", 1, 0.0).over(w).alias("y"))
    last = F.max(F.struct("pfp", "tpr"))
    area = F.sum((F.col("pfp") - F.col("x")) * (F.col("tpr") + F.col("y")) / 2)
    return step.agg((area + (1 - last["pfp"]) * (1 + last["tpr"]) / 2).alias("auc"))


def precision_recall(hits: DataFrame, truth: DataFrame) -> DataFrame:
    """n_hits, n_truth, n_correct, precision, recall over all queries; a full join, so either side may lack a pair."""
    both = hits.select("query_id", "vec_id", F.lit(1).alias("h")).join(truth.select("query_id", "vec_id", F.lit(1).alias("t")), ["query_id", "vec_id"], "full")
    out = both.agg(F.count("h").alias("n_hits"), F.count("t").alias("n_truth"), F.count(F.when(F.col("h").isNotNull() & F.col("t").isNotNull(), 1)).alias("n_correct"))
    return out.withColumn("precision", F.when(F.col("n_hits") > 0, F.col("n_correct") / F.col("n_hits"))).withColumn("recall", F.when(F.col("n_truth") > 0, F.col("n_correct") / F.col("n_truth")))


def average_precision(hits: DataFrame, truth: DataFrame, interpolation: str = "none", exclude_self: bool = False) -> DataFrame:
    """query_id, ap. hits carry hit_rank; relevant items that no hit shows contribute nothing.

    "trapezoid" averages the precision before and after each relevant hit, "none" takes it at the hit.
    """
    if exclude_self:
        hits, truth = hits.where("query_id <> vec_id"), truth.where("query_id <> vec_id")
        hits = hits.withColumn("hit_rank", F.row_number().over(Window.partitionBy("query_id").orderBy("hit_rank")))
    found = hits.join(truth.select("query_id", "vec_id"), ["query_id", "vec_id"], "left_semi")
    nth = F.row_number().over(Window.partitionBy("query_id").orderBy("hit_rank"))
    at = found.withColumn("n", nth).withColumn("p", F.col("n") / F.col("hit_rank"))
    before = F.when(F.col("hit_rank") == 1, 1.0).otherwise((F.col("n") - 1) / F.greatest(F.col("hit_rank") - 1, F.lit(1)))
    gain = F.col("p") if interpolation == "none" else (F.col("p") + before) / 2
    sums = at.groupBy("query_id").agg(F.sum(gain).alias("s"))
    sizes = truth.groupBy("query_id").agg(F.count("*").alias("relevant"))
    return sizes.join(sums, "query_id", "left").select("query_id", (F.coalesce("s", F.lit(0.0)) / F.col("relevant")).alias("ap"))


def mean_average_precision(hits: DataFrame, truth: DataFrame, **options) -> DataFrame:
    return average_precision(hits, truth, **options).agg(F.avg("ap").alias("map"), F.count("*").alias("queries"))


def mean_correct_at(hits: DataFrame, truth: DataFrame, queries: DataFrame, k: int = 4) -> DataFrame:
    """Mean number of correct items among the k best of each query."""
    good = hits.where(F.col("hit_rank") <= k).join(truth.select("query_id", "vec_id"), ["query_id", "vec_id"], "left_semi").groupBy("query_id").agg(F.count("*").alias("n"))
    return queries.select("query_id").join(good, "query_id", "left").agg(F.avg(F.coalesce("n", F.lit(0))).alias("correct"), F.count("*").alias("queries"))


def unit_matches(ranked: DataFrame, members: DataFrame, truth: DataFrame) -> DataFrame:
    """query_id, unit_id, unit_rank, n_match: how many true matches of the query each ranked unit holds."""
    of_unit = truth.join(members.select("vec_id", "unit_id"), "vec_id").groupBy("query_id", "unit_id").agg(F.count("*").alias("n"))
    return ranked.join(of_unit, ["query_id", "unit_id"], "left").select("query_id", "unit_id", "unit_rank", F.coalesce("n", F.lit(0)).alias("n_match"))


def match_probability_by_rank(matches: DataFrame) -> DataFrame:
    return matches.groupBy("unit_rank").agg(F.avg((F.col("n_match") > 0).cast("int")).alias("p_match"))


def matches_given_positive_by_rank(matches: DataFrame) -> DataFrame:
    return matches.where("n_match > 0").groupBy("unit_rank").agg(F.avg("n_match").alias("avg_matches"))


def imbalance(assigned: DataFrame, units: int | None = None, by: list[str] | None = None) -> DataFrame:
    """n, units, delta, var_size: units times the sum of squared shares; 1 for equal units. units: those asked for, empty ones too."""
    by = by or []
    sizes = assigned.groupBy(*by, "unit_id").agg(F.count("*").alias("c"))
    m = F.lit(units) if units else F.count("*")
    out = sizes.groupBy(*by).agg(F.sum("c").alias("n"), m.cast("bigint").alias("units"), F.sum(F.col("c") * F.col("c")).alias("s2"))
    out = out.withColumn("delta", F.col("units") * F.col("s2") / (F.col("n") * F.col("n")))
    return out.withColumn("var_size", (F.col("delta") - 1) * F.col("n") * F.col("n") / (F.col("units") * F.col("units"))).drop("s2")


def index_overhead(reps: DataFrame, members: DataFrame) -> DataFrame:
    """Numbers stored for representatives over those of members."""
    a = reps.agg(F.sum(F.size("rep")).alias("rep_numbers"))
    b = members.agg(F.sum(F.size("vec")).alias("member_numbers"))
    return a.crossJoin(b).withColumn("overhead", F.col("rep_numbers") / F.col("member_numbers"))


def build_cost(n: int, units: int, rounds: int, batch: int | None = None, per_unit: int = 10) -> int:
    """Vector operations of assignment: none for random units, rounds x vectors x units of a batch for k-means."""
    return rounds * n * (units if batch is None else max(1, batch // per_unit))


def kl_empirical(scores: DataFrame) -> DataFrame:
    """Divergence of related from unrelated scores if both are normal with their means and variances."""
    m = scores.agg(
        *[f(F.when(c, F.col("score"))).alias(a) for c, tag in ((F.col("related"), "1"), (~F.col("related"), "0")) for f, a in ((F.avg, f"mean{tag}"), (F.var_pop, f"var{tag}"))]
    )
    kl = (F.col("var1") / F.col("var0") + (F.col("mean1") - F.col("mean0")) ** 2 / F.col("var0") - 1 - F.log(F.col("var1") / F.col("var0"))) / 2
    return m.withColumn("kl", kl)


def filter_queries(truth: DataFrame, least: int = 1, most: int = 1000) -> DataFrame:
    """query_id, matches of queries whose number of matches lies in a range."""
    return truth.groupBy("query_id").agg(F.count("*").alias("matches")).where(F.col("matches").between(least, most))


def quality_cost_curve(scores: DataFrame, reps: DataFrame, members: DataFrame, truth: DataFrame, queries: DataFrame, n: int, taus: list[float]) -> DataFrame:
    """tau, ratio_mean, recall: cost and recall of range search at every threshold, from one scoring of units.

    A true match is found exactly if its unit is opened, so no verification is run.
    """
    units, asked = reps.count(), queries.count()
    tau = F.explode(F.array(*[F.lit(float(t)) for t in taus])).alias("tau")
    sized = scores.join(reps.select("unit_id", "n_members"), "unit_id")
    match = truth.join(members.select("vec_id", "unit_id"), "vec_id").groupBy("query_id", "unit_id").agg(F.count("*").alias("n_match"))
    rows = sized.join(match, ["query_id", "unit_id"], "left").select("score", "n_members", F.coalesce("n_match", F.lit(0)).alias("n_match"), tau)
    hit = F.col("score") > F.col("tau")
    out = rows.groupBy("tau").agg(F.sum(F.when(hit, F.col("n_members")).otherwise(0)).alias("opened"), F.sum(F.when(hit, F.col("n_match")).otherwise(0)).alias("found"), F.sum("n_match").alias("all"))
    return out.select("tau", ((F.col("opened") / asked + units) / n).alias("ratio_mean"), F.when(F.col("all") > 0, F.col("found") / F.col("all")).alias("recall"))


def repeat_runs(runs: list[DataFrame], by: list[str], value: str) -> DataFrame:
    """Mean and spread of a value over runs with different seeds."""
    out = runs[0]
    for r in runs[1:]:
        out = out.unionByName(r)
    return out.groupBy(*by).agg(F.avg(value).alias(f"{value}_mean"), F.stddev_pop(value).alias(f"{value}_sd"), F.count("*").alias("runs"))


def metrics_rollup(results: DataFrame, dims: list[str], value: str) -> DataFrame:
    return results.rollup(*dims).agg(F.avg(value).alias(f"avg_{value}"), F.count("*").alias("cnt"))


def metrics_cube(results: DataFrame, dims: list[str], value: str) -> DataFrame:
    return results.cube(*dims).agg(F.avg(value).alias(f"avg_{value}"), F.count("*").alias("cnt"))


def pivot_by_kind(results: DataFrame, row: str, column: str, values: list[str], value: str) -> DataFrame:
    return results.groupBy(row).pivot(column, values).agg(F.first(value))
