"""Experiment workloads without a SQL twin: each gives the rows of a curve or table. Tests hold them against numpy and the model."""

from __future__ import annotations

import itertools
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import features as ft
from ..functions import kernels, theory, udtf
from ..functions import vectors as vx
from ..operators import assign, baselines, codes, metrics, reduce, represent, search
from ..sources import tables
from ..streaming import arrivals
from .queries import D, dimensions, members, pinv_index, planted, r6, stated, vectors

OPENED = [1, 2, 5, 10, 20, 40]
ALPHAS = (0.5, 0.6, 0.7, 0.8, 0.9)
UNIT, TURNS = 10, 1 << 20


# vector families ---------------------------------------------------------------------------------------------------------------


def document_vectors(spark, sf, d: int = 256) -> DataFrame:
    """Hashed words of documents, centred by language."""
    docs = tables.load_table(spark, sf, "documents", ["doc_id", "text", "lang"])
    return vx.center_vectors(ft.hash_vectors(docs, "doc_id", "text", d, keep=["lang"]).cache(), "lang").where("vec is not null").select("vec_id", "vec")


def stored_documents(spark, sf, d: int = 256, centred: bool = True) -> tuple[DataFrame, str]:
    """(document_vectors, their folder) with nothing kept in the executors' heaps. Not centred: hashed counts, mostly zeros, are what is
    stored, and every scan centres them again."""
    docs = tables.load_table(spark, sf, "documents", ["doc_id", "text", "lang"])
    hashed, path = tables.save(ft.hash_vectors(docs, "doc_id", "text", d, keep=["lang"]), "hashed")
    v = vx.center_vectors(hashed, "lang").where("vec is not null").select("vec_id", "vec")
    if not centred:
        return v, path
    out = tables.save(v, "vectors")
    tables.drop(spark, path)
    return out


def trigram_vectors(spark, sf) -> DataFrame:
    """Hashed character trigrams of documents, not centred: a family of low intrinsic dimension."""
    return ft.hash_vectors(tables.load_table(spark, sf, "documents", ["doc_id", "text"]), "doc_id", "text", 512, kind="char")


def conversation_vectors(spark, sf) -> DataFrame:
    """Turns; the id has the turn in its last 20 bits, so conversations of up to a million turns never meet."""
    turns = tables.load_table(spark, sf, "conversations").select((F.col("conv_id") * TURNS + F.col("turn")).alias("id"), "text")
    return vx.center_vectors(ft.hash_vectors(turns, "id", "text", 256).cache()).where("vec is not null")


def page_vectors(spark, sf) -> DataFrame:
    pages = tables.load_table(spark, sf, "pages", ["page_id", "html"]).select("page_id", ft.html_to_text(F.col("html")).alias("text"))
    return ft.hash_vectors(pages, "page_id", "text", 256)


def basket_vectors(spark, sf) -> DataFrame:
    t = {n: tables.load_table(spark, sf, n) for n in ("lineitem", "orders", "part")}
    return vx.center_vectors(ft.basket_vectors(t["lineitem"], t["orders"], t["part"], "o_custkey", 128), None).where("vec is not null")


def profile_vectors(spark, sf) -> DataFrame:
    return vx.center_vectors(ft.profile_vectors(tables.load_table(spark, sf, "events")), None).where("vec is not null")


# curves --------------------------------------------------------------------------------------------------------------------------


def curve_by_units(index: search.Index, queries: DataFrame, truth: DataFrame | float, n: int, opened: list[int] = OPENED, every: int | None = None) -> DataFrame:
    """opened, ratio_mean, ratio_std, recall when a fixed number of best units is opened, all numbers from one probe.

    truth: the matches, or the similarity that makes a match; then ``every`` is their number (search.count_matches), and only members
    of opened units are compared again. Computed at once, so that shuffles and caches of an index go with it.
    """
    m, most = index.reps.count(), max(opened)
    ranked, at = search.rank_stored(index.reps, queries, most)
    if isinstance(truth, float):
        few = queries.count() * most <= tables.BROADCAST_ROWS
        found = search.verify(ranked, index.members, queries, truth, with_unit=True, few=few).where("query_id <> vec_id").select("query_id", F.col("unit_id").cast("bigint").alias("unit_id"))
    else:
        found = truth.join(index.members.select("vec_id", "unit_id"), "vec_id")
        every = truth.count()
    match = found.groupBy("query_id", "unit_id").agg(F.count("*").alias("n_match"))
    k = F.explode(F.array(*[F.lit(x) for x in opened])).alias("opened")
    rows = ranked.drop("score").join(index.reps.select("unit_id", "n_members"), "unit_id").join(match, ["query_id", "unit_id"], "left")
    rows = rows.select("query_id", "unit_rank", "n_members", F.coalesce("n_match", F.lit(0)).alias("n_match"), k)
    per = rows.where("unit_rank <= opened").groupBy("opened", "query_id").agg(((F.sum("n_members") + m) / n).alias("ratio"), F.sum("n_match").alias("found"))
    out = per.groupBy("opened").agg(F.avg("ratio").alias("ratio_mean"), F.stddev_pop("ratio").alias("ratio_std"), F.sum("found").alias("found"))
    out = tables.now(out.select("opened", r6("ratio_mean").alias("ratio_mean"), r6("ratio_std").alias("ratio_std"), r6(F.col("found") / max(every, 1)).alias("recall")))
    tables.drop(ranked.sparkSession, at)
    return out


def _truth(v: DataFrame, queries: DataFrame, alpha0: float) -> DataFrame:
    return search.exhaustive_search(v, queries, alpha0=alpha0).where("query_id <> vec_id").select("query_id", "vec_id", "sim")


def _tag(df: DataFrame, **columns) -> DataFrame:
    for name, value in columns.items():
        df = df.withColumn(name, F.lit(value))
    return df


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def index_of(v: DataFrame, method: str, n: int, d: int, seed: int = 0, unit: int = UNIT, batch: int | None = None) -> search.Index:
    """An index by name: random, batch, full or minibatch assignment; sum or pinv; _norm for unit-norm centroids.

    A full clustering is one batch of all rows, a batch a quarter of them if nothing else is asked for. Where a batch is clustered,
    in a task or over all of them, follows from its size; its units don't.
    """
    how, _, rest = method.partition("-")
    kind, normalize = rest.removesuffix("_norm") or "pinv", rest.endswith("_norm")
    if how == "minibatch":
        return baselines.minibatch_index(v, max(1, n // unit), max(1, n // 10), 40, seed)
    if how == "ivf":
        return baselines.ivf_index(v, max(1, n // unit), seed=seed)
    if how == "random":
        return search.build_index(assign.assign_random(v, unit, n, seed).select("vec_id", "vec", "unit_id"), kind, d)  # a map over the vectors
    size = max(1, n) if how == "full" else batch or max(1, n // 4)
    placed = assign.batch_spherical_kmeans(v, size, unit, kind, normalize, seed, n=n)
    folder = tables.saved_folder(placed, "assigned")
    placed = placed.select("vec_id", "vec", "unit_id")
    return search.build_index(placed if folder else placed.cache(), kind, d, normalize, folder=folder)


def _done(index: search.Index) -> None:
    """Frees what an index keeps once its results are computed."""
    index.members.unpersist()
    if index.meta.get("folder"):
        tables.drop(index.members.sparkSession, index.meta["folder"])


def _stored(v: DataFrame) -> tuple[DataFrame, str | None]:
    """Vectors in the shared folder, out of the executors' heaps, and the folder if it was made now."""
    return (v, None) if tables.saved_folder(v) else tables.save(v.select("vec_id", "vec"), "vectors")


def _compare(v: DataFrame, d: int, methods: list[str], alpha0: float, seeds=(0,), opened=OPENED, every: int | None = None, **options) -> DataFrame:
    v, path = _stored(v)
    n, queries = v.count(), ft.every_50th(v).cache()
    every, out = search.count_matches(v, queries, alpha0) if every is None else every, []
    for m, s in itertools.product(methods, seeds):
        index = index_of(v, m, n, d, s, **options)
        out.append(_tag(curve_by_units(index, queries, float(alpha0), n, opened, every), method=m, seed=s))
        _done(index)
    queries.unpersist()
    if path:
        tables.drop(v.sparkSession, path)
    return _union(out)


# representatives -------------------------------------------------------------------------------------------------------------


def rep_pinv_degenerate(spark, sf):
    """Units of documents that hold exact copies: their Gram matrices are singular, yet members keep product one."""
    index = search.build_index(document_vectors(spark, sf).withColumn("unit_id", F.col("vec_id") % 20), "pinv", 256)
    from ..functions.vectors import dot

    off = index.members.join(index.reps, "unit_id").groupBy("unit_id").agg(F.max(F.abs(dot("vec", "rep") - 1)).alias("worst"), F.count("*").alias("n"))
    return off.select("unit_id", "n", r6("worst").alias("worst"))


def rep_ridge(spark, sf):
    base = members(spark, sf)
    parts = [_tag(represent.ridge_representatives(base, lam).select("unit_id", r6("rep_norm2").alias("rep_norm2")), lam=lam) for lam in (0.0, 0.1, 1.0, 10.0)]
    return _union(parts)


def rep_online(spark, sf):
    return represent.online_representatives(members(spark, sf)).select("unit_id", "n_members", r6("rep_norm2").alias("rep_norm2"))


def gram_spectrum(spark, sf):
    """Eigenvalues of units' Gram matrices against the limit law: share in ten bins of its support."""
    lo, hi = theory.mp_support(UNIT / D)
    rows = represent.gram_eigenvalues(members(spark, sf))
    total = rows.count()
    b = F.floor((F.col("lambda") - lo) / (hi - lo) * 10).cast("int")
    got = rows.groupBy(b.alias("bin")).agg((F.count("*") / total).alias("share"))
    grid = [(i, sum(theory.mp_pdf(lo + (hi - lo) * (i + (j + 0.5) / 50) / 10, UNIT / D) for j in range(50)) / 50 * (hi - lo) / 10) for i in range(10)]
    model = spark.createDataFrame(grid, "bin int, model double")
    return model.join(got, "bin", "full").select("bin", r6("share").alias("share"), r6("model").alias("model"))


# model -------------------------------------------------------------------------------------------------------------------------


def mp_moments(spark, sf):
    """Moments of the eigenvalues of Gram matrices of the table's units, of several sizes, beside those of the limit law."""
    out = []
    for size in (3, 6, 13, 32, 51):
        c = size / D
        measured = represent.gram_eigenvalues(members(spark, sf, size)).agg(*[r6(F.avg(F.pow("lambda", F.lit(k)))).alias(name) for k, name in ((0, "m0"), (1, "m1"), (2, "m2"), (-1, "m_inv"))])
        model = {f"{name}_model": round(theory.mp_moment(k, c), 6) for k, name in ((0, "m0"), (1, "m1"), (2, "m2"), (-1, "m_inv"))}
        out.append(_tag(measured, c=c, norm2_pinv=round(1 / (1 - c), 6), **model))
    return _union(out)


ETAS = [-1.0, *(round(i / 20, 2) for i in range(0, 20))]


def _kl(spark, sf, kind):
    """Divergence along a sweep of the cap, in the table's dimension."""
    (d,) = dimensions(spark, sf)
    rows = [(e, *(round(x, 9) for x in r)) for e, *r in theory.kl_curve(kind, d, UNIT, 0.5, ETAS)]
    return spark.createDataFrame(rows, "eta double, e0 double, v0 double, e1 double, v1 double, kl double")


def kl_sum(spark, sf):
    return _kl(spark, sf, "sum")


def kl_pinv(spark, sf):
    return _kl(spark, sf, "pinv")


CAPS = (0.0, 0.3, 0.5, 0.7, 0.9)


def _runs(spark, sf, rows: int) -> DataFrame:
    """The table's vectors in runs of so many consecutive ids; who uses them leaves out a run that is not full."""
    return vectors(spark, sf).withColumn("run", F.floor(F.col("vec_id") / rows)).select("run", "vec_id", "vec")


def cap_simulation(spark, sf):
    """Scores of clustered units made of the table's vectors against the model: means and variances under both hypotheses, n = 10.

    Ten vectors of a run are moved onto a cap, the eleventh, whose sign alternates, is unrelated; every eighth component serves as axis.
    """
    n, alpha = UNIT, 0.5

    def simulate(key, table):
        x = kernels.matrix(table.sort_by("vec_id").column("vec"))
        rows = []
        for eta, turn in itertools.product(CAPS, range(0, x.shape[1], 8) if len(x) == n + 1 else ()):
            turned = np.roll(x, -turn, axis=1)
            y, z = ft.onto_cap(turned[:n], eta), turned[n] / np.linalg.norm(turned[n])
            z = z if turn % 16 else -z  # as likely
            w = z - (y @ z)[:, None] * y  # every member is asked for
            asked = alpha * y + (1 - alpha**2) ** 0.5 * w / np.linalg.norm(w, axis=1, keepdims=True)
            for kind in ("sum", "pinv"):
                m = kernels.representative(y, kind)
                rows += [(kind, eta, float(m @ z), float(s)) for s in asked @ m]
        return _arrow(rows, [("kind", pa.string()), ("eta", pa.float64()), ("s0", pa.float64()), ("s1", pa.float64())])

    got = _runs(spark, sf, n + 1).groupBy("run").applyInArrow(simulate, "kind string, eta double, s0 double, s1 double")
    got = got.groupBy("kind", "eta").agg(*[f(c).alias(f"{a}_{c}") for c in ("s0", "s1") for f, a in ((F.avg, "mean"), (F.var_pop, "var"))])
    model = [(k, e, *theory.moments(k, n, D, alpha, e)) for k in ("sum", "pinv") for e in CAPS]
    return got.join(spark.createDataFrame(model, "kind string, eta double, e0 double, v0 double, e1 double, v1 double"), ["kind", "eta"])


def _arrow(rows: list[tuple], fields: list[tuple]) -> pa.Table:
    return pa.table([pa.array([r[i] for r in rows], kind) for i, (_, kind) in enumerate(fields)], names=[name for name, _ in fields])


def cost_curve_cap(spark, sf):
    """Expected cost against unit size for clustered units, in the table's dimension."""
    (d,) = dimensions(spark, sf)
    grid = itertools.product(("sum", "pinv"), ALPHAS, (0.0, 0.1, 0.2, 0.4), (2, 3, 5, 7, 10, 15, 20, 30, 50, 70, 100, 150))
    rows = [(k, a, e, n, round(theory.expected_cost_ratio(k, n, d, a, 0.01, e), 6)) for k, a, e, n in grid]
    return spark.createDataFrame(rows, "kind string, alpha0 double, eta double, n int, cost_ratio double")


def cost_cap_measured(spark, sf):
    """The same cost measured: share of clustered units of the table's vectors that unrelated vectors open at the modelled threshold, and
    one probe a unit. Twenty vectors of a run are moved onto a cap, twenty are unrelated; every second component serves as axis."""
    eps = 0.05
    tau = {(k, n, e, a): theory.threshold(k, n, D, a, eps, e) for k in ("sum", "pinv") for n in (5, 10, 20) for e in (0.0, 0.2, 0.4) for a in (0.5, 0.7, 0.9)}

    def measure(key, table):
        x = kernels.matrix(table.sort_by("vec_id").column("vec"))
        opened = dict.fromkeys(tau, 0)
        turns = range(0, x.shape[1], 2) if len(x) == 40 else ()
        for turn in turns:
            turned = np.roll(x, -turn, axis=1)
            z = turned[20:] / np.linalg.norm(turned[20:], axis=1, keepdims=True)
            for e in (0.0, 0.2, 0.4):
                y = ft.onto_cap(turned[:20], e)
                for n, k in itertools.product((5, 10, 20), ("sum", "pinv")):
                    s = z @ kernels.representative(y[:n], k)
                    for a in (0.5, 0.7, 0.9):
                        opened[k, n, e, a] += int((s > tau[k, n, e, a]).sum())
        rows = [(*t, o, 20 * len(turns)) for t, o in opened.items()]
        return _arrow(rows, [("kind", pa.string()), ("n", pa.int32()), ("eta", pa.float64()), ("alpha0", pa.float64()), ("opened", pa.int32()), ("tried", pa.int32())])

    got = _runs(spark, sf, 40).groupBy("run").applyInArrow(measure, "kind string, n int, eta double, alpha0 double, opened int, tried int")
    got = got.groupBy("kind", "n", "eta", "alpha0").agg((F.try_divide(F.sum("opened"), F.sum("tried")) + 1 / F.col("n")).alias("ratio"))
    model = [(k, n, e, a, round(theory.expected_cost_ratio(k, n, D, a, eps, e), 6)) for k, n, e, a in tau]
    return got.join(spark.createDataFrame(model, "kind string, n int, eta double, alpha0 double, ratio_model double"), ["kind", "n", "eta", "alpha0"]).withColumn("ratio", r6("ratio"))


#: First components of the table's vectors whose dimension is measured.
PREFIXES = (16, 32, 48, 64)


def capacity(spark, sf):
    """Largest units in the measured dimensions of the table's vectors and of their first components."""
    dims = list(zip(PREFIXES, dimensions(spark, sf, PREFIXES), strict=True))
    rows = [(k, c, d, theory.capacity(k, d, 0.7, 0.01, 0.05)) for k in ("sum", "pinv") for c, d in dims]
    return spark.createDataFrame(rows, "kind string, components int, d int, n int")


def plans(spark, sf):
    """Plans for the measured dimensions of the table's vectors and of their first components."""
    dims = zip(PREFIXES, dimensions(spark, sf, PREFIXES), strict=True)
    rows = [(c, d, a, p.kind, p.unit_size, round(p.tau, 6), round(p.cost_ratio, 6)) for c, d in dims for a in (0.5, 0.7, 0.9) for p in [search.auto_plan(d, a, 0.01)]]
    return spark.createDataFrame(rows, "components int, d int, alpha0 double, kind string, unit_size int, tau double, cost_ratio double")


def roc_planted(spark, sf):
    """Measured and modelled rates of random units for five similarities, both representatives."""
    out = []
    for kind, index in (("sum", search.build_index(members(spark, sf), "sum", D)), ("pinv", pinv_index(spark, sf))):
        own = index.members.select(F.col("vec_id").alias("query_id"), F.col("unit_id").alias("own"))
        for alpha in (0.5, 0.6, 0.7, 0.8, 0.9):
            rates = tables.now(search.own_rates(index.reps, planted(spark, sf, alpha).join(own, "query_id"), [0.21, 0.41, 0.61]))
            model = [(t, *theory.error_rates(kind, t, UNIT, D, alpha)) for t in (0.21, 0.41, 0.61)]
            joined = rates.join(spark.createDataFrame(model, "tau double, pfp_model double, pfn_model double"), "tau")
            out.append(_tag(joined, kind=kind, alpha=alpha))
    return _union(out)


def roc_sphere(spark, sf):
    """Measured and modelled rates on generated vectors of 100 components, both representatives, three similarities."""
    d = 100
    v = ft.sphere(spark, 2000, d, 5).cache()
    placed = assign.assign_random(v, UNIT, 2000, mode="modulo").cache()
    own = placed.select(F.col("vec_id").alias("query_id"), F.col("unit_id").alias("own"))
    out = []
    for kind, alpha in itertools.product(("sum", "pinv"), (0.5, 0.7, 0.9)):
        index = search.build_index(placed, kind, d)
        s = search.probe(index.reps, ft.plant_queries(v, alpha)).join(own, "query_id").select("score", (F.col("unit_id") == F.col("own")).alias("related"))
        model = [(t, *theory.error_rates(kind, t, UNIT, d, alpha)) for t in (0.21, 0.41, 0.61, 0.81)]
        out.append(_tag(metrics.error_rates(s, [m[0] for m in model]).join(spark.createDataFrame(model, "tau double, pfp_model double, pfn_model double"), "tau"), kind=kind, alpha=alpha))
    return _union(out)


def roc_families(spark, sf):
    """ROC of random units on documents and conversations: a unit is related if it holds a vector of that cosine, both representatives."""
    out = []
    for family, v in (("documents", document_vectors(spark, sf)), ("conversations", conversation_vectors(spark, sf))):
        v = v.cache()
        n, queries = v.count(), ft.every_50th(v).cache()
        for kind in ("sum", "pinv"):
            placed = assign.assign_random(v, UNIT, n).select("unit_id", "vec_id", "vec")
            counts = search.near_counts(placed, queries, kind, (0.5, 0.7, 0.9), -0.5, 1.5, 20)
            for alpha0 in (0.5, 0.7, 0.9):
                curve = metrics.roc_of_counts(counts.where(F.col("alpha0") == alpha0).drop("alpha0"), -0.5, 1.5, 20)
                area = metrics.auc(curve).first()[0]
                out.append(_tag(curve.select(r6("tau").alias("tau"), r6("pfp").alias("pfp"), r6("tpr").alias("tpr")), family=family, kind=kind, alpha0=alpha0, auc=None if area is None else round(float(area), 6)))
        v.unpersist()
    return _union([o.withColumn("auc", F.col("auc").cast("double")) for o in out])


# clustering and imbalance --------------------------------------------------------------------------------------------------------


def _kmeans(spark, sf, rep, normalize):
    out = assign.spherical_kmeans(vectors(spark, sf), 20, rep, normalize, "first", max_iter=4, d=D)
    return metrics.imbalance(out, 20).select("n", "units", r6("delta").alias("delta"))


def kmeans_pinv(spark, sf):
    return _kmeans(spark, sf, "pinv", False)


def kmeans_pinv_norm(spark, sf):
    return _kmeans(spark, sf, "pinv", True)


def batch_kmeans(spark, sf):
    v = document_vectors(spark, sf).cache()
    out = assign.batch_spherical_kmeans(v, 250, UNIT, "pinv", True)
    return metrics.imbalance(out, by=["batch_id"]).select("batch_id", "n", "units", r6("delta").alias("delta"))


def batch_kmeans_full(spark, sf):
    v = document_vectors(spark, sf).cache()
    return metrics.imbalance(index_of(v, "full-pinv_norm", v.count(), 256).members).select("n", "units", r6("delta").alias("delta"))


def imbalance_variants(spark, sf):
    """Imbalance of the four centroid updates and of mini-batch k-means on three families."""
    out = []
    for family, v, d in (("documents", document_vectors(spark, sf), 256), ("conversations", conversation_vectors(spark, sf), 256), ("baskets", basket_vectors(spark, sf), 128)):
        v, path = _stored(v)
        n = v.count()
        for method in ("full-sum", "full-sum_norm", "full-pinv", "full-pinv_norm", "minibatch"):
            index = index_of(v, method, n, d)
            out.append(_tag(tables.now(metrics.imbalance(index.members, max(1, n // UNIT)).select("n", "units", r6("delta").alias("delta"))), family=family, method=method))
            _done(index)
        tables.drop(spark, path)
    return _union(out)


def random_and_clustered(spark, sf):
    """Cost and recall of random and clustered units on documents, both representatives."""
    v, path = stored_documents(spark, sf)
    out = _compare(v, 256, ["random-sum", "random-pinv", "full-sum_norm", "full-pinv_norm"], 0.5)
    tables.drop(spark, path)
    return out


def unit_sizes(spark, sf):
    v, path = stored_documents(spark, sf)
    every = search.count_matches(v, ft.every_50th(v), 0.5)
    out = _union([_tag(_compare(v, 256, ["random-pinv", "full-pinv_norm"], 0.5, every=every, unit=n), n=n) for n in (5, 10, 20, 50)])
    tables.drop(spark, path)
    return out


def low_dimension(spark, sf):
    """Measured against expected cost where intrinsic dimension is low: trigrams against uniform vectors."""
    out = []
    for family, v, d in (("trigrams", trigram_vectors(spark, sf), 512), ("embeddings", vectors(spark, sf), D)):
        v = v.cache()
        base, unrelated = ft.holdout(v, 50)
        n = base.count()
        index = search.build_index(assign.assign_random(base, UNIT, n).cache(), "sum", d)
        tau = theory.threshold("sum", UNIT, d, 0.7, 0.05)
        costs = metrics.complexity_ratio(metrics.query_cost(search.probe(index.reps, unrelated, tau), index.reps, unrelated), n)
        row = costs.agg(F.avg("ratio")).first()[0]
        out.append((family, d, round(reduce.effective_dimension(v), 4), round(row, 6), round(theory.expected_cost_ratio("sum", UNIT, d, 0.7, 0.05), 6)))
    return spark.createDataFrame(out, "family string, d int, effective_d double, ratio double, ratio_model double")


FAMILIES = (("documents", document_vectors, 256, 0.5), ("conversations", conversation_vectors, 256, 0.4), ("profiles", profile_vectors, 120, 0.3))


def cost_spread(spark, sf):
    """Spread of cost over queries when a fixed number of units is opened: plain sum, pinv, mini-batch, on three families."""
    return _union([_tag(_compare(make(spark, sf), d, ["full-sum", "full-pinv", "minibatch"], alpha0, opened=[4, 10]), family=family) for family, make, d, alpha0 in FAMILIES])


def _query_ratios(index: search.Index, queries: DataFrame, n: int, opened: int) -> DataFrame:
    """query_id, ratio when the best so many units are opened."""
    positives, _ = search.rank_stored(index.reps, queries, opened)
    return metrics.complexity_ratio(metrics.query_cost(positives, index.reps, queries), n)


def cost_histograms(spark, sf):
    """Histograms of cost over queries at four opened units, in 50 bins up to a half: sum against pinv units on three families."""
    out = []
    for family, make, d, _ in FAMILIES:
        v = make(spark, sf).cache()
        n, queries = v.count(), ft.every_50th(v).cache()
        for method in ("full-sum", "full-pinv"):
            index = index_of(v, method, n, d)
            out.append(_tag(tables.now(metrics.cost_histogram(_query_ratios(index, queries, n, 4), 50, 0.5)), family=family, method=method))
            _done(index)
        v.unpersist()
    return _union(out)


def positive_units_protocol(spark, sf):
    """Cost of a query when 3.5 % of all units are opened: batch clustering against mini-batch k-means, with means and spreads over queries."""
    v = document_vectors(spark, sf).cache()
    n, queries = v.count(), ft.every_50th(v).cache()
    opened, out = max(1, round(0.035 * n / UNIT)), []
    for method in ("batch-pinv_norm", "batch-sum_norm", "minibatch"):
        index = index_of(v, method, n, 256)
        rows = metrics.cost_summary(_query_ratios(index, queries, n, opened))
        out.append(_tag(tables.now(rows.select("queries", r6("ratio_mean").alias("ratio_mean"), r6("ratio_std").alias("ratio_std"))), method=method, opened=opened))
        _done(index)
    return _union(out)


def batch_assignment(spark, sf):
    """Random, batch (two batch sizes) and full clustering, over five seeds."""
    v, path = stored_documents(spark, sf)
    n = v.count()
    every = search.count_matches(v, ft.every_50th(v), 0.5)
    small = _tag(_compare(v, 256, ["batch-pinv_norm"], 0.5, seeds=range(5), opened=[1, 5], every=every, batch=max(1, n // 16)), size="n/16")
    rest = _tag(_compare(v, 256, ["random-pinv", "batch-pinv_norm", "full-pinv_norm"], 0.5, seeds=range(5), opened=[1, 5], every=every), size="")
    tables.drop(spark, path)
    curves = small.unionByName(rest).withColumn("method", F.concat("method", F.when(F.col("size") == "", "").otherwise(F.concat(F.lit(" "), "size")))).cache()
    recall = metrics.repeat_runs([curves], ["method", "opened"], "recall")
    cost = metrics.repeat_runs([curves], ["method", "opened"], "ratio_mean").drop("runs")
    return recall.join(cost, ["method", "opened"]).select("method", "opened", r6("ratio_mean_mean").alias("ratio"), r6("recall_mean").alias("recall"), r6("recall_sd").alias("recall_sd"), "runs")


def minibatch_imbalance(spark, sf):
    """Imbalance of mini-batch k-means and of independent batches, mean and spread over five seeds."""
    v, path = stored_documents(spark, sf)
    n = v.count()

    def delta(m, seed):
        index = index_of(v, m, n, 256, seed)
        row = tables.now(metrics.imbalance(index.members, max(1, n // UNIT)).select("delta"))
        _done(index)
        return row

    runs = {m: [delta(m, seed) for seed in range(5)] for m in ("minibatch", "batch-pinv_norm", "batch-sum_norm")}
    tables.drop(spark, path)
    return _union([_tag(metrics.repeat_runs(r, [], "delta").select(r6("delta_mean").alias("delta_mean"), r6("delta_sd").alias("delta_sd"), "runs"), method=m) for m, r in runs.items()])


def minibatch_comparison(spark, sf):
    return _compare(document_vectors(spark, sf), 256, ["batch-pinv_norm", "batch-sum_norm", "minibatch"], 0.5, batch=250)


def large_protocol(spark, sf):
    """Queries with one to a thousand matches only; three kinds of index, recall against cost."""
    v = document_vectors(spark, sf).cache()
    n, queries = v.count(), ft.every_50th(v).cache()
    truth = _truth(v, queries, 0.5).cache()
    kept = metrics.filter_queries(truth, 1, 1000).select("query_id")
    queries, truth = queries.join(kept, "query_id", "left_semi").cache(), truth.join(kept, "query_id", "left_semi").cache()
    return _union([_tag(curve_by_units(index_of(v, m, n, 256, batch=500), queries, truth, n), method=m) for m in ("random-pinv", "batch-sum_norm", "batch-pinv_norm")])


def distractors(spark, sf):
    """Recall of document queries as pages join the database."""
    docs, pages = ft.hash_vectors(tables.load_table(spark, sf, "documents", ["doc_id", "text"]), "doc_id", "text", 256), page_vectors(spark, sf)
    both = docs.unionByName(pages.select((-F.col("vec_id") - 1).alias("vec_id"), "vec"))
    out = []
    for name, v in (("documents", docs), ("documents+pages", both)):
        v = vx.center_vectors(v, None).where("vec is not null").cache()
        n, queries = v.count(), ft.every_50th(v.where("vec_id >= 0")).cache()
        index = index_of(v, "batch-pinv_norm", n, 256)
        out.append(_tag(curve_by_units(index, queries, 0.8, n, every=search.count_matches(v, queries, 0.8)), database=name, n=n))
        _done(index)
        v.unpersist()
    return _union(out)


#: Best hits of the exhaustive search that mean average precision looks at.
BEST_HITS = 200


def _map_curve(v: DataFrame, q: DataFrame, truth: DataFrame | float, n: int, d: int, methods: list[str]) -> DataFrame:
    """Mean average precision against cost as more units are opened, beside the exhaustive search, all numbers of an index from one scan.

    truth: the matches of queries; or the similarity that makes another vector a match, then queries without any are left out.
    """
    opened, out = sorted({max(1, n // UNIT * share // 200) for share in (1, 4, 10, 20, 60)}), []
    for method in methods:
        index = index_of(v, method, n, d)
        if isinstance(truth, float):
            per = search.near_precision(index, q, opened, truth, BEST_HITS)
            asked = per.where("opened = 0").count()
        else:
            per = search.listed_precision(index, q, opened, truth, BEST_HITS)
            asked = truth.select("query_id").distinct().count()
        rows = per.groupBy("opened").agg(F.sum("ap").alias("s"), F.avg(F.col("verified") / n).alias("ratio")).collect()
        found = {r.opened: r for r in rows}
        for k in ([] if out else [0]) + opened:
            s, ratio = (found[k].s, found[k].ratio) if k in found else (None, None)
            out.append((method if k else "exhaustive", k, round(float(ratio or 0), 6) if k else 1.0, round((s or 0.0) / asked, 6) if asked else None, asked))
        _done(index)
        tables.release(v.sparkSession)
    return v.sparkSession.createDataFrame(out, "method string, opened int, ratio double, map double, queries bigint")


def passages(spark, sf):
    """Benchmark items as queries for documents that contain them: mean average precision against cost, beside the exhaustive search.

    Which documents contain an item is found by the items' shingles, so no text is compared with all items.
    """
    docs = tables.load_table(spark, sf, "documents", ["doc_id", "text"])
    items = tables.load_table(spark, sf, "benchmark", ["item_id", "text"])
    v, path = tables.save(ft.hash_vectors(docs, "doc_id", "text", 256), "vectors")
    q = ft.hash_vectors(items, "item_id", "text", 256).select(F.col("vec_id").alias("query_id"), F.col("vec").alias("qvec")).cache()
    truth = ft.containing_texts(docs, items).select(F.col("item_id").alias("query_id"), F.col("doc_id").alias("vec_id")).cache()
    out = _map_curve(v, q, truth, v.count(), 256, ["random-pinv", "batch-pinv_norm", "full-pinv_norm"])
    tables.drop(spark, path)
    return out


def near_copy_map(spark, sf):
    """Documents as queries for their near copies (cosine 0.9 or more): mean average precision against cost."""
    v, path = tables.save(document_vectors(spark, sf), "vectors")
    out = _map_curve(v, ft.every_50th(v), 0.9, v.count(), 256, ["random-sum", "random-pinv", "full-pinv_norm"])
    tables.drop(spark, path)
    return out


def match_by_rank_families(spark, sf):
    """Chance that the unit of a rank holds a match, and mean matches if it does: three families, random and clustered units."""
    out = []
    families = (("documents", document_vectors(spark, sf), 256, 0.5), ("conversations", conversation_vectors(spark, sf), 256, 0.4), ("profiles", profile_vectors(spark, sf), 120, 0.3))
    for family, v, d, alpha0 in families:
        v, path = _stored(v)
        n, queries = v.count(), v.select(F.col("vec_id").alias("query_id"), F.col("vec").alias("qvec")).where(F.pmod("vec_id", F.lit(50)) == 0).cache()
        for method in ("random-pinv", "full-sum_norm", "full-pinv_norm"):
            index = index_of(v, method, n, d)
            ranked, at = search.rank_stored(index.reps, queries, 10)
            found = search.verify(ranked, index.members, queries, alpha0, with_unit=True, few=queries.count() * 10 <= tables.BROADCAST_ROWS).where("query_id <> vec_id")
            m = ranked.join(found.groupBy("query_id", F.col("unit_id").cast("bigint").alias("unit_id")).agg(F.count("*").alias("n")), ["query_id", "unit_id"], "left")
            m = m.select("unit_rank", F.coalesce("n", F.lit(0)).alias("n_match")).cache()
            rows = metrics.match_probability_by_rank(m).join(metrics.matches_given_positive_by_rank(m), "unit_rank", "left")
            out.append(_tag(tables.now(rows.select("unit_rank", r6("p_match").alias("p_match"), r6("avg_matches").alias("avg_matches"))), family=family, method=method))
            m.unpersist()
            _done(index)
            tables.drop(spark, at)
        queries.unpersist()
        tables.drop(spark, path)
    return _union(out)


def same_conversation(spark, sf):
    """Turns as queries: how many of the four best other turns belong to the same conversation, exhaustive and as more units open."""
    v, path = tables.save(conversation_vectors(spark, sf).select("vec_id", "vec"), "vectors")
    n, queries = v.count(), ft.every_50th(v)
    index = index_of(v, "batch-pinv_norm", n, 256)
    opened = sorted({1, 5, max(3, n // 200), max(3, n // 50)})
    best, asked = search.best_others(index, queries, opened, 4), queries.count()
    good = F.sum((F.floor(F.col("vec_id") / TURNS) == F.floor(F.col("query_id") / TURNS)).cast("int"))
    found = {r.opened: r.good for r in best.groupBy("opened").agg(good.alias("good")).collect()}
    _done(index)
    tables.drop(spark, path)
    rows = [(found.get(k, 0) / asked if asked else None, asked, "units" if k else "exhaustive", k) for k in (0, *opened)]
    return spark.createDataFrame(rows, "correct double, queries bigint, method string, opened int")


def vector_normalisation(spark, sf):
    """Signed powers before indexing: means of both representatives' squared norms draw together as vectors get more orthogonal."""
    out = []
    for name, v in (("plain", trigram_vectors(spark, sf)), ("power", vx.power_normalize(trigram_vectors(spark, sf), 0.5))):
        diag = represent.unit_diagnostics(v.withColumn("unit_id", F.pmod("vec_id", F.lit(100))))
        out.append(_tag(diag.agg(r6(F.avg("norm2_sum")).alias("norm2_sum"), r6(F.avg("norm2_pinv")).alias("norm2_pinv"), r6(F.avg("lambda_max")).alias("lambda_max")), vectors=name))
    return _union(out)


# reduction and codes -----------------------------------------------------------------------------------------------------------


def pca_variance(spark, sf):
    model = reduce.fit_pca(document_vectors(spark, sf).cache(), 64)
    share = np.cumsum(model.variance) / model.variance.sum()
    rows = [(i + 1, round(float(model.variance[i]), 6), round(float(share[i]), 6)) for i in range(64)]
    return spark.createDataFrame(rows, "component int, variance double, share double")


def pca_search(spark, sf):
    """Search on reduced vectors, held against matches of the full ones."""
    v = document_vectors(spark, sf).cache()
    low = reduce.apply_pca(reduce.fit_pca(v, 64), v).cache()
    n, queries = v.count(), ft.every_50th(v).cache()
    truth = _truth(v, queries, 0.7).cache()
    asked = ft.every_50th(low).cache()
    full = _tag(curve_by_units(index_of(v, "batch-pinv_norm", n, 256), queries, truth, n), d=256)
    return full.unionByName(_tag(curve_by_units(index_of(low, "batch-pinv_norm", n, 64), asked, truth, n), d=64))


SIGN_TAUS = [0.1, 0.15, 0.2, 0.25, 0.3, 0.35, 0.4, 0.5, 0.6]


def sign_documents(spark, sf):
    """Curves of recall against cost for sign codes of reduced document vectors: symmetric and asymmetric, both representatives, beside
    the same units without codes and the exhaustive scan of codes at a threshold."""
    v, path = tables.save(document_vectors(spark, sf), "vectors")
    low, reduced = tables.save(reduce.apply_pca(reduce.fit_pca(v, 64), v), "reduced")
    tables.drop(spark, path)
    n, queries = low.count(), ft.every_50th(low)
    placed, asked = assign.assign_random(low, UNIT, n), queries.count()
    counts = codes.curve_counts(placed, queries, 0.7, 64, SIGN_TAUS)
    units = placed.select("unit_id").distinct().count()
    # a scan of codes: every vector its own unit, verified for nothing
    ratio = F.when(F.col("way") == "scan", 1.0).otherwise(r6((F.col("opened") / asked + units) / n))
    out = tables.now(counts.select("tau", ratio.alias("ratio"), r6(F.when(F.col("all") > 0, F.col("found") / F.col("all"))).alias("recall"), "kind", "way"))
    tables.drop(spark, reduced)
    return out


def other_features(spark, sf):
    """The second family of features: recall against cost for two similarities."""
    v = trigram_vectors(spark, sf).cache()
    return _union([_tag(_compare(v, 512, ["random-pinv", "batch-pinv_norm"], a), alpha0=a) for a in (0.9, 0.98)])


def high_dimension(spark, sf):
    """Words hashed to 1024 and 1920 components: recall against cost, random and batch units, and what a reduction to 128 costs."""
    out = []
    with tables.batches_of(spark, 1000):  # rows of 15 KB
        for d in (1024, 1920):
            v, path = stored_documents(spark, sf, d, centred=False)
            out.append(_tag(_compare(v, d, ["random-pinv", "batch-pinv_norm"], 0.5, batch=1000), d=d, reduced=0))
            if d == 1024:
                low, reduced = tables.save(reduce.apply_pca(reduce.fit_pca(v, 128), v).select("vec_id", "vec"), "reduced")
                n, queries = v.count(), ft.every_50th(v)
                index = index_of(low, "batch-pinv_norm", n, 128, batch=1000)
                curve = curve_by_units(index, ft.every_50th(low).cache(), _truth(v, queries, 0.5).cache(), n)
                out.append(_tag(curve, method="batch-pinv_norm", seed=0, d=d, reduced=128))
                _done(index)
                tables.drop(spark, reduced)
            tables.drop(spark, path)
    return _union(out)


# baselines ---------------------------------------------------------------------------------------------------------------------


def baseline_forest(spark, sf):
    """A tuned forest of k-d trees: every grid point with its precision and the share of vectors it compares."""
    v, q = vectors(spark, sf).cache(), stated(spark, sf, 0.7).cache()
    n = v.count()
    tuned = baselines.tune_forest(v, q, search.exhaustive_search(v, q, k=1).cache(), n)
    return spark.createDataFrame([(i, t.trees, t.checks, round(t.precision, 6), round(t.ratio, 6), round(t.cost, 6)) for i, t in enumerate(tuned)], "place int, trees int, checks int, precision double, ratio double, cost double")


def forest_or_units(spark, sf):
    """The tuned forest beside units at equal recall, on documents among pages: share of vectors compared until 90 % of matches are found.

    The forest is the cheapest of k-d and k-means trees that meets the precision on the best hit; units open until they find as many.
    """
    docs, pages = ft.hash_vectors(tables.load_table(spark, sf, "documents", ["doc_id", "text"]), "doc_id", "text", 256), page_vectors(spark, sf)
    v = vx.center_vectors(docs.unionByName(pages.select((-F.col("vec_id") - 1).alias("vec_id"), "vec")).cache()).where("vec is not null").cache()
    n, q = v.count(), ft.every_50th(v.where("vec_id >= 0")).cache()
    truth = search.exhaustive_search(v, q, k=1).cache()
    tuned = baselines.tune_forest(v, q, truth, n, grid=((1, 4), (128, 512, 2048), (16, 64), ("kd", "kmeans")))
    best = tuned[0]
    rows = [("forest", f"{best.algorithm}, {best.trees} trees, {best.checks} checks, leaves of {best.leaf}", round(best.precision, 6), round(best.ratio, 6))]
    # the query itself is its best hit: units are asked to open the unit of it, which is where that hit lies
    for method in ("random-pinv", "batch-pinv_norm"):
        for r in sorted(curve_by_units(index_of(v, method, n, 256), q, truth.select("query_id", "vec_id"), n).collect(), key=lambda r: r.opened):
            rows.append((method, f"{r.opened} units", r.recall, r.ratio_mean))
            if r.recall >= best.precision:
                break
    return spark.createDataFrame(rows, "method string, setting string, precision double, ratio double")


def execution_time(spark, sf, n: int = 20_000, d: int = 1024, asked: int = 64):
    """Seconds a query through the library's own plans: exhaustive, two-stage over random units at a fifth of the cost, and sign codes.

    Vectors are generated and stored first, so that every way reads them alike; all queries of a block share a scan.
    """
    import time

    base = f"{tables.shared_dir(spark)}/time-{uuid.uuid4().hex}"
    ft.sphere(spark, n, d, 3).write.parquet(f"{base}/v")
    v = spark.read.parquet(f"{base}/v")
    queries = ft.plant_queries(v.where(F.col("vec_id") % (n // asked) == 0), 0.8).cache()
    placed = assign.assign_random(v, UNIT, n, mode="modulo")
    tables.write_index(represent.sum_representatives(placed, d=d), placed, {}, f"{base}/real")
    reps, members, _ = tables.read_index(spark, f"{base}/real")
    coded = codes.sign_index(members, "sum", d)
    tables.write_index(coded.reps.drop("rep"), coded.members.select("vec_id", "unit_id", "batch_id", "code"), {}, f"{base}/code")
    code_reps, code_members, _ = tables.read_index(spark, f"{base}/code")
    signs, every = search.Index(code_reps, code_members, {"d": d}), codes.encode(queries, d, "qvec", "code")
    share = max(1, n // UNIT // 10)  # a tenth of the units opened: with the probe a fifth of the products

    def two_stage():
        return search.verify(search.score_pairs(reps, queries, "unit_id", "rep", k=share).drop("score"), members, queries, 0.5)

    def by_codes():
        top = search.score_pairs(signs.reps, every, "unit_id", "code", k=share, measure=codes.NEARNESS, qvec="code")
        return search.verify(top, signs.members, every, -0.45 * d, measure=codes.NEARNESS, vec="code", qvec="code")

    ways = (("exhaustive", lambda: search.score_pairs(v, queries, "vec_id", "vec", 0.5)), ("two_stage", two_stage), ("codes_scan", lambda: search.score_pairs(signs.members, every, "vec_id", "code", -0.45 * d, measure=codes.NEARNESS, qvec="code")), ("codes_two_stage", by_codes))
    rows, count = [], queries.count()
    for name, run in ways:
        started = time.perf_counter()
        found = run().count()
        rows.append((name, n, d, (time.perf_counter() - started) / count, found))
    return spark.createDataFrame(rows, "way string, n int, d int, seconds_per_query double, found long")


def baseline_mbk(spark, sf):
    return _compare(document_vectors(spark, sf), 256, ["minibatch"], 0.5)


def baseline_ivf(spark, sf):
    return _compare(document_vectors(spark, sf), 256, ["ivf"], 0.5)


def baseline_lsh(spark, sf):
    v, q = vectors(spark, sf), stated(spark, sf)
    return metrics.precision_recall(baselines.lsh_search(v, q, 0.8), search.exhaustive_search(v, q, alpha0=0.8))


def two_level(spark, sf):
    """Representatives of representatives: how many products a probe of both levels needs against one."""
    index = pinv_index(spark, sf)
    top, grouped = search.build_two_level(index, 5, D)
    queries = stated(spark, sf)
    opened = search.probe(top, queries, 0.1).join(top.select("unit_id", "n_members"), "unit_id")
    cost = opened.groupBy("query_id").agg(F.sum("n_members").alias("second"))
    m, t = index.reps.count(), top.count()
    return queries.select("query_id").join(cost, "query_id", "left").select("query_id", (F.coalesce("second", F.lit(0)) + t).alias("ops"), F.lit(m).alias("one_level"))


# streams -----------------------------------------------------------------------------------------------------------------------


def streaming_sizes(spark, sf):
    """Units of consecutive arrivals, from 10 to 500 members: cost and recall of both representatives."""
    v = vectors(spark, sf).cache()
    n, queries = v.count(), stated(spark, sf, 0.8).cache()
    truth = queries.select("query_id", F.col("query_id").alias("vec_id"))
    out = []
    for size in (10, 20, 50, 100, 500):
        placed = assign.assign_arrival(v.withColumn("ts", F.col("vec_id")), size, 1, ("ts", "vec_id")).select("vec_id", "vec", "unit_id").cache()
        for kind in ("sum", "pinv"):
            index = search.build_index(placed, kind, D)
            tau = theory.threshold("sum", size, D, 0.8, 0.05) if kind == "sum" or size >= D else theory.threshold("pinv", size, D, 0.8, 0.05)
            scores = search.probe(index.reps, queries)
            curve = metrics.quality_cost_curve(scores, index.reps, index.members, truth, queries, n, [tau])
            out.append(_tag(curve.select(r6("ratio_mean").alias("ratio"), r6("recall").alias("recall")), n=size, kind=kind))
    return _union(out)


def stream_units(spark, sf):
    """Events bring vectors as a stream; lanes fill units; all that is available is processed, sealed units are the result."""
    v = vectors(spark, sf)
    base = f"{tables.shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    arrivals.arrivals_of(tables.load_table(spark, sf, "events"), v, v.count()).select(
        "event_id", F.col("ts").cast("timestamp").alias("ts"), "vec_id", "vec"
    ).repartition(4).write.mode("overwrite").parquet(f"{base}/in")
    stream = arrivals.read_arrivals(spark, f"{base}/in", files=2)
    sealed = arrivals.fill_units(stream, 20, lanes=4)
    run = sealed.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    run.awaitTermination()
    out = spark.read.schema(arrivals.SEALED).parquet(f"{base}/out")
    return out.select("unit_id", "lane", "n_members", r6("rep_norm2").alias("rep_norm2"))


def sql_surface(spark, sf):
    """Aggregates and the table function from SQL."""
    index = search.build_index(members(spark, sf), "pinv", D)
    path = f"{tables.shared_dir(spark)}/index-{uuid.uuid4().hex}"
    tables.write_index(index.reps, index.members, index.meta, path)
    udtf.register(spark, path, 0.5)
    stated(spark, sf).createOrReplaceTempView("groupsearch_asked")
    return spark.sql("SELECT q.query_id, s.vec_id, round(s.sim, 6) AS sim FROM groupsearch_asked q, LATERAL group_search(q.qvec, 5) s")


NAMES = """rep_pinv_degenerate rep_ridge rep_online gram_spectrum mp_moments kl_sum kl_pinv cap_simulation cost_curve_cap cost_cap_measured
capacity plans roc_planted roc_sphere roc_families kmeans_pinv kmeans_pinv_norm batch_kmeans batch_kmeans_full imbalance_variants
random_and_clustered unit_sizes low_dimension cost_spread cost_histograms positive_units_protocol batch_assignment minibatch_imbalance
minibatch_comparison large_protocol distractors passages near_copy_map match_by_rank_families
same_conversation vector_normalisation sign_documents pca_variance pca_search other_features high_dimension
baseline_forest forest_or_units execution_time baseline_mbk baseline_ivf baseline_lsh two_level streaming_sizes stream_units sql_surface""".split()


def queries() -> dict:
    return {n: globals()[n] for n in NAMES}
