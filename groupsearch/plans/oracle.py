"""DuckDB SQL for the registered queries: each says in relational terms what its query computes with engine operators."""

from __future__ import annotations

from ..functions import theory
from . import queries as q

D, A, TAU = q.D, q.ALPHA, q.TAU
B = repr((1 - A * A) ** 0.5)

V = "v as (select vec_id, embedding::double[] as x from embeddings)"
U = f"u as (select vec_id, vec_id % (select ceil(count(*) / {q.UNIT}.0)::bigint from embeddings) as unit_id, x from v)"
PARTS = "p as (select unit_id, unnest(x) as val, generate_subscripts(x, 1) as pos from u)"
R = "r as (select unit_id, list(s order by pos) as m, max(n) as n_members from (select unit_id, pos, sum(val) as s, count(*) as n from p group by 1, 2) group by 1)"


def _query(name: str, alpha: float, where: str = "vec_id % 50 = 0") -> str:
    beta = repr((1 - alpha * alpha) ** 0.5)
    mixed = f"list_transform(x, lambda e, i: {alpha} * e + x[{D} + 1 - i] * (case when i % 2 = 1 then {beta} else -{beta} end))"
    return f"{name} as (select vec_id as query_id, {mixed} as y from v where {where})"


Q = _query("q", A)
ALL = _query("q", A, "true")
BASE = f"with {V}, {U}, {PARTS}, {R}, {Q}"
PROBE = "s as (select query_id, unit_id, n_members, list_dot_product(m, y) as score from r cross join q)"
HITS = "h as (select s.query_id, u.vec_id, list_dot_product(u.x, q.y) as sim from s join u on s.unit_id = u.unit_id and s.score > {tau} join q on q.query_id = s.query_id)"
TOP = "t as (select * from (select *, row_number() over (partition by query_id order by score desc, unit_id) as unit_rank from s) where unit_rank <= 7)"
TOPHITS = "h as (select t.query_id, u.vec_id, list_dot_product(u.x, q.y) as sim from t join u using (unit_id) join q on q.query_id = t.query_id)"
TRUTH = "truth as (select query_id, vec_id, list_dot_product(x, y) as sim from v cross join q where list_dot_product(x, y) >= {a})"
LABELLED = f"with {V}, {U}, {PARTS}, {R}, {ALL}, l as (select list_dot_product(r.m, q.y) as score, r.unit_id, r.unit_id = u.unit_id as related from r cross join q join u on u.vec_id = q.query_id)"
COST = f"c as (select q.query_id, (select count(*) from r) as n_units, count(s.unit_id) as n_opened, coalesce(sum(s.n_members), 0)::bigint as n_verified from q left join s on s.query_id = q.query_id and s.score > {TAU} group by 1)"
RATIO = f"{BASE}, {PROBE}, {COST}, o as (select *, n_units + n_verified as ops, (n_units + n_verified) / (select count(*) from v) as ratio from c)"


def flat(source: str, keys: str, vec: str) -> str:
    return f"select {keys}, (generate_subscripts({vec}, 1) - 1)::int as pos, round(unnest({vec}), 6) as value from {source}"


def phi(x: str) -> str:
    """Normal distribution function by its power series; flat beyond eight."""
    series = f"list_sum(list_transform(range(0, 160), lambda k: exp((2 * k + 1) * ln(abs({x})) - k * ln(2) - lgamma(k + 1) - ln(2 * k + 1)) * (case when k % 2 = 0 then 1 else -1 end)))"
    inner = f"0.5 + sign({x}) / sqrt(2 * pi()) * {series}"
    return f"(case when {x} > 5.5 then 1.0 when {x} < -5.5 then 0.0 when abs({x}) < 1e-300 then 0.5 else {inner} end)"


def betainc(x: str, a: str, b: str) -> str:
    """Regularised incomplete beta function by a series of positive terms."""
    terms = f"list_sum(list_transform(range(0, 1500), lambda k: exp(lgamma({a} + {b} + k) - lgamma({a} + {b}) - lgamma({a} + 1 + k) + lgamma({a} + 1) + k * ln({x}))))"
    head = f"exp({a} * ln({x}) + {b} * ln(1 - {x}) - lgamma({a}) - lgamma({b}) + lgamma({a} + {b}) - ln({a}))"
    return f"(case when {x} <= 0 then 0.0 when {x} >= 1 then 1.0 else {head} * {terms} end)"


def grid(name: str, values) -> str:
    return f"{name} as (select unnest([{', '.join(map(repr, values))}]::double[]) as {name})"


#: The table's dimension: that of evenly spread vectors with as large squared products.
DIM = f"""w as (select i, j, avg(x[i] * x[j]) as value from v, (select unnest(range(1, {D} + 1)) as i), (select unnest(range(1, {D} + 1)) as j) group by 1, 2),
dim as (select floor(power(sum(value) filter (i = j), 2) / sum(value * value) + 0.5) as d from w)"""


def _measured(where: str) -> str:
    """kind, alpha0, n and the expected cost in the table's dimension; minimum-norm units as large as it open always."""
    z = theory.phi_inv(q.COST_EPS)
    return f"""
with {V}, {DIM}, {grid("alpha0", q.ROC_ALPHAS)}, n as (select unnest(range(1, 101)) as n), kind as (select unnest(['sum', 'pinv']) as kind),
g as (select kind, alpha0, n, d, kind = 'pinv' and n >= d as all_open from kind, alpha0, n, dim),
m as (select *, case when all_open then 1.0 when kind = 'sum' then n / d else n / (1 - n / d) / d end as v0,
        case when all_open then 1.0 when kind = 'sum' then (n - 1) / d else (1 - alpha0 * alpha0) * n / (1 - n / d) / d end as v1 from g),
t as (select *, alpha0 + sqrt(v1) * {z!r} as tau from m),
c as (select *, 1.0 / n + case when all_open then 1.0 else {phi("(-tau / sqrt(v0))")} end as cost from t)
{where}"""


def _model(where: str) -> str:
    """kind, alpha, n with the moments of both hypotheses, in d dimensions."""
    z = theory.phi_inv(q.COST_EPS)
    return f"""
with {grid("alpha0", q.ROC_ALPHAS)}, n as (select unnest(range(1, 101)) as n), kind as (select unnest(['sum', 'pinv']) as kind),
g as (select kind, alpha0, n, {q.COST_D}.0 as d from kind, alpha0, n),
m as (select *, case when kind = 'sum' then n / d else n / (1 - n / d) / d end as v0,
        case when kind = 'sum' then (n - 1) / d else (1 - alpha0 * alpha0) * n / (1 - n / d) / d end as v1 from g),
t as (select *, alpha0 + sqrt(v1) * {z!r} as tau from m),
c as (select *, 1.0 / n + {phi("(-tau / sqrt(v0))")} as cost from t)
{where}"""


def _kmeans(normalize: bool, rounds: int = 3) -> str:
    """Rounds of assignment and summing, written one after the other; ties go to the smaller unit."""
    ctes = [V, f"c0 as (select vec_id as unit_id, x as m from v order by vec_id limit {q.KMEANS_UNITS})"]
    for i in range(rounds):
        ctes.append(f"a{i} as (select vec_id, unit_id, x from (select v.vec_id, c{i}.unit_id, v.x, row_number() over (partition by v.vec_id order by list_dot_product(v.x, c{i}.m) desc, c{i}.unit_id) as k from v cross join c{i}) where k = 1)")
        if i + 1 < rounds:
            ctes.append(f"p{i} as (select unit_id, unnest(x) as val, generate_subscripts(x, 1) as pos from a{i})")
            ctes.append(f"w{i} as (select unit_id, list(s order by pos) as m from (select unit_id, pos, sum(val) as s from p{i} group by 1, 2) group by 1)")
            m = "list_transform(m, lambda e: e / sqrt(list_dot_product(m, m)))" if normalize else "m"
            ctes.append(f"c{i + 1} as (select unit_id, {m} as m from w{i})")
    # ids of units are the ranks of the first vectors
    ctes.append(f"ids as (select unit_id, row_number() over (order by unit_id) - 1 as rank from c0)")
    ctes.append(f"own as (select vec_id, rank as unit_id from a{rounds - 1} join ids using (unit_id))")
    return "with " + ", ".join(ctes)


def _delta(source: str, units: str) -> str:
    return f"(select {units} * sum(c * c) / (sum(c) * sum(c)) from (select count(*)::double as c from {source} group by unit_id))"


def _pinv(units: str) -> str:
    """Minimum-norm representatives by growing an orthonormal basis, one member a step."""
    coef = "list_transform(basis, lambda b: list_dot_product(b, x))"
    rest = f"case when len(basis) = 0 then x else list_transform(range(1, {D} + 1), lambda i: x[i] - list_dot_product({coef}, list_transform(basis, lambda b: b[i]))) end"
    return f"""
with recursive {V}, {units},
o as (select *, row_number() over (partition by unit_id order by vec_id) as k from u),
g(unit_id, k, m, basis) as (
  select distinct unit_id, 0::bigint, list_transform(range({D}), lambda i: 0.0::double), []::double[][] from u
  union all
  select unit_id, k, list_transform(m, lambda e, i: e + (1 - list_dot_product(m, x)) / list_dot_product(z, z) * z[i]),
    list_append(basis, list_transform(z, lambda e: e / sqrt(list_dot_product(z, z))))
  from (select o.unit_id, o.k, g.m, g.basis, o.x, {rest} as z from g join o on o.unit_id = g.unit_id and o.k = g.k + 1)),
f as (select unit_id, k as n_members, m from g qualify row_number() over (partition by unit_id order by k desc) = 1)"""


WORDS = [f"list_sum(list_transform(range(0, {min(32, D - 32 * w)}), lambda b: case when x[{32 * w} + b + 1] >= 0 then (1::bigint << b::int) else 0 end))::bigint" for w in range(-(-D // 32))]
CODED = f"list_value({', '.join(WORDS)})"


def _distance(a: str, b: str) -> str:
    return "(" + " + ".join(f"bit_count(xor({a}[{w + 1}], {b}[{w + 1}]))" for w in range(len(WORDS))) + ")"


SIGNED = f"with {V}, {U}, {PARTS}, {R}, {Q}, z as (select unit_id, list_transform(m, lambda e: case when e >= 0 then 1.0 else -1.0 end) as m, m as x from r), y as (select vec_id, unit_id, list_transform(x, lambda e: case when e >= 0 then 1.0 else -1.0 end) as s, x from u)"


def sql() -> dict[str, str]:
    h = HITS.format(tau=TAU)
    pair = "with " + V + ", u as (select vec_id, vec_id // 2 as unit_id, x from v)"
    cube = f"{RATIO}, b as (select label, (o.query_id % 100 >= 50)::int as half, ratio from o join embeddings e on e.vec_id = o.query_id)"
    label_truth = "lt as (select a.vec_id as query_id, b.vec_id from embeddings a join embeddings b using (label) where a.vec_id % 50 = 0 and a.vec_id <> b.vec_id)"
    plain = _query("q", 1.0)
    ranked = f"with {V}, {U}, {PARTS}, {R}, {plain}, {PROBE}, {TOP}, {TOPHITS}, k as (select *, row_number() over (partition by query_id order by sim desc, vec_id) as hit_rank from h where query_id <> vec_id), {label_truth}"
    two = f"{BASE}, {PROBE}, {h.replace('h as', 'ha as')}, {TOP}, {TOPHITS}"
    matches = f"{BASE}, {PROBE}, {TRUTH.format(a=0.3)}, k as (select *, row_number() over (partition by query_id order by score desc, unit_id)::int as unit_rank from s), mt as (select k.query_id, k.unit_rank, count(truth.vec_id) as n_match from k left join u on u.unit_id = k.unit_id left join truth on truth.query_id = k.query_id and truth.vec_id = u.vec_id group by 1, 2)"
    d_grid = f"d as (select unnest({q.CDF_D}) as d), {grid('s', q.CDF_S)}"
    theory_roc = f"""
with {V}, {DIM}, {grid("alpha", q.ROC_ALPHAS)}, {grid("tau", q.ROC_TAUS)}, kind as (select unnest(['sum', 'pinv']) as kind), n as (select {q.UNIT}.0 as n),
m as (select kind, alpha, tau, case when kind = 'sum' then n / d else n / (1 - n / d) / d end as v0, case when kind = 'sum' then (n - 1) / d else (1 - alpha * alpha) * n / (1 - n / d) / d end as v1 from kind, alpha, tau, n, dim)
select kind, alpha, tau, round({phi("(-tau / sqrt(v0))")}, 6) as pfp, round({phi("((alpha - tau) / sqrt(v1))")}, 6) as tpr from m"""
    tail = "(1 - sign(eta) * ({}))"
    i1, i3 = betainc("(eta * eta)", "0.5", "((d - 1) / 2.0)"), betainc("(eta * eta)", "1.5", "((d - 1) / 2.0)")
    hashed = "select doc_id, ('0x' || substr(md5(w), 1, 8))::bigint as h from (select doc_id, unnest(regexp_extract_all(lower(coalesce(text, '')), '[\\p{L}\\p{N}]+')) as w from documents)"
    rows_of = {
        "rep_sum": f"with {V}, {U}, {PARTS}, {R} " + flat("r", "unit_id, n_members", "m"),
        "rep_sum_norm": f"with {V}, {U}, {PARTS}, {R}, w as (select unit_id, n_members, list_transform(m, lambda e: e / sqrt(list_dot_product(m, m))) as m from r) " + flat("w", "unit_id, n_members", "m"),
        "rep_pinv_pairs": pair
        + ", w as (select a.unit_id, 2::bigint as n_members, list_transform(a.x, lambda e, i: (e + b.x[i]) / (1 + list_dot_product(a.x, b.x))) as m, list_dot_product(a.x, a.x) as aa, list_dot_product(b.x, b.x) as bb, list_dot_product(a.x, b.x) as ab, a.x as ax, b.x as bx from u a join u b on a.unit_id = b.unit_id and a.vec_id < b.vec_id)"
        + ", e as (select unit_id, n_members, list_transform(ax, lambda e, i: (e * (bb - ab) + bx[i] * (aa - ab)) / (aa * bb - ab * ab)) as m from w union all select unit_id, 1, list_transform(x, lambda e: e / list_dot_product(x, x)) from u where unit_id in (select unit_id from u group by 1 having count(*) = 1)) "
        + flat("e", "unit_id, n_members", "m"),
        "rep_pinv": _pinv(U) + " " + flat("f", "unit_id, n_members", "m"),
        "rep_norms": _pinv(U)
        + f", s as (select unit_id, count(*) as n, round(sum(list_dot_product(x, x)), 6) as trace from u group by 1), t as (select unit_id, list(w order by pos) as m from (select unit_id, pos, sum(val) as w from (select unit_id, unnest(x) as val, generate_subscripts(x, 1) as pos from u) group by 1, 2) group by 1) select s.unit_id, s.n, round(list_dot_product(t.m, t.m), 6) as norm2_sum, round(list_dot_product(f.m, f.m), 6) as norm2_pinv, s.trace from s join t using (unit_id) join f using (unit_id)",
        "rep_append": _pinv(U) + " select unit_id, n_members, round(list_dot_product(m, m), 6) as rep_norm2 from f",
        "rep_online": _pinv(U) + " select unit_id, n_members, round(list_dot_product(m, m), 6) as rep_norm2 from f",
        "unit_thresholds_pinv": _pinv(U) + f" select unit_id, round({A} + sqrt(list_dot_product(m, m)) * (sqrt(1 - {A} * {A}) / sqrt({D})) * {theory.phi_inv(0.05)!r}, 6) as tau from f",
        "sql_surface": _pinv(U) + f", {Q}, h as (select q.query_id, u.vec_id, list_dot_product(u.x, q.y) as sim from f join q on list_dot_product(f.m, q.y) > {TAU} join u on u.unit_id = f.unit_id) select query_id, vec_id, round(sim, 6) as sim from h qualify row_number() over (partition by query_id order by sim desc, vec_id) <= 5",
        "power_norm": f"with {V}, w as (select vec_id, list_transform(x, lambda e: sign(e) * sqrt(abs(e))) as x from v), n as (select vec_id, list_transform(x, lambda e: e / sqrt(list_dot_product(x, x))) as x from w) " + flat("n", "vec_id", "x"),
        "normalize_vectors": f"with {V}, n as (select vec_id, list_transform(x, lambda e: e / sqrt(list_dot_product(x, x))) as x from v) " + flat("n", "vec_id", "x"),
        "pinv_constraint": _pinv(U) + " select u.unit_id, count(*) as n, sum((abs(list_dot_product(u.x, f.m) - 1) < 1e-6)::int)::bigint as satisfied from u join f using (unit_id) group by 1",
        "h0_variance": f"with {V}, {U}, {PARTS}, {R} select unit_id, round(list_dot_product(m, m) / {D}, 6) as variance from r",
        "score_cdf_grid": f"with {d_grid} select d, s, round(case when s <= -1 then 0.0 when s >= 1 then 1.0 else 0.5 * (1 + sign(s) * {betainc('(s * s)', '0.5', '((d - 1) / 2.0)')}) end, 6) as cdf from d, s",
        "score_pdf_grid": f"with {d_grid} select d, s, round(case when abs(s) >= 1 then 0.0 else exp((d - 3) / 2.0 * ln(1 - s * s) - lgamma(0.5) - lgamma((d - 1) / 2.0) + lgamma(d / 2.0)) end, 6) as pdf from d, s",
        "roc_theory": theory_roc,
        "thresholds": _model("select kind, alpha0, n::int as n, round(tau, 6) as tau from c"),
        "cost_curve": _measured("select kind, alpha0, n::int as n, round(cost, 6) as cost_ratio from c"),
        "cost_optimum": _measured("select kind, alpha0, n::int as n, round(cost, 6) as cost_ratio from c qualify row_number() over (partition by kind, alpha0 order by round(cost, 6), n) = 1"),
        "unit_thresholds": f"with {V}, {U}, {PARTS}, {R} select unit_id, round({A} + sqrt((n_members - 1) / {D}.0) * {theory.phi_inv(0.05)!r}, 6) as tau from r",
        "cap_moments": f"with {V}, d as (select unnest({q.CAP_DIMS}) as d), {grid('eta', q.CAP_ETAS)}, s as (select d, x[1:d] as y from v, d), c as (select d, unnest(list_transform(y, lambda e: e / sqrt(list_dot_product(y, y)))) as c from s where list_dot_product(y, y) > 0), f as (select c.d, eta, count(*) as n, round(avg(c), 6) as mu1, round(avg(c * c), 6) as mu2 from c join eta on c > eta group by 1, 2) select d.d, eta.eta, coalesce(n, 0) as n, mu1, mu2, round(2 * exp((d - 1) / 2.0 * ln(1 - eta * eta) - lgamma(0.5) - lgamma((d - 1) / 2.0) + lgamma(d / 2.0)) / ((d - 1) * {tail.format(i1)}), 6) as mu1_model, round({tail.format(i3)} / {tail.format(i1)} / d, 6) as mu2_model from d cross join eta left join f using (d, eta)",
        "assign_random": f"with {V}, {U} select vec_id, unit_id from u",
        "assign_arrival": "select event_id, (row_number() over (partition by event_id % 8 order by ts, event_id) - 1) // 50 * 8 + event_id % 8 as unit_id from events",
        "assign_label": "select vec_id, dense_rank() over (order by label) - 1 as unit_id from embeddings",
        "kmeans_sum": _kmeans(False) + " select vec_id, unit_id from own",
        "kmeans_sum_norm": _kmeans(True) + " select vec_id, unit_id from own",
        "index_build": f"with {V}, {U}, {PARTS}, {R} select r.unit_id, r.n_members, round(list_dot_product(any_value(r.m), any_value(r.m)), 6) as rep_norm2, min(u.vec_id) as first_vec, max(u.vec_id) as last_vec from r join u using (unit_id) group by 1, 2",
        "probe_scores": f"{BASE}, {PROBE} select query_id, unit_id, round(score, 6) as score from s",
        "probe_native": f"{BASE}, {PROBE} select query_id, unit_id, round(score, 6) as score from s where score > {TAU}",
        "probe_threshold": f"{BASE}, {PROBE} select query_id, unit_id, round(score, 6) as score from s where score > {TAU}",
        "probe_unit_tau": f"{BASE}, {PROBE} select query_id, unit_id, round(score, 6) as score from s where score > {A} + sqrt((n_members - 1) / {D}.0) * {theory.phi_inv(0.05)!r}",
        "probe_top_units": f"{BASE}, {PROBE}, {TOP} select query_id, unit_id, unit_rank::int as unit_rank, round(score, 6) as score from t",
        "search_threshold": f"{BASE}, {PROBE}, {h} select query_id, vec_id, round(sim, 6) as sim, row_number() over (partition by query_id order by sim desc, vec_id)::int as hit_rank from h",
        "search_range": f"{BASE}, {PROBE}, {h} select query_id, vec_id, round(sim, 6) as sim from h where sim >= 0.3",
        "search_topk": f"{BASE}, {PROBE}, {TOP}, {TOPHITS} select query_id, vec_id, round(sim, 6) as sim, k::int as hit_rank from (select *, row_number() over (partition by query_id order by sim desc, vec_id) as k from h) where k <= 4",
        "membership": f"{BASE}, {PROBE} select q.query_id, count(s.unit_id) as n_positive, count(s.unit_id) > 0 as member from q left join s on s.query_id = q.query_id and s.score > 0.7 group by 1",
        "similarity_join": f"with {V}, {U}, {PARTS}, {R} select distinct least(a.vec_id, u.vec_id) as left_id, greatest(a.vec_id, u.vec_id) as right_id, round(list_dot_product(a.x, u.x), 6) as sim from v a join r on list_dot_product(r.m, a.x) > 0.3 join u on u.unit_id = r.unit_id where a.vec_id <> u.vec_id and list_dot_product(a.x, u.x) >= 0.35",
        "filtered_search": f"{BASE}, {PROBE}, {h} select query_id, vec_id, round(sim, 6) as sim from h join embeddings using (vec_id) where label = 3",
        "exact_range": f"with {V}, {Q}, {TRUTH.format(a=0.3)} select query_id, vec_id, round(sim, 6) as sim from truth",
        "exact_topk": f"with {V}, {Q} select query_id, vec_id, round(sim, 6) as sim, k::int as hit_rank from (select *, row_number() over (partition by query_id order by sim desc, vec_id) as k from (select query_id, vec_id, list_dot_product(x, y) as sim from v cross join q)) where k <= 10",
        "baseline_filter_refine": f"with {V}, {Q}, {TRUTH.format(a=0.3)} select query_id, vec_id, round(sim, 6) as sim from truth",
        "no_miss_copy": _pinv(U) + " select count(*) as queries, sum((list_dot_product(u.x, f.m) <= 0.999)::int)::bigint as misses from u join f using (unit_id)",
        "second_moment": f"with {V}, i as (select unnest(range(0, {D})) as i), j as (select unnest(range(0, {D})) as j) select i::int as i, j::int as j, round(avg(x[i + 1] * x[j + 1]), 6) as value from v, i, j where j >= i group by 1, 2",
        "sign_codes": f"with {V}, c as (select vec_id, {CODED} as code from v) select vec_id, (generate_subscripts(code, 1) - 1)::int as word, unnest(code) as code from c",
        "hamming_topk": f"with {V}, {Q}, c as (select vec_id, {CODED} as code from v), qc as (select query_id, {CODED.replace('x[', 'y[')} as qcode from q) select query_id, vec_id, distance::int as distance, hit_rank::int as hit_rank from (select *, row_number() over (partition by query_id order by distance, vec_id) as hit_rank from (select query_id, vec_id, {_distance('code', 'qcode')} as distance from c cross join qc)) where hit_rank <= 10",
        "search_sign_asym": f"{SIGNED} select query_id, y.vec_id, round(list_dot_product(y.s, q.y) / sqrt({D}), 6) as sim from z join q on list_dot_product(z.m, q.y) / sqrt({D}) > {q.SIGN_TAU} join y using (unit_id)",
        "search_sign_sym": f"{SIGNED}, qs as (select query_id, list_transform(y, lambda e: case when e >= 0 then 1.0 else -1.0 end) as s from q) select query_id, y.vec_id, round(list_dot_product(y.s, qs.s) / {D}, 6) as sim from z join qs on list_dot_product(z.m, qs.s) / {D} > {q.SIGN_TAU} join y using (unit_id)",
        "query_cost": f"{RATIO} select query_id, n_units, n_opened, n_verified, ops from o",
        "complexity_ratio": f"{RATIO} select query_id, ops, round(ratio, 6) as ratio, round(1 / ratio, 6) as speedup, (select count(*) from v) - ops as saved from o",
        "cost_histogram": f"{RATIO} select case when ratio < 0 then 0 when ratio >= 1 then 21 else floor(ratio * 20) + 1 end::bigint as bin, count(*) as cnt from o group by 1",
        "cost_h0": f"with {V}, u as (select vec_id, vec_id // 10 as unit_id, x from v where vec_id % 10 <> 0), {PARTS}, {R}, q as (select vec_id as query_id, x as y from v where vec_id % 10 = 0), {PROBE}, {COST}, o as (select (n_units + n_verified) / (select count(*) from u) as ratio from c) select count(*) as queries, round(avg(ratio), 6) as ratio_mean, round(stddev_pop(ratio), 6) as ratio_std from o",
        "error_rates": f"{LABELLED}, {grid('tau', q.RATE_TAUS)} select tau, round(avg(case when not related then (score > tau)::int end), 6) as pfp, round(avg(case when related then (score <= tau)::int end), 6) as pfn from l, tau group by 1",
        "roc_empirical": f"{LABELLED}, b as (select -1.5 + unnest(range(0, 41)) * 0.1 as tau, unnest(range(0, 41)) as b) select round(tau, 6) as tau, round(avg(case when not related then (ceil((score + 1.5) / 0.1) > b)::int end), 6) as pfp, round(avg(case when related then (ceil((score + 1.5) / 0.1) > b)::int end), 6) as tpr from l, b group by tau",
        "kl_empirical": f"{LABELLED}, m as (select avg(score) filter (related) as m1, var_pop(score) filter (related) as v1, avg(score) filter (not related) as m0, var_pop(score) filter (not related) as v0 from l) select round(m1, 6) as mean1, round(v1, 6) as var1, round(m0, 6) as mean0, round(v0, 6) as var0, round((v1 / v0 + (m1 - m0) * (m1 - m0) / v0 - 1 - ln(v1 / v0)) / 2, 6) as kl from m",
        "score_summary": f"{LABELLED} select related, count(*) as n, round(avg(score), 6) as mean, round(stddev_samp(score), 6) as sd, round(min(score), 6) as least, round(max(score), 6) as most, round(quantile_cont(score, 0.5), 6) as median, count(distinct unit_id) as units, max_by(unit_id, score) as best_unit from l group by 1",
        "recall_at_alpha": f"{BASE}, {PROBE}, {h}, {TRUTH.format(a=0.3)}, n as (select (select count(*) from h where sim >= 0.3) as n_hits, (select count(*) from truth) as n_truth, (select count(*) from h join truth using (query_id, vec_id) where h.sim >= 0.3) as n_correct) select n_hits, n_truth, n_correct, round(n_correct / n_hits, 6) as precision, round(n_correct / n_truth, 6) as recall from n",
        "map_score": f"{ranked}, g as (select k.query_id, k.hit_rank, row_number() over (partition by k.query_id order by k.hit_rank) as n from k semi join lt using (query_id, vec_id)), a as (select c.query_id, coalesce(sum(g.n / g.hit_rank), 0) / any_value(c.relevant) as ap from (select query_id, count(*) as relevant from lt group by 1) c left join g using (query_id) group by 1) select round(avg(ap), 6) as map, count(*) as queries from a",
        "recall4": f"{ranked} select round(avg(n), 6) as correct, count(*) as queries from (select q.query_id, count(lt.vec_id) as n from q left join k on k.query_id = q.query_id and k.hit_rank <= 4 left join lt on lt.query_id = k.query_id and lt.vec_id = k.vec_id group by 1)",
        "match_by_rank": f"{matches} select unit_rank, round(avg((n_match > 0)::int), 6) as p_match from mt group by 1",
        "matches_given_pos": f"{matches} select unit_rank, round(avg(n_match), 6) as avg_matches from mt where n_match > 0 group by 1",
        "imbalance": _kmeans(True) + f" select count(*) as n, {q.KMEANS_UNITS}::bigint as units, round({_delta('own', str(q.KMEANS_UNITS))}, 6) as delta, round(({_delta('own', str(q.KMEANS_UNITS))} - 1) * count(*) * count(*) / {q.KMEANS_UNITS ** 2}, 6) as var_size from own",
        "imbalance_pivot": f"select 'embeddings' as dataset, ({_kmeans(False)} select round({_delta('own', str(q.KMEANS_UNITS))}, 6)) as plain, ({_kmeans(True)} select round({_delta('own', str(q.KMEANS_UNITS))}, 6)) as norm, (with {V}, {U} select round({_delta('u', '(select count(distinct unit_id) from u)')}, 6)) as random",
        "quality_cost_curve": f"{BASE}, {PROBE}, {TRUTH.format(a=0.3)}, {grid('tau', [0.11, 0.31, 0.51, 0.71, 0.91])}, f as (select truth.query_id, s.score from truth join u using (vec_id) join s on s.query_id = truth.query_id and s.unit_id = u.unit_id) select tau, round(((select sum(n_members) filter (score > tau) from s) / (select count(*) from q) + (select count(*) from r)) / (select count(*) from v), 6) as ratio_mean, round((select avg((score > tau)::int) from f), 6) as recall from tau",
        "truth_filter": f"with {V}, {Q}, {TRUTH.format(a=0.3)} select query_id, count(*) as matches from truth where query_id <> vec_id group by 1 having count(*) between 1 and 1000",
        "build_cost": f"with n as (select count(*) as n from embeddings) select 'random' as method, 0::bigint as ops from n union all select 'full', 12 * n * ceil(n / {q.UNIT}.0)::bigint from n union all select 'batch_100', 12 * n * 10 from n",
        "index_overhead": f"with {V}, {U}, {PARTS}, {R} select (select sum(len(m))::bigint from r) as rep_numbers, (select sum(len(x))::bigint from u) as member_numbers, round((select sum(len(m)) from r) / (select sum(len(x)) from u), 6) as overhead",
        "score_gaps": f"{BASE}, {PROBE} select query_id, row_number() over w::int as unit_rank, round(lag(score) over w - score, 6) as gap, ntile(4) over w::int as quarter from s window w as (partition by query_id order by score desc, unit_id)",
        "metrics_rollup": f"{cube} select label, half, round(avg(ratio), 6) as avg_ratio, count(*) as cnt from b group by rollup (label, half)",
        "metrics_cube": f"{cube} select label, half, round(avg(ratio), 6) as avg_ratio, count(*) as cnt from b group by cube (label, half)",
        "scan_embeddings": "select label, count(*) as n, min(vec_id) as first_id from embeddings group by 1",
        "reject_invalid": "select vec_id, case vec_id % 20 when 1 then 'null' when 2 then 'zero' when 3 then 'length' when 4 then 'not_finite' end as reason from embeddings where vec_id % 20 between 1 and 4",
        "queries_without_hit": f"with {V}, {U}, {PARTS}, {R}, {_query('q', 0.6)}, {PROBE}, {HITS.format(tau=0.9)} select query_id from q where query_id not in (select query_id from h where sim >= 0.5)",
        "asof_index_version": "select e.event_id, v.event_id as version from events e asof left join (select event_id, ts from events where event_id % 1000 = 0) v on e.ts >= v.ts",
        "hits_intersect": f"{two} select query_id, vec_id from ha where sim >= 0.25 intersect select query_id, vec_id from h where sim >= 0.25",
        "hits_except": f"{two} select query_id, vec_id from ha where sim >= 0.25 except all select query_id, vec_id from h where sim >= 0.25",
        "dot_self": f"with {V} select vec_id, round(list_dot_product(x, x), 6) as norm2, round(sqrt(list_dot_product(x, x)), 6) as norm from v",
        "cosine_pairs": f"with {V} select a.vec_id, round(list_dot_product(a.x, b.x) / sqrt(list_dot_product(a.x, a.x) * list_dot_product(b.x, b.x)), 6) as cosine from v a join v b on b.vec_id = a.vec_id + 1",
        "sql_dot": f"with {V} select a.vec_id, round(list_dot_product(a.x, b.x), 6) as product, round(sqrt(list_dot_product(a.x, a.x)), 6) as norm from v a join v b on b.vec_id = a.vec_id + 1",
        "hash_features": f"select doc_id, h % 256 as pos, sum(case when h // 256 % 2 = 0 then 1 else -1 end)::bigint as weight from ({hashed}) group by 1, 2",
        "user_profiles": "select user_id, (dense_rank() over (order by event_type) - 1) * 24 + h as slot, n from (select user_id, event_type, hour(ts) as h, count(*) as n from events group by all)",
        "props_k": "select json_extract_string(props, '$.k')::int as k, count(*) as n, round(sum(value), 6) as total from events group by 1",
        "tumbling_arrivals": "select epoch_us(time_bucket(interval '1 hour', ts, timestamp '1970-01-01')) as start_us, count(*) as arrivals from events group by 1",
        "sliding_arrivals": "select epoch_us(time_bucket(interval '1 hour', ts, timestamp '1970-01-01')) - o * 3600000000 as start_us, count(*) as arrivals from events, (select unnest([0, 1]) as o) group by 1",
        "session_arrivals": "select user_id, epoch_us(min(ts)) as start_us, count(*) as arrivals from (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as g from (select user_id, ts, coalesce((ts - lag(ts) over (partition by user_id order by ts) >= interval '6 hours')::int, 1) as new from events)) group by user_id, g",
        "roc_documents": f"""
with w as (select doc_id, h % 256 as pos, sum(case when h // 256 % 2 = 0 then 1 else -1 end)::double as weight from ({hashed}) group by 1, 2),
f as (select doc_id as vec_id, pos, weight / sqrt(sum(weight * weight) over (partition by doc_id)) as x, doc_id % 100 as unit_id from w qualify sum(weight * weight) over (partition by doc_id) > 0),
r as (select unit_id, pos, sum(x) as m from f group by 1, 2), q as (select vec_id as query_id, pos, x as y from f where vec_id % 50 = 0),
ids as (select distinct query_id from q), units as (select distinct unit_id from f),
sc as (select query_id, unit_id, sum(m * y) as score from r join q using (pos) group by 1, 2),
truth as (select query_id, vec_id, any_value(unit_id) as unit_id from f join q using (pos) where query_id <> vec_id group by 1, 2 having sum(x * y) >= 0.9),
l as (select coalesce(score, 0) as score, (query_id, unit_id) in (select (query_id, unit_id) from truth) as related from ids cross join units left join sc using (query_id, unit_id)),
{grid('tau', [2.05, 4.05, 6.05, 8.05])}
select tau, round(avg(case when not related then (score > tau)::int end), 6) as pfp, round(avg(case when related then (score > tau)::int end), 6) as tpr from l, tau group by 1""",
    }
    return rows_of
