"""Two-stage search: probe the representatives, open positive units, compare with their members, rank."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from ..functions import kernels, theory
from ..functions.kernels import Best
from ..functions.vectors import dot
from ..sources import tables
from ..sources.tables import BROADCAST_BYTES, BROADCAST_ROWS
from .represent import normalize_representatives, representatives

#: Bytes of queries that one scan of the representatives answers at once, rows met at a time, and products of a block of scores.
#: And ids of queries that travel with a member of a unit they open.
BLOCK_BYTES, SLICE, TILE, LIST = 64 << 20, 1024, 1 << 22, 256


@dataclass
class Index:
    """Representatives (unit_id, rep, n_members, rep_norm2), members (vec_id, vec, unit_id) and what is known of them."""

    reps: DataFrame
    members: DataFrame
    meta: dict = field(default_factory=dict)


def build_index(members: DataFrame, rep: str = "pinv", d: int = 64, normalize: bool = False, **meta) -> Index:
    reps = representatives(members, rep, d)
    return Index(normalize_representatives(reps) if normalize else reps, members, {"rep": rep, "d": d, "normalize": normalize, **meta})


@dataclass
class Measure:
    """How blocks of queries and rows are compared. kind: of the components."""

    blocks: Callable[[np.ndarray, np.ndarray], np.ndarray]
    kind: type = float


PRODUCT = Measure(lambda q, x: q @ x.T)


def query_blocks(queries: DataFrame, qvec: str = "qvec", kind: type = float) -> Iterator[tuple[Column | None, Broadcast]]:
    """(condition that picks the block's queries, broadcast (ids in order, matrix)) of blocks of about BLOCK_BYTES.

    The driver holds one block at a time; a block that turns out larger than BROADCAST_BYTES raises.
    """
    asked = queries.select("query_id", qvec)
    size = asked.agg(F.count("*").alias("n"), F.coalesce(F.max(F.size(qvec)), F.lit(0)).alias("d")).first()
    blocks = max(1, -(-size.n * max(size.d, 1) * 8 // BLOCK_BYTES))
    for block in range(blocks):
        mine = F.pmod(F.xxhash64("query_id"), F.lit(blocks)) == block if blocks > 1 else None
        got = (asked if mine is None else asked.where(mine)).orderBy("query_id").toArrow()
        q = kernels.matrix(got.column(qvec), kind)
        if q.nbytes > BROADCAST_BYTES:
            raise ValueError("a block of queries is too large to broadcast; lower BLOCK_BYTES")
        yield mine, queries.sparkSession.sparkContext.broadcast((got.column("query_id").to_numpy(), q))


def score_pairs(
    rows: DataFrame, queries: DataFrame, id_col: str, vec: str, tau: float | str | None = None, k: int | None = None, measure: Measure = PRODUCT, qvec: str = "qvec"
) -> DataFrame:
    """query_id, id, score of the rows that score above tau against a query, or of each task's k best of a query.

    Queries are broadcast in blocks, each in one scan of the rows; scores are dense blocks of at most TILE in Arrow tasks, and only
    pairs that pass leave them: with k, one list of k a query and task. tau may be a number or the name of a column of rows.
    """
    kind = dict(rows.dtypes)[id_col]
    tau_col = tau if isinstance(tau, str) else None
    columns = [id_col, vec] + ([tau_col] if tau_col else [])
    out = None
    for _, shared in query_blocks(queries, qvec, measure.kind):

        def run(batches, shared=shared):
            q_ids, q = shared.value
            best = Best(len(q_ids), k) if k is not None else None
            for b in batches:
                if not len(q_ids):
                    continue
                for i in range(0, b.num_rows, SLICE):
                    part = b.slice(i, SLICE)
                    x, ids = kernels.matrix(part.column(1), measure.kind), part.column(0).to_numpy(zero_copy_only=False)
                    least = part.column(2).to_numpy(zero_copy_only=False)[None, :] if tau_col else tau
                    step = max(1, TILE // len(ids))
                    for j in range(0, len(q), step):
                        s = measure.blocks(q[j : j + step], x)
                        if best:
                            best.add(j, s, ids)
                            continue
                        a, c = np.nonzero(s > least) if tau is not None else (y.reshape(-1) for y in np.indices(s.shape))
                        yield pa.RecordBatch.from_arrays([pa.array(q_ids[j + a], pa.int64()), pa.array(ids[c], part.column(0).type), pa.array(s[a, c], pa.float64())], names)
            if best:
                a, c = np.nonzero(np.isfinite(best.score))
                yield pa.RecordBatch.from_arrays([pa.array(q_ids[a], pa.int64()), pa.array(best.ids[a, c]).cast(id_type), pa.array(best.score[a, c])], names)

        names, id_type = ["query_id", id_col, "score"], to_arrow_type(rows.schema[id_col].dataType)
        part = rows.select(*columns).mapInArrow(run, f"query_id bigint, {id_col} {kind}, score double")
        out = part if out is None else out.unionByName(part)
    return out


def probe(reps: DataFrame, queries: DataFrame, tau: float | str | None = None) -> DataFrame:
    """query_id, unit_id, score of every unit, or of those above tau."""
    return score_pairs(reps, queries, "unit_id", "rep", tau)


def probe_native(reps: DataFrame, queries: DataFrame, tau: float | None = None) -> DataFrame:
    """The same as a theta join in the JVM, for SQL users and as a check on the dense one. Queries are broadcast: at most BROADCAST_ROWS."""
    score = dot("rep", "qvec")
    joined = reps.select("unit_id", "rep").join(bounded_broadcast(queries.select("query_id", "qvec")), score > tau if tau is not None else F.lit(True))
    return joined.select("query_id", "unit_id", score.alias("score"))


def rank_units(scores: DataFrame, k: int | None = None) -> DataFrame:
    """scores with unit_rank by falling score, ties to the smaller unit; the k best only, cut before the shuffle."""
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "unit_id"))
    out = scores.withColumn("unit_rank", rank)
    return out.where(F.col("unit_rank") <= k) if k is not None else out


def select_units(reps: DataFrame, queries: DataFrame, tau: float | str | None = None, top_units: int | None = None) -> DataFrame:
    """Positive units: above a threshold (strictly), above each unit's own (the name of a column of reps), or a fixed number."""
    if top_units is not None:
        return rank_units(score_pairs(reps, queries, "unit_id", "rep", k=top_units), top_units)
    return probe(reps, queries, tau)


def rank_stored(reps: DataFrame, queries: DataFrame, k: int, qvec: str = "qvec") -> tuple[DataFrame, str]:
    """(query_id, unit_id, score, unit_rank of each query's k best units, its folder), for many units or a large k.

    Queries are dealt to the tasks and representatives read from the shared folder, so a query's list is whole in one task: nothing
    is shuffled, and a task holds the lists of a few queries.
    """
    spark = reps.sparkSession
    _, path = tables.save(reps.select("unit_id", "rep"), "reps")
    some = max(1, min(SLICE // 2, TILE // 4 // max(k, 1)))

    @tables.tidy
    def run(batches):
        for whole in batches:
            for i in range(0, whole.num_rows, some):
                b = whole.slice(i, some)
                q, ids, best = kernels.matrix(b.column(1)), b.column(0).to_numpy(), Best(b.num_rows, k)
                for block in tables.stored_blocks(path, 2 * SLICE):
                    best.add(0, q @ kernels.matrix(block.column("rep")).T, block.column("unit_id").to_numpy())
                a, c = np.nonzero(np.isfinite(best.score))
                yield pa.RecordBatch.from_arrays([pa.array(ids[a]), pa.array(best.ids[a, c]), pa.array(best.score[a, c]), pa.array((c + 1).astype(np.int32))], ["query_id", "unit_id", "score", "unit_rank"])

    dealt = queries.select("query_id", qvec).repartition(3 * spark.sparkContext.defaultParallelism)
    out = tables.save(dealt.mapInArrow(run, "query_id bigint, unit_id bigint, score double, unit_rank int"), "ranked")
    tables.drop(spark, path)
    return out


def opened_scan(index: Index, queries: DataFrame, opened: list[int], work, schema: str) -> DataFrame:
    """Rows that ``work(batch, q, verified, scan)`` gives for blocks of queries (query_id, qvec, more columns), computed at once.

    scan() goes over all members: ids, products with the queries, and levels: the place in ``opened`` (rising numbers of best units) that
    first opens a member's unit, len(opened) if none does. verified: representatives and members compared by each query at each level. Queries are dealt to
    the tasks, which read representatives and members from the shared folder block by block: neither hits nor pairs are ever a table.
    """
    spark = index.reps.sparkSession
    _, reps = tables.save(index.reps.select("unit_id", "rep", "n_members"), "reps")
    _, rows = tables.save(index.members.select(F.col("unit_id").cast("bigint").alias("unit_id"), "vec_id", "vec"), "members")
    m, dealt = spark.read.parquet(reps).count(), 3 * spark.sparkContext.defaultParallelism
    some, few = max(1, min(SLICE // 2, 8 * TILE // max(m, 1))), max(1, TILE // 2 // max(m, 1))
    level_of = np.searchsorted(opened, np.arange(1, max(opened, default=0) + 1)).astype(np.int8)

    @tables.tidy
    def run(batches):
        for whole in batches:
            for i in range(0, whole.num_rows, some):
                b = whole.slice(i, some)
                q = kernels.matrix(b.column(1))
                levels, verified = np.full((len(q), m), len(opened), np.int8), np.zeros((len(q), len(opened)), np.int64)
                units, order = np.zeros(0, np.int64), np.zeros(0, np.int64)
                for j in range(0, len(q), few):
                    s, at, sizes, known = np.empty((len(q[j : j + few]), m)), 0, np.empty(m, np.int64), np.empty(m, np.int64)
                    for block in tables.stored_blocks(reps, SLICE):
                        to = at + block.num_rows
                        s[:, at:to] = q[j : j + few] @ kernels.matrix(block.column("rep")).T
                        known[at:to], sizes[at:to] = block.column("unit_id").to_numpy(), block.column("n_members").to_numpy()
                        at = to
                    order = np.argsort(known)
                    units, sizes = known[order], sizes[order]
                    best = np.argsort(-s[:, order], axis=1, kind="stable")[:, : len(level_of)]  # ties to the smaller unit
                    np.put_along_axis(levels[j : j + few], best, np.broadcast_to(level_of[: best.shape[1]], best.shape), 1)
                    for l in range(len(opened)):
                        verified[j : j + few, l] = m + (levels[j : j + few] <= l) @ sizes

                def scan(q=q, units=units, levels=levels):
                    for block in tables.stored_blocks(rows, 2 * SLICE):
                        place = np.searchsorted(units, block.column("unit_id").to_numpy())
                        yield block.column("vec_id").to_numpy(), q @ kernels.matrix(block.column("vec")).T, levels[:, place]

                yield from work(b, q, verified, scan)

    out = tables.save(queries.repartition(dealt).mapInArrow(run, schema), "scanned")[0]
    for path in (reps, rows):
        tables.drop(spark, path)
    return out


def best_others(index: Index, queries: DataFrame, opened: list[int], k: int) -> DataFrame:
    """query_id, opened, vec_id: the k best members, the query itself apart, at each number of opened units and (0) of all members."""

    def work(b, q, verified, scan):
        asked, best = b.column(0).to_numpy(), [Best(len(q), k) for _ in (*opened, 0)]
        for ids, s, levels in scan():
            s[asked[:, None] == ids[None, :]] = -np.inf
            for l, held in enumerate(best):
                held.add(0, s if l == len(opened) else np.where(levels <= l, s, -np.inf), ids)
        for held, n in zip(best, (*opened, 0), strict=True):
            a, c = np.nonzero(np.isfinite(held.score))
            yield pa.RecordBatch.from_arrays([pa.array(asked[a]), pa.array([n] * len(a), pa.int32()), pa.array(held.ids[a, c])], ["query_id", "opened", "vec_id"])

    return opened_scan(index, queries.select("query_id", "qvec"), opened, work, "query_id bigint, opened int, vec_id bigint")


def near_precision(index: Index, queries: DataFrame, opened: list[int], alpha0: float, k: int) -> DataFrame:
    """query_id, opened, ap, verified of the queries that have other members of at least alpha0 as matches; opened is 0 for the k best of
    all members, the query itself among them. All matches precede all else, so the precision at each that is found is one."""

    def work(b, q, verified, scan):
        asked = b.column(0).to_numpy()
        found, before, own = np.zeros((len(q), len(opened) + 1), np.int64), [], np.full(len(q), np.inf)
        for ids, s, levels in scan():
            r, c = np.nonzero(asked[:, None] == ids[None, :])
            own[r] = s[r, c]
            s[r, c] = -np.inf
            r, c = np.nonzero(s >= alpha0)
            np.add.at(found, (r, levels[r, c]), 1)
            before.append((r, ids[c], s[r, c]))
        r, ids, s = (np.concatenate(x) for x in zip(*before, strict=True)) if before else (np.zeros(0, np.int64),) * 3
        ahead = np.bincount(r[(s > own[r]) | ((s == own[r]) & (ids < asked[r]))], minlength=len(q))
        n = found.sum(1)
        of_all = np.minimum(n, np.where(ahead < k, k - 1, k))  # the query itself takes a place if it is among the k best
        has = np.flatnonzero(n)
        shares = [*((found[has, : l + 1].sum(1) / n[has], verified[has, l]) for l in range(len(opened))), (of_all[has] / n[has], 0 * has)]
        yield _precisions(asked[has], opened, shares)

    return opened_scan(index, queries.select("query_id", "qvec"), opened, work, _PRECISION)


_PRECISION = "query_id bigint, opened int, ap double, verified bigint"


def _precisions(asked: np.ndarray, opened: list[int], rows: list[tuple]) -> pa.RecordBatch:
    n = np.repeat([*opened, 0], len(asked)).astype(np.int32)
    ap, verified = (np.concatenate(x) for x in zip(*rows, strict=True))
    return pa.RecordBatch.from_arrays([pa.array(np.tile(asked, len(rows))), pa.array(n), pa.array(ap, pa.float64()), pa.array(verified, pa.int64())], ["query_id", "opened", "ap", "verified"])


def listed_precision(index: Index, queries: DataFrame, opened: list[int], truth: DataFrame, k: int) -> DataFrame:
    """The same for matches (query_id, vec_id) of any similarity; a row for every query, ap is null where it has no match.

    Tasks scan the members twice: for the similarities of the matches, then for how many members come before each of them.
    """
    lists = truth.groupBy("query_id").agg(F.sort_array(F.collect_set("vec_id")).alias("matches"))
    none = F.array().cast("array<bigint>")
    asked = queries.select("query_id", "qvec").join(lists, "query_id", "left").select("query_id", "qvec", F.coalesce("matches", none).alias("matches"))

    def work(b, q, verified, scan):
        want = b.column(2).combine_chunks() if isinstance(b.column(2), pa.ChunkedArray) else b.column(2)
        size = np.array([len(x) for x in want], np.int64)
        row, match = np.repeat(np.arange(len(q)), size), want.flatten().to_numpy(zero_copy_only=False)
        order = np.argsort(match, kind="stable")
        row, match = row[order], match[order]
        got = []
        for ids, s, levels in scan():
            lo, hi = np.searchsorted(match, ids, "left"), np.searchsorted(match, ids, "right")
            c = np.repeat(np.arange(len(ids)), hi - lo)
            at = np.arange(len(c)) - np.repeat(np.cumsum(hi - lo) - (hi - lo), hi - lo) + np.repeat(lo, hi - lo)
            r = row[at]
            got.append((r, -s[r, c], ids[c], levels[r, c]))
        r, far, ids, level = (np.concatenate(x) for x in zip(*got, strict=True)) if got else (np.zeros(0, np.int64),) * 4
        order = np.lexsort((ids, far, r))
        r, far, ids, level = r[order], far[order], ids[order], level[order]
        cut = np.searchsorted(r, np.arange(len(q) + 1))
        held = [(far[a:z], ids[a:z], level[a:z]) for a, z in zip(cut, cut[1:], strict=False)]
        count = [np.zeros((len(opened) + 1, len(h[0]) + 1), np.int64) for h in held]
        for got_ids, s, levels in scan():
            for j, (x, of, _) in enumerate(held):
                near = np.flatnonzero(s[j] >= -x[-1]) if len(x) else ()
                if not len(near):
                    continue
                lo, hi = np.searchsorted(x, -s[j, near], "left"), np.searchsorted(x, -s[j, near], "right")
                for t in np.flatnonzero(lo < hi):  # of equal similarity: smaller ids come first
                    hi[t] = lo[t] + np.searchsorted(of[lo[t] : hi[t]], got_ids[near[t]], "right")
                np.add.at(count[j], (levels[j, near], hi), 1)
        rows = []
        for l in range(len(opened) + 1):
            ap = np.full(len(q), np.nan)
            for j, (x, _, own) in enumerate(held):
                if size[j]:
                    ahead = count[j][: l + 1].sum(0).cumsum()[: len(x)]
                    hit = np.flatnonzero((own <= l) & ((ahead < k) if l == len(opened) else True))
                    ap[j] = (np.arange(1, len(hit) + 1) / (ahead[hit] + 1)).sum() / size[j]
            rows.append((ap, verified[:, l] if l < len(opened) else np.zeros(len(q), np.int64)))
        yield _precisions(b.column(0).to_numpy(), opened, rows)

    out = opened_scan(index, asked, opened, work, _PRECISION)
    return out.withColumn("ap", F.when(~F.isnan("ap"), F.col("ap")))


def own_scores(reps: DataFrame, queries: DataFrame, work, schema: str) -> DataFrame:
    """Rows that ``work(blocks)`` gives in each task for (scores, units, own) blocks of queries (qvec, own unit) against representatives.

    As in rank_stored, queries are dealt to the tasks and representatives read from the shared folder: none passes through the driver,
    and of all the scores only what the work makes of them leaves its task.
    """
    _, path = tables.save(reps.select("unit_id", "rep"), "reps")

    def scores(batches):
        for whole in batches:
            for i in range(0, whole.num_rows, SLICE):
                b = whole.slice(i, SLICE)
                q, own = kernels.matrix(b.column(0)), b.column(1).to_numpy()
                for block in tables.stored_blocks(path, 2 * SLICE):
                    yield q @ kernels.matrix(block.column("rep")).T, block.column("unit_id").to_numpy(), own

    @tables.tidy
    def run(batches):
        yield from work(scores(batches))

    return queries.select("qvec", "own").repartition(3 * reps.sparkSession.sparkContext.defaultParallelism).mapInArrow(run, schema)


def own_rates(reps: DataFrame, queries: DataFrame, taus: list[float]) -> DataFrame:
    """tau, pfp, pfn of queries (qvec, own) against all units, of which just the own one is related; counted in the tasks."""
    names = ["tau", "related", "above", "n"]

    def count(blocks):
        for s, units, own in blocks:
            same = units[None, :] == own[:, None]
            for t in taus:
                above, both = s > t, np.count_nonzero(same)
                hit = np.count_nonzero(above & same)
                rows = [[float(t)] * 2, [True, False], [hit, np.count_nonzero(above) - hit], [both, s.size - both]]
                yield pa.RecordBatch.from_arrays([pa.array(rows[0]), pa.array(rows[1]), pa.array(rows[2], pa.int64()), pa.array(rows[3], pa.int64())], names)

    got = own_scores(reps, queries, count, "tau double, related boolean, above bigint, n bigint").groupBy("tau")
    share = {r: F.try_divide(F.sum(F.when(F.col("related") == r, F.col("above"))), F.sum(F.when(F.col("related") == r, F.col("n")))) for r in (True, False)}
    return got.agg(share[False].alias("pfp"), (1 - share[True]).alias("pfn"))


def near_counts(members: DataFrame, queries: DataFrame, kind: str, alphas: tuple[float, ...], lo: float, hi: float, bins: int) -> DataFrame:
    """alpha0, b, p, n: scores of all units against all queries counted by bin (see metrics.roc), related (p) or not (n).

    A unit is related to a query if it holds another vector of cosine alpha0 or more. Members are stored with whole units in a file;
    queries are dealt to the tasks, which read the files one by one, so neither scores nor matches are ever a table.
    """
    spark = members.sparkSession
    _, path = tables.save(members.select("unit_id", "vec_id", "vec").repartition("unit_id").sortWithinPartitions("unit_id"), "units")
    width, names = (hi - lo) / bins, ["alpha0", "b", "p", "n"]

    @tables.tidy
    def run(batches):
        for whole in batches:
            for i in range(0, whole.num_rows, max(1, SLICE // 4)):
                b = whole.slice(i, max(1, SLICE // 4))
                q, asked = kernels.matrix(b.column(1)), b.column(0).to_numpy()
                p, n = np.zeros((2, len(alphas), bins + 2), np.int64)
                for units, ids, x in tables.stored_groups(path, 4 * SLICE):
                    first = np.flatnonzero(np.diff(units, prepend=units[0] - 1))
                    own = np.repeat(np.arange(len(first)), np.diff([*first, len(units)]))
                    reps, _ = kernels.unit_reps(x, own, len(first), kind)
                    place = np.clip(np.ceil((q @ reps.T - lo) / width), 0, bins + 1).astype(np.int64)
                    near = q @ x.T
                    near[asked[:, None] == ids[None, :]] = -np.inf
                    near = np.maximum.reduceat(near, first, axis=1)
                    for j, alpha0 in enumerate(alphas):
                        p[j] += np.bincount(place[near >= alpha0], minlength=bins + 2)
                        n[j] += np.bincount(place[near < alpha0], minlength=bins + 2)
                at = np.tile(np.arange(bins + 2, dtype=np.int32), len(alphas))
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(alphas, bins + 2)), pa.array(at), pa.array(p.reshape(-1)), pa.array(n.reshape(-1))], names)

    dealt = queries.select("query_id", "qvec").repartition(spark.sparkContext.defaultParallelism)
    out = tables.now(dealt.mapInArrow(run, "alpha0 double, b int, p bigint, n bigint").groupBy("alpha0", "b").agg(F.sum("p").alias("p"), F.sum("n").alias("n")))
    tables.drop(spark, path)
    return out


#: Bins of a look at scores, and scores that are looked at one by one; the bin that holds the median is cut again if it has more.
BINS, HELD = 1 << 14, 200_000


def own_summary(reps: DataFrame, queries: DataFrame) -> DataFrame:
    """related, n, mean, sd, least, most, median, units, best_unit of the scores of queries (qvec, own) against all units, exactly.

    A task adds its scores up to one row and counts by bin; later passes look at the scores of the bin that holds the median only.
    Representatives and queries are computed once and stored.
    """
    reps, stored = tables.save(reps.select("unit_id", "rep", "rep_norm2"), "summed-reps")
    rows, path = tables.save(queries.select("qvec", "own"), "asked")
    tables.release(reps.sparkSession)
    widest = F.sqrt(F.max(F.aggregate("qvec", F.lit(0.0), lambda s, x: s + x * x)))
    bound = (rows.agg(widest).first()[0] or 0.0) * (reps.agg(F.sqrt(F.max("rep_norm2"))).first()[0] or 0.0) * (1 + 1e-9) + 1e-300
    width = 2 * bound / BINS

    def coarse(s):
        return np.clip(((s + bound) / width).astype(np.int64), 0, BINS - 1)

    def fine(s):  # the same order, each bin cut again
        at = coarse(s)
        return at * BINS + np.clip((((s + bound) / width - at) * BINS).astype(np.int64), 0, BINS - 1)

    def reduce(blocks):
        n, total = np.zeros((2, BINS), np.int64), np.zeros((2, 2))
        ends = [[np.inf, -np.inf, 0], [np.inf, -np.inf, 0]]
        for s, units, own in blocks:
            r, c = np.nonzero(units[None, :] == own[:, None])
            mine = s[r, c]
            of_mine = np.bincount(coarse(mine), minlength=BINS)
            n += np.bincount(coarse(s).reshape(-1), minlength=BINS) - of_mine, of_mine
            s[r, c] = 0.0
            flat = s.reshape(-1)
            total += (flat.sum(), flat @ flat), (mine.sum(), mine @ mine)
            s[r, c] = np.inf
            least = s.min(), mine.min(initial=np.inf)
            s[r, c] = -np.inf
            for related, most in enumerate((s.max(), mine.max(initial=-np.inf))):
                end = ends[related]
                end[0] = min(end[0], least[related])
                if most >= end[1] and most > -np.inf:
                    best = int(units[(s == most).any(0)].min() if not related else units[c[mine == most]].min())
                    end[1:] = most, min(best, end[2]) if most == end[1] else best
        for related in (0, 1):
            at = np.flatnonzero(n[related])
            if len(at):
                summed = [[-1], [n[related].sum()], [total[related, 0]], [total[related, 1]], *([x] for x in ends[related])]
                for row in (summed, [at, n[related, at], *[[None] * len(at)] * 5]):
                    yield pa.RecordBatch.from_arrays([pa.array([bool(related)] * len(row[0])), *(pa.array(x, k) for x, k in zip(row, kinds, strict=True))], names)

    names, kinds = ["related", "b", "n", "s", "s2", "least", "most", "best"], [pa.int64()] * 2 + [pa.float64()] * 4 + [pa.int64()]
    reduced = own_scores(reps, rows, reduce, "related boolean, b bigint, n bigint, s double, s2 double, least double, most double, best bigint").groupBy("related", "b")
    reduced = reduced.agg(F.sum("n").alias("n"), F.sum("s").alias("s"), F.sum("s2").alias("s2"), F.min("least").alias("least"), F.max(F.struct("most", (-F.col("best")).alias("u"))).alias("top"))
    found: dict = {}
    for r in reduced.collect():  # at most 2 * BINS
        found.setdefault(r.related, {})[r.b] = r

    def holding(counts: list[tuple], related: bool, before: dict) -> dict:
        """key -> (rank of its first score, scores) of the bins that hold the median; before: rank of the first score of the bins cut."""
        n, out, at, last = found[related][-1].n, {}, 0, None
        for group, key, m in sorted(counts):
            at, last = (at if group == last else before.get(group, at)), group
            if any(at <= w < at + m for w in ((n - 1) // 2, n // 2)):
                out[key] = at, m
            at += m
        return out

    def look(parts: dict, of, key, many: bool):
        """related, key, x, n of the scores in parts: of each value, or of all of a bin of key."""

        def take(blocks):
            for s, units, own in blocks:
                r, c = np.nonzero(units[None, :] == own[:, None])
                mine = s[r, c]
                s[r, c] = np.inf
                for related, x in ((False, s.reshape(-1)), (True, mine)):
                    wanted = list(parts.get(related, {}))
                    x = x[np.isfinite(x)]
                    x = x[np.isin(of(x), wanted)] if wanted else x[:0]
                    keys, n = np.unique(key(x) if many else x, return_counts=True)
                    at = np.zeros(len(keys)) if many else keys
                    keys = keys if many else of(keys)
                    if len(keys):
                        yield pa.RecordBatch.from_arrays([pa.array([related] * len(keys)), pa.array(keys, pa.int64()), pa.array(at), pa.array(n, pa.int64())], ["related", "key", "x", "n"])

        got = own_scores(reps, rows, take, "related boolean, key bigint, x double, n bigint")
        return got.groupBy("related", "key", "x").agg(F.sum("n").alias("n"))

    parts = {r: holding([(0, b, x.n) for b, x in of.items() if b >= 0], r, {}) for r, of in found.items()}
    key = coarse
    if any(m > HELD for p in parts.values() for _, m in p.values()):
        cut = look(parts, coarse, fine, True).collect()  # at most BINS of each bin that was cut
        parts = {r: holding([(x.key // BINS, x.key, x.n) for x in cut if x.related == r], r, {b: at for b, (at, _) in p.items()}) for r, p in parts.items()}
        key = fine
    got: dict = {}
    base = {(r, k): at for r, p in parts.items() for k, (at, _) in p.items()}
    for x in look(parts, key, None, False).orderBy("x").toLocalIterator():
        n, at = found[x.related][-1].n, base[x.related, x.key]
        got |= {(x.related, w): x.x for w in ((n - 1) // 2, n // 2) if at <= w < at + x.n}
        base[x.related, x.key] = at + x.n
    n_units, out = reps.count(), []
    own_units = rows.select(F.col("own").alias("unit_id")).join(reps, "unit_id", "left_semi").distinct().count()
    lone = own_units == 1 == rows.select("own").distinct().count()  # a unit that is every query's own is unrelated to none
    for related, bins in sorted(found.items(), reverse=True):
        a = bins[-1]
        mean = a.s / a.n
        var = max(0.0, a.s2 - a.n * mean * mean) / (a.n - 1) if a.n > 1 else None
        median = (got[related, (a.n - 1) // 2] + got[related, a.n // 2]) / 2
        units = own_units if related else n_units - (1 if lone else 0)
        out.append((related, a.n, mean, var**0.5 if var is not None else None, a.least, a.top.most, median, units, -a.top.u))
    for at in (path, stored):
        tables.drop(reps.sparkSession, at)
    return reps.sparkSession.createDataFrame(out, "related boolean, n bigint, mean double, sd double, least double, most double, median double, units bigint, best_unit bigint")


def with_unit_thresholds(reps: DataFrame, d: int, alpha0: float, eps: float, kind: str = "pinv") -> DataFrame:
    """reps with tau: each unit's threshold from its own norm (pinv) or size (sum)."""
    z = theory.phi_inv(eps)
    if kind == "pinv":
        spread = F.sqrt("rep_norm2") * ((1 - alpha0**2) ** 0.5 / d**0.5)
    else:
        spread = F.sqrt((F.col("n_members") - 1) / d)
    return reps.withColumn("tau", F.lit(alpha0) + spread * z)


def verify(
    positives: DataFrame, members: DataFrame, queries: DataFrame, min_sim: float | None = None, strict: bool = False, measure: Measure = PRODUCT, vec: str = "vec", qvec: str = "qvec", with_unit: bool = False, few: bool = False
) -> DataFrame:
    """query_id, vec_id, sim of the members of positive units, those of at least min_sim; with_unit: and unit_id.

    few: positives are at most BROADCAST_ROWS and are broadcast, so members stay where they are.

    An equi-join on unit_id of members and lists of at most LIST query ids; Spark picks broadcast or sort-merge and splits skewed
    units. Query vectors are not shuffled: tasks have them in blocks, as probing has; a member is met by a whole list at once.
    """
    out = None
    kind, id_type = dict(members.dtypes)["vec_id"], to_arrow_type(members.schema["vec_id"].dataType)
    names, unit_kind = ["query_id", "vec_id", "sim"] + ["unit_id"] * with_unit, dict(members.dtypes)["unit_id"]
    for mine, shared in query_blocks(queries, qvec, measure.kind):
        asked = positives.select("query_id", "unit_id")
        asked = asked if mine is None else asked.where(mine)
        lists = max(1, -(-len(shared.value[0]) // LIST))
        by_unit = asked.groupBy("unit_id", F.pmod(F.xxhash64("query_id", F.lit(1)), F.lit(lists)).alias("part")).agg(F.collect_list("query_id").alias("asked"))
        by_unit = F.broadcast(by_unit) if few else by_unit
        pairs = members.select("unit_id", "vec_id", vec).join(by_unit, "unit_id").select("vec_id", vec, "asked", "unit_id", "part")

        @tables.tidy
        def run(batches, shared=shared):
            ids, q = shared.value
            for whole in batches:
                for i in range(0, whole.num_rows, SLICE):
                    b = whole.slice(i, SLICE)
                    x, asked = kernels.matrix(b.column(1), measure.kind), b.column(2)
                    unit, part = (b.column(j).to_numpy(zero_copy_only=False) for j in (3, 4))
                    order = np.lexsort((part, unit))
                    cut = np.flatnonzero((np.diff(unit[order]) != 0) | (np.diff(part[order]) != 0)) + 1
                    rows, cols, sims = [], [], []
                    for members_of in np.split(order, cut):  # the members of a unit here, against all that open it
                        at = asked[int(members_of[0])].values.to_numpy(zero_copy_only=False)
                        place = np.searchsorted(ids, at)
                        place = place[(place < len(ids)) & (ids[np.minimum(place, len(ids) - 1)] == at)] if len(ids) else place[:0]
                        s = measure.blocks(q[place], x[members_of])
                        i_q, i_x = np.nonzero(np.ones(s.shape, bool) if min_sim is None else s > min_sim if strict else s >= min_sim)
                        rows.append(members_of[i_x])
                        cols.append(ids[place[i_q]])
                        sims.append(s[i_q, i_x])
                    at = pa.array(np.concatenate(rows), pa.int64())
                    out = [pa.array(np.concatenate(cols), pa.int64()), b.column(0).take(at).cast(id_type), pa.array(np.concatenate(sims), pa.float64()), b.column(3).take(at)]
                    yield pa.RecordBatch.from_arrays(out[: len(names)], names)

        part = pairs.mapInArrow(run, f"query_id bigint, vec_id {kind}, sim double" + f", unit_id {unit_kind}" * with_unit)
        out = part if out is None else out.unionByName(part)
    return out


def rank_hits(hits: DataFrame, k: int | None = None) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("sim"), "vec_id"))
    out = hits.withColumn("hit_rank", rank)
    return out.where(F.col("hit_rank") <= k) if k is not None else out


def search(
    index: Index, queries: DataFrame, tau: float | str | None = None, top_units: int | None = None, min_sim: float | None = None, k: int | None = None, strict: bool = False, where: Column | None = None
) -> DataFrame:
    """query_id, vec_id, sim, hit_rank: range search (min_sim), top k, or all members of the positive units.

    where: a condition on member columns; it reaches their scan if they are columns of the stored members (see tables.write_index).
    """
    positives = select_units(index.reps, queries, tau, top_units)
    members = index.members.where(where) if where is not None else index.members
    return rank_hits(verify(positives, members, queries, min_sim, strict), k)


def membership_test(reps: DataFrame, queries: DataFrame, tau: float) -> DataFrame:
    """query_id, member, n_positive: whether any unit may hold something similar; no member is read."""
    positives = probe(reps, queries, tau).groupBy("query_id").agg(F.count("*").alias("n"))
    out = queries.select("query_id").join(positives, "query_id", "left")
    return out.select("query_id", F.coalesce(F.col("n"), F.lit(0)).alias("n_positive"), F.col("n").isNotNull().alias("member"))


def similarity_join(left: DataFrame, index: Index, alpha0: float, tau: float, same: bool = True) -> DataFrame:
    """left_id, right_id, sim of all pairs of at least alpha0 that the index finds, each once.

    The left table is the queries, met in blocks by the representatives. same: left is the indexed table itself; then a pair counts
    whichever of the two finds the other's unit, once with the smaller id on the left. The method is approximate: see the query for
    its measured recall.
    """
    queries = left.select(F.col("vec_id").alias("query_id"), F.col("vec").alias("qvec"))
    hits = verify(probe(index.reps, queries, tau), index.members, queries, alpha0)
    if not same:
        return hits.select(F.col("query_id").alias("left_id"), F.col("vec_id").alias("right_id"), "sim")
    pairs = hits.where("query_id <> vec_id").select(F.least("query_id", "vec_id").alias("left_id"), F.greatest("query_id", "vec_id").alias("right_id"), "sim")
    return pairs.groupBy("left_id", "right_id").agg(F.max("sim").alias("sim"))


def exhaustive_search(vectors: DataFrame, queries: DataFrame, k: int | None = None, alpha0: float | None = None) -> DataFrame:
    """The reference for accuracy: every vector against every query; top k or all of at least alpha0."""
    hits = score_pairs(vectors, queries, "vec_id", "vec", np.nextafter(alpha0, -np.inf) if alpha0 is not None else None, k)
    return rank_hits(hits.withColumnRenamed("score", "sim"), k)


def count_matches(vectors: DataFrame, queries: DataFrame, alpha0: float) -> int:
    """Pairs of a query and another vector of at least alpha0, counted in the tasks: as many as they are, none is kept."""
    total = 0
    for _, shared in query_blocks(queries):

        @tables.tidy
        def run(batches, shared=shared):
            ids, q = shared.value
            n = 0
            for b in batches:
                for i in range(0, b.num_rows if len(ids) else 0, SLICE):
                    x, own = kernels.matrix(b.column(1).slice(i, SLICE)), b.column(0).slice(i, SLICE).to_numpy(zero_copy_only=False)
                    step = max(1, TILE // len(own))
                    for j in range(0, len(q), step):
                        s = q[j : j + step] @ x.T
                        n += int(np.count_nonzero(s >= alpha0))
                        place = np.searchsorted(ids[j : j + step], own)
                        same = np.flatnonzero((place < len(s)) & (ids[j : j + step][np.minimum(place, len(s) - 1)] == own))
                        n -= int(np.count_nonzero(s[place[same], same] >= alpha0))
            yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], ["n"])

        total += vectors.select("vec_id", "vec").mapInArrow(run, "n bigint").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        shared.unpersist()
    return total


@dataclass
class Plan:
    kind: str
    unit_size: int
    tau: float
    cost_ratio: float
    levels: int = 1


def auto_plan(d: int, alpha0: float, eps: float, n_max: int = 500) -> Plan:
    """Representative, unit size and threshold of least expected cost."""
    best = min((theory.optimal_unit_size(k, d, alpha0, eps, n_max) + (k,) for k in ("sum", "pinv")), key=lambda x: x[1])
    return Plan(best[2], best[0], theory.threshold(best[2], best[0], d, alpha0, eps), best[1])


def calibrated_threshold(scores: DataFrame, eps: float) -> float:
    """An empirical threshold: the quantile eps of scores of units that do hold a match. For data of low intrinsic dimension."""
    return scores.agg(F.percentile_approx("score", eps, 10_000)).first()[0]


def build_two_level(index: Index, n: int = 10, d: int = 64) -> tuple[DataFrame, DataFrame]:
    """(representatives of groups of representatives, representatives with their group): screens the screening."""
    scaled = index.reps.select(F.col("unit_id").alias("vec_id"), F.transform("rep", lambda x: x / F.sqrt("rep_norm2")).alias("vec"))
    size = index.reps.count()
    grouped = scaled.withColumn("unit_id", F.pmod(F.xxhash64("vec_id"), F.lit(max(1, -(-size // n)))))
    return representatives(grouped, "pinv", d), grouped


def bounded_broadcast(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """df, marked for broadcast; raises if it has more rows than may be broadcast and no other way exists."""
    if df.limit(rows + 1).count() > rows:
        raise ValueError(f"more than {rows} rows to broadcast; take them in blocks")
    return F.broadcast(df)


def broadcast_if_small(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df
