"""Sign codes: symmetric search by Hamming distance, asymmetric search with real queries."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels
from ..functions.vectors import binarize, signs
from ..sources import tables
from .represent import representatives
from .search import SLICE, Index, Measure, rank_hits, score_pairs, verify

#: Codes compared by falling similarity: minus the distance.
NEARNESS = Measure(lambda q, x: -kernels.hamming_block(q, x).astype(float), np.int64)


def encode(df: DataFrame, d: int, vec: str = "vec", code: str = "code") -> DataFrame:
    return df.withColumn(code, binarize(vec, d))


def hamming_search(vectors: DataFrame, queries: DataFrame, d: int, k: int) -> DataFrame:
    """query_id, vec_id, distance, hit_rank by exhaustive scan of codes. Queries (code, query_id) are broadcast in blocks."""
    scored = score_pairs(vectors, queries, "vec_id", "code", k=k, measure=NEARNESS, qvec="code")
    scored = scored.select("query_id", "vec_id", (-F.col("score")).cast("int").alias("distance"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("distance", "vec_id"))
    return scored.withColumn("hit_rank", rank).where(F.col("hit_rank") <= k)


def sign_index(members: DataFrame, kind: str = "sum", d: int = 64) -> Index:
    """Members and representatives as signs: the sign code of every member, and that of every representative of the real members."""
    reps = representatives(members, kind, d).withColumn("rep", signs("rep"))
    return Index(encode(reps, d, "rep"), encode(members, d).withColumn("vec", signs("vec")), {"codec": "sign", "rep": kind, "d": d})


def measures(d: int, symmetric: bool) -> Measure:
    """Products over the number of components: of two sign codes, or of a real query, scaled to unit length, with signs scaled likewise."""
    if symmetric:
        return Measure(lambda q, x: 1 - 2 * kernels.hamming_block(q, x) / d, np.int64)
    return Measure(lambda q, x: q @ x.T / d**0.5)


def sign_scores(index: Index, queries: DataFrame, symmetric: bool = False, tau: float | None = None) -> DataFrame:
    """query_id, unit_id, score of every unit, or of those above tau."""
    measure = measures(index.meta["d"], symmetric)
    if symmetric:
        return score_pairs(index.reps, encode(queries, index.meta["d"], "qvec", "qcode"), "unit_id", "code", tau, measure=measure, qvec="qcode")
    return score_pairs(index.reps, queries, "unit_id", "rep", tau, measure=measure)


def search_signs(index: Index, queries: DataFrame, tau: float, symmetric: bool = False, k: int | None = None) -> DataFrame:
    """query_id, vec_id, sim, hit_rank through an index of signs; sim and tau are products over the number of components.

    Asymmetric: real queries scaled to unit length against signs scaled likewise, so only additions and subtractions. Symmetric:
    queries become signs too, and products become 1 - 2 * distance / d.
    """
    d = index.meta["d"]
    positives = sign_scores(index, queries, symmetric, tau)
    if symmetric:
        return rank_hits(verify(positives, index.members, encode(queries, d, "qvec", "qcode"), measure=measures(d, True), vec="code", qvec="qcode"), k)
    return rank_hits(verify(positives, index.members, queries, measure=measures(d, False)), k)


def curve_counts(members: DataFrame, queries: DataFrame, alpha0: float, d: int, taus: list[float]) -> DataFrame:
    """kind, way, tau, opened, found, all: what a range search opens and finds at every threshold, by real vectors and by codes.

    opened: members of units that score above tau; found: matches (other members of at least alpha0) in them; all: matches. The way
    "scan" compares the code of every member, which is then found by itself. Members are stored with whole units in a file; queries
    are dealt to the tasks, which read the files one by one, so neither scores nor matches are ever a table.
    """
    spark = members.sparkSession
    _, path = tables.save(members.select("unit_id", "vec_id", "vec").repartition("unit_id").sortWithinPartitions("unit_id"), "units")
    ways = [(kind, way) for kind in ("sum", "pinv") for way in ("real", "asymmetric", "symmetric")] + [("none", "scan")]

    def signed(x):
        return np.where(x >= 0, 1.0, -1.0)

    def agreement(q, x):  # as measures() has it
        return 1 - 2 * ((d - q @ x.T) / 2) / d

    @tables.tidy
    def run(batches):
        opened, found, every = np.zeros((len(ways), len(taus)), np.int64), np.zeros((len(ways), len(taus)), np.int64), 0
        for whole in batches:
            for i in range(0, whole.num_rows, SLICE):
                b = whole.slice(i, SLICE)
                q, asked = kernels.matrix(b.column(1)), b.column(0).to_numpy()
                code = signed(q)
                for units, ids, x in tables.stored_groups(path, 2 * SLICE):
                    first = np.flatnonzero(np.diff(units, prepend=units[0] - 1))
                    size = np.diff([*first, len(units)])
                    own = np.repeat(np.arange(len(first)), size)
                    near = q @ x.T
                    near[asked[:, None] == ids[None, :]] = -np.inf
                    r, c = np.nonzero(near >= alpha0)
                    every += len(r)
                    for w, (kind, way) in enumerate(ways):
                        if way == "real":
                            reps, _ = kernels.unit_reps(x, own, len(first), kind)
                            s = q @ reps.T
                        elif way == "scan":
                            s = agreement(code, signed(x))
                        else:
                            s = q @ signed(reps).T / d**0.5 if way == "asymmetric" else agreement(code, signed(reps))
                        of_match = s[r, c if way == "scan" else own[c]]
                        for t, tau in enumerate(taus):
                            found[w, t] += np.count_nonzero(of_match > tau)
                            if way != "scan":
                                opened[w, t] += int(np.count_nonzero(s > tau, axis=0) @ size)
        rows = [(*way, float(tau), int(opened[w, t]), int(found[w, t]), every) for w, way in enumerate(ways) for t, tau in enumerate(taus)]
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*rows, strict=True)], ["kind", "way", "tau", "opened", "found", "all"])

    dealt = queries.select("query_id", "qvec").repartition(spark.sparkContext.defaultParallelism)
    parts = dealt.mapInArrow(run, "kind string, way string, tau double, opened bigint, found bigint, all bigint")
    out = tables.now(parts.groupBy("kind", "way", "tau").agg(*[F.sum(c).alias(c) for c in ("opened", "found", "all")]))
    tables.drop(spark, path)
    return out
