"""Representatives of units: sum, minimum-norm (pinv), ridge, normalised, online, and their diagnostics."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import kernels
from ..functions.vectors import norm2
from ..sources import tables

#: Up to so many components the sum is d partial sums in generated code; beyond, Arrow adds rows up.
SUM_COLUMNS = 128
_REPS = "unit_id bigint, rep array<double>, n_members bigint, rep_norm2 double"


def sum_representatives(members: DataFrame, unit: str = "unit_id", vec: str = "vec", d: int = 64) -> DataFrame:
    """Component-wise sums: unit_id, rep, n_members, rep_norm2. Partial sums before the shuffle, so large units are no hot keys."""
    if d <= SUM_COLUMNS:
        sums = F.array(*[F.sum(F.get(vec, i)) for i in range(d)])
        out = members.groupBy(F.col(unit).cast("bigint").alias("unit_id")).agg(sums.alias("rep"), F.count("*").alias("n_members"))
        return out.withColumn("rep_norm2", norm2("rep"))

    @tables.tidy
    def partial(batches):
        for b in batches:
            units, x = b.column(0).to_numpy(zero_copy_only=False), kernels.matrix(b.column(1))
            keys, place = np.unique(units, return_inverse=True)
            total = np.zeros((len(keys), d))
            np.add.at(total, place, x)
            n = np.bincount(place, minlength=len(keys))
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), kernels.vectors_column(total), pa.array(n, pa.int64())], ["unit_id", "part", "n"])

    parts = members.select(F.col(unit).cast("bigint"), vec).mapInArrow(partial, "unit_id bigint, part array<double>, n bigint")

    @tables.tidy
    def final(batches):
        for t in whole_units(batches):
            keys, at = np.unique(t.column("unit_id").to_numpy(), return_inverse=True)
            total, _ = kernels.unit_reps(kernels.matrix(t.column("part")), at, len(keys), "sum")
            yield _rows(keys, total, np.bincount(at, t.column("n").to_numpy()).astype(np.int64))

    return parts.repartition("unit_id").sortWithinPartitions("unit_id").mapInArrow(final, _REPS)


def whole_units(batches):
    """Tables of rows (unit_id first) that come sorted by unit, cut between units; the last unit waits for its other rows."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        units = b.column(0).to_numpy()
        cut = int(np.searchsorted(units, units[-1]))
        if held and units[0] != held[-1].column(0)[-1].as_py():
            yield pa.Table.from_batches([*held, b.slice(0, cut)])
            held = []
        elif cut:
            yield pa.Table.from_batches([*held, b.slice(0, cut)])
            held = []
        held.append(b.slice(cut))
    if held:
        yield pa.Table.from_batches(held)


def _rows(units: np.ndarray, m: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(units, pa.int64()), kernels.vectors_column(m), pa.array(n, pa.int64()), pa.array((m * m).sum(1))], ["unit_id", "rep", "n_members", "rep_norm2"])


def _row(unit, m: np.ndarray, n: int) -> pa.Table:
    return pa.table([pa.array([unit], pa.int64()), kernels.vectors_column(m[None, :]), pa.array([n], pa.int64()), pa.array([float(m @ m)])], names=["unit_id", "rep", "n_members", "rep_norm2"])


def pinv_representatives(members: DataFrame, unit: str = "unit_id", vec: str = "vec", rcond: float = 1e-10, lam: float = 0.0) -> DataFrame:
    """The shortest vectors whose product with every member is one; nearest in squares where members contradict each other.

    One shuffle by unit; a task solves many units at a time, each of bounded size by assignment.
    """
    if not lam:

        @tables.tidy
        def many(batches):
            for t in whole_units(batches):
                keys, at = np.unique(t.column("unit_id").to_numpy(), return_inverse=True)
                yield _rows(keys, *kernels.unit_reps(kernels.matrix(t.column("vec")), at, len(keys), "pinv", rcond=rcond))

        rows = members.select(F.col(unit).cast("bigint").alias("unit_id"), F.col(vec).alias("vec"))
        return rows.repartition("unit_id").sortWithinPartitions("unit_id").mapInArrow(many, _REPS)

    def solve(key, table):
        x = kernels.matrix(table.column("vec"))
        return _row(key[0].as_py(), kernels.pinv_rep(x, rcond, lam), len(x))

    return members.select(F.col(unit).cast("bigint").alias("unit_id"), F.col(vec).alias("vec")).groupBy("unit_id").applyInArrow(solve, _REPS)


def ridge_representatives(members: DataFrame, lam: float, unit: str = "unit_id", vec: str = "vec") -> DataFrame:
    return pinv_representatives(members, unit, vec, lam=lam)


def solved(members: DataFrame, kind: str) -> DataFrame:
    """unit_id, rep of members (unit_id, vec) or, for sums, of partial sums: many units at a time in a task."""

    @tables.tidy
    def many(batches):
        for t in whole_units(batches):
            keys, at = np.unique(t.column("unit_id").to_numpy(), return_inverse=True)
            yield pa.RecordBatch.from_arrays([pa.array(keys), kernels.vectors_column(kernels.unit_reps(kernels.matrix(t.column("vec")), at, len(keys), kind)[0])], ["unit_id", "rep"])

    return members.select("unit_id", "vec").repartition("unit_id").sortWithinPartitions("unit_id").mapInArrow(many, "unit_id bigint, rep array<double>")


def representatives(members: DataFrame, kind: str, d: int = 64) -> DataFrame:
    return sum_representatives(members, d=d) if kind == "sum" else pinv_representatives(members)


def normalize_representatives(reps: DataFrame) -> DataFrame:
    scaled = F.transform("rep", lambda x: x / F.sqrt("rep_norm2"))
    return reps.where("rep_norm2 > 0").withColumn("rep", scaled).withColumn("rep_norm2", F.lit(1.0))


def online_representatives(members: DataFrame, order: str = "vec_id", kind: str = "pinv") -> DataFrame:
    """The same representatives, built by appending a unit's members one at a time in an order."""

    def build(key, table):
        table = table.sort_by(order)
        state = kernels.UnitState(kind)
        for x in kernels.matrix(table.column("vec")):
            state.append(x)
        return _row(key[0].as_py(), state.rep, len(state.members))

    return members.select("unit_id", order, "vec").groupBy("unit_id").applyInArrow(build, _REPS)


def append_to_units(reps: DataFrame, new: DataFrame, d: int = 64) -> DataFrame:
    """Sum representatives after new members: the running sum, without reading old members."""
    both = reps.select("unit_id", "rep", "n_members").unionByName(sum_representatives(new, d=d).select("unit_id", "rep", "n_members"))
    sums = F.array(*[F.sum(F.get("rep", i)) for i in range(d)])
    return both.groupBy("unit_id").agg(sums.alias("rep"), F.sum("n_members").alias("n_members")).withColumn("rep_norm2", norm2("rep"))


def append_to_pinv_units(reps: DataFrame, members: DataFrame, new: DataFrame) -> DataFrame:
    """Minimum-norm representatives after new members: units that get one are solved anew from their members, all others stay.

    A unit has as many members as assignment gives it, so what is read again is small; members are met by a semi-join on the touched
    units. kernels.UnitState does the same one vector at a time where a task holds the unit.
    """
    columns = ["unit_id", "rep", "n_members", "rep_norm2"]
    touched = new.select(F.col("unit_id").cast("bigint").alias("unit_id")).distinct()
    again = members.select("unit_id", "vec").join(touched, "unit_id", "left_semi").unionByName(new.select("unit_id", "vec"))
    return reps.join(touched, "unit_id", "left_anti").select(*columns).unionByName(pinv_representatives(again).select(*columns))


def unit_diagnostics(members: DataFrame) -> DataFrame:
    """unit_id, n, squared norms of both representatives, extreme eigenvalues and trace of the Gram matrix, condition number."""
    schema = "unit_id bigint, n bigint, norm2_sum double, norm2_pinv double, lambda_min double, lambda_max double, trace double, condition double"

    def look(key, table):
        x = kernels.matrix(table.column("vec"))
        values = np.linalg.eigvalsh(x @ x.T)
        s, p = x.sum(0), kernels.pinv_rep(x)
        row = [key[0].as_py(), len(x), s @ s, p @ p, values[0], values[-1], values.sum(), values[-1] / max(values[0], 1e-300)]
        return pa.table([pa.array([v]) for v in row], names=[c.split()[0] for c in schema.split(", ")]).cast(_DIAG)

    return members.select(F.col("unit_id").cast("bigint").alias("unit_id"), "vec").groupBy("unit_id").applyInArrow(look, schema)


_DIAG = pa.schema([("unit_id", pa.int64()), ("n", pa.int64()), *((c, pa.float64()) for c in ("norm2_sum", "norm2_pinv", "lambda_min", "lambda_max", "trace", "condition"))])


def gram_eigenvalues(members: DataFrame) -> DataFrame:
    """unit_id, lambda: all eigenvalues of each unit's Gram matrix."""

    def look(key, table):
        x = kernels.matrix(table.column("vec"))
        values = np.linalg.eigvalsh(x @ x.T)
        return pa.table({"unit_id": pa.array([key[0].as_py()] * len(values), pa.int64()), "lambda": pa.array(values)})

    return members.select(F.col("unit_id").cast("bigint").alias("unit_id"), "vec").groupBy("unit_id").applyInArrow(look, "unit_id bigint, lambda double")
