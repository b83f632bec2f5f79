"""Column functions on vectors (array<double>): products, norms, normalisation, sign codes. All stay in the JVM."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from . import kernels


def _col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def as_double(vec) -> Column:
    return _col(vec).cast("array<double>")


def dot(a, b) -> Column:
    return F.aggregate(F.zip_with(_col(a), _col(b), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm2(a) -> Column:
    return F.aggregate(_col(a), F.lit(0.0), lambda s, x: s + x * x)


def norm(a) -> Column:
    return F.sqrt(norm2(a))


def cosine(a, b) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def scale(a, c) -> Column:
    return F.transform(_col(a), lambda x: x * c)


def add(a, b) -> Column:
    return F.zip_with(_col(a), _col(b), lambda x, y: x + y)


def axpy(c, a, b) -> Column:
    """c * a + b, by component."""
    return F.zip_with(_col(a), _col(b), lambda x, y: x * c + y)


def normalize(df: DataFrame, vec: str = "vec") -> DataFrame:
    """Vectors scaled to unit length; a zero vector becomes null."""
    n = f"__norm_{vec}"
    out = df.withColumn(n, norm(vec))
    return out.withColumn(vec, F.when(F.col(n) > 0, F.transform(vec, lambda x: x / F.col(n)))).drop(n)


def power_normalize(df: DataFrame, exponent: float = 0.5, vec: str = "vec") -> DataFrame:
    """Signed power of every component, then unit length: makes directions closer to orthogonal."""
    return normalize(df.withColumn(vec, F.transform(vec, lambda x: F.signum(x) * F.pow(F.abs(x), F.lit(exponent)))), vec)


def mean_vectors(df: DataFrame, by: str | None = None, vec: str = "vec") -> DataFrame:
    """One row of component means, for each value of ``by`` or overall: dense partial sums of a task, added up by value."""
    kind = dict(df.dtypes)[by] if by else "int"
    parts = df.where(F.col(vec).isNotNull()).select((F.col(by) if by else F.lit(0)).alias("k"), vec)

    def partial(batches):
        sums: dict = {}
        for b in batches:
            x = kernels.matrix(b.column(1))
            coded = b.column(0).dictionary_encode()
            names, place = coded.dictionary.to_pylist(), coded.indices.fill_null(-1).to_numpy(zero_copy_only=False)
            for i in np.unique(place):
                rows = x[place == i]
                total = sums.setdefault(names[i] if i >= 0 else None, [np.zeros(x.shape[1]), 0])
                total[0] += rows.sum(0)
                total[1] += len(rows)
        out = list(sums.items())
        yield pa.RecordBatch.from_arrays(
            [pa.array([k for k, _ in out], key_type), kernels.vectors_column(np.stack([t[0] for _, t in out]) if out else np.zeros((0, 0))), pa.array([t[1] for _, t in out], pa.int64())], ["k", "total", "n"]
        )

    def final(key, table):
        total = kernels.matrix(table.column("total")).sum(0) / sum(table.column("n").to_pylist())
        return pa.table([pa.array([key[0].as_py()], key_type), kernels.vectors_column(total[None, :])], names=["k", "mean"])

    key_type = to_arrow_type(parts.schema["k"].dataType)
    out = parts.mapInArrow(partial, f"k {kind}, total array<double>, n bigint").groupBy("k").applyInArrow(final, f"k {kind}, mean array<double>")
    return out.withColumnRenamed("k", by) if by else out.select("mean")


def center_vectors(df: DataFrame, by: str | None = None, vec: str = "vec") -> DataFrame:
    """Subtracts the mean vector, overall or of a column's value (few values: means are broadcast), then scales to unit length.

    Vectors that are their mean become null, null vectors stay null. Dense blocks in Arrow tasks; the input is read twice.
    """
    means = mean_vectors(df, by, vec)
    if by:
        means = means.withColumnRenamed(by, "__by")
        joined = df.join(F.broadcast(means), df[by].eqNullSafe(F.col("__by")), "left").drop("__by")
    else:
        joined = df.join(F.broadcast(means), F.lit(True), "left")
    names = df.columns
    at = names.index(vec)

    def run(batches):
        for b in batches:
            columns = [b.column(i) for i in range(len(names))]
            known = np.flatnonzero(columns[at].is_valid().to_numpy(zero_copy_only=False))
            x = kernels.matrix(columns[at].take(pa.array(known))) - kernels.matrix(b.column(len(names)).take(pa.array(known))) if len(known) else np.zeros((0, 0))
            size = np.linalg.norm(x, axis=1) if len(known) else np.zeros(0)
            place = np.full(b.num_rows, -1)
            place[known[size > 0]] = np.arange(int((size > 0).sum()))
            scaled = kernels.vectors_column(x[size > 0] / size[size > 0, None]) if (size > 0).any() else pa.array([], pa.list_(pa.float64()))
            columns[at] = scaled.take(pa.array(place, mask=place < 0))
            yield pa.RecordBatch.from_arrays(columns, names)

    schema = T.StructType([T.StructField(f.name, T.ArrayType(T.DoubleType()) if f.name == vec else f.dataType) for f in df.schema])
    return joined.select(*names, "mean").mapInArrow(run, schema)


def binarize(vec, d: int) -> Column:
    """Sign bits in 32-bit words as array<bigint>; an exact zero counts as positive. Bit i of word w stands for component 32w + i."""
    v = _col(vec)

    def word(w):
        part = F.reverse(F.slice(v, w * 32 + 1, 32))
        return F.aggregate(part, F.lit(0).cast("bigint"), lambda bits, x: bits * 2 + F.when(x >= 0, 1).otherwise(0))

    return F.transform(F.sequence(F.lit(0), F.lit(-(-d // 32) - 1)), word)


def signs(vec) -> Column:
    """Components as +1.0 and -1.0; an exact zero counts as positive."""
    return F.transform(_col(vec), lambda x: F.when(x >= 0, F.lit(1.0)).otherwise(F.lit(-1.0)))


def hamming(a, b, words: int) -> Column:
    """Differing bits of two codes; unrolled over the known number of words, so it stays in generated code."""
    total = F.lit(0)
    for w in range(words):
        total = total + F.bit_count(F.get(_col(a), w).bitwiseXOR(F.get(_col(b), w)))
    return total


def register_sql(spark: SparkSession) -> None:
    """vec_dot, vec_norm, vec_normalize and hamming_words as SQL functions that the analyser inlines."""
    double = "ARRAY<DOUBLE>"
    spark.sql(
        f"CREATE OR REPLACE TEMPORARY FUNCTION vec_dot(a {double}, b {double}) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0.0D, (s, x) -> s + x)"
    )
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION vec_norm(a {double}) RETURNS DOUBLE RETURN sqrt(aggregate(a, 0.0D, (s, x) -> s + x * x))")
    spark.sql(
        f"CREATE OR REPLACE TEMPORARY FUNCTION vec_normalize(a {double}) RETURNS {double} RETURN transform(a, x -> x / sqrt(aggregate(a, 0.0D, (s, y) -> s + y * y)))"
    )
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION hamming_words(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS INT RETURN aggregate(zip_with(a, b, (x, y) -> bit_count(x ^ y)), 0, (s, x) -> s + x)"
    )
