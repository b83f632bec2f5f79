"""SQL surface beyond scalar functions: representative aggregates and a table function that searches a group index on disk."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from . import kernels, theory


@pandas_udf(T.ArrayType(T.DoubleType()))
def pinv_rep(vectors: pd.Series) -> list[float]:
    """Aggregate: the minimum-norm representative of a group's vectors."""
    return kernels.pinv_rep(np.stack(vectors.to_list())).tolist()


@pandas_udf(T.ArrayType(T.DoubleType()))
def sum_rep(vectors: pd.Series) -> list[float]:
    return np.stack(vectors.to_list()).sum(0).tolist()


@pandas_udf(T.DoubleType())
def phi(x: pd.Series) -> pd.Series:
    return x.map(theory.phi)


def register(spark: SparkSession, path: str | None = None, tau: float = 0.5) -> None:
    """Registers pinv_rep, sum_rep and phi; with the folder of an index (see tables.write_index), group_search(query, k) as a table function.

    The function streams the representatives, batch by batch, and reads from the members only row groups of the units it opens, so
    neither the driver nor a worker holds the index. The folder must be one that executors can read.
    """
    for name, f in (("pinv_rep", pinv_rep), ("sum_rep", sum_rep), ("phi", phi)):
        spark.udf.register(name, f)
    if path is None:
        return

    @udtf(returnType="vec_id bigint, sim double")
    class GroupSearch:
        def __init__(self):
            import pyarrow.dataset as ds
            from pyarrow import fs

            store, root = fs.FileSystem.from_uri(path if "://" in path or path.startswith("file:") else f"file://{path}")
            self.reps, self.members = (ds.dataset(f"{root}/{name}", filesystem=store, format="parquet") for name in ("reps", "members"))
            self.unit = ds.field("unit_id")

        def eval(self, query: list, k: int):
            q = np.asarray(query, float)
            opened: list[int] = []
            for b in self.reps.to_batches(columns=["unit_id", "rep"]):
                if b.num_rows:
                    opened += b.column(0).to_numpy()[kernels.matrix(b.column(1)) @ q > tau].tolist()
            ids, sims = np.zeros(0, np.int64), np.zeros(0)
            for b in self.members.to_batches(columns=["vec_id", "vec"], filter=self.unit.isin(opened)) if opened else ():
                if b.num_rows:
                    ids, sims = np.concatenate([ids, b.column(0).to_numpy()]), np.concatenate([sims, kernels.matrix(b.column(1)) @ q])
                    best = np.lexsort((ids, -sims))[:k]
                    ids, sims = ids[best], sims[best]
            yield from zip(ids.tolist(), sims.tolist(), strict=True)

    spark.udtf.register("group_search", GroupSearch)
