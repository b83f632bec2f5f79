"""Vectors from text, events and baskets, planted queries and generators."""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels

_WORD = re.compile(r"\w+")
#: Bytes of vectors in a batch that a task hands on.
OUT_BYTES = 4 << 20


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(r"[\p{L}\p{N}]+"), F.lit(0))


def html_to_text(html: Column) -> Column:
    """Text of a page: scripts, styles, comments and tags go, entities of the five basic kinds are resolved."""
    out = F.regexp_replace(F.coalesce(html, F.lit("")), r"(?is)<(script|style)[^>]*>.*?</(script|style)>|<!--.*?-->|<[^>]*>", " ")
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        out = F.replace(out, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(out, r"\s+", " "))


def hash_weights(df: DataFrame, id_col: str, text: Column, d: int) -> DataFrame:
    """id, pos, weight: signed hashing of words as sparse rows. The first 8 hex digits of a word's md5 give place and sign."""
    words = df.select(F.col(id_col), F.explode(tokens(text)).alias("w"))
    h = F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("bigint")
    placed = words.select(id_col, (h % d).alias("pos"), F.when(F.floor(h / d) % 2 == 0, 1).otherwise(-1).alias("s"))
    return placed.groupBy(id_col, "pos").agg(F.sum("s").alias("weight"))


def _hashed(items: list[str], memo: dict) -> list[int]:
    out = []
    for w in items:
        h = memo.get(w)
        if h is None:
            h = int(hashlib.md5(w.encode()).hexdigest()[:8], 16)
            if len(memo) < 500_000:
                memo[w] = h
        out.append(h)
    return out


def hash_vectors(df: DataFrame, id_col: str, text_col: str, d: int, kind: str = "word", keep: list[str] | None = None) -> DataFrame:
    """vec_id, vec and kept columns: unit-length hashed counts of words or of character trigrams; texts without any are left out.

    A map over rows in Arrow batches: dense vectors come without the shuffle that counting word by word would need.
    """
    keep = keep or []
    kinds = dict(df.dtypes)
    step = max(1, OUT_BYTES // (8 * d))  # rows of a batch that leaves a task

    def run(batches):
        memo: dict[str, int] = {}
        for b in (whole.slice(i, step) for whole in batches for i in range(0, max(whole.num_rows, 1), step)):
            rows, at = [], []
            for i, t in enumerate(b.column(1).to_pylist()):
                t = (t or "").lower()
                items = _WORD.findall(t) if kind == "word" else [t[j : j + 3] for j in range(len(t) - 2)]
                h = np.array(_hashed(items, memo), np.int64)
                v = np.bincount(h % d, 1.0 - 2.0 * (h // d % 2), d)
                n = np.linalg.norm(v)
                if n > 0:
                    rows.append(v / n)
                    at.append(i)
            kept = [b.column(2 + j).take(pa.array(at, pa.int64())) for j in range(len(keep))]
            x = kernels.vectors_column(np.stack(rows) if rows else np.zeros((0, d)))
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at, pa.int64())), x, *kept], ["vec_id", "vec", *keep])

    schema = ", ".join(["vec_id bigint", "vec array<double>", *(f"{c} {kinds[c]}" for c in keep)])
    tasks = df.sparkSession.sparkContext.defaultParallelism
    if 0 < len(df.inputFiles()) < tasks:  # a table of few files is spread first
        df = df.repartition(tasks)
    return df.select(F.col(id_col).cast("bigint"), text_col, *keep).mapInArrow(run, schema)


def containing_texts(docs: DataFrame, items: DataFrame, size: int = 24) -> DataFrame:
    """doc_id, item_id of the documents whose text contains an item's text; items shorter than ``size`` characters only match as a whole.

    An item is looked up by its first ``size`` characters among all such runs of a document, in one pass over its text; then the whole
    is compared. Tasks read the items from the shared folder, in blocks.
    """
    from ..sources import tables

    path = tables.save(items.where(F.col("text").isNotNull()).select("item_id", "text"), "items")[1]
    kinds = [dict(docs.dtypes)["doc_id"], dict(items.dtypes)["item_id"]]

    def run(batches):
        keyed: list[dict[str, list[int]]] = []
        blocks = []
        for block in tables.stored_blocks(path, 100_000):
            of: dict[str, list[int]] = {}
            for j, t in enumerate(block.column(1).to_pylist()):
                of.setdefault(t[:size], []).append(j)
            keyed.append(of)
            blocks.append(block)
        for b in batches:
            docs_at = []
            for of, block in zip(keyed, blocks, strict=True):
                known, passages = of.keys(), block.column(1)
                for i, t in enumerate(b.column(1).to_pylist()):
                    if t is None:
                        continue
                    runs = known & {t[j : j + size] for j in range(max(len(t) - size, 0) + 1)}
                    docs_at += [(i, block.column(0)[j]) for key in runs for j in of[key] if passages[j].as_py() in t]
            ids = b.column(0).take(pa.array([i for i, _ in docs_at], pa.int64()))
            yield pa.RecordBatch.from_arrays([ids, pa.array([j.as_py() for _, j in docs_at], blocks[0].column(0).type if blocks else pa.int64())], ["doc_id", "item_id"])

    tasks = docs.sparkSession.sparkContext.defaultParallelism
    if 0 < len(docs.inputFiles()) < tasks:
        docs = docs.repartition(tasks)
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kinds[0]}, item_id {kinds[1]}").distinct()


def broadcast_if_few(df: DataFrame, rows: int = 100_000) -> DataFrame:
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def user_profiles(events: DataFrame) -> DataFrame:
    """user_id, slot, n: counts over event type and hour of day; slot = 24 * type's place in the alphabet + hour."""
    kinds = events.select("event_type").distinct()
    places = kinds.select("event_type", (F.dense_rank().over(_order("event_type")) - 1).alias("place"))
    joined = events.join(F.broadcast(places), "event_type")
    slot = F.col("place") * 24 + F.hour("ts")
    return joined.groupBy("user_id", slot.alias("slot")).agg(F.count("*").alias("n"))


def _order(*columns):
    from pyspark.sql import Window

    return Window.orderBy(*columns)  # over the few event types only


def profile_vectors(events: DataFrame, types: int = 5) -> DataFrame:
    counts = user_profiles(events)
    m = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("slot", F.col("n").cast("double")))).alias("m"))
    v = F.transform(F.sequence(F.lit(0), F.lit(24 * types - 1)), lambda i: F.coalesce(F.element_at("m", i.cast("int")), F.lit(0.0)))
    dense = m.select(F.col("user_id").cast("bigint").alias("vec_id"), v.alias("vec"))
    size = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x * x))
    return dense.select("vec_id", F.transform("vec", lambda x: x / size).alias("vec"))


def basket_vectors(lineitem: DataFrame, orders: DataFrame, part: DataFrame, key: str = "o_custkey", d: int = 128) -> DataFrame:
    """Per customer or order: hashed counts of brand and type of the parts bought."""
    h = F.conv(F.substring(F.md5(F.concat_ws("|", "p_brand", "p_type")), 1, 8), 16, 10).cast("bigint")
    bought = lineitem.join(part.select("p_partkey", (h % d).cast("int").alias("pos"), F.when(F.floor(h / d) % 2 == 0, 1.0).otherwise(-1.0).alias("s")), F.col("l_partkey") == F.col("p_partkey"))
    rows = bought.join(orders.select("o_orderkey", key), F.col("l_orderkey") == F.col("o_orderkey"))
    v = F.array(*[F.sum(F.when(F.col("pos") == i, F.col("s")).otherwise(0.0)) for i in range(d)])
    dense = rows.groupBy(F.col(key).cast("bigint").alias("vec_id")).agg(v.alias("vec"))
    size = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x * x))
    return dense.where(size > 0).select("vec_id", F.transform("vec", lambda x: x / size).alias("vec"))


def plant_queries(vectors: DataFrame, alpha: float) -> DataFrame:
    """query_id, qvec, src_id, alpha: every vector mixed with one orthogonal to it, so that their product is alpha.

    The orthogonal part is the vector reversed with alternating signs, for an even number of components.
    """
    beta = (1 - alpha * alpha) ** 0.5
    n = F.size("vec")
    q = F.transform("vec", lambda x, i: x * alpha + F.get(F.col("vec"), n - 1 - i) * F.when(i % 2 == 0, beta).otherwise(-beta))
    return vectors.select(F.col("vec_id").alias("query_id"), q.alias("qvec"), F.col("vec_id").alias("src_id"), F.lit(float(alpha)).alias("alpha"))


def every_50th(vectors: DataFrame, vec: str = "vec") -> DataFrame:
    """The stated query set of searches: rows whose id is divisible by 50."""
    return vectors.where(F.col("vec_id") % 50 == 0).select(F.col("vec_id").alias("query_id"), F.col(vec).alias("qvec"))


def holdout(vectors: DataFrame, mod: int = 10, rem: int = 0) -> tuple[DataFrame, DataFrame]:
    """(database, queries unrelated to it)."""
    mine = F.pmod(F.col("vec_id"), F.lit(mod)) == rem
    return vectors.where(~mine), vectors.where(mine).select(F.col("vec_id").alias("query_id"), F.col("vec").alias("qvec"))


def _generated(spark: SparkSession, n: int, make, parts: int | None = None) -> DataFrame:
    def run(batches):
        for b in batches:
            ids = b.column(0).to_numpy()
            yield pa.RecordBatch.from_arrays([b.column(0), kernels.vectors_column(np.stack([make(int(i)) for i in ids]) if len(ids) else np.zeros((0, 1)))], ["vec_id", "vec"])

    return spark.range(0, n, 1, parts or max(1, min(200, n // 2000))).select(F.col("id").alias("vec_id")).mapInArrow(run, "vec_id bigint, vec array<double>")


def sphere(spark: SparkSession, n: int, d: int, seed: int = 0) -> DataFrame:
    """Uniform unit vectors; the seed and the id, not the partition, decide each."""

    def make(i: int) -> np.ndarray:
        x = np.random.default_rng([seed, i]).standard_normal(d)
        return x / np.linalg.norm(x)

    return _generated(spark, n, make)


def cap_point(rng: np.random.Generator, d: int, eta: float) -> np.ndarray:
    """A uniform point on the cap around the first axis, by rejection from the law of the cosine on a fine grid."""
    t = np.linspace(eta, 1, 4097)
    mid = (t[1:] + t[:-1]) / 2
    log = (d - 3) / 2 * np.log1p(-mid * mid)
    p = np.exp(log - log.max())
    c = np.cumsum(p / p.sum())
    j = int(np.searchsorted(c, rng.random()))
    cos = t[j] + (t[1] - t[0]) * rng.random()
    rest = rng.standard_normal(d - 1)
    return np.concatenate([[cos], rest / np.linalg.norm(rest) * np.sqrt(max(0.0, 1 - cos * cos))])


def onto_cap(x: np.ndarray, eta: float) -> np.ndarray:
    """Unit vectors moved onto the cap around the first axis: the cosine to it keeps its quantile, the rest its direction.

    Evenly spread vectors become evenly spread on the cap.
    """
    d = x.shape[1]
    x = x / np.linalg.norm(x, axis=1, keepdims=True)

    def law(lo: float) -> tuple[np.ndarray, np.ndarray]:
        t = np.linspace(lo, 1, 8193)
        mid = (t[1:] + t[:-1]) / 2
        log = (d - 3) / 2 * np.log1p(-mid * mid)
        p = np.exp(log - log.max())
        return t, np.concatenate([[0], np.cumsum(p / p.sum())])

    t, c = law(-1.0)
    on, share = law(eta)
    cos = np.interp(np.interp(x[:, 0], t, c), share, on)
    size = np.linalg.norm(x[:, 1:], axis=1)
    return np.column_stack([cos, x[:, 1:] * (np.sqrt(np.maximum(0, 1 - cos * cos)) / np.where(size > 0, size, 1))[:, None]])


def cap(spark: SparkSession, n: int, d: int, eta: float, seed: int = 0) -> DataFrame:
    return _generated(spark, n, lambda i: cap_point(np.random.default_rng([seed, i]), d, eta))
