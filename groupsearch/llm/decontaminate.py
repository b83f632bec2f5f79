"""Benchmark decontamination: size-partitioned MinHash containment search, verified by exact shingle containment.

One hash of each five-word shingle serves all hash functions: a document of the size partition with b bits has 2**(b + e) bins, the
ranges of the hash's high bits, and the least hash of each bin is kept. A test item is binned in the same way for each partition. If a
document holds enough of an item's shingles, one of them is, but for a chance set by e, the least of its bin on both sides,
however long the document: bins grow with the partition, so an item in a long text is found as surely as in a short one.
Sorting puts the least of each bin first in its run, so all of it is array expressions and one hash join.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Workspace

#: Words of a shingle, containment that counts, chance that a sufficient overlap is overlooked, most rows that are broadcast.
WORDS, CONTAINMENT, OVERLOOKED, BROADCAST_ROWS = 5, 0.8, 1e-7, 1_000_000


def words_of(text: Column) -> Column:
    """Runs of letters and digits, lower-cased."""
    return F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), "")


def _starts(words: Column, n: int) -> Column:
    size = F.size(words)
    return F.when(size > 0, F.sequence(F.lit(0), F.greatest(size - n, F.lit(0)))).otherwise(F.array().cast("array<int>"))


def shingle_hashes(words: Column, n: int = WORDS) -> Column:
    """Sorted 64-bit hashes of all runs of n words, or of the whole sequence where it has fewer."""
    return F.sort_array(F.transform(_starts(words, n), lambda i: F.xxhash64(*[F.get(words, i + k) for k in range(n)])))


def shingle_texts(words: Column, n: int = WORDS) -> Column:
    return F.array_distinct(F.transform(_starts(words, n), lambda i: F.array_join(F.slice(words, i + 1, n), " ")))


def _least_of_bins(hashes: Column, bits: Column) -> Column:
    """Of sorted hashes those that are the first in their range of the top so many bits."""
    drop = F.lit(64) - bits

    def first(x, i):
        return (i == 0) | (F.call_function("shiftright", x, drop) != F.call_function("shiftright", F.get(hashes, i - 1), drop))

    return F.filter(hashes, first)


def extra_bits(smallest: int, containment: float = CONTAINMENT, overlooked: float = OVERLOOKED) -> int:
    """Bits e, so that of the shingles a document must share with an item of so many, all fail to be least of their bin that rarely.

    With at most 2**-e shingles a bin, one fails with a chance of about 2**-e / 2.
    """
    shared = max(1, math.ceil(containment * smallest))
    e = 0
    while (2.0**-e / 2) ** shared > overlooked:
        e += 1
    return e


def contained_items(
    docs: DataFrame, items: DataFrame, words: int = WORDS, containment: float = CONTAINMENT, id_col: str = "doc_id", item_col: str = "item_id"
) -> DataFrame:
    """doc_id, item_id, n_shared, n_item, containment of every item whose distinct shingles a document holds to that share or more.

    Texts are cut into lower-cased runs of letters and digits. An item of fewer words than a shingle is one shingle, which only a
    text of just these words holds; null texts and those without words hold nothing and are held by nothing. Of rows that share an
    id the best counts; rows with a null id take no part; an empty table gives no rows; other columns are ignored.

    Documents are read twice, never shuffled: once for candidates, once to verify those of them that have any. Items are broadcast
    up to BROADCAST_ROWS shingles, candidates up to as many rows; beyond, the joins shuffle.
    """
    spark = docs.sparkSession
    work = Workspace(spark, "decontaminate")
    texts = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).alias("doc_id"), F.col("text").cast("string").alias("text"))
    tests = items.where(F.col(item_col).isNotNull()).select(F.col(item_col).alias("item_id"), words_of(F.col("text").cast("string")).alias("w"))
    tests = work.save(tests.where(F.size("w") > 0).select("item_id", shingle_texts(F.col("w"), words).alias("s"), shingle_hashes(F.col("w"), words).alias("h")).distinct(), "items")
    size = tests.agg(F.coalesce(F.sum(F.size("s")), F.lit(0)).alias("n"), F.coalesce(F.min(F.size("s")), F.lit(1)).alias("least")).first()
    e = extra_bits(size.least, containment)
    # an item's hash is least of its bin from some number of bits on: the first at which its bin parts from the next smaller hash
    own = tests.select("item_id", F.array_distinct("h").alias("h")).select("item_id", "h", F.posexplode("h").alias("i", "x"))
    below = F.call_function("try_element_at", F.col("h"), F.when(F.col("i") > 0, F.col("i")).otherwise(F.lit(None).cast("int")))
    shared_bits = F.lit(64) - F.length(F.bin(F.col("x").bitwiseXOR(below)))
    keys = own.select(F.col("x").alias("key"), "item_id", F.when(below.isNull(), F.lit(0)).otherwise(shared_bits + 1).alias("from_bits")).distinct()

    # one column a step: an expression that a lambda refers to is then evaluated once a row, not once an element
    hashed = texts.select("doc_id", words_of(F.col("text")).alias("w")).select("doc_id", shingle_hashes(F.col("w"), words).alias("h"))
    bits = F.least(F.length(F.bin(F.size("h").cast("bigint"))) + F.lit(e), F.lit(63))
    sketch = hashed.select("doc_id", bits.alias("bits"), "h").select("doc_id", "bits", F.explode(_least_of_bins(F.col("h"), F.col("bits"))).alias("key"))
    small = size.n <= BROADCAST_ROWS
    met = sketch.join(F.broadcast(keys) if small else keys, "key").where("bits >= from_bits")
    found = work.save(met.select("doc_id", "item_id").distinct(), "candidates")

    by_doc = found.groupBy("doc_id").agg(F.collect_list("item_id").alias("items"))
    few = found.count() <= BROADCAST_ROWS
    checked = texts.join(F.broadcast(by_doc) if few else by_doc, "doc_id").select("doc_id", "items", words_of(F.col("text")).alias("w"))
    checked = checked.select("doc_id", "items", shingle_texts(F.col("w"), words).alias("d"))
    pairs = checked.select("doc_id", "d", F.explode("items").alias("item_id")).join(F.broadcast(tests.select("item_id", "s")) if small else tests.select("item_id", "s"), "item_id")
    judged = pairs.select("doc_id", "item_id", F.size(F.array_intersect("d", "s")).cast("bigint").alias("n_shared"), F.size("s").cast("bigint").alias("n_item"))
    judged = judged.withColumn("containment", F.col("n_shared") / F.col("n_item")).where(F.col("containment") >= containment)
    best = judged.groupBy("doc_id", "item_id").agg(F.max(F.struct("containment", "n_shared", "n_item")).alias("b"))
    return best.select("doc_id", "item_id", "b.n_shared", "b.n_item", "b.containment")


def drop_contaminated(docs: DataFrame, found: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The documents that hold no test item; rows with a null id stay."""
    ids = found.select(F.col("doc_id").alias("__held")).distinct()
    few = ids.count() <= BROADCAST_ROWS
    return docs.join(F.broadcast(ids) if few else ids, docs[id_col] == F.col("__held"), "left_anti")
