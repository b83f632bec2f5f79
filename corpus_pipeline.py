"""The corpus pipeline: toxicity, near-dedup, substring dedup, decontamination, then token ids.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; all but the last return the columns of
documents. What a stage decides takes effect: rejected documents go, removed bytes leave the text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from groupsearch.llm import bpe, common, decontaminate, simhash, suffix_dedup, toxicity

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the weakly supervised classifier does not predict to be toxic."""
    model = toxicity.fit(docs, common.table(spark, sf_dir, "labels"))
    return toxicity.keep_clean(docs, model).select(COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The first document of each group of near copies; documents with a null id stay."""
    return simhash.without_copies(docs).select(COLUMNS)


def drop_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the bytes of strings of 100 bytes that start earlier; characters that lose a byte go whole."""
    return suffix_dedup.without_repeats(docs).select(COLUMNS)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    found = decontaminate.contained_items(docs, common.table(spark, sf_dir, "benchmark"))
    return decontaminate.drop_contaminated(docs, found).select(COLUMNS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every document that is left."""
    return bpe.encode_documents(docs, common.vocabulary("byte_bpe_50k.json"), keep_ids=False)


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash_near_dedup", drop_near_copies),
    ("suffix_array_dedup", drop_repeats),
    ("decontamination", drop_benchmark),
    ("bpe", encode),
]

#: A fitted classifier and token ids are beyond SQL; tests compare the stages with brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each result written and read again as the next one's input."""
    docs = common.table(spark, sf_dir, "documents")
    work = common.Workspace(spark, "pipeline")
    mine, last = list(common.Workspace.made), None
    for name, stage in STAGES[:-1]:
        docs = work.save(stage(spark, docs, sf_dir), name)
        common.clear_workspaces(*mine)  # what the stage's operators saved, and its input, are of no more use
        if last:
            work.drop(last)
        last = name
    return STAGES[-1][1](spark, docs, sf_dir)
