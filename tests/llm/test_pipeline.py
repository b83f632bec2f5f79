"""The corpus pipeline, stage by stage, against brute-force versions of what each must do to its own input."""

from __future__ import annotations

import corpus_pipeline
from pyspark.sql import functions as F

from groupsearch.llm import common, queries, toxicity

from ..conftest import MEDIUM
from .test_operators import _ascii_shingles, _brute, _components, _shingles


def test_stages(spark):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "simhash_near_dedup", "suffix_array_dedup", "decontamination", "bpe"]
    work = common.Workspace(spark, "t")
    docs, kept = common.table(spark, MEDIUM, "documents"), [common.table(spark, MEDIUM, "documents")]
    for name, stage in corpus_pipeline.STAGES:
        docs = work.save(stage(spark, docs, MEDIUM), name)
        kept.append(docs)
    first, clean, single, cut, fair, coded = kept
    for d in (clean, single, cut, fair):
        assert d.columns == first.columns
    text = [{r.doc_id: r.text for r in d.collect()} for d in (first, clean, single, cut, fair)]

    labels = {r.doc_id: r.toxic for r in common.table(spark, MEDIUM, "labels").collect()}
    model = toxicity.fit(first, common.table(spark, MEDIUM, "labels"))
    rejected = {r.doc_id for r in toxicity.score_documents(first, model).where("predicted = 1").collect()}
    assert set(text[0]) - set(text[1]) == rejected and not any(labels.get(i) == 0 for i in rejected)

    groups = _components({i: _ascii_shingles(t) for i, t in text[1].items()})
    assert set(text[2]) == set(groups.values()) and len(text[2]) < len(text[1])

    want = _brute(list(text[2].items()), 100)
    for i, t in text[3].items():
        n, removed, _, _ = want[i]
        assert n - removed - 400 <= len(t.encode()) <= n - removed

    items = [_shingles(r.text) for r in common.table(spark, MEDIUM, "benchmark").collect()]
    leaks = {i for i, t in text[3].items() if any(len(s & _shingles(t)) >= 0.8 * len(s) for s in items)}
    assert set(text[3]) - set(text[4]) == leaks
    assert {r.doc_id for r in coded.collect()} == set(text[4])
    assert queries.pipeline(spark, MEDIUM).count() == len(text[4])


def test_stages_of_odd_rows(spark, tmp_path):
    """Nulls, empty texts, repeated rows, a very long text and clashing columns go through every stage; empty tables too."""
    long = " ".join(f"w{i}" for i in range(20_000))
    rows = [(1, None), (2, ""), (3, "one"), (4, "one"), (4, "one"), (5, long), (6, long), (None, "no id"), (None, "no id"), (7, "a" * 3000)]
    docs = spark.createDataFrame([(i, t, None, "s", None) for i, t in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    for name in ("labels", "benchmark"):
        common.table(spark, MEDIUM, name).write.parquet(f"{tmp_path}/{name}.parquet")
    for extra in ([], ["key", "fp", "u", "part", "__hash"]):
        now = docs
        for column in extra:
            now = now.withColumn(column, F.lit(1))
        now.write.mode("overwrite").parquet(f"{tmp_path}/documents.parquet")
        out = corpus_pipeline.run(spark, str(tmp_path)).collect()
        assert sorted((r.doc_id is None, r.doc_id or 0) for r in out) == [(False, 1), (False, 3), (False, 5), (False, 7), (True, 0), (True, 0)]
    docs.limit(0).write.mode("overwrite").parquet(f"{tmp_path}/documents.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_a_fit_gives_the_drivers_memory_back(spark, monkeypatch):
    from groupsearch.llm import toxicity

    called = []
    monkeypatch.setattr(toxicity, "give_back", lambda: called.append(1))
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("documents", "labels"))
    toxicity.fit(docs, labels)
    assert called


def test_a_saved_step_gives_the_jvms_memory_back(spark, monkeypatch):
    trimmed = []
    whole = common._trim_native_heap
    monkeypatch.setattr(common, "_trim_native_heap", lambda s: trimmed.append(whole(s)))
    jvm = spark.sparkContext._jvm
    runtime = jvm.java.lang.Runtime.getRuntime()
    work = common.Workspace(spark, "t")
    used = lambda: runtime.totalMemory() - runtime.freeMemory()
    while used() * 2.5 < runtime.maxMemory():
        jvm.java.lang.StringBuilder(64 << 20)
    assert work.save(spark.range(3), "rows").count() == 3
    assert used() * 3 < runtime.maxMemory()
    assert len(trimmed) == 1 and "native heap" in trimmed[0]
    work.delete()
