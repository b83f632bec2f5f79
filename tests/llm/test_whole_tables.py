"""Queries without SQL on a whole table, each against a plain version of what it must return."""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pytest

from groupsearch.llm import common, queries, simhash

from ..conftest import MEDIUM
from .test_operators import _brute


@pytest.fixture(scope="module")
def texts(spark):
    return sorted((r.doc_id, r.text) for r in common.table(spark, MEDIUM, "documents").select("doc_id", "text").collect())


def test_op4(spark, texts):
    fp = {i: simhash.fingerprint((t or "").encode(), 3) for i, t in texts}
    ids, bits = np.array(list(fp)), np.array(list(fp.values()), np.uint64)
    root = ids.copy()
    for i in range(len(ids)):
        near = np.flatnonzero(np.bitwise_count(bits ^ bits[i]) <= 2)
        root[np.isin(root, root[near])] = root[near].min()
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in queries.op4_simhash(spark, MEDIUM).collect()}
    assert got == {i: (f"{fp[i]:016x}", c) for i, c in zip(ids.tolist(), root.tolist(), strict=True)}


def test_op5(spark, texts):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(common.vocabulary("byte_bpe_50k.json"))
    got = {r.doc_id: (r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in queries.op5_bpe(spark, MEDIUM).collect()}
    for i, t in texts:
        ids = library.encode(t or "", add_special_tokens=False).ids
        decoded = library.decode(ids, skip_special_tokens=False)
        assert got[i] == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest())
    assert len(got) == len(texts)


def test_op8(spark, texts):
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in queries.op8_suffix_dedup(spark, MEDIUM).collect()}
    assert got == _brute(texts, 100)


def test_op9(spark, texts):
    from tokenizers import Tokenizer

    library, start = Tokenizer.from_file(common.vocabulary("word_bpe_49k.json")), 0
    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in queries.op9_token_files(spark, MEDIUM).collect()}
    for i, t in texts:
        ids = [*library.encode(t or "", add_special_tokens=False).ids, 1]
        assert got[i] == (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    assert len(got) == len(texts)
