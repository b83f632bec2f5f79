"""Training-data operators on small tables: SQL, brute force, round trips and the odd inputs their docstrings define."""

from __future__ import annotations

import hashlib
import random
import re
import zlib
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from groupsearch.llm import bpe, common, components, decontaminate, licenses, queries, simhash, suffix_dedup, token_files, topk, toxicity, url_filter, warc
from groupsearch.llm.components import connected_components

from ..conftest import MEDIUM, SMALL

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


@pytest.fixture(scope="module")
def odd(spark):
    """Null, empty, blank, repeated and very long texts, equal ids, a null id, and columns with clashing names."""
    long = " ".join(f"w{i}" for i in range(30_000))
    rows = [(1, None), (2, ""), (3, " \n\t "), (4, "one"), (5, "one"), (5, "one"), (6, long), (7, long), (8, "wörter Ünd 漢字 🎉"), (None, "no id at all"), (9, "a" * 5000)]
    out = spark.createDataFrame([(i, t, "en", "s", None) for i, t in rows], DOCS)
    for clash in ("key", "fp", "row", "h", "part", "start", "items", "samples", "keys"):
        out = out.withColumn(clash, F.lit(1))
    return out


@pytest.fixture(scope="module")
def none(spark, odd):
    return odd.limit(0)


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_same_rows_as_sql(name, spark, same_as_sql):
    assert same_as_sql(queries.queries()[name], queries.oracle_sql()[name], spark, MEDIUM) > 0


def test_workspaces_are_deleted(spark):
    import os

    a, b = common.Workspace(spark, "t"), common.Workspace(spark, "t")
    held = b.save(spark.range(3).toDF("doc_id"), "x")
    a.save(spark.range(3).toDF("doc_id"), "x")
    common.clear_workspaces(b)
    assert held.count() == 3 and not os.path.exists(a.path.removeprefix("file://")) and os.path.exists(b.path.removeprefix("file://"))


# op1 -------------------------------------------------------------------------------------------------------------------------


def _judge(host, path, rules):
    fits = [r for r in rules if (host == r[0] or host.endswith("." + r[0])) and path.startswith(r[1])]
    return max(fits, key=lambda r: (len(r[0] + r[1]), r[0] + r[1]), default=None)


@pytest.mark.parametrize("few,limit", [(url_filter.FEW_RULES, url_filter.BROADCAST_ROWS), (0, url_filter.BROADCAST_ROWS), (0, 0)])
def test_urls_against_brute_force(spark, monkeypatch, few, limit):
    monkeypatch.setattr(url_filter, "FEW_RULES", few)
    monkeypatch.setattr(url_filter, "BROADCAST_ROWS", limit)
    rng = random.Random(1)
    hosts = [".".join(rng.choices(["a", "b", "example", "com", "net"], k=rng.randint(1, 4))) for _ in range(60)]
    rules = list({(rng.choice(hosts), rng.choice(["/", "/x", "/x/y", ""])): None for _ in range(40)})
    urls = [f"http{rng.choice(['', 's'])}://{rng.choice(hosts).upper()}{rng.choice(['', '/', '/x/y?q', '/x#z', '?a'])}" for _ in range(300)] + [None, "", "nothing", "://", "a://?x"]
    pages = spark.createDataFrame([(i // 2, u, "clash") for i, u in enumerate(urls)], "page_id bigint, url string, key string").withColumn("block", F.lit(1)).withColumn("listed", F.lit("x"))
    ruled = spark.createDataFrame([(h, p, "block" if i % 3 else "allow") for i, (h, p) in enumerate(rules)] + [(None, "/", "block"), ("x", None, "allow")], "host string, path string, verdict string")
    # the list holds other spellings of some urls
    noted = [u.replace("https://", "http://user@").replace("/", "/", 1) + "#z" for u in urls[:300:4]] + [None, "junk"]
    listed = spark.createDataFrame([(u,) for u in noted], "url string")
    got = url_filter.judge_urls(pages, ruled, listed).collect()
    assert len(got) == len(urls)
    want, known = [], {_plain(u) for u in noted if u and "://" in u}
    for i, u in enumerate(urls):
        rest = (u or "").partition("://")[2] if u and "://" in u else ""
        host = rest.split("/")[0].split("?")[0].split("#")[0]
        path = rest[len(host) :].split("?")[0].split("#")[0]
        best = _judge(host.lower(), path, rules) if host else None
        is_listed = bool(u) and "://" in u and u != "://" and _plain(u) in known
        verdict = ("block" if rules.index(best) % 3 else "allow") if best else "block" if is_listed else "allow"
        want.append((i // 2, host.lower(), path, best and best[0] + best[1], verdict, is_listed))
    assert sorted(map(str, [tuple(r) for r in got])) == sorted(map(str, want))
    assert {w[4] for w in want if w[3] is None} == {"block", "allow"}
    none = url_filter.judge_urls(pages, ruled.limit(0), listed.limit(0))
    assert none.where("verdict <> 'allow' or listed").count() == 0 and none.count() == len(urls)
    assert url_filter.judge_urls(pages.limit(0), ruled, listed).count() == 0


def _plain(url):
    """The canonical form of the test's urls."""
    rest = url.partition("://")[2].split("#")[0].rpartition("@")[2]
    host, _, query = rest.partition("?")
    host, slash, path = host.partition("/")
    return host.lower() + "/" + path + (f"?{query}" if query else "")


def test_bloom_filter_has_no_false_negatives(spark):
    keys = spark.range(2000).select(F.concat(F.lit("k"), "id").alias("key"))
    blocks, n = url_filter.bloom_blocks(keys, 2000)
    tried = keys.unionByName(spark.range(20_000).select(F.concat(F.lit("z"), "id").alias("key")))
    out = tried.withColumn("block", url_filter._block(F.col("key"), n)).join(blocks, "block")
    for i, m in enumerate(url_filter._masks(F.col("key"))):
        out = out.where(F.col(f"w{i}").bitwiseAND(m) == m)
    assert out.where("key like 'k%'").count() == 2000
    assert out.where("key like 'z%'").count() < 400


# op2 -------------------------------------------------------------------------------------------------------------------------


def test_top_k_against_brute_force_with_ties(spark, monkeypatch):
    monkeypatch.setattr(topk, "LEAF", 8)
    rng = np.random.default_rng(0)
    x = rng.integers(-3, 4, (400, 4)) / 256
    x[100:250] = x[100]  # many equal vectors
    rows = [(i, v.tolist(), "c") for i, v in enumerate(x)]
    rows += [(900, None, ""), (901, [None, 1.0, 0.0, 0.0], ""), (902, [float("nan")] * 4, ""), (903, [float("inf")] * 4, ""), (904, [], ""), (905, [1.0] * 5, ""), (None, [1.0] * 4, ""), (5, x[5].tolist(), "again")]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>, v string").withColumn("query", F.lit(1)).withColumn("score", F.lit(1))
    v = topk.integer_vectors(df, "vec_id", "embedding")
    got = {}
    for r in topk.exact_top_k(v, v.where("vec_id % 50 = 0"), 5, block=3).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    z = np.floor(256 * x.astype(np.float32).astype(float)).astype(int)
    for query in range(0, 400, 50):
        best = sorted((-int(z[query] @ z[i]), i) for i in range(400) if i != query)[:5]
        assert sorted(got[query]) == [(n + 1, i, -s) for n, (s, i) in enumerate(best)]
    assert set(got) == set(range(0, 400, 50))
    few = v.where("vec_id < 3")
    assert topk.exact_top_k(few, few.where("vec_id = 0"), 5).count() == 2
    assert topk.exact_top_k(v.limit(0), v.limit(0), 5).count() == topk.exact_top_k(v, v.limit(0), 5).count() == 0


def test_unequal_vectors_with_one_id_all_take_part(spark):
    rows = [(1, [1.0, 0.0]), (2, [3.0, 0.0]), (2, [5.0, 0.0]), (3, [4.0, 0.0]), (1, [-1.0, 0.0])]
    v = spark.createDataFrame(rows, "vec_id bigint, v array<double>")
    got = topk.exact_top_k(v, v.where("vec_id = 1"), 3).collect()
    assert sorted((r.rank, r.vec_id, r.score) for r in got if r.score > 0) == [(1, 2, 5), (2, 3, 4), (3, 2, 3)]
    assert sorted((r.rank, r.vec_id, r.score) for r in got if r.score < 0) == [(1, 2, -3), (2, 3, -4), (3, 2, -5)]


def test_trees_leave_nodes_out():
    rng = np.random.default_rng(3)
    centres = rng.integers(-200, 200, (40, 8))
    x = (centres[rng.integers(0, 40, 8000)] + rng.integers(-9, 10, (8000, 8))).astype(float)
    ids, tree = np.arange(8000), topk.BallTree(np.arange(8000), x, 64)
    at, found, score = tree.search(ids[:50], x[:50], np.full(50, -np.inf), 5)
    assert tree.evaluated < 0.3 * 50 * 8000
    for i in range(50):
        s = x @ x[i]
        s[i] = -np.inf
        want = np.lexsort((ids, -s))[:5]
        assert found[at == i].tolist() == want.tolist() and score[at == i].tolist() == s[want].tolist()


# op3 -------------------------------------------------------------------------------------------------------------------------


def _shingles(text):
    import regex

    w = regex.findall(r"[\p{L}\p{N}]+", (text or "").lower())
    return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


@pytest.mark.parametrize("limit", [decontaminate.BROADCAST_ROWS, 0])
def test_containment_against_brute_force(spark, odd, none, monkeypatch, limit):
    monkeypatch.setattr(decontaminate, "BROADCAST_ROWS", limit)
    rng = random.Random(2)
    words = [f"x{i}" for i in range(60)]
    items = [(i, " ".join(rng.choices(words, k=rng.randint(1, 30)))) for i in range(30)] + [(99, None), (98, ""), (None, "x1 x2")]
    texts = []
    for i in range(80):
        t = rng.choices(words, k=rng.randint(0, 300))
        item = rng.choice(items[:30])[1].split()
        if i % 3:
            if len(item) > 8 and i % 2:
                item[rng.randrange(len(item))] = "changed"
            at = rng.randint(0, len(t))
            t[at:at] = item
        texts.append((i, rng.choice([" ", ", ", "\n"]).join(t)))
    docs = spark.createDataFrame(texts, "doc_id bigint, text string").unionByName(odd.select("doc_id", "text").withColumn("doc_id", F.col("doc_id") + 1000))
    tests = spark.createDataFrame(items, "item_id bigint, text string")
    got = {(r.doc_id, r.item_id): (r.n_shared, r.n_item) for r in decontaminate.contained_items(docs, tests).collect()}
    want = {}
    for r in docs.collect():
        for i, item in items:
            s = _shingles(item)
            if i is not None and r.doc_id is not None and s and len(s & _shingles(r.text)) >= 0.8 * len(s):
                want[r.doc_id, i] = (len(s & _shingles(r.text)), len(s))
    assert got == want and len(want) > 20
    assert decontaminate.contained_items(none, tests).count() == 0
    assert decontaminate.contained_items(docs, tests.limit(0)).count() == 0


# op4 -------------------------------------------------------------------------------------------------------------------------


def _groups(fp, bits=2):
    parent = {x: x for x in fp}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in fp:
        for b in fp:
            if a < b and (a ^ b).bit_count() <= bits:
                parent[max(find(a), find(b))] = min(find(a), find(b))
    return {x: find(x) for x in fp}


@pytest.mark.parametrize("pairwise", [1, 64])
def test_links_by_rings_and_by_balls(spark, pairwise):
    rng = random.Random(3)
    fp = {rng.getrandbits(64) for _ in range(40)}
    for x in list(fp):
        for _ in range(rng.randint(0, 12)):  # chains of near fingerprints, and others just too far
            x ^= sum(1 << b for b in rng.sample(range(64), rng.randint(1, 3)))
            fp.add(x)
    signed = {x - (1 << 64) if x >> 63 else x: x for x in fp}
    df = spark.createDataFrame([(s,) for s in signed], "fp bigint")
    work = common.Workspace(spark, "t")
    links = simhash.fingerprint_links(df, work, pairwise=pairwise)
    got = {r.node: r.root for r in connected_components(links, work).collect()}
    want = _groups(sorted(fp))
    for s, x in signed.items():
        mates = {t for t, y in signed.items() if want[y] == want[x]}
        assert got.get(s, s) == min(mates) and (s == min(mates)) == (s not in got)


def test_fingerprints_follow_their_definition():
    import xxhash

    for text in (b"", b"One", b"a B", b"the quick brown fox\tjumps over\n\x0bthe lazy dog"):
        w = text.lower().split()
        parts = [b" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))] if w else []
        h = [xxhash.xxh64_intdigest(p, 42) for p in parts]
        want = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
        assert simhash.fingerprint(text, 3) == want


def test_near_duplicates_of_odd_rows(spark, odd, none):
    rows = simhash.near_duplicates(odd).collect()
    assert len(rows) == odd.count()
    of = {r.doc_id: r for r in rows}
    assert of[1].fingerprint == of[2].fingerprint == of[3].fingerprint == "0" * 16
    assert {of[i].component_id for i in (1, 2, 3)} == {1} and of[5].component_id == 4 and of[7].component_id == 6
    assert simhash.near_duplicates(none).count() == 0
    near = {r.doc_id: r.component_id for r in simhash.near_copies(odd).collect()}
    assert near[7] == 6 and near[5] == 4 and None not in near


def _ascii_shingles(text):
    w = (text or "").encode().lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def _components(sets, similarity=0.8):
    """The smallest id reachable by pairs of that similarity, by comparing all."""
    root = {i: i for i in sets}
    for i in sorted(sets):
        for j in sorted(sets):
            if j < i and len(sets[i] & sets[j]) >= similarity * len(sets[i] | sets[j]) and root[i] != root[j]:
                a, b = sorted((root[i], root[j]))
                root = {k: a if r == b else r for k, r in root.items()}
    return root


def _edited_texts(seed, n):
    """Originals of 5 to 400 words, half of them behind a passage that many share, and chains of copies with ever more edits."""
    rng = random.Random(seed)
    words, rows = [f"v{i}" for i in range(5000)], []
    passages = [rng.choices(words, k=60) for _ in range(2)]
    for _ in range(n):
        t = rng.choices(words, k=rng.choice([5, 12, 20, 25, 30, 45, 60, 120, 400]))
        if rng.random() < 0.5:
            t = rng.choice(passages) + t
        for _ in range(rng.randint(1, 6)):
            rows.append(" ".join(t))
            t = list(t)
            for _ in range(max(1, len(t) * rng.randint(0, 3) // 60)):
                t[rng.randrange(len(t))] = rng.choice(words)
    rng.shuffle(rows)
    return list(enumerate(rows))


@pytest.mark.parametrize("pairs,seed", [(simhash.PAIRS_OF_KEY, 4), (0, 5)])
def test_near_copies_against_brute_force(spark, monkeypatch, pairs, seed):
    monkeypatch.setattr(simhash, "PAIRS_OF_KEY", pairs)
    monkeypatch.setattr(simhash, "SALTS", 2)
    rows = _edited_texts(seed, 120)
    want = _components({i: _ascii_shingles(t) for i, t in rows})
    got = {r.doc_id: r.component_id for r in simhash.near_copies(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert got == want and len(set(want.values())) < len(rows) - 50


def test_keys_of_similar_sets_meet_as_often_as_stated():
    rng = np.random.default_rng(6)
    bands, lost, tried = simhash.bands_for(4, 0.8, 0.05), 0, 0
    for n in (12, 40, 300):
        for _ in range(500):
            h = rng.integers(0, 1 << 64, n * 10 // 9, dtype=np.uint64)
            k = len(h) - n  # each set lacks some of the other's: similarity 0.8
            a, b = simhash.band_keys(h[k:], 4, bands), simhash.band_keys(h[: len(h) - k], 4, bands)
            if (len(h) - 2 * k) / len(h) >= 0.8:
                tried, lost = tried + 1, lost + (not np.intersect1d(a, b).size)
    assert tried >= 1000 and lost / tried < 0.07


def test_few_edges_are_joined_up_in_one_task(spark, monkeypatch):
    """The same components as by rounds, without a round of shuffles for each step of a long path."""
    edges = [(i, i + 1) for i in range(200)] + [(i, 1000 + i % 7) for i in range(1001, 1400)] + [(5, 5), (-3, -9), (-9, -4), (-3, -9)]
    df, context = spark.createDataFrame(edges, "u bigint, v bigint"), spark.sparkContext
    context.setJobGroup("few-edges", "")
    found = [{(r.node, r.root) for r in connected_components(df, common.Workspace(spark, "t")).collect()}]
    jobs = len(context.statusTracker().getJobIdsForGroup("few-edges"))
    context.setLocalProperty("spark.jobGroup.id", None)
    monkeypatch.setattr(components, "FEW_EDGES", 0)
    found.append({(r.node, r.root) for r in connected_components(df, common.Workspace(spark, "t")).collect()})
    assert found[0] == found[1] and (200, 0) in found[0] and (-3, -9) in found[0] and jobs <= 8


def test_near_copies_keep_what_is_still_read(spark, odd):
    """Of the tables that the search saved, only the rows and the last links are left."""
    before = len(common.Workspace.made)
    simhash.near_copies(odd).count()
    search = next(w for w in common.Workspace.made[before:] if "/near-copies-" in w.path and "-roots-" not in w.path and "-docs-" not in w.path)
    left = {re.sub(r"-\d+$", "", f.name) for f in Path(search.path.removeprefix("file://")).iterdir() if not f.name.startswith(".")}
    assert {"rows", "links"} <= left and not left & {"pairs", "ids", "held", "likely", "counts", "several", "placed", "shingles", "common"}


def test_rows_without_copies(spark, odd, none):
    out = simhash.without_copies(odd)
    assert out.columns == odd.columns and [r.doc_id for r in out.orderBy("doc_id").collect()] == [None, 1, 4, 6, 8, 9]
    two = spark.createDataFrame([(None, "a b"), (None, "a b"), (3, "x y"), (3, "x y"), (3, "z w"), (4, "x y")], "doc_id bigint, text string")
    assert sorted(map(str, (tuple(r) for r in simhash.without_copies(two).collect()))) == ["(3, 'x y')", "(3, 'z w')", "(None, 'a b')", "(None, 'a b')"]
    assert simhash.without_copies(none).count() == 0


def test_components_of_a_long_path_and_a_star(spark):
    edges = [(i, i + 1) for i in range(60)] + [(1000, i) for i in range(1001, 1200)] + [(5, 5)]
    random.Random(5).shuffle(edges)
    got = connected_components(spark.createDataFrame(edges, "u bigint, v bigint"), common.Workspace(spark, "t")).collect()
    assert {r.node: r.root for r in got} == {**{i: 0 for i in range(1, 61)}, **{i: 1000 for i in range(1001, 1200)}}
    assert connected_components(spark.createDataFrame([], "u bigint, v bigint"), common.Workspace(spark, "t")).count() == 0


# op5 and op9 -------------------------------------------------------------------------------------------------------------------

ALPHABET = [*"aB c's'll 12  \n\t\r\x1c\x85\xa0\u2028\u3000éßĞİıΣσ漢🎉.,!$%", "<|endoftext|>", "<|StartOfText|>", " hello", "e\u0301", "'re", "\n\n"]


def _texts(n, seed):
    rng = random.Random(seed)
    return ["".join(rng.choices(ALPHABET, k=rng.randint(0, 40))) for _ in range(n)]


def test_bpe_equals_the_library():
    from tokenizers import Tokenizer

    path = common.vocabulary("byte_bpe_50k.json")
    library, mine = Tokenizer.from_file(path), bpe.ByteBPE(path, cache=50)
    for t in [*_texts(3000, 6), "a" * 3000, "ab" * 2000, "é" * 999]:
        ids = library.encode(t, add_special_tokens=False).ids
        got = mine.encode(t)
        assert np.frombuffer(got, "<u4").tolist() == ids
        assert mine.decode(got) == library.decode(ids, skip_special_tokens=False)


def test_merges_in_order_of_rank_then_place():
    rules = {(1, 1): 0, (2, 1): 1, (2, 2): 2}, [2, 3, 4]
    assert bpe.merge_symbols([1] * 5, *rules) == [2, 3]
    assert bpe.merge_symbols([1, 1, 1, 1], *rules) == [4]
    assert bpe.merge_symbols([], *rules) == [] and bpe.merge_symbols([1], *rules) == [1] and bpe.merge_symbols([1, 9], *rules) == [1, 9]


def test_bpe_of_odd_rows(spark, odd, none):
    out = bpe.encode_documents(odd, common.vocabulary("byte_bpe_50k.json")).collect()
    assert len(out) == odd.count()
    texts = {r.doc_id: r.text or "" for r in odd.collect()}
    assert all(r.decoded == texts[r.doc_id] and r.decoded_sha256 == hashlib.sha256(texts[r.doc_id].encode()).hexdigest() for r in out)
    assert bpe.encode_documents(none, common.vocabulary("byte_bpe_50k.json")).count() == 0


def test_byte_aligned_code_round_trip():
    rng = np.random.default_rng(7)
    for n in (0, 1, 3, 4, 5, 1000):
        x = rng.integers(0, [255, 65535, 2**24, 2**32][n % 4], n, dtype=np.uint64).astype(np.uint32)
        control, data = token_files.pack(x)
        assert len(control) == -(-n // 4) and (token_files.unpack(control, data, n) == x).all()


def test_cached_encoder_equals_the_library():
    import pyarrow as pa

    encoder = token_files.CachedEncoder(common.vocabulary("word_bpe_49k.json"), cache=100)
    texts = _texts(3000, 8)
    for t, ids in zip(texts, encoder.encode(pa.array(texts), 1), strict=True):
        assert ids.tolist() == encoder.tokenizer.encode(t, add_special_tokens=False).ids + [1]


def test_token_files_of_odd_rows(spark, odd, none):
    from tokenizers import Tokenizer

    path = common.vocabulary("word_bpe_49k.json")
    manifest, _ = token_files.write_token_files(odd, path, file_tokens=40)
    rows = sorted(token_files.read_token_files(manifest, keep_ids=True).collect(), key=lambda r: r.start)
    library, start = Tokenizer.from_file(path), 0
    coded = [(r.doc_id, library.encode(r.text or "", add_special_tokens=False).ids + [1]) for r in odd.collect()]
    want = sorted(coded, key=lambda r: (r[0] is None, r[0] or 0))
    assert [(r.doc_id, r.ids) for r in rows] == want
    for r in rows:
        assert r.start == start and r.ids_crc32 == zlib.crc32(np.array(r.ids, "<u4").tobytes())
        start += r.n_tokens
    assert manifest.count() > 2
    used = token_files.read_token_files(manifest).select(F.spark_partition_id().alias("p")).distinct().count()
    assert used == manifest.count()  # a task for each file
    empty, _ = token_files.write_token_files(none, path)
    assert token_files.read_token_files(empty).count() == 0


# op6 and op7 -------------------------------------------------------------------------------------------------------------------


def test_licence_rules(spark, odd, none):
    texts = [
        "Licensed under the Apache License, Version 2.0. You may not use this file except in compliance with the License!\nYou may obtain a copy of the License at: nowhere",
        "Released under the MIT License.\nreleased under the MIT license; All rights reserved.",
        "The software is provided \"as is\", without warranty of any kind.",
        "some line\nThis work is licensed under CC BY-NC-SA 3.0\nanother line",
        "// SPDX-License-Identifier: GPL-2.0-or-later\nint main() {}",
        "This project is licensed under the MIT License - see the LICENSE file for details",
    ]
    got = {r.doc_id: r for r in licenses.scan_licences(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")).collect()}
    assert got[0].sentences == "ref-Apache-2.0 ApacheComply" and got[0].licences == "Apache-2.0" and got[0].unmatched == "ApacheComply"
    assert got[1].licences == "MIT Proprietary" and got[1].unmatched == ""
    assert got[2].licences == "" and got[2].unmatched == "AsIs"
    assert [got[i].licences for i in (3, 4, 5)] == ["CC-BY-NC-SA-3.0", "GPL-2.0-or-later", "MIT"]
    assert licenses.scan_licences(odd).count() == licenses.scan_licences(none).count() == 0
    assert len(licenses.SENTENCES) == len({s for s, _ in licenses.SENTENCES}) > 500
    assert all(ids and all(c not in "".join(ids) for c in "<>| '") for ids, _ in licenses.RULES)


#: Published notices as they stand in files.
NOTICES = {
    "Apache-2.0": '''/*
 * Copyright 2020 Some One
 *
 * Licensed under the Apache License, Version 2.0 (the "License");
 * you may not use this file except in compliance with the License.
 * You may obtain a copy of the License at
 *
 *     http://www.apache.org/licenses/LICENSE-2.0
 *
 * Unless required by applicable law or agreed to in writing, software
 * distributed under the License is distributed on an "AS IS" BASIS,
 * WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
 * See the License for the specific language governing permissions and
 * limitations under the License.
 */''',
    "MIT": '''MIT License

Copyright (c) 2020 Some One

Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER
LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,
OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE
SOFTWARE.''',
    "BSD-3-Clause": '''Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this
   list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation
   and/or other materials provided with the distribution.

3. Neither the name of the copyright holder nor the names of its
   contributors may be used to endorse or promote products derived from
   this software without specific prior written permission.

THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS"
AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE
IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE
DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE
FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL
DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR
SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER
CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY,
OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE
OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.''',
    "GPL-3.0-or-later": '''# This program is free software: you can redistribute it and/or modify
# it under the terms of the GNU General Public License as published by
# the Free Software Foundation, either version 3 of the License, or
# (at your option) any later version.
#
# This program is distributed in the hope that it will be useful,
# but WITHOUT ANY WARRANTY; without even the implied warranty of
# MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the
# GNU General Public License for more details.
#
# You should have received a copy of the GNU General Public License
# along with this program.  If not, see <https://www.gnu.org/licenses/>.''',
    "LGPL-2.1-or-later": '''   This library is free software; you can redistribute it and/or
   modify it under the terms of the GNU Lesser General Public
   License as published by the Free Software Foundation; either
   version 2.1 of the License, or (at your option) any later version.

   This library is distributed in the hope that it will be useful,
   but WITHOUT ANY WARRANTY; without even the implied warranty of
   MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the GNU
   Lesser General Public License for more details.''',
    "MPL-2.0": '''/* This Source Code Form is subject to the terms of the Mozilla Public
 * License, v. 2.0. If a copy of the MPL was not distributed with this
 * file, You can obtain one at https://mozilla.org/MPL/2.0/. */''',
    "ISC": '''Permission to use, copy, modify, and/or distribute this software for any
purpose with or without fee is hereby granted, provided that the above
copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES
WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF
MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR
ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES
WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN
ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF
OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.''',
}


def test_published_notices(spark):
    rows = [(i, f"some code before\n\n{t}\n\nand after") for i, t in enumerate(NOTICES.values())]
    rows.append((100, "\n\n".join(NOTICES.values())))
    rows = [r for i, t in rows for r in ((i, t), (i + 1000, t.replace("\n", "\r\n")))]
    got = {r.doc_id: r for r in licenses.scan_licences(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    for i, name in enumerate(NOTICES):
        assert (got[i].licences, got[i + 1000].licences) == (name, name)
        assert got[i].unmatched == ("GnuHope GnuImplied LGPLSee" if name == "LGPL-2.1-or-later" else "")
    assert set(got[100].licences.split()) == set(NOTICES)


def _records(rows, spark):
    return spark.createDataFrame(rows, "record_id string, kind string, url string, ts timestamp, status int, headers map<string,string>")


@pytest.mark.parametrize("slice_rows", [3, 1000])
def test_revisits_against_brute_force(spark, slice_rows):
    from datetime import datetime, timedelta

    rng = random.Random(9)
    t0, rows = datetime(2024, 1, 1), []
    for i in range(150):
        kind = rng.choice(["response", "revisit", "revisit", "request"])
        head = {"ETag": f'"{rng.randint(0, 2)}"', "X-A": str(i)} if rng.random() < 0.8 else ({"Last-Modified": "x"} if rng.random() < 0.5 else {})
        url = rng.choice(["http://A.com/x?b=1&a=2&utm_z=1", "https://a.com:443/x?a=2&b=1#f", "http://b.com", None, "junk"])
        rows.append((f"r{i:03d}", kind, url, t0 + timedelta(seconds=rng.randint(0, 60)) if i % 29 else None, 200 if i % 7 else 404, head))
    got = {r.record_id: r for r in warc.resolve_revisits(_records(rows, spark), slice_rows).collect()}
    keys = {rows[i][2]: k for i, k in enumerate(r.k for r in spark.createDataFrame([(i, r[2]) for i, r in enumerate(rows)], "i int, url string").orderBy("i").select(warc.canonical_url(F.col("url")).alias("k")).collect())}
    assert keys["http://A.com/x?b=1&a=2&utm_z=1"] == keys["https://a.com:443/x?a=2&b=1#f"] == "a.com/x?a=2&b=1" and keys["http://b.com"] == "b.com/"
    asked = [r for r in rows if r[1] == "revisit"]
    assert set(got) == {r[0] for r in asked}
    for r in asked:
        key = keys[r[2]]
        before = [x for x in rows if x[1] == "response" and x[4] == 200 and key and r[3] and x[3] and keys[x[2]] == key and x[3] < r[3]]
        prior = max(before, key=lambda x: (x[3], x[0]), default=None)
        if not key or not r[3]:
            want = "no_key"
        elif prior is None:
            want = "no_earlier_response"
        elif not r[5]:
            want = "no_validator"
        else:
            name = "ETag" if "ETag" in r[5] else "Last-Modified"
            want = "resolved" if r[5][name] == prior[5].get(name) else "validator_mismatch"
        assert (got[r[0]].outcome, got[r[0]].refers_to) == (want, prior and prior[0])
        if want == "resolved" and "X-A" in prior[5]:
            assert f"x-a: {prior[5]['X-A']}" in got[r[0]].headers.split("\n")
    assert warc.resolve_revisits(_records(rows, spark).limit(0)).count() == 0


def test_warc_files(spark, tmp_path):
    def block(status, *lines):
        return ("\r\n".join([f"HTTP/1.1 {status}", *lines]) + "\r\n\r\nbody").encode()

    records = [
        ({"WARC-Type": "warcinfo", "WARC-Record-ID": "i"}, b"x"),
        ({"WARC-Type": "response", "WARC-Record-ID": "a", "WARC-Target-URI": "http://x.com/", "WARC-Date": "2024-01-01T00:00:00Z"}, block("200 OK", 'ETag: "1"', "Vary: a")),
        ({"WARC-Type": "revisit", "WARC-Record-ID": "b", "WARC-Target-URI": "http://x.com/", "WARC-Date": "2024-02-01T00:00:00Z"}, block("304 Not Modified", 'ETag: W/"1"', "Vary: b", "Server: s")),
    ]
    for compress in (True, False):
        raw = warc.write_warc(records, compress)
        assert [(h["warc-type"], b) for h, b in warc.parse_warc(raw)] == [(h["WARC-Type"], b) for h, b in records]
        assert [(h["warc-type"], b) for h, b in warc.parse_warc(raw[:-30])] == [(h["WARC-Type"], b) for h, b in records[:2]]
        long = warc.write_warc([({"WARC-Type": "response"}, bytes([i % 251]) * (i * 977 % 300_000)) for i in range(60)], compress)
        assert [len(b) for _, b in warc.parse_warc(long)] == [i * 977 % 300_000 for i in range(60)]
        assert len(list(warc.parse_warc(long[: len(long) // 2] + b"junk" * 9))) < 60
        assert list(warc.parse_warc(raw[:12])) == list(warc.parse_warc(b"")) == []
    odd = b"WARC/1.1\r\nWARC-Type: response\r\nContent-Length: many\r\n\r\nx\r\n\r\n" + warc.write_warc(records[:1], False)
    assert [h["warc-type"] for h, _ in warc.parse_warc(odd)] == ["warcinfo"]
    (tmp_path / "a.warc.gz").write_bytes(warc.write_warc(records))
    rows = warc.read_warc(spark, str(tmp_path))
    assert rows.count() == 2 and bytes(rows.where("record_id = 'a'").first().body) == b"body"
    one = warc.resolve_revisits(rows).first()
    assert (one.refers_to, one.outcome, one.headers) == ("a", "resolved", 'etag: W/"1"\nvary: b')


# op8 -------------------------------------------------------------------------------------------------------------------------


def _brute(rows, window):
    seen, out = set(), {}
    for i, t in sorted(rows):
        b = (t or "").encode()
        mask = np.zeros(len(b), bool)
        for k in range(len(b) - window + 1):
            if b[k : k + window] in seen:
                mask[k : k + window] = True
            seen.add(b[k : k + window])
        kept = bytes(np.frombuffer(b, np.uint8)[~mask])
        out[i] = (len(b), int(mask.sum()), int((np.diff(mask.astype(int), prepend=0) == 1).sum()), hashlib.sha256(kept).hexdigest())
    return out


def test_covers_are_perfect_difference_sets():
    for v, c in suffix_dedup.COVERS.items():
        assert sorted((a - b) % v for a in c for b in c if a != b) == list(range(1, v))


@pytest.mark.parametrize("window,buffer", [(100, 1 << 20), (100, 2000), (30, 5000), (12, 1 << 20)])
def test_repeats_against_brute_force(spark, tmp_path, monkeypatch, window, buffer):
    rng = random.Random(window + buffer)
    words = ["".join(rng.choices("abcdeé", k=rng.randint(1, 7))) for _ in range(300)]
    shared = [" ".join(rng.choices(words, k=rng.randint(10, 60))) for _ in range(12)]
    rows = []
    for i in range(120):
        t = " ".join(rng.choices(words, k=rng.randint(0, 200)))
        for _ in range(rng.randint(0, 4)):
            x, k = rng.choice(shared), rng.randint(0, len(t))
            a = rng.randint(0, len(x) // 2)
            t = t[:k] + x[a : a + rng.randint(50, 400)] + t[k:]
        if i % 7 == 0:
            t += "la " * rng.randint(1, 300)
        if i % 11 == 0 and rows:
            t = rng.choice(rows)[1]
        rows.append((i * 7 % 121, None if i == 50 else t))
    monkeypatch.setattr(suffix_dedup, "BATCH", buffer)
    spark.createDataFrame(rows, "doc_id bigint, text string").repartition(4).write.parquet(f"{tmp_path}/d")
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.remove_repeats(spark.read.parquet(f"{tmp_path}/d"), window).collect()}
    assert got == _brute(rows, window)


def _parity(i):
    return i.bit_count() & 1


def test_texts_made_to_confuse_hashes_modulo_a_power_of_two(spark, tmp_path):
    rows = []
    for period in (3, 5, 7):
        base = [i % period * 2 + 97 for i in range(1024)]
        rows += [(period * 10 + k, bytes(c + (_parity(i) ^ k) for i, c in enumerate(base)).decode()) for k in (0, 1)]
    for n in (11, 12):  # longer ones, behind a common text
        rows += [(n * 100 + k, "common " * 20 + "".join(chr(98 + (_parity(i) ^ k)) for i in range(1 << n))) for k in (0, 1)]
    spark.createDataFrame(rows, "doc_id bigint, text string").write.parquet(f"{tmp_path}/d")
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.remove_repeats(spark.read.parquet(f"{tmp_path}/d")).collect()}
    assert got == _brute(rows, 100)


def test_products_and_hashes_modulo_the_prime():
    prime, rng = int(suffix_dedup._PRIME), np.random.default_rng(1)
    a, b = rng.integers(0, prime, (2, 500), dtype=np.uint64)
    a[:3], b[:3] = [prime - 1, 0, 1], prime - 1
    assert [int(x) * int(y) % prime for x, y in zip(a, b, strict=True)] == suffix_dedup._times(a, b).tolist()
    data, bases = rng.integers(0, 256, 3000, dtype=np.uint8), suffix_dedup.random_bases()
    hashes = suffix_dedup.Prefixes(data, suffix_dedup.Powers(bases))
    for k, base in enumerate(bases):
        for i, j in ((0, 10), (7, 2000), (2990, 3000)):
            want = sum((int(c) + 1) * pow(base, n, prime) for n, c in enumerate(data[i:j])) % prime
            assert int(hashes.of(np.array([i]), np.array([j]), k)[0]) == want


def test_repeats_of_odd_rows(spark, odd, none, tmp_path):
    odd.write.parquet(f"{tmp_path}/d")
    df = spark.read.parquet(f"{tmp_path}/d")
    rows = suffix_dedup.remove_repeats(df).collect()
    assert len(rows) == odd.count()
    of = {r.doc_id: r for r in rows}
    assert of[7].n_removed == of[7].n_bytes and of[6].n_removed == 0 and of[1].n_bytes == 0
    assert of[9].n_removed == 4999  # a run of one letter keeps its first byte
    texts = {r.doc_id: r.text for r in suffix_dedup.without_repeats(df).collect()}
    assert texts[1] is None and texts[9] == "a" and texts[7] == "" and set(suffix_dedup.without_repeats(df).columns) == set(odd.columns)
    assert suffix_dedup.remove_repeats(none).count() == 0


# op10 ------------------------------------------------------------------------------------------------------------------------


def test_toxicity_on_held_out_rows(spark):
    sf = "/root/testdata/sf0.1"
    labels = common.table(spark, sf, "labels")
    got = queries.op10_toxicity(spark, sf).join(labels, "doc_id").where("held_out").toPandas()
    toxic, clean = got[got.toxic == 1], got[got.toxic == 0]
    assert (clean.predicted == 0).mean() > 0.99 and (toxic.predicted == 1).mean() > 0.9
    assert got.score.between(0, 1).all()
    assert ((got.score >= 0.7).astype(int) == got.predicted).all()


def test_held_out_labels_are_not_learned(spark):
    docs, labels = common.table(spark, MEDIUM, "documents"), common.table(spark, MEDIUM, "labels")
    flipped = labels.withColumn("toxic", F.when(toxicity.held_out(F.col("doc_id")), 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a, b = toxicity.fit(docs, labels), toxicity.fit(docs, flipped)
    assert a.voters == b.voters and np.allclose(a.weights, b.weights)
    row = spark.createDataFrame([(1,), (22,)], "doc_id bigint").select("doc_id", toxicity.held_out(F.col("doc_id")).alias("h")).collect()
    assert all(r.h == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in row)


def test_toxicity_of_odd_rows(spark, odd, none):
    labels = spark.createDataFrame([(1, None), (None, 1), (2, 0)], "doc_id bigint, toxic int")
    assert toxicity.fit(odd, labels) is None and toxicity.fit(none, labels) is None
    model = toxicity.ToxicityModel(["clow"], np.array([2.0, 0, 0, 0]), -1.0, toxicity.label_model(np.zeros((0, 1)), np.zeros(0))[1])
    scored = toxicity.score_documents(odd, model).collect()
    assert len(scored) == odd.count() and all(r.predicted == 0 and 0 <= r.score <= 1 for r in scored)
    assert toxicity.keep_clean(odd, model).count() == odd.count() and toxicity.score_documents(none, model).count() == 0


def test_label_model_recovers_accuracies_and_correlations():
    rng = np.random.default_rng(0)
    y = rng.random(4000) < 0.2
    votes = np.stack([np.where(y, rng.random(4000) < a, rng.random(4000) < b) for a, b in ((0.8, 0.02), (0.6, 0.05), (0.5, 0.01))], 1).astype(float)
    echo = np.where(rng.random(4000) < 0.9, votes[:, 0], 0)  # a voter that nearly copies another
    votes = np.hstack([votes, echo[:, None]])
    labels = np.where(rng.random(4000) < 0.3, y, -1).astype(int)
    post, model = toxicity.label_model(votes, labels)
    assert ((post > 0.5) == y).mean() > 0.93
    assert model.rates[0, 1] == pytest.approx(0.8, abs=0.15) and model.rates[0, 0] < 0.08
    assert {model.parent[0], model.parent[3]} & {0, 3} and model.parent[2] == -1
    i = 3 if model.parent[3] == 0 else 0
    assert abs(model.given[i, 1, 1] - model.given[i, 0, 1]) < 0.1  # given the other's vote it says little of the label
    one, two = np.eye(4)[[0, 1]], np.array([[1.0, 0, 0, 1], [1, 1, 0, 0]])
    apart, echoed = model.evidence(one)[0], model.evidence(two)
    assert abs(echoed[0] - apart) < 0.1 < echoed[1] - apart
