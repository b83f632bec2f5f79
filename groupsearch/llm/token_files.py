"""Token-id files: frequency-ranked ids in a byte-aligned variable-length code whose control bytes stand apart from the data.

A file holds whole documents in ascending id order::

    magic "GSTK", version, then as little-endian 64-bit integers: documents, tokens, control bytes, data bytes, table entries, and how
    many documents have no id (they come last, with a zero in its place)
    document ids (int64) | tokens of each document (int64) | id of each rank (uint32) | control bytes | data bytes

Each token is the rank of its id by corpus frequency, in one to four bytes. Two bits in a control byte give the length, four
tokens a control byte. Decoding looks the control bytes up in a table of lengths and gathers the data with numpy, no loop.
"""

from __future__ import annotations

import json
import os
import re
import struct
import uuid
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import SPACE
from .common import Workspace, batches_of, bounded_batches, filesystem, tidy

MAGIC = b"GSTK\x02\x00\x00\x00"
HEAD = struct.Struct("<8s6q")
#: Rows of a batch that is encoded at once, so that its distinct stretches are few; most tasks that read files.
BATCH_ROWS, READ_TASKS = 4096, 10_000
_CHUNKS = re.compile(f"[^{SPACE}]+")
#: Lengths of the four tokens that a control byte describes.
LENGTHS = ((np.arange(256)[:, None] >> np.array([0, 2, 4, 6])) & 3).astype(np.uint8) + 1


def pack(values: np.ndarray) -> tuple[bytes, bytes]:
    """(control bytes, data bytes) of unsigned 32-bit integers."""
    v = np.ascontiguousarray(values, "<u4")
    if not len(v):
        return b"", b""
    length = 1 + (v > 0xFF).astype(np.uint8) + (v > 0xFFFF) + (v > 0xFFFFFF)
    codes = np.zeros(-(-len(v) // 4) * 4, np.uint8)
    codes[: len(v)] = length - 1
    control = (codes.reshape(-1, 4) << np.array([0, 2, 4, 6], np.uint8)).sum(1, dtype=np.uint8)
    keep = np.arange(4, dtype=np.uint8) < length[:, None]
    return control.tobytes(), v.view(np.uint8).reshape(-1, 4)[keep].tobytes()


def unpack(control: bytes, data: bytes, n: int) -> np.ndarray:
    """The n integers that pack() wrote."""
    length = LENGTHS[np.frombuffer(control, np.uint8)].reshape(-1)[:n]
    out = np.zeros((n, 4), np.uint8)
    out[np.arange(4, dtype=np.uint8) < length[:, None]] = np.frombuffer(data, np.uint8)
    return out.view("<u4").reshape(-1)


def file_bytes(doc_ids: list[int | None], counts: np.ndarray, ids: np.ndarray, by_rank: np.ndarray, rank_of: np.ndarray) -> bytes:
    control, data = pack(rank_of[ids])
    head = HEAD.pack(MAGIC, len(doc_ids), len(ids), len(control), len(data), len(by_rank), sum(d is None for d in doc_ids))
    named = np.array([d or 0 for d in doc_ids], "<i8")
    return b"".join((head, named.tobytes(), counts.astype("<i8").tobytes(), by_rank.astype("<u4").tobytes(), control, data))


def parse_file(raw: bytes) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """(document ids, tokens of each, all ids in order) of a file's bytes."""
    magic, docs, tokens, n_control, n_data, entries, unnamed = HEAD.unpack_from(raw)
    if magic != MAGIC:
        raise ValueError("not a token file")
    at = HEAD.size
    doc_ids = pa.array(np.frombuffer(raw, "<i8", docs, at), pa.int64(), mask=np.arange(docs) >= docs - unnamed)
    counts = np.frombuffer(raw, "<i8", docs, at := at + 8 * docs)
    by_rank = np.frombuffer(raw, "<u4", entries, at := at + 8 * docs)
    at += 4 * entries
    ranks = unpack(raw[at : at + n_control], raw[at + n_control : at + n_control + n_data], tokens)
    return doc_ids, counts, by_rank[ranks]


#: Texts with none of these can be lower-cased and cut at white space before the tokenizer sees them: no character that normal
#: forms compose or that lower-cases to two, and no start of a special token. The rest of a text's characters lie below U+0250.
_UNSAFE = r"[^\x00-\x{12f}\x{131}-\x{24f}]|<\|"


class CachedEncoder:
    """Encodes whole texts with the tokenizers library, looking recurring stretches between white space up in a bounded cache.

    Holds for tokenizers that lower-case and whose tokens never reach across white space or from a word into the punctuation that
    ends it, as in vocabularies that mark word ends. Arrow cuts a batch and finds its distinct stretches; only those are looked up.
    """

    def __init__(self, path: str, cache: int = 800_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_padding()
        self.tokenizer.no_truncation()
        self.known: dict[str, bytes] = {"": b""}
        self.cache = cache
        suffix = json.loads(self.tokenizer.to_str())["model"].get("end_of_word_suffix")
        self.ends = None  # whether an id ends a word
        if suffix:
            vocab = self.tokenizer.get_vocab()
            self.ends = np.zeros(max(vocab.values()) + 1, bool)
            self.ends[[i for t, i in vocab.items() if t.endswith(suffix)]] = True

    def ids_of(self, chunks: list[str]) -> list[bytes]:
        """Ids of each of distinct stretches, as little-endian 32-bit integers."""
        known = self.known
        if len(known) > self.cache:
            known.clear()
            known[""] = b""
        new = [c for c in chunks if c not in known]
        long = {}
        if self.ends is not None:  # plain words by the hundred: the ids that end a word part them again
            words = [c for c in new if c.isalpha() and len(c) < 64]
            for i in range(0, len(words), 500):
                part = words[i : i + 500]
                ids = np.array(self.tokenizer.encode(" ".join(part), add_special_tokens=False).ids, "<u4")
                stops = np.flatnonzero(self.ends[ids]) + 1
                if len(stops) == len(part) and stops[-1] == len(ids):
                    raw, at = ids.tobytes(), 0
                    for word, stop in zip(part, (4 * stops).tolist(), strict=True):
                        known[word] = raw[at:stop]
                        at = stop
            new = [c for c in new if c not in known]
        for i in range(0, len(new), 20_000):
            part = new[i : i + 20_000]
            for chunk, e in zip(part, self.tokenizer.encode_batch(part, add_special_tokens=False), strict=True):
                (known if len(chunk) < 64 else long)[chunk] = np.array(e.ids, "<u4").tobytes()
        return [long[c] if c in long else known[c] for c in chunks] if long else [known[c] for c in chunks]

    def _cut(self, texts: pa.Array) -> pa.Array:
        low = pc.utf8_lower(texts)
        apart = pc.replace_substring_regex(low, r"([\pL\pN])([.,!?;:]+)([\t-\r \x{85}\x{a0}]|$)", r"\1 \2\3")
        for space in "\x85\xa0":
            apart = pc.replace_substring(apart, space, " ")
        return pc.ascii_split_whitespace(apart)

    def encode(self, texts: pa.Array, end: int) -> list[np.ndarray]:
        """Ids of each text, then the end id; a null text counts as empty."""
        texts = pc.fill_null(texts, "")
        unsafe = pc.match_substring_regex(texts, _UNSAFE)
        out: list = [None] * len(texts)
        safe_at = np.flatnonzero(~unsafe.to_numpy(zero_copy_only=False))
        other_at = np.flatnonzero(unsafe.to_numpy(zero_copy_only=False))
        if len(safe_at):
            self._gather(self._cut(texts.take(pa.array(safe_at))), safe_at, end, out)
        if len(other_at):
            cut = pa.array([_CHUNKS.findall(t) for t in texts.take(pa.array(other_at)).to_pylist()], pa.list_(pa.string()))
            self._gather(cut, other_at, end, out)
        return out

    def _gather(self, cut: pa.Array, at: np.ndarray, end: int, out: list) -> None:
        coded = cut.flatten().dictionary_encode()
        place = coded.indices.to_numpy(zero_copy_only=False)
        ids = self.ids_of(coded.dictionary.to_pylist())
        sizes = np.fromiter(map(len, ids), np.int64, len(ids)) // 4
        pool = np.frombuffer(b"".join(ids), "<u4")
        first = np.cumsum(sizes) - sizes
        length = sizes[place]
        stop = np.concatenate([[0], np.cumsum(length)])
        total = int(stop[-1])
        tokens = pool[np.repeat(first[place] - stop[:-1], length) + np.arange(total)]
        bounds = stop[np.asarray(cut.offsets) - cut.offsets[0].as_py()]
        tail = np.array([end], "<u4")
        for i, a, b in zip(at.tolist(), bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            out[i] = np.concatenate([tokens[a:b], tail])


@lru_cache(maxsize=1)
def encoder(path: str) -> CachedEncoder:
    return CachedEncoder(path)


def write_token_files(
    docs: DataFrame, path: str, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", file_tokens: int = 1 << 23, folder: str | None = None
) -> tuple[DataFrame, int]:
    """Encodes whole texts, appends end_id to each and writes ids to token files in ascending document id; gives their manifest.

    Steps: deal documents out by ranges of id, encode once into a Parquet table; count every id of the vocabulary over all
    documents (one row of counts a task, at most the vocabulary to the driver) and rank them by falling count; code ranks file by
    file, about file_tokens tokens each, longer only for one longer document. A file is written under a name of its own and then
    moved, so a retried task leaves a whole file. Manifest: path, first_doc, last_doc, n_docs, n_tokens, base
    (tokens before it), file (its number).
    Null texts count as empty (the end id alone). Rows with equal ids stay, in any order; rows with a null id come last. Empty tables
    give an empty manifest.
    """
    spark = docs.sparkSession
    work = Workspace(spark, "token-files")
    folder = folder or f"{work.path}/files"
    ordered = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    last = F.col("doc_id").asc_nulls_last()
    ordered = ordered.repartitionByRange(last).sortWithinPartitions(last)

    @tidy
    def encode(batches):
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        for b in batches:
            ids = [x.astype("<u2").tobytes() if x.max() < 1 << 16 else b"\0" + x.tobytes() for x in encoder(path).encode(b.column(1), end_id)]
            yield pa.RecordBatch.from_arrays([pa.array([part] * b.num_rows, pa.int32()), b.column(0), pa.array(ids, pa.binary())], ["part", "doc_id", "ids"])

    with batches_of(spark, BATCH_ROWS):
        coded = work.save(ordered.mapInArrow(encode, "part int, doc_id bigint, ids binary"), "coded")
    work.release()

    def whole(raw: bytes) -> np.ndarray:
        return np.frombuffer(raw, "<u4", offset=1) if len(raw) % 2 else np.frombuffer(raw, "<u2").astype("<u4")

    @tidy
    def count(batches):
        total = np.zeros(1, np.int64)
        for b in batches:
            for raw in b.column(0).to_pylist():
                got = np.bincount(whole(raw))
                if len(got) > len(total):
                    total = np.concatenate([total, np.zeros(len(got) - len(total), np.int64)])
                total[: len(got)] += got
        seen = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(seen, pa.int64()), pa.array(total[seen], pa.int64())], ["id", "n"])

    counts = coded.select("ids").mapInArrow(count, "id bigint, n bigint").groupBy("id").agg(F.sum("n").alias("n")).collect()
    by_rank = np.array([r.id for r in sorted(counts, key=lambda r: (-r.n, r.id))], np.int64)
    table = spark.sparkContext.broadcast(by_rank)

    @tidy
    def write(batches):
        ranks = table.value
        rank_of = np.zeros(int(ranks.max(initial=0)) + 1, np.uint32)
        rank_of[ranks] = np.arange(len(ranks), dtype=np.uint32)
        store, root = filesystem(folder)
        store.create_dir(root, recursive=True)
        ids, docs, held, last = [], [], 0, None

        def flush():
            counts = np.array([len(x) for x in ids], np.int64)
            raw = file_bytes(docs, counts, np.concatenate(ids), ranks, rank_of)
            name = f"{root}/{'unnamed' if docs[0] is None else f'{docs[0]:020d}'}-{uuid.uuid4().hex}.gstk"
            with store.open_output_stream(f"{name}.part") as out:
                out.write(raw)
            store.move(f"{name}.part", name)
            return (f"{folder}/{name.rsplit('/', 1)[1]}", docs[0], docs[-1], len(docs), int(counts.sum()))

        done = []
        for b in batches:
            for part, doc, raw in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if docs and (held >= file_tokens or part != last or (doc is None, doc or 0) < (docs[-1] is None, docs[-1] or 0)):
                    done.append(flush())
                    ids, docs, held = [], [], 0
                last = part
                x = whole(raw)
                ids.append(x)
                docs.append(doc)
                held += len(x)
        if docs:
            done.append(flush())
        kinds = [pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64()]
        names = ["path", "first_doc", "last_doc", "n_docs", "n_tokens"]
        yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(zip(*done) if done else [[]] * 5, kinds, strict=True)], names)

    manifest = work.save(coded.mapInArrow(write, "path string, first_doc bigint, last_doc bigint, n_docs bigint, n_tokens bigint"), "manifest")
    work.drop("coded")
    files = Window.orderBy(F.col("first_doc").asc_nulls_last(), F.col("last_doc").asc_nulls_last(), "path")  # one row a file
    before = F.sum("n_tokens").over(files.rowsBetween(Window.unboundedPreceding, -1))
    return manifest.withColumn("base", F.coalesce(before, F.lit(0))).withColumn("file", F.row_number().over(files) - 1), len(by_rank)


def read_token_files(manifest: DataFrame, keep_ids: bool = False) -> DataFrame:
    """Documents of token files: doc_id, start (tokens of all documents before), n_tokens, ids_crc32 and, with keep_ids, ids.

    manifest: path, base, file (numbers from 0). A file is a task of its own, up to READ_TASKS; beyond, tasks take several.
    """
    spark = manifest.sparkSession
    tasks = max(1, min(manifest.count(), READ_TASKS))
    extra = ", ids array<bigint>" if keep_ids else ""

    @tidy
    def read(batches):
        for b in batches:
            for path, base in zip(*(c.to_pylist() for c in b.columns), strict=True):
                store, name = filesystem(path)
                with store.open_input_file(name) as f:
                    doc_ids, counts, ids = parse_file(f.read())
                ends = np.cumsum(counts)
                starts = ends - counts
                raw = memoryview(ids.astype("<u4").tobytes())
                crc = [zlib.crc32(raw[4 * s : 4 * e]) for s, e in zip(starts.tolist(), ends.tolist(), strict=True)]
                columns = [doc_ids, pa.array(starts + base, pa.int64()), pa.array(counts, pa.int64()), pa.array(crc, pa.int64())]
                names = ["doc_id", "start", "n_tokens", "ids_crc32"]
                if keep_ids:
                    columns.append(pa.array([ids[s:e].tolist() for s, e in zip(starts, ends, strict=True)], pa.list_(pa.int64())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names)

    bounded_batches(spark)
    dealt = manifest.select("path", "base", F.pmod("file", F.lit(tasks)).cast("int").alias("task")).repartitionById(tasks, "task").select("path", "base")
    return dealt.mapInArrow(read, f"doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint{extra}")
