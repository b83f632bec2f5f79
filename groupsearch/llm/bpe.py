"""Byte-level BPE encoding and decoding by a segment tree over the ranks of adjacent pairs.

The tree holds, for each gap between two neighbouring symbols, the rank of their merge and the gap's place as one integer, so its
root is the leftmost merge of lowest rank. A merge touches three gaps, each a point update of logarithmic cost; the loop ends
when the root is empty. Words that recur are looked up in a bounded cache.
"""

from __future__ import annotations

import hashlib
import json
import sys
from array import array
from functools import lru_cache
from itertools import islice

import numpy as np
import pyarrow as pa
import regex
import re
from pyspark.sql import DataFrame

from .common import bounded_batches, tidy

#: The white space of the pre-tokenizer's pattern, and the pattern of byte-level BPE.
SPACE = "\t-\r \x85\xa0  -     　"
WORDS = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{SPACE}\p{{L}}\p{{N}}]+|[{SPACE}]+(?![^{SPACE}])|[{SPACE}]+"

_WORDS = regex.compile(WORDS)
#: The same for texts whose characters all lie below U+0250 and are no fractions or superscripts: there Python's own classes agree.
_LATIN = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?[^\W\d_]+| ?\d+| ?(?:[^{SPACE}\w]|_)+|[{SPACE}]+(?![^{SPACE}])|[{SPACE}]+")
_OTHER = re.compile("[²³¹¼½¾]|[^\x00-\u024f]")
_NONE = 1 << 62


def byte_alphabet() -> list[str]:
    """The printable character that stands for each byte in vocabularies of byte-level BPE."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


def merge_symbols(symbols: list[int], ranks: dict[tuple[int, int], int], merged: list[int]) -> list[int]:
    """Applies merges, the lowest rank first and the leftmost of equal ranks, until none fits.

    ranks: pair of symbols to the rank of its merge; merged: the symbol that the merge of each rank makes.
    """
    n = len(symbols)
    if n < 2:
        return symbols
    size = 1 << (n - 2).bit_length() if n > 2 else 1
    shift = size.bit_length() - 1
    mask = size - 1
    tree = [_NONE] * (2 * size)
    get = ranks.get
    i = size
    for pair in zip(symbols, symbols[1:]):
        rank = get(pair)
        if rank is not None:
            tree[i] = rank << shift | i - size
        i += 1
    for i in range(mask, 0, -1):
        a, b = tree[2 * i], tree[2 * i + 1]
        tree[i] = a if a < b else b
    root = tree[1]
    if root == _NONE:
        return symbols
    after = list(range(1, n + 1))
    before = list(range(-1, n - 1))
    symbols = list(symbols)
    while root != _NONE:
        left = root & mask
        right = after[left]
        beyond = after[right]
        symbol = symbols[left] = merged[root >> shift]
        after[left] = beyond
        gaps = []
        if beyond < n:
            before[beyond] = left
            rank = get((symbol, symbols[beyond]))
            gaps.append((size + right, _NONE))
            gaps.append((size + left, _NONE if rank is None else rank << shift | left))
        else:
            gaps.append((size + left, _NONE))
        prior = before[left]
        if prior >= 0:
            rank = get((symbols[prior], symbol))
            gaps.append((size + prior, _NONE if rank is None else rank << shift | prior))
        for i, value in gaps:  # point updates, each up to where the minimum stays
            if tree[i] == value:
                continue
            tree[i] = value
            while i > 1:
                other = tree[i ^ 1]
                i >>= 1
                if other < value:
                    value = other
                if tree[i] == value:
                    break
                tree[i] = value
        root = tree[1]
    out = []
    i = 0
    while i < n:
        out.append(symbols[i])
        i = after[i]
    return out


class Known(dict):
    """Ids by word, computed where they are not known; at most so many short words are kept, the older half makes room."""

    def __init__(self, compute, most: int):
        super().__init__()
        self.compute, self.most = compute, most

    def __missing__(self, word: str) -> bytes:
        ids = self.compute(word)
        if len(word) < 64:
            if len(self) >= self.most:
                for old in list(islice(self, self.most // 2)):
                    del self[old]
            self[word] = ids
        return ids


class ByteBPE:
    """Encoder and decoder for a byte-level vocabulary file of the tokenizers library (special tokens in a text count as such)."""

    def __init__(self, path: str, cache: int = 600_000):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab = spec["model"]["vocab"]
        alphabet = byte_alphabet()
        self.symbol = [vocab[c] for c in alphabet]
        pairs = (m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"])
        pairs = list(pairs)
        self.ranks = {(vocab[a], vocab[b]): rank for rank, (a, b) in enumerate(pairs)}
        self.merged = [vocab[a + b] for a, b in pairs]
        back = {c: b for b, c in enumerate(alphabet)}
        self.pieces = [b""] * (max(max(vocab.values()), *(t["id"] for t in spec["added_tokens"]), 0) + 1)
        for token, i in vocab.items():
            if all(c in back for c in token):
                self.pieces[i] = bytes(back[c] for c in token)
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        for content, i in special.items():
            self.pieces[i] = content.encode()
        self.special = {s: np.array([i], "<u4").tobytes() for s, i in special.items()}
        self.cut = re.compile("(" + "|".join(map(re.escape, sorted(special, key=len, reverse=True))) + ")") if special else None
        self.words = Known(self.word, cache)

    def word(self, word: str) -> bytes:
        symbol = self.symbol
        ids = array("I", merge_symbols([symbol[b] for b in word.encode("utf-8", "surrogatepass")], self.ranks, self.merged))
        if sys.byteorder == "big":
            ids.byteswap()
        return ids.tobytes()

    def encode(self, text: str) -> bytes:
        """The ids of a whole text as little-endian 32-bit integers."""
        if self.cut is None or not self.cut.search(text):
            return self._plain(text)
        return b"".join(self.special.get(part) or self._plain(part) for part in self.cut.split(text) if part)

    def _plain(self, text: str) -> bytes:
        words = (_WORDS if _OTHER.search(text) else _LATIN).findall(text)
        return b"".join(map(self.words.__getitem__, words))

    def decode(self, ids: bytes) -> str:
        """The text of ids; bytes that are no UTF-8 become U+FFFD."""
        pieces = self.pieces
        return b"".join([pieces[i] for i in np.frombuffer(ids, "<u4").tolist()]).decode("utf-8", "replace")


@lru_cache(maxsize=2)
def codec(path: str) -> ByteBPE:
    return ByteBPE(path)


def encode_documents(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = True) -> DataFrame:
    """Encodes every whole text and decodes it again: id, n_tokens, ids_sha256, decoded_sha256 and, with keep_ids, ids and decoded.

    A null text counts as empty: no tokens, digests of nothing. Repeated rows and equal ids each give their own row, an empty
    table gives none, other columns are ignored. A text is held in memory with its ids, nothing else is; no shuffle.
    """
    spark = docs.sparkSession
    bounded_batches(spark)
    kind = dict(docs.dtypes)[id_col]
    extra = ", ids binary, decoded string" if keep_ids else ""

    @tidy
    def run(batches):
        bpe = codec(path)
        for batch in batches:
            n_tokens, digest, back, all_ids, all_texts = [], [], [], [], []
            for text in batch.column(1).to_pylist():
                ids = bpe.encode(text or "")
                decoded = bpe.decode(ids)
                n_tokens.append(len(ids) // 4)
                digest.append(hashlib.sha256(ids).hexdigest())
                back.append(hashlib.sha256(decoded.encode("utf-8", "replace")).hexdigest())
                if keep_ids:
                    all_ids.append(ids)
                    all_texts.append(decoded)
            columns = [batch.column(0), pa.array(n_tokens, pa.int64()), pa.array(digest, pa.string()), pa.array(back, pa.string())]
            names = [id_col, "n_tokens", "ids_sha256", "decoded_sha256"]
            if keep_ids:
                columns += [pa.array(all_ids, pa.binary()), pa.array(all_texts, pa.string())]
                names += ["ids", "decoded"]
            yield pa.RecordBatch.from_arrays(columns, names)

    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string{extra}")
