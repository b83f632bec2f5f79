"""Exact substring dedup by a difference-cover suffix order, as far as an order of the first 100 bytes is needed.

A difference cover of v residues has, for any two positions i and j, a shift below v that takes both to sampled positions. So two
equal strings of ``window`` bytes hold equal sampled strings of ``window - v + 1`` bytes at equal places. The steps:

1. Name the sampled suffixes by a hash of their prefix of that length, deal names out by value, sort them, and mark the positions
   whose name occurs at another place. Only the order of prefixes up to ``window`` is needed, so one round of naming does what
   recursion does for a whole suffix array.
2. Positions that no marked sample covers have no equal string. Merge the rest: name their prefixes of ``window`` bytes by two
   hashes, sort, and compare neighbours; all but the first of equal ones are removed.

Prefixes and pieces are compared by polynomial hashes modulo the prime 2**61 - 1 in two bases drawn anew for every run. For any two
different strings of n bytes, whoever made them, the bases that confuse them are at most n of 2**61, and the two are independent.

Long copies would bring all their positions to step 2. They are met before: texts are cut where the content says, and of pieces
with equal bytes (and equal ``window - 1`` bytes behind) all but the first are removed whole. Samples that lie alike in equal pieces
count as one place in step 1, so what reaches step 2 are the positions around the ends of copies.
"""

from __future__ import annotations

import hashlib
import secrets

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Workspace, bounded_batches, tidy

WINDOW = 100
#: Perfect difference sets, every residue but zero is a difference of two of them exactly once.
COVERS = {
    7: (0, 1, 3),
    13: (0, 1, 3, 9),
    21: (0, 1, 4, 14, 16),
    31: (0, 1, 3, 8, 12, 18),
    57: (0, 1, 3, 13, 32, 36, 43, 52),
    73: (1, 2, 4, 8, 16, 32, 37, 55, 64),
}
#: Bytes of text that a task names at a time, bytes of text for each partition of names.
BATCH, PART_BYTES = 1 << 20, 10 << 20
#: Bytes that the local hash which cuts texts looks at, and the least distance of cuts.
CUT_BYTES, CUT_APART = 16, 64
_PRIME = np.uint64((1 << 61) - 1)
_ODD, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xFF51AFD7ED558CCD)
_LAST = (1 << 63) - 1


def cover_for(window: int) -> tuple[int, tuple[int, ...]]:
    """The largest cover of at most three fifths of the window: sparser samples, but of strings that seldom recur by chance."""
    v = max(v for v in COVERS if v <= max(7, 3 * window // 5))
    return v, COVERS[v]


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * _MIX
    return h ^ (h >> np.uint64(29))


def _fold(x: np.ndarray) -> np.ndarray:
    """Numbers of 64 bits modulo 2**61 - 1."""
    x = (x & _PRIME) + (x >> np.uint64(61))
    return np.minimum(x, x - _PRIME)  # below the prime the difference wraps round and is the larger


def _times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Products modulo 2**61 - 1 of numbers below it, from halves of 32 bits: 2**61 counts as 1, 2**64 as 8."""
    half, low = np.uint64(32), np.uint64(0xFFFFFFFF)
    a1, a0, b1, b0 = a >> half, a & low, b >> half, b & low
    cross = a1 * b0 + a0 * b1
    least = a0 * b0
    return _fold((least & _PRIME) + (least >> np.uint64(61)) + (a1 * b1 << np.uint64(3)) + (cross >> np.uint64(29)) + ((cross & np.uint64((1 << 29) - 1)) << half))


def random_bases() -> tuple[int, int]:
    """Two bases that nobody knows before the run."""
    return tuple(secrets.randbelow((1 << 61) - (1 << 20)) + (1 << 19) for _ in range(2))


class Powers:
    """Powers of the hash bases and of their inverses modulo 2**61 - 1, as far as the longest buffer so far."""

    def __init__(self, bases: tuple[int, int]):
        self.n = 1
        self.bases = bases
        self.up = [np.ones(1, np.uint64) for _ in bases]
        self.down = [np.ones(1, np.uint64) for _ in bases]

    def reach(self, n: int) -> None:
        if n <= self.n:
            return
        self.n = -(-n // (1 << 17)) << 17
        prime = int(_PRIME)
        for tables, sign in ((self.up, 1), (self.down, -1)):
            for k, base in enumerate(self.bases):
                steps = tables[k]
                while len(steps) < self.n:
                    more = steps[: self.n - len(steps)]
                    steps = np.concatenate([steps, _times(more, np.uint64(pow(base, sign * len(steps), prime)))])
                tables[k] = steps


_POWERS: list[Powers] = []


def powers_of(bases: tuple[int, int]) -> Powers:
    """The tables of this worker, kept from task to task unless a very long text made them large."""
    if not _POWERS or _POWERS[0].bases != bases or _POWERS[0].n > 4 * BATCH:
        _POWERS[:] = [Powers(bases)]
    return _POWERS[0]


class Prefixes:
    """Hashes of any substring of a buffer, from prefix sums of its bytes times powers of a base."""

    def __init__(self, data: np.ndarray, powers: Powers):
        powers.reach(len(data) + 1)
        self.powers = powers
        self.sums = []
        half, low = np.uint64(31), np.uint64((1 << 31) - 1)
        for up in powers.up:
            up, byte = up[: len(data)], data.astype(np.uint64) + np.uint64(1)
            high = (up >> np.uint64(32)) * byte
            term = (up & np.uint64(0xFFFFFFFF)) * byte
            term += high >> np.uint64(29)
            term += (high & np.uint64((1 << 29) - 1)) << np.uint64(32)
            term = (term & _PRIME) + (term >> np.uint64(61))
            least, most = np.cumsum(term & low), np.cumsum(term >> half)  # exact up to 2**33 bytes
            s = np.zeros(len(data) + 1, np.uint64)
            s[1:] = _fold(least + (most >> np.uint64(30)) + ((most & np.uint64((1 << 30) - 1)) << half))
            self.sums.append(s)

    def of(self, start: np.ndarray, stop: np.ndarray, k: int = 0) -> np.ndarray:
        s = self.sums[k]
        return _times(_fold(s[stop] + (_PRIME - s[start])), self.powers.down[k][start])


def _local(data: np.ndarray) -> np.ndarray:
    """A hash of the CUT_BYTES bytes at each place; it only says where to cut."""
    word = data.astype(np.uint64)
    for step in (1, 2, 4):
        word = word[:-step] | (word[step:] << np.uint64(8 * step))
    return _mix(word[:-8] * _ODD ^ _mix(word[8:]))


def cuts(data: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """Places where the content cuts texts: strict minima, within CUT_APART, among local hashes that are low at all.

    first, last: first byte of each document and the last place in it where a string of the window starts.
    """
    if len(data) < CUT_BYTES:
        return np.zeros(0, np.int64)
    h = _local(data)
    low = np.flatnonzero(h < np.uint64(1 << 59))  # one in 32
    doc = np.searchsorted(first, low, "right") - 1
    inside = low <= last[doc] + CUT_APART
    low, doc = low[inside], doc[inside]
    value = h[low]
    del h
    least = np.ones(len(low), bool)
    for s in range(1, len(low)):
        near = (low[s:] - low[:-s] < CUT_APART) & (doc[s:] == doc[:-s])
        if not (low[s:] - low[:-s] < CUT_APART).any():
            break
        least[:-s] &= ~(near & (value[:-s] >= value[s:]))
        least[s:] &= ~(near & (value[s:] >= value[:-s]))
    return low[least & (low <= last[doc]) & (low > first[doc])]


def _pack(kind: int, part: int, uid: int, *columns: np.ndarray) -> tuple:
    return (part, kind, uid, len(columns[0]), b"".join(np.ascontiguousarray(c).tobytes() for c in columns))


class Batch:
    """Documents of one buffer, in ascending id order."""

    def __init__(self, rows: list[tuple[int, int, bytes]], window: int, powers: Powers):
        rows.sort(key=lambda r: r[:2])
        self.ids = np.array([r[0] for r in rows], np.int64)
        self.text_hash = np.array([r[1] for r in rows], np.int64)
        sizes = np.array([len(r[2]) for r in rows], np.int64)
        self.first = np.cumsum(sizes) - sizes
        self.last = self.first + sizes - window
        self.data = np.frombuffer(b"".join(r[2] for r in rows), np.uint8)
        self.prefixes = Prefixes(self.data, powers)
        self.uid = int.from_bytes(hashlib.blake2b(self.ids.tobytes() + self.text_hash.tobytes(), digest_size=8).digest(), "little", signed=True)

    def named(self, window: int, parts: int) -> list[tuple]:
        """Rows to deal out: samples (kind 1), marked samples (2), pieces (3), repeated pieces (4), the documents (0)."""
        v, cover = cover_for(window)
        width = window - v + 1
        start = np.sort(np.concatenate([self.first, cuts(self.data, self.first, self.last)]))
        owner = np.searchsorted(self.first, start, "right") - 1
        stop = np.concatenate([start[1:], [len(self.data)]])
        stop = np.minimum(stop, self.last[owner] + 1)
        out = [_pack(0, self.uid % parts, self.uid, self.ids, self.text_hash, self.first)]

        a, b = self.prefixes.of(start, stop + window - 1), self.prefixes.of(start, stop + window - 1, 1)
        order = np.lexsort((start, b, a))
        again = np.concatenate([[False], (a[order][1:] == a[order][:-1]) & (b[order][1:] == b[order][:-1])])
        # a piece of a row whose id occurs twice is as early as the other row's
        known = np.zeros(len(start), bool)
        if again.any():
            group = np.cumsum(~again) - 1
            head = order[~again][group]
            known[order] = again & ((self.ids[owner[order]] != self.ids[owner[head]]) | (start[order] - self.first[owner[order]] != start[head] - self.first[owner[head]]))
        if known.any():
            out.append(_pack(4, self.uid % parts, self.uid, start[known].astype(np.uint32), stop[known].astype(np.uint32)))
        new = np.flatnonzero(~known)
        part = (_mix(a[new]) % np.uint64(parts)).astype(np.int64)
        by = np.argsort(part, kind="stable")
        for p, at in _runs(part[by]):
            x = new[by[at]]
            out.append(_pack(3, p, self.uid, a[x], b[x], self.ids[owner[x]], start[x] - self.first[owner[x]], start[x].astype(np.uint32), stop[x].astype(np.uint32)))

        sampled = [np.add.outer(np.arange(0, n + v, v), np.sort(cover)).reshape(-1) for n in (self.last - self.first + v).tolist()]
        sampled = [x[: np.searchsorted(x, n)] for x, n in zip(sampled, (self.last - self.first + v).tolist(), strict=True)]
        d = np.repeat(np.arange(len(self.ids)), [len(x) for x in sampled])
        p = np.concatenate(sampled) + self.first[d]
        name = _mix(self.prefixes.of(p, p + width))
        left = np.searchsorted(start, np.maximum(p - v + 1, self.first[d]), "right") - 1
        right = np.searchsorted(start, np.minimum(p, self.last[d]), "right") - 1
        at_start = start[left] == self.first[d]
        tag = _mix(self.prefixes.of(start[left], stop[right] + window - 1, 1) + (p - start[left]).astype(np.uint64) * _ODD + at_start.astype(np.uint64))
        tag >>= np.uint64(24)
        order = np.lexsort((p, tag, name))
        name, tag, p = name[order], tag[order], p[order]
        same = name[1:] == name[:-1]
        one = np.concatenate([[True], ~(same & (tag[1:] == tag[:-1]))])  # the first place of each name and tag
        name, tag, p = name[one], tag[one], p[one]
        same = np.concatenate([[False], name[1:] == name[:-1], [False]])
        several = same[1:] | same[:-1]
        if several.any():
            out.append(_pack(2, self.uid % parts, self.uid, np.sort(p[several]).astype(np.uint32)))
        send = ~same[:-1] | ~np.concatenate([[False], same[:-2]]) if len(name) else np.zeros(0, bool)  # at most two places of a name
        name, tag, p = name[send], tag[send], p[send]
        part = (name % np.uint64(parts)).astype(np.int64)
        rest = name // np.uint64(parts)
        by = np.lexsort((p, part))
        part, rest, tag, p = part[by], rest[by], tag[by], p[by]
        for k, at in _runs(part):
            low, place = rest[at].view(np.uint8).reshape(-1, 8)[:, :4], tag[at].view(np.uint8).reshape(-1, 8)[:, :5]
            gaps = np.diff(p[at], prepend=0).astype(np.uint32).view(np.uint8).reshape(-1, 4).T
            out.append(_pack(1, k, self.uid, low, place, gaps))
        return out

    def merged(self, at: np.ndarray, window: int, parts: int) -> list[tuple]:
        """Rows to deal out: strings of the window at candidate places (kind 5), those later than an equal one here (2), documents (0)."""
        owner = np.searchsorted(self.first, at, "right") - 1
        x, y = _mix(self.prefixes.of(at, at + window)), self.prefixes.of(at, at + window, 1)
        out = [_pack(0, self.uid % parts, self.uid, self.ids, self.text_hash, self.first)]
        later = np.zeros(len(at), bool)
        later[_later(x, y, self.ids[owner], at - self.first[owner])] = True
        if later.any():
            out.append(_pack(2, self.uid % parts, self.uid, at[later].astype(np.uint32)))
        at, owner, x, y = at[~later], owner[~later], x[~later], y[~later]
        part = (x % np.uint64(parts)).astype(np.int64)
        x = x // np.uint64(parts)
        y = _mix(y) >> np.uint64(24)
        by = np.argsort(part, kind="stable")
        part, at, owner, x, y = part[by], at[by], owner[by], x[by], y[by]
        for p, k in _runs(part):
            docs, held = np.unique(owner[k], return_counts=True)
            low = x[k].view(np.uint8).reshape(-1, 8)[:, :6]
            gaps = np.diff(at[k], prepend=0).astype(np.uint32).view(np.uint8).reshape(-1, 4).T
            head = (len(docs).to_bytes(4, "little"), self.ids[docs].astype("<i8").tobytes(), self.first[docs].astype("<u4").tobytes(), held.astype("<u4").tobytes())
            more = y[k].view(np.uint8).reshape(-1, 8)[:, :5]
            body = (np.ascontiguousarray(low).tobytes(), np.ascontiguousarray(more).tobytes(), np.ascontiguousarray(gaps).tobytes())
            out.append((p, 5, self.uid, len(at[k]), b"".join(head + body)))
        return out


def _runs(sorted_values: np.ndarray):
    if len(sorted_values):
        edge = np.concatenate([[0], np.flatnonzero(sorted_values[1:] != sorted_values[:-1]) + 1, [len(sorted_values)]])
        for a, b in zip(edge[:-1], edge[1:], strict=True):
            yield int(sorted_values[a]), slice(a, b)


_NAMED = "part int, kind int, uid bigint, n int, packed binary"
_FIELDS = ["part", "kind", "uid", "n", "packed"]


def _table(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.binary()]
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], _FIELDS)


def _buffers(batches, window: int, powers: Powers):
    rows, size = [], 0
    for b in batches:
        for doc, h, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).cast(pa.binary()).to_pylist(), strict=True):
            if text is not None and len(text) >= window:
                rows.append((doc, h, text))
                size += len(text)
                if size >= BATCH:
                    yield Batch(rows, window, powers)
                    rows, size = [], 0
    if rows:
        yield Batch(rows, window, powers)


def _split(raw: bytes, n: int, *kinds: str) -> list[np.ndarray]:
    out, at = [], 0
    for kind in kinds:
        step = np.dtype(kind)
        out.append(np.frombuffer(raw, step, n, at))
        at += n * step.itemsize
    return out


@tidy
def _meet(batches):
    """A partition of dealt-out rows: marks the samples whose name lies at two places, and the pieces that are not the first."""
    rows = [r for b in batches for r in zip(*(c.to_pylist() for c in b.columns), strict=True)]
    passed = [r for r in rows if r[1] in (0, 2, 4)]
    if passed:
        yield _table(passed)
    samples = [r for r in rows if r[1] == 1]
    if samples:
        names, tags, places, source = [], [], [], []
        for i, (_, _, _, n, raw) in enumerate(samples):
            names.append(np.frombuffer(raw, "<u4", n))
            wide = np.zeros((n, 8), np.uint8)
            wide[:, :5] = np.frombuffer(raw, np.uint8, 5 * n, 4 * n).reshape(n, 5)
            tags.append(wide.view("<u8").reshape(-1))
            gaps = np.ascontiguousarray(np.frombuffer(raw, np.uint8, 4 * n, 9 * n).reshape(4, n).T).view("<u4").reshape(-1)
            places.append(np.cumsum(gaps, dtype=np.int64).astype(np.uint32))
            source.append(np.full(n, i, np.int32))
        name, tag, place, source = map(np.concatenate, (names, tags, places, source))
        del names, tags, places
        order = np.argsort(name)
        name, tag = name[order], tag[order]
        edge = np.concatenate([[0], np.flatnonzero(name[1:] != name[:-1]) + 1])
        several = np.minimum.reduceat(tag, edge) != np.maximum.reduceat(tag, edge)
        marked = order[np.repeat(several, np.diff(np.append(edge, len(name))))]
        marked = marked[np.lexsort((place[marked], source[marked]))]
        found = [_pack(2, 0, samples[i][2], place[marked[at]]) for i, at in _runs(source[marked])]
        if found:
            yield _table(found)
    pieces = [r for r in rows if r[1] == 3]
    if pieces:
        parts = [_split(r[4], r[3], "<u8", "<u8", "<i8", "<i8", "<u4", "<u4") for r in pieces]
        a, b, doc, at, start, stop = (np.concatenate(c) for c in zip(*parts, strict=True))
        source = np.repeat(np.arange(len(pieces)), [r[3] for r in pieces])
        later = _later(a, b, doc, at)
        later = later[np.lexsort((start[later], source[later]))]
        found = [_pack(4, 0, pieces[i][2], start[later[x]], stop[later[x]]) for i, x in _runs(source[later])]
        if found:
            yield _table(found)


def _later(a: np.ndarray, b: np.ndarray, doc: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Indices of those whose (a, b) also stands at a smaller (doc, at)."""
    order = np.lexsort((at, doc, b, a))
    a, b, doc, at = a[order], b[order], doc[order], at[order]
    new = np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])]) if len(a) else np.zeros(0, bool)
    head = np.flatnonzero(new)[np.cumsum(new) - 1]
    return order[(doc != doc[head]) | (at != at[head])]


def _by_document(key, table: pa.Table) -> pa.Table:
    """The marks of one buffer, by document: samples and pieces, counted from the document's first byte."""
    rows = list(zip(*(table.column(c).to_pylist() for c in ("kind", "n", "packed")), strict=True))
    maps = [r for r in rows if r[0] == 0]
    if not maps:
        raise RuntimeError("the input's rows changed between reads; write it to a table first")
    ids, hashes, first = _split(maps[0][2], maps[0][1], "<i8", "<i8", "<i8")
    samples = np.sort(np.concatenate([np.zeros(0, np.uint32), *(_split(r[2], r[1], "<u4")[0] for r in rows if r[0] == 2)])).astype(np.int64)
    pieces = [_split(r[2], r[1], "<u4", "<u4") for r in rows if r[0] == 4]
    start = np.concatenate([np.zeros(0, np.uint32), *(p[0] for p in pieces)]).astype(np.int64)
    stop = np.concatenate([np.zeros(0, np.uint32), *(p[1] for p in pieces)]).astype(np.int64)
    order = np.argsort(start)
    start, stop = start[order], stop[order]
    in_s = np.append(np.searchsorted(samples, first), len(samples))
    in_p = np.append(np.searchsorted(start, first), len(start))
    out = [
        (
            int(ids[d]),
            int(hashes[d]),
            (samples[in_s[d] : in_s[d + 1]] - first[d]).astype("<u4").tobytes(),
            (np.stack([start[in_p[d] : in_p[d + 1]], stop[in_p[d] : in_p[d + 1]]], 1) - first[d]).astype("<u4").tobytes(),
        )
        for d in np.flatnonzero((np.diff(in_s) > 0) | (np.diff(in_p) > 0))
    ]
    kinds = [pa.int64(), pa.int64(), pa.binary(), pa.binary()]
    return pa.table([pa.array([r[i] for r in out], k) for i, k in enumerate(kinds)], names=["doc", "text_hash", "samples", "pieces"])


def _starts(raw: bytes, n: int) -> np.ndarray:
    """Which of n places lie in the packed (start, stop) pairs."""
    edge = np.zeros(n + 1, np.int32)
    pairs = np.frombuffer(raw, "<u4").reshape(-1, 2).astype(np.int64)
    np.add.at(edge, pairs[:, 0], 1)
    np.add.at(edge, pairs[:, 1], -1)
    return np.cumsum(edge[:n]) > 0


def _candidates(size: int, samples: bytes, pieces: bytes, window: int) -> np.ndarray:
    """Places in pieces that stay, whose string of the window holds a marked sample where the cover may have put it."""
    n = size - window + 1
    v, _ = cover_for(window)
    edge = np.zeros(n + 1, np.int32)
    p = np.frombuffer(samples, "<u4").astype(np.int64)
    np.add.at(edge, np.maximum(p - v + 1, 0), 1)
    np.add.at(edge, np.minimum(p + 1, n), -1)
    return np.flatnonzero((np.cumsum(edge[:n]) > 0) & ~_starts(pieces, n))


def repeated_starts(docs: DataFrame, window: int = WINDOW, work: Workspace | None = None) -> DataFrame:
    """doc, text_hash, pieces, starts: where strings of the window begin that also begin earlier, as packed pairs and packed places.

    docs: doc (bigint), text_hash, text, from files or any input whose rows come in the same order when read again. See the
    module's docstring for the steps. Shuffled are about 1.3 bytes for each byte of text in step 1, then the texts of documents with
    marked samples and the places of step 2. Within a buffer of a task names are made unique first, so a passage that very many
    documents share sends at most two rows a buffer to its partition.
    """
    spark = docs.sparkSession
    work = work or Workspace(spark, "suffix-dedup")
    bounded_batches(spark)
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-total // PART_BYTES))
    bases = random_bases()

    @tidy
    def name(batches):
        powers = powers_of(bases)
        for buffer in _buffers(batches, window, powers):
            rows = buffer.named(window, parts)
            for i in range(0, len(rows), 64):
                yield _table(rows[i : i + 64])
            del buffer, rows

    dealt = docs.mapInArrow(name, _NAMED).repartitionById(parts, "part")
    met = work.save(dealt.mapInArrow(_meet, _NAMED).select("kind", "uid", "n", "packed"), "met")
    work.release()
    kinds = "doc bigint, text_hash bigint, samples binary, pieces binary"
    marks = work.save(met.groupBy("uid").applyInArrow(lambda key, table: _by_document(key, table), kinds), "marks")
    work.drop("met")

    @tidy
    def merge(batches):
        powers = powers_of(bases)
        for buffer, at in _candidate_buffers(batches, window, powers):
            yield _table(buffer.merged(at, window, parts))
            del buffer, at

    sampled = marks.where(F.octet_length("samples") > 0)
    joined = docs.join(sampled, ["doc", "text_hash"]).select("doc", "text_hash", "text", "samples", "pieces")
    # in an order of their own, so that a task that is run again makes the same buffers
    named = joined.sortWithinPartitions("doc", "text_hash").mapInArrow(merge, _NAMED)
    compared = work.save(named.repartitionById(parts, "part").mapInArrow(_compare, _NAMED).select("kind", "uid", "n", "packed"), "compared")
    work.release()
    kinds = "doc bigint, text_hash bigint, samples binary, pieces binary"
    later = work.save(compared.groupBy("uid").applyInArrow(lambda key, table: _by_document(key, table), kinds), "later")
    work.drop("compared")
    none = F.lit(None).cast("binary")
    whole = marks.where(F.octet_length("pieces") > 0).select("doc", "text_hash", "pieces", none.alias("starts"))
    parts_of = whole.unionByName(later.select("doc", "text_hash", none.alias("pieces"), F.col("samples").alias("starts")))
    return parts_of.groupBy("doc", "text_hash").agg(F.collect_list("pieces").alias("pieces"), F.collect_list("starts").alias("starts"))


def _candidate_buffers(batches, window: int, powers: Powers):
    """(buffer, candidate places in it) of joined documents."""
    rows, size = [], 0

    def ready():
        marks = {r[:2]: r[3:] for r in rows}
        buffer = Batch([r[:3] for r in rows], window, powers)
        stop = buffer.last + window
        at = [
            buffer.first[i] + _candidates(int(stop[i] - buffer.first[i]), *marks[int(buffer.ids[i]), int(buffer.text_hash[i])], window) for i in range(len(buffer.ids))
        ]
        return buffer, np.concatenate(at)

    for b in batches:
        columns = [b.column(i).to_pylist() for i in (0, 1, 3, 4)]
        for doc, h, samples, pieces, text in zip(*columns, b.column(2).cast(pa.binary()).to_pylist(), strict=True):
            rows.append((doc, h, text, samples, pieces))
            size += len(text)
            if size >= BATCH:
                yield ready()
                rows, size = [], 0
    if rows:
        yield ready()


@tidy
def _compare(batches):
    """A partition of dealt-out strings of the window: marks all but the first of equal ones."""
    rows = [r for b in batches for r in zip(*(c.to_pylist() for c in b.columns), strict=True)]
    passed = [r for r in rows if r[1] in (0, 2)]
    if passed:
        yield _table(passed)
    dealt = [r for r in rows if r[1] == 5]
    if not dealt:
        return
    xs, ys, docs, ats, places, source = [], [], [], [], [], []
    for i, (_, _, _, n, raw) in enumerate(dealt):
        n_docs = int.from_bytes(raw[:4], "little")
        doc, first, held = _split(raw[4:], n_docs, "<i8", "<u4", "<u4")
        at = 4 + 16 * n_docs
        x = np.zeros((n, 8), np.uint8)
        x[:, :6] = np.frombuffer(raw, np.uint8, 6 * n, at).reshape(n, 6)
        y = np.zeros((n, 8), np.uint8)
        y[:, :5] = np.frombuffer(raw, np.uint8, 5 * n, at + 6 * n).reshape(n, 5)
        gaps = np.ascontiguousarray(np.frombuffer(raw, np.uint8, 4 * n, at + 11 * n).reshape(4, n).T).view("<u4").reshape(-1)
        place = np.cumsum(gaps, dtype=np.int64)
        xs.append(x.view("<u8").reshape(-1))
        ys.append(y.view("<u8").reshape(-1))
        docs.append(np.repeat(doc, held))
        ats.append(place - np.repeat(first.astype(np.int64), held))
        places.append(place.astype(np.uint32))
        source.append(np.full(n, i, np.int32))
    x, y, doc, at, place, source = map(np.concatenate, (xs, ys, docs, ats, places, source))
    later = _later(x, y, doc, at)
    later = later[np.lexsort((place[later], source[later]))]
    found = [_pack(2, 0, dealt[i][2], place[later[k]]) for i, k in _runs(source[later])]
    if found:
        yield _table(found)


def removed_mask(size: int, pieces: list[bytes] | None, starts: list[bytes] | None, window: int) -> np.ndarray:
    """Which bytes of a text are covered by strings of the window that begin at the marked places."""
    mask = np.zeros(size, bool)
    n = size - window + 1
    if n <= 0 or not (pieces or starts):
        return mask
    at = np.zeros(n, bool)
    for raw in pieces or ():
        at |= _starts(raw, n)
    for raw in starts or ():
        at[np.frombuffer(raw, "<u4")] = True
    edge = np.zeros(size + 1, np.int32)
    edge[:n] += at
    edge[window : window + n] -= at
    return np.cumsum(edge[:size]) > 0


def remove_repeats(docs: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", keep_text: bool = True) -> DataFrame:
    """Removes each byte that a string of so many bytes covers which also starts earlier: in a smaller id, or earlier in its text.

    Gives id, n_bytes, n_removed, n_spans, kept_sha256 and, with keep_text, kept (binary) of every row. Texts are UTF-8 bytes;
    overlaps count; strings are judged on the input. Null and shorter texts lose nothing. Rows that share an id are as early as each
    other: copies among them all stay. Null ids come after all others. An empty table gives no rows; other columns are ignored.
    """
    spark = docs.sparkSession
    work = Workspace(spark, "suffix-dedup")
    kind = dict(docs.dtypes)[id_col]
    rows = docs.select(F.coalesce(F.col(id_col).cast("bigint"), F.lit(_LAST)).alias("doc"), F.xxhash64(text_col).alias("text_hash"), F.col(text_col).cast("string").alias("text"), F.col(id_col).alias("id"))
    marked = repeated_starts(rows.select("doc", "text_hash", "text"), window, work)

    @tidy
    def cut(batches):
        for b in batches:
            out = []
            for text, pieces, starts in zip(b.column(1).cast(pa.binary()).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True):
                text = text or b""
                mask = removed_mask(len(text), pieces, starts, window)
                kept = np.frombuffer(text, np.uint8)[~mask].tobytes() if mask.any() else text
                spans = int((np.diff(mask.astype(np.int8), prepend=0) == 1).sum())
                out.append((len(text), int(mask.sum()), spans, hashlib.sha256(kept).hexdigest(), kept))
            names, kinds = ["n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"], [pa.int64()] * 3 + [pa.string(), pa.binary()]
            use = range(5 if keep_text else 4)
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array([r[i] for r in out], kinds[i]) for i in use)], [id_col, *(names[i] for i in use)])

    bounded_batches(spark)
    joined = rows.join(marked, ["doc", "text_hash"], "left").select("id", "text", "pieces", "starts")
    return joined.mapInArrow(cut, f"`{id_col}` {kind}, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string" + (", kept binary" if keep_text else ""))


def without_repeats(docs: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with repeated bytes taken out of the text, and n_chars, where there is one of an integer type, counted anew.

    A character that loses some of its bytes is taken out whole, so texts stay valid; null texts stay null. All rows stay.
    """
    spark = docs.sparkSession
    work = Workspace(spark, "suffix-dedup")
    keyed = docs.withColumn("__doc", F.coalesce(F.col(id_col).cast("bigint"), F.lit(_LAST))).withColumn("__hash", F.xxhash64(text_col))
    marked = repeated_starts(keyed.select(F.col("__doc").alias("doc"), F.col("__hash").alias("text_hash"), F.col(text_col).cast("string").alias("text")), window, work)
    marked = marked.select(F.col("doc").alias("__doc"), F.col("text_hash").alias("__hash"), F.col("pieces").alias("__pieces"), F.col("starts").alias("__starts"))
    joined = keyed.join(marked, ["__doc", "__hash"], "left").select(*docs.columns, "__pieces", "__starts")
    names = docs.columns

    @tidy
    def cut(batches):
        for b in batches:
            out = []
            at = names.index(text_col)
            pieces, starts = (b.column(b.schema.get_field_index(c)).to_pylist() for c in ("__pieces", "__starts"))
            for text, p, s in zip(b.column(at).cast(pa.binary()).to_pylist(), pieces, starts, strict=True):
                if text is not None and (p or s):
                    mask = removed_mask(len(text), p, s, window)
                    text = np.frombuffer(text, np.uint8)[~_whole_characters(text, mask)].tobytes()
                out.append(None if text is None else text.decode("utf-8", "ignore"))
            columns = [b.column(i) for i in range(len(names))]
            columns[at] = pa.array(out, pa.string())
            if n_chars:
                at = names.index("n_chars")
                columns[at] = pa.array([None if t is None else len(t) for t in out], pa.int64()).cast(columns[at].type)
            yield pa.RecordBatch.from_arrays(columns, names)

    bounded_batches(spark)
    n_chars = "n_chars" in names and isinstance(docs.schema["n_chars"].dataType, T.IntegralType)
    return joined.mapInArrow(cut, docs.schema)


def _whole_characters(text: bytes, mask: np.ndarray) -> np.ndarray:
    """mask, spread over all bytes of every UTF-8 character that it touches."""
    data = np.frombuffer(text, np.uint8)
    if not mask.any() or data.max() < 128:
        return mask
    character = np.cumsum((data & 0xC0) != 0x80)
    hit = np.zeros(character[-1] + 1, bool)
    hit[character[mask]] = True
    return hit[character]
