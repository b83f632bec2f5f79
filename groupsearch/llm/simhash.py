"""Near-duplicates by SimHash, candidates found by the pigeonring principle.

Fingerprints of 64 bits that differ in at most t bits are cut into m segments on a ring. Some start i then has, for every length
l, at most l * t / m differing bits in the l segments from i on. So the first segments of that chain, up to the largest l with
l * t < m, are equal: they are the key of a hash join. Longer chains are checked next, the full distance comes last.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Workspace, batches_of, bounded_batches, gathered, if_small, tidy
from .components import connected_components

#: Differing bits that still link, segments on the ring, distinct fingerprints of a key that are compared pair by pair.
LINK_BITS, SEGMENTS, PAIRWISE = 2, 5, 64
_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.int64)
_LANE = np.arange(8, dtype=np.uint16) * 256


def shingle_hashes(text: bytes, words: int) -> np.ndarray:
    """XXH64 (seed 42) of every run of so many words, joined by spaces; of the whole sequence where there are fewer."""
    w = text.lower().split()
    if not w:
        return np.zeros(0, np.uint64)
    x = xxhash.xxh64_intdigest
    if len(w) <= words:
        return np.array([x(b" ".join(w), 42)], np.uint64)
    return np.array([x(b" ".join(s), 42) for s in zip(*(w[i:] for i in range(words)), strict=False)], np.uint64)


def simhash_of(h: np.ndarray) -> int:
    """The bits that over half of the hashes have; zero of none."""
    if not len(h):
        return 0
    lanes = h.astype("<u8").view(np.uint8).reshape(-1, 8) + _LANE
    counts = np.bincount(lanes.reshape(-1), minlength=2048).reshape(8, 256) @ _BITS
    bits = (2 * counts > len(h)).reshape(-1)
    return int(np.packbits(bits, bitorder="little").view("<u8")[0])


def fingerprint(text: bytes, words: int = 3) -> int:
    """The SimHash of a text in UTF-8; zero without words."""
    return simhash_of(shingle_hashes(text, words))


def fingerprints(docs: DataFrame, words: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fp (signed) of every row; a null text counts as empty. A map over rows, no shuffle."""
    bounded_batches(docs.sparkSession)

    @tidy
    def run(batches):
        for b in batches:
            texts = b.column(1).cast(pa.binary()).to_pylist()
            fp = np.array([fingerprint(t or b"", words) for t in texts], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp, pa.int64())], ["doc_id", "fp"])

    kind = dict(docs.dtypes)[id_col]
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, f"doc_id {kind}, fp bigint")


def _segments(m: int) -> list[tuple[int, int]]:
    """(first bit, bits) of each segment."""
    cuts = [64 * i // m for i in range(m + 1)]
    return [(a, b - a) for a, b in zip(cuts, cuts[1:], strict=False)]


def chain_keys(fp: Column, t: int, m: int) -> Column:
    """For each start on the ring: the start and the bits of the segments that must be equal there."""
    run = math.ceil(m / t) - 1 if t else m
    out = []
    for i in range(m):
        key = F.lit(0).cast("bigint")
        for first, bits in (_segments(m)[(i + l) % m] for l in range(run)):
            part = F.shiftrightunsigned(fp, first).bitwiseAND(F.lit((1 << bits) - 1))
            key = F.shiftleft(key, bits).bitwiseOR(part)
        out.append(F.struct(F.lit(i).alias("start"), key.alias("key")))
    return F.array(*out)


def chain_check(start: Column, differing: Column, t: int, m: int) -> Column:
    """Whether, from a start on the ring, every chain of segments keeps within its share of t differing bits."""
    seg = []
    for first, bits in _segments(m):
        mask = ((1 << bits) - 1) << first
        seg.append(F.bit_count(differing.bitwiseAND(F.lit(mask - (1 << 64) if mask >> 63 else mask))))
    by_start = F.lit(False)
    for i in range(m):
        ok, so_far = F.lit(True), F.lit(0)
        for l in range(1, m + 1):
            so_far = so_far + seg[(i + l - 1) % m]
            ok = ok & (so_far <= l * t // m)
        by_start = F.when(start == i, ok).otherwise(by_start)
    return by_start


def fingerprint_links(distinct: DataFrame, work: Workspace, t: int = LINK_BITS, m: int = SEGMENTS, pairwise: int = PAIRWISE) -> DataFrame:
    """Edges u, v among distinct fingerprints (column fp) that join all that differ in t bits or fewer into the same components.

    Keys that up to ``pairwise`` fingerprints share are joined pair by pair. Of keys with more, every fingerprint is linked through
    the values at distance t/2: two fingerprints are within t of each other exactly if some value is within t/2 of both (t even),
    at most 65 fingerprints surround a value for t = 2, and the first of them links to the others. That is linear in the
    fingerprints whatever their number, and loses no component. t is 0 or 2 there; other t compare all keys pair by pair.
    """
    keyed = distinct.select("fp", F.explode(chain_keys(F.col("fp"), t, m)).alias("c")).select("fp", "c.start", "c.key")
    counts = keyed.groupBy("start", "key").agg(F.count("*").alias("n")).where("n > 1")
    shared = work.save(keyed.join(counts, ["start", "key"]), "shared")
    few = shared.where(F.col("n") <= pairwise) if t == 2 else shared
    a, b = few.select("start", "key", F.col("fp").alias("u")), few.select("start", "key", F.col("fp").alias("v"))
    differing = F.col("u").bitwiseXOR(F.col("v"))
    pairs = a.join(b, ["start", "key"]).where("u > v").where(chain_check(F.col("start"), differing, t, m)).where(F.bit_count(differing) <= t)
    links = pairs.select("u", "v").distinct()
    if t == 2:
        many = shared.where(F.col("n") > pairwise).select("fp").distinct()
        near = F.array(F.lit(0).cast("bigint"), *[F.lit((1 << b) - (1 << 64) if b == 63 else 1 << b) for b in range(64)])
        around = many.select("fp", F.explode(near).alias("flip")).select("fp", F.col("fp").bitwiseXOR(F.col("flip")).alias("value"))
        held = around.groupBy("value").agg(F.collect_list("fp").alias("fps")).where(F.size("fps") > 1)
        least = F.array_min("fps")
        links = links.unionByName(held.select(F.explode("fps").alias("u"), least.alias("v")).where("u <> v").distinct())
    return links


def near_duplicates(
    docs: DataFrame, words: int = 3, t: int = LINK_BITS, m: int = SEGMENTS, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (the smallest doc_id reachable by links of t bits or fewer).

    Texts are lower-cased in A-Z and cut at ASCII white space. A null text counts as empty; texts without words have fingerprint
    zero and link like others. Repeated rows give a row each; equal ids link their rows' groups only through their fingerprints.
    Null ids are kept with their own fingerprint and never name a component unless all ids in it are null. An empty table gives no
    rows; other columns are ignored.

    Whole texts are read once. Equal fingerprints meet in a partial aggregate, so a group of copies of any size is one row from
    there on; only distinct fingerprints are joined, by keys of the pigeonring.
    """
    work = Workspace(docs.sparkSession, "simhash")
    rows = work.save(fingerprints(docs, words, id_col, text_col), "rows")
    distinct = work.save(rows.groupBy("fp").agg(F.min("doc_id").alias("first")), "distinct")
    roots = connected_components(fingerprint_links(distinct, work, t, m), work)
    placed = work.save(distinct.join(roots, distinct.fp == roots.node, "left").select("fp", "first", F.coalesce("root", "fp").alias("root")), "placed")
    named = placed.groupBy("root").agg(F.min("first").alias("component_id"))
    of_fp = work.save(placed.join(named, "root").select("fp", "component_id"), "of-fp")
    hexed = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return rows.join(of_fp, "fp").select("doc_id", hexed.alias("fingerprint"), "component_id")


#: Near copies: words of a shingle, least similarity, chance that a pair of that similarity shares no key.
NEAR_WORDS, NEAR_SIMILARITY, OVERLOOKED = 5, 0.8, 1e-6
#: Least values that make one key.
ROWS = 8
#: Hashes of a sketch; pairs whose sketches are this much less similar than asked for aren't read again.
SKETCH, MARGIN = 128, 0.2
#: Bytes of sketches or texts of leaders that are broadcast.
BROADCAST_BYTES = 64 << 20
#: Pairs of one shingle that are still open and are then compared directly; salts by which a shingle with more names leaders.
PAIRS_OF_KEY, SALTS = 4_000_000, 1024


def bands_for(rows: int, similarity: float, overlooked: float = OVERLOOKED) -> int:
    """Keys of so many least values each, so that two sets of that similarity share none only that rarely."""
    return max(1, math.ceil(math.log(overlooked) / math.log1p(-(similarity**rows)))) if similarity < 1 else 1


def _scramble(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(29))


def band_keys(h: np.ndarray, rows: int, bands: int) -> np.ndarray:
    """Keys of a set of hashes: the least value under each of rows * bands multiplications, so many to a key; none of an empty set."""
    if not len(h):
        return np.zeros(0, np.int64)
    odd = np.random.default_rng(rows).integers(0, 1 << 63, rows * bands, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    least = np.empty(len(odd), np.uint64)
    step = max(1, (1 << 17) // len(h))
    for i in range(0, len(odd), step):
        least[i : i + step] = (odd[i : i + step, None] * h[None, :]).min(1)
    key = np.arange(bands, dtype=np.uint64)
    for column in least.reshape(bands, rows).T:
        key = _scramble(key ^ column)
    return key.view(np.int64)


def sketch_similarity(a: bytes, b: bytes, k: int = SKETCH) -> float:
    """Jaccard similarity from two bottom-k sketches: exact where neither set has more than k, else of the k least of the union."""
    x, y = np.frombuffer(a, "<u4"), np.frombuffer(b, "<u4")
    if not len(x) and not len(y):
        return 1.0
    union = np.union1d(x, y)
    if len(x) >= k or len(y) >= k:
        union = union[:k]
    both = np.intersect1d(x, y, assume_unique=True)
    return float(np.searchsorted(both, union[-1], "right")) / len(union) if len(union) else 0.0


def similar(a: np.ndarray, b: np.ndarray, similarity: float) -> bool:
    """Whether two sets of distinct hashes have that Jaccard similarity; two empty ones do."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both >= similarity * (len(a) + len(b) - both) - 1e-9


class _Copies:
    """One search for near copies: what was read of the documents, links found so far, and pairs that were compared."""

    def __init__(self, texts: DataFrame, words: int, similarity: float):
        self.texts, self.words, self.similarity = texts, words, similarity
        self.work = Workspace(texts.sparkSession, "near-copies")
        self.steps, self.stored = 0, []

    def save(self, df: DataFrame, name: str) -> DataFrame:
        self.steps += 1
        self.stored.append(f"{name}-{self.steps}")
        return self.work.save(df, self.stored[-1])

    def keep(self, *names: str) -> None:
        """Deletes all saved tables but these: no later step reads them."""
        self.work.drop(*(x for x in self.stored if x not in names))
        self.stored = [x for x in self.stored if x in names]

    def done(self, before: list[str]) -> None:
        """A step's last table is its result; what it saved on the way, besides what was there before it, goes."""
        self.keep(*before, self.stored[-1])

    def read(self) -> DataFrame:
        """doc_id, fp, n (distinct shingles), set_a, set_b (128 bits that name the set), keys, sketch of every row."""
        words, bands = self.words, bands_for(ROWS, self.similarity)

        @tidy
        def run(batches):
            for b in batches:
                out = []
                for t in b.column(1).cast(pa.binary()).to_pylist():
                    h = shingle_hashes(t or b"", words)
                    own = np.unique(h)
                    name = hashlib.blake2b(own.tobytes(), digest_size=16).digest()
                    sketch = np.unique((own >> np.uint64(32)).astype(np.uint32))[:SKETCH].astype("<u4").tobytes()
                    fp = simhash_of(h)
                    out.append((fp - (1 << 64) if fp >> 63 else fp, len(own), *(int.from_bytes(name[i : i + 8], "little", signed=True) for i in (0, 8)), band_keys(own, ROWS, bands), sketch))
                yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array([r[i] for r in out], k) for i, k in enumerate(_READ_KINDS))], _READ)

        kinds = "doc_id bigint, fp bigint, n bigint, set_a bigint, set_b bigint, keys array<bigint>, sketch binary"
        return self.save(self.texts.mapInArrow(run, kinds), "rows")

    def compare(self, pairs: DataFrame) -> DataFrame:
        """u, v of the pairs whose whole texts have the similarity; sizes and sketches first discard those far below it."""
        words, similarity, before = self.words, self.similarity, list(self.stored)
        pairs = self.save(pairs.select("u", "v").distinct(), "pairs")

        def both(table: DataFrame, found: DataFrame, wide: str, *columns: str) -> DataFrame:
            """found, a saved table, with columns of both documents. v, which may be the leader of very many, comes first: broadcast if all are small."""
            named = gathered(found)
            for side in ("v", "u"):
                ids = self.save(named.select(F.col(side).alias("doc_id")).distinct(), "ids")
                held = self.save(table.select("doc_id", *columns, wide).join(if_small(ids), "doc_id", "left_semi"), "held")
                size = held.agg(F.coalesce(F.sum(F.octet_length(wide) + 64), F.lit(0))).first()[0]
                held = held.select(F.col("doc_id").alias(side), *(F.col(c).alias(f"{c}_{side}") for c in (*columns, wide)))
                found = found.join(F.broadcast(held) if size <= BROADCAST_BYTES else held, side)
            return found

        @tidy
        def discard(batches):
            for b in batches:
                x, y = b.column(2).to_pylist(), b.column(3).to_pylist()
                yield b.filter(pa.array([sketch_similarity(p, q) >= similarity - MARGIN for p, q in zip(x, y, strict=True)], pa.bool_())).select([0, 1])

        sized = both(self.rows, pairs, "sketch", "n").where(F.least("n_u", "n_v") >= similarity * F.greatest("n_u", "n_v") - 1e-9)
        likely = self.save(sized.select("u", "v", "sketch_u", "sketch_v").mapInArrow(discard, "u bigint, v bigint").distinct(), "likely")
        self.done(before)

        @tidy
        def verify(batches):
            known: dict[bytes, np.ndarray] = {}  # leaders come again and again
            for b in batches:
                x, y = (c.cast(pa.binary()).to_pylist() for c in b.columns[2:4])
                ok = []
                for p, q in zip(x, y, strict=True):
                    if q not in known:
                        if len(known) >= 64:
                            known.clear()
                        known[q] = np.unique(shingle_hashes(q or b"", words))
                    ok.append(similar(np.unique(shingle_hashes(p or b"", words)), known[q], similarity))
                yield b.filter(pa.array(ok, pa.bool_())).select([0, 1])

        with batches_of(self.texts.sparkSession, 64):
            links = self.save(both(self.texts, likely, "text").select("u", "v", "text_u", "text_v").mapInArrow(verify, "u bigint, v bigint").distinct(), "links")
        self.done(before)
        return links

    def open_keys(self, keyed: DataFrame, links: DataFrame) -> DataFrame:
        """keyed (key, doc_id, ...) of the keys that documents of several components share, with comp, and open: their pairs between components."""
        before, work = list(self.stored), Workspace(self.texts.sparkSession, "near-copies-roots")
        roots = connected_components(links, work)
        comp = keyed.join(if_small(roots), F.col("doc_id") == F.col("node"), "left").select(*keyed.columns, F.coalesce("root", "doc_id").alias("comp"))
        comp = self.save(comp, "placed")
        work.delete()
        held = gathered(comp).groupBy("key", "comp").agg(F.count("*").alias("n")).groupBy("key").agg(F.count("*").alias("comps"), F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("n2"))
        several = held.where("comps > 1").select("key", ((F.col("n") * F.col("n") - F.col("n2")) / 2).alias("open"))
        out = self.save(comp.join(if_small(self.save(several, "several")), "key"), "open")
        self.done(before)
        return out

    def shared_keys(self, keyed: DataFrame) -> DataFrame:
        """key, doc_id, lead (the smallest document) of the keys that several documents have."""
        before = list(self.stored)
        counts = self.save(keyed.groupBy("key").agg(F.min("doc_id").alias("lead"), F.max("doc_id").alias("last")).where("lead < last").select("key", "lead"), "counts")
        out = self.save(keyed.join(if_small(counts), "key").select("key", "doc_id", "lead").distinct(), "shared")
        self.done(before)
        return out

    def prefixes(self, placed: DataFrame) -> DataFrame:
        """key, doc_id, n, before: the rarest shingles of each document, so many that two documents of the similarity share one of them.

        placed: doc_id, comp. Of n shingles sharing may leave out n - similarity * n; one more makes a prefix in any common order, here by
        how many components hold a shingle. Shingles that only one component holds join no two: they come first and need no rows.
        before: shingles ahead of the key.
        """
        words, before = self.words, list(self.stored)

        @tidy
        def run(batches):
            for b in batches:
                own = [np.unique(shingle_hashes(t or b"", words)).view(np.int64) for t in b.column(2).cast(pa.binary()).to_pylist()]
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(own, pa.list_(pa.int64()))], ["doc_id", "comp", "own"])

        held = self.texts.join(if_small(placed), "doc_id").select("doc_id", "comp", "text")
        held = self.save(held.mapInArrow(run, "doc_id bigint, comp bigint, own array<bigint>"), "shingles").select("doc_id", "comp", F.size("own").alias("n"), F.explode("own").alias("key"))
        common = held.groupBy("key", "comp").agg(F.lit(1).alias("one")).groupBy("key").agg(F.count("*").alias("comps"))
        common = self.save(common.where("comps > 1"), "common")
        ranked = held.drop("comp").distinct().join(if_small(common), "key").groupBy("doc_id", "n").agg(F.sort_array(F.collect_list(F.struct("comps", "key"))).alias("s"))
        lone = F.col("n") - F.size("s")
        length = F.col("n") - F.ceil(F.lit(self.similarity) * F.col("n") - F.lit(1e-9)) + 1 - lone
        first = ranked.select("doc_id", "n", lone.alias("lone"), F.posexplode(F.slice("s", F.lit(1), F.greatest(length, F.lit(0)).cast("int"))).alias("i", "k"))
        out = self.save(first.select("k.key", "doc_id", "n", (F.col("lone") + F.col("i")).alias("before")), "prefixes")
        self.done(before)
        return out

    def may_reach(self, a: str, b: str) -> Column:
        """Whether two documents whose first common shingle is the key may share enough: all they share lies from it on.

        Pairs that are similar enough pass at their first common shingle, and no other key needs to let them through.
        """
        behind = F.least(*(F.col(f"n_{x}") - F.col(f"before_{x}") for x in (a, b)))
        return behind >= F.lit(self.similarity / (1 + self.similarity)) * (F.col(f"n_{a}") + F.col(f"n_{b}")) - 1e-9

    def links(self) -> DataFrame:
        self.rows = rows = self.read()
        sets = self.save(rows.groupBy("set_a", "set_b").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).where("first < last").drop("last"), "sets")
        links = self.save(rows.select("doc_id", "set_a", "set_b").join(if_small(sets), ["set_a", "set_b"]).where("doc_id <> first").select(F.col("doc_id").alias("u"), F.col("first").alias("v")).distinct(), "same")
        single = rows.join(if_small(links.select(F.col("u").alias("doc_id")).distinct()), "doc_id", "left_anti")

        # nearest copies by the pigeonring, and the first holder of each key, which most copies of a text are similar to
        distinct = self.save(single.groupBy("fp").agg(F.min("doc_id").alias("first")), "fps")
        near = fingerprint_links(distinct, self.work)
        first = distinct.select(F.col("fp").alias("u"), F.col("first").alias("a")), distinct.select(F.col("fp").alias("v"), F.col("first").alias("b"))
        ringed = near.join(first[0], "u").join(first[1], "v").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
        equal = single.select("doc_id", "fp").join(distinct, "fp").where("doc_id <> first").select(F.col("doc_id").alias("u"), F.col("first").alias("v"))
        shared = self.shared_keys(single.select("doc_id", F.explode("keys").alias("key")))
        led = shared.where("doc_id <> lead").select(F.col("doc_id").alias("u"), F.col("lead").alias("v"))
        links = self.save(links.unionByName(self.compare(ringed.unionByName(equal).unionByName(led).where("u <> v"))), "links")
        self.work.drop("shared")  # of the pigeonring
        linked = self.stored[-1]

        # documents that share a key with others than their copies: an exact join among them, by the prefix of each one's shingles
        mixed = self.open_keys(shared.select("key", "doc_id"), links)
        if mixed.isEmpty():
            return links
        keyed = self.prefixes(self.save(gathered(mixed.select("doc_id", "comp")).distinct(), "mixed"))
        open_, everyone = self.open_keys(keyed, links), False
        self.keep(self.stored[0], linked, self.stored[-1])  # rows of all documents, links, open keys
        while not open_.isEmpty():
            few = open_.where(F.col("open") <= PAIRS_OF_KEY) if everyone else open_.limit(0)
            a, b = (few.select("key", *(F.col(c).alias(f"{c}_{x}") for c in _HOLDER)) for x in "uv")
            pairs = a.join(b, "key").where("doc_id_u > doc_id_v and comp_u <> comp_v").where(self.may_reach("u", "v")).select(F.col("doc_id_u").alias("u"), F.col("doc_id_v").alias("v"))
            many = open_.where(F.col("open") > PAIRS_OF_KEY) if everyone else open_
            # the shortest holders of a key lead it: they are what the others have in common; a leader that has met all leaves the key
            salt = F.pmod(F.xxhash64("doc_id"), F.lit(SALTS if everyone else 1))
            best = F.min(F.struct(*_HOLDER)).alias("l")
            leaders = gathered(many).groupBy("key", salt.alias("salt")).agg(best).select("key", *(F.col(f"l.{c}").alias(f"{c}_v") for c in _HOLDER))
            leaders = self.save(leaders, "leaders")
            asked = many.select("key", *(F.col(c).alias(f"{c}_u") for c in _HOLDER)).join(if_small(leaders), "key")
            asked = asked.where("doc_id_u <> doc_id_v and comp_u <> comp_v").where(self.may_reach("u", "v"))
            pairs = pairs.unionByName(asked.select(F.greatest("doc_id_u", "doc_id_v").alias("u"), F.least("doc_id_u", "doc_id_v").alias("v")))
            links = self.save(links.unionByName(self.compare(pairs)).distinct(), "links")
            linked = self.stored[-1]
            left = many.join(if_small(leaders.select("key", F.col("doc_id_v").alias("doc_id"))), ["key", "doc_id"], "left_anti").select(*keyed.columns)
            open_, everyone = self.open_keys(self.save(left, "left"), links), True
            self.keep(self.stored[0], linked, self.stored[-1])
        return links


#: What is known of a holder of a shingle; the shortest comes first.
_HOLDER = ("n", "doc_id", "before", "comp")
_READ = ["doc_id", "fp", "n", "set_a", "set_b", "keys", "sketch"]
_READ_KINDS = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.binary()]


def near_copies(docs: DataFrame, words: int = NEAR_WORDS, similarity: float = NEAR_SIMILARITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, component_id of every document: components of links between texts whose shingle sets are that similar (Jaccard).

    Every link is verified on the shingles of both whole texts. Candidates come in this order: equal sets; fingerprints within
    LINK_BITS, by the pigeonring; then keys of ROWS least values, so many that two documents of the similarity share none with a
    chance of OVERLOOKED, however short or long they are. (At a similarity of 0.8 fingerprints differ in about ten bits, beyond any
    selective chain.) Of a key's holders the first is compared with all. Documents that still share a key with others than their
    copies are joined exactly, by prefixes of their shingles in order of rarity: of the holders of a shingle the shortest is compared
    with all that may reach the similarity, then every pair that no link has joined yet, if these are at most PAIRS_OF_KEY; of
    shingles with more some leaders at a time, until nobody is left. So no partner is given up.

    Null ids take no part; null texts count as empty, and texts without words are copies of each other; rows of one id are one
    document, which any of its texts links; an empty table gives no rows; other columns are ignored.
    """
    spark = docs.sparkSession
    bounded_batches(spark)
    source = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    search = _Copies(source, words, similarity)
    components = connected_components(search.links(), Workspace(spark, "near-copies-docs"))
    return search.rows.select("doc_id").distinct().join(components, F.col("doc_id") == F.col("node"), "left").select("doc_id", F.coalesce("root", "doc_id").alias("component_id"))


def without_copies(docs: DataFrame, words: int = NEAR_WORDS, similarity: float = NEAR_SIMILARITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of the smallest id of each group of near copies, with all their columns; rows with a null id all stay.

    Of rows that share an id and a text one stays; with another text they stay if their id does.
    """
    groups = near_copies(docs, words, similarity, id_col, text_col)
    work = Workspace(docs.sparkSession, "without-copies")
    spare = work.save(groups.where("doc_id <> component_id").select(F.col("doc_id").alias("__spare")), "spare")
    left = docs.join(if_small(spare), docs[id_col] == F.col("__spare"), "left_anti")
    twice = work.save(docs.where(F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("__twice")).count().where("count > 1").select("__twice"), "twice")
    held = if_small(twice)
    again = left.join(held, left[id_col] == F.col("__twice"), "left_semi").dropDuplicates([id_col, text_col])
    return left.join(held, left[id_col] == F.col("__twice"), "left_anti").unionByName(again)
