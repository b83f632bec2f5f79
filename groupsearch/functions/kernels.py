"""Numerics on dense blocks: representatives of a unit, their online form, scoring, Lloyd iterations. No Spark in here."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def matrix(column, kind=float) -> np.ndarray:
    """Rows of an Arrow list column, all of one length, as a matrix of doubles or of another kind."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    if not n:
        return np.zeros((0, 0), kind)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return np.asarray(flat, kind).reshape(n, -1)


def vectors_column(x: np.ndarray) -> pa.Array:
    """A double matrix as an Arrow list column."""
    x = np.ascontiguousarray(x, float)
    n, d = x.shape if x.ndim == 2 else (0, 0)
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * d, pa.int32()), pa.array(x.reshape(-1)))


def sum_rep(x: np.ndarray) -> np.ndarray:
    return x.sum(0)


def pinv_rep(x: np.ndarray, rcond: float = 1e-10, lam: float = 0.0) -> np.ndarray:
    """The shortest vector whose product with every row is one, or nearest to one in squares where none exists.

    Solved in the smaller of row and column space; eigenvalues below rcond times the largest count as zero. lam > 0 adds a ridge.
    """
    n, d = x.shape
    if n <= d:
        values, basis = np.linalg.eigh(x @ x.T)
        keep = values > rcond * max(values[-1], 0.0)
        weights = basis[:, keep] @ ((basis[:, keep].T @ np.ones(n)) / (values[keep] + lam))
        return x.T @ weights
    values, basis = np.linalg.eigh(x.T @ x)
    keep = values > rcond * max(values[-1], 0.0)
    return basis[:, keep] @ ((basis[:, keep].T @ x.sum(0)) / (values[keep] + lam))


def representative(x: np.ndarray, kind: str, normalize: bool = False, lam: float = 0.0) -> np.ndarray:
    m = sum_rep(x) if kind == "sum" else pinv_rep(x, lam=lam)
    size = np.linalg.norm(m)
    return m / size if normalize and size > 0 else m


def unit_reps(v: np.ndarray, own: np.ndarray, units: int, kind: str, normalize: bool = False, rcond: float = 1e-10) -> tuple[np.ndarray, np.ndarray]:
    """(representatives of all units, sizes): rows of units without members are zero. Units of one size are solved in one call."""
    size = np.bincount(own, minlength=units)
    order = np.argsort(own, kind="stable")
    first = np.cumsum(size) - size
    reps = np.zeros((units, v.shape[1]))
    if kind == "sum":
        held = np.flatnonzero(size)
        if len(held):
            reps[held] = np.add.reduceat(v[order], first[held])
    else:
        for n in np.unique(size[size > 0]):
            which = np.flatnonzero(size == n)
            if n > v.shape[1]:
                for j in which:
                    reps[j] = pinv_rep(v[order[first[j] : first[j] + n]], rcond)
                continue
            step = max(1, (1 << 22) // (n * v.shape[1]))
            for i in range(0, len(which), step):
                part = which[i : i + step]
                x = v[order[first[part][:, None] + np.arange(n)]]
                values, basis = np.linalg.eigh(x @ x.transpose(0, 2, 1))
                keep = values > rcond * np.maximum(values[:, -1:], 0)
                weight = np.einsum("uij,uj->ui", basis, np.where(keep, basis.sum(1) / np.where(keep, values, 1), 0))
                reps[part] = np.einsum("ui,uid->ud", weight, x)
    if normalize:
        length = np.linalg.norm(reps, axis=1, keepdims=True)
        reps /= np.where(length > 0, length, 1)
    return reps, size


class UnitState:
    """A representative that grows by one vector at a time.

    sum adds. pinv keeps an orthonormal basis of the members' span: the part of a new vector outside it is all that may change the
    representative without touching the products with earlier members. A vector inside the span with product one changes nothing;
    one with another product contradicts earlier members, and the least-squares solution is solved for anew.
    """

    def __init__(self, kind: str = "pinv", tol: float = 1e-8):
        self.kind, self.tol = kind, tol
        self.members: list[np.ndarray] = []
        self.rep: np.ndarray | None = None
        self.basis: np.ndarray | None = None
        self.exact = True

    def append(self, x: np.ndarray) -> None:
        x = np.asarray(x, float)
        self.members.append(x)
        if self.rep is None:
            self.rep, self.basis = np.zeros(len(x)), np.zeros((0, len(x)))
        if self.kind == "sum":
            self.rep = self.rep + x
            return
        if not self.exact:
            self.rep = pinv_rep(np.stack(self.members))
            return
        rest = x - self.basis.T @ (self.basis @ x)
        rest -= self.basis.T @ (self.basis @ rest)
        size = np.linalg.norm(rest)
        miss = 1 - x @ self.rep
        if size > self.tol * max(np.linalg.norm(x), 1e-300):
            self.rep = self.rep + miss / size**2 * rest
            self.basis = np.vstack([self.basis, rest / size])
        elif abs(miss) > 1e-9:
            self.exact = False
            self.rep = pinv_rep(np.stack(self.members))


def best_units(v: np.ndarray, centroids: np.ndarray, block: int = 4096) -> np.ndarray:
    """Row of the centroid with the largest product for every vector, the first of equals; score blocks stay bounded."""
    out = np.zeros(len(v), np.int64)
    for i in range(0, len(v), block):
        out[i : i + block] = np.argmax(v[i : i + block] @ centroids.T, 1)
    return out


class Nearest:
    """The unit with the largest product for each row, units taken in block after block, and a bound on all others' products.

    Products in single precision leave those out that can't be the largest; the others are computed in doubles. Products that differ
    by less than EQUAL count as equal, the smaller unit wins: what is found depends on neither blocks nor the order of sums.
    """

    #: Products that differ by less, relative to the larger if it exceeds one.
    EQUAL = 1e-9

    def __init__(self, x: np.ndarray, best: np.ndarray | None = None, unit: np.ndarray | None = None, bound: np.ndarray | None = None):
        n = len(x)
        self.x, self.low, self.size = x, x.astype(np.float32), np.linalg.norm(x, axis=1)
        self.best = np.full(n, -np.inf) if best is None else best.copy()
        self.unit = np.full(n, np.iinfo(np.int64).max) if unit is None else unit.copy()
        self.bound = np.full(n, -np.inf) if bound is None else bound.copy()

    def add(self, c: np.ndarray, ids: np.ndarray, rows: np.ndarray | None = None, less: np.ndarray | None = None) -> None:
        """Takes in units for all rows, or some. less: a number for each unit that comes off its products."""
        if not len(c) or not len(self.x) or (rows is not None and not len(rows)):
            return
        at = np.arange(len(self.x)) if rows is None else rows
        s = (self.low if rows is None else self.low[rows]) @ c.T.astype(np.float32)
        far = np.linalg.norm(c, axis=1).max()
        if less is not None:
            s -= less.astype(np.float32)
            far += np.abs(less).max()  # rows of unit length or less
        # rounding of components, products and their sums
        off = (c.shape[1] + 4) * 2.0**-24 * np.maximum(self.size[at], 1) * far
        line, first = np.arange(len(at)), s.argmax(1)
        top = s[line, first].astype(float)
        s[line, first] = -np.inf
        after = s.max(1).astype(float)
        bar = np.maximum(top - 2 * off, self.best[at] - off) - 2 * self.EQUAL * np.maximum(1, np.abs(top))
        r, col = np.flatnonzero(top >= bar), first[top >= bar]
        more = np.flatnonzero(after >= bar)
        if len(more):
            a, b = np.nonzero(s[more] >= bar[more, None])
            r, col = np.concatenate([r, more[a]]), np.concatenate([col, b])
        p = np.empty(len(r))
        for i in range(0, len(r), 1 << 14):
            k = slice(i, i + (1 << 14))
            p[k] = np.einsum("ij,ij->i", self.x[at[r[k]]], c[col[k]])
        if less is not None:
            p -= less[col]
        most = np.full(len(at), -np.inf)
        np.maximum.at(most, r, p)
        near = p >= most[r] - self.EQUAL * np.maximum(1, np.abs(most[r]))
        winner = np.full(len(at), np.iinfo(np.int64).max)
        np.minimum.at(winner, r[near], ids[col[near]])
        rest = np.where(winner == ids[first], after, top) + off  # all of the block but the winner
        best, unit, bound = self.best[at], self.unit[at], self.bound[at]
        gap = self.EQUAL * np.maximum(1, np.abs(most))
        with np.errstate(invalid="ignore"):
            ahead = (most > best + gap) | ((np.abs(most - best) <= gap) & (winner < unit))
        other = np.where(np.isneginf(most), top + off, np.maximum(most, rest))
        self.bound[at] = np.where(ahead, np.maximum(np.maximum(bound, rest), best), np.maximum(bound, other))
        self.best[at], self.unit[at] = np.where(ahead, most, best), np.where(ahead, winner, unit)


def nearest_again(x: np.ndarray, old: tuple[np.ndarray, np.ndarray, np.ndarray] | None, changed: np.ndarray, new_blocks, kept_blocks) -> Nearest:
    """Nearest over all units, given (unit, best, bound) of a round before and which units' representatives changed (ids, rising).

    new_blocks() and kept_blocks() go over (representatives, ids) of units that changed and of the others. The others are met again
    only by rows that may lie nearest to one of them: rows whose unit changed and lost its lead over the bound.
    """
    if old is None:
        out = Nearest(x)
        for c, ids in new_blocks():
            out.add(c, ids)
        return out
    unit, best, bound = old
    lost = np.isin(unit, changed)
    out = Nearest(x, np.where(lost, -np.inf, best), np.where(lost, np.iinfo(np.int64).max, unit), np.where(lost, -np.inf, bound))
    for c, ids in new_blocks():
        out.add(c, ids)
    again = lost & (out.best <= bound + 2 * Nearest.EQUAL * np.maximum(1, np.abs(bound)))
    sure = lost & ~again
    out.bound[sure] = np.maximum(out.bound[sure], bound[sure])
    rows = np.flatnonzero(again)
    if len(rows):
        for c, ids in kept_blocks():
            out.add(c, ids, rows)
    return out


def spherical_lloyd(v: np.ndarray, units: int, kind: str, normalize: bool, seed: int, max_iter: int = 12, empty: str = "drop", start: np.ndarray | None = None):
    """(unit of each row, representatives by unit) of spherical k-means whose update is the representative of the kind.

    Starts from rows drawn by the seed. Stops when no row moves. An empty unit goes ("drop", the others are numbered anew) or takes
    the row that fits its own unit worst ("reseed"). Only units whose members changed are solved and met again.
    """
    units = min(units, len(v))
    if start is None:
        start = np.random.default_rng(seed).permutation(len(v))[:units]
    reps = v[start].copy()
    held, changed = np.ones(len(reps), bool), np.arange(len(reps))
    own, old, block, rows = np.full(len(v), -1), None, 1024, 4096

    def over(which):
        return lambda: ((reps[which[i : i + block]], which[i : i + block]) for i in range(0, len(which), block))

    for _ in range(max_iter):
        kept = np.flatnonzero(held & ~np.isin(np.arange(len(reps)), changed))
        got = []
        for i in range(0, len(v), rows):
            part = slice(i, i + rows)
            near = nearest_again(v[part], old and tuple(o[part] for o in old), changed, over(changed), over(kept))
            got.append((near.unit, near.best, near.bound))
        old = tuple(np.concatenate(g) for g in zip(*got, strict=True)) if got else None
        if not len(v) or (old[0] == own).all():
            break
        new = old[0]
        moved = new != own
        touched = np.union1d(new[moved], own[moved & (own >= 0)])
        own = new
        size = np.bincount(own, minlength=len(reps))
        changed = touched[size[touched] > 0] if empty == "drop" else touched
        place = np.full(len(reps), -1)
        place[changed] = np.arange(len(changed))
        mine = np.flatnonzero(place[own] >= 0)
        reps[changed] = unit_reps(v[mine], place[own[mine]], len(changed), kind, normalize)[0]
        if empty == "reseed" and (size == 0).any():
            fit = (v * reps[own]).sum(1)
            for j in np.flatnonzero(size == 0):
                worst = int(np.argmin(fit))
                fit[worst] = np.inf
                reps[j] = v[worst]
            changed = np.union1d(changed, np.flatnonzero(size == 0))
        if empty == "drop":
            held = size > 0
    if empty == "drop" and len(v):
        own, reps = (np.cumsum(held) - 1)[own], reps[held]
    return own, reps


def minibatch_kmeans(v: np.ndarray, start: np.ndarray, drawn: np.ndarray) -> np.ndarray:
    """Centroids of mini-batch k-means: each centre moves to a step's rows by a rate of one over its count, to the mean of all its rows.

    start: rows of the first centres. drawn: which rows each step draws (rows x steps). Of equal distances the first centre's counts.
    """
    c = v[start].copy()
    count = np.zeros(len(c))
    for step in drawn.T:
        rows = np.flatnonzero(step)
        for i in range(0, len(rows), 4096):
            near = Nearest(v[rows[i : i + 4096]])
            for j in range(0, len(c), 1024):
                near.add(c[j : j + 1024], np.arange(j, min(j + 1024, len(c))), less=(c[j : j + 1024] ** 2).sum(1) / 2)
            own = near.unit if not i else np.concatenate([own, near.unit])
        if not len(rows):
            continue
        units, at = np.unique(own, return_inverse=True)
        total, n = unit_reps(v[rows], at, len(units), "sum")
        count[units] += n
        c[units] += (total - n[:, None] * c[units]) / count[units, None]
    return c


def top_k_rows(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """For each row of scores the columns of the k best, ties to the smaller id. ids: of each column, or of each score."""
    ids = np.broadcast_to(ids, scores.shape)
    if scores.shape[1] > 4 * k:
        cut = -np.partition(-scores, k - 1, axis=1)[:, k - 1]
        wide = scores >= cut[:, None]
        most = int(wide.sum(1).max())
        part = np.argsort(~wide, axis=1, kind="stable")[:, :most]
        sub = np.where(np.take_along_axis(wide, part, 1), np.take_along_axis(scores, part, 1), -np.inf)
        order = np.lexsort((np.take_along_axis(ids, part, 1), -sub), axis=1)[:, :k]
        return np.take_along_axis(part, order, 1)
    return np.lexsort((ids, -scores), axis=1)[:, :k]


class Best:
    """The k best of each query so far, blocks of scores taken in one after the other."""

    def __init__(self, queries: int, k: int):
        self.k = k
        self.score, self.ids = np.full((queries, k), -np.inf), np.full((queries, k), np.iinfo(np.int64).max)

    def add(self, first: int, scores: np.ndarray, ids: np.ndarray) -> None:
        """Scores of the queries from the first on against columns of these ids."""
        rows = slice(first, first + len(scores))
        at = top_k_rows(scores, ids, self.k)
        both = np.concatenate([self.score[rows], np.take_along_axis(scores, at, 1)], 1)
        held = np.concatenate([self.ids[rows], ids[at]], 1)
        at = np.lexsort((held, -both), axis=1)[:, : self.k]
        self.score[rows], self.ids[rows] = np.take_along_axis(both, at, 1), np.take_along_axis(held, at, 1)


def hamming_distances(words: np.ndarray, code: np.ndarray) -> np.ndarray:
    """Differing bits of a code and many, whose 64-bit words lie word by word (words x codes).

    One pass over contiguous memory each, in blocks that stay in the cache; three words fit a sum of one byte.
    """
    n = words.shape[1]
    out = np.zeros(n, np.uint16)
    step = 16384
    differing, bits, few = np.empty(step, words.dtype), np.empty(step, np.uint8), np.empty(step, np.uint8)
    for i in range(0, n, step):
        block = words[:, i : i + step]
        m = block.shape[1]
        d, b, f, total = differing[:m], bits[:m], few[:m], out[i : i + m]
        for j in range(0, len(code), 3):
            np.bitwise_count(np.bitwise_xor(block[j], code[j], out=d), out=f)
            for k in range(j + 1, min(j + 3, len(code))):
                np.add(f, np.bitwise_count(np.bitwise_xor(block[k], code[k], out=d), out=b), out=f)
            np.add(total, f, out=total)
    return out


def hamming_block(queries: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """Differing bits of every query code and every code (rows of words)."""
    out = np.zeros((len(queries), len(codes)), np.int32)
    for q, c in zip(np.ascontiguousarray(queries.T), np.ascontiguousarray(codes.T), strict=True):
        out += np.bitwise_count(q[:, None] ^ c[None, :])
    return out
