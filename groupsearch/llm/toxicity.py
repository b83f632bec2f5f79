"""Toxicity by weak supervision.

Voters are lexicon entries (whole words, word starts) and patterns (character n-grams of words), chosen where they are
over-represented in labelled toxic documents. A generative label model with a latent label estimates each voter's accuracy (its vote
rates among clean and among toxic documents) and its correlation with the voter it depends on most (its rates given that one's vote):
a vote that another one explains counts for little. Its posteriors, not the labels, train a logistic classifier over all voters,
which scores every document.
"""

from __future__ import annotations

import gc
import math
import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Workspace, bounded_batches, give_back, tidy

#: Documented bounds: labelled rows the model is fitted on, voters, words looked up by a worker, and the least support of a voter, in
#: toxic rows and as a share of them. As fitted rows are bounded, so are the patterns that enough toxic ones hold.
FIT_ROWS, VOTERS, MEMO, SUPPORT, SUPPORT_SHARE = 20_000, 400, 300_000, 4, 0.002
#: How much likelier a voter is in toxic documents than in clean ones.
GAIN = 12
THRESHOLD = 0.7
_WORD = re.compile(r"\w+")


def patterns(word: str) -> set[str]:
    """What a word can match: itself, its starts of 3 to 7 letters, its n-grams of 4 to 6; ^ and $ mark its ends."""
    w = f"^{word}$"
    found = {w} | {w[:k] for k in range(4, 9)}
    for k in (4, 5, 6):
        found.update(w[i : i + k] for i in range(len(w) - k + 1))
    return found


def words_of(text: str | None) -> set[str]:
    return set(_WORD.findall((text or "").lower()))


def held_out(doc_id: Column) -> Column:
    """Whether labels of a row must not be learned: crc32 of the id's text leaves 1 modulo 3."""
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(3)) == 1


@dataclass
class ToxicityModel:
    voters: list[str]
    weights: np.ndarray
    bias: float
    labels: LabelModel

    def scores(self, votes: list[list[int]]) -> np.ndarray:
        """Scores of documents from the voters that fire on each, all at once."""
        n = np.fromiter(map(len, votes), np.int64, len(votes))
        flat = np.fromiter((i for v in votes for i in v), np.int64, int(n.sum()))
        logit = self.bias + np.bincount(np.repeat(np.arange(len(n)), n), self.weights[flat], len(n)) + _totals(n) @ self.weights[len(self.voters) :]
        return 1 / (1 + np.exp(-np.clip(logit, -50, 50)))


def _totals(n: np.ndarray) -> np.ndarray:
    """Features of how many voters fire on a document at all."""
    return np.stack([n >= 1, n >= 2, np.log1p(n)], -1).astype(float)


@dataclass
class LabelModel:
    """A generative model of votes: by latent label, each voter's rate, and its rates given the vote of the voter it depends on."""

    prior: float
    trust: float  # how often a given label is the latent one
    rates: np.ndarray  # voters x label
    parent: np.ndarray  # of each voter the one it depends on, or -1
    given: np.ndarray  # voters x label x vote of the parent

    def evidence(self, votes: np.ndarray) -> np.ndarray:
        """Log odds that the votes of each row give: a voter that fires, given what its parent does; one that doesn't abstains."""
        free, tied = self.parent < 0, self.parent >= 0
        alone = np.log(self.rates[:, 1] / self.rates[:, 0])
        odds = np.log(self.given[:, 1] / self.given[:, 0])
        of_parent = votes[:, self.parent[tied]]
        return votes[:, free] @ alone[free] + (votes[:, tied] * np.where(of_parent > 0, odds[tied, 1], odds[tied, 0])).sum(1)


def dependencies(votes: np.ndarray, weight: np.ndarray, least: float = 0.01) -> np.ndarray:
    """The parent of each voter in a forest of the strongest mutual information given the label; links of less than the least go.

    weight: rows x label, how much a row counts for each label.
    """
    n, k = votes.shape
    info = np.zeros((k, k))
    for y in (0, 1):
        total = weight[:, y].sum() + 2
        both = (votes.T * weight[:, y]) @ votes + 0.5
        one = votes.T @ weight[:, y] + 1
        share = total / n
        for a, b, joint in ((one, one, both), (one, total - one, one[:, None] - both), (total - one, one, one[None, :] - both), (total - one, total - one, total - one[:, None] - one[None, :] + both)):
            joint = np.clip(joint, 1e-9, None) / total
            info += share * joint * np.log(joint / (a[:, None] / total) / (b[None, :] / total))
    entropy = [-(x * np.log(x) + (1 - x) * np.log(1 - x)) for x in [np.clip(votes.mean(0), 1e-6, 1 - 1e-6)]][0]
    strength = info / np.sqrt(np.outer(entropy, entropy))
    np.fill_diagonal(strength, -1)
    parent, best, link = np.full(k, -1), np.full(k, -1.0), np.full(k, -1)
    left = np.ones(k, bool)
    for _ in range(k):  # a tree grown from its strongest link on; a voter without a strong one starts another
        i = int(np.argmax(np.where(left, best, -2)))
        if best[i] >= least:
            parent[i] = link[i]
        left[i] = False
        closer = left & (strength[i] > best)
        best[closer], link[closer] = strength[i][closer], i
    return parent


def label_model(votes: np.ndarray, labels: np.ndarray, rounds: int = 30) -> tuple[np.ndarray, LabelModel]:
    """EM over binary votes: posteriors of the latent label, and the model. The given labels act as one more voter.

    labels: 0, 1, or -1 where unknown. A voter that does not fire abstains; that none fires at all is evidence of its own. Which
    voter another depends on is chosen anew every tenth round, from what the posteriors leave unexplained.
    """
    n, k = votes.shape
    known = labels >= 0
    post = np.where(known, np.where(labels == 1, 0.98, 0.02), 0.1) if known.any() else np.clip(votes.mean(1) * 4, 0.02, 0.98)
    model = LabelModel(float(post.mean()) if n else 0.1, 0.97, np.full((k, 2), 0.5), np.full(k, -1), np.full((k, 2, 2), 0.5))
    silent = votes.sum(1) == 0
    for step in range(rounds if n else 0):
        weight = np.stack([1 - post, post], 1)
        total = weight.sum(0)
        model.rates = np.clip((votes.T @ weight + 0.5) / (total + 1), 1e-4, 1 - 1e-4)
        model.prior = float(np.clip(total[1] / n, 1e-4, 1 - 1e-4))
        if step % 10 == 0:
            model.parent = dependencies(votes, weight)
        of_parent = np.where(model.parent >= 0, votes[:, model.parent], 0)
        for vote in (0, 1):
            at = of_parent if vote else 1 - of_parent
            pooled = ((votes * at).sum(0) + 0.5) / (at.sum(0) + 1)  # whatever the label: where one label has no such rows, both agree
            model.given[:, :, vote] = np.clip(((votes * at).T @ weight + 2 * pooled[:, None]) / (at.T @ weight + 2), 1e-4, 1 - 1e-4)
        quiet = np.clip((silent @ weight + 0.5) / (total + 1), 1e-4, 1 - 1e-4)
        logit = np.log(model.prior / (1 - model.prior)) + model.evidence(votes) + silent * np.log(quiet[1] / quiet[0])
        logit += np.where(known, np.where(labels == 1, 1, -1) * np.log(model.trust / (1 - model.trust)), 0)
        post = 1 / (1 + np.exp(-np.clip(logit, -30, 30)))
        if known.any():
            model.trust = float(np.clip(np.where(labels == 1, post, 1 - post)[known].mean(), 0.6, 0.995))
    return post, model


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.05, steps: int = 25) -> tuple[np.ndarray, float]:
    """Ridge-penalised logistic regression on soft labels by Newton steps; the bias is free."""
    z = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(z.shape[1])
    pen = np.full(z.shape[1], ridge)
    pen[-1] = 1e-6
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        grad = z.T @ (p - y) + pen * w
        hess = (z * (p * (1 - p) + 1e-9)[:, None]).T @ z + np.diag(pen)
        move = np.linalg.solve(hess, grad)
        w -= move
        if np.abs(move).max() < 1e-6:
            break
    return w[:-1], float(w[-1])


def _candidates(pos: dict, neg: dict, n_pos: int, n_neg: int) -> list[str]:
    """Over-represented patterns, the strongest first; of nested ones that equally many toxic documents hold, only the shortest."""
    rated = []
    for p, a in pos.items():
        gain = math.log((a + 0.5) / (n_pos + 1)) - math.log((neg.get(p, 0) + 0.5) / (n_neg + 1))
        if gain > math.log(GAIN):
            rated.append((a, gain, p))
    kept: dict[int, set[str]] = {}
    out = []
    for a, gain, p in sorted(rated, key=lambda r: (len(r[2]), r[2])):
        held = kept.setdefault(a, set())
        if not any(p[i:j] in held for i in range(len(p)) for j in range(i + 1, min(len(p), i + 8) + 1)):
            held.add(p)
            out.append((a * gain * gain, p))
    return [p for _, p in sorted(out, reverse=True)]


def _cover(votes: list[list[int]], toxic: list[int], n: int, most: int, times: int = 8) -> list[int]:
    """Voters in their order, each taken if some toxic document has fewer than so many voters yet."""
    holders: list[list[int]] = [[] for _ in range(n)]
    for doc, (v, y) in enumerate(zip(votes, toxic, strict=True)):
        if y:
            for i in v:
                holders[i].append(doc)
    covered, chosen = Counter(), []
    for i in range(n):
        short = sum(covered[d] < times for d in holders[i])
        if short >= max(2, len(holders[i]) // 10):
            chosen.append(i)
            covered.update(holders[i])
            if len(chosen) == most:
                break
    return chosen


def fit(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS, voters: int = VOTERS) -> ToxicityModel | None:
    """Fits on rows whose labels may be learned, about fit_rows of them, chosen by a hash of the id; None without toxic rows.

    The chosen labels are broadcast (fit_rows bounds them) to find their documents. Counting is distributed: a task counts in how
    many of its documents each pattern occurs; the driver gets only patterns that at least SUPPORT toxic rows and SUPPORT_SHARE of them
    hold, which the bound on rows bounds, then a list of votes for each fitted row. Repeated labels of an id count once, the largest of them; null labels and ids are ignored.
    What the fit took of the driver's memory goes back to the system: the driver's next steps need it.
    """
    try:
        return _fit(docs, labels, fit_rows, voters)
    finally:
        gc.collect()
        give_back()


def _fit(docs: DataFrame, labels: DataFrame, fit_rows: int, voters: int) -> ToxicityModel | None:
    spark = docs.sparkSession
    bounded_batches(spark)
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).where(~held_out(F.col("doc_id")))
    known = known.groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    n = known.count()
    if not n:
        return None
    share = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20))
    chosen_labels = known.where(share < F.lit(min(1 << 20, int(fit_rows / n * (1 << 20)) or 1)))
    work = Workspace(spark, "toxicity")
    rows = work.save(docs.select("doc_id", "text").join(F.broadcast(chosen_labels), "doc_id"), "rows")

    def count(batches, only=None):
        got, sizes = {0: Counter(), 1: Counter()}, Counter()
        memo: dict[str, set[str]] = {}
        for b in batches:
            for text, y in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                y = int(y == 1)
                if (only is None) != (y == 1):
                    continue
                seen: set[str] = set()
                for w in words_of(text):
                    p = memo.get(w)
                    if p is None:
                        p = patterns(w) if only is None else patterns(w) & only
                        if len(memo) < MEMO // 10:
                            memo[w] = p
                    seen |= p
                got[y].update(seen)
                sizes[y] += 1
        for y in (0, 1):
            items = [("", sizes[y]), *got[y].items()]
            for i in range(0, len(items), 20_000):
                part = items[i : i + 20_000]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([p for p, _ in part]), pa.array([y] * len(part), pa.int32()), pa.array([c for _, c in part], pa.int64())], ["pattern", "toxic", "n"]
                )

    kinds = "pattern string, toxic int, n bigint"
    held = rows.mapInArrow(tidy(count), kinds).groupBy("pattern", "toxic").agg(F.sum("n").alias("n")).where("toxic = 1")
    held = work.save(held.where((F.col("n") >= SUPPORT) | (F.col("pattern") == "")).select("pattern", "n"), "held")
    n_pos = held.where("pattern = ''").agg(F.max("n")).first()[0] or 0
    pos = {r.pattern: r.n for r in held.where(F.col("pattern") != "").where(F.col("n") >= SUPPORT_SHARE * n_pos).collect()}
    if not pos:
        return None
    only = spark.sparkContext.broadcast(set(pos))
    counted = rows.mapInArrow(tidy(lambda batches: count(batches, only.value)), kinds).where("toxic = 0").groupBy("pattern").agg(F.sum("n").alias("n")).collect()
    neg = {r.pattern: r.n for r in counted}
    n_neg = neg.pop("", 0)
    ranked = _candidates(pos, neg, n_pos, n_neg)
    if not ranked:
        return None
    votes = sorted(votes_of(rows.select("doc_id", "text", "toxic"), ranked, keep="toxic").collect(), key=lambda r: (r.doc_id is None, r.doc_id))
    y = np.array([int(r.toxic == 1) for r in votes])
    place = {v: i for i, v in enumerate(_cover([r.votes for r in votes], y.tolist(), len(ranked), voters))}
    x = np.zeros((len(votes), len(place)))
    for i, r in enumerate(votes):
        x[i, [place[v] for v in r.votes if v in place]] = 1
    post, model = label_model(x, y)
    weights, bias = logistic(np.hstack([x, _totals(x.sum(1))]), post)
    return ToxicityModel([ranked[v] for v in place], weights, bias, model)


class Voting:
    """Votes of the chosen voters on texts, by a bounded memory of words."""

    def __init__(self, voters: list[str]):
        self.place = {v: i for i, v in enumerate(voters)}
        self.keys = frozenset(voters)
        self.memo: dict[str, tuple[int, ...]] = {}

    def __call__(self, text: str | None) -> set[int]:
        memo, out = self.memo, set()
        for w in words_of(text):
            hit = memo.get(w)
            if hit is None:
                hit = tuple(self.place[p] for p in self.keys & patterns(w))
                if len(memo) >= MEMO:
                    memo.clear()
                if len(w) <= 40:
                    memo[w] = hit
            if hit:
                out.update(hit)
        return out


def votes_of(docs: DataFrame, voters: list[str], keep: str) -> DataFrame:
    @tidy
    def run(batches):
        vote = Voting(voters)
        for b in batches:
            found = [sorted(vote(t)) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(found, pa.list_(pa.int32()))], ["doc_id", keep, "votes"])

    kinds = dict(docs.dtypes)
    return docs.mapInArrow(run, f"doc_id {kinds['doc_id']}, {keep} {kinds[keep]}, votes array<int>")


def score_documents(docs: DataFrame, model: ToxicityModel | None, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score, predicted for every row; a map without shuffle. Without a model every score is 0.

    Null and empty texts get the score of a text without votes. Repeated rows each get theirs; other columns are ignored.
    """
    bounded_batches(docs.sparkSession)
    kind = dict(docs.dtypes)["doc_id"]

    @tidy
    def run(batches):
        vote = Voting(model.voters if model else [])
        for b in batches:
            if model:
                score = model.scores([sorted(vote(t)) for t in b.column(1).to_pylist()])
            else:
                score = np.zeros(b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(score, pa.float64())], ["doc_id", "score"])

    scored = docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, score double")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_clean(docs: DataFrame, model: ToxicityModel | None, threshold: float = THRESHOLD) -> DataFrame:
    """The rows whose score stays below the threshold, with all their columns; a filter over rows, no join."""
    if model is None:
        return docs
    bounded_batches(docs.sparkSession)

    @tidy
    def run(batches):
        vote = Voting(model.voters)
        for b in batches:
            at = b.schema.get_field_index("text")
            yield b.filter(pa.array(model.scores([sorted(vote(t)) for t in b.column(at).to_pylist()]) < threshold, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
