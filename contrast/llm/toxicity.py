"""Toxicity by weak supervision: many voters, a generative label model, a linear classifier.

Voters look at a text's words and shape: one for each word of a lexicon, others for how many of its
words occur, for repeats, shouting, marks and the like. The lexicon's words are those that mark toxic
texts in a bounded sample of labelled ones. A label model explains all texts' votes by a hidden class:
each voter has its accuracy in each class, and depends on one other voter, so that voters which vote
together don't count twice; the dependencies form the tree of largest conditional mutual information.
It is fitted by expectation maximisation over counts of equal vote patterns, with the labels of the
training rows as one more, noisy voter. Last, logistic regression on the votes is fitted to the
posterior labels, and its probability is the score.

All that the driver sees are sums over voters and pairs of voters.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from contrast.llm.common import crc_remainder, materialise

#: Labelled training rows that the lexicon is read from at most, by a hash of their ids.
SAMPLE = 20_000
LEXICON = 40
#: Least texts of class 1 that a lexicon word is in, and how much more often than in the others.
LEAST, RATIO = 5, 4.0
WORD = re.compile(r"[^\W\d_]+")
UPPER = re.compile(r"[A-Z]")
#: Votes that don't depend on single words: name and test of distinct hits, hits, characters, capitals and exclamation marks.
SHAPES: tuple[tuple[str, Callable[..., bool]], ...] = (
    ("one hit", lambda d, h, n, u, m: d >= 1),
    ("two hits", lambda d, h, n, u, m: d >= 2),
    ("three hits", lambda d, h, n, u, m: d >= 3),
    ("five hits", lambda d, h, n, u, m: d >= 5),
    ("a hit again", lambda d, h, n, u, m: h > d),
    ("dense hits", lambda d, h, n, u, m: 200 * h >= n and h >= 1),
    ("shouting", lambda d, h, n, u, m: 3 * u >= n and n >= 40),
    ("marks", lambda d, h, n, u, m: m >= 3),
    ("short", lambda d, h, n, u, m: n < 300),
)
#: Weight of a training label against the votes: how often it is taken to be right.
TRUST = 0.95
ROUNDS, STEPS, RIDGE = 12, 12, 1.0
TOTALS = 2


def labelled_sample(docs: DataFrame, labels: DataFrame, limit: int) -> DataFrame:
    """text and toxic of a bounded number of labelled rows, the same at every run; equal texts once."""
    few = labels.select("doc_id", "toxic").orderBy(F.xxhash64("doc_id"), "doc_id").limit(limit)
    return docs.join(F.broadcast(few), "doc_id").select("text", "toxic").groupBy(F.xxhash64("text")).agg(F.first("text").alias("text"), F.max("toxic").alias("toxic"))


def mine_lexicon(sample: DataFrame, size: int = LEXICON) -> list[str]:
    """The words whose texts are most surely toxic, by the z-value of their log odds ratio."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found: dict[str, list[int]] = {}
            for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                for word in set(WORD.findall(text.lower())):
                    found.setdefault(word, [0, 0])[toxic] += 1
            yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.string()), pa.array([v[1] for v in found.values()], pa.int64()), pa.array([v[0] for v in found.values()], pa.int64())], ["word", "bad", "good"])

    sample = sample.where("text is not null and toxic in (0, 1)").select("text", F.col("toxic").cast("int").alias("toxic"))
    bad, good = sample.agg(F.coalesce(F.sum("toxic"), F.lit(0)), F.coalesce(F.sum(1 - F.col("toxic")), F.lit(0))).first()
    if not bad:
        return []
    a, b = F.col("bad") + 0.5, F.col("good") + 0.5
    z = (F.log(a / (bad + 1 - a)) - F.log(b / (good + 1 - b))) / F.sqrt(1 / a + 1 / b)
    words = sample.mapInArrow(run, "word string, bad long, good long").groupBy("word").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good"))
    telling = words.where((F.col("bad") >= LEAST) & (F.col("bad") * (good + 1.0) >= RATIO * (F.col("good") + 1) * float(bad)))
    return [r["word"] for r in telling.orderBy(z.desc(), "word").limit(size).collect()]


class Voters:
    """The votes of a text as the bits of a number: lexicon words first, then shapes."""

    def __init__(self, lexicon: list[str]):
        self.lexicon = lexicon
        self.count = len(lexicon) + len(SHAPES)

    def prepare(self):
        self.automaton = ahocorasick.Automaton()
        for i, word in enumerate(self.lexicon):
            self.automaton.add_word(word, (i, len(word)))
        if self.lexicon:
            self.automaton.make_automaton()
        return self

    def votes(self, text: str) -> int:
        low, out, hits = text.lower(), 0, 0
        if self.lexicon:
            for end, (i, size) in self.automaton.iter(low):
                before, after = low[end - size : end - size + 1] if end >= size else "", low[end + 1 : end + 2]
                if not (WORD.match(before) or WORD.match(after)):
                    out |= 1 << i
                    hits += 1
        distinct, n = out.bit_count(), len(text)
        upper = len(UPPER.findall(text))
        marks = text.count("!")
        for k, (_, test) in enumerate(SHAPES):
            if test(distinct, hits, n, upper, marks):
                out |= 1 << len(self.lexicon) + k
        return out


def vote_all(docs: DataFrame, voters: Voters) -> DataFrame:
    """doc_id and votes (a long of bits) of every row; a null text is empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        votes = Voters(voters.lexicon).prepare().votes
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([votes(t.as_py()) for t in batch.column(1)], pa.int64())], ["doc_id", "votes"])

    slim = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    return slim.mapInArrow(run, f"doc_id {slim.schema['doc_id'].dataType.simpleString()}, votes long")


def bits(votes: np.ndarray, count: int) -> np.ndarray:
    return (votes[:, None] >> np.arange(count) & 1).astype(np.float64)


def _summed(patterns: DataFrame, size: int, part: Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray]) -> np.ndarray:
    """The sum over all patterns of part(votes, label, n), whose length is size; -1 for no label."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size)
        for batch in batches:
            votes, label, n = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
            for begin in range(0, len(votes), 4096):
                total += part(votes[begin : begin + 4096], label[begin : begin + 4096], n[begin : begin + 4096].astype(np.float64))
        yield pa.RecordBatch.from_arrays([pa.array([total.tolist()], pa.list_(pa.float64()))], ["s"])

    out = np.zeros(size)
    for row in patterns.mapInArrow(run, "s array<double>").toLocalIterator():
        out += np.asarray(row["s"])
    return out


class LabelModel:
    """P(votes | class) over a tree of voters, and the classes' shares."""

    def __init__(self, count: int):
        self.count = count
        self.share, self.parent = 0.1, np.full(count, -1)
        self.order = list(range(count))
        self.chance: np.ndarray | None = None  # [class, voter, parent's vote] of a vote

    def log_odds(self, votes: np.ndarray) -> np.ndarray:
        """Log of toxic to clean, by the votes alone."""
        v = bits(votes, self.count)
        above = np.where(self.parent >= 0, v[:, self.parent], 0).astype(int)
        p = self.chance[:, np.arange(self.count), above]
        each = np.where(v[None] > 0, np.log(p), np.log1p(-p)).sum(axis=2)
        return each[1] - each[0] + np.log(self.share / (1 - self.share))

    def posterior(self, votes: np.ndarray, label: np.ndarray, trust: float = TRUST) -> np.ndarray:
        bent = np.log(trust / (1 - trust)) * np.where(label == 1, 1.0, np.where(label == 0, -1.0, 0.0))
        first = np.where(label >= 0, np.where(label == 1, trust, 1 - trust), self.share)
        if self.chance is None:
            return first
        return 1 / (1 + np.exp(-np.clip(self.log_odds(votes) + bent, -30, 30)))

    def sums(self, votes: np.ndarray, label: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Expected counts by class of each pair of votes, and of the classes."""
        v = bits(votes, self.count)
        weight = self.posterior(votes, label)
        if self.chance is None:  # the first round learns from labelled rows alone
            n = n * (label >= 0)
        pairs = [(v * (n * w)[:, None]).T @ v for w in (1 - weight, weight)]
        return np.concatenate([*(p.reshape(-1) for p in pairs), [(n * (1 - weight)).sum(), (n * weight).sum()]])

    def update(self, total: np.ndarray) -> None:
        k = self.count
        pairs, classes = total[:-TOTALS].reshape(2, k, k), total[-TOTALS:]
        self.share = float(np.clip(classes[1] / max(classes.sum(), 1e-9), 1e-3, 0.5))
        single = np.diagonal(pairs, axis1=1, axis2=2)
        self.parent = _tree(pairs, single, classes)
        chance = np.empty((2, k, 2))
        for i in range(k):
            j = self.parent[i]
            for c in (0, 1):
                if j < 0:
                    chance[c, i] = (single[c, i] + 0.5) / (classes[c] + 1)
                else:
                    with_j = pairs[c, i, j]
                    chance[c, i, 1] = (with_j + 0.5) / (single[c, j] + 1)
                    chance[c, i, 0] = (single[c, i] - with_j + 0.5) / (classes[c] - single[c, j] + 1)
        self.chance = np.clip(chance, 1e-6, 1 - 1e-6)


def _tree(pairs: np.ndarray, single: np.ndarray, classes: np.ndarray) -> np.ndarray:
    """Each voter's parent (-1: none) in the tree of largest mutual information given the class."""
    k, every = pairs.shape[1], max(classes.sum(), 1e-9)
    info = np.zeros((k, k))
    for c in (0, 1):
        n, one = max(classes[c], 1e-9), single[c]
        for x in (0, 1):
            for y in (0, 1):
                joint = pairs[c] if x and y else one[:, None] - pairs[c] if x else one[None] - pairs[c] if y else n - one[:, None] - one[None] + pairs[c]
                p, q = (one if x else n - one)[:, None], (one if y else n - one)[None]
                ratio = np.maximum(joint, 1e-9) * n / np.maximum(p * q, 1e-9)
                info += np.where(joint > 0.5, joint / every * np.log(np.maximum(ratio, 1e-9)), 0)
    parent, inside = np.full(k, -1), np.zeros(k, bool)
    if not k:
        return parent
    inside[0] = True
    best, link = info[0].copy(), np.zeros(k, int)
    for _ in range(k - 1):
        i = int(np.argmax(np.where(inside, -np.inf, best)))
        parent[i] = link[i] if best[i] > 1e-4 else -1
        inside[i] = True
        closer = info[i] > best
        best, link = np.where(closer, info[i], best), np.where(closer, i, link)
    return parent


def fit_linear(patterns: DataFrame, model: LabelModel) -> np.ndarray:
    """Weights of the votes, and the constant last: logistic regression on the posterior labels, by Newton steps."""
    k = model.count + 1
    weights = np.zeros(k)
    for _ in range(STEPS):

        def part(votes, label, n, weights=weights):
            x = np.column_stack([bits(votes, model.count), np.ones(len(votes))])
            p = 1 / (1 + np.exp(-np.clip(x @ weights, -30, 30)))
            slope = x.T @ (n * (model.posterior(votes, label) - p))
            curve = (x * (n * p * (1 - p))[:, None]).T @ x
            return np.concatenate([slope, curve.reshape(-1)])

        total = _summed(patterns, k + k * k, part)
        ridge = RIDGE * np.eye(k)
        ridge[-1, -1] = 1e-6
        step = np.linalg.solve(total[k:].reshape(k, k) + ridge, total[:k] - ridge @ weights)
        weights = weights + np.clip(step, -4, 4)
        if np.abs(step).max(initial=0) < 1e-4:
            break
    return weights


def scored(docs: DataFrame, labels: DataFrame, modulus: int = 5, out: int = 0, sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, votes, score, predicted of every row of docs (doc_id, text).

    Labels (doc_id, toxic) count where crc32 of the id, modulo a number, isn't `out`; of several labels
    of an id the largest. Scores come from the text alone. Null texts are empty, repeated rows come out
    repeated, and without labels no word is telling and all scores are low.
    """
    train = labels.where((crc_remainder(F.col("doc_id"), modulus) != out) & F.col("toxic").isin(0, 1)).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    rows = docs.select("doc_id", "text")
    voters = Voters(mine_lexicon(materialise(labelled_sample(rows, train, sample), "labelled")))
    voted = materialise(vote_all(rows, voters), "votes")
    known = voted.join(train, "doc_id", "left").groupBy("votes", F.coalesce(F.col("toxic"), F.lit(-1)).cast("int").alias("label")).agg(F.count(F.lit(1)).alias("n"))
    patterns = materialise(known, "vote_patterns")
    model = LabelModel(voters.count)
    for _ in range(ROUNDS):
        model.update(_summed(patterns, 2 * voters.count**2 + TOTALS, model.sums))
    weights = fit_linear(patterns, model)
    margin = F.lit(float(weights[-1]))
    for i, w in enumerate(weights[:-1]):
        margin = margin + F.when(F.shiftright("votes", i).bitwiseAND(F.lit(1)) == 1, float(w)).otherwise(0.0)
    score = 1 / (1 + F.exp(-margin))
    return voted.select("doc_id", (crc_remainder(F.col("doc_id"), modulus) == out).alias("held_out"), "votes", score.alias("score")).withColumn("predicted", (F.col("score") >= 0.5).cast("int"))
