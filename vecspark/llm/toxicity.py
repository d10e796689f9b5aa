"""Toxic passages by maximum-scoring segments of token log-odds.

Training: words of labelled documents are counted by class with grouped aggregation;
log-odds with an informative Dirichlet prior (the pooled counts) and their standard
error tell which words mark the class; all other words share the small negative
log-ratio that is left for them. Scoring: the scores' maximal segments are found in
one pass, and extreme-value theory turns a segment's score into evidence beyond
what a text of that length holds by chance. A logistic fit on the same sample maps
the evidence to a probability.

Defined cases: null text is empty; empty texts get the score of no evidence; no
labels at all give every text the same low score; repeated rows are scored each; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
import string
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.llm.common import Scratch, arrow_rows, fold, slices
from vecspark.llm.labelled import fit_logistic, labelled_sample, sigmoid, scored_rows

EDGE = string.punctuation + "«»“”„‘’…–—¿¡"
PARTS, HELD = 4, 2


def words_of(text: str) -> list[str]:
    """Lower-case words without marks at their edges; words of marks alone stay as empty words."""
    return [w.strip(EDGE) for w in text.lower().split()]


class Weights(dict):
    """Scores of raw words (marks at the edges count as nothing), kept up to a limit."""

    def __init__(self, model: dict[str, float], other: float):
        super().__init__()
        self.model, self.other = model, other

    def __missing__(self, word: str) -> float:
        value = self.model.get(word.strip(EDGE), self.other)
        if len(self) >= 400_000:
            self.clear()
        if len(word) <= 64:
            self[word] = value
        return value


def maximal_segments(scores: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal scoring segments [start, end) with their sums, left to right, in linear time.

    Each candidate keeps the running total before it (left) and after it (right). A new
    positive run joins back over candidates while an earlier one starts lower; runs of
    non-positive scores only move the total.
    """
    at = np.flatnonzero(scores > 0)
    if not len(at):
        return []
    before = np.concatenate(([0.0], np.cumsum(scores)))
    # Neighbouring positive scores form one run.
    starts = at[np.concatenate(([True], np.diff(at) > 1))]
    ends = at[np.concatenate((np.diff(at) > 1, [True]))] + 1
    stack: list[list[float]] = []  # start, end, left, right, index of the nearest earlier one with lower left
    for s, e in zip(starts.tolist(), ends.tolist(), strict=True):
        start, left, right = s, float(before[s]), float(before[e])
        while True:
            j = len(stack) - 1
            while j >= 0 and stack[j][2] >= left:
                j = stack[j][4]
            if j < 0 or stack[j][3] >= right:
                stack.append([start, e, left, right, j])
                break
            start, left = stack[j][0], stack[j][2]
            del stack[j:]
    return [(int(s), int(e), r - l) for s, e, l, r, _ in stack]


class Model:
    """Word scores, extreme-value constants and the logistic map."""

    def __init__(self, weights: dict[str, float], other: float, scale: float, rate: float, fit: list[float] | None = None):
        self.weights, self.other, self.scale, self.rate, self.fit = weights, other, scale, rate, fit

    def evidence(self, words: list[str], table: Weights) -> tuple[list[float], list[tuple[int, int, float, float]]]:
        """Features of a text and its significant segments (start, end, score, evidence)."""
        n = len(words)
        if not n:
            return [0.0, 0.0, 0.0, 0.0], []
        scores = np.fromiter([table[w] for w in words], float, n)
        chance = math.log(max(self.rate * n, 1e-12))
        found = [(s, e, v, self.scale * v - chance) for s, e, v in maximal_segments(scores)]
        good = [x for x in found if x[3] > 0]
        total = sum(x[3] for x in good)
        best = max((x[3] for x in found), default=-abs(chance))
        return [max(-20.0, min(60.0, best)), math.log1p(total), min(1.0, max(0.0, sum(x[2] for x in good)) / n), float(scores.sum()) / n], good


def _count(batch_rows: int = 512):
    schema = pa.schema([("word", pa.string()), ("toxic", pa.int64()), ("clean", pa.int64())])

    def make():
        def each(batch: pa.RecordBatch):
            tallies = (Counter(), Counter())
            for text, label in zip(batch["text"].to_pylist(), batch["label"].to_pylist(), strict=True):
                tallies[0 if label else 1].update(set(words_of(text)))  # once a document, so that bursts count once
            words = list(tallies[0].keys() | tallies[1].keys())
            yield pa.RecordBatch.from_arrays([pa.array(words, pa.string()), pa.array([tallies[0][w] for w in words], pa.int64()), pa.array([tallies[1][w] for w in words], pa.int64())], schema=schema)

        return each

    return make


def train(spark: SparkSession, documents: DataFrame, labels: DataFrame, limit: int = 8000, prior: float = 0.1, z: float = 3.0, seen: int = 4) -> Model:
    """``limit``: labelled documents used at most; ``prior``: weight of the pooled counts, as a share of all counts
    (a tenth of it when the weight itself is taken);
    ``z``: standard errors by which a word must stand out; ``seen``: labelled documents that must hold it, as the
    normal approximation behind ``z`` says nothing of fewer. All such words weigh; the sample bounds their number."""
    scratch = Scratch(spark, "toxicity")
    sample = labelled_sample(scratch, documents, labels, "toxic", PARTS, HELD, limit)
    counts = scratch.keep(arrow_rows(sample, _count(), "word string, toxic long, clean long").groupBy("word").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean")), "counts")
    sums = counts.agg(F.coalesce(F.sum("toxic"), F.lit(0)).alias("toxic"), F.coalesce(F.sum("clean"), F.lit(0)).alias("clean")).first()
    n1, n0 = max(1, sums["toxic"]), max(1, sums["clean"])

    def odds(share: float) -> tuple:
        """Log-odds of the classes under a prior of that share of the pooled counts, and its variance."""
        pooled, mass = F.lit(share) * (F.col("toxic") + F.col("clean")), share * (n1 + n0)
        logs = [F.log((F.col(c) + pooled) / (F.lit(float(n) + mass) - F.col(c) - pooled)) for c, n in (("toxic", n1), ("clean", n0))]
        return logs[0] - logs[1], 1 / (F.col("toxic") + pooled) + 1 / (F.col("clean") + pooled)

    (tested, variance), (delta, _) = odds(prior), odds(prior / 10)
    scored = counts.where("word <> ''").select("word", "toxic", "clean", delta.alias("delta"), (tested / F.sqrt(variance)).alias("z"))
    marked = scored.where((F.abs("z") > z) & (F.col("toxic") + F.col("clean") >= seen)).orderBy("word").collect()
    weights = {r["word"]: float(np.clip(r["delta"], -8, 8)) for r in marked}
    p1 = sum(r["toxic"] for r in marked) / n1
    p0 = sum(r["clean"] for r in marked) / n0
    other = min(-0.01, math.log(max(1e-6, 1 - p1) / max(1e-6, 1 - p0)))
    # The scale at which clean text's scores have mean exponential 1, and how often clean text opens a segment.
    base = [((r["clean"] + 0.5) / n0, weights[r["word"]]) for r in marked] + [(max(1e-6, 1 - p0), other)]

    def excess(scale: float) -> float:
        return sum(p * math.exp(scale * w) for p, w in base) - 1

    low, high = 1e-3, 1.0
    while high < 16 and excess(high) < 0:
        high *= 2
    for _ in range(60):
        middle = (low + high) / 2
        low, high = (middle, high) if excess(middle) < 0 else (low, middle)
    scale = high
    rate = sum(p * math.exp(scale * w) for p, w in base[:-1] if w > 0) or 1e-6
    model = Model(weights, other, scale, rate)
    rows = arrow_rows(sample, _features(model), "label int, f array<double>").collect()  # limit rows of four numbers
    x = np.array([r["f"] for r in rows], float).reshape(-1, 4)
    model.fit = fit_logistic(x, np.array([r["label"] for r in rows], float)).tolist()
    scratch.drop()
    return model


def _features(model: Model):
    schema = pa.schema([("label", pa.int32()), ("f", pa.list_(pa.float64()))])

    def make():
        table = Weights(model.weights, model.other)

        def each(batch: pa.RecordBatch):
            f = [model.evidence(t.lower().split(), table)[0] for t in batch["text"].to_pylist()]
            yield pa.RecordBatch.from_arrays([batch["label"].cast(pa.int32()), pa.array(f, schema.field(1).type)], schema=schema)

        return each

    return make


SCORES = "doc_id long, score double, passages array<struct<start:int,end:int,score:double,evidence:double>>"


def _score(model: Model):
    passage = pa.struct([("start", pa.int32()), ("end", pa.int32()), ("score", pa.float64()), ("evidence", pa.float64())])
    schema = pa.schema([("doc_id", pa.int64()), ("score", pa.float64()), ("passages", pa.list_(passage))])

    def make():
        table, w = Weights(model.weights, model.other), np.array(model.fit)

        def each(batch: pa.RecordBatch):
            for part in slices(batch):
                scores, passages = [], []
                for text in part.column(1).to_pylist():
                    f, good = model.evidence((text or "").lower().split(), table)
                    scores.append(float(sigmoid(np.dot(w[:-1], f) + w[-1])))
                    passages.append([dict(zip(("start", "end", "score", "evidence"), g, strict=True)) for g in good])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(scores, pa.float64()), pa.array(passages, schema.field(2).type)], schema=schema)

        return each

    return make


def score(documents: DataFrame, model: Model) -> DataFrame:
    """(doc_id, text) -> (doc_id, score, passages by word position); map-only."""
    return arrow_rows(documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), _score(model), SCORES)


def score_rows(documents: DataFrame, model: Model) -> DataFrame:
    """The rows of ``documents`` (which have a ``text``) with their score; map-only."""
    return scored_rows(documents, lambda: _scorer(model))


def _scorer(model: Model):
    table, w = Weights(model.weights, model.other), np.array(model.fit)

    def each(texts: list[str | None]) -> list[float]:
        return [float(sigmoid(np.dot(w[:-1], model.evidence((t or "").lower().split(), table)[0]) + w[-1])) for t in texts]

    return each


def with_folds(scored: DataFrame, parts: int, held: int, threshold: float = 0.3) -> DataFrame:
    return scored.select("doc_id", (fold("doc_id", parts) == held).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), *[c for c in scored.columns if c not in ("doc_id", "score")])
