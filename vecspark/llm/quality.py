"""Document quality by attention-based multiple-instance learning over passages.

Every passage of a document (64 words) is encoded by shares of character classes,
word statistics and how much it repeats; a gated attention network learns from
document labels which passages matter, and scores the weighted representation.

Defined cases: null text is empty; a text without words is one empty passage;
without labels every text gets the same score; repeated rows are scored each; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.llm.common import Scratch, arrow_rows, slices
from vecspark.llm.labelled import labelled_sample, sigmoid, scored_rows

PARTS, HELD = 5, 0
PASSAGE = 64
# Characters that share a class; classes are numbered from 1, all other bytes are 0.
CLASSES = ("abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", " ", "\n", "\t\r\x0b\x0c", ".", ",", ";:", "!", "?", "%", "*", "&", "$", "#", "|", "<>", "()[]{}", "@", "_", "-", "'\"`", "/\\", "=+~^")


def _byte_classes() -> np.ndarray:
    out = np.zeros(256, np.int64)
    for number, chars in enumerate(CLASSES, 1):
        out[list(chars.encode())] = number
    out[128:] = len(CLASSES) + 1
    return out


BYTE_CLASS = _byte_classes()
N_CLASSES = len(CLASSES) + 2
WIDTH = N_CLASSES + 7
IS_SPACE = np.isin(np.arange(256), list(b" \n\t\r\x0b\x0c"))


def encode(text: str) -> np.ndarray:
    """Passages x features, from the whole text."""
    raw = text.encode()
    words = raw.split()
    if not words:
        out = np.zeros((1, WIDTH))
        out[0, -1] = 1
        return out
    data = np.frombuffer(raw, np.uint8)
    space = IS_SPACE[data]
    starts = np.flatnonzero(~space & np.concatenate(([True], space[:-1])))
    cuts = starts[::PASSAGE]
    cuts[0] = 0
    n = len(cuts)
    which = np.zeros(len(data), np.int64)
    which[cuts[1:]] = 1
    np.cumsum(which, out=which)
    shares = np.bincount(which * N_CLASSES + BYTE_CLASS[data], minlength=n * N_CLASSES).reshape(n, N_CLASSES)
    sizes = shares.sum(axis=1)
    known: dict[bytes, int] = {}
    ids = np.array([known.setdefault(w, len(known)) for w in words])
    passage = np.arange(len(ids)) // PASSAGE
    counts = np.bincount(passage, minlength=n)
    same = np.concatenate(([False], ids[1:] == ids[:-1]))
    repeats = np.bincount(passage, weights=same, minlength=n) / counts
    top = np.maximum.accumulate(ids)
    fresh = np.bincount(passage, weights=np.concatenate(([True], top[1:] > top[:-1])), minlength=n) / counts
    distinct = np.array([len(set(words[i : i + PASSAGE])) for i in range(0, len(words), PASSAGE)]) / counts
    pairs = len(np.unique(ids[1:] * len(known) + ids[:-1])) / max(1, len(ids) - 1) if len(ids) > 1 else 1.0
    out = np.empty((n, WIDTH))
    out[:, :N_CLASSES] = np.sqrt(shares / sizes[:, None])
    out[:, N_CLASSES:] = np.column_stack([repeats, fresh, distinct, np.full(n, pairs), np.minimum(sizes / counts, 40) / 10, np.full(n, np.log1p(len(words)) / 10), np.zeros(n)])
    return out


class Attention:
    """Encoder, gated attention and scorer; ``starts`` marks each document's first passage."""

    NAMES = ("enc", "enc_b", "tan", "gate", "att", "out", "out_b")

    def __init__(self, mean: np.ndarray, spread: np.ndarray, weights: dict[str, np.ndarray]):
        self.mean, self.spread, self.w = mean, spread, weights

    @classmethod
    def fresh(cls, x: np.ndarray, hidden: int, seed: int) -> Attention:
        rng, d = np.random.default_rng(seed), x.shape[1]
        w = {"enc": rng.normal(0, d**-0.5, (d, hidden)), "enc_b": np.zeros(hidden), "tan": rng.normal(0, hidden**-0.5, (hidden, hidden)), "gate": rng.normal(0, hidden**-0.5, (hidden, hidden)), "att": rng.normal(0, hidden**-0.5, hidden), "out": rng.normal(0, hidden**-0.5, hidden), "out_b": np.zeros(1)}
        return cls(x.mean(axis=0), x.std(axis=0) + 0.02, w)

    def forward(self, x: np.ndarray, starts: np.ndarray) -> dict[str, np.ndarray]:
        w = self.w
        size = np.diff(np.append(starts, len(x)))
        z = np.clip((x - self.mean) / self.spread, -8, 8)
        h = np.tanh(z @ w["enc"] + w["enc_b"])
        t, g = np.tanh(h @ w["tan"]), sigmoid(h @ w["gate"])
        a = (t * g) @ w["att"]
        a = np.exp(a - np.repeat(np.maximum.reduceat(a, starts), size))
        a /= np.repeat(np.add.reduceat(a, starts), size)
        bag = np.add.reduceat(h * a[:, None], starts)
        return {"size": size, "z": z, "h": h, "t": t, "g": g, "a": a, "bag": bag, "p": sigmoid(bag @ w["out"] + w["out_b"][0])}

    def gradient(self, x: np.ndarray, starts: np.ndarray, y: np.ndarray, weight: np.ndarray) -> dict[str, np.ndarray]:
        f, w = self.forward(x, starts), self.w
        d = (f["p"] - y) * weight / weight.sum()
        g = {"out": f["bag"].T @ d, "out_b": np.array([d.sum()])}
        to_bag = np.repeat(d, f["size"])[:, None] * w["out"]
        along = (to_bag * f["h"]).sum(axis=1)
        da = f["a"] * (along - np.repeat(np.add.reduceat(f["a"] * along, starts), f["size"]))
        g["att"] = (f["t"] * f["g"]).T @ da
        inner = da[:, None] * w["att"]
        dt, dg = inner * f["g"] * (1 - f["t"] ** 2), inner * f["t"] * f["g"] * (1 - f["g"])
        g["tan"], g["gate"] = f["h"].T @ dt, f["h"].T @ dg
        dh = (to_bag * f["a"][:, None] + dt @ w["tan"].T + dg @ w["gate"].T) * (1 - f["h"] ** 2)
        g["enc"], g["enc_b"] = f["z"].T @ dh, dh.sum(axis=0)
        return g

    def fit(self, x: np.ndarray, starts: np.ndarray, y: np.ndarray, steps: int = 400, rate: float = 0.01, decay: float = 1e-4, batch: int = 256, seed: int = 7) -> Attention:
        """Adam over batches of documents."""
        m, v = ({k: np.zeros_like(a) for k, a in self.w.items()} for _ in range(2))
        rng, size = np.random.default_rng(seed), np.diff(np.append(starts, len(x)))
        for i in range(1, steps + 1):
            own = rng.choice(len(y), min(batch, len(y)), replace=False)
            first = np.cumsum(np.append(0, size[own][:-1]))
            rows = np.repeat(starts[own] - first, size[own]) + np.arange(size[own].sum())
            for k, g in self.gradient(x[rows], first, y[own], np.ones(len(own))).items():
                g = g + decay * self.w[k]
                m[k] = 0.9 * m[k] + 0.1 * g
                v[k] = 0.999 * v[k] + 0.001 * g * g
                self.w[k] = self.w[k] - rate * (m[k] / (1 - 0.9**i)) / (np.sqrt(v[k] / (1 - 0.999**i)) + 1e-8)
        return self


def _encode_sample():
    schema = pa.schema([("doc_id", pa.int64()), ("label", pa.int32()), ("passages", pa.binary())])

    def each(batch: pa.RecordBatch):
        for part in slices(batch, 128):
            out = [encode(text).astype("<f4").tobytes() for text in part["text"].to_pylist()]
            yield pa.RecordBatch.from_arrays([part["doc_id"], part["label"].cast(pa.int32()), pa.array(out, pa.binary())], schema=schema)

    return each


def train(spark: SparkSession, documents: DataFrame, labels: DataFrame, limit: int = 4000, hidden: int = 12, seed: int = 7) -> Attention:
    """``limit``: labelled documents at most; training uses every passage of each."""
    scratch = Scratch(spark, "quality")
    sample = labelled_sample(scratch, documents, labels, "quality", PARTS, HELD, limit)
    rows = arrow_rows(sample, _encode_sample, "doc_id long, label int, passages binary").collect()
    rows.sort(key=lambda r: r["doc_id"])
    bags = [np.frombuffer(r["passages"], "<f4").reshape(-1, WIDTH) for r in rows] or [np.zeros((1, WIDTH), "<f4")]
    x = np.concatenate(bags).astype(float)
    starts = np.cumsum([0] + [len(b) for b in bags[:-1]])
    y = np.array([r["label"] for r in rows] or [1], float)
    model = Attention.fresh(x, hidden, seed)
    if rows:
        model.fit(x, starts, y)
    scratch.drop()
    return model


SCORES = "doc_id long, score double, passages int, strongest int"


def _score(model: Attention):
    schema = pa.schema([("doc_id", pa.int64()), ("score", pa.float64()), ("passages", pa.int32()), ("strongest", pa.int32())])

    def make():
        def each(batch: pa.RecordBatch):
            for part in slices(batch, 128):
                bags = [encode(t or "") for t in part.column(1).to_pylist()]
                sizes = [len(b) for b in bags]
                starts = np.cumsum([0] + sizes[:-1])
                f = model.forward(np.concatenate(bags), starts)
                strongest = [int(np.argmax(f["a"][s : s + n])) for s, n in zip(starts, sizes, strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(f["p"], pa.float64()), pa.array(sizes, pa.int32()), pa.array(strongest, pa.int32())], schema=schema)

        return each

    return make


def score(documents: DataFrame, model: Attention) -> DataFrame:
    """(doc_id, text) -> (doc_id, score, passages, strongest: the passage with most attention); map-only."""
    return arrow_rows(documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), _score(model), SCORES)


def score_rows(documents: DataFrame, model: Attention) -> DataFrame:
    """The rows of ``documents`` (which have a ``text``) with their score; map-only."""

    def make():
        def each(texts: list[str | None]) -> list[float]:
            bags = [encode(t or "") for t in texts]
            starts = np.cumsum([0] + [len(b) for b in bags[:-1]])
            return model.forward(np.concatenate(bags), starts)["p"].tolist()

        return each

    return scored_rows(documents, make, 128)
