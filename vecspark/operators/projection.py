"""Principal axes and random rotations."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.plans.kernels import map_batches, matrix


def moments(vectors: DataFrame, d: int) -> tuple[int, np.ndarray, np.ndarray]:
    """Number, mean and covariance from one aggregate of d + 1 rows."""

    def make():
        def each(batch):
            x = np.column_stack([matrix(batch), np.ones(batch.num_rows)])
            return {"row": np.arange(d + 1), "sums": x.T @ x}

        return each

    parts = map_batches(vectors.select("e"), make, "row long, sums array<double>")
    total = np.zeros((d + 1, d + 1))
    for r in parts.groupBy("row").agg(F.array(*[F.sum(F.col("sums")[i]) for i in range(d + 1)]).alias("s")).collect():
        total[r["row"]] = r["s"]
    n = total[d, d]
    mean = total[d, :d] / max(n, 1)
    return int(n), mean, total[:d, :d] / max(n, 1) - np.outer(mean, mean)


def pca_compress(vectors: DataFrame, k: int, center: bool = True) -> tuple[DataFrame, np.ndarray]:
    """(vec_id, e of k) and the k axes; signs make each axis's largest weight positive."""
    d = len(vectors.select("e").first()["e"])
    _, mean, covariance = moments(vectors, d)
    values, axes = np.linalg.eigh(covariance)
    axes = axes[:, np.argsort(-values)[:k]].T
    axes *= np.sign(axes[np.arange(k), np.abs(axes).argmax(axis=1)])[:, None]
    shift = mean if center else np.zeros(d)

    def make():
        return lambda batch: {"vec_id": batch["vec_id"], "e": (matrix(batch) - shift) @ axes.T}

    return map_batches(vectors.select("vec_id", "e"), make, "vec_id long, e array<double>"), axes


FIXED = 4096


def fixed_rotation(d: int, seed: int) -> list[list[int]]:
    """A random rotation in fixed point."""
    return np.rint(random_rotation(d, seed) * FIXED).astype(int).tolist()


def rotate_fixed(vectors: DataFrame, rotation: list[list[int]]) -> DataFrame:
    """(vec_id, floor(R e / 4096)) of integer vectors; sums stay below 2^53."""
    r = np.array(rotation, float)

    def make():
        return lambda batch: {"vec_id": batch["vec_id"], "e": np.floor((matrix(batch) @ r.T) / FIXED).astype(np.int64)}

    return map_batches(vectors.select("vec_id", "e"), make, "vec_id long, e array<long>")


def random_rotation(d: int, seed: int) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(d, d)))
    return q * np.sign(np.diag(r))
