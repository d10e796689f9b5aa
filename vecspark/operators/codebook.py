"""Codebooks: k-means, equal-size k-means, product, optimised and nested quantizers.

Training sets are bounded samples; a Lloyd step is one job whose tasks emit sums
(parts x centroids x dimensions), never rows. Codebooks are small arrays on the driver.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.functions.ranking import value_of_rank
from vecspark.plans.kernels import map_batches, matrix, nearest, squared


@dataclass
class PQModel:
    """m codebooks of 2^b centroids over d/m dimensions each; an optional rotation comes first."""

    m: int
    b: int
    d: int
    books: np.ndarray  # m x k x d/m
    rotation: np.ndarray | None = None
    coarse: np.ndarray | None = field(default=None, repr=False)  # nested: m x 2^b_coarse x d/m

    @property
    def k(self) -> int:
        return self.books.shape[1]

    @property
    def number(self) -> str:
        return "long" if np.issubdtype(self.books.dtype, np.integer) else "double"

    def rotated(self, x: np.ndarray) -> np.ndarray:
        return x if self.rotation is None else x @ self.rotation.T

    def parts(self, x: np.ndarray) -> list[np.ndarray]:
        return np.split(self.rotated(x), self.m, axis=1)

    def encode(self, x: np.ndarray) -> np.ndarray:
        return np.stack([nearest(p, c) for p, c in zip(self.parts(x), self.books, strict=True)], axis=1)

    def decode(self, codes: np.ndarray) -> np.ndarray:
        y = np.concatenate([c[codes[:, j]] for j, c in enumerate(self.books)], axis=1)
        return y if self.rotation is None else y @ self.rotation

    def tables(self, x: np.ndarray, coarse: bool = False) -> np.ndarray:
        """Distances of each row's sub-vectors to all centroids: n x m x k."""
        return np.stack([squared(p, c) for p, c in zip(self.parts(x), self.coarse if coarse else self.books, strict=True)], axis=1)


def _means(sums: np.ndarray, counts: np.ndarray, old: np.ndarray) -> np.ndarray:
    new = sums / np.maximum(counts, 1)[..., None]
    new = np.floor(new).astype(np.int64) if np.issubdtype(old.dtype, np.integer) else new
    return np.where(counts[..., None] > 0, new, old)


def stride_start(training: DataFrame, k: int, key: str = "vec_id") -> np.ndarray:
    """The vectors of rank floor(i * n / k) by id: k rows at most reach the driver."""
    n = training.count()
    ids = value_of_rank(training, key, [i * n // k for i in range(k)], n)
    wanted = training.sparkSession.createDataFrame([(i,) for i in sorted(set(ids))], f"{key} long")
    rows = {r[key]: r["e"] for r in training.select(key, "e").join(F.broadcast(wanted), key).collect()}
    return np.array([rows[i] for i in ids])


def plusplus_start(training: DataFrame, k: int, seed: int, pool: int = 5000) -> np.ndarray:
    """Seeds drawn by squared distance from a bounded pool of training vectors."""
    rows = training.orderBy(F.xxhash64("vec_id", F.lit(seed)), "vec_id").limit(pool).select("e").collect()
    x, rng = np.array([r["e"] for r in rows], float), np.random.default_rng(seed)
    chosen = [int(rng.integers(len(x)))]
    least = squared(x, x[chosen])[:, 0]
    while len(chosen) < k:
        share = np.maximum(least, 0) / max(least.sum(), 1e-12)
        chosen.append(int(rng.choice(len(x), p=share / share.sum() if share.sum() else None)))
        least = np.minimum(least, squared(x, x[chosen[-1:]])[:, 0])
    return np.array([rows[i]["e"] for i in chosen])


def lloyd_step(training: DataFrame, books: np.ndarray, rotation: np.ndarray | None = None) -> tuple[np.ndarray, float]:
    """One step of all m codebooks in one job: new books, and the squared error before it."""
    m, k, width = books.shape

    def make():
        model = PQModel(m, 0, m * width, books, rotation)

        def each(batch):
            x = matrix(batch)
            codes = model.encode(x)
            out = {"cell": [], "n": [], "sums": []}
            parts = model.parts(x)
            for j in range(m):
                counts = np.bincount(codes[:, j], minlength=k)
                sums = np.zeros((k, width))
                np.add.at(sums, codes[:, j], parts[j])
                error = ((parts[j] - books[j][codes[:, j]]) ** 2).sum()
                for i in np.flatnonzero(counts):
                    out["cell"].append(j * k + int(i))
                    out["n"].append(int(counts[i]))
                    out["sums"].append(np.append(sums[i], 0.0))
                out["cell"].append(m * k)
                out["n"].append(1)
                out["sums"].append(np.append(np.zeros(width), error))
            return {"cell": np.array(out["cell"]), "n": np.array(out["n"]), "sums": np.array(out["sums"])}

        return each

    partial = map_batches(training.select("e"), make, "cell long, n long, sums array<double>")
    total = partial.groupBy("cell").agg(F.sum("n").alias("n"), F.array(*[F.sum(F.col("sums")[i]) for i in range(width + 1)]).alias("sums"))
    counts, sums, error = np.zeros(m * k), np.zeros((m * k, width)), 0.0
    for r in total.collect():  # m * k + 1 rows at most
        if r["cell"] == m * k:
            error = r["sums"][width]
        else:
            counts[r["cell"]], sums[r["cell"]] = r["n"], r["sums"][:width]
    return _means(sums.reshape(books.shape), counts.reshape(m, k), books), error


def train_pq(training: DataFrame, m: int, b: int, iters: int = 3, k: int | None = None, init: str = "stride", seed: int = 7, key: str = "vec_id") -> PQModel:
    """m codebooks by k-means; integer vectors give integer (floored) centroids."""
    k = k or 1 << b
    start = stride_start(training, k, key) if init == "stride" else plusplus_start(training, k, seed)
    books = np.stack(np.split(start, m, axis=1))
    for _ in range(iters):
        books, _ = lloyd_step(training, books)
    return PQModel(m, b, start.shape[1], books)


def train_kmeans(training: DataFrame, k: int, iters: int = 3, init: str = "stride", seed: int = 7) -> np.ndarray:
    """k centroids of whole vectors."""
    return train_pq(training, 1, 0, iters, k, init, seed).books[0]


def train_opq(training: DataFrame, m: int, b: int, iters: int = 8, k: int | None = None) -> tuple[PQModel, list[float]]:
    """Rotation and codebooks by turns: a Lloyd step, then the orthogonal map that brings
    vectors nearest to their reconstructions (from the SVD of a summed d x d matrix).
    Returns the model and the error before each turn."""
    start = stride_start(training, k or 1 << b)
    d = start.shape[1]
    rotation, errors = np.eye(d), []
    books = np.stack(np.split(start.astype(float), m, axis=1))
    for _ in range(iters):
        books, error = lloyd_step(training, books, rotation)
        errors.append(error)
        model = PQModel(m, b, d, books, rotation)

        def make(model=model):
            def each(batch):
                x = matrix(batch)
                y = np.concatenate([c[i] for c, i in zip(model.books, model.encode(x).T, strict=True)], axis=1)
                return {"row": np.arange(d), "sums": y.T @ x}

            return each

        cross = np.zeros((d, d))
        products = map_batches(training.select("e"), make, "row long, sums array<double>")
        for r in products.groupBy("row").agg(F.array(*[F.sum(F.col("sums")[i]) for i in range(d)]).alias("sums")).collect():
            cross[r["row"]] = r["sums"]
        u, _, vt = np.linalg.svd(cross)
        rotation = u @ vt
    books, error = lloyd_step(training, books, rotation)
    return PQModel(m, b, d, books, rotation), errors + [error]


def same_size_partition(points: np.ndarray, clusters: int, iters: int = 6) -> np.ndarray:
    """Cluster of each point, all clusters of one size (len(points) divisible by clusters).

    Points with most to lose choose first; afterwards pairs are swapped between clusters
    while that shortens the sum of distances. The points are a codebook's centroids.
    """
    x = points.astype(float)
    size = len(x) // clusters
    if size * clusters != len(x):
        raise ValueError("the number of points must be a multiple of the number of clusters")
    centers = x[np.linspace(0, len(x) - 1, clusters).astype(int)]
    best, best_cost = None, np.inf
    for _ in range(iters):
        cost = squared(x, centers)
        order = np.argsort(cost.min(axis=1) - cost.max(axis=1), kind="stable")
        room, label = np.full(clusters, size), np.zeros(len(x), int)
        choices = np.argsort(cost, axis=1, kind="stable")
        for i in order:
            label[i] = next(c for c in choices[i] if room[c])
            room[label[i]] -= 1
        for _ in range(4):
            moved = False
            gain = cost[np.arange(len(x)), label][:, None] - cost
            for i in np.argsort(-gain.max(axis=1)):
                c = int(gain[i].argmax())
                if gain[i, c] <= 0 or c == label[i]:
                    continue
                others = np.flatnonzero(label == c)
                change = gain[others, label[i]] + gain[i, c]
                j = others[int(change.argmax())]
                if change.max() > 1e-9:
                    label[i], label[j] = c, label[i]
                    for t in (i, j):
                        gain[t] = cost[t, label[t]] - cost[t]
                    moved = True
            if not moved:
                break
        now = cost[np.arange(len(x)), label].sum()
        if now < best_cost:
            best, best_cost = label.copy(), now
        centers = np.stack([x[label == c].mean(axis=0) for c in range(clusters)])
    return best


def ntile_partition(points: np.ndarray, clusters: int) -> np.ndarray:
    """Control: clusters of one size by the order of coordinate sums (ties by index)."""
    order = np.lexsort((np.arange(len(points)), points.sum(axis=1)))
    label = np.empty(len(points), int)
    label[order] = np.arange(len(points)) // (len(points) // clusters)
    return label


def partition(points: np.ndarray, clusters: int, numbering: str) -> np.ndarray:
    return same_size_partition(points, clusters) if numbering == "same_size" else ntile_partition(points, clusters)


def renumber(model: PQModel, clusters: int = 16, numbering: str = "same_size") -> tuple[PQModel, np.ndarray]:
    """Centroids in an order that gives each cluster consecutive indices (its number is the
    index's high part). Returns the model and, for each part, the new index of each old one."""
    books, maps = np.empty_like(model.books), np.empty(model.books.shape[:2], int)
    for j, book in enumerate(model.books):
        label = partition(book, clusters, numbering)
        order = np.lexsort((np.arange(len(book)), label))
        books[j], maps[j][order] = book[order], np.arange(len(book))
    return PQModel(model.m, model.b, model.d, books, model.rotation), maps


def nest(model: PQModel, b_coarse: int, numbering: str = "same_size") -> PQModel:
    """Fine codebooks renumbered so that the low b_coarse bits of an index are its cluster,
    and the coarse codebook of the clusters' means."""
    clusters = 1 << b_coarse
    books = np.empty_like(model.books)
    coarse = np.empty((model.m, clusters, model.books.shape[2]), model.books.dtype)
    for j, book in enumerate(model.books):
        label = partition(book, clusters, numbering)
        for c in range(clusters):
            own = np.flatnonzero(label == c)
            books[j][np.arange(len(own)) * clusters + c] = book[own]
            mean = book[own].sum(axis=0) / len(own)
            coarse[j, c] = np.floor(mean) if np.issubdtype(book.dtype, np.integer) else mean
    return PQModel(model.m, model.b, model.d, books, model.rotation, coarse)


def train_nested(training: DataFrame, m: int, b: int, b_coarse: int, iters: int = 3, numbering: str = "same_size") -> PQModel:
    return nest(train_pq(training, m, b, iters), b_coarse, numbering)
