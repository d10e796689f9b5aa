"""Additive, tree and composite quantizers: a vector is a sum of centroids of the full dimension.

The literature behind leaves training open; here codebooks start as a chain of k-means
on residuals (restricted to overlapping blocks for the tree), and encoding is greedy, by
beam, or by coordinate. Distances from tables are exact whatever the training.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from vecspark.operators.codebook import train_kmeans
from vecspark.plans.kernels import map_batches, matrix, nearest


@dataclass
class Additive:
    books: np.ndarray  # m x k x d
    edges: tuple[tuple[int, int], ...]  # pairs of parts whose products are not zero

    @property
    def m(self) -> int:
        return len(self.books)

    def encode(self, x: np.ndarray, beam: int = 1) -> np.ndarray:
        """Codes by a beam over the parts in order; beam 1 is greedy."""
        if beam == 1:
            rest, out = x.copy(), []
            for book in self.books:
                out.append(nearest(rest, book))
                rest = rest - book[out[-1]]
            return np.stack(out, axis=1)
        out = []
        for v in x:
            front = [(float((v * v).sum()), (), v)]
            for book in self.books:
                grown = []
                for _, codes, rest in front:
                    d = ((rest - book) ** 2).sum(axis=1)
                    grown += [(float(d[i]), codes + (int(i),), rest - book[i]) for i in np.argsort(d, kind="stable")[:beam]]
                front = sorted(grown, key=lambda g: (g[0], g[1]))[:beam]
            out.append(front[0][1])
        return np.array(out)

    def tables(self, q: np.ndarray) -> np.ndarray:
        """|c|^2 - 2 q.c for each query, part and centroid."""
        norms = (self.books.astype(float) ** 2).sum(axis=2)
        return norms[None] - 2 * np.einsum("qd,mkd->qmk", q, self.books.astype(float))

    def products(self) -> dict[tuple[int, int], np.ndarray]:
        """2 c.c' for the pairs of parts in ``edges``."""
        return {(i, j): 2 * self.books[i].astype(float) @ self.books[j].astype(float).T for i, j in self.edges}

    def distances(self, q: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """queries x codes, from look-ups alone: m query tables and a pair table for each edge."""
        t, out = self.tables(q), (q * q).sum(axis=1)[:, None]
        for j in range(self.m):
            out = out + t[:, j, codes[:, j]]
        for (i, j), p in self.products().items():
            out = out + p[codes[:, i], codes[:, j]][None]
        return out

    def lookups(self) -> int:
        return self.m + len(self.edges)


def blocks_of(j: int, m: int, d: int) -> slice:
    """The tree's part j covers blocks j and j + 1 of m + 1, so only neighbours overlap."""
    width = d // (m + 1)
    return slice(j * width, d if j == m - 1 else (j + 2) * width)


def train_residual_chain(training: DataFrame, m: int, k: int, d: int, iters: int = 3, tree: bool = False) -> Additive:
    """Each part is a k-means of what the parts before leave over; the tree's parts see two blocks."""
    kind = dict(training.dtypes)["e"].replace("bigint", "long")
    books: list[np.ndarray] = []
    for j in range(m):
        def make(books=tuple(books), j=j):
            def each(batch):
                x = matrix(batch)
                for book in books:
                    x = x - book[nearest(x, book)]
                return {"vec_id": batch["vec_id"], "e": x[:, blocks_of(j, m, d)] if tree else x}

            return each

        part = train_kmeans(map_batches(training.select("vec_id", "e"), make, f"vec_id long, e {kind}"), k, iters)
        whole = np.zeros((k, d), part.dtype)
        whole[:, blocks_of(j, m, d) if tree else slice(0, d)] = part
        books.append(whole)
    edges = tuple((j, j + 1) for j in range(m - 1)) if tree else tuple((i, j) for i in range(m) for j in range(i + 1, m))
    return Additive(np.stack(books), edges)


def train_composite(sample: np.ndarray, m: int, k: int, rounds: int = 12, penalty: float = 1.0, seed: int = 5) -> tuple[Additive, float]:
    """Codebooks whose cross products sum to nearly one constant, which the scan may drop.

    Alternates greedy codes (with coordinate sweeps) and gradient steps on error plus
    penalised deviation of the cross products. Returns the quantizer and the constant.
    """
    rng = np.random.default_rng(seed)
    x = sample.astype(float)
    width = x.shape[1] // m
    books = np.zeros((m, k, x.shape[1]))
    for j in range(m):  # disjoint blocks: the constant starts at zero
        at = slice(j * width, (j + 1) * width if j < m - 1 else x.shape[1])
        books[j][:, at] = x[rng.choice(len(x), k, replace=len(x) < k)][:, at]
    constant = 0.0
    for _ in range(rounds):
        q = Additive(books, ())
        codes = q.encode(x)
        for _ in range(2):
            for j in range(m):
                others = sum(books[i][codes[:, i]] for i in range(m) if i != j)
                codes[:, j] = nearest(x - others, books[j])
        chosen = np.stack([books[j][codes[:, j]] for j in range(m)])
        whole = chosen.sum(axis=0)
        cross = (whole**2).sum(axis=1) - (chosen**2).sum(axis=(0, 2))
        constant = float(cross.mean())
        scale = (x**2).sum(axis=1).mean()
        for j in range(m):
            gradient = (whole - x) + penalty * ((cross - constant) / scale)[:, None] * (whole - chosen[j])
            for i in range(k):
                own = codes[:, j] == i
                if own.any():
                    books[j][i] -= 0.5 * gradient[own].mean(axis=0)
    return Additive(books, ()), constant


def encode_additive(vectors: DataFrame, model: Additive, beam: int = 1) -> DataFrame:
    def make():
        def each(batch):
            codes = model.encode(matrix(batch), beam)
            return {"vec_id": batch["vec_id"]} | {f"c{j}": codes[:, j] for j in range(model.m)}

        return each

    return map_batches(vectors.select("vec_id", "e"), make, ", ".join(["vec_id long"] + [f"c{j} long" for j in range(model.m)]))


def additive_scan(codes: DataFrame, queries: list[tuple[int, list]], model: Additive, constant: float = 0.0) -> DataFrame:
    """(qid, vec_id, dist) for a batch of queries held by the driver; map-only."""
    number = "long" if np.issubdtype(model.books.dtype, np.integer) else "double"

    def make():
        ids = np.array([q for q, _ in queries])
        x = np.array([v for _, v in queries], float)

        def each(batch):
            c = np.stack([batch[f"c{j}"].to_numpy(zero_copy_only=False) for j in range(model.m)], axis=1)
            d = model.distances(x, c) + constant
            n = len(c)
            return {"qid": np.repeat(ids, n), "vec_id": np.tile(batch["vec_id"].to_numpy(zero_copy_only=False), len(ids)), "dist": d.ravel()}

        return each

    return map_batches(codes, make, f"qid long, vec_id long, dist {number}")
