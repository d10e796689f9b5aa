"""KD-trees and forests, k-means trees. Nodes are few and live on the driver; vectors stay put.

Nodes are numbered as in a heap: the root is 1, the children of i are 2i and 2i + 1.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.functions.ranking import top_k
from vecspark.functions.vectors import l2sq
from vecspark.operators.codebook import train_kmeans
from vecspark.plans.kernels import map_batches, matrix, nearest, squared


@dataclass
class KdTree:
    depth: int
    d: int
    nodes: dict[int, tuple[int, float]]  # node -> (dimension, threshold)

    def leaf_of(self, x: np.ndarray) -> np.ndarray:
        dims, cuts = np.zeros(1 << self.depth, np.int64), np.full(1 << self.depth, -np.inf)
        for i, (dim, cut) in self.nodes.items():
            if i < len(dims):
                dims[i], cuts[i] = dim, cut
        at, rows = np.ones(len(x), np.int64), np.arange(len(x))
        for _ in range(self.depth):
            at = at * 2 + (x[rows, dims[at]] >= cuts[at])
        return at

    def boxes(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Leaf numbers with their lower and upper corners."""
        leaves = np.arange(1 << self.depth, 2 << self.depth)
        low, high = np.full((len(leaves), self.d), -np.inf), np.full((len(leaves), self.d), np.inf)
        for row, leaf in enumerate(leaves):
            i = int(leaf)
            while i > 1:
                dim, cut = self.nodes.get(i // 2, (0, -np.inf))
                if i % 2:
                    low[row, dim] = max(low[row, dim], cut)
                else:
                    high[row, dim] = min(high[row, dim], cut)
                i //= 2
        return leaves, low, high

    def leaf_distances(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        leaves, low, high = self.boxes()
        gap = np.maximum(np.maximum(low - x[:, None, :], x[:, None, :] - high), 0)
        return leaves, (gap**2).sum(axis=2)


def kdtree_build(vectors: DataFrame, d: int, depth: int, pick: Callable[[int], int] = lambda node: 0, approximate: bool = False) -> KdTree:
    """Level by level: variances of all dimensions of all nodes in one aggregate, then the medians
    of the chosen ones. ``pick``: which place by variance a node splits on (0: the greatest).
    ``approximate``: medians by sketch instead of exact counts."""
    tree = KdTree(0, d, {})
    for level in range(depth):
        placed = with_leaf(vectors, tree)
        moments: dict[int, np.ndarray] = {}
        for r in leaf_moments(vectors, tree).groupBy("leaf", "dim").agg(F.sum("n").alias("n"), F.sum("s").alias("s"), F.sum("q").alias("q")).collect():
            moments.setdefault(r["leaf"], np.zeros((3, d)))[:, r["dim"]] = r["n"], r["s"], r["q"]
        split = {}
        for leaf, (n, sums, squares) in moments.items():
            spread = n * squares - sums**2
            split[leaf] = int(np.lexsort((np.arange(d), -spread))[pick(leaf)])
        chosen = F.element_at(F.create_map(*[F.lit(v) for kv in split.items() for v in kv]), F.col("leaf").cast("int"))
        value = placed.select("leaf", F.get("e", chosen).alias("x"))
        median = F.percentile_approx("x", 0.5, 10_000) if approximate else F.expr("percentile_disc(0.5) within group (order by x)")
        for r in value.groupBy("leaf").agg(median.alias("cut")).collect():
            tree.nodes[r["leaf"]] = (split[r["leaf"]], r["cut"])
        tree.depth = level + 1
    return tree


def leaf_moments(vectors: DataFrame, tree: KdTree) -> DataFrame:
    """(leaf, dim, n, s, q): counts, sums and sums of squares of each batch's rows."""

    def make():
        def each(batch):
            x = matrix(batch)
            leaf = tree.leaf_of(x)
            own = np.unique(leaf)
            d = x.shape[1]
            sums = [np.stack([values[leaf == i].sum(axis=0) for i in own]) for values in (x, x * x)]
            n = np.repeat([np.count_nonzero(leaf == i) for i in own], d)
            return {"leaf": np.repeat(own, d), "dim": np.tile(np.arange(d), len(own)), "n": n, "s": sums[0].ravel(), "q": sums[1].ravel()}

        return each

    return map_batches(vectors.select("e"), make, "leaf long, dim long, n long, s double, q double")


def with_leaf(vectors: DataFrame, tree: KdTree, key: str = "vec_id") -> DataFrame:
    """(key, e, leaf); map-only."""
    kind = dict(vectors.dtypes)["e"].replace("bigint", "long")

    def make():
        return lambda batch: {key: batch[key], "e": batch["e"], "leaf": tree.leaf_of(matrix(batch))}

    return map_batches(vectors.select(key, "e"), make, f"{key} long, e {kind}, leaf long")


def leaf_order(queries: DataFrame, tree: KdTree, order: str = "priority") -> DataFrame:
    """(qid, leaf, dist, rk): leaves by box distance, or in the order of depth-first backtracking."""

    def make():
        def backtrack(x: np.ndarray) -> list[int]:
            out, stack = [], [1]
            while stack:
                i = stack.pop()
                while i < 1 << tree.depth:
                    dim, cut = tree.nodes.get(i, (0, -np.inf))
                    near = i * 2 + int(x[dim] >= cut)
                    stack.append(near ^ 1)
                    i = near
                out.append(i)
            return out

        def each(batch):
            x = matrix(batch)
            leaves, dist = tree.leaf_distances(x)
            ids = batch["qid"].to_numpy(zero_copy_only=False)
            out = {"qid": [], "leaf": [], "dist": [], "rk": []}
            for q, row, v in zip(ids, dist, x, strict=True):
                ranked = leaves[np.lexsort((leaves, row))] if order == "priority" else np.array(backtrack(v))
                out["qid"].append(np.full(len(leaves), q))
                out["leaf"].append(ranked)
                out["dist"].append(row[ranked - leaves[0]])
                out["rk"].append(np.arange(1, len(leaves) + 1))
            return {k: np.concatenate(v) for k, v in out.items()}

        return each

    return map_batches(queries.select("qid", "e"), make, f"qid long, leaf long, dist {dict(queries.dtypes)['e'][6:-1].replace('bigint', 'long')}, rk long")


def scan_leaves(placed: DataFrame, queries: DataFrame, visited: DataFrame, k: int, d: int) -> DataFrame:
    """Exact distances to the vectors of the visited leaves: (qid, rk, vec_id, dist)."""
    probes = visited.select("qid", "leaf").join(queries.withColumnRenamed("e", "q"), "qid")
    scored = placed.join(F.broadcast(probes), "leaf").select("qid", "vec_id", l2sq(F.col("q"), F.col("e"), d).alias("dist"))
    return top_k(scored.distinct(), k, ["qid"], ["dist", "vec_id"])


def kdtree_knn(placed: DataFrame, queries: DataFrame, tree: KdTree, k: int, n_max: int | None = None, order: str = "priority") -> DataFrame:
    """Stopped after n_max leaves, or exact: the own leaf gives a ball, then the leaves that meet it."""
    ranked = leaf_order(queries, tree, order)
    if n_max is not None:
        return scan_leaves(placed, queries, ranked.where(F.col("rk") <= n_max), k, tree.d)
    first = scan_leaves(placed, queries, ranked.where("rk = 1"), k, tree.d)
    ball = first.groupBy("qid").agg(F.max("dist").alias("ball"), F.count("*").alias("n"))
    meets = ranked.join(F.broadcast(ball), "qid", "left").where((F.coalesce("n", F.lit(0)) < k) | (F.col("leaf_dist" if "leaf_dist" in ranked.columns else "dist") <= F.col("ball")))
    return scan_leaves(placed, queries, meets, k, tree.d)


def kdforest_knn(vectors: DataFrame, queries: DataFrame, trees: list[tuple[KdTree, np.ndarray | None]], k: int, n_max: int, d: int) -> DataFrame:
    """n_max leaves shared by the trees; a tree may look at rotated vectors. Distances are of the originals."""
    share, found = max(1, n_max // len(trees)), None
    for tree, rotation in trees:
        v, q = (vectors, queries) if rotation is None else (rotate(vectors, rotation, "vec_id"), rotate(queries, rotation, "qid"))
        visited = leaf_order(q, tree).where(F.col("rk") <= share).select("qid", "leaf")
        pairs = with_leaf(v, tree).select("vec_id", "leaf").join(F.broadcast(visited), "leaf").select("qid", "vec_id")
        found = pairs if found is None else found.unionByName(pairs)
    scored = found.dropDuplicates(["qid", "vec_id"]).join(vectors, "vec_id").join(F.broadcast(queries.withColumnRenamed("e", "q")), "qid")
    return top_k(scored.select("qid", "vec_id", l2sq(F.col("q"), F.col("e"), d).alias("dist")), k, ["qid"], ["dist", "vec_id"])


def rotate(vectors: DataFrame, rotation: np.ndarray, key: str) -> DataFrame:
    def make():
        return lambda batch: {key: batch[key], "e": matrix(batch) @ rotation.T}

    return map_batches(vectors.select(key, "e"), make, f"{key} long, e array<double>")


@dataclass
class KmeansTree:
    """Two levels of k centroids each; leaf = first * k + second."""

    first: np.ndarray
    second: np.ndarray  # k x k x d

    @property
    def k(self) -> int:
        return len(self.first)

    def leaf_of(self, x: np.ndarray) -> np.ndarray:
        top = nearest(x, self.first)
        out = np.empty(len(x), np.int64)
        for i in range(self.k):
            own = np.flatnonzero(top == i)
            out[own] = i * self.k + nearest(x[own], self.second[i])
        return out


def kmeans_tree(vectors: DataFrame, k: int, iters: int = 3) -> KmeansTree:
    first = train_kmeans(vectors, k, iters)
    kind = dict(vectors.dtypes)["e"].replace("bigint", "long")

    def make():
        return lambda batch: {"vec_id": batch["vec_id"], "e": batch["e"], "top": nearest(matrix(batch), first)}

    placed = map_batches(vectors.select("vec_id", "e"), make, f"vec_id long, e {kind}, top long")
    return KmeansTree(first, np.stack([train_kmeans(placed.where(F.col("top") == i), k, iters) for i in range(k)]))


def kmeans_leaves(vectors: DataFrame, tree: KmeansTree) -> DataFrame:
    kind = dict(vectors.dtypes)["e"].replace("bigint", "long")

    def make():
        return lambda batch: {"vec_id": batch["vec_id"], "e": batch["e"], "leaf": tree.leaf_of(matrix(batch))}

    return map_batches(vectors.select("vec_id", "e"), make, f"vec_id long, e {kind}, leaf long")


def kmeans_tree_knn(vectors: DataFrame, queries: DataFrame, tree: KmeansTree, k: int, n_max: int, d: int) -> DataFrame:
    """The n_max leaves of the nearest leaf centroids."""
    centers = tree.second.reshape(tree.k * tree.k, -1)

    def make():
        def each(batch):
            dist = squared(matrix(batch), centers)
            leaf = np.argsort(dist, axis=1, kind="stable")[:, :n_max]
            return {"qid": np.repeat(batch["qid"].to_numpy(zero_copy_only=False), leaf.shape[1]), "leaf": leaf.ravel()}

        return each

    visited = map_batches(queries.select("qid", "e"), make, "qid long, leaf long")
    return scan_leaves(kmeans_leaves(vectors, tree), queries, visited, k, d)


def auto_select(measured: list[tuple[str, float, float, float, float]], target: float, w_time: float, w_mem: float, w_build: float) -> str:
    """The cheapest configuration (name, recall, search, bytes, build) that meets the target recall;
    the most accurate one if none does."""
    good = [x for x in measured if x[1] >= target]
    if not good:
        return max(measured, key=lambda x: x[1])[0]
    scale = [min(x[i] for x in good) or 1.0 for i in (2, 3, 4)]
    return heapq.nsmallest(1, good, key=lambda x: w_time * x[2] / scale[0] + w_mem * x[3] / scale[1] + w_build * x[4] / scale[2])[0][0]
