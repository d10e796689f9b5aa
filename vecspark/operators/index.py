"""Inverted indexes: one quantizer (lists), two half quantizers (cells), trees or hashes as lists."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecspark.operators.codebook import PQModel, train_kmeans, train_pq
from vecspark.operators.encode import code_columns
from vecspark.plans.kernels import map_batches, matrix, nearest, squared


@dataclass
class IvfIndex:
    """K lists; codes of residuals to the list's centroid, or of the vectors themselves."""

    coarse: np.ndarray
    model: PQModel
    residual: bool = True

    @classmethod
    def build(cls, training: DataFrame, k: int, m: int, b: int, iters: int = 3, residual: bool = True) -> IvfIndex:
        coarse = train_kmeans(training, k, iters)
        return cls(coarse, train_pq(residuals(training, coarse) if residual else training, m, b, iters), residual)

    def encode(self, vectors: DataFrame) -> DataFrame:
        """(vec_id, e) -> (vec_id, list_id, codes); map-only."""
        names = code_columns(self.model.m)

        def make():
            def each(batch):
                x = matrix(batch)
                own = nearest(x, self.coarse)
                codes = self.model.encode(x - self.coarse[own] if self.residual else x)
                return {"vec_id": batch["vec_id"], "list_id": own} | {n: codes[:, j] for j, n in enumerate(names)}

            return each

        return map_batches(vectors.select("vec_id", "e"), make, ", ".join(["vec_id long", "list_id long"] + [f"{n} long" for n in names]))

    def tables(self, queries: DataFrame, probes: DataFrame) -> DataFrame:
        """A table row for each (query, probed list): (qid, list_id, t0 .. t{m-1})."""
        if not self.residual:
            return lookup_tables(queries, self.model).join(F.broadcast(probes.select("qid", "list_id")), "qid")
        shifted = probes.select("qid", "list_id").join(queries, "qid")
        return lookup_tables(shifted, self.model, ("qid", "list_id"), shift=self.coarse)


def residuals(vectors: DataFrame, coarse: np.ndarray) -> DataFrame:
    """(vec_id, e - nearest centroid)."""
    kind = dict(vectors.dtypes)["e"].replace("bigint", "long")

    def make():
        def each(batch):
            x = matrix(batch)
            return {"vec_id": batch["vec_id"], "e": x - coarse[nearest(x, coarse)]}

        return each

    return map_batches(vectors.select("vec_id", "e"), make, f"vec_id long, e {kind}")


def lookup_tables(queries: DataFrame, model: PQModel, keys: tuple[str, ...] = ("qid",), shift: np.ndarray | None = None, coarse: bool = False) -> DataFrame:
    """(keys, e) -> (keys, t0 .. t{m-1}); with ``shift``, the centroid of list_id is subtracted first."""
    number = model.number

    def make():
        def each(batch):
            x = matrix(batch)
            if shift is not None:
                x = x - shift[batch["list_id"].to_numpy(zero_copy_only=False)]
            t = model.tables(x, coarse)
            return {k: batch[k] for k in keys} | {f"t{j}": t[:, j] for j in range(model.m)}

        return each

    return map_batches(queries.select(*keys, "e"), make, ", ".join([f"{k} long" for k in keys] + [f"t{j} array<{number}>" for j in range(model.m)]))


def list_distances(queries: DataFrame, coarse: np.ndarray) -> DataFrame:
    """(qid, list_id, dist) for every list."""

    def make():
        def each(batch):
            d = squared(matrix(batch), coarse)
            return {"qid": np.repeat(batch["qid"].to_numpy(zero_copy_only=False), d.shape[1]), "list_id": np.tile(np.arange(d.shape[1]), len(d)), "dist": d.ravel()}

        return each

    number = "long" if np.issubdtype(coarse.dtype, np.integer) else "double"
    return map_batches(queries.select("qid", "e"), make, f"qid long, list_id long, dist {number}")


def probes(queries: DataFrame, coarse: np.ndarray, ma: int = 1) -> DataFrame:
    """The ma nearest lists of each query: (qid, list_id, dist, rk)."""
    w = W.partitionBy("qid").orderBy("dist", "list_id")
    return list_distances(queries, coarse).withColumn("rk", F.row_number().over(w).cast("long")).where(F.col("rk") <= ma)


def probes_by_budget(queries: DataFrame, coarse: np.ndarray, sizes: DataFrame, budget: int) -> DataFrame:
    """Lists in order until they hold ``budget`` codes: (qid, list_id, rk, before)."""
    near = list_distances(queries, coarse).join(F.broadcast(sizes.select("list_id", "n")), "list_id", "left").withColumn("n", F.coalesce("n", F.lit(0)))
    w = W.partitionBy("qid").orderBy("dist", "list_id")
    out = near.withColumn("rk", F.row_number().over(w).cast("long")).withColumn("before", F.coalesce(F.sum("n").over(w.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    return out.where(F.col("before") < budget).select("qid", "list_id", "rk", "before")


def index_step(queries: DataFrame, coarse: np.ndarray, ma: int) -> DataFrame:
    """Probed lists with the query's residual: (qid, list_id, e)."""
    number = dict(queries.dtypes)["e"].replace("bigint", "long")

    def make():
        return lambda batch: {"qid": batch["qid"], "list_id": batch["list_id"], "e": matrix(batch) - coarse[batch["list_id"].to_numpy(zero_copy_only=False)]}

    return map_batches(probes(queries, coarse, ma).select("qid", "list_id").join(queries, "qid"), make, f"qid long, list_id long, e {number}")


@dataclass
class MultiIndex:
    """K^2 cells of a two-part quantizer; cell = first * K + second; codes of residuals."""

    halves: PQModel
    model: PQModel

    @classmethod
    def build(cls, training: DataFrame, k: int, m: int, b: int, iters: int = 3) -> MultiIndex:
        halves = train_pq(training, 2, 0, iters, k)
        number = dict(training.dtypes)["e"].replace("bigint", "long")

        def make():
            def each(batch):
                x = matrix(batch)
                return {"vec_id": batch["vec_id"], "e": x - halves.decode(halves.encode(x))}

            return each

        return cls(halves, train_pq(map_batches(training.select("vec_id", "e"), make, f"vec_id long, e {number}"), m, b, iters))

    @property
    def k(self) -> int:
        return self.halves.k

    def cells(self, vectors: DataFrame) -> DataFrame:
        def make():
            def each(batch):
                own = self.halves.encode(matrix(batch))
                return {"vec_id": batch["vec_id"], "i": own[:, 0], "j": own[:, 1]}

            return each

        return map_batches(vectors.select("vec_id", "e"), make, "vec_id long, i long, j long")

    def encode(self, vectors: DataFrame) -> DataFrame:
        names = code_columns(self.model.m)

        def make():
            def each(batch):
                x = matrix(batch)
                own = self.halves.encode(x)
                codes = self.model.encode(x - self.halves.decode(own))
                return {"vec_id": batch["vec_id"], "list_id": own[:, 0] * self.k + own[:, 1]} | {n: codes[:, j] for j, n in enumerate(names)}

            return each

        return map_batches(vectors.select("vec_id", "e"), make, ", ".join(["vec_id long", "list_id long"] + [f"{n} long" for n in names]))

    def sequence(self, queries: DataFrame, sizes: DataFrame, budget: int) -> DataFrame:
        """Cells by ascending distance until they hold ``budget`` codes: (qid, list_id, dist, rk, before).

        A cell at place L has rank product at most L (every pair that is lower in both
        ranks comes before it), so the halves join under that bound; L doubles until
        the budget is met or no cell is left.
        """
        k = self.k
        tables = lookup_tables(queries, self.halves)
        w = W.partitionBy("qid").orderBy("dist", "idx")
        ranked = [tables.select("qid", F.posexplode(f"t{h}").alias("idx", "dist")).withColumn("rank", F.row_number().over(w)).select("qid", *[F.col(c).alias(f"{c}{h}") for c in ("idx", "dist", "rank")]) for h in (0, 1)]
        n_codes = sizes.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        limit = min(k * k, max(1, int(np.ceil(k * k * budget / max(1, n_codes)))))
        while True:
            pairs = ranked[0].join(ranked[1], "qid").where(F.col("rank0") * F.col("rank1") <= limit).withColumn("list_id", (F.col("idx0") * k + F.col("idx1")).cast("long")).withColumn("dist", F.col("dist0") + F.col("dist1"))
            order = W.partitionBy("qid").orderBy("dist", "rank0", "rank1")
            placed = pairs.withColumn("rk", F.row_number().over(order).cast("long")).where(F.col("rk") <= limit)
            sized = placed.join(F.broadcast(sizes.select("list_id", "n")), "list_id", "left").withColumn("n", F.coalesce("n", F.lit(0)))
            run = W.partitionBy("qid").orderBy("rk").rowsBetween(W.unboundedPreceding, -1)
            out = sized.withColumn("before", F.coalesce(F.sum("n").over(run), F.lit(0)))
            if limit == k * k or out.groupBy("qid").agg(F.sum("n").alias("s")).where(F.col("s") < budget).isEmpty():
                return out.where(F.col("before") < budget).select("qid", "list_id", "dist", "rk", "before")
            limit = min(k * k, 2 * limit)

    def tables(self, queries: DataFrame, visited: DataFrame) -> DataFrame:
        centers = np.stack([np.concatenate([self.halves.books[0][i], self.halves.books[1][j]]) for i in range(self.k) for j in range(self.k)])
        return lookup_tables(visited.select("qid", "list_id").join(queries, "qid"), self.model, ("qid", "list_id"), shift=centers)


def list_sizes(codes: DataFrame) -> DataFrame:
    return codes.groupBy("list_id").agg(F.count("*").alias("n"))


def salted(codes: DataFrame, probed: DataFrame, parts: int) -> tuple[DataFrame, DataFrame]:
    """Lists dealt over ``parts`` sub-lists each, for joins in which a list is hot."""
    return codes.withColumn("sub", F.pmod("vec_id", F.lit(parts))), probed.withColumn("sub", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
