"""Locality-sensitive hashing: projections as columns, buckets as equi-joins."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecspark.functions.bits import interleave
from vecspark.functions.ranking import global_rank, top_k
from vecspark.functions.vectors import l2sq, total
from vecspark.plans.kernels import map_batches, matrix

SCALE = 4096


def normals(count: int, d: int, seed: int = 42) -> list[list[int]]:
    """Seeded normal vectors in fixed point."""
    return np.rint(np.random.default_rng(seed).normal(size=(count, d)) * SCALE).astype(int).tolist()


def offsets(count: int, w: int, seed: int = 43) -> list[int]:
    return np.random.default_rng(seed).integers(0, w * SCALE, count).tolist()


def hash_columns(d: int, count: int, w: int, seed: int = 42) -> list[Column]:
    """floor((a.v + b) / w) for each of ``count`` functions; w in the vectors' units."""
    out = []
    for a, b in zip(normals(count, d, seed), offsets(count, w, seed + 1), strict=True):
        projected = total([F.col("e")[i] * a[i] for i in range(d)]) + b
        out.append(F.floor(projected.cast("double") / float(w * SCALE)).cast("long"))
    return out


def hashed(vectors: DataFrame, key: str, d: int, count: int, w: int, seed: int = 42) -> DataFrame:
    """(key, e, h0 .. h{count-1}) of fixed-point vectors; one matrix product for each Arrow batch
    (its sums stay below 2^53, so they equal ``hash_columns``)."""
    a, b = np.array(normals(count, d, seed), float), np.array(offsets(count, w, seed + 1), float)

    def make():
        def each(batch):
            h = np.floor((matrix(batch) @ a.T + b) / float(w * SCALE)).astype(np.int64)
            return {key: batch[key], "e": batch["e"]} | {f"h{i}": h[:, i] for i in range(count)}

        return each

    return map_batches(vectors.select(key, "e"), make, f"{key} long, e array<long>, " + ", ".join(f"h{i} long" for i in range(count)))


def compound(m: int, tables: int) -> Column:
    """Rows (tbl, key) of an entity with m * tables hashes: the key joins m of them."""
    return F.explode(F.array(*[F.struct(F.lit(t).cast("long").alias("tbl"), F.concat_ws(",", *[F.col(f"h{t * m + i}") for i in range(m)]).alias("key")) for t in range(tables)]))


def e2lsh_tables(vectors: DataFrame, key: str, d: int, m: int, tables: int, w: int, seed: int = 42) -> DataFrame:
    """(key, tbl, key string), one row for each table."""
    return hashed(vectors, key, d, m * tables, w, seed).select(key, compound(m, tables).alias("x")).select(key, "x.tbl", "x.key")


def e2lsh_candidates(base: DataFrame, queries: DataFrame) -> DataFrame:
    """Entities that share a table's key with a query: (qid, tbl, vec_id)."""
    return base.join(F.broadcast(queries), ["tbl", "key"]).select("qid", "tbl", "vec_id")


def exact_distances(pairs: DataFrame, vectors: DataFrame, queries: DataFrame, d: int) -> DataFrame:
    joined = pairs.join(vectors.select("vec_id", "e"), "vec_id").join(F.broadcast(queries.select("qid", F.col("e").alias("q"))), "qid")
    return joined.select("qid", "vec_id", l2sq(F.col("q"), F.col("e"), d).alias("dist"))


def near_within(candidates: DataFrame, vectors: DataFrame, queries: DataFrame, d: int, tables: int, radius_sq: int) -> DataFrame:
    """The (R, c) answer: of the first 3 * tables candidates in (table, id) order, the nearest within the radius."""
    few = top_k(candidates, 3 * tables, ["qid"], ["tbl", "vec_id"]).select("qid", "vec_id").distinct()
    return top_k(exact_distances(few, vectors, queries, d).where(F.col("dist") <= radius_sq), 1, ["qid"], ["dist", "vec_id"])


def z_values(vectors: DataFrame, key: str, d: int, m: int, w: int, bits: int, seed: int) -> DataFrame:
    """(key, z): hashes clipped to ``bits`` and interleaved."""
    half = 1 << (bits - 1)
    h = hashed(vectors, key, d, m, w, seed)
    clipped = [F.greatest(F.least(F.col(f"h{i}") + half, F.lit((1 << bits) - 1)), F.lit(0)) for i in range(m)]
    return h.select(key, interleave(clipped, bits).alias("z"))


def common_prefix(a: Column, b: Column, width: int) -> Column:
    """Length of the common prefix of two bit strings."""
    x = a.bitwiseXOR(b)
    return F.lit(width) - F.when(x == 0, F.lit(0)).otherwise(F.length(F.bin(x)))


def lsb_candidates(base: DataFrame, queries: DataFrame, width: int, budget: int) -> DataFrame:
    """(qid, vec_id): entries by longest common prefix with the query, a budget for each tree.

    The prefix shortens as one walks away from a query in Z-order, so the ``budget`` neighbours on
    either side tell the length that the last of the budget has; entries with that prefix are
    fetched by an equi-join on (length, prefix) and ranked.
    """
    base, queries = base.persist(), queries.persist()
    near = sk_candidates(base.withColumnRenamed("z", "k"), queries.withColumnRenamed("z", "k"), budget)
    keyed = near.join(base, "vec_id").join(F.broadcast(queries.withColumnRenamed("z", "zq")), "qid")
    lengths = top_k(keyed.withColumn("llcp", common_prefix(F.col("z"), F.col("zq"), width)), budget, ["qid"], [F.col("llcp").desc(), F.col("vec_id")]).groupBy("qid").agg(F.min("llcp").alias("length"))

    def prefix(z: str) -> Column:
        return F.expr(f"shiftright({z}, cast({width} - length as int))")

    wanted = lengths.join(queries.withColumnRenamed("z", "zq"), "qid").withColumn("prefix", prefix("zq"))
    present = [r["length"] for r in lengths.select("length").distinct().collect()]  # at most width + 1
    entries = base.withColumn("length", F.explode(F.array(*[F.lit(x) for x in present or [0]]))).withColumn("prefix", prefix("z"))
    pairs = entries.join(F.broadcast(wanted), ["length", "prefix"]).select("qid", "vec_id", common_prefix(F.col("z"), F.col("zq"), width).alias("llcp"))
    return top_k(pairs, budget, ["qid"], [F.col("llcp").desc(), F.col("vec_id")]).select("qid", "vec_id")


def c2lsh_counts(base: DataFrame, queries: DataFrame, count: int, radius: int) -> DataFrame:
    """(qid, vec_id, n): functions in which both fall in one bucket of that radius."""
    def long(frame, key):
        return frame.select(key, F.explode(F.array(*[F.struct(F.lit(i).alias("f"), F.floor(F.col(f"h{i}") / radius).cast("long").alias("bucket")) for i in range(count)])).alias("x")).select(key, "x.f", "x.bucket")

    return long(base, "vec_id").join(F.broadcast(long(queries, "qid")), ["f", "bucket"]).groupBy("qid", "vec_id").agg(F.count("*").alias("n"))


def c2lsh_search(base: DataFrame, queries: DataFrame, vectors: DataFrame, asked: DataFrame, count: int, radii: tuple[int, ...], least: int, k: int, d: int) -> DataFrame:
    """(qid, rk, vec_id, dist, radius): the k nearest of the entries that collide in ``least`` functions at
    the first radius at which k of them do (the last radius with any otherwise)."""
    found = None
    for radius in radii:
        hits = c2lsh_counts(base, queries, count, radius).where((F.col("n") >= least) & (F.col("qid") != F.col("vec_id"))).withColumn("radius", F.lit(radius).cast("long"))
        found = hits if found is None else found.unionByName(hits)
    many = found.groupBy("qid", "radius").agg(F.count("*").alias("many"))
    pick = many.groupBy("qid").agg(F.coalesce(F.min(F.when(F.col("many") >= k, F.col("radius"))), F.max("radius")).alias("radius"))
    chosen = found.join(F.broadcast(pick), ["qid", "radius"]).select("qid", "vec_id", "radius")  # a row for each query
    near = exact_distances(chosen, vectors, asked, d).join(F.broadcast(pick), "qid")
    return top_k(near, k, ["qid"], ["dist", "vec_id"]).select("qid", "rk", "vec_id", "dist", "radius")


def sk_keys(vectors: DataFrame, key: str, d: int, m: int, w: int, seed: int) -> DataFrame:
    """(key, k): m hashes as one number in their lexicographic order."""
    h = hashed(vectors, key, d, m, w, seed)
    return h.select(key, total([(F.col(f"h{i}") + 512) * (1024 ** (m - 1 - i)) for i in range(m)]).alias("k"))


def sk_candidates(base: DataFrame, queries: DataFrame, budget: int) -> DataFrame:
    """(qid, vec_id): entries within ``budget`` places of the query's place in the linear order.

    Base and queries are ranked together (a query before the entries of its own key); a query then
    names the places that it looks at, and an equi-join on places fetches them.
    """
    base, queries = base.persist(), queries.persist()  # two narrow columns, read by each ranking
    both = base.select("vec_id", F.lit(1).alias("_kind"), "k").unionByName(queries.select(F.col("qid").alias("vec_id"), F.lit(0).alias("_kind"), "k"))
    ranked = global_rank(both, "k", "_at", ("_kind", "vec_id"))
    asked = ranked.where("_kind = 0").select(F.col("vec_id").alias("qid"), "_at")
    # A query's place among the entries alone: its place less the queries before it.
    spots = asked.withColumn("_at", F.col("_at") - (F.row_number().over(W.orderBy("_at")) - 1))
    places = spots.select("qid", F.explode(F.sequence(F.col("_at") - budget, F.col("_at") + budget - 1)).alias("_at"))
    entries = global_rank(base, "k", "_at", ("vec_id",)).select("vec_id", "_at")
    return entries.join(F.broadcast(places), "_at").select("qid", "vec_id")
