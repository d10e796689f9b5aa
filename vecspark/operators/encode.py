"""Vectors to codes and back; codes are one column for each part."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.functions.bits import group_id, high_nibble, low_nibble
from vecspark.operators.codebook import PQModel
from vecspark.plans.kernels import map_batches, matrix, nearest


def code_columns(m: int) -> list[str]:
    return [f"c{j}" for j in range(m)]


def assign(vectors: DataFrame, centroids: np.ndarray, key: str = "vec_id", name: str = "idx") -> DataFrame:
    """(key, e, ...) -> the same with the index of the nearest centroid; map-only."""

    def make():
        return lambda batch: {key: batch[key], "e": batch["e"], name: nearest(matrix(batch), centroids)}

    kind = dict(vectors.dtypes)["e"].replace("bigint", "long")
    return map_batches(vectors.select(key, "e"), make, f"{key} long, e {kind}, {name} long")


def encode_pq(vectors: DataFrame, model: PQModel, keys: tuple[str, ...] = ("vec_id",)) -> DataFrame:
    """(keys, e) -> (keys, c0 .. c{m-1}); map-only."""
    names = code_columns(model.m)

    def make():
        def each(batch):
            codes = model.encode(matrix(batch))
            return {k: batch[k] for k in keys} | {n: codes[:, j] for j, n in enumerate(names)}

        return each

    return map_batches(vectors.select(*keys, "e"), make, ", ".join([f"{k} long" for k in keys] + [f"{n} long" for n in names]))


def decode_pq(codes: DataFrame, model: PQModel, keys: tuple[str, ...] = ("vec_id",)) -> DataFrame:
    """(keys, codes) -> (keys, e), the reconstruction; map-only."""
    names = code_columns(model.m)

    def make():
        def each(batch):
            x = model.decode(np.stack([batch[n].to_numpy(zero_copy_only=False) for n in names], axis=1))
            return {k: batch[k] for k in keys} | {"e": x}

        return each

    return map_batches(codes.select(*keys, *names), make, ", ".join([f"{k} long" for k in keys] + [f"e array<{model.number}>"]))


def group_codes(codes: DataFrame, g: int, low_bits: int = 4) -> DataFrame:
    """Adds ``grp``, the tuple of the first g codes' high parts."""
    return codes.withColumn("grp", group_id([F.col(c) for c in code_columns(g)], low_bits))


def group_layout(codes: DataFrame, g: int, low_bits: int = 4) -> DataFrame:
    """The storage layout: range-partitioned and sorted by group, so that row groups hold few groups."""
    return group_codes(codes, g, low_bits).repartitionByRange("grp").sortWithinPartitions("grp", "vec_id")


def max_group_components(n: int, portions: int = 16, least: int = 50) -> int:
    """The greatest g such that n codes give groups of ``least`` codes on average."""
    g = 0
    while n >= least * portions ** (g + 1):
        g += 1
    return g


def compact_codes(codes: DataFrame, m: int, g: int) -> DataFrame:
    """Shared high nibbles dropped: ``grp``, g low nibbles packed, the other codes."""
    out = group_codes(codes, g)
    low = [low_nibble(F.col(f"c{j}")) for j in range(g)]
    packed = sum((F.shiftleft(x, 4 * j) for j, x in enumerate(low[1:], 1)), low[0])
    return out.select("vec_id", "grp", packed.alias("lows"), *[f"c{j}" for j in range(g, m)])


def expand_codes(compact: DataFrame, m: int, g: int) -> DataFrame:
    """Inverse of ``compact_codes``."""
    high = [F.shiftright("grp", 4 * (g - 1 - j)).bitwiseAND(15) for j in range(g)]
    low = [F.shiftright("lows", 4 * j).bitwiseAND(15) for j in range(g)]
    return compact.select("vec_id", *[(h * 16 + lo).alias(f"c{j}") for j, (h, lo) in enumerate(zip(high, low, strict=True))], *[f"c{j}" for j in range(g, m)])


def pack_nibble_codes(codes: DataFrame, m: int) -> DataFrame:
    """Two four-bit codes in a byte: b0 .. b{m/2-1}; the first code is the low nibble."""
    return codes.select("vec_id", *[(F.col(f"c{2 * j + 1}") * 16 + F.col(f"c{2 * j}")).alias(f"b{j}") for j in range(m // 2)])


def unpack_nibble_codes(packed: DataFrame, m: int) -> DataFrame:
    return packed.select("vec_id", *[(low_nibble(F.col(f"b{j // 2}")) if j % 2 == 0 else high_nibble(F.col(f"b{j // 2}"))).alias(f"c{j}") for j in range(m)])


def pack_blocks(codes: DataFrame, m: int, size: int = 16) -> DataFrame:
    """Transposed blocks: for each run of ``size`` codes in id order, a row of each component's values."""
    from vecspark.functions.ranking import global_rank

    placed = global_rank(codes, "vec_id", "pos").withColumn("block", F.floor(F.col("pos") / size).cast("long"))
    ordered = F.array_sort(F.collect_list(F.struct("pos", *code_columns(m))))
    grouped = placed.groupBy("block").agg(ordered.alias("rows"))
    return grouped.select("block", F.explode(F.array(*[F.struct(F.lit(j).cast("long").alias("part"), F.col(f"rows.c{j}").alias("row")) for j in range(m)])).alias("x")).select("block", "x.part", "x.row")
