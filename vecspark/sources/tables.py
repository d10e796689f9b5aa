"""The given tables and the vector sets derived from them."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.functions.vectors import SCALE, fixed_point
from vecspark.plans.kernels import column

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vectors_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """V0 in fixed point: (vec_id, e of 64)."""
    return load(spark, sf_dir, "embeddings").select("vec_id", fixed_point(F.col("embedding")).alias("e"))


EVERY = 50  # ids divisible by it are queries


def split(vectors: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(queries (qid, e), base): every fiftieth id asks, all rows are searched."""
    return vectors.where(F.pmod("vec_id", F.lit(EVERY)) == 0).select(F.col("vec_id").alias("qid"), "e"), vectors


def lineitem_components() -> list[tuple[str, str]]:
    """(name, integer expression over a line item) of V1's dimensions; the SQL is common to both engines."""
    return [
        ("quantity", "cast(floor(l_quantity * 100 + 0.5) as bigint)"),
        ("extendedprice", "cast(floor(l_extendedprice * 100 + 0.5) as bigint)"),
        ("discount", "cast(floor(l_discount * 10000 + 0.5) as bigint)"),
        ("tax", "cast(floor(l_tax * 10000 + 0.5) as bigint)"),
        ("ship", "cast(datediff(cast(l_shipdate as date), date '1992-01-01') as bigint)"),
        ("partkey", "l_partkey"),
        ("suppkey", "l_suppkey"),
        ("linenumber", "cast(l_linenumber as bigint)"),
    ]


def vectors_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """V1 in fixed point: (vec_id, e of 8), grouped by (order, line), floor means, min-max scaled to 0..4096."""
    names = [n for n, _ in lineitem_components()]
    items = load(spark, sf_dir, "lineitem").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).cast("long").alias("vec_id"), *[F.expr(x).alias(n) for n, x in lineitem_components()])
    means = items.groupBy("vec_id").agg(*[(F.min(n) if n == "linenumber" else F.floor(F.sum(n).cast("double") / F.count("*")).cast("long")).alias(n) for n in names])
    ends = means.agg(*[F.min(n).alias(f"{n}_low") for n in names], *[F.max(n).alias(f"{n}_high") for n in names])
    scaled = [F.floor(((F.col(n) - F.col(f"{n}_low")) * SCALE).cast("double") / F.greatest(F.col(f"{n}_high") - F.col(f"{n}_low"), F.lit(1))).cast("long") for n in names]
    return means.crossJoin(F.broadcast(ends)).select("vec_id", F.array(*scaled).alias("e"))


GRAM_ROWS = 256  # texts counted at once
LETTERS = 255  # characters whose grams have a table; those of others are looked up one by one


class Grams:
    """Counts of the 3-grams of texts (a shorter text is one gram) by bucket, the first 32 bits of a gram's md5."""

    def __init__(self, d: int):
        self.d, self.letters = d, 0
        self.place = np.zeros(0x110000, np.int32)  # of a character: 0 not met, up to LETTERS, or more
        self.bucket = np.zeros(1 << 24, np.int32)  # of a gram of letters, plus one

    def hashed(self, gram: str) -> int:
        return int.from_bytes(hashlib.md5(gram.encode()).digest()[:4], "big") % self.d

    def _places(self, codes: np.ndarray) -> np.ndarray:
        at = self.place[codes]
        if not at.all():
            for c in np.unique(codes[at == 0]).tolist():
                self.letters += 1
                self.place[c] = min(self.letters, LETTERS + 1)
            at = self.place[codes]
        return at

    def count(self, texts: list[list[str]]) -> np.ndarray:
        """Rows of counts, one for each list of texts."""
        out = np.zeros((len(texts), self.d), np.int64)
        pieces = [(i, t) for i, some in enumerate(texts) for t in some]
        for i, t in pieces:
            if 0 < len(t) < 3:
                out[i, self.hashed(t)] += 1
        pieces = [(i, t) for i, t in pieces if len(t) > 2]
        if not pieces:
            return out
        codes = np.frombuffer("".join(t for _, t in pieces).encode("utf-32-le"), np.uint32).astype(np.int64)
        sizes = np.array([len(t) for _, t in pieces])
        ends, owner = np.cumsum(sizes), np.repeat([i for i, _ in pieces], sizes)
        opens = np.ones(len(codes), bool)
        opens[ends - 1] = opens[ends - 2] = False
        first = np.flatnonzero(opens)
        at = self._places(codes)
        a, b, c = at[first], at[first + 1], at[first + 2]
        wide = np.maximum(np.maximum(a, b), c) > LETTERS
        key = np.where(wide, 0, a << 16 | b << 8 | c)
        new, where = np.unique(key[(self.bucket[key] == 0) & ~wide], return_index=True)
        spots = first[(self.bucket[key] == 0) & ~wide][where]
        for k, s in zip(new.tolist(), spots.tolist(), strict=True):
            self.bucket[k] = 1 + self.hashed("".join(map(chr, codes[s : s + 3].tolist())))
        found = self.bucket[key] - 1
        if wide.any():
            rest = first[wide]
            grams, of = np.unique(codes[rest] << 42 | codes[rest + 1] << 21 | codes[rest + 2], return_inverse=True)
            mask = (1 << 21) - 1
            found[wide] = np.array([self.hashed(chr(g >> 42) + chr(g >> 21 & mask) + chr(g & mask)) for g in grams.tolist()])[of]
        return out + np.bincount(owner[first] * self.d + found, minlength=out.size).reshape(out.shape)


def text_vectors(frame: DataFrame, keys: list[str], text: str, d: int = 128) -> DataFrame:
    """Character 3-gram counts in md5 buckets, scaled to a length of about 4096: (keys, e).

    Texts of a key are shuffled whole; a task counts their grams itself, with a table of the buckets it has met.
    """
    held = frame.where(F.length(text) > 0).groupBy(*keys).agg(F.collect_list(text).alias("texts"))

    def run(batches):
        counter = Grams(d)
        for batch in batches:
            for at in range(0, batch.num_rows, GRAM_ROWS):
                part = batch.slice(at, GRAM_ROWS)
                n = counter.count(part.column("texts").to_pylist())
                norm = np.floor(np.sqrt((n * n).sum(axis=1).astype(float)))
                e = np.floor((n * SCALE).astype(float) / np.maximum(norm, 1)[:, None]).astype(np.int64)
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in keys), column(e, pa.list_(pa.int64()))], names=[*keys, "e"])

    kinds = dict(held.dtypes)
    return held.mapInArrow(run, ", ".join([f"{k} {kinds[k]}" for k in keys] + ["e array<long>"]))


def vectors_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """V2: (vec_id = doc_id, e of 128)."""
    return text_vectors(load(spark, sf_dir, "documents").select(F.col("doc_id").alias("vec_id"), "text"), ["vec_id"], "text")


def descriptors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """V3: one vector for each non-empty line of a document: (doc_id, pos, e of 128)."""
    lines = load(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("pos", "line")).where("line <> ''")
    return text_vectors(lines, ["doc_id", "pos"], "line")


EVENT_TYPES_SQL = "select distinct event_type from events"


def profiles_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """V4 in long form: (user_id, event_type, hour, n)."""
    return load(spark, sf_dir, "events").groupBy("user_id", "event_type", F.hour("ts").cast("long").alias("hour")).agg(F.count("*").alias("n"))


def profiles_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """V5 in long form: (custkey, brand, type, spend), spend in whole units of each line."""
    items = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", F.floor("l_extendedprice").cast("long").alias("spend"))
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    part = load(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type")
    joined = items.join(part, items.l_partkey == part.p_partkey).join(orders, items.l_orderkey == orders.o_orderkey)
    return joined.groupBy(F.col("o_custkey").alias("custkey"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type")).agg(F.sum("spend").alias("spend"))
