"""The corpus pipeline: toxicity, quality, near-dedup, decontamination, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last
return the columns of ``documents``. ``run`` writes what each stage returns and reads
it back as the next one's input.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.llm import decontaminate, minhash, packing, quality, toxicity
from vecspark.llm.common import Scratch, documents_only, table

THRESHOLD = 0.3
BROADCAST_IDS = 500_000


def without(docs: DataFrame, dropped: DataFrame, keys: list[str], how: str = "left_anti") -> DataFrame:
    """Documents whose keys are not among ``dropped`` (written, distinct), nulls being equal (``left_semi``:
    those whose keys are): a broadcast up to a checked number of rows, a shuffle join beyond it."""
    small = dropped.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    side = (F.broadcast(dropped) if small else dropped).select(*[F.col(k).alias(f"_{k}") for k in keys])
    same = [docs[k].eqNullSafe(side[f"_{k}"]) for k in keys]
    return docs.join(side, same, how)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that score below the threshold. Each row is judged by its own text (null: empty), so repeated rows
    share a verdict and rows that share an id, or have none, do not. Without labels the prior
    alone scores. An empty table stays empty; columns that documents do not have go."""
    docs = documents_only(docs)
    model = toxicity.train(spark, docs, table(spark, sf_dir, "labels"))
    return documents_only(toxicity.score_rows(docs, model).where(F.col("score") < THRESHOLD))


def drop_poor(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that score the threshold or more for quality; the cases are those of ``drop_toxic``."""
    docs = documents_only(docs)
    model = quality.train(spark, docs, table(spark, sf_dir, "labels"))
    return documents_only(quality.score_rows(docs, model).where(F.col("score") >= THRESHOLD))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near duplicates, that with the least id.

    Of rows that share an id, equal ones count as one; one text keeps the id, the others, and rows without
    an id, go by a large hash of id and text, so that rows with ids stay before them. Rows without words are in no group. An empty table stays empty.
    """
    docs, scratch = documents_only(docs), Scratch(spark, "drop-near")
    shared = scratch.keep(docs.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 or doc_id is null").select("doc_id"), "shared")
    keyed = docs.withColumn("row_key", F.col("doc_id"))
    if not shared.isEmpty():
        single = without(docs, shared, ["doc_id"]).withColumn("row_key", F.col("doc_id"))
        key = F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.lit("-")), F.coalesce("text", F.lit("")))
        others = without(docs, shared, ["doc_id"], "left_semi").withColumn("mark", key.bitwiseAND((1 << 62) - 1) + (1 << 62)).dropDuplicates(["mark"])
        first = others.groupBy("doc_id").agg(F.min("mark").alias("mark")).withColumn("row_key", F.col("doc_id"))
        others = others.join(first, ["doc_id", "mark"], "left").withColumn("row_key", F.coalesce("row_key", "mark"))
        keyed = scratch.keep(single.unionByName(others.select(*single.columns)), "keyed")
    seen = minhash.near_duplicates(spark, keyed.select(F.col("row_key").alias("doc_id"), "text"))
    copies = scratch.keep(seen.where("not kept").select(F.col("doc_id").alias("row_key")).distinct(), "copies")
    return documents_only(without(keyed, copies, ["row_key"]))


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows in which no item of the benchmark is found. A row is known by id and text, nulls included, so
    rows that share an id are judged apart. An empty benchmark or table drops nothing."""
    docs = documents_only(docs).withColumn("text_hash", F.xxhash64("text"))
    found = decontaminate.leaks(spark, docs, table(spark, sf_dir, "benchmark"))
    scratch = Scratch(spark, "drop-leaks")
    return documents_only(without(docs, scratch.keep(found.select("doc_id", "text_hash").distinct(), "rows"), ["doc_id", "text_hash"]))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences, as ``packing.pack_documents`` gives them: every row is packed, a null text as its
    end id alone; an empty table gives no rows."""
    return packing.pack_documents(spark, docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("quality_classifier", drop_poor),
    ("minhash_near_dedup", drop_near_duplicates),
    ("benchmark_decontamination", drop_leaks),
    ("packing", pack),
]

# The first stages are trained classifiers, which SQL does not express; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in turn, each on all that its predecessor kept; what a stage leaves in the shared folder
    goes once its result is written and the next one's too."""
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        mark = len(Scratch.opened)
        out = stage(spark, docs, sf_dir)
        scratch = Scratch(spark, "pipeline")
        docs = scratch.keep(out, name)
        Scratch.opened.remove(scratch)
        Scratch.drop_since(mark)
        if before:
            before.drop()
        before = scratch
    return docs
