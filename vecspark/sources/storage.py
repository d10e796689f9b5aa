"""Indexes on storage: codes laid out by list, models beside them."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.operators.codebook import PQModel


def save_codes(codes: DataFrame, path: str, span: int = 256) -> None:
    """Folders of ``span`` lists each, sorted by list inside, so that row groups hold few lists
    and a probe of some lists reads few of them. Overwrites only the folders written."""
    block = codes.withColumn("list_block", F.floor(F.col("list_id") / span).cast("int"))
    placed = block.repartitionByRange("list_block", "list_id").sortWithinPartitions("list_id", "vec_id")
    placed.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("list_block").parquet(path)


def load_codes(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).drop("list_block")


def probe_codes(spark: SparkSession, path: str, probes: DataFrame, span: int = 256) -> DataFrame:
    """Codes of the probed lists: the join on the folder column prunes folders at run time."""
    wanted = probes.select("qid", "list_id").withColumn("list_block", F.floor(F.col("list_id") / span).cast("int"))
    return spark.read.parquet(path).join(F.broadcast(wanted), ["list_block", "list_id"])


def save_bucketed(codes: DataFrame, name: str, buckets: int = 16) -> None:
    """A table bucketed by list, for repeated joins without a shuffle."""
    codes.write.mode("overwrite").bucketBy(buckets, "list_id").sortBy("list_id", "vec_id").saveAsTable(name)


def model_json(model: PQModel) -> str:
    def as_list(a):
        return None if a is None else np.asarray(a).tolist()

    return json.dumps({"m": model.m, "b": model.b, "d": model.d, "books": as_list(model.books), "rotation": as_list(model.rotation), "coarse": as_list(model.coarse)})


def model_from_json(text: str) -> PQModel:
    x = json.loads(text)
    return PQModel(x["m"], x["b"], x["d"], np.array(x["books"]), None if x["rotation"] is None else np.array(x["rotation"]), None if x["coarse"] is None else np.array(x["coarse"]))


def save_model(spark: SparkSession, model: PQModel, path: str) -> None:
    spark.createDataFrame([(model_json(model),)], "value string").coalesce(1).write.mode("overwrite").text(path)


def load_model(spark: SparkSession, path: str) -> PQModel:
    return model_from_json(spark.read.text(path, wholetext=True).first()["value"])


def export_neighbours(result: DataFrame, path: str, kind: str = "json") -> None:
    """Neighbours as one JSON or CSV line a query."""
    nested = result.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("rk", "vec_id", "dist"))).alias("neighbours"))
    if kind == "json":
        nested.write.mode("overwrite").json(path)
    else:
        result.write.mode("overwrite").option("header", True).csv(path)


def scratch_path(spark: SparkSession) -> str:
    """A folder of this session in the shared folder that the session names; of this machine where all
    executors share its disk."""
    import tempfile

    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        root = f"{tempfile.gettempdir()}/checkpoints"
    return f"{root.rstrip('/')}/vecspark-{spark.sparkContext.applicationId}"


def write_vectors(vectors: DataFrame, path: str, kind: str) -> None:
    """(vec_id, e) in a text or columnar format; CSV, which has no arrays, gets joined numbers."""
    frame = vectors.select("vec_id", "e")
    if kind == "csv":
        frame = frame.select("vec_id", F.array_join(F.transform("e", lambda x: x.cast("string")), " ").alias("e"))
    frame.write.mode("overwrite").format(kind).save(path)


def read_vectors(spark: SparkSession, path: str, kind: str, number: str = "long") -> DataFrame:
    if kind == "csv":
        return spark.read.schema("vec_id long, e string").csv(path).select("vec_id", F.transform(F.split("e", " "), lambda x: x.cast(number)).alias("e"))
    return spark.read.schema(f"vec_id long, e array<{number}>").format(kind).load(path)
