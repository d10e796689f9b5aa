"""What the training-data operators share: tables, scratch storage, Arrow plumbing."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DOCUMENT_COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, read by Spark alone (the path may be in any store Spark knows)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_root(spark: SparkSession) -> str:
    """The shared folder of this session: ``spark.checkpoint.dir``, which a cluster must name; on one
    machine, where executors share its disk, a folder of our own if it is unset."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        root = f"{tempfile.gettempdir()}/checkpoints"
    return f"{root.rstrip('/')}/vecspark-{spark.sparkContext.applicationId}"


class Scratch:
    """Tables written to the shared folder, so that later stages neither recompute nor lose rows."""

    opened: list[Scratch] = []

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.base = f"{scratch_root(spark)}/{label}-{uuid.uuid4().hex[:12]}"
        self.count = 0
        Scratch.opened.append(self)

    def keep(self, frame: DataFrame, name: str) -> DataFrame:
        """Write the rows once and return a frame that reads them."""
        self.count += 1
        path = f"{self.base}/{self.count:02d}-{name}"
        frame.write.option("compression", "zstd").parquet(path)
        return self.spark.read.schema(frame.schema).parquet(path)

    def drop(self, frame: DataFrame | None = None) -> None:
        """Delete the tables (or the one that a frame of ``keep`` reads)."""
        paths = [self.base] if frame is None else [f.rsplit("/", 1)[0] for f in frame.inputFiles()[:1]]
        for text in paths:
            path = self.spark._jvm.org.apache.hadoop.fs.Path(text)
            path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)

    @classmethod
    def drop_since(cls, mark: int) -> None:
        """Delete the tables of all scratches opened after the first ``mark``: nothing reads them any more."""
        for scratch in cls.opened[mark:]:
            scratch.drop()
        del cls.opened[mark:]


def arrow_rows(
    frame: DataFrame,
    make: Callable[[], Callable[[pa.RecordBatch], Iterable[pa.RecordBatch]]],
    schema: str,
) -> DataFrame:
    """``mapInArrow`` whose worker state (models, caches) is built once a task by ``make``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        each = make()
        for batch in batches:
            if batch.num_rows:
                yield from each(batch)

    return frame.mapInArrow(run, schema)


def slices(batch: pa.RecordBatch, rows: int = 512) -> Iterator[pa.RecordBatch]:
    """Parts of a batch, so that what Python holds at once stays small."""
    for at in range(0, batch.num_rows, rows):
        yield batch.slice(at, rows)


def documents_only(frame: DataFrame) -> DataFrame:
    """The columns of ``documents`` in order; extra columns go, missing ones are null."""
    kinds = {"doc_id": "long", "text": "string", "lang": "string", "source": "string", "n_chars": "long"}
    return frame.select(*[(F.col(c) if c in frame.columns else F.lit(None)).cast(kinds[c]).alias(c) for c in DOCUMENT_COLUMNS])


def fold(column: str, parts: int) -> F.Column:
    """crc32 of the id as text, modulo ``parts``."""
    return F.pmod(F.crc32(F.col(column).cast("string")), F.lit(parts))


def bounded_sample(frame: DataFrame, key: str, limit: int) -> DataFrame:
    """At most ``limit`` rows, chosen by a hash of the key, alike on any partitioning. The hash cuts
    to little more than the limit first, so that the last task gets no more than that."""
    mark = F.xxhash64(F.col(key).cast("string"), F.lit("sample"))
    rows = frame.count()
    if rows <= limit:
        return frame
    parts = 1 << 30
    few = frame.where(F.pmod(mark, F.lit(parts)) <= int(parts * min(1.0, (1.2 * limit + 200) / rows)))
    return few.orderBy(F.pmod(mark, F.lit(parts)), mark, F.col(key)).limit(limit)
