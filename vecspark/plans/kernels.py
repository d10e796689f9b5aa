"""NumPy kernels behind ``mapInArrow``; integers below 2^53 stay exact in float64."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

ARROW = {"long": pa.int64(), "double": pa.float64(), "int": pa.int32(), "array<long>": pa.list_(pa.int64()), "array<double>": pa.list_(pa.float64()), "binary": pa.binary(), "string": pa.string()}


def arrow_schema(fields: str) -> pa.Schema:
    return pa.schema([(n, ARROW[t]) for n, t in (f.rsplit(" ", 1) for f in fields.split(", "))])


def map_batches(frame: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], dict]], fields: str) -> DataFrame:
    """Batches to dicts of columns; ``make`` builds a task's state once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        each, schema = make(), arrow_schema(fields)
        for batch in batches:
            if batch.num_rows:
                got = each(batch)
                yield pa.RecordBatch.from_arrays([column(got[f.name], f.type) for f in schema], schema=schema)

    return frame.mapInArrow(run, fields)


def column(values, kind: pa.DataType) -> pa.Array:
    if isinstance(values, pa.Array | pa.ChunkedArray):
        return values.cast(kind)
    if isinstance(values, np.ndarray) and values.ndim == 2:
        flat = pa.array(np.ascontiguousarray(values).ravel()).cast(kind.value_type)
        return pa.ListArray.from_arrays(pa.array(np.arange(0, values.size + 1, max(1, values.shape[1]), dtype=np.int32)[: len(values) + 1]), flat)
    return pa.array(values).cast(kind) if len(values) else pa.array([], kind)


def matrix(batch: pa.RecordBatch, name: str = "e") -> np.ndarray:
    """Rows of an array column of equal lengths, as float64."""
    return batch[name].flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(batch.num_rows, -1)


def squared(x: np.ndarray, centroids: np.ndarray) -> np.ndarray:
    """All squared distances, n x k."""
    c = centroids.astype(np.float64)
    return (x * x).sum(axis=1)[:, None] - 2 * (x @ c.T) + (c * c).sum(axis=1)


def nearest(x: np.ndarray, centroids: np.ndarray) -> np.ndarray:
    """Index of the nearest centroid of each row, the least index on ties; in tiles of at most 32 MB."""
    tile = max(16, (1 << 22) // max(1, len(centroids)))
    return np.concatenate([squared(x[i : i + tile], centroids).argmin(axis=1) for i in range(0, len(x), tile)]) if len(x) else np.zeros(0, np.int64)


def least_rows(distance: np.ndarray, ids: np.ndarray, r: int) -> np.ndarray:
    """Positions of the r least by (distance, id). A sample's quantile cuts first; only if it cuts too
    deep are all distances partitioned."""
    n = len(distance)
    if n > 32 * r and n >= 8192:
        step = n // 4096
        some = distance[::step]
        at = min(len(some) - 1, 2 * r // step + 8)
        near = np.flatnonzero(distance <= np.partition(some, at)[at])
        if r <= len(near) < n:
            return near[least_rows(distance[near], ids[near], r)]
    if n > 4 * r:
        bound = np.partition(distance, r - 1)[r - 1]
        kept = np.flatnonzero(distance <= bound)
        return kept[np.lexsort((ids[kept], distance[kept]))[:r]]
    return np.lexsort((ids, distance))[:r]


def joined(out: dict[str, list]) -> dict[str, np.ndarray]:
    """Columns gathered piece by piece; empty where there was no piece."""
    return {k: np.concatenate(v) if v else np.zeros(0, np.int64) for k, v in out.items()}
