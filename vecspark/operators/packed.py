"""Scans of packed codes: the main path.

A code is one BINARY value (``code``), its parts in order, two to a byte where they have four
bits. What is broadcast are the queries themselves, under a checked size, and the model; a task
makes the tables of a query when it scans a block of codes, keeps the best r of each query
over all its blocks and emits them once, at its end.

Parts are looked up by words: as many parts as fit in 16 bits share one table, the sums of their
tables, so an 8x8 code takes four look-ups and a 16x4 code too.

Results are (qid, rk, vec_id, dist), ties by vec_id, equal to those of the declarative forms in
``scan``.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.functions.ranking import prefix_ends, top_k
from vecspark.operators.codebook import PQModel
from vecspark.operators.encode import code_columns
from vecspark.plans.kernels import ARROW, column, least_rows, matrix

BROADCAST_BYTES = 256 << 20
BLOCK_ROWS = 1 << 18
SHORT_BITS = 12  # words whose tables are made for each query and block
HEAD_ROWS = 1 << 10  # codes of a prefix for each task
WORD_BITS = 16


# -- codes as bytes ----------------------------------------------------------------------------


def code_bytes(m: int, b: int) -> int:
    return -(-m // 2) if b <= 4 else m if b <= 8 else 2 * m


def to_bytes(codes: np.ndarray, b: int) -> np.ndarray:
    """n x m parts as n x bytes."""
    if b <= 4:
        whole = np.pad(codes, ((0, 0), (0, codes.shape[1] % 2))).astype(np.uint8)
        return whole[:, ::2] | whole[:, 1::2] << 4
    return codes.astype(np.uint8) if b <= 8 else np.ascontiguousarray(codes.astype("<u2")).view(np.uint8).reshape(len(codes), -1)


def from_bytes(raw: np.ndarray, m: int, b: int) -> np.ndarray:
    if b <= 4:
        out = np.empty((len(raw), 2 * raw.shape[1]), np.uint8)
        out[:, ::2], out[:, 1::2] = raw & 15, raw >> 4
        return out[:, :m]
    return raw if b <= 8 else np.ascontiguousarray(raw).view("<u2")


def binary_array(raw: np.ndarray) -> pa.Array:
    n, width = raw.shape
    offsets = np.arange(0, (n + 1) * width, width, dtype=np.int32) if width else np.zeros(n + 1, np.int32)
    return pa.BinaryArray.from_buffers(pa.binary(), n, [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(raw))])


def raw_codes(batch: pa.RecordBatch, width: int, name: str = "code") -> np.ndarray:
    """The bytes of a column of codes of one width, without a copy."""
    col = batch[name]
    first = np.frombuffer(col.buffers()[1], np.int32)[col.offset]
    return np.frombuffer(col.buffers()[2], np.uint8)[first : first + len(col) * width].reshape(len(col), width)


def encode_packed(vectors: DataFrame, model: PQModel, coarse: np.ndarray | None = None, residual: bool = True) -> DataFrame:
    """(vec_id, e) -> (vec_id, code), or (vec_id, list_id, code) with the centroids of lists; map-only."""
    from vecspark.plans.kernels import nearest

    listed = coarse is not None
    schema = pa.schema([("vec_id", pa.int64()), *([("list_id", pa.int64())] if listed else []), ("code", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                x, extra = matrix(batch), []
                if listed:
                    own = nearest(x, coarse)
                    extra, x = [pa.array(own)], x - coarse[own] if residual else x
                yield pa.RecordBatch.from_arrays([batch["vec_id"], *extra, binary_array(to_bytes(model.encode(x), model.b))], schema=schema)

    return vectors.select("vec_id", "e").mapInArrow(run, "vec_id long, " + ("list_id long, " if listed else "") + "code binary")


def pack(codes: DataFrame, m: int, b: int, keys: tuple[str, ...] = ("vec_id",)) -> DataFrame:
    """(keys, c0 ..) -> (keys, code)."""
    names = code_columns(m)
    schema = pa.schema([*[(k, pa.int64()) for k in keys], ("code", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                c = np.stack([batch[n].to_numpy(zero_copy_only=False) for n in names], axis=1)
                yield pa.RecordBatch.from_arrays([*[batch[k].cast(pa.int64()) for k in keys], binary_array(to_bytes(c, b))], schema=schema)

    return codes.select(*keys, *names).mapInArrow(run, ", ".join([f"{k} long" for k in keys] + ["code binary"]))


def unpack(codes: DataFrame, m: int, b: int, keys: tuple[str, ...] = ("vec_id",)) -> DataFrame:
    """Inverse of ``pack``; parts are smallints."""
    width, names = code_bytes(m, b), code_columns(m)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                c = from_bytes(raw_codes(batch, width), m, b).astype(np.int32)
                yield pa.RecordBatch.from_arrays([*[batch[k] for k in keys], *[pa.array(c[:, j]) for j in range(m)]], names=[*keys, *names])

    return codes.select(*keys, "code").mapInArrow(run, ", ".join([f"{k} long" for k in keys] + [f"{n} int" for n in names]))


def remap(codes: DataFrame, maps: np.ndarray) -> DataFrame:
    """Eight-bit codes under another numbering (``codebook.renumber``'s maps). Unlike encoding anew, ties between
    centroids stay as they were broken, so distances do too."""
    m = len(maps)
    tables = maps.astype(np.uint8)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                raw = raw_codes(batch, m)
                new = np.stack([tables[j].take(raw[:, j]) for j in range(m)], axis=1)
                yield pa.RecordBatch.from_arrays([batch["vec_id"], binary_array(new)], names=["vec_id", "code"])

    return codes.select("vec_id", "code").mapInArrow(run, "vec_id long, code binary")


def tasks_for(codes: DataFrame, rows: int) -> int:
    """As few tasks as keep all cores busy and hold no more than a block each: every task makes every query's tables."""
    return max(1, min(codes.sparkSession.sparkContext.defaultParallelism, -(-rows // HEAD_ROWS)), -(-rows // BLOCK_ROWS))


def dealt(codes: DataFrame) -> DataFrame:
    """Stored codes, read by ``tasks_for`` tasks; shuffles leave one task for each of their partitions, however few rows it has."""
    return codes.coalesce(tasks_for(codes, codes.count()))


def by_list(codes: DataFrame) -> DataFrame:
    """Codes of lists laid out by list, a large list over several tasks: a query's tables are made by the few that hold its lists."""
    return codes.repartitionByRange(tasks_for(codes, codes.count()), "list_id", "vec_id").sortWithinPartitions("list_id", "vec_id")


# -- queries -----------------------------------------------------------------------------------


@dataclass
class Batch:
    """Queries of a checked size, and the lists that each looks at (None: all codes)."""

    ids: np.ndarray
    x: np.ndarray
    probes: list[np.ndarray] | None = None  # list ids of each query
    centers: np.ndarray | None = None  # subtracted from a query before its tables are made

    def tables(self, model: PQModel, i: int, lst: int | None) -> np.ndarray:
        """Tables of a query (less a list's centre): made for a run of queries, or for all lists of one, at once."""
        listed = lst is not None and self.centers is not None
        key = (id(model), i if listed else i // CHUNK, listed)
        if getattr(self, "_key", None) != key:
            if listed:
                x, self._row = self.x[i : i + 1] - self.centers[self.probes[i]], {int(p): n for n, p in enumerate(self.probes[i])}
            else:
                x = self.x[i // CHUNK * CHUNK : (i // CHUNK + 1) * CHUNK]
            t = model.tables(x)
            self._key, self._made = key, np.rint(t).astype(np.int64) if model.number == "long" else t
        return self._made[self._row[lst] if listed else i % CHUNK]

    def run(self, model: PQModel, first: int) -> np.ndarray:
        """Tables of the run of queries that starts at ``first``, a multiple of CHUNK."""
        self.tables(model, first, None)
        return self._made


CHUNK = 64  # queries whose tables are made at once


def batches_of(queries: DataFrame, probes: DataFrame | None = None, centers: np.ndarray | None = None, limit: int = BROADCAST_BYTES) -> Iterator[Batch]:
    """The queries in batches that may be broadcast: (qid, e), and (qid, list_id) if lists are probed."""
    looked: dict[int, list[int]] | None = None
    ids, rows, size = [], [], 0
    if probes is not None:
        looked = {}
        for r in probes.select("qid", "list_id").toLocalIterator():
            looked.setdefault(r["qid"], []).append(r["list_id"])

    def made() -> Batch:
        own = None if looked is None else [np.array(sorted(looked.get(q, ())), np.int64) for q in ids]
        return Batch(np.array(ids, np.int64), np.array(rows, float).reshape(len(rows), -1), own, centers)

    for r in queries.select("qid", "e").orderBy("qid").toLocalIterator():
        ids.append(r["qid"])
        rows.append(r["e"])
        size += 8 * len(r["e"]) + 8 * (len(looked.get(r["qid"], ())) if looked else 0)
        if size >= limit:
            yield made()
            ids, rows, size = [], [], 0
    if ids:
        yield made()


# -- words -------------------------------------------------------------------------------------


def words_of(codes: np.ndarray, b: int) -> np.ndarray:
    """n x m parts as words of up to 16 bits, a row for each word, ready for ``take``."""
    per, m = max(1, WORD_BITS // b), codes.shape[1]
    out = np.empty((-(-m // per), len(codes)), np.intp)
    for w in range(len(out)):
        out[w] = codes[:, w * per]
        for i in range(1, min(per, m - w * per)):
            out[w] |= codes[:, w * per + i].astype(np.intp) << b * i
    return out


def word_tables(t: np.ndarray, b: int) -> list[np.ndarray]:
    """Tables of m parts (m x k) as tables of words."""
    per, out = max(1, WORD_BITS // b), []
    size = 1 << b
    if t.shape[1] < size:
        t = np.pad(t, ((0, 0), (0, size - t.shape[1])))
    for w in range(0, len(t), per):
        whole = t[w]
        for part in t[w + 1 : w + per]:
            whole = (part[:, None] + whole[None, :]).ravel()
        out.append(whole)
    return out


def saturated_words(bins: np.ndarray, b: int, top: int) -> list[np.ndarray]:
    """Tables of words of bins 0 .. top (127 at most), sums saturating at ``top``: a byte an entry."""
    per, out, bins = max(1, WORD_BITS // b), [], bins.astype(np.uint8)
    if bins.shape[1] < 1 << b:
        bins = np.pad(bins, ((0, 0), (0, (1 << b) - bins.shape[1])))
    for w in range(0, len(bins), per):
        whole = bins[w]
        for part in bins[w + 1 : w + per]:
            whole = np.minimum(part[:, None] + whole[None, :], top).ravel()
        out.append(whole)
    return out


def narrow(t: np.ndarray) -> np.ndarray:
    """Integer tables in four bytes where all sums fit."""
    if not np.issubdtype(t.dtype, np.integer):
        return t
    return t.astype(np.int32 if int(t.max(axis=1).sum()) < 2**31 else np.int64)


def summed(tables: list[np.ndarray], words: np.ndarray, rows: np.ndarray | None = None) -> np.ndarray:
    pick = words if rows is None else words[:, rows]
    out = tables[0].take(pick[0])
    for t, w in zip(tables[1:], pick[1:], strict=True):
        out += t.take(w)
    return out


class Best:
    """The r least (distance, id) seen, and the distance from which nothing counts any more."""

    def __init__(self, r: int, top=None):
        self.r, self.top = r, top
        self.d, self.ids = np.zeros(0), np.zeros(0, np.int64)

    def add(self, d: np.ndarray, ids: np.ndarray) -> None:
        if not len(d):
            return
        if len(self.d):
            d, ids = np.concatenate([self.d, d]), np.concatenate([self.ids, ids])
        kept = least_rows(d, ids, self.r)
        self.d, self.ids = d[kept], ids[kept]
        if self.d.dtype == np.uint8:  # saturated sums
            self.d = self.d.astype(np.int64)
        if len(kept) == self.r:
            last = self.d[-1]
            self.top = last if self.top is None else min(self.top, last)

    def offer(self, d: np.ndarray, ids: np.ndarray) -> None:
        if self.top is not None:
            near = np.flatnonzero(d <= self.top)
            d, ids = d[near], ids[near]
        self.add(d, ids)


# -- blocks ------------------------------------------------------------------------------------


class Block:
    """Codes of a task, gathered from Arrow batches."""

    def __init__(self, parts: list[pa.RecordBatch], m: int, b: int):
        self.n = sum(p.num_rows for p in parts)
        width = code_bytes(m, b)
        self.ids = np.concatenate([p["vec_id"].to_numpy(zero_copy_only=False) for p in parts])
        self.raw = np.concatenate([raw_codes(p, width) for p in parts])
        self.m, self.b = m, b
        self._words: np.ndarray | None = None
        self.runs: dict[int, tuple[int, int]] | None = None
        if "list_id" in parts[0].schema.names:
            lists = np.concatenate([p["list_id"].to_numpy(zero_copy_only=False) for p in parts])
            order = np.argsort(lists, kind="stable")
            if (order[1:] < order[:-1]).any():
                lists, self.ids, self.raw = lists[order], self.ids[order], self.raw[order]
            first = np.flatnonzero(np.concatenate(([True], lists[1:] != lists[:-1])))
            self.runs = {int(lists[a]): (int(a), int(z)) for a, z in zip(first, np.append(first[1:], self.n), strict=True)}

    @property
    def codes(self) -> np.ndarray:
        return from_bytes(self.raw, self.m, self.b)

    @property
    def words(self) -> np.ndarray:
        if self._words is None:
            self._words = words_of(self.codes, self.b)
        return self._words


def blocks(batches: Iterator[pa.RecordBatch], m: int, b: int, rows: int = BLOCK_ROWS) -> Iterator[Block]:
    held, n = [], 0
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            n += batch.num_rows
            if n >= rows:
                yield Block(held, m, b)
                held, n = [], 0
    if held:
        yield Block(held, m, b)


def emitted(best: dict[int, Best], ids: np.ndarray, schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """The kept rows of all queries, some queries to a batch."""
    held: list[tuple] = []
    for i, b in best.items():
        if len(b.d):
            held.append((np.full(len(b.d), ids[i]), b.ids, b.d))
        if sum(len(x[0]) for x in held) > 100_000:
            yield pa.RecordBatch.from_arrays([column(np.concatenate(c), f.type) for c, f in zip(zip(*held, strict=True), schema, strict=True)], schema=schema)
            held = []
    if held:
        yield pa.RecordBatch.from_arrays([column(np.concatenate(c), f.type) for c, f in zip(zip(*held, strict=True), schema, strict=True)], schema=schema)


ScanBlock = Callable[[Block, int, int, Batch, Best], None]


def scan_blocks(codes: DataFrame, batch: Batch, model: PQModel, r: int, make: Callable[[], ScanBlock], number: str, tops: dict | None = None, rows: int = BLOCK_ROWS) -> DataFrame:
    """(qid, vec_id, dist): at most r rows for each task and query."""
    shared = codes.sparkSession.sparkContext.broadcast((batch, tops))
    m, b = model.m, model.b
    schema = pa.schema([("qid", pa.int64()), ("vec_id", pa.int64()), ("dist", ARROW[number])])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (own, top), each = shared.value, make()
        best: dict[int, Best] = {}
        for block in blocks(batches, m, b, rows):
            for i in range(len(own.ids)):
                if i not in best:
                    best[i] = Best(r, None if top is None else top.get(int(own.ids[i])))
                each(block, 0, block.n, own, best[i], i) if own.probes is None else _probe(block, own, best[i], i, each)
        yield from emitted(best, own.ids, schema)

    names = ["vec_id", *(["list_id"] if batch.probes is not None else []), *[c for c in ("grp",) if c in codes.columns], "code"]
    return codes.select(*names).mapInArrow(run, f"qid long, vec_id long, dist {number}")


def _probe(block: Block, own: Batch, best: Best, i: int, each) -> None:
    for lst in own.probes[i].tolist():
        if lst in block.runs:
            each(block, *block.runs[lst], own, best, i, lst)


def _tables(model: PQModel, own: Batch, i: int, lst: int | None) -> np.ndarray:
    return own.tables(model, i, lst)


PAIRED_ROWS = 1 << 14  # fewer codes do not repay tables of words


def union_topk(parts: list[DataFrame], r: int) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return top_k(out, r, ["qid"], ["dist", "vec_id"])


def empty_result(codes: DataFrame, model: PQModel) -> DataFrame:
    return codes.sparkSession.createDataFrame([], f"qid long, vec_id long, dist {model.number}")


def plain_scan(codes: DataFrame, queries: DataFrame, model: PQModel, r: int, probes: DataFrame | None = None, centers: np.ndarray | None = None, **how) -> DataFrame:
    """Table-sum scan of (vec_id, [list_id,] code): all codes, or those of the probed lists."""

    def make():
        def each(block: Block, low: int, high: int, own: Batch, best: Best, i: int, lst: int | None = None) -> None:
            t = narrow(_tables(model, own, i, lst))
            best.offer(distances(t, block, low, high, model.b), block.ids[low:high])

        return each

    parts = [scan_blocks(codes, b, model, r, make, model.number, **how) for b in batches_of(queries, probes, centers)]
    return union_topk(parts or [empty_result(codes, model)], r)


def distances(t: np.ndarray, block: Block, low: int, high: int, b: int) -> np.ndarray:
    if high - low >= PAIRED_ROWS:
        return summed(word_tables(t, b), block.words[:, low:high])
    c = from_bytes(block.raw[low:high], block.m, b)
    out = t[0].take(c[:, 0])
    for j in range(1, block.m):
        out += t[j].take(c[:, j])
    return out


# -- scans by matrix products ------------------------------------------------------------------

TILE = 1 << 11  # codes of one product
PRODUCT_ROWS = 1 << 16  # codes of a block; their ones and zeros are held
PRODUCT_WIDTH = 256  # ones and zeros of a code, at most


def one_hot(parts: np.ndarray, k: int) -> np.ndarray:
    """n x m parts below k as n x (m k) ones and zeros: a product with small tables sums their entries,
    exactly while the sums stay below 2^24."""
    return (parts[:, :, None] == np.arange(k, dtype=parts.dtype)).reshape(len(parts), -1).astype(np.float32)


def passed(sieve: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of what is true; little is."""
    return np.divmod(np.flatnonzero(sieve.ravel()), sieve.shape[1])


class Run:
    """The best of a run of queries. What comes within their thresholds is merged once it is much."""

    def __init__(self, best: list[Best]):
        self.best, self.held, self.n = best, [], 0
        self.room = 2 * sum(b.r for b in best)
        self.refresh()

    def refresh(self) -> None:
        self.top = np.array([np.inf if b.top is None else b.top for b in self.best], float)

    def offer(self, place: np.ndarray, d: np.ndarray, ids: np.ndarray) -> bool:
        """Takes rows of the queries at ``place``; whether thresholds were made anew."""
        self.held.append((place, d, ids))
        self.n += len(d)
        return self.merge() if self.n > self.room else False

    def merge(self) -> bool:
        if not self.n:
            return False
        place, d, ids = (np.concatenate(x) for x in zip(*self.held, strict=True))
        order = np.argsort(place, kind="stable")
        ends = np.searchsorted(place[order], np.arange(len(self.best) + 1))
        for i in np.flatnonzero(np.diff(ends)).tolist():
            rows = order[ends[i] : ends[i + 1]]
            self.best[i].add(d[rows], ids[rows])
        self.held, self.n = [], 0
        self.refresh()
        return True


def product_blocks(codes: DataFrame, batch: Batch, model: PQModel, r: int, make: Callable, number: str, tops: dict | None = None) -> DataFrame:
    """As ``scan_blocks``, for scans that take runs of queries: ``make()`` gives a function of a block
    which gives one of (queries, place of the first query, their Best)."""
    shared = codes.sparkSession.sparkContext.broadcast((batch, tops))
    schema = pa.schema([("qid", pa.int64()), ("vec_id", pa.int64()), ("dist", ARROW[number])])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (own, top), opened = shared.value, make()
        best = [Best(r, None if top is None else top.get(int(q))) for q in own.ids]
        for block in blocks(batches, model.m, model.b, PRODUCT_ROWS):
            each = opened(block)
            for first in range(0, len(best), CHUNK):
                each(own, first, best[first : first + CHUNK])
        yield from emitted(dict(enumerate(best)), own.ids, schema)

    return codes.select("vec_id", "code").mapInArrow(run, f"qid long, vec_id long, dist {number}")


# -- bounded scan ------------------------------------------------------------------------------


def grouped(codes: DataFrame, model: PQModel, g: int, low_bits: int = 4, keys: tuple[str, ...] = ()) -> DataFrame:
    """The storage layout of the bounded scan: codes with their group number (the high bits of the first
    g parts), dealt to ranges of groups and sorted by group, so that a task's blocks hold runs of one group."""
    wide = 8 - low_bits

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                raw = raw_codes(batch, model.m)
                grp = np.zeros(batch.num_rows, np.int64)
                for j in range(g):
                    grp = grp << wide | raw[:, j] >> low_bits
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(grp)], names=[*batch.schema.names, "grp"])

    fields = ", ".join(f"{c} {'binary' if c == 'code' else 'long'}" for c in codes.columns)
    return codes.mapInArrow(run, f"{fields}, grp long").repartitionByRange(tasks_for(codes, codes.count()), *keys, "grp").sortWithinPartitions(*keys, "grp", "vec_id")


def _gathered(head: DataFrame) -> DataFrame:
    """Codes of a prefix in a few tasks, as each makes every query's tables."""
    return head.coalesce(max(1, -(-head.count() // HEAD_ROWS)))


HEAD_BYTES = 32 << 20  # ids and codes of a prefix that may be broadcast


def _nth_least(d: np.ndarray, r: int):
    """The r-th least distance, the last of fewer. A sample's quantile cuts first, as in ``least_rows``."""
    n, r = len(d), min(r, len(d))
    if n > 32 * r and n >= 8192:
        some = d[:: n // 4096]
        at = min(len(some) - 1, 2 * r // (n // 4096) + 8)
        near = d[d <= np.partition(some, at)[at]]
        if len(near) >= r:
            d = near
    return np.partition(d, r - 1)[r - 1]


def _held_tops(codes: DataFrame, queries: DataFrame, model: PQModel, cases: list[tuple[int, int]]) -> DataFrame | None:
    """(qid, t0 ..): the r-th distance (the last, of fewer) among the codes up to the last id of each case (r, last id),
    by one scan of the longest prefix for each query, in the queries' tasks; None where the prefix is not to be broadcast."""
    head, width = codes.where(F.col("vec_id") <= F.lit(max(end for _, end in cases))).select("vec_id", "code"), code_bytes(model.m, model.b)
    if head.count() * (8 + width) > HEAD_BYTES:
        return None

    def bytes_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                held = (batch["vec_id"].to_numpy(zero_copy_only=False).astype(np.int64), raw_codes(batch, width))
                yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in held], names=["ids", "codes"])

    rows = head.mapInArrow(bytes_of, "ids binary, codes binary").collect()  # of a checked size
    ids, raw = (np.frombuffer(b"".join(bytes(r[c]) for r in rows), kind) for c, kind in (("ids", np.int64), ("codes", np.uint8)))
    order = np.argsort(ids)
    last = np.searchsorted(ids[order], [end for _, end in cases], "right").tolist()
    if not min(last):
        return None
    shared = codes.sparkSession.sparkContext.broadcast(raw.reshape(-1, width)[order])
    names = ["qid", *[f"t{i}" for i in range(len(cases))]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tiles = None
        for batch in batches:
            if not batch.num_rows:
                continue
            if tiles is None:
                words = words_of(from_bytes(shared.value, model.m, model.b), model.b)
                tiles = [np.ascontiguousarray(words[:, at : at + WORD_TILE]) for at in range(0, words.shape[1], WORD_TILE)]
            x, out = matrix(batch), []
            for first in range(0, len(x), CHUNK):
                t = model.tables(x[first : first + CHUNK])
                for own in np.rint(t).astype(np.int64) if model.number == "long" else t:
                    tables = word_tables(narrow(own), model.b)
                    d = np.concatenate([summed(tables, tile) for tile in tiles])
                    out.append([_nth_least(d[:n], r) for (r, _), n in zip(cases, last, strict=True)])
            yield pa.RecordBatch.from_arrays([batch["qid"].cast(pa.int64()), *[pa.array(c, ARROW[model.number]) for c in zip(*out, strict=True)]], names=names)

    return queries.select("qid", "e").mapInArrow(run, "qid long, " + ", ".join(f"{n} {model.number}" for n in names[1:]))


def prefix_tops(codes: DataFrame, queries: DataFrame, model: PQModel, r: int, share: float | None = 0.01, count: int | None = None) -> dict[int, float]:
    """The r-th distance of each query among the first ceil(share * n) codes by id (r at least). The prefix
    is a filter on ids, which stored codes push down to the scan."""
    limit = F.greatest(F.lit(r), F.lit(count) if count is not None else F.ceil(F.col("_total") * F.lit(share))).cast("long")
    end = prefix_ends(codes, "vec_id", limit).first()
    if end is None:
        return {}
    held = _held_tops(codes, queries, model, [(r, end["_end"])])
    if held is not None and codes.where(F.col("vec_id") <= F.lit(end["_end"])).limit(r).count() == r:
        return {row["qid"]: row["t0"] for row in held.collect()}  # a row for each query of a batch
    near = plain_scan(_gathered(codes.where(F.col("vec_id") <= F.lit(end["_end"]))), queries, model, r)
    return {row["qid"]: row["top"] for row in near.groupBy("qid").agg(F.max("dist").alias("top"), F.count("*").alias("n")).where(F.col("n") >= r).collect()}  # a row for each query of a batch


class BoundedBlock:
    """A block's portions as ones and zeros, and where its runs of one group begin."""

    def __init__(self, block: Block, g: int, low_bits: int):
        c = block.codes
        high = c >> low_bits
        self.block, self.g, self.low_bits, self.portions = block, g, low_bits, 1 << (8 - low_bits)
        self.rest = one_hot(high[:, g:], self.portions)
        edge = (high[1:, :g] != high[:-1, :g]).any(axis=1) if g else np.zeros(max(0, block.n - 1), bool)
        self.first = np.flatnonzero(np.concatenate(([True], edge)))
        self.group = one_hot(high[self.first, :g], self.portions)
        self.places = c + (np.arange(block.m) * (1 << block.b))  # in a query's tables

    def scan(self, own: Batch, model: PQModel, start: int, best: list[Best], tally: np.ndarray | None = None) -> None:
        """The three sieves of the bounded scan for a run of queries; ``tally`` counts what each leaves."""
        block, t = self.block, narrow(own.run(model, start))
        count, m, k = t.shape
        at, tally = 0, np.zeros((count, 5), np.int64) if tally is None else tally
        tally[:, :2] += (block.n, len(self.first))
        if any(b.top is None for b in best):  # the first rows give thresholds
            at = min(block.n, max(TILE, best[0].r))
            for i, b in enumerate(best):
                b.offer(distances(t[i], block, 0, at, model.b), block.ids[:at])
            tally[:, 3:] += at
            tally[:, 2] += np.searchsorted(self.first, at)
        run, flat = Run(best), t.reshape(-1)
        least = t.reshape(count, m, self.portions, 1 << self.low_bits).min(axis=3)
        lows = least.min(axis=2)
        floor, span = lows.sum(axis=1), (least.max(axis=2) - lows).sum(axis=1)
        # Minima above the least, in steps so wide that no sum reaches 2^21; rounded down, they stay bounds.
        whole = t.dtype.kind == "i"
        step = np.maximum(1, -(-span // (1 << 20))) if whole else np.maximum(span, 1e-30) / (1 << 20)
        bins = ((least - lows[:, :, None]) // step[:, None, None]).reshape(count, -1).astype(np.float32)
        spare = (run.top - floor) // step + (0 if whole else 1)
        near_bins, far_bins = bins[:, : self.g * self.portions].T, bins[:, self.g * self.portions :]
        while at < block.n:
            end = min(block.n, at + TILE)
            # The tile's runs of one group; the first may have begun before it.
            low, upto = np.searchsorted(self.first, at, "right") - 1, np.searchsorted(self.first, end)
            size = np.diff(np.append(np.maximum(self.first[low:upto], at), end))
            left = spare - self.group[low:upto] @ near_bins  # what each group leaves to a code's other parts
            near = left >= 0
            tally[:, 2] += near[int(self.first[low] < at) :].sum(axis=0)
            active = np.flatnonzero(near.any(axis=0))
            if len(active):
                bound = self.rest[at:end] @ far_bins[active].T
                rows, place = passed(bound <= np.repeat(left[:, active].astype(np.float32), size, axis=0))
                place, rows = active.take(place), rows + at
                tally[active, 3] += end - at
                tally[:, 4] += np.bincount(place, minlength=count)
                d = flat.take(self.places.take(rows, axis=0) + (place * (m * k))[:, None], mode="clip").sum(axis=1)
                kept = np.flatnonzero(d <= run.top.take(place))
                if len(kept) and run.offer(place[kept], d[kept], block.ids[rows[kept]]):
                    spare = (run.top - floor) // step + (0 if whole else 1)
            at = end
        run.merge()


def bounded_scan(codes: DataFrame, queries: DataFrame, model: PQModel, r: int, g: int, tops: dict | None = None, low_bits: int = 4, stats: bool = False) -> DataFrame:
    """Exactly the plain scan's rows, from codes in the layout of ``grouped``.

    Three sieves, each on what the one before left: a tile of codes all of whose groups are beyond a query's
    threshold is skipped for it; a code's bound is the sum of the quantized minima of its portions, made
    for a run of queries by one matrix product; only codes that both pass are summed. The threshold starts
    from a prefix's (``tops``) and falls as a task finds nearer codes. ``stats`` gives (qid, codes, groups,
    groups_kept, bounded, summed) instead.
    """

    def make():
        def opened(block: Block):
            held = BoundedBlock(block, g, low_bits)
            return lambda own, first, best: held.scan(own, model, first, best)

        return opened

    if stats:
        return _bounded_stats(codes, queries, model, r, g, low_bits, tops)
    parts = [product_blocks(codes, b, model, r, make, model.number, tops) for b in batches_of(queries)]
    return union_topk(parts or [empty_result(codes, model)], r)


def _bounded_stats(codes: DataFrame, queries: DataFrame, model: PQModel, r: int, g: int, low_bits: int, tops: dict | None) -> DataFrame:
    names = ("codes", "groups", "groups_kept", "bounded", "summed")
    out = None
    for batch in batches_of(queries):
        shared = codes.sparkSession.sparkContext.broadcast((batch, tops))

        def run(batches, shared=shared):
            own, top = shared.value
            best = [Best(r, None if top is None else top.get(int(q))) for q in own.ids]
            seen = np.zeros((len(best), 5), np.int64)
            for block in blocks(batches, model.m, model.b, PRODUCT_ROWS):
                held = BoundedBlock(block, g, low_bits)
                for i in range(0, len(best), CHUNK):
                    held.scan(own, model, i, best[i : i + CHUNK], seen[i : i + CHUNK])
            yield pa.RecordBatch.from_arrays([pa.array(own.ids), *[pa.array(seen[:, j]) for j in range(5)]], names=["qid", *names])

        part = codes.select("vec_id", "code").mapInArrow(run, "qid long, " + ", ".join(f"{n} long" for n in names))
        out = part if out is None else out.unionByName(part)
    return out.groupBy("qid").agg(*[F.sum(n).alias(n) for n in names])


# -- counts of the bounds as published ---------------------------------------------------------


WORD_TILE = 1 << 15  # codes whose words are summed at once


def _lane_counts(total: np.ndarray, top: int, bits: int, ones: int, shifts: list) -> np.ndarray:
    """How many numbers have the highest bit of each lane set."""
    kind = total.dtype.type
    if len(shifts) == 1:
        return np.array([np.count_nonzero(total >= kind(1 << top))])
    total >>= kind(top)
    total &= ones
    run = (1 << bits) - 1  # no lane of a sum of so many overflows
    sums = np.add.reduceat(total, np.arange(0, len(total), run))
    return np.array([int((sums >> by & kind(run)).sum()) for by in shifts])


class CountedBlock:
    """A block's codes, or those of one list, laid out to count the codes that bounds on quantized tables prune.

    ``whole`` parts are bounded by their own entries, the others by the minima of portions of ``1 << low_bits``
    entries. Where all parts are whole, few codes are kept: a product with the minima of clusters, which are at
    most the entries, finds them. Else bins are summed by words of few bits, those of several cases at once."""

    def __init__(self, codes: np.ndarray, ids: np.ndarray, model: PQModel, whole: int, low_bits: int):
        m, k = model.books.shape[:2]
        order = np.argsort(ids, kind="stable")
        self.ids, codes = ids[order], codes[order]
        self.whole, self.width = whole, 1 << low_bits
        if whole == m:
            # Any order of a part's entries is right, one by value is tight.
            self.order = np.stack([np.argsort(book.sum(axis=1), kind="stable") for book in model.books])
            named = np.argsort(self.order, axis=1) // self.width
            self.hot = one_hot(np.stack([named[j].take(codes[:, j]) for j in range(m)], axis=1).astype(np.uint8), -(-k // self.width))
            self.places = codes.astype(np.intp) + np.arange(m) * k
            return
        bits = max(1, int(k - 1).bit_length())
        sizes = [bits if j < whole else max(0, bits - low_bits) for j in range(m)]
        # Parts of a word: whole ones first, two where their table of 16 bits is shorter than the codes; then
        # others while the word's table stays small.
        wide = WORD_BITS if len(codes) >= PAIRED_ROWS else SHORT_BITS
        held, rest = [], list(range(m))
        while rest:
            fit = next((w for w in held if sum(sizes[j] for j in w) + sizes[rest[0]] <= (wide if rest[0] < whole else SHORT_BITS)), None)
            if fit is None:
                held.append(fit := [])
            fit.append(rest.pop(0))
        self.held, self.words = held, np.zeros((len(held), len(codes)), np.intp)
        for word, parts in zip(self.words, held, strict=True):
            for j in parts:
                word *= 1 << sizes[j]
                word += codes[:, j] if j < whole else codes[:, j] >> low_bits
        self.sizes, self._tiles = sizes, None

    def tiles(self, ends: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
        """(words, whether each case counts them): rows between the ends of two prefixes, a tile at a time. Rows
        of all prefixes are in none."""
        if self._tiles is None or not np.array_equal(self._tiles[0], ends):
            edges, out = np.searchsorted(self.ids, ends, "right"), []
            cuts = [*np.unique(edges).tolist(), len(self.ids)]
            for low, high in zip(cuts, cuts[1:]):
                order = low + np.argsort(self.words[0, low:high], kind="stable")  # near places of a large table
                for at in range(0, len(order), WORD_TILE):
                    out.append((np.ascontiguousarray(self.words[:, order[at : at + WORD_TILE]]), edges <= low))
            self._tiles = (ends, out)
        return self._tiles[1]

    def count(self, t: np.ndarray, tops: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Pruned codes of each query and case: q tables, q x cases thresholds, the last id of each case's prefix."""
        return self._by_product(t, tops, ends) if self.whole == t.shape[1] else self._by_words(t, tops, ends)

    def _by_words(self, t: np.ndarray, tops: np.ndarray, ends: np.ndarray) -> np.ndarray:
        (count, m, k), cases = t.shape, tops.shape[1]
        low, starts = t.reshape(count, -1).min(axis=1), np.arange(0, k, self.width)
        if not len(self.ids):
            return np.zeros((count, cases), np.int64)
        parts = [t[:, j] if j < self.whole else np.minimum.reduceat(t[:, j], starts, axis=1) for j in range(m)]
        parts = [np.pad(x, ((0, 0), (0, (1 << size) - x.shape[1]))) - low[:, None] for x, size in zip(parts, self.sizes, strict=True)]
        tiles = self.tiles(ends)
        spans = tops - low[:, None]
        cuts = -(-(tops - m * low[:, None]) * 127 // np.maximum(spans, 1))
        # A lane of a number for each case: no sum of bins reaches its highest bit, which what is added to the
        # first word's table sets from ``cut`` on.
        top = int(m * 127).bit_length()
        bits = top + 1
        out = np.zeros((count, cases), np.int64)
        for first in range(0, cases, 64 // bits):
            lanes = range(first, min(cases, first + 64 // bits))
            kind = np.uint16 if len(lanes) * bits <= 16 else np.uint64
            shifts = [kind((c - first) * bits) for c in lanes]
            own = [sum((np.minimum(x * 127 // np.maximum(spans[:, c], 1)[:, None], 127).astype(kind) << by for c, by in zip(lanes, shifts, strict=True)), kind(0)) for x in parts]
            add = sum(((1 << top) - cuts[:, c].clip(0, 1 << top)).astype(kind) << by for c, by in zip(lanes, shifts, strict=True))
            ones = kind(sum(1 << int(by) for by in shifts))
            for i in np.flatnonzero((spans[:, lanes.start : lanes.stop] > 0).any(axis=1)).tolist():
                tables = []
                for places in self.held:
                    table = own[places[0]][i] + add[i] if not tables else own[places[0]][i]
                    for j in places[1:]:
                        table = (table[:, None] + own[j][i][None, :]).ravel()
                    tables.append(table)
                found = np.zeros(len(lanes), np.int64)
                for words, counts in tiles:
                    total = tables[0].take(words[0], mode="clip")
                    for table, places in zip(tables[1:], words[1:], strict=True):
                        total += table.take(places, mode="clip")
                    found += np.where(counts[lanes.start : lanes.stop], _lane_counts(total, top, bits, ones, shifts), 0)
                out[i, lanes.start : lanes.stop] = found
        return np.where(spans > 0, out, 0)

    def _by_product(self, t: np.ndarray, tops: np.ndarray, ends: np.ndarray) -> np.ndarray:
        (count, m, k), cases = t.shape, tops.shape[1]
        low = t.reshape(count, -1).min(axis=1)
        span = tops - low[:, None]
        some = span > 0
        # A code is pruned if its bins, the integer parts of (entry - low) * 127 / span, sum to ``cut``. The sum of
        # entries settles that from ``sure`` on and below ``never``; bins are summed in between.
        cut = np.where(some, -(-(tops - m * low[:, None]) * 127 // np.maximum(span, 1)), 0)
        sure = np.where(some, m * low[:, None] - (-(cut + m - 1) * span // 127), np.iinfo(np.int64).min)
        never = np.where(some, m * low[:, None] - (-cut * span // 127), np.iinfo(np.int64).min)
        free = np.array([np.count_nonzero(self.ids > e) for e in ends])
        kept = np.zeros((count, cases), np.int64)
        by_value = np.take_along_axis(t, np.broadcast_to(self.order, (count, m, k)), axis=2)
        floors = np.minimum.reduceat(by_value, np.arange(0, k, self.width), axis=2)
        lows = floors.min(axis=2)
        floor, height = lows.sum(axis=1), (floors.max(axis=2) - lows).sum(axis=1)
        step = np.maximum(1, -(-height // (1 << 20)))
        bins = ((floors - lows[:, :, None]) // step[:, None, None]).reshape(count, -1).T.astype(np.float32)
        # below ``far``, an entry sum may be below ``sure`` in some case
        far = np.where(some.any(axis=1), -((floor - sure.max(axis=1, initial=0, where=some)) // step), 0).clip(0, 1 << 22).astype(np.float32)
        flat = t.reshape(-1)
        for at in range(0, len(self.ids), TILE):
            rows, place = passed(self.hot[at : at + TILE] @ bins < far)
            if not len(rows):
                continue
            spots = self.places.take(rows + at, axis=0)
            total = flat.take(spots + (place * (m * k))[:, None]).sum(axis=1)
            near = np.flatnonzero(total < sure.max(axis=1)[place])
            rows, place, spots, total = rows[near], place[near], spots[near], total[near]
            ids = self.ids.take(rows + at)
            for c in range(cases):
                held = (total < never[place, c]) & (ids > ends[c])
                between = np.flatnonzero((total >= never[place, c]) & (total < sure[place, c]) & (ids > ends[c]))
                if len(between):
                    own = place[between]
                    entries = flat.take(spots[between] + (own * (m * k))[:, None])
                    sums = ((entries - low[own][:, None]) * 127 // span[own, c][:, None]).sum(axis=1)
                    held[between] = sums < cut[own, c]
                kept[:, c] += np.bincount(place[held], minlength=count)
        return np.where(some, free - kept, 0)


def _counts(codes: DataFrame, queries: DataFrame, model: PQModel, whole: int, low_bits: int, probes: DataFrame | None, ends: dict, tops: Callable[[Batch], dict], cases: int) -> DataFrame:
    """(qid, [list_id,] case, n_codes, n_pruned). ``ends``: list (None: all codes) -> last prefix id of each case;
    ``tops``: of a batch, (place, list) -> threshold of each case."""
    listed, out = probes is not None, None
    names = ["qid", *(["list_id"] if listed else []), "case", "n_codes", "n_pruned"]
    for batch in batches_of(queries, probes):
        shared = codes.sparkSession.sparkContext.broadcast((batch, ends, tops(batch)))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            own, last, top = shared.value
            found: dict[int | None, np.ndarray] = {}
            asked: dict[int | None, np.ndarray] = {None: np.arange(len(own.ids))}
            if listed:
                pairs = [(lst, i) for i, some in enumerate(own.probes) for lst in some.tolist()]
                asked = {}
                for lst, i in pairs:
                    asked.setdefault(lst, []).append(i)
            for block in blocks(batches, model.m, model.b, PRODUCT_ROWS if whole == model.m else BLOCK_ROWS):
                spans = block.runs if listed else {None: (0, block.n)}
                for lst, (a, z) in spans.items():
                    if lst not in asked:
                        continue
                    places = np.array(asked[lst])
                    held = CountedBlock(block.codes[a:z], block.ids[a:z], model, whole, low_bits)
                    total = found.setdefault(lst, np.zeros((len(places), cases, 2), np.int64))
                    total[:, :, 0] += z - a
                    for i in range(0, len(places), CHUNK):
                        part = places[i : i + CHUNK]
                        t = np.rint(model.tables(own.x[part])).astype(np.int64)
                        total[i : i + CHUNK, :, 1] += held.count(t, np.array([top[int(p), lst] for p in part], np.int64), last[lst])
            for lst, total in found.items():
                n, qids = len(total), own.ids[np.array(asked[lst])]
                columns = [np.repeat(qids, cases), *([np.full(n * cases, lst)] if listed else []), np.tile(np.arange(cases), n), total[:, :, 0].ravel(), total[:, :, 1].ravel()]
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=names)

        part = codes.select("vec_id", *(["list_id"] if listed else []), "code").mapInArrow(run, ", ".join(f"{n} long" for n in names))
        out = part if out is None else out.unionByName(part)
    if out is None:
        out = codes.sparkSession.createDataFrame([], ", ".join(f"{n} long" for n in names))
    return out.groupBy(*names[:-2]).agg(F.sum("n_codes").alias("n_codes"), F.sum("n_pruned").alias("n_pruned"))


def bounded_cases(codes: DataFrame, queries: DataFrame, model: PQModel, cases: list[tuple[int, float]], g: int, mode: str = "full", low_bits: int = 4) -> DataFrame:
    """(qid, case, n_codes, n_pruned) of ``bounded_counts`` for several (r, share) at once: one pass over the codes."""
    ends, tops = [0] * len(cases), {}
    for i, (r, share) in enumerate(cases):
        limit = F.greatest(F.lit(r), F.ceil(F.col("_total") * F.lit(share))).cast("long")
        end = prefix_ends(codes, "vec_id", limit).first()
        ends[i] = end["_end"] if end else 0
    held = _held_tops(codes, queries, model, [(r, end) for (r, _), end in zip(cases, ends, strict=True)])
    if held is not None:
        tops = {row[0]: list(row[1:]) for row in held.collect()}  # a row for each query
    for end in sorted(set(ends)) if held is None else ():  # one scan of each prefix
        own = [i for i, e in enumerate(ends) if e == end]
        near = plain_scan(_gathered(codes.where(F.col("vec_id") <= F.lit(end))), queries, model, max(cases[i][0] for i in own))
        at = near.groupBy("qid").agg(*[F.max(F.when(F.col("rk") <= cases[i][0], F.col("dist"))).alias(f"t{i}") for i in own])
        for row in at.collect():  # a row for each query
            for i in own:
                tops.setdefault(row["qid"], [0] * len(cases))[i] = row[f"t{i}"]

    def of(batch: Batch) -> dict:
        return {(i, None): tops[q] for i, q in enumerate(batch.ids.tolist())}

    return _counts(codes, queries, model, g if mode == "full" else model.m, low_bits, None, {None: np.array(ends, np.int64)}, of, len(cases))


def bounded_counts(codes: DataFrame, queries: DataFrame, model: PQModel, r: int, g: int, share: float = 0.01, mode: str = "full", low_bits: int = 4) -> DataFrame:
    """(qid, n_codes, n_pruned) of the bounds on quantized tables: whole for the first g parts, portion
    minima for the others (``quant_only``: whole for all); codes of the prefix are never pruned."""
    return bounded_cases(codes, queries, model, [(r, share)], g, mode, low_bits).drop("case")


def listed_counts(codes: DataFrame, queries: DataFrame, probes: DataFrame, model: PQModel, r: int, g: int, share: float = 0.01, low_bits: int = 4) -> DataFrame:
    """(qid, list_id, n_codes, n_pruned): the same for the probed lists of (vec_id, list_id, code), each with its own prefix."""
    limit = F.greatest(F.lit(r), F.ceil(F.col("_total") * F.lit(share))).cast("long")
    held = prefix_ends(codes, "vec_id", limit, ("list_id",)).persist()
    ends = {row["list_id"]: np.array([row["_end"]], np.int64) for row in held.collect()}  # a row for each list
    head = codes.join(F.broadcast(held), "list_id").where(F.col("vec_id") <= F.col("_end")).select("vec_id", "list_id", "code")

    def of(batch: Batch) -> dict:
        return {at: [int(top)] for at, top in _probe_tops(head, batch, model, r).items()}

    return _counts(codes, queries, model, g, low_bits, probes, ends, of, 1).drop("case")


# -- nibble scan -------------------------------------------------------------------------------


def nibble_scan(codes: DataFrame, queries: DataFrame, model: PQModel, r: int, count: int = 20, bins: int = 127, probes: DataFrame | None = None, centers: np.ndarray | None = None) -> DataFrame:
    """Four-bit (or other short) parts with tables quantized to one byte and saturating sums.

    Bins reach from the least entry to the r-th distance among the first max(r, count) codes, of
    each probed list where lists are probed. ``dist`` is the saturated sum.
    """
    parts = []
    if probes is None and model.m * model.k <= PRODUCT_WIDTH and max(r, count) <= PRODUCT_ROWS:
        head = _first_codes(codes, model, max(r, count))
        for batch in batches_of(queries):
            parts.append(product_blocks(codes, batch, model, r, lambda: lambda block: _nibble_products(block, model, bins, r, head), "long"))
    else:
        for batch in batches_of(queries, probes, centers):
            parts.append(_nibble_part(codes, batch, model, r, bins, list_tops(codes, batch, model, r, count)))
    if not parts:
        return union_topk([empty_result(codes, model)], r)
    return union_topk(parts, r)


def list_tops(codes: DataFrame, batch: Batch, model: PQModel, r: int, count: int) -> dict:
    """(query place, list or None) -> the r-th distance (the last, of fewer) among the prefix's codes.

    The prefixes are max(r, count) codes of each list; they are read once and their tables made on
    the driver, which holds nothing larger than a batch's probes times a prefix."""
    keys = ("list_id",) if batch.probes is not None else ()
    ends = prefix_ends(codes, "vec_id", F.lit(max(r, count)).cast("long"), keys)
    head = codes.join(F.broadcast(ends), list(keys)) if keys else codes.crossJoin(F.broadcast(ends))
    return _probe_tops(head.where(F.col("vec_id") <= F.col("_end")).select(*keys, "vec_id", "code"), batch, model, r)


def _probe_tops(rows: DataFrame, batch: Batch, model: PQModel, r: int) -> dict:
    """(query place, list or None) -> the r-th distance (the last, of fewer) among the prefixes' codes."""
    shared = rows.sparkSession.sparkContext.broadcast(batch)
    m, b = model.m, model.b

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, held, n = shared.value, [], 0

        def joined() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held, strict=True)], names=["place", "list_id", "vec_id", "dist"])

        for block in blocks(batches, m, b):
            for i in range(len(own.ids)):
                for lst in [None] if own.probes is None else own.probes[i].tolist():
                    span = (0, block.n) if lst is None else block.runs.get(lst)
                    if span:
                        d = distances(_tables(model, own, i, lst), block, *span, b)
                        kept = least_rows(d, block.ids[span[0] : span[1]], r)
                        held.append((np.full(len(kept), i), np.full(len(kept), -1 if lst is None else lst), block.ids[span[0] : span[1]][kept], d[kept].astype(float)))
                        n += len(kept)
                if n >= 50_000:
                    yield joined()
                    held, n = [], 0
        if held:
            yield joined()

    near = top_k(rows.mapInArrow(run, "place long, list_id long, vec_id long, dist double"), r, ["place", "list_id"], ["dist", "vec_id"])
    found = near.groupBy("place", "list_id").agg(F.max("dist").alias("top")).collect()  # a row for each probe of the batch
    return {(x["place"], None if x["list_id"] < 0 else x["list_id"]): x["top"] for x in found}


def quantized_tables(t: np.ndarray, top: float, bins: int) -> np.ndarray:
    low = t.min()
    if top <= low:
        return np.zeros(t.shape, np.uint8)
    scaled = (t - low) * bins // (int(top) - low) if t.dtype.kind == "i" else np.floor((t - low) * bins / (top - low))
    return np.minimum(scaled, bins).astype(np.uint8)


def _nibble_part(codes: DataFrame, batch: Batch, model: PQModel, r: int, bins: int, tops: dict) -> DataFrame:
    shared = codes.sparkSession.sparkContext.broadcast(tops)

    def make():
        def each(block: Block, low: int, high: int, own: Batch, best: Best, i: int, lst: int | None = None) -> None:
            top = shared.value.get((i, lst))
            if top is None:
                return
            q = quantized_tables(_tables(model, own, i, lst), top, bins)
            if high - low >= PAIRED_ROWS:
                acc = None
                for w, t in zip(block.words, saturated_words(q, model.b, bins), strict=True):
                    part = t.take(w[low:high])
                    acc = part if acc is None else np.minimum(acc + part, np.uint8(bins))
            else:
                c = from_bytes(block.raw[low:high], block.m, block.b)
                acc = q[0].take(c[:, 0])
                for j in range(1, block.m):
                    acc = np.minimum(acc + q[j].take(c[:, j]), np.uint8(bins))
            best.offer(acc, block.ids[low:high])

        return each

    return scan_blocks(codes, batch, model, r, make, "long")


def _first_codes(codes: DataFrame, model: PQModel, count: int) -> np.ndarray:
    """The first ``count`` codes by id, n x m: as many rows as a result, which every task is given."""
    rows = codes.select("vec_id", "code").orderBy("vec_id").limit(count).collect()  # each task sends its first ones only
    raw = np.frombuffer(b"".join(bytes(x["code"]) for x in rows), np.uint8).reshape(len(rows), code_bytes(model.m, model.b))
    return from_bytes(raw, model.m, model.b)


def _nibble_products(block: Block, model: PQModel, bins: int, r: int, head: np.ndarray):
    """Saturated sums of a block's codes for runs of queries: a product with the quantized tables, cut at ``bins``.
    Bins reach to the r-th distance among the codes of ``head`` (the last, of fewer)."""
    hot, nth = one_hot(block.codes, model.k), min(r, len(head)) - 1

    def each(own: Batch, first: int, best: list[Best]) -> None:
        t = own.run(model, first)
        near = t[:, 0, head[:, 0]]
        for j in range(1, model.m):
            near = near + t[:, j, head[:, j]]
        tops = np.partition(near, nth, axis=1)[:, nth]
        small = np.stack([quantized_tables(x, top, bins).ravel() for x, top in zip(t, tops, strict=True)]).T.astype(np.float32)
        run, at = Run(best), 0
        while at < block.n:
            unknown = np.isinf(run.top).any()  # the first rows, more of them, give thresholds
            end = min(block.n, at + (4 * TILE if unknown else TILE))
            acc = hot[at:end] @ small
            if unknown:
                for i, b in enumerate(run.best):
                    b.offer(np.minimum(acc[:, i], bins).astype(np.int64), block.ids[at:end])
                run.refresh()
            else:
                # At a threshold of ``bins`` saturated sums still count.
                rows, place = passed(acc <= np.where(run.top >= bins, np.inf, run.top).astype(np.float32))
                if len(rows):
                    run.offer(place, np.minimum(acc[rows, place], bins).astype(np.int64), block.ids[at + rows])
            at = end
        run.merge()

    return each


# -- nested scan -------------------------------------------------------------------------------


def nested_candidates(codes: DataFrame, queries: DataFrame, model: PQModel, r2: int) -> DataFrame:
    """First pass over the low bits: (qid, vec_id, bucket, code) of whole buckets until r2 codes.

    Each task drops, block by block, what lies beyond the bucket at which it has r2 codes itself; the
    union's histogram gives the cutoff of all.
    """
    k2 = model.coarse.shape[1]
    low_model = PQModel(model.m, max(1, int(np.log2(k2))), model.d, model.coarse, model.rotation)
    narrowed = max(1, int(np.log2(k2)))
    end = prefix_ends(codes, "vec_id", F.lit(r2).cast("long")).first()
    out = None
    for batch in batches_of(queries):
        head = _low_tops(codes.where(F.col("vec_id") <= F.lit(end["_end"] if end else 0)), batch, low_model, narrowed, model)
        shared = codes.sparkSession.sparkContext.broadcast((batch, head))
        schema = pa.schema([("qid", pa.int64()), ("vec_id", pa.int64()), ("bucket", pa.int64()), ("code", pa.binary())])

        def run(batches, shared=shared, schema=schema):
            own, tops = shared.value
            held: dict[int, tuple] = {}
            for block in blocks(batches, model.m, model.b):
                low = words_of(block.codes & (k2 - 1), narrowed)
                for i, q in enumerate(own.ids.tolist()):
                    if i not in tops:
                        continue
                    bins = quantized_tables(_tables(low_model, own, i, None), tops[i], 255).astype(np.int32)
                    acc = summed(word_tables(bins, narrowed), low)
                    cut, old = held.get(i, (255, None))
                    kept = np.flatnonzero(acc <= cut)
                    new = (block.ids[kept], acc[kept], block.raw[kept])
                    new = new if old is None else tuple(np.concatenate(x) for x in zip(old, new, strict=True))
                    upto = np.cumsum(np.bincount(new[1], minlength=256)[:256])
                    if upto[-1] >= r2:
                        cut = int(np.searchsorted(upto, r2))
                        near = new[1] <= cut
                        new = tuple(x[near] for x in new)
                    held[i] = (cut, new)
            for i, (_, (ids, bucket, raw)) in held.items():
                if len(ids):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), own.ids[i])), pa.array(ids), pa.array(bucket.astype(np.int64)), binary_array(raw)], schema=schema)

        part = codes.select("vec_id", "code").mapInArrow(run, "qid long, vec_id long, bucket long, code binary")
        out = part if out is None else out.unionByName(part)
    from vecspark.operators.scan import capped_buckets

    out = out.persist()  # read for the histogram and again for its codes
    return out.join(F.broadcast(capped_buckets(out, r2)), "qid").where("bucket <= cutoff").drop("cutoff")


def _low_tops(head: DataFrame, batch: Batch, low_model: PQModel, bits: int, model: PQModel) -> dict:
    """The greatest coarse distance of each query among the prefix's codes."""
    shared = head.sparkSession.sparkContext.broadcast(batch)
    k2 = model.coarse.shape[1]

    def run(batches):
        own = shared.value
        for block in blocks(batches, model.m, model.b):
            low = words_of(block.codes & (k2 - 1), bits)
            top = [float(summed(word_tables(_tables(low_model, own, i, None), bits), low).max()) for i in range(len(own.ids))]
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(top))), pa.array(top)], names=["place", "top"])

    found = head.select("vec_id", "code").mapInArrow(run, "place long, top double").groupBy("place").agg(F.max("top").alias("top"))
    return {r["place"]: r["top"] for r in found.collect()}


def rerank(found: DataFrame, queries: DataFrame, model: PQModel, r: int, entries: bool = False) -> DataFrame:
    """Fine distances of candidates, which carry their codes; a query's fine tables are filled entry by
    entry, as codes name them. ``entries``: (qid, filled), the entries that a query's candidates fill."""
    m, k, width = model.m, model.k, code_bytes(model.m, model.b)
    parts = []
    for batch in batches_of(queries):
        shared = found.sparkSession.sparkContext.broadcast(batch)
        schema = pa.schema([("qid", pa.int64()), ("filled", pa.int64())] if entries else [("qid", pa.int64()), ("vec_id", pa.int64()), ("dist", ARROW[model.number])])

        def run(batches, shared=shared, schema=schema):
            own = shared.value
            place = {int(q): i for i, q in enumerate(own.ids)}
            books = model.books.astype(float)
            tables: dict[int, tuple[np.ndarray, np.ndarray]] = {}
            for part in batches:
                if not part.num_rows:
                    continue
                qids, ids = part["qid"].to_numpy(zero_copy_only=False), part["vec_id"].to_numpy(zero_copy_only=False)
                codes = from_bytes(raw_codes(part, width), m, model.b).astype(np.intp)
                order = np.argsort(qids, kind="stable")
                first = np.flatnonzero(np.concatenate(([True], qids[order][1:] != qids[order][:-1])))
                out = []
                for a, z in zip(first, np.append(first[1:], len(order)), strict=True):
                    rows = order[a:z]
                    q = int(qids[rows[0]])
                    if q not in place:
                        continue
                    if q not in tables:
                        if len(tables) >= max(1, (64 << 20) // (9 * m * k)):
                            tables.clear()
                        tables[q] = (np.zeros((m, k)), np.zeros((m, k), bool))
                    t, known = tables[q]
                    x = np.split(model.rotated(own.x[place[q] : place[q] + 1])[0], m)
                    d = np.zeros(len(rows))
                    for j in range(m):
                        need = np.unique(codes[rows, j])
                        new = need[~known[j, need]]
                        t[j, new] = ((books[j][new] - x[j]) ** 2).sum(axis=1)
                        known[j, new] = True
                        d += t[j].take(codes[rows, j])
                    out.append((qids[rows], ids[rows], d))
                if out and not entries:
                    yield pa.RecordBatch.from_arrays([column(np.concatenate(c), f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)
            if entries and tables:
                yield pa.RecordBatch.from_arrays([pa.array(list(tables), pa.int64()), pa.array([int(k2.sum()) for _, k2 in tables.values()], pa.int64())], schema=schema)

        near = found.select("qid", "vec_id", "code")
        near = near.repartition("qid") if entries else near
        parts.append(near.mapInArrow(run, "qid long, filled long" if entries else f"qid long, vec_id long, dist {model.number}"))
    if entries:
        return parts[0]
    return union_topk(parts, r)
