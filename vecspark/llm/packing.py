"""Sequence packing by minimum bin slack over a histogram of lengths.

A document's ids are cut into full windows and a rest. How the rests fill windows
is planned on counts by length alone, at most ``capacity`` numbers whatever the
corpus: the longest length left opens a window, a bitset subset-sum over the lengths
left picks the multiset that fills it closest, backtracking gives the counts, and the
pattern is used as often as the counts allow. A gap that no multiset fills is closed
by cutting a piece, whose rest goes back to the counts; what is left at the end, less
than a window, is dealt to sequences whose lengths are powers of two. So no sequence
needs padding.

The rows then find their place without meeting in one task: a task ranks its rows by
length, per-task counts give each task's first rank, and ranks map to the plan's
intervals, a table bounded by the plan.

Defined cases: null text is empty and packs its end id alone; repeated rows are packed
each; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import deque

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecspark.llm.common import Scratch, arrow_rows, slices
from vecspark.llm.tokens import PieceTokenizer

CAPACITY = 2048
END_ID = 1
PLAN_FIELDS = "length int, lo long, hi long, seq long, seq_offset int, cut_start int, cut_length int"


def closest_fill(counts: dict[int, int], room: int) -> dict[int, int]:
    """The multiset of lengths, within ``counts``, whose sum is the greatest that ``room`` holds."""
    mask, reach, steps = (1 << (room + 1)) - 1, 1, []
    for length in sorted(counts, reverse=True):
        left, size = min(counts[length], room // length), 1
        while left > 0:
            take = min(size, left)
            grown = reach | (reach << (length * take)) & mask
            if grown != reach:
                steps.append((length, take, reach))
                reach = grown
            left, size = left - take, size * 2
        if reach >> room & 1:
            break
    total, chosen = reach.bit_length() - 1, {}
    for length, take, before in reversed(steps):
        if not before >> total & 1:  # unreachable without this step
            chosen[length] = chosen.get(length, 0) + take
            total -= length * take
    return chosen


class Stock:
    """Items by their current length, as runs: (source length, first rank, items, cut start)."""

    def __init__(self, counts: dict[int, int]):
        self.runs = {n: deque([(n, 0, c, 0)]) for n, c in counts.items() if c > 0}
        self.counts = {n: c for n, c in counts.items() if c > 0}

    def take(self, length: int, items: int) -> list[tuple[int, int, int, int]]:
        out, runs = [], self.runs[length]
        self.counts[length] -= items
        if not self.counts[length]:
            del self.counts[length]
        while items:
            source, first, have, cut = runs.popleft()
            used = min(have, items)
            out.append((source, first, used, cut))
            if have > used:
                runs.appendleft((source, first + used, have - used, cut))
            items -= used
        return out

    def put(self, length: int, run: tuple[int, int, int, int]) -> None:
        self.runs.setdefault(length, deque()).append(run)
        self.counts[length] = self.counts.get(length, 0) + run[2]


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int, int, int]]:
    """Rows of PLAN_FIELDS: item r of a length, lo <= r < hi, has its part [cut_start, +cut_length)
    in sequence seq + r - lo at seq_offset."""
    stock, out, sequence = Stock(counts), [], 0

    def place(runs, seq: int, offset: int, length: int) -> None:
        for source, first, items, cut in runs:
            out.append((source, first, first + items, seq, offset, cut, length))
            seq += items

    while sum(n * c for n, c in stock.counts.items()) >= capacity:
        longest = max(stock.counts)
        rest = dict(stock.counts)
        rest[longest] -= 1
        rest = {n: c for n, c in rest.items() if c}
        pattern = closest_fill(rest, capacity - longest) if longest < capacity else {}
        pattern[longest] = pattern.get(longest, 0) + 1
        gap = capacity - sum(n * c for n, c in pattern.items())
        need = dict(pattern)
        split = 0
        if gap:
            split = min(n for n, c in stock.counts.items() if c > pattern.get(n, 0))
            need[split] = need.get(split, 0) + 1
        times = min(stock.counts[n] // c for n, c in need.items())
        offset = 0
        for length in sorted(pattern, reverse=True):
            for _ in range(pattern[length]):
                place(stock.take(length, times), sequence, offset, length)
                offset += length
        if gap:
            runs = stock.take(split, times)
            place(runs, sequence, offset, gap)
            for source, first, items, cut in runs:
                stock.put(split - gap, (source, first, items, cut + gap))
        sequence += times
    left = [(source, first + i, cut, n) for n, runs in sorted(stock.runs.items(), reverse=True) for source, first, items, cut in runs for i in range(items)]
    total = sum(x[3] for x in left)
    rooms = deque((1 << b) for b in reversed(range(total.bit_length())) if total >> b & 1)
    offset = 0
    for source, rank, cut, n in left:
        while n:
            used = min(n, rooms[0] - offset)
            out.append((source, rank, rank + 1, sequence, offset, cut, used))
            cut, n, offset = cut + used, n - used, offset + used
            if offset == rooms[0]:
                rooms.popleft()
                sequence, offset = sequence + 1, 0
    return out


ITEMS = "doc_id long, text_hash long, start long, length int, ids_crc32 long, doc_tokens long, task int, rank long"


def _tokenize(path: str | None, capacity: int, end_id: int):
    kinds = {"long": pa.int64(), "int": pa.int32()}
    schema = pa.schema([(c.split()[0], kinds[c.split()[1]]) for c in ITEMS.split(", ")])

    def make():
        tokenizer, seen, task = PieceTokenizer(path, added=True), [0] * (capacity + 1), TaskContext.get().partitionId()

        def each(batch: pa.RecordBatch):
            for part in slices(batch, 1024):
                cols: list[list] = [[] for _ in schema]
                for doc_id, text, key in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    ids = tokenizer.ids(text or "")
                    ids = ids.tobytes() + end_id.to_bytes(4, "little")
                    n = len(ids) // 4
                    for start in range(0, n, capacity):
                        length = min(capacity, n - start)
                        row = (doc_id, key, start, length, zlib.crc32(ids[start * 4 : (start + length) * 4]), n, task, seen[length])
                        seen[length] += 1
                        for c, v in zip(cols, row, strict=True):
                            c.append(v)
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, schema, strict=True)], schema=schema)

        return each

    return make


def _cut_crc(path: str | None, end_id: int):
    schema = pa.schema([("task", pa.int32()), ("length", pa.int32()), ("rank", pa.int64()), ("cut_start", pa.int32()), ("cut_crc32", pa.int64())])

    def make():
        tokenizer = PieceTokenizer(path, added=True)

        def each(batch: pa.RecordBatch):
            crc = []
            for text, start, length in zip(batch["text"].to_pylist(), batch["start"].to_pylist(), batch["cut_length"].to_pylist(), strict=True):
                ids = tokenizer.ids(text or "").tobytes() + end_id.to_bytes(4, "little")
                crc.append(zlib.crc32(ids[start * 4 : (start + length) * 4]))
            yield pa.RecordBatch.from_arrays([batch[n] for n in ("task", "length", "rank", "cut_start")] + [pa.array(crc, pa.int64())], schema=schema)

        return each

    return make


PLAN_ROWS = 1_000_000  # intervals that may be broadcast; a longer plan is joined by a shuffle


def interval_table(spark: SparkSession, rows: list[tuple], counts: dict[int, int]) -> tuple[DataFrame, DataFrame]:
    """The plan for an equi-join: (length, width) and (length, slot, PLAN_FIELDS without length).

    The ranks of a length are cut into slots, as many as it has intervals, and an interval stands in
    each slot that it touches. So the table has at most three rows for each interval, and an item
    meets two of its length's intervals on average, and one for each further part it is cut into.
    """
    many: dict[int, int] = {}
    for row in rows:
        many[row[0]] = many.get(row[0], 0) + 1
    width = {n: max(1, -(-counts[n] // k)) for n, k in many.items()}
    spread = [(row[0], slot, *row[1:]) for row in rows for slot in range(row[1] // width[row[0]], (row[2] - 1) // width[row[0]] + 1)]
    table = spark.createDataFrame(spread, PLAN_FIELDS.replace("length int,", "length int, slot long,", 1))
    widths = spark.createDataFrame(list(width.items()), "length int, width long")
    return widths, F.broadcast(table) if len(spread) <= PLAN_ROWS else table


def pack_documents(spark: SparkSession, documents: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, vocabulary: str | None = None, broadcast_rows: int = 20_000) -> DataFrame:
    """(doc_id, text) -> one row per piece: where its ids lie in the document and in a sequence.

    ``vocabulary``: path of the ranks file (None: the installed public one).
    ``broadcast_rows``: up to so many cut pieces are joined to their texts by a broadcast.
    """
    scratch = Scratch(spark, "packing")
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    docs = docs.withColumn("text_hash", F.xxhash64("text"))
    items = scratch.keep(arrow_rows(docs, _tokenize(vocabulary, capacity, end_id), ITEMS), "items")
    tally = scratch.keep(items.groupBy("task", "length").agg(F.count("*").alias("n")), "tally")
    counts = {r["length"]: r["n"] for r in tally.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # capacity rows at most
    rows = plan(counts, capacity)
    cuts = sum(hi - lo for length, lo, hi, _, _, _, cut in rows if cut != length)
    widths, table = interval_table(spark, rows, counts)
    before = W.partitionBy("length").orderBy("task").rowsBetween(W.unboundedPreceding, -1)
    firsts = tally.select("task", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first"))
    placed = (
        items.join(firsts.join(F.broadcast(widths), "length"), ["task", "length"])  # widths: a row for each length
        .withColumn("r", F.col("rank") + F.col("first"))
        .withColumn("slot", F.expr("r div width"))
        .join(table, ["length", "slot"])
        .where("r >= lo and r < hi")
        .withColumn("start", F.col("start") + F.col("cut_start"))
        .withColumn("sequence_id", F.col("seq") + F.col("r") - F.col("lo"))
    )
    crc = F.col("ids_crc32")
    if cuts:
        part = placed.where("cut_length <> length").select("doc_id", "text_hash", "task", "length", "rank", "start", "cut_start", "cut_length")
        texts = docs.join(F.broadcast(part) if cuts <= broadcast_rows else part, on=[docs["doc_id"].eqNullSafe(part["doc_id"]), docs["text_hash"] == part["text_hash"]])
        found = arrow_rows(texts.select("text", "task", "length", "rank", "start", "cut_start", "cut_length"), _cut_crc(vocabulary, end_id), "task int, length int, rank long, cut_start int, cut_crc32 long")
        found = scratch.keep(found.dropDuplicates(["task", "length", "rank", "cut_start"]), "cuts")
        placed = placed.join(F.broadcast(found) if cuts <= broadcast_rows else found, ["task", "length", "rank", "cut_start"], "left")
        crc = F.when(F.col("cut_length") != F.col("length"), F.col("cut_crc32")).otherwise(crc)
    return placed.select("doc_id", "start", F.col("cut_length").cast("long").alias("length"), crc.alias("ids_crc32"), "doc_tokens", "sequence_id", F.col("seq_offset").cast("long").alias("offset"))
