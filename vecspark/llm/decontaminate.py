"""Benchmark decontamination by latent semantic retrieval.

Passages are weighted by TF-IDF over the benchmark's vocabulary, with document
frequencies counted over every passage of the corpus; every word keeps a positive
weight, however common its own leaks make it. A randomised SVD, whose products
run on the executors, gives a latent basis; it is fitted on all
passages together with all items. Every window of every document is then compared
by cosine with the items of like length, and every window that comes near one is a candidate.
What the latent space misses comes by a
second, exact route: a leak must hold some of its item's rarest words close together,
so every place that holds them is a candidate too. ``latent`` tells whether a candidate of the cosine
is a leak itself. Candidates of either route are held against the
item word by word: longest common subsequence, and whether the item's answer (its last
sentence) is there too, which a paraphrase must have. Items of more than 96 words are held
against the text whole, and in segments of which each alone is a leak if verbatim. An item of W window blocks is
looked for in stretches of W + 2 blocks that begin at any block.

The benchmark is the query set: it is read in blocks of a stated size, each held
against all documents; nothing of the documents is gathered on the driver but
matrices of the vocabulary's size.

Defined cases: null or empty texts and items match nothing; a repeated item or row
is compared on its own (an item id is reported once a document row); an empty
benchmark or table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
import string
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.llm.common import Scratch, arrow_rows, slices

MARKS = bytes(32 if chr(b) in string.punctuation else b for b in range(256))
BLOCK = 8  # words; windows begin at multiples of it
PASSAGE = 64  # words of the passages that frequencies and the basis are taken from
SEGMENT = 96  # words; longer items are searched in parts
LADDER = (4, 6, 8, 11, 14)  # window lengths in blocks, 15 at most
RARE = 4  # rare words of an item that must stand close together
FLOOR = 0.1  # weight of a word found in every passage
OFTEN = 512  # words found in most passages: a dense part of the products
PLACES = 25  # bits of the table of queries' words


def words_of(text: str) -> list[bytes]:
    """Lower-case words in UTF-8; ASCII marks count as white space."""
    return text.lower().encode().translate(MARKS).split()


def common_subsequence(a: list, b: list) -> int:
    """Length of the longest common subsequence, by bit-parallel rows."""
    places: dict = {}
    for i, w in enumerate(a):
        places[w] = places.get(w, 0) | 1 << i
    full = (1 << len(a)) - 1
    row = full
    for w in b:
        m = places.get(w, 0)
        if m:
            u = row & m
            row = ((row + u) | (row - u)) & full
    return len(a) - row.bit_count()


def answer_of(text: str) -> list[bytes]:
    """Words of the last sentence."""
    parts = [w for w in map(words_of, re.split(r"[.!?\n]+", text)) if w]
    return parts[-1] if parts else []


def least_words(n: int, share: float) -> int:
    """The least number of an item's ``n`` words that is the share."""
    return next((m for m in range(1, n + 1) if m / n >= share), n)


class Query:
    """An item or a segment of one: its words, the item's answer, the window it needs.

    Items longer than a segment are looked for whole too, by the exact route alone, in windows
    longer than the ladder's with a quarter of room.
    """

    def __init__(self, item_id: int, words: list[bytes], answer: list[bytes]):
        self.item_id, self.words, self.answer = item_id, words, answer
        need = -(-len(words) // BLOCK) + 1
        self.window = next((w for w in LADDER if w >= need), LADDER[-1])
        if len(words) > SEGMENT:
            self.window = need + -(-need // 4)

    def number(self, vocabulary: dict[bytes, int]) -> None:
        self.ids, self.answer_ids = ([vocabulary[w] for w in words] for words in (self.words, self.answer))
        self.distinct = frozenset(self.ids)


def queries_of(items: list[tuple[int, str | None]]) -> list[Query]:
    out = []
    for item_id, text in items:
        words = words_of(text or "")
        parts = [words[i : i + SEGMENT] for i in range(0, len(words), SEGMENT)]
        if len(parts) > 1 and len(parts[-1]) < SEGMENT // 2:
            parts[-1] = words[-SEGMENT:]
        for part in parts:
            out.append(Query(item_id, part, answer_of(text) if len(parts) == 1 else []))
        if len(parts) > 1:
            out.append(Query(item_id, words, answer_of(text)))
    return out


def _ids(vocabulary: dict[bytes, int], text: str | None) -> np.ndarray:
    return _numbers(vocabulary, words_of(text) if text else [])


def _numbers(vocabulary: dict[bytes, int], words: list[bytes]) -> np.ndarray:
    get = vocabulary.get
    return np.fromiter(map(get, words, repeat(0)), np.int32, len(words))


NUMBERS = "doc_id long, text_hash long, ids binary"


def _kind(size: int) -> type:
    """Numbers of a vocabulary of ``size`` words, 0 included, as they are kept."""
    return np.uint16 if size <= 1 << 16 else np.int32


def _numbered(vocabulary: dict[bytes, int]):
    """Word numbers of each text that has words: neither the products nor the search split texts again."""
    schema = pa.schema([("doc_id", pa.int64()), ("text_hash", pa.int64()), ("ids", pa.binary())])
    kind = _kind(len(vocabulary) + 1)

    def make():
        def each(batch: pa.RecordBatch):
            for part in slices(batch):
                ids = [_ids(vocabulary, text).astype(kind).tobytes() for text in part.column("text").to_pylist()]
                held = pa.array([len(x) > 0 for x in ids], pa.bool_())
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text_hash"), pa.array(ids, pa.binary())], schema=schema).filter(held)

        return each

    return make


def _passages(batch: pa.RecordBatch, size: int):
    """Tables of passages, a row of sorted word numbers each (0: no word of the vocabulary)."""
    for part in slices(batch):
        rows = [np.frombuffer(x, _kind(size)) for x in part.column("ids").to_pylist()]
        rows = [np.pad(x, (0, -len(x) % PASSAGE)) for x in rows if len(x)]
        if rows:
            yield np.sort(np.concatenate(rows).reshape(-1, PASSAGE), axis=1).astype(np.int32)


def _frequencies(size: int):
    schema = pa.schema([("term", pa.int32()), ("n", pa.int64())])

    def make():
        def each(batch: pa.RecordBatch):
            seen = np.zeros(size, np.int64)
            for table in _passages(batch, size):
                first = np.ones(table.shape, bool)
                first[:, 1:] = table[:, 1:] != table[:, :-1]
                seen += np.bincount(table[first & (table > 0)], minlength=size)
                seen[0] += len(table)  # term 0 counts the passages
            terms = np.flatnonzero(seen)
            yield pa.RecordBatch.from_arrays([pa.array(terms, pa.int32()), pa.array(seen[terms], pa.int64())], schema=schema)

        return each

    return make


SUMS = "part long, sums binary"
MERGES = 8  # tasks that add the tasks' sums


def _product(idf: np.ndarray, right: np.ndarray, often: np.ndarray):
    """Partial sums of AᵀA·right over a task's passages, one matrix for each task."""

    def run(batches):
        out = np.zeros_like(right)
        for batch in batches:
            for table in _passages(batch, len(idf)):
                for at in range(0, len(table), 2048):
                    _add_grams(out, table[at : at + 2048], idf, right, often)
        yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()], pa.int64()), pa.array([out.tobytes()], pa.binary())], names=["part", "sums"])

    return run


def _added(batches):
    """One sum of a task's matrices, in the order in which they come."""
    first, out = None, None
    for batch in batches:
        for part, sums in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            x = np.frombuffer(sums, np.float32)
            first, out = (part, x.copy()) if out is None else (first, np.add(out, x, out=out))
    if out is not None:
        yield pa.RecordBatch.from_arrays([pa.array([first], pa.int64()), pa.array([out.tobytes()], pa.binary())], names=["part", "sums"])


def _add_grams(out: np.ndarray, table: np.ndarray, idf: np.ndarray, right: np.ndarray, often: np.ndarray | None = None) -> None:
    """``_add_gram`` of all rows of a table of sorted word numbers. The words ``often`` found make up a
    dense matrix, which costs less than to gather their rows; the others are summed entry by entry."""
    ids, row = table.ravel(), np.repeat(np.arange(len(table)), table.shape[1])
    weighs = idf[ids] > 0
    ids, row = ids[weighs], row[weighs]
    if not len(ids):
        return
    first = np.flatnonzero(np.concatenate(([True], (ids[1:] != ids[:-1]) | (row[1:] != row[:-1]))))
    terms, row, tf = ids[first], row[first], np.diff(np.append(first, len(ids)))
    weight = ((1 + np.log(tf)) * idf[terms]).astype(np.float32)
    opens = np.flatnonzero(np.concatenate(([True], row[1:] != row[:-1])))
    place = np.repeat(np.arange(len(opens)), np.diff(np.append(opens, len(row))))
    weight /= np.sqrt(np.add.reduceat(weight * weight, opens))[place]
    along, dense = np.zeros((len(opens), right.shape[1]), np.float32), None
    if often is not None and len(often):
        slot = np.full(len(idf), -1)
        slot[often] = np.arange(len(often))
        own = slot[terms]
        held = own >= 0
        dense = np.zeros((len(opens), len(often)), np.float32)
        dense[place[held], own[held]] = weight[held]
        along += dense @ right[often]
        terms, place, weight = terms[~held], place[~held], weight[~held]
    if len(terms):
        opens = np.flatnonzero(np.concatenate(([True], place[1:] != place[:-1])))
        along[place[opens]] += np.add.reduceat(weight[:, None] * right.take(terms, axis=0), opens, axis=0)
        order = np.argsort(terms, kind="stable")
        back = weight[order][:, None] * along.take(place[order], axis=0)
        starts = np.flatnonzero(np.concatenate(([True], np.diff(terms[order]) != 0)))
        out[terms[order][starts]] += np.add.reduceat(back, starts, axis=0)
    if dense is not None:
        out[often] += dense.T @ along


def _add_gram(out: np.ndarray, ids: np.ndarray, idf: np.ndarray, right: np.ndarray) -> None:
    ids = ids[idf[ids] > 0]
    if len(ids):
        terms, tf = np.unique(ids, return_counts=True)
        row = ((1 + np.log(tf)) * idf[terms]).astype(np.float32)
        row /= np.sqrt((row * row).sum())
        out[terms] += row[:, None] * (row @ right[terms])


class Index:
    """Vocabulary, weights and latent vectors of the items."""

    def __init__(self, vocabulary: dict[bytes, int], latent: np.ndarray, queries: list[Query]):
        self.vocabulary, self.latent, self.queries = vocabulary, latent, queries
        for q in queries:
            q.number(vocabulary)
        vectors = np.stack([latent[_numbers(vocabulary, q.words)].sum(axis=0) for q in queries])
        vectors /= np.maximum(np.linalg.norm(vectors, axis=1, keepdims=True), 1e-9)
        self.vectors, self.groups = vectors.astype(np.float32), []
        for window in LADDER:
            own = [i for i, q in enumerate(queries) if q.window == window]
            if own:
                self.groups.append((window, own, np.ascontiguousarray(vectors[own].T, np.float32)))

    def near(self, docs: list[np.ndarray], least: float) -> list[tuple[int, int, int]]:
        """(document, query, block) of the windows that come near a query, the best of
        each run of neighbouring windows. Windows end with their document."""
        blocks = np.array([-(-len(d) // BLOCK) for d in docs])
        first = np.cumsum(blocks) - blocks
        n = int(blocks.sum())
        if not n:
            return []
        ids = np.concatenate([np.pad(d, (0, -len(d) % BLOCK)) for d in docs])
        ids = ids.reshape(n, BLOCK)
        held = np.zeros((n, self.latent.shape[1]), np.float32)
        for j in range(BLOCK):  # number 0, of words without weight, has the zero vector
            held += self.latent.take(ids[:, j], axis=0)
        # Zero rows between documents end their windows; sums of 2, 4 and 8 blocks make those of any window.
        owner = np.repeat(np.arange(len(docs)), blocks)
        rows = np.arange(n) + owner * LADDER[-1]
        apart = np.zeros((n + len(docs) * LADDER[-1], held.shape[1]), np.float32)
        apart[rows] = held
        sums = {1: apart}
        for size in (1, 2, 4):
            sums[2 * size] = sums[size].copy()
            sums[2 * size][:-size] += sums[size][size:]
        out = []
        for window, own, vectors in self.groups:
            sizes = [size for size in (8, 4, 2, 1) if window & size]
            x = sums[sizes[0]].take(rows, axis=0)
            for i, size in enumerate(sizes[1:], 1):
                x += sums[size].take(rows + sum(sizes[:i]), axis=0)
            length = np.maximum(np.sqrt(np.einsum("ij,ij->i", x, x)), 1e-4)
            cosine = x @ vectors
            hits = np.flatnonzero((cosine >= (least * length)[:, None]).ravel())
            if not len(hits):
                continue
            hits = hits[np.argsort(hits % len(own), kind="stable")]
            place, which = np.divmod(hits, len(own))
            value = cosine[place, which] / length[place]
            opens = np.concatenate(([True], (np.diff(which) != 0) | (np.diff(place) != 1) | (np.diff(owner[place]) != 0)))
            run = np.cumsum(opens) - 1
            order = np.lexsort((place, -value, run))
            best = order[np.searchsorted(run[order], np.arange(run[-1] + 1))]
            doc = owner[place[best]]
            queries = np.array(own)[which[best]]
            out += list(zip(doc.tolist(), queries.tolist(), (place[best] - first[doc]).tolist(), strict=True))
        return out

    def set_rare(self, df: np.ndarray, verbatim: float, paraphrase: float) -> None:
        """Postings (term -> queries) of the words of which a leak must hold some: at most n - t of
        an item's n words are missing from it, so of its n - t + k rarest k at least are there."""
        lists: list[list[int]] = [[] for _ in range(len(self.vocabulary) + 1)]
        self.window = np.array([q.window for q in self.queries], np.int64)
        self.need, self.span = np.zeros(len(self.queries), np.int64), np.zeros(len(self.queries), np.int64)
        for i, q in enumerate(self.queries):
            t = least_words(len(q.words), min(verbatim, paraphrase) if q.answer else verbatim) if q.words else 0
            self.need[i], self.span[i] = min(RARE, t), (q.window + 2) * BLOCK
            terms = _numbers(self.vocabulary, q.words)
            for term in np.unique(terms[np.argsort(df[terms], kind="stable")[: len(terms) - t + self.need[i]]]):
                lists[term].append(i)
        self.listed = np.array([len(x) for x in lists])
        self.offset = np.cumsum(self.listed) - self.listed
        self.posting = np.array([i for x in lists for i in x], np.int64)

    def rare(self, docs: list[np.ndarray]) -> list[tuple[int, int, int, int]]:
        """(document, query, first block, last block): runs of all the stretches that hold enough of a
        query's rare words."""
        ids = np.concatenate(docs) if docs else np.zeros(0, np.int32)
        place = np.flatnonzero(self.listed[ids])
        if not len(place):
            return []
        times = self.listed[ids[place]]
        nth = np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
        query = self.posting[np.repeat(self.offset[ids[place]], times) + nth]
        sizes = np.array([len(d) for d in docs])
        first = np.cumsum(sizes) - sizes
        doc = np.repeat(np.repeat(np.arange(len(docs)), sizes)[place], times)
        place = np.repeat(place, times) - first[doc]
        order = np.lexsort((place, doc, query))
        query, doc, place = query[order], doc[order], place[order]
        at = np.arange(len(query))
        other = at + self.need[query] - 1
        at = at[other < len(query)]
        other = other[at]
        at = at[(query[other] == query[at]) & (doc[other] == doc[at]) & (place[other] - place[at] < self.span[query[at]])]
        if not len(at):
            return []
        # Stretches from block - 1 to block + window that hold both words: runs of blocks, in order.
        q, d = query[at], doc[at]
        low = np.maximum(0, place[at + self.need[q] - 1] // BLOCK - self.window[q])
        high = place[at] // BLOCK + 1
        some = low <= high
        q, d, low, high = q[some], d[some], low[some], high[some]
        if not len(q):
            return []
        opens = np.concatenate(([True], (q[1:] != q[:-1]) | (d[1:] != d[:-1]) | (low[1:] > high[:-1] + 1)))
        first = np.flatnonzero(opens)
        return list(zip(d[first].tolist(), q[first].tolist(), np.minimum.reduceat(low, first).tolist(), np.maximum.reduceat(high, first).tolist(), strict=True))

    def set_words(self, verbatim: float, paraphrase: float) -> None:
        """The words of each query as a table, and how many of its words a leak holds at least. Pairs of query and word
        that share a place of the table, where they are many, only raise a count."""
        self.size = len(self.vocabulary) + 1
        self.least = np.array([least_words(len(q.ids), min(verbatim, paraphrase) if q.answer_ids else verbatim) for q in self.queries], np.int64)
        pairs = np.concatenate([np.zeros(0, np.int64), *[i * self.size + np.array(sorted(q.distinct), np.int64) for i, q in enumerate(self.queries)]])
        self.mask = (1 << min(PLACES, max(1, len(self.queries) * self.size - 1).bit_length())) - 1
        self.holds = np.zeros(self.mask + 1, np.uint8)
        self.holds[pairs & self.mask] = 1

    def enough(self, docs: list[np.ndarray], found: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
        """The candidates of ``near`` whose stretch, from block - 1 to block + window, holds as many words of the
        query as its longest common subsequence must have; the others cannot be leaks."""
        if not found:
            return []
        doc, query, block = np.array(found, np.int64).T
        sizes = np.array([len(d) for d in docs])
        ends = np.cumsum(sizes)
        words, out = np.append(np.concatenate(docs), 0).astype(np.int64), np.zeros(len(found), bool)
        low = (ends - sizes)[doc] + np.maximum(0, (block - 1) * BLOCK)
        high = np.minimum(ends[doc], (ends - sizes)[doc] + (block + self.window[query] + 1) * BLOCK)
        for window in np.unique(self.window[query]):
            own = np.flatnonzero(self.window[query] == window)
            for part in np.split(own, range(4096, len(own), 4096)):
                at = low[part][:, None] + np.arange((window + 2) * BLOCK)
                ids = words.take(np.where(at < high[part][:, None], at, len(words) - 1))  # 0, of no query, beyond the end
                out[part] = self.holds.take(ids + (query[part] * self.size)[:, None] & self.mask).sum(axis=1, dtype=np.int32) >= self.least[query[part]]
        return [found[i] for i in np.flatnonzero(out).tolist()]

    def cosine(self, ids: np.ndarray, query: int) -> float:
        x = self.latent[ids].sum(axis=0)
        return float(x @ self.vectors[query] / max(float(np.linalg.norm(x)), 1e-4))


def fit_basis(gram, size: int, items: list[np.ndarray], idf: np.ndarray, rank: int, rounds: int, seed: int = 11) -> np.ndarray:
    """Orthonormal basis (terms x rank) of the leading right singular vectors.

    ``gram(x)`` gives AᵀA·x over all passages; the items add theirs here.
    """
    rank = min(rank, size)

    def product(x: np.ndarray) -> np.ndarray:
        out = gram(x)
        for ids in items:
            _add_gram(out, ids, idf, x)
        return out

    q = np.linalg.qr(np.random.default_rng(seed).normal(size=(size, min(size, rank + 8))).astype(np.float32))[0]
    for _ in range(rounds):
        q = np.linalg.qr(product(np.ascontiguousarray(q, np.float32)))[0]
    y = product(np.ascontiguousarray(q, np.float32))
    values, vectors = np.linalg.eigh(q.T @ y)
    return np.ascontiguousarray((q @ vectors[:, np.argsort(-values)[:rank]]), np.float32)


def build_index(spark: SparkSession, scratch: Scratch, documents: DataFrame, items: list[tuple[int, str | None]], rank: int, common: float, verbatim: float, paraphrase: float, rounds: int = 2) -> tuple[Index, DataFrame] | None:
    """The index of a block of items, and the documents' word numbers in its vocabulary."""
    queries = queries_of(items)
    vocabulary: dict[bytes, int] = {}
    for q in queries:
        for w in q.words:
            vocabulary.setdefault(w, len(vocabulary) + 1)
    if not vocabulary:
        return None
    size = len(vocabulary) + 1
    numbers = scratch.keep(arrow_rows(documents.select("doc_id", "text_hash", "text"), _numbered(vocabulary), NUMBERS), "numbers")
    counts = arrow_rows(numbers, _frequencies(size), "term int, n long").groupBy("term").agg(F.sum("n").alias("n"))
    df = np.zeros(size)
    for r in counts.collect():  # a row for each word of the benchmark at most
        df[r["term"]] = r["n"]
    passages, df[0] = max(1.0, df[0]), 0
    idf = (np.log((passages + 1) / (df + 1)) + FLOOR).astype(np.float32)
    idf[df > common * passages] = FLOOR
    idf[0] = 0
    often = np.argsort(-df, kind="stable")[:OFTEN]
    often = np.sort(often[idf[often] > 0])

    def gram(x: np.ndarray) -> np.ndarray:
        out = np.zeros_like(x)
        sums = numbers.select("ids").mapInArrow(_product(idf, x, often), SUMS)
        merged = sums.repartition(MERGES, F.col("part") % MERGES).sortWithinPartitions("part").mapInArrow(_added, SUMS)
        for r in sorted(merged.collect(), key=lambda r: r["part"]):  # a matrix for each merging task
            out += np.frombuffer(r["sums"], np.float32).reshape(x.shape)
        return out

    basis = fit_basis(gram, size, [_numbers(vocabulary, q.words) for q in queries], idf, rank, rounds)
    index = Index(vocabulary, basis * idf[:, None], queries)
    index.set_rare(df, verbatim, paraphrase)
    return index, numbers


LEAKS = "doc_id long, text_hash long, item_id long, cosine double, common double, answered boolean, first_word long, last_word long, latent boolean"


def leaks_at(q: Query, ids: list[int], runs: list[tuple[int, int]], verbatim: float, paraphrase: float) -> list[tuple]:
    """(share, answered, block, first word, end) of the stretches that begin in runs of blocks
    and hold the query. ``ids`` are a text's words by number; words of no item are 0, which no query has."""
    n, out, size = len(q.ids), [], len(ids)
    least = least_words(n, min(verbatim, paraphrase) if q.answer_ids else verbatim)
    # A common subsequence of that length misses no more than the rest of the query's words.
    distinct, enough = q.distinct, len(q.distinct) - (n - least)
    for first, last in runs:
        # What all of a run's stretches hold together bounds each.
        whole = ids[max(0, (first - 1) * BLOCK) : min(size, (last + q.window + 1) * BLOCK)]
        if len(distinct.intersection(whole)) < enough or last > first and common_subsequence(q.ids, whole) < least:
            continue
        for block in range(first, last + 1):
            low, high = max(0, (block - 1) * BLOCK), min(size, (block + q.window + 1) * BLOCK)
            region = ids[low:high]
            if last > first and len(distinct.intersection(region)) < enough:
                continue
            share = common_subsequence(q.ids, region) / n
            if share < verbatim and share < paraphrase:
                continue
            answered = bool(q.answer_ids) and common_subsequence(q.answer_ids, region) >= 0.8 * len(q.answer_ids)
            if share >= verbatim or answered:
                out.append((share, answered, block, low, high))
    return out


def _search(index: Index, least: float, verbatim: float, paraphrase: float):
    fields = [("doc_id", pa.int64()), ("text_hash", pa.int64()), ("item_id", pa.int64()), ("cosine", pa.float64()), ("common", pa.float64()), ("answered", pa.bool_()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("latent", pa.bool_())]
    schema, kind = pa.schema(fields), _kind(len(index.latent))

    def make():
        index.set_words(verbatim, paraphrase)

        def each(batch: pa.RecordBatch):
            for part in slices(batch, 64):
                ids, hashes, held = (c.to_pylist() for c in part.columns)
                best: dict[tuple[int, int], tuple] = {}
                numbers = [np.frombuffer(x, kind).astype(np.int32) for x in held]
                routes: dict[tuple[int, int, bool], list[tuple[int, int]]] = {}
                for at, query, block in index.enough(numbers, index.near(numbers, least)):
                    routes.setdefault((at, query, True), []).append((block, block))
                for at, query, first, last in index.rare(numbers):
                    routes.setdefault((at, query, False), []).append((first, last))
                lists: dict[int, list[int]] = {}
                latent: set[tuple[int, int]] = set()
                for (at, query, by_cosine), runs in routes.items():
                    q = index.queries[query]
                    if at not in lists:
                        lists[at] = numbers[at].tolist()
                    for share, answered, block, low, high in leaks_at(q, lists[at], runs, verbatim, paraphrase):
                        if by_cosine:
                            latent.add((at, q.item_id))
                        old = best.get((at, q.item_id))
                        if old is None or (old[4], -old[6], -old[7]) < (share, -low, -high):
                            cosine = index.cosine(numbers[at][block * BLOCK : (block + q.window) * BLOCK], query)
                            best[at, q.item_id] = (ids[at], hashes[at], q.item_id, cosine, share, answered, low, high)
                rows = [(*row, key in latent) for key, row in best.items()]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

        return each

    return make


def leaks(spark: SparkSession, documents: DataFrame, benchmark: DataFrame, rank: int = 64, common: float = 0.05, least: float = 0.6, verbatim: float = 0.8, paraphrase: float = 0.55, block: int = 5000) -> DataFrame:
    """(doc_id, text) and (item_id, text) -> a row for each document row and item found in it; ``text_hash``
    (xxhash64) tells rows of one id apart.

    ``rank``: latent dimensions; ``common``:
    share of passages from which a word weighs the floor only; ``least``: cosine of a
    candidate of the latent route;
    ``verbatim``: share of the item's words in order that is a leak; ``paraphrase``: share
    that is one where the answer is there too; ``block``: items searched for at a time.
    """
    scratch = Scratch(spark, "decontaminate")
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("text_hash", F.xxhash64("text"))
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).distinct().orderBy("item_id", "text")
    out, part = spark.createDataFrame([], LEAKS), []

    def found(part: list) -> DataFrame | None:
        built = build_index(spark, scratch, docs, part, rank, common, verbatim, paraphrase)
        return built and arrow_rows(built[1], _search(built[0], least, verbatim, paraphrase), LEAKS)

    for r in items.toLocalIterator():
        part.append((r["item_id"], r["text"]))
        if len(part) == block:
            got, part = found(part), []
            out = out.unionByName(got) if got is not None else out
    if part and (got := found(part)) is not None:
        out = out.unionByName(got)
    return out
