"""Near-duplicate documents by bottom-k sketches of word shingles.

One 64-bit hash of every distinct shingle orders a document's set; its k least
values are the sketch. Documents with equal sets are one class from the start.
Inverted lists of the sketch values generate candidates, the k least values of a
pair's union estimate its similarity and filter, and the full sets, shingled anew
from the texts, decide.

Lists are never expanded into all their pairs. Of its values, a document is listed
under the rarest only: so many that two similar documents cannot share all they must
share among the others (the prefix filter). Each list pairs its members with its least
one, and the links found so far give components; a list within one component is done.
Lists that still hold several components give the pairs across them, unless that would
be more than ``partners`` for each member. The members of those few lists are taken
again with their full sets, where the rarest fifth suffices. A pair also counts only if
both hold enough values from the shared one on, in the common order of rarity (the
positional filter), so that documents that are alike in a shared passage alone, or not
quite alike enough, no longer meet.

Sketches of a pair of similarity 0.8 overlap less than the filter asks with a chance
of 1e-9 (``least_overlap``); sets smaller than a sketch are known in full.

Defined cases: null, empty or blank text has no shingles and links with nothing;
fewer words than a shingle make one shingle; a repeated row is a row of its own;
a null doc_id never is a component's id unless its class has no other; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.llm.common import Scratch, arrow_rows, slices

SKETCH = 64


def _mix(h: np.ndarray) -> np.ndarray:
    """The finalizer of a 64-bit generator: every input bit reaches every output bit."""
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


class Words(dict):
    """64-bit hashes of words, kept up to a limit."""

    def __missing__(self, word: bytes) -> int:
        import xxhash

        value = xxhash.xxh3_64_intdigest(word)
        if len(self) >= 400_000:
            self.clear()
        if len(word) <= 64:
            self[word] = value
        return value


class Shingler:
    """Sorted distinct 63-bit hashes of a text's shingles of ``width`` words."""

    def __init__(self, width: int):
        self.width, self.words = width, Words()
        odd = np.arange(1, width + 1, dtype=np.uint64)
        self.factors = _mix(odd * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)

    def __call__(self, raw: bytes | None) -> np.ndarray:
        words = raw.lower().split() if raw else []  # of bytes: A-Z only, and the six ASCII white spaces
        if not words:
            return np.zeros(0, np.uint64)
        table = self.words
        ids = np.fromiter([table[w] for w in words], np.uint64, len(words))
        n = max(1, len(ids) - self.width + 1)
        total = np.full(n, min(len(ids), self.width), np.uint64)
        for i in range(min(self.width, len(ids))):
            total += ids[i : i + n] * self.factors[i]
        return np.unique(_mix(total) >> np.uint64(1))


SETS = "doc_id long, n_shingles long, print_a long, print_b long, sketch array<long>"


def _sets(width: int, k: int):
    schema = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("print_a", pa.int64()), ("print_b", pa.int64()), ("sketch", pa.list_(pa.int64()))])

    def make():
        shingler = Shingler(width)

        def each(batch: pa.RecordBatch):
            for part in slices(batch):
                sizes, a, b, sketches = [], [], [], []
                for raw in part.column(1).to_pylist():
                    got = shingler(raw)
                    sizes.append(len(got))
                    a.append(int(np.bitwise_xor.reduce(got).view(np.int64)) if len(got) else 0)
                    b.append(int(_mix(got).sum(dtype=np.uint64).view(np.int64)) if len(got) else 0)
                    sketches.append(got[:k].view(np.int64))
                offsets = np.cumsum([0] + [len(s) for s in sketches]).astype(np.int32)
                values = pa.array(np.concatenate(sketches) if sketches else np.zeros(0, np.int64))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64()), pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), values)], schema=schema)

        return each

    return make


def _verify(width: int, percent: int):
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def make():
        shingler, recent = Shingler(width), {}

        def shingles(doc_id: int, raw: bytes) -> np.ndarray:
            if doc_id not in recent:
                if len(recent) >= 32:
                    recent.pop(next(iter(recent)))
                recent[doc_id] = shingler(raw)
            return recent[doc_id]

        def each(batch: pa.RecordBatch):
            for part in slices(batch):
                keep_a, keep_b = [], []
                for a, b, x, y in zip(*(part[n].to_pylist() for n in ("a", "b", "text_a", "text_b")), strict=True):
                    u, v = shingles(a, x), shingles(b, y)
                    both = len(np.intersect1d(u, v, assume_unique=True))
                    if both and 100 * both >= percent * (len(u) + len(v) - both):
                        keep_a.append(a)
                        keep_b.append(b)
                yield pa.RecordBatch.from_arrays([pa.array(keep_a, pa.int64()), pa.array(keep_b, pa.int64())], schema=schema)

        return each

    return make


def least_overlap(k: int, share: float, risk: float = 1e-9) -> int:
    """The greatest m such that k draws of chance ``share`` give fewer than m with probability under ``risk``."""
    total = 0.0
    for m in range(k + 1):
        total += math.comb(k, m) * share**m * (1 - share) ** (k - m)
        if total >= risk:
            return m
    return k


def components(scratch: Scratch, links: DataFrame) -> DataFrame:
    """(a, b) links -> (node, component): the least node that each linked node reaches.

    Alternates two steps on written tables: every node points its greater neighbours,
    then its lesser ones, at the least node it knows; ends when nothing changes.
    """
    edges = scratch.keep(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "edges")
    state = None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = scratch.keep(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")), "least")
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = scratch.keep(large.where("u <> v").distinct(), "large")
        small = scratch.keep(large.groupBy("u").agg(F.min("v").alias("m")), "small")
        moved = large.join(small, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(small.select("u", F.col("m").alias("v")))
        edges = scratch.keep(moved.where("u <> v").distinct(), "edges")
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if tuple(now) == state:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
        state = tuple(now)


def _full_sets(width: int):
    schema = pa.schema([("doc", pa.int64()), ("n", pa.int64()), ("value", pa.int64())])

    def make():
        shingler = Shingler(width)

        def each(batch: pa.RecordBatch):
            for part in slices(batch, 64):
                ids = part.column(0).to_pylist()
                sets = [shingler(raw) for raw in part.column(1).to_pylist()]
                sizes = [len(x) for x in sets]
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, sizes), pa.int64()), pa.array(np.repeat(sizes, sizes), pa.int64()), pa.array(np.concatenate(sets).view(np.int64))], schema=schema)

        return each

    return make


def rare_first(index: DataFrame, scratch: Scratch, needed: str, name: str) -> DataFrame:
    """(doc, n, held, value) -> (value, doc, n, held, place): each document's rarest values that
    others share too, and how many of its values come before each in the common order.

    ``held``: the values that the document has in the index; ``needed``: of these, the SQL
    expression for how many it must share with a similar document. Among the
    held - needed + 1 rarest, a similar pair shares one.
    """
    shared = scratch.keep(index.groupBy("value").agg(F.count("*").alias("members")).where("members > 1"), f"{name}-shared")
    ranked = index.join(shared, "value").groupBy("doc", "n", "held").agg(F.array_sort(F.collect_list(F.struct("members", "value"))).alias("values"))
    # Values that no other document has are the rarest; they use up places and meet nobody.
    alone = F.col("held") - F.size("values")
    places = (F.col("held") - F.expr(needed) + 1 - alone).cast("int")
    kept = ranked.withColumn("alone", alone).withColumn("places", places).where("places > 0").select("doc", "n", "held", "alone", F.posexplode(F.slice("values", F.lit(1), F.col("places"))).alias("i", "x"))
    return scratch.keep(kept.select("x.value", "doc", "n", "held", (F.col("alone") + F.col("i")).cast("long").alias("place")), f"{name}-keys")


def near_duplicates(spark: SparkSession, documents: DataFrame, width: int = 5, percent: int = 80, k: int = SKETCH, partners: int = 4) -> DataFrame:
    """(doc_id, text) -> (doc_id, n_shingles, component_id, kept), a row per row.

    ``width``: words of a shingle; ``percent``: least similarity of a link;
    ``k``: values of a sketch; ``partners``: cross-component pairs for each member
    above which a list's members are compared by their full sets.
    """
    scratch = Scratch(spark, "minhash")
    raw = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").cast("binary").alias("text"))
    sets = scratch.keep(arrow_rows(raw, _sets(width, k), SETS), "sets")
    prints = ["n_shingles", "print_a", "print_b"]
    # One representative for each distinct set; its sketch is that of any member.
    classes = scratch.keep(sets.where("n_shingles > 0").groupBy(*prints).agg(F.min("doc_id").alias("rep"), F.first("sketch").alias("sketch")), "classes")
    named = classes.where("rep is not null")
    floor = least_overlap(k, percent / 100)

    def alike(a: str, b: str) -> F.Column:
        return F.expr(f"100 * least({a}, {b}) >= {percent} * greatest({a}, {b})")

    sketches = named.select("rep", "sketch")

    def texts_of(ids: DataFrame, name: str) -> DataFrame:
        """(doc_id, text) of the documents named, once each."""
        return scratch.keep(raw.where("doc_id is not null").join(ids, "doc_id", "left_semi").dropDuplicates(["doc_id"]), f"{name}-texts")

    def confirmed(pairs: DataFrame, name: str) -> DataFrame:
        """Pairs (a, b) whose union sketch, then whose full sets are similar enough."""
        joined = pairs.join(sketches.select(F.col("rep").alias("a"), F.col("sketch").alias("sketch_a")), "a").join(sketches.select(F.col("rep").alias("b"), F.col("sketch").alias("sketch_b")), "b")
        union = F.slice(F.array_sort(F.array_union("sketch_a", "sketch_b")), 1, k)
        likely = joined.select("a", "b", F.size(F.array_intersect(F.array_intersect("sketch_a", "sketch_b"), union)).alias("o"), F.size(union).alias("u"))
        # A union smaller than a sketch is known in full.
        likely = scratch.keep(likely.where(f"(u >= {k} and o >= {floor}) or (u < {k} and 100 * o >= {percent} * u)").select("a", "b"), f"{name}-likely")
        ids = scratch.keep(likely.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct(), f"{name}-ids")
        texts = texts_of(ids, name)
        wide = likely.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a")), "a").join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b")), "b")
        return scratch.keep(arrow_rows(wide, _verify(width, percent), "a long, b long"), f"{name}-links")

    # A sketch holds n values or k; a set of fewer than k may face one cut to k.
    needed = f"case when n >= {k} then {floor} else least(ceil({percent} * n / 100), {k} - ceil((100 - {percent}) * n / {percent})) end"
    index = named.select(F.col("rep").alias("doc"), F.col("n_shingles").alias("n"), F.size("sketch").alias("held"), F.explode("sketch").alias("value"))
    keys = rare_first(index, scratch, needed, "sketch")
    lists = scratch.keep(keys.groupBy("value").agg(F.min(F.struct("doc", "n")).alias("first"), F.count("*").alias("members")).where("members > 1"), "lists")
    members = scratch.keep(keys.join(lists, "value"), "members")
    star = members.where("doc <> first.doc").where(alike("n", "first.n")).select(F.col("first.doc").alias("a"), F.col("doc").alias("b"))
    tried = scratch.keep(star.distinct(), "stars")
    links = confirmed(tried, "star")
    linked = components(scratch, links)

    # What lists hold beside one component.
    owned = members.select("value", "doc", "n", "held", "place").join(linked.select(F.col("node").alias("doc"), "component"), "doc", "left").withColumn("component", F.coalesce("component", "doc"))
    owned = scratch.keep(owned, "owned")
    parts = owned.groupBy("value", "component").agg(F.count("*").alias("c")).groupBy("value").agg(F.sum("c").alias("all"), F.sum(F.col("c") * F.col("c")).alias("within"), F.count("*").alias("parts"))
    mixed = scratch.keep(parts.where("parts > 1").select("value", ((F.col("all") * F.col("all") - F.col("within")) / F.col("all") > partners).alias("hot")), "mixed")

    def across(frame: DataFrame, shared: str) -> DataFrame:
        """Pairs of a list's members in different components that can still share enough: what a
        document has from the list's value on, in the common order, must reach ``shared``, SQL for
        what similar sets share (the first value that a pair shares passes this)."""
        x, y = (frame.select("value", *[F.col(c).alias(f"{c}_{s}") for c in ("doc", "n", "held", "place", "component")]) for s in "ab")
        able = F.expr(f"least(held_a - place_a, held_b - place_b) >= {shared}")
        met = x.join(y, "value").where("doc_a < doc_b and component_a <> component_b").where(alike("n_a", "n_b")).where(able)
        return met.select(F.col("doc_a").alias("a"), F.col("doc_b").alias("b"))

    columns = ["value", "doc", "n", "held", "place", "component"]
    both = f"ceil({percent} * (n_a + n_b) / (100 + {percent}))"
    sketched = f"case when least(n_a, n_b) >= {k} then {floor} when greatest(n_a, n_b) < {k} then {both} else {k} - ceil((100 - {percent}) * least(n_a, n_b) / {percent}) end"
    pairs = across(scratch.keep(owned.join(mixed.where("not hot"), "value").select(*columns), "cold"), sketched)
    crowded = scratch.keep(owned.join(mixed.where("hot"), "value").select("doc", "component").distinct(), "crowded")
    if not crowded.isEmpty():
        full = scratch.keep(arrow_rows(texts_of(crowded.select(F.col("doc").alias("doc_id")), "crowded"), _full_sets(width), "doc long, n long, value long"), "full").withColumn("held", F.col("n"))
        rare = rare_first(full, scratch, f"ceil({percent} * n / 100)", "full")
        pairs = pairs.unionByName(across(scratch.keep(rare.join(crowded, "doc").select(*columns), "crowded-keys"), both))
    pairs = scratch.keep(pairs.distinct().join(tried, ["a", "b"], "left_anti"), "across")
    more = confirmed(pairs, "across")
    final = linked if more.isEmpty() else components(scratch, links.unionByName(more))

    reps = classes.select(*prints, "rep").join(final.select(F.col("node").alias("rep"), "component"), "rep", "left")
    reps = scratch.keep(reps.select(*prints, F.coalesce("component", "rep").alias("component")), "reps")
    out = sets.drop("sketch").join(reps, prints, "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id")).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))
