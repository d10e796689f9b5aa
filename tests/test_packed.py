"""Packed kernels against the declarative scans, on several blocks and tasks."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecspark.operators import codebook, encode, index, packed, scan
from vecspark.operators.codebook import PQModel


def vectors(spark, n=6000, d=8, seed=1):
    rng = np.random.default_rng(seed)
    x = np.clip(rng.normal(2048, 700, (n, d)), 0, 4095).astype(int)
    base = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id long, e array<long>").repartition(5).cache()
    return base.where("vec_id % 300 = 0").select(F.col("vec_id").alias("qid"), "e"), base, x


def random_model(x, m, b, seed=2) -> PQModel:
    rows = x[np.random.default_rng(seed).choice(len(x), 1 << b, replace=len(x) < 1 << b)]
    return PQModel(m, b, x.shape[1], np.stack(np.split(rows, m, axis=1)))


def rows_of(frame):
    return sorted((r["qid"], r["rk"], r["vec_id"], round(r["dist"], 6)) for r in frame.collect())


@pytest.mark.parametrize("m,b", [(8, 8), (8, 4), (4, 6), (2, 3), (8, 1)])
def test_packed_codes_round_trip_and_plain_scan(spark, m, b):
    q, base, x = vectors(spark)
    model = random_model(x, m, b)
    codes = encode.encode_pq(base, model)
    small = packed.encode_packed(base, model)
    assert small.exceptAll(packed.pack(codes, m, b)).isEmpty() and small.count() == 6000
    assert packed.unpack(small, m, b).select("vec_id", *[F.col(f"c{j}").cast("long") for j in range(m)]).exceptAll(codes).isEmpty()
    want = rows_of(scan.adc_topk(codes, index.lookup_tables(q, model), m, 20))
    assert rows_of(packed.plain_scan(small, q, model, 20)) == want
    assert rows_of(packed.plain_scan(small, q, model, 20, rows=700)) == want


def test_wide_parts(spark):
    q, base, x = vectors(spark, 2000)
    model = random_model(x, 2, 12)
    codes = encode.encode_pq(base, model)
    small = packed.encode_packed(base, model)
    assert rows_of(packed.plain_scan(small, q, model, 9)) == rows_of(scan.adc_topk(codes, index.lookup_tables(q, model), 2, 9))


@pytest.mark.parametrize("g,low_bits", [(0, 4), (1, 4), (3, 4), (4, 4), (8, 4), (2, 6), (4, 6)])
def test_bounded_scan_is_the_plain_scan(spark, monkeypatch, g, low_bits):
    q, base, x = vectors(spark)
    model = codebook.renumber(random_model(x, 8, 8), 1 << (8 - low_bits))[0]
    small = packed.encode_packed(base, model).cache()
    want = rows_of(packed.plain_scan(small, q, model, 10))
    laid = packed.grouped(small, model, g, low_bits).cache()
    assert laid.count() == 6000
    tops = packed.prefix_tops(small, q, model, 10)
    assert rows_of(packed.bounded_scan(laid, q, model, 10, g, tops, low_bits)) == want
    assert rows_of(packed.bounded_scan(laid, q, model, 10, g, None, low_bits)) == want
    stats = packed.bounded_scan(laid, q, model, 10, g, tops, low_bits, stats=True).agg(F.sum("codes").alias("codes"), F.sum("bounded").alias("bounded"), F.sum("summed").alias("summed")).first()
    assert stats["codes"] == 6000 * 20 and stats["summed"] <= stats["bounded"] <= stats["codes"]
    if g in (3, 4) and low_bits == 4:
        assert stats["summed"] < 0.6 * stats["codes"]


@pytest.mark.parametrize("mode", ["full", "quant_only"])
def test_bounded_counts_are_the_marks(spark, mode):
    q, base, x = vectors(spark, 3000)
    model = random_model(x, 8, 8)
    codes = encode.encode_pq(base, model)
    marks = scan.bounded_marks(scan.with_prefix(codes, 0.01, None, 10), index.lookup_tables(q, model), 8, 10, 2, mode=mode)
    want = sorted(tuple(r) for r in scan.pruned_counts(marks).select("qid", "n_codes", "n_pruned").collect())
    got = sorted(tuple(r) for r in packed.bounded_counts(packed.encode_packed(base, model), q, model, 10, 2, 0.01, mode).collect())
    assert got == want


def test_lists_and_nibbles(spark):
    q, base, x = vectors(spark)
    coarse = x[:12]
    model = random_model(x - 2048, 8, 4)
    ivf = index.IvfIndex(coarse, model)
    probes = index.probes(q, coarse, 3)
    codes, tabs = ivf.encode(base), ivf.tables(q, probes)
    small = packed.encode_packed(base, model, coarse)
    assert rows_of(packed.plain_scan(small, q, model, 15, probes, coarse)) == rows_of(scan.adc_topk(codes, tabs, 8, 15, ("list_id",)))
    placed = scan.with_prefix(codes, None, 20, 15, ("list_id",))
    want = rows_of(scan.nibble_topk(placed, scan.nibble_tables(placed, tabs, 8, 15, ("list_id",)), 8, 15, ("list_id",)))
    assert rows_of(packed.nibble_scan(small, q, model, 15, 20, probes=probes, centers=coarse)) == want
    whole = random_model(x, 8, 4)
    codes = encode.encode_pq(base, whole)
    tabs = index.lookup_tables(q, whole)
    want = rows_of(scan.nibble_topk(codes, scan.nibble_tables(scan.with_prefix(codes, None, 20, 15), tabs, 8, 15), 8, 15))
    assert rows_of(packed.nibble_scan(packed.encode_packed(base, whole), q, whole, 15)) == want


def test_nested_candidates_and_rerank(spark):
    q, base, x = vectors(spark)
    model = codebook.nest(random_model(x, 4, 8), 4)
    codes, small = encode.encode_pq(base, model), packed.encode_packed(base, model)
    buckets = scan.first_pass(codes, index.lookup_tables(q, model, coarse=True), 4, 4, 300)
    want = scan.candidates(buckets, 300)
    found = packed.nested_candidates(small, q, model, 300).cache()
    assert found.select("qid", "vec_id", "bucket").exceptAll(want).isEmpty() and found.count() == want.count()
    assert rows_of(packed.rerank(found, q, model, 10)) == rows_of(scan.rerank(want, codes, q, model, 10))
    filled = {r["qid"]: r["filled"] for r in packed.rerank(found, q, model, 10, entries=True).collect()}
    assert filled == {r["qid"]: r["n"] for r in scan.lazy_entries(want, codes, 4).groupBy("qid").agg(F.count("*").alias("n")).collect()}


def test_queries_come_in_batches(spark):
    q, base, x = vectors(spark, 2000)
    model = random_model(x, 8, 8)
    small = packed.encode_packed(base, model)
    assert len(list(packed.batches_of(q, limit=100))) > 1
    assert packed.plain_scan(small, q.where("false"), model, 5).count() == 0
    assert packed.plain_scan(small.where("false"), q, model, 5).count() == 0


@pytest.mark.parametrize("g,low_bits,known,number", [(3, 4, True, "long"), (3, 4, False, "long"), (0, 4, True, "long"), (2, 6, True, "double"), (8, 4, False, "double")])
def test_products_of_small_tiles_find_what_sums_find(monkeypatch, g, low_bits, known, number):
    """Kernels alone: thresholds merged often, tiles that begin within a group, runs of queries that are not full."""
    import pyarrow as pa

    monkeypatch.setattr(packed, "TILE", 64)
    rng = np.random.default_rng(5)
    x = np.clip(rng.normal(2048, 700, (3000, 8)), 0, 4095).astype(int)
    model = random_model(x, 8, 8)
    codes = model.encode(x.astype(float)).astype(np.uint8)
    codes = codes[np.lexsort([codes[:, j] >> low_bits for j in reversed(range(max(1, g)))])]
    block = packed.Block([pa.RecordBatch.from_arrays([pa.array(rng.permutation(3000)), packed.binary_array(codes)], names=["vec_id", "code"])], 8, 8)
    own, want = packed.Batch(np.arange(70), x[:70].astype(float)), []
    factor = 1 if number == "long" else 0.37
    monkeypatch.setattr(packed.Batch, "run", lambda self, m, first: m.tables(self.x[first : first + packed.CHUNK]).astype(np.int64 if number == "long" else float) * factor)
    tops = []
    for i in range(70):
        t = own.run(model, i // packed.CHUNK * packed.CHUNK)[i % packed.CHUNK]
        best = packed.Best(7)
        best.offer(sum(t[j].take(codes[:, j]) for j in range(8)), block.ids)
        want.append(best)
        tops.append(best.d[-1] * 1.5)
    best = [packed.Best(7, tops[i] if known else None) for i in range(70)]
    held, tally = packed.BoundedBlock(block, g, low_bits), np.zeros((70, 5), np.int64)
    for first in range(0, 70, packed.CHUNK):
        held.scan(own, model, first, best[first : first + packed.CHUNK], tally[first : first + packed.CHUNK])
    for a, b in zip(best, want, strict=True):
        assert a.ids.tolist() == b.ids.tolist() and np.allclose(a.d, b.d)
    assert (tally[:, 0] == 3000).all() and (tally[:, 4] <= tally[:, 3]).all() and (tally[:, 2] <= tally[:, 1]).all()


def test_listed_counts_equal_the_marks_without_making_pairs(spark, sf):
    from vecspark.operators import encode, index, scan
    from vecspark.queries import models, workloads

    q, b = models.v1(spark, sf)
    coarse, model = workloads.coarse1(spark, sf, 8), models.pq1(spark, sf, 8, 256)
    ivf = index.IvfIndex(coarse, model, residual=False)
    probes = index.probes(q, coarse, 1)
    marks = scan.bounded_marks(scan.with_prefix(ivf.encode(b), 0.01, None, 10, ("list_id",)), ivf.tables(q, probes), 8, 10, 1, ("list_id",))
    want = marks.groupBy("qid", "list_id").agg(F.count("*").alias("n_codes"), F.count_if("pruned").alias("n_pruned"))
    got = workloads.listed_counts(spark, sf, 8)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert "bounded_marks" not in workloads.__dict__ and not hasattr(workloads, "listed_marks")
