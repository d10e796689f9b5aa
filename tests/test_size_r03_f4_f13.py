"""Counts of several cases are made together, and thresholds of prefixes without a merge of tasks' rows."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecspark.operators import packed
from vecspark.operators.codebook import PQModel


def made(n=5000, m=8, k=256, seed=2):
    rng = np.random.default_rng(seed)
    model = PQModel(m, 8, m, rng.integers(0, 4096, (m, k, 1)).astype(np.int64), None)
    ids = rng.permutation(n * 3)[:n].astype(np.int64)
    return rng, model, ids, rng.integers(0, k, (n, m)).astype(np.uint8)


def pruned(t, codes, ids, top, end, whole, low_bits):
    """Case by case and code by code, as the SQL states it."""
    m, k = t.shape
    low = t.min()
    if top <= low:
        return 0
    small = t.reshape(m, -1, 1 << low_bits).min(axis=2)
    total = np.zeros(len(ids), np.int64)
    for j in range(m):
        x = t[j][codes[:, j]] if j < whole else small[j][codes[:, j] >> low_bits]
        total += np.minimum((x - low) * 127 // (top - low), 127)
    return int(((total >= -(-(top - m * low) * 127 // (top - low))) & (ids > end)).sum())


@pytest.mark.parametrize(("n", "whole", "cases"), [(5000, 2, 1), (5000, 2, 5), (40000, 2, 7), (3000, 1, 11), (5000, 0, 3), (1, 2, 2)])
def test_counts_of_several_cases(n, whole, cases):
    rng, model, ids, codes = made(n)
    t = np.rint(model.tables(rng.integers(0, 4096, (5, 8)).astype(float))).astype(np.int64)
    ends = rng.choice(np.append(ids, [-1, ids.max()]), cases)
    tops = (t.sum(axis=2).sum(axis=1)[:, None] // 256 * rng.random((5, cases))).astype(np.int64)
    tops[1, 0], tops[2, -1] = t[1].min(), t[2].min() + 1
    got = packed.CountedBlock(codes, ids, model, whole, 4).count(t, tops, ends)
    want = [[pruned(t[i], codes, ids, tops[i, c], ends[c], whole, 4) for c in range(cases)] for i in range(5)]
    assert got.tolist() == want


def test_thresholds_of_prefixes_need_no_merge(spark, monkeypatch):
    """Each task gave r rows a query: most of the time of w_r_sweep, whose largest r is 500."""
    rng, model, ids, codes = made()
    rows = [(int(i), bytes(c)) for i, c in zip(ids, codes, strict=True)]
    frame = spark.createDataFrame(rows, "vec_id long, code binary").repartition(5)
    x = rng.integers(0, 4096, (70, 8))
    queries = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "qid long, e array<long>")
    cases = [(1, 0.005), (10, 0.1), (500, 0.01), (100, 0.5)]
    order = np.argsort(ids)
    d = np.rint(model.tables(x.astype(float))).astype(np.int64)
    dist = sum(d[:, j][:, codes[order, j]] for j in range(8))
    sizes = [max(r, int(np.ceil(len(ids) * share))) for r, share in cases]
    want = {i: [int(np.sort(dist[i, :n])[r - 1]) for (r, _), n in zip(cases, sizes, strict=True)] for i in range(len(x))}
    ends = [int(ids[order[n - 1]]) for n in sizes]
    got = packed._held_tops(frame, queries, model, [(r, end) for (r, _), end in zip(cases, ends, strict=True)])
    assert {r[0]: list(r[1:]) for r in got.collect()} == want
    with monkeypatch.context() as patch:
        patch.setattr(packed, "plain_scan", None)
        near = packed.bounded_cases(frame, queries, model, cases, 2).collect()
    monkeypatch.setattr(packed, "HEAD_BYTES", 0)  # a prefix too large to broadcast
    assert sorted(map(tuple, near)) == sorted(map(tuple, packed.bounded_cases(frame, queries, model, cases, 2).collect()))
    at = {(r["qid"], r["case"]): r["n_pruned"] for r in near}
    for i in (0, 7, 69):
        for c, end in enumerate(ends):
            assert at[i, c] == pruned(d[i], codes, ids, want[i][c], end, 2, 4)


def test_prefix_tops_either_way(spark, monkeypatch):
    rng, model, ids, codes = made(3000)
    frame = spark.createDataFrame([(int(i), bytes(c)) for i, c in zip(ids, codes, strict=True)], "vec_id long, code binary")
    queries = spark.createDataFrame([(i, rng.integers(0, 4096, 8).tolist()) for i in range(20)], "qid long, e array<long>")
    held = packed.prefix_tops(frame, queries, model, 10)
    none = packed.prefix_tops(frame.where(F.col("vec_id") < int(np.sort(ids)[5])), queries, model, 10)
    monkeypatch.setattr(packed, "HEAD_BYTES", 0)
    assert held == packed.prefix_tops(frame, queries, model, 10) and len(held) == 20 and none == {}
