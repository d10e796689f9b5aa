"""Worked examples, invariants and plans of the methods."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecspark.functions import bits, vectors
from vecspark.operators import additive, codebook, encode, index, measures, scan, trees
from vecspark.plans import costs, planner
from vecspark.queries import models
from vecspark.sources import storage
from vecspark.streaming import profiles


def plan_of(frame) -> str:
    return frame._jdf.queryExecution().executedPlan().toString()


def test_worked_groups(spark):
    codes = [(0, 1, 2, 3), (5, 15, 9, 11), (10, 14, 13, 12), (60, 20, 44, 3), (51, 31, 33, 12), (250, 241, 255, 240), (244, 255, 242, 243), (1, 2, 3, 17)]
    f = spark.createDataFrame([(i, *c) for i, c in enumerate(codes)], "vec_id long, c0 long, c1 long, c2 long, c3 long")
    sizes = {r["grp"]: r["count"] for r in encode.group_codes(f, 4).groupBy("grp").count().collect()}
    assert sizes == {0: 3, 3 << 12 | 1 << 8 | 2 << 4: 2, 0xFFFF: 2, 1: 1}


def test_arithmetic():
    assert encode.max_group_components(50 * 16**4) == 4 and encode.max_group_components(50 * 16**4 - 1) == 3
    assert encode.max_group_components(12_800, 4) == 4 and encode.max_group_components(3_200, 4) == 3
    assert [4 * 16 << 4, 4 * 8 << 8, 4 * 4 << 16] == [4096 // 4, 8192, 1 << 20]
    assert costs.bounded_cost(8, 0.98) < 9 / 4


def test_worked_numbering():
    points = np.array([[float(10 * c + r)] for r in range(4) for c in range(4)])
    model = codebook.nest(codebook.PQModel(1, 4, 1, points[None]), 2)
    for cluster in range(4):
        own = model.books[0][cluster::4, 0] // 10
        assert len(set(own)) == 1  # ids cluster, cluster + 4, + 8, + 12 share their low bits


@pytest.mark.parametrize("clusters", [4, 16])
def test_same_size_partition(clusters):
    x = np.random.default_rng(3).normal(size=(64, 5))
    label = codebook.same_size_partition(x, clusters)
    assert set(np.bincount(label)) == {64 // clusters}

    def spread(lab):
        return sum(((x[lab == c] - x[lab == c].mean(axis=0)) ** 2).sum() for c in range(clusters))

    assert spread(label) < spread(np.arange(64) % clusters)


def test_minimum_tables(spark):
    table = list(range(100, 356))
    f = spark.createDataFrame([(table,)], "t0 array<long>")
    got = f.select(scan.min_table("t0").alias("m"), scan.portion("t0", F.lit(3)).alias("p")).first()
    assert got["m"] == [100 + 16 * i for i in range(16)] and got["p"] == table[48:64]


def test_pack_round_trip(spark):
    f = spark.createDataFrame([tuple(range(16))], ", ".join(f"c{j} long" for j in range(16))).withColumn("vec_id", F.lit(1))
    back = encode.unpack_nibble_codes(encode.pack_nibble_codes(f, 16), 16).first()
    assert [back[f"c{j}"] for j in range(16)] == list(range(16))
    z = f.select(bits.interleave([F.lit(5), F.lit(3)], 3).alias("z")).first()["z"]
    assert z == 0b100111


def test_kernels_equal_columns(spark, sf):
    q, b = models.v0(spark, sf)
    model = models.pq0(spark, sf, 8, 16)
    codes, tabs = encode.encode_pq(b, model), index.lookup_tables(q, model)
    want = {tuple(r) for r in scan.adc_topk(codes, tabs, 8, 7).select("qid", "rk", "vec_id", "dist").collect()}
    for parts in (1, 4, 16):
        from vecspark.queries.core import table_rows

        got = {tuple(r) for r in scan.kernel_topk(codes.repartition(parts), table_rows(tabs, 8), 8, 7).select("qid", "rk", "vec_id", "dist").collect()}
        assert got == want


@pytest.mark.parametrize("r,share,g,mode", [(1, 0.01, 4, "full"), (10, 0.05, 2, "full"), (50, 0.01, 1, "quant_only"), (10, 0.5, 0, "full")])
def test_bounded_is_exact(spark, sf, r, share, g, mode):
    q, b = models.v0(spark, sf)
    model = models.pq0(spark, sf, 8, 256)
    codes, tabs = encode.encode_pq(b, model), index.lookup_tables(q.where("qid < 10"), model)
    want = {tuple(x) for x in scan.adc_topk(codes, tabs, 8, r).collect()}
    got = scan.bounded_topk(scan.with_prefix(codes, share, None, r), tabs, 8, r, g, mode=mode)
    assert {tuple(x) for x in got.collect()} == want


def test_bounded_plan(spark, sf):
    q, b = models.v0(spark, sf)
    model = models.pq0(spark, sf, 8, 256)
    codes = encode.encode_pq(b, model)
    text = plan_of(scan.adc_topk(codes, index.lookup_tables(q, model), 8, 10))
    assert text.count("WindowGroupLimit") >= 2 and "BroadcastNestedLoopJoin" in text and "ArrowEvalPython" not in text


def test_nested_candidates_hold_r2(spark, sf):
    from vecspark.queries.bounded import nested

    for r2 in (10, 100):
        found = scan.candidates(nested(spark, sf, r2)[3], r2).groupBy("qid").count().agg(F.min("count")).first()[0]
        assert found >= r2


def test_opq(spark, sf):
    b = models.v0(spark, sf)[1].select("vec_id", F.transform("e", lambda x: x.cast("double")).alias("e"))
    model, errors = codebook.train_opq(b, 8, 4, 4)
    assert np.allclose(model.rotation @ model.rotation.T, np.eye(64), atol=1e-8)
    assert all(y <= x * (1 + 1e-9) for x, y in zip(errors, errors[1:]))


def test_multi_sequence_is_the_sorted_list(spark, sf):
    imi = models.imi0(spark, sf)
    q, b = models.v0(spark, sf)
    got = imi.sequence(q, index.list_sizes(imi.encode(b)), 10**9)
    assert got.groupBy("qid").count().agg(F.min("count")).first()[0] == 16
    rows = got.where("qid = 3").orderBy("rk").collect()
    assert [r["dist"] for r in rows] == sorted(r["dist"] for r in rows)


def test_recall_grows(spark, sf):
    q, b = models.v0(spark, sf)
    truth = measures.ground_truth(q, b, 64)
    out = {}
    for m, k in ((8, 16), (16, 16)):
        model = models.pq0(spark, sf, m, k)
        rows = measures.recall_at(scan.adc_topk(encode.encode_pq(b, model), index.lookup_tables(q, model), m, 100), truth, (1, 10, 100)).orderBy("r").collect()
        out[m] = [r["hits"] for r in rows]
        assert out[m] == sorted(out[m])
    assert sum(out[16]) >= sum(out[8])


def test_additive_distance():
    rng = np.random.default_rng(0)
    books, q = rng.normal(size=(3, 5, 8)), rng.normal(size=(4, 8))
    model = additive.Additive(books, ((0, 1), (0, 2), (1, 2)))
    codes = rng.integers(0, 5, (6, 3))
    whole = sum(books[j][codes[:, j]] for j in range(3))
    assert np.allclose(model.distances(q, codes), ((q[:, None] - whole[None]) ** 2).sum(axis=2))
    x = rng.normal(size=(20, 8))
    errors = [((x - sum(books[j][c[:, j]] for j in range(3))) ** 2).sum() for c in (model.encode(x, b) for b in (1, 8))]
    assert errors[1] <= errors[0] and model.lookups() == 6


def test_auto_select():
    runs = [("a", 0.9, 10, 5, 1), ("b", 0.8, 2, 5, 1), ("c", 0.4, 1, 1, 1)]
    assert trees.auto_select(runs, 0.75, 1, 0, 0) == "b" and trees.auto_select(runs, 0.95, 1, 0, 0) == "a"


def test_planner():
    assert planner.choose(10**5, 100, 10).scan == "plain"
    p = planner.choose(25 * 10**6, 1, 1000)
    assert p.scan == "bounded" and p.grouped == 4 and p.tables == "broadcast"
    assert planner.choose(10**9, 65536, 10**5, 16, 4, 64).tables == "shuffle"


def test_validate(spark):
    f = spark.createDataFrame([(1, [1.0, 2.0]), (2, [1.0]), (3, None), (4, [float("nan"), 1.0]), (5, [None, 1.0])], "vec_id long, e array<double>")
    assert [r["vec_id"] for r in vectors.validate(f, 2).collect()] == [1]


def test_storage(spark, sf, tmp_path):
    ivf = models.ivf0(spark, sf)
    codes = ivf.encode(models.v0(spark, sf)[1])
    storage.save_codes(codes, str(tmp_path / "codes"), 4)
    back = storage.load_codes(spark, str(tmp_path / "codes"))
    assert sorted(map(tuple, back.select(*codes.columns).collect())) == sorted(map(tuple, codes.collect()))
    probes = index.probes(models.v0(spark, sf)[0], ivf.coarse, 1)
    hit = storage.probe_codes(spark, str(tmp_path / "codes"), probes, 4)
    assert "dynamicpruning" in plan_of(hit).lower() and hit.count() > 0
    storage.save_model(spark, ivf.model, str(tmp_path / "model"))
    assert np.array_equal(storage.load_model(spark, str(tmp_path / "model")).books, ivf.model.books)


def test_append_codes(spark, sf, tmp_path):
    stream = profiles.read_events(spark, sf).select(F.col("event_id").alias("vec_id"), F.array(F.col("user_id"), F.col("event_id")).alias("e"))
    model = codebook.PQModel(2, 1, 2, np.array([[[0], [100]], [[0], [500]]]))
    profiles.append_codes(stream, lambda f: encode.encode_pq(f, model), str(tmp_path / "out"), str(tmp_path / "ck")).awaitTermination()
    assert spark.read.parquet(str(tmp_path / "out")).count() == spark.read.parquet(f"{sf}/events.parquet").count()


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())


def test_encoding_errors_cover_the_whole_base(spark):
    from vecspark.operators import additive
    from vecspark.queries import baselines

    x = np.random.default_rng(3).integers(0, 4096, (700, 64))
    x[400:] *= 3
    model, _ = additive.train_composite(x[:400].astype(float), 4, 8)
    codes = model.encode(x.astype(float))
    want = ((x - sum(model.books[j][codes[:, j]] for j in range(4))) ** 2).sum(axis=1).mean()
    base = spark.createDataFrame([(v.tolist(),) for v in x], "e array<long>")
    assert abs(baselines.encoding_error(base, model) / want - 1) < 1e-9
