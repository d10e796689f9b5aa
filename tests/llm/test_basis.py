"""The latent basis of the decontamination is fitted on every passage."""

import inspect

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from vecspark.llm import decontaminate as d


def test_products_of_tables_equal_products_of_passages():
    rng = np.random.default_rng(3)
    table = np.sort(rng.integers(0, 40, (300, d.PASSAGE)), axis=1).astype(np.int32)
    table[5] = 0
    idf = rng.random(40).astype(np.float32)
    idf[[0, 7]] = 0
    right = rng.normal(size=(40, 6)).astype(np.float32)
    one, all_at_once = np.zeros_like(right), np.zeros_like(right)
    for ids in table:
        d._add_gram(one, ids, idf, right)
    d._add_grams(all_at_once, table, idf, right)
    assert np.allclose(one, all_at_once, rtol=1e-3, atol=1e-3)


def test_no_passage_is_left_out_of_the_fit():
    assert "sample" not in inspect.signature(d.leaks).parameters
    assert "sample" not in inspect.signature(d.build_index).parameters


def test_frequent_words_as_a_dense_part_give_the_same_products():
    rng = np.random.default_rng(4)
    table = np.sort(rng.integers(0, 40, (300, d.PASSAGE)), axis=1).astype(np.int32)
    table[5], table[6] = 0, 3
    idf = rng.random(40).astype(np.float32)
    idf[[0, 7]] = 0
    right = rng.normal(size=(40, 6)).astype(np.float32)
    plain = np.zeros_like(right)
    d._add_grams(plain, table, idf, right)
    for often in ([3], [1, 3, 5, 39], [i for i in range(40) if idf[i] > 0]):
        out = np.zeros_like(right)
        d._add_grams(out, table, idf, right, np.array(often))
        assert np.allclose(plain, out, rtol=1e-3, atol=1e-3)


def test_search_reads_the_kept_word_numbers(spark, sf):
    """The search split every text a second time."""
    docs, bench = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "benchmark"))
    found = d.leaks(spark, docs.repartition(16), bench)
    assert all("numbers" in f for f in found.inputFiles()), found.inputFiles()
    assert found.count() == d.leaks(spark, docs.coalesce(1), bench).count() > 0


def test_a_task_gives_one_matrix(spark):
    """A task gave a matrix for each Arrow batch, and the driver fetched them in a job a partition."""
    rng = np.random.default_rng(5)
    rows = [(i, i, rng.integers(0, 30, 100).astype(np.uint16).tobytes()) for i in range(60)]
    numbers = spark.createDataFrame(rows, d.NUMBERS).repartition(3).cache()
    idf, right = np.ones(30, np.float32), rng.normal(size=(30, 4)).astype(np.float32)
    idf[0] = 0
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "5")
    try:
        got = numbers.mapInArrow(d._product(idf, right, np.array([2, 4])), d.SUMS).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    want = np.zeros_like(right)
    for _, _, ids in rows:
        for part in np.pad(np.frombuffer(ids, np.uint16), (0, 28)).reshape(-1, d.PASSAGE).astype(np.int32):
            d._add_gram(want, part, idf, right)
    assert len(got) == 3
    assert np.allclose(sum(np.frombuffer(r["sums"], np.float32).reshape(right.shape) for r in got), want, rtol=1e-3, atol=1e-3)


def test_candidates_of_the_cosine_are_compared_themselves(spark, sf, monkeypatch):
    """Candidates of the latent route were dropped where the other route had none."""
    docs, bench = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "benchmark"))
    items = [(r["item_id"], r["text"]) for r in bench.collect()]
    index, numbers = d.build_index(spark, d.Scratch(spark, "test"), docs.withColumn("text_hash", F.xxhash64("text")), items, 64, 0.05, 0.8, 0.55)
    batch = pa.RecordBatch.from_pylist([r.asDict() for r in numbers.collect()])

    def search():
        return [r for part in d._search(index, 0.6, 0.8, 0.55)()(batch) for r in part.to_pylist()]

    def key(r):
        return r["doc_id"], r["text_hash"], r["item_id"]

    both = {key(r): r for r in search()}
    monkeypatch.setattr(index, "rare", lambda docs: [])
    alone = {key(r): r for r in search()}
    assert alone and all(r["latent"] for r in alone.values())
    assert set(alone) == {k for k, r in both.items() if r["latent"]}
    assert all(alone[k]["common"] <= both[k]["common"] for k in alone)


def test_no_candidate_that_holds_a_leak_is_sieved(spark):
    """The count of words leaves out no stretch that is a leak, wherever places of the table are shared."""
    rng = np.random.default_rng(9)
    items = [(i, " ".join(f"w{x}" for x in rng.integers(0, 60, 20 + 10 * i)) + ". " + " ".join(f"w{x}" for x in rng.integers(0, 60, 4))) for i in range(6)]
    queries, vocabulary = d.queries_of(items), {f"w{x}".encode(): x + 1 for x in range(60)}
    docs = [d._numbers(vocabulary, q.words) for q in queries] + [rng.integers(0, 61, 300).astype(np.int32) for _ in range(4)]
    docs += [np.concatenate([rng.integers(0, 61, 13), x[: len(x) * 9 // 10], rng.integers(0, 61, 30)]).astype(np.int32) for x in docs[:6]]
    index = d.Index(vocabulary, rng.normal(size=(61, 8)).astype(np.float32), queries)
    index.set_rare(rng.random(61), 0.8, 0.55)
    found = [(i, j, b) for i, x in enumerate(docs) for j in range(len(queries)) for b in range(-(-len(x) // d.BLOCK))]
    want = {c for c in found if d.leaks_at(queries[c[1]], docs[c[0]].tolist(), [(c[2], c[2])], 0.8, 0.55)}
    assert len(want) >= 12
    for places in (d.PLACES, 6):
        d.PLACES, kept = places, d.PLACES
        try:
            index.set_words(0.8, 0.55)
        finally:
            d.PLACES = kept
        assert want <= set(index.enough(docs, found))
    index.set_words(0.8, 0.55)
    assert len(index.enough(docs, found)) < len(found)
