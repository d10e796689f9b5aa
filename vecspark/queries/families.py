"""Combinations: lists from trees and hashes, rotated multi-indexes, bounds over composite sums, wide parts,
further vector sets, and times as measured."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from vecspark.functions.ranking import top_k
from vecspark.functions.vectors import l2sq
from vecspark.operators import additive, bof, codebook, encode, index, lsh, measures, packed, scan, trees
from vecspark.operators.exact import nearest_rows
from vecspark.plans import timing
from vecspark.queries import models, oracle
from vecspark.queries.baselines import D, bof_sql, e2_sql, first, kd_sql, tree0
from vecspark.queries.core import IVF_ADC, coded, imi_full_sql, pq_sql
from vecspark.queries.registry import query
from vecspark.queries.workloads import floats, recalls, union, v1_setup
from vecspark.sources import tables as T

TREE_ADC = f"SELECT r.qid, c.vec_id, CAST({oracle.adc(8)} AS BIGINT) AS dist FROM kd_rank r JOIN kd_leaf l USING (leaf) JOIN codes c USING (vec_id) JOIN tabs t ON t.qid = r.qid WHERE r.rk <= 3"


@query(kd_sql(pq_sql(8, 16, tabled=True), "kd", "base", 3, first).select(oracle.topk(TREE_ADC, 10)))
def q_tree_lists(spark, sf):
    """Codes in the leaves of a KD-tree; a query scans its three nearest leaves."""
    q, b = models.v0(spark, sf)
    tree, model = tree0(spark, sf), models.pq0(spark, sf, 8, 16)
    codes = packed.encode_packed(b, model).join(trees.with_leaf(b, tree).select("vec_id", F.col("leaf").alias("list_id")), "vec_id").select("vec_id", "list_id", "code")
    probes = trees.leaf_order(q, tree).where("rk <= 3").select("qid", F.col("leaf").alias("list_id"))
    return packed.plain_scan(codes, q, model, 10, probes)


HASH_ADC = f"SELECT qid, vec_id, CAST({oracle.adc(8)} AS BIGINT) AS dist FROM (SELECT DISTINCT qid, vec_id FROM e_cand) x JOIN codes c USING (vec_id) JOIN tabs t USING (qid)"


@query(e2_sql(16384, s=pq_sql(8, 16, tabled=True)).select(oracle.topk(HASH_ADC, 10)))
def q_hash_lists(spark, sf):
    """Codes in the buckets of three hash tables; a query scans the codes of its own buckets."""
    q, _ = models.v0(spark, sf)
    codes, tabs, _ = coded(spark, sf)
    both = [lsh.e2lsh_tables(f, k, D, 4, 3, 16384) for f, k in ((models.v0(spark, sf)[1], "vec_id"), (q, "qid"))]
    pairs = lsh.e2lsh_candidates(*both).select("qid", "vec_id").distinct()
    scored = pairs.join(codes, "vec_id").join(F.broadcast(tabs), "qid").select("qid", "vec_id", scan.adc(8).alias("dist"))
    return top_k(scored, 10, ["qid"], ["dist", "vec_id"])


@query(imi_full_sql(50, True).select(oracle.topk(IVF_ADC, 10)))
def q_imi_rotated(spark, sf):
    """Multi-index over rotated vectors (a fixed rotation)."""
    q, b = models.v0_rotated(spark, sf)
    imi = models.once(spark, (sf, "imir"), lambda: index.MultiIndex.build(b, 4, 8, 4, 3))
    codes = imi.encode(b)
    return scan.adc_topk(codes, imi.tables(q, imi.sequence(q, index.list_sizes(codes), 50)), 8, 10, ("list_id",))


@query()
def q_imi_opq(spark, sf):
    """Multi-index over vectors turned by a learnt rotation."""
    from vecspark.operators.projection import rotate_fixed

    b = models.v0(spark, sf)[1]
    turned = models.once(spark, (sf, "v0opq"), lambda: rotate_fixed(b, np.rint(codebook.train_opq(floats(b), 8, 4, 4)[0].rotation * 4096).astype(int).tolist()).persist())
    q, b = T.split(turned)
    imi = models.once(spark, (sf, "imiopq"), lambda: index.MultiIndex.build(b, 4, 8, 4, 3))
    codes = imi.encode(b)
    return scan.adc_topk(codes, imi.tables(q, imi.sequence(q, index.list_sizes(codes), 50)), 8, 10, ("list_id",))


@query(
    oracle.encode(oracle.pq(oracle.v0(), "p", "base", D, 4, 256, 3), "codes", "p", "base", D, 4)
    .add("recon", "SELECT n.vec_id, list(p.c ORDER BY p.part, p.dim) AS e FROM codes_near n JOIN p_cb p USING (part, idx) GROUP BY n.vec_id")
    .select(oracle.topk(f"SELECT q.qid, r.vec_id, {oracle.l2('q.e', 'r.e')} - CAST(list_sum(list_transform(q.e, lambda x: x * x)) AS BIGINT) AS dist FROM queries q, recon r", 10))
)
def q_cq_bounded(spark, sf):
    """The bounded scan over sums of full-dimension centroids; tables hold |c|^2 - 2 q.c, which may be negative."""
    q, b = models.v0(spark, sf)
    pq = models.pq0(spark, sf, 4, 256)
    books = np.zeros((4, 256, D), np.int64)
    for j in range(4):
        books[j][:, j * 16 : (j + 1) * 16] = pq.books[j]
    model = additive.Additive(books, ())
    rows = [(r["qid"], *[t.astype(np.int64).tolist() for t in model.tables(np.array([r["e"]], float))[0]]) for r in q.collect()]  # a batch of queries
    tabs = spark.createDataFrame(rows, "qid long, " + ", ".join(f"t{j} array<long>" for j in range(4)))
    return scan.bounded_topk(scan.with_prefix(encode.encode_pq(b, pq), 0.01, None, 10), tabs, 4, 10, 2)


@query()
def q_cq_trained_search(spark, sf):
    """Codes of the trained composite quantizer, searched: recall by r."""
    q, b = models.v0(spark, sf)

    def make():
        x = np.array([r["e"] for r in b.orderBy("vec_id").limit(400).collect()], float)  # a bounded sample
        return additive.train_composite(x, 4, 8)

    model, _ = models.once(spark, (sf, "cq"), make)
    rows = [(r["qid"], r["e"]) for r in q.collect()]
    found = top_k(additive.additive_scan(additive.encode_additive(b, model), rows, model), 101, ["qid"], ["dist", "vec_id"])
    return recalls({"composite": found}, measures.ground_truth(q, b, D))


@query(
    oracle.probes(oracle.nearest(oracle.components(oracle.centroid_lists(oracle.pq(oracle.v0(), "co", "base", 64, 1, 16, 1), "cents", "co"), "b_sub", "base", 64, 1), "own", "b_sub", "co_cb"), 3).select(
        oracle.topk(f"SELECT p.qid, v.vec_id, {oracle.l2('p.whole', 'v.e')} AS dist FROM probes p JOIN own o ON o.idx = p.list_id JOIN base v USING (vec_id)", 10)
    )
)
def q_words_knn(spark, sf):
    """Visual words as an index of nearest neighbours: the vectors of the three nearest words' cells."""
    q, b = models.v0(spark, sf)
    words = models.once(spark, (sf, "words16"), lambda: codebook.train_kmeans(b, 16, 1))
    held = encode.assign(b, words, name="list_id")
    probed = index.probes(q, words, 3).select("qid", "list_id").join(q.withColumnRenamed("e", "q"), "qid")
    scored = held.join(F.broadcast(probed), "list_id").select("qid", "vec_id", l2sq(F.col("q"), F.col("e"), 64).alias("dist"))
    return top_k(scored, 10, ["qid"], ["dist", "vec_id"])


def item_votes_sql() -> str:
    s = bof_sql()
    items = oracle.v2(source="SELECT item_id AS vec_id, text FROM benchmark")
    for part in items.parts:
        name, body = part.split(" AS MATERIALIZED (", 1)
        for n in ("texts", "grams", "counts", "norms"):
            body = body.replace(f"FROM {n}", f"FROM i_{n}").replace(f"JOIN {n}", f"JOIN i_{n}")
        s.add(f"i_{name}", body[:-1])
    oracle.components(s, "i_sub", "i_v", 128, 1)
    oracle.nearest(s, "i_words", "i_sub", "w_cb")
    s.add("found", "SELECT w.vec_id AS qid, i.doc_id, CAST(sum(i.n) AS BIGINT) AS votes FROM i_words w JOIN idx i ON i.word = w.idx GROUP BY 1, 2")
    return s.select("SELECT qid, rk, doc_id, votes FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY votes DESC, doc_id) AS rk FROM found) WHERE rk <= 3")


@query(item_votes_sql())
def w_retrieval_votes(spark, sf):
    """Benchmark passages as query objects: the votes of the documents' line descriptors by words."""
    lines = T.descriptors(spark, sf).withColumn("vec_id", F.col("doc_id") * 67108864 + F.col("pos"))
    words = models.once(spark, (sf, "bof"), lambda: codebook.train_kmeans(lines.where(F.pmod("vec_id", F.lit(7)) == 0).select("vec_id", "e"), 16, 1))
    items = T.text_vectors(T.load(spark, sf, "benchmark").select(F.col("item_id").alias("vec_id"), "text"), ["vec_id"], "text")
    asked = encode.assign(items, words, name="word").groupBy(F.col("vec_id").alias("qid"), "word").agg(F.count("*").alias("n"))
    idx = bof.bof_index(lines, words)
    votes = idx.join(F.broadcast(asked.withColumnRenamed("n", "nq")), "word").groupBy("qid", "doc_id").agg(F.sum(F.col("n") * F.col("nq")).alias("votes"))
    return top_k(votes, 3, ["qid"], [F.col("votes").desc(), F.col("doc_id")]).select("qid", "rk", "doc_id", "votes")


@query(
    oracle.v2()
    .add("known", "SELECT v.vec_id, v.e, l.quality FROM v JOIN labels l ON l.doc_id = v.vec_id")
    .add("near", oracle.topk(f"SELECT q.vec_id AS qid, k.vec_id, {oracle.l2('q.e', 'k.e')} AS dist FROM known q, known k WHERE q.vec_id % 50 = 0 AND q.vec_id <> k.vec_id", 5))
    .add("votes", "SELECT qid, sum(quality) * 2 > 5 AS guess FROM near JOIN known USING (vec_id) GROUP BY qid")
    .select("SELECT count(*) AS n, count(*) FILTER (WHERE guess = (quality = 1)) AS correct FROM votes JOIN known ON vec_id = qid")
)
def w_nn_classifier_documents(spark, sf):
    """Quality of documents by the majority of the five nearest labelled texts."""
    labels = T.load(spark, sf, "labels").select(F.col("doc_id").alias("vec_id"), "quality")
    known = T.vectors_documents(spark, sf).join(labels, "vec_id").select("vec_id", "e", "quality").persist()
    near = nearest_rows(*T.split(known.select("vec_id", "e")), 5, others=True)
    quality = known.select("vec_id", "quality")
    votes = near.join(quality, "vec_id").groupBy("qid").agg((F.sum("quality") * 2 > 5).alias("guess"))
    votes = votes.join(quality.select(F.col("vec_id").alias("qid"), F.col("quality").alias("truth")), "qid")
    return votes.agg(F.count("*").alias("n"), F.count_if(F.col("guess") == (F.col("truth") == 1)).alias("correct"))


@query(
    "WITH p AS MATERIALIZED (SELECT user_id, event_type || ':' || CAST(hour(ts) AS VARCHAR) AS item, count(*) AS n FROM events GROUP BY 1, 2), "
    "dots AS MATERIALIZED (SELECT a.user_id AS qid, b.user_id, CAST(sum(a.n * b.n) AS BIGINT) AS dot FROM p a JOIN p b USING (item) WHERE a.user_id % 50 = 0 AND a.user_id <> b.user_id GROUP BY 1, 2), "
    "near AS MATERIALIZED (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dot DESC, user_id) AS rk FROM dots) WHERE rk <= 5) "
    "SELECT n.qid, s.item, CAST(sum(s.n) AS BIGINT) AS score FROM near n JOIN p s USING (user_id) WHERE NOT EXISTS (SELECT 1 FROM p o WHERE o.user_id = n.qid AND o.item = s.item) GROUP BY 1, 2"
)
def w_recommender_events(spark, sf):
    """What a user's nearest profiles of events by hour hold and the user's own does not."""
    p = T.profiles_events(spark, sf).select("user_id", F.concat_ws(":", "event_type", F.col("hour").cast("string")).alias("item"), "n")
    mine = p.where("user_id % 50 = 0").select(F.col("user_id").alias("qid"), "item", F.col("n").alias("x"))
    dots = p.join(F.broadcast(mine), "item").where("user_id <> qid").groupBy("qid", "user_id").agg(F.sum(F.col("n") * F.col("x")).alias("dot"))
    near = top_k(dots, 5, ["qid"], [F.col("dot").desc(), F.col("user_id")])
    scored = near.join(p, "user_id").groupBy("qid", "item").agg(F.sum("n").alias("score"))
    return scored.join(mine.select("qid", "item"), ["qid", "item"], "left_anti")


@query()
def w_wide_parts(spark, sf):
    """Two parts of as many bits as the set's size supports (sixteen at most), alone and nested, against parts of
    eight bits: table bytes, quantization error and recall."""
    from vecspark.queries.core import reconstruction

    q, b = models.v1(spark, sf)
    bits = min(16, int(np.log2(b.count())))
    truth, out = measures.ground_truth(q, b, 8).cache(), []
    for name, b_part in (("2x8", 8), (f"2x{bits}", bits)):
        model = models.once(spark, (sf, "wide", b_part), lambda b_part=b_part: codebook.train_pq(b, 2, b_part, 1))
        codes = packed.encode_packed(b, model).persist()
        runs = {name: packed.plain_scan(codes, q, model, 101)}
        if b_part > 8:
            nested = codebook.nest(model, 8, "ntile")
            runs[f"nested 2x8,{bits}"] = packed.rerank(packed.nested_candidates(packed.encode_packed(b, nested), q, nested, max(101, b.count() // 50)), q, nested, 101)
        error = reconstruction(b, model).agg((F.sum("error") / F.count("*")).alias("error"))
        for run, found in runs.items():
            hits = measures.recall_at(found, truth, (1, 10, 100))
            out.append(hits.crossJoin(error).select(F.lit(run).alias("model"), F.lit(4 * 2 << b_part).cast("long").alias("table_bytes"), "error", "r", "hits", "queries", "recall"))
    return union(out)


# -- times as measured -------------------------------------------------------------------------


@query()
def w_time_split(spark, sf):
    """Seconds of the index, tables and scan steps over three of sixteen lists (as measured: they vary)."""
    q, b = models.v0(spark, sf)
    ivf = models.ivf0(spark, sf, 16, 8, 4)
    return timing.frame(spark, timing.time_split(q, b, ivf, 3, 50))


@query()
def w_response_times(spark, sf):
    """Seconds a query, alone in its block, of the plain and the bounded scan on line items: mean and quantiles."""
    q, model, codes = v1_setup(spark, sf, True)
    return timing.frame(spark, timing.response_times(codes, q, model, 10, 3))


@query()
def w_partition_sweep(spark, sf):
    """Seconds of a batch over 1, 2, 4 and 8 tasks."""
    q, model, codes = v1_setup(spark, sf)
    return timing.frame(spark, timing.partition_sweep(codes, q, model, 10))


@query()
def w_concurrency(spark, sf):
    """Seconds of 1, 2 and 4 batches of queries sent at once."""
    q, model, codes = v1_setup(spark, sf)
    return timing.frame(spark, timing.concurrency(codes, q, model, 10))


# -- further relational forms ------------------------------------------------------------------


@query("SELECT CAST(p_size AS BIGINT) AS size, " + ", ".join(f"count(*) FILTER (WHERE p_brand = 'Brand#{i}') AS b{i}" for i in (11, 12, 13)) + " FROM part GROUP BY p_size")
def o_pivot(spark, sf):
    p = T.load(spark, sf, "part").groupBy(F.col("p_size").cast("long").alias("size")).pivot("p_brand", [f"Brand#{i}" for i in (11, 12, 13)]).count()
    return p.select("size", *[F.coalesce(F.col(f"`Brand#{i}`"), F.lit(0)).alias(f"b{i}") for i in (11, 12, 13)])


@query("SELECT n_nationkey, c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 1)")
def o_correlated_top1(spark, sf):
    """The best row of each outer row: a correlated top-1 as a grouped maximum of structs."""
    c = T.load(spark, sf, "customer").groupBy(F.col("c_nationkey").alias("n_nationkey")).agg(F.max(F.struct("c_acctbal", (-F.col("c_custkey")).alias("key"))).alias("x"))
    return T.load(spark, sf, "nation").select("n_nationkey").join(c, "n_nationkey").select("n_nationkey", (-F.col("x.key")).alias("c_custkey"))


@query("SELECT CAST(label AS BIGINT) AS label, count(*) AS n FROM (SELECT label, row_number() OVER (PARTITION BY label ORDER BY md5(CAST(vec_id AS VARCHAR)), vec_id) AS rk FROM embeddings) WHERE rk <= 5 GROUP BY 1")
def o_stratified_sample(spark, sf):
    """Five of each class, by a hash."""
    v = T.load(spark, sf, "embeddings").select("vec_id", F.col("label").cast("long").alias("label"))
    return top_k(v, 5, ["label"], [F.md5(F.col("vec_id").cast("string").cast("binary")), F.col("vec_id")]).groupBy("label").agg(F.count("*").alias("n"))


@query(oracle.v0().select("SELECT format, count(*) AS n, CAST(sum(list_sum(e)) AS BIGINT) AS total FROM v, (SELECT unnest(['csv', 'json', 'orc']) AS format) GROUP BY format"))
def o_vector_formats(spark, sf):
    """Vectors written and read back as CSV (joined numbers), JSON and ORC."""
    from vecspark.sources.storage import read_vectors, scratch_path, write_vectors

    v, out = models.v0(spark, sf)[1], []
    for kind in ("csv", "json", "orc"):
        path = f"{scratch_path(spark)}/vectors-{kind}"
        write_vectors(v, path, kind)
        back = read_vectors(spark, path, kind)
        out.append(back.agg(F.lit(kind).alias("format"), F.count("*").alias("n"), F.sum(F.aggregate("e", F.lit(0).cast("long"), lambda s, x: s + x)).alias("total")))
    return union(out)
