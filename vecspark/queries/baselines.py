"""Queries of the baselines: trees, hashing, bags of features, optimised and additive quantizers."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from vecspark.functions.ranking import scalar_neighbours, top_k
from vecspark.operators import additive, bof, codebook, encode, index, lsh, measures, scan, trees
from vecspark.operators.projection import random_rotation
from vecspark.queries import models, oracle
from vecspark.queries.core import EXACT_SQL, exact
from vecspark.queries.oracle import Sql
from vecspark.queries.registry import query
from vecspark.sources import tables as T

D = 64

# -- one dimension -----------------------------------------------------------------------------


@query(
    "WITH x AS (SELECT DISTINCT CAST(floor(l_extendedprice * 100 + 0.5) AS BIGINT) AS x FROM lineitem), q AS (SELECT CAST(p_partkey AS BIGINT) AS qid, CAST(floor(p_retailprice * 100 + 0.5) AS BIGINT) AS v FROM part) "
    "SELECT q.qid, q.v, coalesce(lo.x, -1) AS below, coalesce(hi.x, -1) AS above FROM q ASOF LEFT JOIN x lo ON q.v >= lo.x ASOF LEFT JOIN x hi ON q.v <= hi.x"
)
def q_scalar_nn(spark, sf):
    """Neighbours of scalars on either side, by a search in the sorted ranges of the values."""
    x = T.load(spark, sf, "lineitem").select(F.floor(F.col("l_extendedprice") * 100 + 0.5).cast("long").alias("x"))
    q = T.load(spark, sf, "part").select(F.col("p_partkey").cast("long").alias("qid"), F.floor(F.col("p_retailprice") * 100 + 0.5).cast("long").alias("v"))
    return scalar_neighbours(x, q).select("qid", "v", F.coalesce("below", F.lit(-1)).alias("below"), F.coalesce("above", F.lit(-1)).alias("above"))


# -- trees -------------------------------------------------------------------------------------


def kd_sql(s: Sql, p: str, src: str, depth: int, pick) -> Sql:
    """{p}_leaf(vec_id, leaf), {p}_nodes(node, dim, cut), {p}_box(leaf, dim, low, high)."""
    s.add(f"{p}_long", f"SELECT vec_id, unnest(range(0, {D})) AS dim, unnest(e) AS x FROM {src}")
    s.add(f"{p}_p0", f"SELECT vec_id, 1 AS node FROM {src}")
    for level in range(depth):
        picks = " ".join(f"WHEN {n} THEN {pick(n) + 1}" for n in range(1 << level, 2 << level))
        s.add(f"{p}_v{level}", f"SELECT node, dim, row_number() OVER (PARTITION BY node ORDER BY count(*) * sum(x * x) - sum(x) * sum(x) DESC, dim) AS place FROM {p}_long JOIN {p}_p{level} USING (vec_id) GROUP BY node, dim")
        s.add(f"{p}_d{level}", f"SELECT node, dim FROM {p}_v{level} WHERE place = CASE node {picks} END")
        s.add(f"{p}_n{level}", f"SELECT node, dim, x AS cut FROM (SELECT node, dim, x, row_number() OVER (PARTITION BY node ORDER BY x) AS rn, count(*) OVER (PARTITION BY node) AS n FROM {p}_long JOIN {p}_p{level} USING (vec_id) JOIN {p}_d{level} USING (node, dim)) WHERE rn = (n + 1) // 2")
        s.add(f"{p}_p{level + 1}", f"SELECT l.vec_id, n.node * 2 + CASE WHEN l.x >= n.cut THEN 1 ELSE 0 END AS node FROM {p}_p{level} a JOIN {p}_n{level} n USING (node) JOIN {p}_long l ON l.vec_id = a.vec_id AND l.dim = n.dim")
    s.add(f"{p}_leaf", f"SELECT vec_id, node AS leaf FROM {p}_p{depth}")
    s.add(f"{p}_nodes", " UNION ALL ".join(f"SELECT * FROM {p}_n{level}" for level in range(depth)))
    sides = " UNION ALL ".join(
        f"SELECT leaf, n.dim, CASE WHEN (leaf >> {up}) % 2 = 1 THEN n.cut END AS low, CASE WHEN (leaf >> {up}) % 2 = 0 THEN n.cut END AS high FROM (SELECT unnest(range({1 << depth}, {2 << depth})) AS leaf) JOIN {p}_nodes n ON n.node = leaf >> {up + 1}" for up in range(depth)
    )
    s.add(f"{p}_box", f"SELECT leaf, dim, max(low) AS low, min(high) AS high FROM ({sides}) GROUP BY leaf, dim")
    s.add(f"{p}_q", f"SELECT qid, unnest(range(0, {D})) AS dim, unnest(e) AS x FROM queries")
    return s.add(f"{p}_rank", f"SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, leaf) AS rk FROM (SELECT qid, leaf, CAST(sum(power(greatest(coalesce(low - x, 0), coalesce(x - high, 0), 0), 2)) AS BIGINT) AS dist FROM {p}_box JOIN {p}_q USING (dim) GROUP BY qid, leaf)")


def tree0(spark, sf, seed: int = 0):
    return models.once(spark, (sf, "kd", seed), lambda: trees.kdtree_build(models.v0(spark, sf)[1], D, 3, (lambda n: (seed * 7 + n * 3) % 5) if seed else (lambda n: 0)))


def first(n):
    return 0


def forest_pick(seed):
    return lambda n: (seed * 7 + n * 3) % 5


@query(kd_sql(oracle.v0(), "kd", "base", 3, first).select("SELECT CAST(leaf AS BIGINT) AS leaf, vec_id FROM kd_leaf"))
def q_kdtree_leaves(spark, sf):
    return trees.with_leaf(models.v0(spark, sf)[1], tree0(spark, sf)).select("leaf", "vec_id")


@query(oracle.v0().select(oracle.topk(EXACT_SQL, 5)))
def q_kdtree_exact(spark, sf):
    q, b = models.v0(spark, sf)
    tree = tree0(spark, sf)
    return trees.kdtree_knn(trees.with_leaf(b, tree), q, tree, 5)


KD_SCAN = f"SELECT DISTINCT r.qid, v.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM kd_rank r JOIN kd_leaf l USING (leaf) JOIN base v USING (vec_id) JOIN queries q ON q.qid = r.qid WHERE r.rk <= 2"


@query(kd_sql(oracle.v0(), "kd", "base", 3, first).select(oracle.topk(KD_SCAN, 5)))
def q_kdtree_priority(spark, sf):
    q, b = models.v0(spark, sf)
    tree = tree0(spark, sf)
    return trees.kdtree_knn(trees.with_leaf(b, tree), q, tree, 5, 2)


@query()
def q_kdtree_nmax(spark, sf):
    """Depth-first backtracking, stopped after two cells."""
    q, b = models.v0(spark, sf)
    tree = tree0(spark, sf)
    return trees.kdtree_knn(trees.with_leaf(b, tree), q, tree, 5, 2, "backtrack")


def forest_sql() -> str:
    s = oracle.v0()
    for t in (1, 2, 3):
        kd_sql(s, f"k{t}", "base", 3, forest_pick(t))
    s.add("pairs", " UNION ".join(f"SELECT qid, vec_id FROM k{t}_rank JOIN k{t}_leaf USING (leaf) WHERE rk <= 2" for t in (1, 2, 3)))
    return s.select(oracle.topk(f"SELECT p.qid, p.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM pairs p JOIN base v USING (vec_id) JOIN queries q ON q.qid = p.qid", 5))


@query(forest_sql())
def q_kdforest(spark, sf):
    """Three trees that split on different dimensions among the most variable; six leaves in all."""
    q, b = models.v0(spark, sf)
    return trees.kdforest_knn(b, q, [(tree0(spark, sf, t), None) for t in (1, 2, 3)], 5, 6, D)


@query()
def q_kdforest_rotated(spark, sf):
    """Trees over randomly rotated vectors."""
    q, b = models.v0(spark, sf)
    forest = []
    for seed in (1, 2):
        r = random_rotation(D, seed)
        forest.append((trees.kdtree_build(trees.rotate(b, r, "vec_id"), D, 3, approximate=True), r))
    return trees.kdforest_knn(b, q, forest, 5, 4, D)


@query()
def q_kdforest_pca(spark, sf):
    """Trees over vectors aligned with their principal axes and rotated."""
    from vecspark.operators.projection import pca_compress

    q, b = models.v0(spark, sf)
    _, axes = pca_compress(b, D, center=False)
    forest = []
    for seed in (3, 4):
        r = random_rotation(D, seed) @ axes
        forest.append((trees.kdtree_build(trees.rotate(b, r, "vec_id"), D, 3, approximate=True), r))
    return trees.kdforest_knn(b, q, forest, 5, 4, D)


def vocab_sql() -> Sql:
    s = oracle.pq(oracle.v0(), "top", "base", D, 1, 4, 3)
    oracle.components(s, "b_sub", "base", D, 1)
    oracle.nearest(s, "b_top", "b_sub", "top_cb")
    for i in range(4):
        s.add(f"m{i}", f"SELECT v.* FROM base v JOIN b_top t USING (vec_id) WHERE t.idx = {i}")
        oracle.pq(s, f"s{i}", f"m{i}", D, 1, 4, 3)
        oracle.components(s, f"m{i}_sub", f"m{i}", D, 1)
        oracle.nearest(s, f"m{i}_near", f"m{i}_sub", f"s{i}_cb")
    s.add("leaves", " UNION ALL ".join(f"SELECT vec_id, {i * 4} + idx AS leaf FROM m{i}_near" for i in range(4)))
    return s.add("leafc", " UNION ALL ".join(f"SELECT {i * 4} + idx AS leaf, list(c ORDER BY dim) AS e FROM s{i}_cb GROUP BY idx" for i in range(4)))


def vtree(spark, sf):
    return models.once(spark, (sf, "vtree"), lambda: trees.kmeans_tree(models.v0(spark, sf)[1], 4))


@query(vocab_sql().select("SELECT vec_id, CAST(leaf AS BIGINT) AS leaf FROM leaves"))
def q_vocab_tree(spark, sf):
    return trees.kmeans_leaves(models.v0(spark, sf)[1], vtree(spark, sf)).select("vec_id", "leaf")


@query(
    vocab_sql().add("near", f"SELECT qid, leaf, row_number() OVER (PARTITION BY qid ORDER BY {oracle.l2('q.e', 'c.e')}, leaf) AS rk FROM queries q, leafc c").select(
        oracle.topk(f"SELECT n.qid, v.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM near n JOIN leaves l USING (leaf) JOIN base v USING (vec_id) JOIN queries q ON q.qid = n.qid WHERE n.rk <= 3", 5)
    )
)
def q_kmtree_priority(spark, sf):
    q, b = models.v0(spark, sf)
    return trees.kmeans_tree_knn(b, q, vtree(spark, sf), 5, 3, D)


@query()
def q_auto_select(spark, sf):
    """Recall, seconds and bytes of forest and k-means tree as measured here, and the configuration chosen."""
    import pickle
    import time

    q, b = models.v0(spark, sf)
    truth = measures.ground_truth(q, b, D).cache()

    def timed(run):
        start = time.perf_counter()
        out = run()
        return out, time.perf_counter() - start

    built = {"kd": timed(lambda: trees.kdtree_build(b, D, 3)), "kmeans": timed(lambda: trees.kmeans_tree(b, 4))}
    measured = []
    for name, cells in (("kd", 1), ("kd", 4), ("kmeans", 2), ("kmeans", 8)):
        tree, build = built[name]

        def search(name=name, tree=tree, cells=cells):
            found = trees.kdtree_knn(trees.with_leaf(b, tree), q, tree, 10, cells) if name == "kd" else trees.kmeans_tree_knn(b, q, tree, 10, cells, D)
            return measures.recall_at(found, truth, (10,)).first()["recall"]

        recall, seconds = timed(search)
        measured.append((f"{name}-{cells}", recall, seconds, float(len(pickle.dumps(tree))), build))
    best = trees.auto_select(measured, 0.5, 1.0, 0.01, 0.01)
    return spark.createDataFrame([(*m, m[0] == best) for m in measured], "name string, recall double, search_seconds double, bytes double, build_seconds double, chosen boolean")


# -- bags of features --------------------------------------------------------------------------


def bof_sql() -> Sql:
    s = oracle.v2(source="SELECT doc_id * 67108864 + pos - 1 AS vec_id, line AS text FROM (SELECT doc_id, unnest(range(1, len(string_split(text, chr(10))) + 1)) AS pos, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE line <> ''")
    s.add("trainset", "SELECT * FROM v WHERE vec_id % 7 = 0")
    oracle.pq(s, "w", "trainset", 128, 1, 16, 1)
    oracle.components(s, "l_sub", "v", 128, 1)
    oracle.nearest(s, "words", "l_sub", "w_cb")
    s.add("idx", "SELECT vec_id // 67108864 AS doc_id, idx AS word, count(*) AS n FROM words GROUP BY 1, 2")
    return s.add("votes", "SELECT q.doc_id AS qid, i.doc_id, CAST(sum(q.n * i.n) AS BIGINT) AS votes FROM idx q JOIN idx i ON q.word = i.word AND q.doc_id <> i.doc_id WHERE q.doc_id % 50 = 0 GROUP BY 1, 2")


@query(bof_sql().select("SELECT qid, rk, doc_id, votes FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY votes DESC, doc_id) AS rk FROM votes) WHERE rk <= 3"))
def q_bof_vote(spark, sf):
    """Documents as bags of line descriptors; every fiftieth asks for its likes."""
    lines = T.descriptors(spark, sf).withColumn("vec_id", F.col("doc_id") * 67108864 + F.col("pos"))
    words = models.once(spark, (sf, "bof"), lambda: codebook.train_kmeans(lines.where(F.pmod("vec_id", F.lit(7)) == 0).select("vec_id", "e"), 16, 1))
    idx = bof.bof_index(lines, words).persist()
    return bof.bof_vote(idx, idx.where("doc_id % 50 = 0").withColumnRenamed("doc_id", "qid"), 3).select("qid", "rk", "doc_id", "votes")


# -- hashing -----------------------------------------------------------------------------------

W, M, TABLES = 8192, 4, 3


def hash_sql(count: int, w: int, seed: int = 42, src: str = "v", key: str = "vec_id") -> str:
    """SELECT of key, e, h (list) from src."""
    items = []
    for a, b in zip(lsh.normals(count, D, seed), lsh.offsets(count, w, seed + 1), strict=True):
        items.append(f"CAST(floor(CAST(list_sum(list_transform(list_zip(e, {a}), lambda z: z[1] * z[2])) + {b} AS DOUBLE) / {float(w * lsh.SCALE)}) AS BIGINT)")
    return f"SELECT {key}, e, [{', '.join(items)}] AS h FROM {src}"


def e2_sql(w: int = W, m: int = M, tables: int = TABLES, seed: int = 42, s: Sql | None = None, p: str = "e") -> Sql:
    s = s or oracle.v0()
    s.add(f"{p}_h", hash_sql(m * tables, w, seed))
    s.add(f"{p}_keys", f"SELECT vec_id, t AS tbl, array_to_string(h[t * {m} + 1 : t * {m} + {m}], ',') AS key FROM {p}_h, (SELECT unnest(range(0, {tables})) AS t)")
    return s.add(f"{p}_cand", f"SELECT q.vec_id AS qid, b.tbl, b.vec_id FROM {p}_keys b JOIN {p}_keys q USING (tbl, key) WHERE q.vec_id % 50 = 0")


@query(e2_sql().select("SELECT vec_id, CAST(tbl AS BIGINT) AS tbl, key FROM e_keys"))
def q_e2lsh_hash(spark, sf):
    return lsh.e2lsh_tables(T.vectors_embeddings(spark, sf), "vec_id", D, M, TABLES, W)


def e2_candidates(spark, sf, w: int = W, m: int = M, tables: int = TABLES, seed: int = 42):
    q, b = models.v0(spark, sf)
    return lsh.e2lsh_candidates(lsh.e2lsh_tables(b, "vec_id", D, m, tables, w, seed), lsh.e2lsh_tables(q, "qid", D, m, tables, w, seed))


RC = 30_000_000


@query(
    e2_sql(2 * W).add("few", f"SELECT DISTINCT qid, vec_id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY tbl, vec_id) AS rk FROM e_cand) WHERE rk <= {3 * TABLES}").select(
        oracle.topk(f"SELECT f.qid, f.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM few f JOIN base v USING (vec_id) JOIN queries q ON q.qid = f.qid WHERE {oracle.l2('q.e', 'v.e')} <= {RC}", 1)
    )
)
def q_e2lsh_rc(spark, sf):
    q, b = models.v0(spark, sf)
    return lsh.near_within(e2_candidates(spark, sf, 2 * W), b, q, D, TABLES, RC)


def rigorous_sql() -> str:
    s = oracle.v0()
    for radius in (1, 2, 4):
        e2_sql(W * radius, s=s, p=f"r{radius}")
        s.add(f"few{radius}", f"SELECT DISTINCT qid, vec_id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY tbl, vec_id) AS rk FROM r{radius}_cand WHERE qid <> vec_id) WHERE rk <= {3 * TABLES}")
        s.add(f"hit{radius}", f"SELECT {radius} AS radius, f.qid, f.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM few{radius} f JOIN base v USING (vec_id) JOIN queries q ON q.qid = f.qid WHERE {oracle.l2('q.e', 'v.e')} <= {RC} * {radius * radius}")
    s.add("hits", " UNION ALL ".join(f"SELECT * FROM hit{r}" for r in (1, 2, 4)))
    return s.select("SELECT qid, CAST(radius AS BIGINT) AS radius, vec_id, dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY radius, dist, vec_id) AS rk FROM hits) WHERE rk = 1")


@query(rigorous_sql())
def q_lsh_rigorous(spark, sf):
    """Tables for each radius of a geometric series: the answer of the least radius that has one."""
    q, b = models.v0(spark, sf)
    out = None
    for radius in (1, 2, 4):
        near = lsh.near_within(e2_candidates(spark, sf, W * radius).where("qid <> vec_id"), b, q, D, TABLES, RC * radius * radius)
        row = near.select(F.lit(radius).cast("long").alias("radius"), "qid", "vec_id", "dist")
        out = row if out is None else out.unionByName(row)
    return top_k(out, 1, ["qid"], ["radius", "dist", "vec_id"]).select("qid", "radius", "vec_id", "dist")


ADHOC = f"SELECT c.qid, c.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM (SELECT DISTINCT qid, vec_id FROM e_cand) c JOIN base v USING (vec_id) JOIN queries q ON q.qid = c.qid"


@query(e2_sql(2 * W).select(oracle.topk(ADHOC, 5)))
def q_lsh_adhoc(spark, sf):
    """One radius for all queries."""
    q, b = models.v0(spark, sf)
    pairs = e2_candidates(spark, sf, 2 * W).select("qid", "vec_id").distinct()
    return top_k(lsh.exact_distances(pairs, b, q, D), 5, ["qid"], ["dist", "vec_id"])


@query(e2_sql(2 * W).add("found", oracle.topk(ADHOC, 5)).add("truth", oracle.topk(EXACT_SQL, 5)).select("SELECT f.qid, f.rk, round(sqrt(CAST(f.dist AS DOUBLE)) / sqrt(CAST(greatest(t.dist, 1) AS DOUBLE)), 6) AS ratio FROM found f JOIN truth t USING (qid, rk)"))
def q_c_approx(spark, sf):
    q, b = models.v0(spark, sf)
    return measures.approximation(q_lsh_adhoc(spark, sf), top_k(exact(q, b, D), 5, ["qid"], ["dist", "vec_id"]))


LSB_BITS, LSB_M, LSB_W = 6, 4, 2048


def lsb_sql() -> str:
    s = oracle.v0()
    width = LSB_BITS * LSB_M
    for t in range(2):
        s.add(f"h{t}", hash_sql(LSB_M, LSB_W, 100 + 10 * t))
        place = " + ".join(f"(((least(greatest(h[{j + 1}] + 32, 0), 63) >> {bit}) & 1) << {bit * LSB_M + LSB_M - 1 - j})" for bit in range(LSB_BITS) for j in range(LSB_M))
        s.add(f"z{t}", f"SELECT vec_id, {place} AS z FROM h{t}")
        s.add(f"p{t}", f"SELECT q.vec_id AS qid, b.vec_id, row_number() OVER (PARTITION BY q.vec_id ORDER BY CASE WHEN xor(q.z, b.z) = 0 THEN {width} ELSE {width} - length(bin(xor(q.z, b.z))) END DESC, b.vec_id) AS rk FROM z{t} b, z{t} q WHERE q.vec_id % 50 = 0")
    s.add("pairs", " UNION ".join(f"SELECT qid, vec_id FROM p{t} WHERE rk <= 20" for t in range(2)))
    return s.select(oracle.topk(f"SELECT p.qid, p.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM pairs p JOIN base v USING (vec_id) JOIN queries q ON q.qid = p.qid", 5))


@query(lsb_sql())
def q_lsb_forest(spark, sf):
    q, b = models.v0(spark, sf)
    pairs = None
    for t in range(2):
        z = [lsh.z_values(f, k, D, LSB_M, LSB_W, LSB_BITS, 100 + 10 * t) for f, k in ((b, "vec_id"), (q, "qid"))]
        found = lsh.lsb_candidates(*z, LSB_BITS * LSB_M, 20)
        pairs = found if pairs is None else pairs.unionByName(found)
    return top_k(lsh.exact_distances(pairs.distinct(), b, q, D), 5, ["qid"], ["dist", "vec_id"])


C2_LEAST = 4


def c2_sql() -> str:
    s = oracle.v0().add("h", hash_sql(8, 2048, 7)).add("longs", "SELECT vec_id, unnest(range(0, 8)) AS f, unnest(h) AS x FROM h")
    s.add("counts", "SELECT r, q.vec_id AS qid, b.vec_id, count(*) AS n FROM (SELECT unnest([1, 2, 4]) AS r), longs q, longs b WHERE q.f = b.f AND q.vec_id % 50 = 0 AND q.vec_id <> b.vec_id AND floor(CAST(q.x AS DOUBLE) / r) = floor(CAST(b.x AS DOUBLE) / r) GROUP BY 1, 2, 3")
    s.add("cand", f"SELECT * FROM counts WHERE n >= {C2_LEAST}")
    s.add("pick", "SELECT qid, coalesce(min(r) FILTER (WHERE many >= 5), max(r)) AS r FROM (SELECT qid, r, count(*) AS many FROM cand GROUP BY 1, 2) GROUP BY 1")
    near = oracle.topk(f"SELECT c.qid, c.vec_id, c.r, {oracle.l2('q.e', 'v.e')} AS dist FROM cand c JOIN pick USING (qid, r) JOIN base v USING (vec_id) JOIN queries q ON q.qid = c.qid", 5, ", CAST(r AS BIGINT) AS radius")
    return s.select(near)


@query(c2_sql())
def q_c2lsh(spark, sf):
    """Vectors that collide in at least half of eight functions; the radius grows until five do."""
    q, b = models.v0(spark, sf)
    hb, hq = lsh.hashed(b, "vec_id", D, 8, 2048, 7).persist(), lsh.hashed(q, "qid", D, 8, 2048, 7).persist()
    return lsh.c2lsh_search(hb, hq, b, q, 8, (1, 2, 4), C2_LEAST, 5, D)


def sk_sql() -> str:
    s = oracle.v0()
    for t in range(3):
        s.add(f"h{t}", hash_sql(3, 4096, 200 + 10 * t))
        s.add(f"k{t}", f"SELECT vec_id, (h[1] + 512) * 1048576 + (h[2] + 512) * 1024 + h[3] + 512 AS k FROM h{t}")
        s.add(f"r{t}", f"SELECT vec_id, k, row_number() OVER (ORDER BY k, vec_id) - 1 AS rank FROM k{t}")
        s.add(f"a{t}", f"SELECT q.vec_id AS qid, count(*) FILTER (WHERE b.k < q.k) AS spot FROM k{t} q, r{t} b WHERE q.vec_id % 50 = 0 GROUP BY 1")
        s.add(f"p{t}", f"SELECT qid, vec_id FROM r{t}, a{t} WHERE rank >= spot - 10 AND rank < spot + 10")
    s.add("pairs", " UNION ".join(f"SELECT * FROM p{t}" for t in range(3)))
    return s.select(oracle.topk(f"SELECT p.qid, p.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM pairs p JOIN base v USING (vec_id) JOIN queries q ON q.qid = p.qid", 5))


@query(sk_sql())
def q_sklsh(spark, sf):
    q, b = models.v0(spark, sf)
    pairs = None
    for t in range(3):
        found = lsh.sk_candidates(lsh.sk_keys(b, "vec_id", D, 3, 4096, 200 + 10 * t), lsh.sk_keys(q, "qid", D, 3, 4096, 200 + 10 * t), 10)
        pairs = found if pairs is None else pairs.unionByName(found)
    return top_k(lsh.exact_distances(pairs.distinct(), b, q, D), 5, ["qid"], ["dist", "vec_id"])


# -- optimised and additive quantizers ---------------------------------------------------------


def opq0(spark, sf):
    floats = models.v0(spark, sf)[1].select("vec_id", F.transform("e", lambda x: x.cast("double")).alias("e"))
    return models.once(spark, (sf, "opq"), lambda: codebook.train_opq(floats, 8, 4, 6))


@query()
def q_opq_search(spark, sf):
    """Rotated and quantized; queries are rotated before their tables are made."""
    model, _ = opq0(spark, sf)
    q, b = models.v0(spark, sf)
    out = scan.adc_topk(encode.encode_pq(b, model), index.lookup_tables(q, model), 8, 10)
    return out.withColumn("dist", F.round("dist", 3))


@query()
def q_opq_errors(spark, sf):
    """Training error before each turn: it must not rise."""
    _, errors = opq0(spark, sf)
    return spark.createDataFrame([(i, float(e)) for i, e in enumerate(errors)], "turn long, error double")


def chain_sql(m: int, k: int, tree: bool) -> Sql:
    """Books b{j}(idx, e) by k-means of residuals, codes by the greedy chain."""
    s = oracle.v0().add("rest0", "SELECT vec_id, e FROM base")
    for j in range(m):
        at = additive.blocks_of(j, m, D) if tree else slice(0, D)
        w = at.stop - at.start
        s.add(f"seen{j}", f"SELECT vec_id, e[{at.start + 1}:{at.stop}] AS e FROM rest{j}")
        oracle.pq(s, f"b{j}", f"seen{j}", w, 1, k, 3)
        padded = f"list_concat(list_concat({[0] * at.start}::BIGINT[], list(c ORDER BY dim)), {[0] * (D - at.stop)}::BIGINT[])"
        s.add(f"bk{j}", f"SELECT idx, {padded} AS e FROM b{j}_cb GROUP BY idx")
        s.add(f"near{j}", f"SELECT vec_id, min({oracle.l2('r.e', 'b.e')} * 65536 + idx) % 65536 AS idx FROM rest{j} r, bk{j} b GROUP BY vec_id")
        s.add(f"rest{j + 1}", f"SELECT r.vec_id, {oracle.minus('r.e', 'b.e')} AS e FROM rest{j} r JOIN near{j} n USING (vec_id) JOIN bk{j} b ON b.idx = n.idx")
    s.add("recon", f"SELECT v.vec_id, {oracle.minus('v.e', 'r.e')} AS e FROM base v JOIN rest{m} r USING (vec_id)")
    return s


CHAIN = f"SELECT q.qid, r.vec_id, {oracle.l2('q.e', 'r.e')} AS dist FROM queries q, recon r"


def chain_query(spark, sf, tree: bool):
    q, b = models.v0(spark, sf)
    model = models.once(spark, (sf, "chain", tree), lambda: additive.train_residual_chain(b, 3, 8, D, 3, tree))
    rows = [(r["qid"], r["e"]) for r in q.collect()]
    return top_k(additive.additive_scan(additive.encode_additive(b, model), rows, model), 10, ["qid"], ["dist", "vec_id"])


@query(chain_sql(3, 8, False).select(oracle.topk(CHAIN, 10)))
def q_aq_distance(spark, sf):
    """Sums of full-dimension centroids: query tables and a table for each pair of parts."""
    return chain_query(spark, sf, False)


@query(chain_sql(3, 8, True).select(oracle.topk(CHAIN, 10)))
def q_tq_distance(spark, sf):
    """Only neighbouring parts overlap: a pair table for each edge of the chain."""
    return chain_query(spark, sf, True)


@query(oracle.encode(oracle.pq(oracle.v0(), "p", "base", D, 4, 16, 3), "codes", "p", "base", D, 4).add("recon", "SELECT n.vec_id, list(p.c ORDER BY p.part, p.dim) AS e FROM codes_near n JOIN p_cb p USING (part, idx) GROUP BY n.vec_id").select(oracle.topk(CHAIN, 10)))
def q_cq_distance(spark, sf):
    """Composite sums with the constant zero: look-ups as many as parts."""
    q, b = models.v0(spark, sf)
    pq = models.pq0(spark, sf, 4, 16)
    books = np.zeros((4, 16, D), np.int64)
    for j in range(4):
        books[j][:, j * 16 : (j + 1) * 16] = pq.books[j]
    model = additive.Additive(books, ())
    rows = [(r["qid"], r["e"]) for r in q.collect()]
    return top_k(additive.additive_scan(encode.encode_pq(b, pq), rows, model), 10, ["qid"], ["dist", "vec_id"])


def encoding_error(base, model, *beam):
    """Mean squared error of all the base's codes, encoded on the executors."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                x = np.array(batch.slice(at, 512).column(0).to_pylist(), float)
                codes = model.encode(x, *beam)
                whole = sum(model.books[j][codes[:, j]] for j in range(codes.shape[1]))
                yield pa.RecordBatch.from_pydict({"total": pa.array([float(((x - whole) ** 2).sum())]), "n": pa.array([len(x)], pa.int64())})

    r = base.select("e").mapInArrow(run, "total double, n long").agg(F.sum("total").alias("total"), F.sum("n").alias("n")).first()
    return r["total"] / r["n"] if r["n"] else 0.0


@query()
def q_cq_trained(spark, sf):
    """Trained composite quantizer (on a bounded sample): error over the whole base and spread of its cross products."""
    b = models.v0(spark, sf)[1]
    rows = b.orderBy("vec_id").limit(400).collect()
    x = np.array([r["e"] for r in rows], float)
    model, constant = additive.train_composite(x, 4, 8)
    return spark.createDataFrame([(encoding_error(b, model), float(constant))], "error double, constant double")


@query()
def q_aq_beam(spark, sf):
    """Error of greedy and beam encoding of the whole base with the same codebooks."""
    q, b = models.v0(spark, sf)
    model = models.once(spark, (sf, "chain", False), lambda: additive.train_residual_chain(b, 3, 8, D, 3, False))
    rows = [(beam, encoding_error(b, model, beam)) for beam in (1, 4, 8)]
    return spark.createDataFrame(rows, "beam long, error double")
