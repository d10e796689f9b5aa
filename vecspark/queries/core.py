"""Queries of the pipeline: quantize, index, tables, plain scan."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecspark.functions import bits, vectors
from vecspark.functions.ranking import top_k
from vecspark.operators import codebook, encode, index, packed, scan
from vecspark.operators.exact import counts_within, metric_pairs, nearest_rows, rows_within
from vecspark.queries import models, oracle
from vecspark.queries.oracle import Sql
from vecspark.queries.registry import query
from vecspark.sources import tables as T


def codebook_frame(spark, books) -> DataFrame:
    """A codebook in long form: (part, idx, dim, c)."""
    rows = [(j, i, q, int(x)) for j, book in enumerate(books) for i, c in enumerate(book) for q, x in enumerate(c)]
    return spark.createDataFrame(rows, "part long, idx long, dim long, c long")


def long_codes(codes: DataFrame, m: int, keys=("vec_id",)) -> DataFrame:
    return codes.select(*[F.col(c).cast("long") for c in (*keys, *encode.code_columns(m))])


def code_select(m: int, keys: str = "vec_id") -> str:
    return f"SELECT {keys}, " + ", ".join(f"CAST(c[{j + 1}] AS BIGINT) AS c{j}" for j in range(m)) + " FROM codes"


def pq_sql(m: int, k: int, iters: int = 3, coded: bool = True, tabled: bool = False) -> Sql:
    s = oracle.pq(oracle.v0(), "p", "base", 64, m, k, iters)
    if coded:
        oracle.encode(s, "codes", "p", "base", 64, m)
    if tabled:
        oracle.tables(s, "tabs", "p", "queries", 64, m)
    return s


CB = "SELECT CAST(part AS BIGINT) AS part, CAST(idx AS BIGINT) AS idx, CAST(dim AS BIGINT) AS dim, CAST(c AS BIGINT) AS c FROM"


def exact(queries: DataFrame, base: DataFrame, d: int) -> DataFrame:
    return base.crossJoin(F.broadcast(queries.withColumnRenamed("e", "q"))).select("qid", "vec_id", vectors.l2sq(F.col("q"), F.col("e"), d).alias("dist"))


EXACT_SQL = f"SELECT q.qid, v.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM queries q, base v"


@query(oracle.v0().select(oracle.topk(EXACT_SQL, 10)))
def q_bruteforce_knn(spark, sf):
    q, b = models.v0(spark, sf)
    return top_k(exact(q, b, 64), 10, ["qid"], ["dist", "vec_id"])


@query(oracle.v0().select(oracle.topk(EXACT_SQL, 5)))
def q_knn(spark, sf):
    q, b = models.v0(spark, sf)
    return top_k(exact(q, b, 64), 5, ["qid"], ["dist", "vec_id"])


RADIUS = 22_000_000


@query(oracle.v0().select(f"SELECT * FROM ({EXACT_SQL}) WHERE dist <= {RADIUS}"))
def q_radius(spark, sf):
    return rows_within(*models.v0(spark, sf), RADIUS)


@query(
    oracle.v0()
    .add("near", EXACT_SQL)
    .add("kth", "SELECT qid, max(dist) AS eps FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, vec_id) AS rk FROM near) WHERE rk <= 10 GROUP BY qid")
    .select("SELECT qid, count(*) AS inside, count(*) FILTER (WHERE dist = eps) AS at_edge FROM near JOIN kth USING (qid) WHERE dist <= eps GROUP BY qid")
)
def q_radius_equals_knn(spark, sf):
    """With the k-th distance as radius, the ball holds the k neighbours (and ties at its edge)."""
    q, b = models.v0(spark, sf)
    kth = nearest_rows(q, b, 10).groupBy("qid").agg(F.max("dist").alias("eps"))
    return counts_within(q, b, {r["qid"]: r["eps"] for r in kth.collect()})  # a row for each query


@query(
    oracle.v0().select(
        "SELECT qid, vec_id, CAST(list_sum(list_transform(list_zip(q.e, v.e), lambda z: abs(z[1] - z[2]))) AS BIGINT) AS l1, "
        f"{oracle.l2('q.e', 'v.e')} AS l2sq, round(sqrt(CAST({oracle.l2('q.e', 'v.e')} AS DOUBLE)), 4) AS l2, "
        "round(CAST(list_sum(list_transform(list_zip(q.e, v.e), lambda z: z[1] * z[2])) AS DOUBLE) / (sqrt(CAST(list_sum(list_transform(q.e, lambda x: x * x)) AS DOUBLE)) * sqrt(CAST(list_sum(list_transform(v.e, lambda x: x * x)) AS DOUBLE))), 9) AS cosine "
        "FROM queries q, base v"
    )
)
def q_metrics(spark, sf):
    q, b = models.v0(spark, sf)
    cosine = F.col("dot") / (F.sqrt(F.col("qq").cast("double")) * F.sqrt(F.col("vv").cast("double")))
    return metric_pairs(q, b).select("qid", "vec_id", "l1", "l2sq", F.round(F.sqrt(F.col("l2sq").cast("double")), 4).alias("l2"), F.round(cosine, 9).alias("cosine"))


@query(
    "WITH n AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings) "
    "SELECT vec_id, i AS dim, round(x / norm, 9) AS x FROM (SELECT vec_id, unnest(range(0, 64)) AS i, unnest(e) AS x, sqrt(list_sum(list_transform(e, lambda y: y * y))) AS norm FROM n)"
)
def q_l2_normalize(spark, sf):
    v = T.load(spark, sf, "embeddings").select("vec_id", vectors.l2_normalize(F.col("embedding")).alias("e"))
    return v.select("vec_id", F.posexplode("e").alias("dim", "x")).select("vec_id", F.col("dim").cast("long").alias("dim"), F.round("x", 9).alias("x"))


@query()
def q_pca_compress(spark, sf):
    """Projection on the leading axes of the covariance; the d x d moments are one aggregate."""
    from vecspark.operators.projection import pca_compress

    v = T.load(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    return pca_compress(v, 16)[0].select("vec_id", F.posexplode("e").alias("dim", "x")).withColumn("x", F.round("x", 6))


@query(oracle.pq(oracle.v0(), "p", "base", 64, 1, 16, 3).select(f"{CB} p_cb"))
def q_kmeans_codebook(spark, sf):
    return codebook_frame(spark, models.pq0(spark, sf, 1, 16).books)


@query(oracle.nearest(oracle.components(oracle.pq(oracle.v0(), "p", "base", 64, 1, 16, 3), "all_sub", "v", 64, 1), "near", "all_sub", "p_cb").select("SELECT vec_id, CAST(idx AS BIGINT) AS idx FROM near"))
def q_vq_assign(spark, sf):
    book = models.pq0(spark, sf, 1, 16).books[0]
    return encode.assign(T.vectors_embeddings(spark, sf), book).select("vec_id", "idx")


@query(
    oracle.nearest(oracle.components(oracle.pq(oracle.v0(), "p", "base", 64, 1, 16, 3), "all_sub", "v", 64, 1), "near", "all_sub", "p_cb").select(
        "SELECT vec_id, CAST(dim AS BIGINT) AS dim, CAST(c AS BIGINT) AS c FROM near JOIN p_cb USING (idx)"
    )
)
def q_vq_decode(spark, sf):
    book = models.pq0(spark, sf, 1, 16).books[0]
    codes = encode.assign(T.vectors_embeddings(spark, sf), book).select("vec_id", "idx")
    frame = codebook_frame(spark, [book]).select("idx", "dim", "c")
    return codes.join(F.broadcast(frame), "idx").select("vec_id", "dim", "c")


@query()
def q_same_size_partition(spark, sf):
    """Sizes of equal-size clusters of the first part's 256 centroids."""
    label = codebook.same_size_partition(models.pq0(spark, sf, 8, 256).books[0], 16)
    return spark.createDataFrame([(i, int(c)) for i, c in enumerate(label)], "idx long, cluster long").groupBy("cluster").agg(F.count("*").alias("n"))


@query(pq_sql(8, 16, coded=False).select(f"{CB} p_cb"))
def q_pq_codebook(spark, sf):
    return codebook_frame(spark, models.pq0(spark, sf, 8, 16).books)


@query(pq_sql(8, 16).select(code_select(8)))
def q_pq_encode(spark, sf):
    return long_codes(encode.encode_pq(models.v0(spark, sf)[1], models.pq0(spark, sf, 8, 16)), 8)


@query(pq_sql(8, 16).select("SELECT n.vec_id, CAST(p.part * 8 + p.dim AS BIGINT) AS dim, CAST(p.c AS BIGINT) AS c FROM codes_near n JOIN p_cb p USING (part, idx)"))
def q_pq_decode(spark, sf):
    model = models.pq0(spark, sf, 8, 16)
    out = encode.decode_pq(encode.encode_pq(models.v0(spark, sf)[1], model), model)
    return out.select("vec_id", F.posexplode("e").alias("dim", "c")).select("vec_id", F.col("dim").cast("long").alias("dim"), "c")


GRID = ((16, 4), (8, 16), (4, 256))


def grid_sql() -> str:
    s = oracle.v0()
    for m, k in GRID:
        oracle.pq(s, f"g{m}", "base", 64, m, k, 3)
        oracle.encode(s, f"x{m}", f"g{m}", "base", 64, m)
        s.add(f"e{m}", f"SELECT CAST(sum((u.x - c.c) * (u.x - c.c)) AS BIGINT) AS total, count(DISTINCT u.vec_id) AS n FROM x{m}_sub u JOIN x{m}_near a USING (vec_id, part) JOIN g{m}_cb c ON c.part = a.part AND c.idx = a.idx AND c.dim = u.dim")
    rows = [f"SELECT CAST({m} AS BIGINT) AS m, CAST({int(math.log2(k))} AS BIGINT) AS b, CAST({m * k * 4} AS BIGINT) AS table_bytes, CAST(total // n AS BIGINT) AS error FROM e{m}" for m, k in GRID]
    return s.select(" UNION ALL ".join(rows))


@query(grid_sql())
def q_param_grid(spark, sf):
    """Code length fixed at 32 bits: fewer, finer parts lower the error and enlarge the tables."""
    _, b = models.v0(spark, sf)
    out = None
    for m, k in GRID:
        model = models.pq0(spark, sf, m, k)
        error = reconstruction(b, model).agg(F.floor(F.sum("error") / F.count("*")).cast("long").alias("error"))
        row = error.select(F.lit(m).cast("long").alias("m"), F.lit(model.b).cast("long").alias("b"), F.lit(m * k * 4).cast("long").alias("table_bytes"), "error")
        out = row if out is None else out.unionByName(row)
    return out


def reconstruction(frame: DataFrame, model) -> DataFrame:
    """(vec_id, error): squared distance to the reconstruction, in one map."""
    from vecspark.plans.kernels import map_batches, matrix

    def make():
        def each(batch):
            x = matrix(batch)
            return {"vec_id": batch["vec_id"], "error": ((x - model.decode(model.encode(x))) ** 2).sum(axis=1)}

        return each

    return map_batches(frame.select("vec_id", "e"), make, f"vec_id long, error {model.number}")


@query(pq_sql(8, 16).select("SELECT CAST(sum((u.x - c.c) * (u.x - c.c)) AS BIGINT) AS total, count(DISTINCT u.vec_id) AS n FROM codes_sub u JOIN codes_near a USING (vec_id, part) JOIN p_cb c ON c.part = a.part AND c.idx = a.idx AND c.dim = u.dim"))
def q_quant_error(spark, sf):
    return reconstruction(models.v0(spark, sf)[1], models.pq0(spark, sf, 8, 16)).agg(F.sum("error").alias("total"), F.count("*").alias("n"))


@query(pq_sql(8, 16).select("SELECT vec_id, " + " + ".join(f"c[{j + 1}] * {1 << (4 * j)}" for j in range(8)) + " AS packed, CAST(c[3] AS BIGINT) AS third FROM codes"))
def q_pack_bits(spark, sf):
    """Four-bit codes in one long, and one of them taken out again."""
    codes = encode.encode_pq(models.v0(spark, sf)[1], models.pq0(spark, sf, 8, 16))
    packed = bits.pack_bits([F.col(c) for c in encode.code_columns(8)], 4)
    return codes.select("vec_id", packed.alias("packed")).withColumn("third", bits.unpack_bits(F.col("packed"), 2, 4))


@query("SELECT vec_id, vec_id * 31 % 8192 AS a, vec_id * 57 % 8192 AS b, (vec_id * 31 % 8192) + (vec_id * 57 % 8192) * 8192 AS packed FROM embeddings")
def q_pack_odd_bits(spark, sf):
    """Thirteen-bit codes need shifts and masks across byte borders."""
    v = T.load(spark, sf, "embeddings").select("vec_id", F.expr("vec_id * 31 % 8192").alias("x"), F.expr("vec_id * 57 % 8192").alias("y"))
    packed = v.select("vec_id", bits.pack_bits([F.col("x"), F.col("y")], 13).alias("packed"))
    return packed.select("vec_id", bits.unpack_bits(F.col("packed"), 0, 13).alias("a"), bits.unpack_bits(F.col("packed"), 1, 13).alias("b"), "packed")


ADC = f"SELECT qid, vec_id, CAST({oracle.adc(8)} AS BIGINT) AS dist FROM codes c, tabs t"


def coded(spark, sf, m=8, k=16):
    q, b = models.v0(spark, sf)
    model = models.pq0(spark, sf, m, k)
    codes = models.once(spark, (sf, "codes0", m, k), lambda: encode.encode_pq(b, model).persist())
    return codes, index.lookup_tables(q, model), model


@query(pq_sql(8, 16, coded=False, tabled=True).select("SELECT qid, CAST(part AS BIGINT) AS part, CAST(idx AS BIGINT) AS idx, dist FROM tabs_long"))
def q_lookup_tables(spark, sf):
    _, tabs, model = coded(spark, sf)
    parts = F.explode(F.array(*[F.struct(F.lit(j).cast("long").alias("part"), F.col(f"t{j}").alias("t")) for j in range(8)]))
    return tabs.select("qid", parts.alias("x")).select("qid", "x.part", F.posexplode("x.t").alias("idx", "dist")).select("qid", "part", F.col("idx").cast("long").alias("idx"), "dist")


@query(pq_sql(8, 16, tabled=True).select(ADC))
def q_adc_distance(spark, sf):
    codes, tabs, _ = coded(spark, sf)
    return scan.with_tables(codes, tabs).select("qid", "vec_id", scan.adc(8).alias("dist"))


@query(pq_sql(8, 16, tabled=True).select(oracle.topk(ADC, 10)))
def q_adc_topk(spark, sf):
    codes, tabs, _ = coded(spark, sf)
    return scan.adc_topk(codes, tabs, 8, 10)


@query(pq_sql(8, 16, tabled=True).select(oracle.topk(ADC, 100)))
def q_adc_exhaustive(spark, sf):
    """All packed codes scanned, by the kernel of words."""
    q, b = models.v0(spark, sf)
    model = models.pq0(spark, sf, 8, 16)
    return packed.plain_scan(packed.encode_packed(b, model), q, model, 100)


def table_rows(tabs: DataFrame, m: int, listed: bool = False) -> list:
    """Tables of a query batch on the driver: [(qid, list_id, m x k)]."""
    return [(r["qid"], r["list_id"] if listed else None, [r[f"t{j}"] for j in range(m)]) for r in tabs.collect()]


@query(pq_sql(8, 16, tabled=True).select(oracle.topk(ADC, 10)))
def q_adc_packed(spark, sf):
    """One long holds all components of a code; shifts and masks take them apart."""
    codes, tabs, _ = coded(spark, sf)
    packed = codes.select("vec_id", bits.pack_bits([F.col(c) for c in encode.code_columns(8)], 4).alias("word"))
    scored = scan.with_tables(packed, tabs).select("qid", "vec_id", scan.adc_packed(F.col("word"), 8, 4).alias("dist"))
    return top_k(scored, 10, ["qid"], ["dist", "vec_id"])


def _variant(name: str):
    def run(spark, sf):
        codes, tabs, _ = coded(spark, sf)
        return scan.kernel_topk(codes, table_rows(tabs, 8), 8, 10, name, 4)

    run.__name__ = f"q_adc_{name}"
    return query(pq_sql(8, 16, tabled=True).select(oracle.topk(ADC, 10)))(run)


q_adc_vertical, q_adc_gather = _variant("vertical"), _variant("gather")


# -- indexes -----------------------------------------------------------------------------------


def ivf_sql(ma: int | None = None, residual: bool = True, k: int = 8, m: int = 8, kk: int = 16) -> Sql:
    s = oracle.ivf(oracle.v0(), 64, k, m, kk, residual=residual)
    if ma:
        oracle.probes(s, ma)
        s.add("shifted", f"SELECT qid, list_id, {'e' if residual else 'whole AS e'} FROM probes")
        oracle.tables(s, "tabs", "fi", "shifted", 64, m, "qid, list_id")
    return s


IVF_ADC = f"SELECT qid, vec_id, CAST({oracle.adc(8)} AS BIGINT) AS dist FROM codes c JOIN tabs t ON c.list_id = t.list_id"


@query(ivf_sql().select(code_select(8, "vec_id, CAST(list_id AS BIGINT) AS list_id")))
def q_ivf_build(spark, sf):
    return long_codes(models.ivf0(spark, sf).encode(models.v0(spark, sf)[1]), 8, ("vec_id", "list_id"))


@query(ivf_sql(2).select("SELECT qid, CAST(list_id AS BIGINT) AS list_id, dist, rk FROM probes"))
def q_ivf_probe_ma(spark, sf):
    return index.probes(models.v0(spark, sf)[0], models.ivf0(spark, sf).coarse, 2)


@query(
    oracle.probes(ivf_sql(), 8)
    .add("sizes", "SELECT list_id, count(*) AS n FROM codes GROUP BY list_id")
    .select("SELECT qid, CAST(list_id AS BIGINT) AS list_id, rk, CAST(before AS BIGINT) AS before FROM (SELECT p.qid, p.list_id, p.rk, coalesce(sum(coalesce(n, 0)) OVER (PARTITION BY qid ORDER BY rk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM probes p LEFT JOIN sizes USING (list_id)) WHERE before < 100")
)
def q_ivf_probe_budget(spark, sf):
    ivf = models.ivf0(spark, sf)
    q, b = models.v0(spark, sf)
    return index.probes_by_budget(q, ivf.coarse, index.list_sizes(ivf.encode(b)), 100)


@query(ivf_sql(2).select("SELECT qid, CAST(list_id AS BIGINT) AS list_id, CAST(unnest(range(0, 64)) AS BIGINT) AS dim, unnest(e) AS x FROM probes"))
def q_index_step(spark, sf):
    q, _ = models.v0(spark, sf)
    out = index.index_step(q, models.ivf0(spark, sf).coarse, 2)
    return out.select("qid", "list_id", F.posexplode("e").alias("dim", "x")).withColumn("dim", F.col("dim").cast("long"))


def ivf_search(spark, sf, r: int, ma: int, residual: bool = True) -> DataFrame:
    ivf = models.ivf0(spark, sf, residual=residual)
    q, b = models.v0(spark, sf)
    tabs = ivf.tables(q, index.probes(q, ivf.coarse, ma))
    return scan.adc_topk(ivf.encode(b), tabs, 8, r, ("list_id",))


@query(ivf_sql(2).select(oracle.topk(IVF_ADC, 10)))
def q_ivf_search(spark, sf):
    return ivf_search(spark, sf, 10, 2)


@query(ivf_sql(2, residual=False).select(oracle.topk(IVF_ADC, 10)))
def q_ivf_search_plain_codes(spark, sf):
    """Lists of codes of the vectors themselves."""
    return ivf_search(spark, sf, 10, 2, residual=False)


@query(
    oracle.probes(oracle.nearest(oracle.components(oracle.centroid_lists(oracle.pq(oracle.v0(), "co", "base", 64, 1, 8, 3), "cents", "co"), "b_sub", "base", 64, 1), "own", "b_sub", "co_cb"), 2).select(
        oracle.topk(f"SELECT p.qid, v.vec_id, {oracle.l2('p.whole', 'v.e')} AS dist FROM probes p JOIN own o ON o.idx = p.list_id JOIN base v USING (vec_id)", 10)
    )
)
def q_ivf_search_vectors(spark, sf):
    """Lists of the vectors themselves: exact distances within the probed lists."""
    coarse = models.ivf0(spark, sf).coarse
    q, b = models.v0(spark, sf)
    held = encode.assign(b, coarse, name="list_id")
    probed = index.probes(q, coarse, 2).select("qid", "list_id").join(q.withColumnRenamed("e", "q"), "qid")
    scored = held.join(F.broadcast(probed), "list_id").select("qid", "vec_id", vectors.l2sq(F.col("q"), F.col("e"), 64).alias("dist"))
    return top_k(scored, 10, ["qid"], ["dist", "vec_id"])


@query(ivf_sql(3).select(oracle.topk(IVF_ADC, 20)))
def q_ann_search(spark, sf):
    """Index, tables, scan over three lists, with hot lists dealt over two sub-lists each."""
    ivf = models.ivf0(spark, sf)
    q, b = models.v0(spark, sf)
    codes, tabs = index.salted(ivf.encode(b), ivf.tables(q, index.probes(q, ivf.coarse, 3)), 2)
    return scan.adc_topk(codes, tabs, 8, 20, ("list_id", "sub"))


@query(ivf_sql().select("SELECT CAST(list_id AS BIGINT) AS list_id, count(*) AS n FROM codes GROUP BY list_id"))
def q_list_sizes(spark, sf):
    return index.list_sizes(models.ivf0(spark, sf).encode(models.v0(spark, sf)[1]))


@query(
    ivf_sql(2)
    .add("sizes", "SELECT list_id, count(*) AS n FROM codes GROUP BY list_id")
    .select("SELECT qid, CAST(sum(n) AS BIGINT) AS scanned, round(CAST(sum(n) AS DOUBLE) / (SELECT count(*) FROM codes), 6) AS share FROM probes JOIN sizes USING (list_id) GROUP BY qid")
)
def q_scan_fraction(spark, sf):
    ivf = models.ivf0(spark, sf)
    q, b = models.v0(spark, sf)
    sizes = index.list_sizes(ivf.encode(b))
    n = sizes.agg(F.sum("n").alias("whole"))
    return index.probes(q, ivf.coarse, 2).join(F.broadcast(sizes), "list_id").groupBy("qid").agg(F.sum("n").alias("scanned")).crossJoin(F.broadcast(n)).select("qid", "scanned", F.round(F.col("scanned").cast("double") / F.col("whole"), 6).alias("share"))


def imi_sql(budget: int | None = None, rotated: bool = False) -> Sql:
    s = oracle.pq(oracle.v0(rotated), "h", "base", 64, 2, 4, 3)
    oracle.encode(s, "cells", "h", "base", 64, 2)
    if budget is not None:
        oracle.tables(s, "ht", "h", "queries", 64, 2)
        s.add("sizes", "SELECT c[1] * 4 + c[2] AS list_id, count(*) AS n FROM cells GROUP BY 1")
        s.add("ranks", "SELECT qid, part, idx, dist, row_number() OVER (PARTITION BY qid, part ORDER BY dist, idx) AS rank FROM ht_long")
        s.add("pairs", "SELECT a.qid, a.idx * 4 + b.idx AS list_id, a.dist + b.dist AS dist, row_number() OVER (PARTITION BY a.qid ORDER BY a.dist + b.dist, a.rank, b.rank) AS rk FROM ranks a JOIN ranks b ON a.qid = b.qid AND a.part = 0 AND b.part = 1")
        s.add("seq", f"SELECT * FROM (SELECT qid, list_id, dist, rk, coalesce(sum(coalesce(n, 0)) OVER (PARTITION BY qid ORDER BY rk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM pairs LEFT JOIN sizes USING (list_id)) WHERE before < {budget}")
    return s


@query(imi_sql().select("SELECT vec_id, CAST(c[1] AS BIGINT) AS i, CAST(c[2] AS BIGINT) AS j FROM cells"))
def q_imi_build(spark, sf):
    return models.imi0(spark, sf).cells(models.v0(spark, sf)[1])


@query(imi_sql(50).select("SELECT qid, CAST(list_id AS BIGINT) AS list_id, dist, rk, CAST(before AS BIGINT) AS before FROM seq"))
def q_imi_sequence(spark, sf):
    imi = models.imi0(spark, sf)
    q, b = models.v0(spark, sf)
    return imi.sequence(q, index.list_sizes(imi.encode(b)), 50)


@query(imi_sql(50).select("SELECT qid, count(*) AS cells, CAST(max(before) AS BIGINT) AS before_last FROM seq GROUP BY qid"))
def q_cells_explored(spark, sf):
    return q_imi_sequence(spark, sf).groupBy("qid").agg(F.count("*").alias("cells"), F.max("before").alias("before_last"))


def imi_full_sql(budget: int, rotated: bool = False) -> Sql:
    s = imi_sql(budget, rotated)
    s.add("hv", "SELECT part, idx, list(c ORDER BY dim) AS e FROM h_cb GROUP BY part, idx")
    s.add("centers", "SELECT a.idx * 4 + b.idx AS list_id, list_concat(a.e, b.e) AS ce FROM hv a JOIN hv b ON a.part = 0 AND b.part = 1")
    s.add("own", f"SELECT v.vec_id, x.list_id, {oracle.minus('v.e', 'x.ce')} AS e FROM base v JOIN cells c USING (vec_id) JOIN centers x ON x.list_id = c.c[1] * 4 + c.c[2]")
    oracle.pq(s, "fi", "own", 64, 8, 16, 3)
    oracle.encode(s, "own_codes", "fi", "own", 64, 8)
    s.add("codes", "SELECT vec_id, list_id, c FROM own_codes JOIN own USING (vec_id)")
    s.add("shifted", f"SELECT s.qid, s.list_id, {oracle.minus('q.e', 'x.ce')} AS e FROM seq s JOIN queries q USING (qid) JOIN centers x USING (list_id)")
    return oracle.tables(s, "tabs", "fi", "shifted", 64, 8, "qid, list_id")


@query(imi_full_sql(50).select(oracle.topk(IVF_ADC, 10)))
def q_imi_search(spark, sf):
    imi = models.imi0(spark, sf)
    q, b = models.v0(spark, sf)
    codes = imi.encode(b)
    return scan.adc_topk(codes, imi.tables(q, imi.sequence(q, index.list_sizes(codes), 50)), 8, 10, ("list_id",))
