"""The experiment workloads on the given tables, at the ratios that their sizes allow."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.functions.ranking import top_k
from vecspark.functions.vectors import l2sq
from vecspark.operators.codebook import PQModel
from vecspark.operators import codebook, encode, index, measures, packed, scan
from vecspark.operators.exact import greatest_products, items_of, profiles
from vecspark.queries import models, oracle
from vecspark.queries.bounded import bounded_sql, nested_sql, nibble_sql
from vecspark.queries.core import table_rows
from vecspark.queries.oracle import Sql
from vecspark.queries.registry import query
from vecspark.sources import tables as T

RS = (1, 10, 50, 100)
TRUTHS = f"SELECT qid, arg_min(vec_id, (dist, vec_id)) AS truth FROM (SELECT q.qid, v.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM queries q, base v WHERE q.qid <> v.vec_id) GROUP BY qid"


def union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def recalls(results: dict[str, DataFrame], truth: DataFrame, grid=RS) -> DataFrame:
    """(model, r, hits, queries, recall) of several result sets."""
    return union([measures.recall_at(f, truth, grid).select(F.lit(name).alias("model"), "r", "hits", "queries", "recall") for name, f in results.items()])


def recalls_sql(s: Sql, results: dict[str, str], grid=RS) -> str:
    """Results: model name -> name of a CTE (qid, rk, vec_id)."""
    s.add("truths", TRUTHS)
    parts = [
        f"SELECT '{name}' AS model, CAST(r AS BIGINT) AS r, count(*) FILTER (WHERE f.rk <= r) AS hits, count(*) AS queries, round(count(*) FILTER (WHERE f.rk <= r) * 1.0 / count(*), 6) AS recall FROM truths t CROSS JOIN (SELECT unnest({list(grid)}) AS r) LEFT JOIN (SELECT qid, vec_id, row_number() OVER (PARTITION BY qid ORDER BY rk) AS rk FROM {cte} WHERE vec_id <> qid) f ON f.qid = t.qid AND f.vec_id = t.truth GROUP BY r"
        for name, cte in results.items()
    ]
    return s.select(" UNION ALL ".join(parts))


def pq_result(s: Sql, p: str, m: int, k: int, d: int = 64, iters: int = 3, r: int = 100) -> str:
    """Adds the plain scan of an m x log2(k) quantizer: {p}_res."""
    oracle.pq(s, p, "base", d, m, k, iters)
    oracle.encode(s, f"{p}_codes", p, "base", d, m)
    oracle.tables(s, f"{p}_tabs", p, "queries", d, m)
    s.add(f"{p}_res", oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(m)} AS BIGINT) AS dist FROM {p}_codes c, {p}_tabs t", r))
    return f"{p}_res"


def nibble_result(s: Sql, p: str, m: int, r: int = 100, count: int = 20) -> str:
    """Adds the nibble scan over {p}'s codes: {p}_nib."""
    t = Sql()
    t.add("codes", f"SELECT * FROM {p}_codes").add("tabs", f"SELECT * FROM {p}_tabs")
    nibble_sql(r, count, m, s=t)
    names = ("codes", "tabs", "placed", "heads", "thrs", "lows", "small", "scored")
    for part in t.parts:
        name, body = part.split(" AS MATERIALIZED (", 1)
        body = body[:-1]
        import re

        for n in names:
            body = re.sub(rf"(FROM|JOIN) {n}\b", rf"\1 {p}_{n}x", body)
        s.add(f"{p}_{name}x", body)
    s.add(f"{p}_nib", oracle.topk(f"SELECT qid, vec_id, dist FROM {p}_scoredx", r))
    return f"{p}_nib"


def plain(spark, sf, m: int, k: int, r: int = 100) -> DataFrame:
    q, b = models.v0(spark, sf)
    model = models.pq0(spark, sf, m, k)
    return scan.adc_topk(encode.encode_pq(b, model), index.lookup_tables(q, model), m, r)


def nibble(spark, sf, m: int, r: int = 100) -> DataFrame:
    q, b = models.v0(spark, sf)
    model = models.pq0(spark, sf, m, 16)
    codes, tabs = encode.encode_pq(b, model), index.lookup_tables(q, model)
    return scan.nibble_topk(codes, scan.nibble_tables(scan.with_prefix(codes, None, 20, r), tabs, m, r), m, r)


def truth0(spark, sf) -> DataFrame:
    return measures.ground_truth(*models.v0(spark, sf), 64)


def grid_recall_sql() -> str:
    s = oracle.v0()
    return recalls_sql(s, {"16x2": pq_result(s, "a", 16, 4), "8x4": pq_result(s, "b", 8, 16), "4x8": pq_result(s, "c", 4, 256)})


@query(grid_recall_sql())
def w_param_grid(spark, sf):
    """Same code length, fewer and finer parts: recall by r."""
    return recalls({n: plain(spark, sf, m, k) for n, m, k in (("16x2", 16, 4), ("8x4", 8, 16), ("4x8", 4, 256))}, truth0(spark, sf))


@query(recalls_sql((_r := oracle.v0()), {"8x4": pq_result(_r, "b", 8, 16)}))
def q_recall_at(spark, sf):
    return recalls({"8x4": plain(spark, sf, 8, 16)}, truth0(spark, sf))


def variants_sql() -> str:
    s = oracle.pq(oracle.v0(), "p", "base", 64, 8, 16, 3)
    oracle.encode(s, "codes", "p", "base", 64, 8)
    oracle.tables(s, "tabs", "p", "queries", 64, 8)
    s.add("near", oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(8)} AS BIGINT) AS dist FROM codes c, tabs t", 10))
    return s.select(" UNION ALL ".join(f"SELECT '{n}' AS variant, count(*) AS n, CAST(sum(vec_id) AS BIGINT) AS ids, CAST(sum(dist) AS BIGINT) AS total FROM near" for n in ("columns", "packed", "vertical", "gather")))


@query(variants_sql())
def w_scan_variants(spark, sf):
    """Four layouts of the plain scan give one result; bench.py has their times."""
    q, b = models.v0(spark, sf)
    model = models.pq0(spark, sf, 8, 16)
    codes, rows = encode.encode_pq(b, model), table_rows(index.lookup_tables(q, model), 8)
    out = []
    for name in ("columns", "packed", "vertical", "gather"):
        near = scan.kernel_topk(codes, rows, 8, 10, name, 4)
        out.append(near.agg(F.lit(name).alias("variant"), F.count("*").alias("n"), F.sum("vec_id").alias("ids"), F.sum("dist").alias("total")))
    return union(out)


# -- eight lists and the bounded scan on line items --------------------------------------------

def v1_lists_sql(k: int = 8) -> Sql:
    s = oracle.v1().add("trainset", "SELECT * FROM base WHERE vec_id % 101 = 0")
    oracle.pq(s, "co", "trainset", 8, 1, k, 1)
    oracle.components(s, "b_sub", "base", 8, 1)
    oracle.nearest(s, "own", "b_sub", "co_cb")
    return s


def coarse1(spark, sf, k: int):
    return models.once(spark, (sf, "co1", k), lambda: codebook.train_kmeans(models.v1_training(spark, sf), k, 1))


@query(v1_lists_sql().select("SELECT CAST(idx AS BIGINT) AS list_id, count(*) AS n, count(*) FILTER (WHERE vec_id % 50 = 0) AS queries FROM own GROUP BY idx"))
def w_eight_lists(spark, sf):
    """Sizes of eight lists and the queries that each gets."""
    own = encode.assign(models.v1(spark, sf)[1], coarse1(spark, sf, 8), name="list_id").select("vec_id", "list_id")
    return own.groupBy("list_id").agg(F.count("*").alias("n"), F.count_if(F.pmod("vec_id", F.lit(T.EVERY)) == 0).alias("queries"))


def v1_codes_sql() -> Sql:
    s = oracle.v1().add("trainset", "SELECT * FROM base WHERE vec_id % 101 = 0")
    oracle.pq(s, "p", "trainset", 8, 8, 256, 1)
    oracle.encode(s, "codes", "p", "base", 8, 8)
    return oracle.tables(s, "tabs", "p", "queries", 8, 8)


def v1_setup(spark, sf, renumbered: bool = False):
    """(queries, model, packed codes) of the whole set."""
    q, b = models.v1(spark, sf)
    model = models.pq1(spark, sf, 8, 256)
    codes = models.once(spark, (sf, "v1codes"), lambda: packed.encode_packed(packed.dealt(b), model).persist())
    if renumbered:
        model, maps = codebook.renumber(model)
        codes = models.once(spark, (sf, "v1codes", True), lambda: packed.remap(codes, maps).persist())
    return q, model, codes


def pruned_total(setup, r: int, share: float, g: int = 2, mode: str = "full") -> DataFrame:
    q, model, codes = setup
    return packed.bounded_counts(codes, q, model, r, g, share, mode).agg(F.sum("n_codes").alias("n_codes"), F.sum("n_pruned").alias("n_pruned"))


def pruned_totals(spark, setup, cases: list[tuple[int, float]]) -> DataFrame:
    """(r, init_permille, n_codes, n_pruned) of several result sizes and prefixes, counted together."""
    q, model, codes = setup
    named = spark.createDataFrame([(i, r, round(share * 1000)) for i, (r, share) in enumerate(cases)], "case long, r long, init_permille long")
    counted = packed.bounded_cases(codes, q, model, cases, 2).groupBy("case").agg(F.sum("n_codes").alias("n_codes"), F.sum("n_pruned").alias("n_pruned"))
    return counted.join(F.broadcast(named), "case").drop("case")


def pruned_sql(r: int, share: float, mode: str = "full") -> str:
    return bounded_sql(r, share, 2, mode, s=Sql().add("codes", "SELECT * FROM all_codes", True).add("tabs", "SELECT * FROM all_tabs", True), once=True).select("SELECT count(*) AS n_codes, count(*) FILTER (WHERE pruned) AS n_pruned FROM pruned")


def sweep_sql(cases: list[tuple[str, int, float, str]]) -> str:
    """Cases: (SELECT prefix, r, init share, mode)."""
    s = v1_codes_sql().add("all_codes", "SELECT * FROM codes").add("all_tabs", "SELECT * FROM tabs")
    return s.select(" UNION ALL ".join(f"SELECT {head}, x.* FROM ({pruned_sql(r, share, mode)}) x" for head, r, share, mode in cases))


INITS = (0.001, 0.005, 0.01, 0.05, 0.1)


@query(sweep_sql([(f"CAST({round(i * 1000)} AS BIGINT) AS init_permille, CAST({r} AS BIGINT) AS r", r, i, "full") for i in INITS for r in (10, 100)]))
def w_init_sweep(spark, sf):
    """Codes pruned as the prefix grows, for two result sizes."""
    return pruned_totals(spark, v1_setup(spark, sf), [(r, i) for i in INITS for r in (10, 100)]).select("init_permille", "r", "n_codes", "n_pruned")


@query(sweep_sql([(f"CAST({r} AS BIGINT) AS r", r, 0.005, "full") for r in (1, 10, 50, 100, 500)]))
def w_r_sweep(spark, sf):
    """More neighbours, a farther threshold, fewer codes pruned."""
    return pruned_totals(spark, v1_setup(spark, sf), [(r, 0.005) for r in (1, 10, 50, 100, 500)]).select("r", "n_codes", "n_pruned")


@query(sweep_sql([("'full' AS mode", 10, 0.01, "full"), ("'quant_only' AS mode", 10, 0.01, "quant_only")]))
def w_quant_only(spark, sf):
    """Bounds from 256-entry quantized tables alone prune a little more than portions and minima."""
    setup = v1_setup(spark, sf)
    return union([pruned_total(setup, 10, 0.01, mode=m).select(F.lit(m).alias("mode"), "*") for m in ("full", "quant_only")])


@query()
def w_numbering(spark, sf):
    """Pruned share with arbitrary and with equal-size-cluster numbering of centroids."""
    return union([pruned_total(v1_setup(spark, sf, n), 10, 0.01).select(F.lit("clusters" if n else "arbitrary").alias("numbering"), "*", F.round(F.col("n_pruned") / F.col("n_codes"), 4).alias("share")) for n in (False, True)])


@query(
    bounded_sql(10, 0.01, 2, s=v1_codes_sql(), once=True).add("work", "SELECT qid, count(*) FILTER (WHERE NOT pruned) AS n_full FROM pruned GROUP BY qid").select(
        "SELECT round(avg(n_full), 4) AS mean, round(quantile_cont(n_full, 0.25), 4) AS q25, round(quantile_cont(n_full, 0.5), 4) AS median, round(quantile_cont(n_full, 0.75), 4) AS q75, round(quantile_cont(n_full, 0.95), 4) AS q95 FROM work"
    )
)
def w_work_distribution(spark, sf):
    """Full sums a query needs: the deterministic stand-in for its response time."""
    q, model, codes = v1_setup(spark, sf)
    work = packed.bounded_counts(codes, q, model, 10, 2).withColumn("n_full", F.col("n_codes") - F.col("n_pruned"))
    return work.agg(F.round(F.avg("n_full"), 4).alias("mean"), *[F.round(F.percentile("n_full", F.lit(p)), 4).alias(n) for p, n in ((0.25, "q25"), (0.5, "median"), (0.75, "q75"), (0.95, "q95"))])


@query(bounded_sql(10, 0.01, 2, s=v1_codes_sql(), once=True).select("SELECT CAST(9 AS DOUBLE) AS plain_reads, round(1 + (1 - count(*) FILTER (WHERE pruned) * 1.0 / count(*)) * 9, 6) AS bounded_reads FROM pruned"))
def w_operation_model(spark, sf):
    """Memory reads for a code: nine plain (a word and eight tables) against one and the share kept."""
    return pruned_total(v1_setup(spark, sf), 10, 0.01).select(F.lit(9.0).alias("plain_reads"), F.round(1 + (1 - F.col("n_pruned") / F.col("n_codes")) * 9, 6).alias("bounded_reads"))


@query(v1_codes_sql().select(oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(8)} AS BIGINT) AS dist FROM codes c, tabs t", 10)))
def w_bounded_lineitem(spark, sf):
    """The bounded scan with group skipping over all line items: the oracle is the plain scan."""
    q, model, codes = v1_setup(spark, sf, True)
    laid = models.once(spark, (sf, "v1laid", 3), lambda: packed.grouped(codes, model, 3).persist())
    return packed.bounded_scan(laid, q, model, 10, 3, packed.prefix_tops(codes, q, model, 10))


@query()
def w_group_skipping(spark, sf):
    """What each sieve of the bounded scan leaves, by size of the portions and number of grouped parts."""
    q, b = models.v1(spark, sf)
    out = []
    for low_bits, g in ((4, 2), (4, 3), (4, 4), (6, 4), (6, 6)):
        model = codebook.renumber(models.pq1(spark, sf, 8, 256), 1 << (8 - low_bits))[0]
        codes = models.once(spark, (sf, "v1codes", low_bits), lambda model=model: packed.encode_packed(packed.dealt(b), model).persist())
        stats = packed.bounded_scan(packed.grouped(codes, model, g, low_bits), q, model, 10, g, packed.prefix_tops(codes, q, model, 10), low_bits, stats=True)
        total = stats.agg(*[F.sum(c).alias(c) for c in ("codes", "groups", "groups_kept", "bounded", "summed")])
        out.append(total.select(F.lit(16 if low_bits == 4 else 64).alias("portion"), F.lit(g).alias("grouped"), "*"))
    return union(out)


def list_size_sql(k: int, body: str) -> str:
    s = v1_lists_sql(k)
    s.add("cents", "SELECT idx, list(c ORDER BY dim) AS e FROM co_cb GROUP BY idx")
    oracle.pq(s, "p", "trainset", 8, 8, 256, 1)
    oracle.encode(s, "plain_codes", "p", "base", 8, 8)
    s.add("codes", "SELECT vec_id, idx AS list_id, c FROM plain_codes JOIN own USING (vec_id)")
    oracle.probes(s, 1)
    s.add("whole", "SELECT qid, list_id, whole AS e FROM probes")
    oracle.tables(s, "tabs", "p", "whole", 8, 8, "qid, list_id")
    bounded_sql(10, 0.01, 1, s=s, keys="qid, list_id", once=True)
    return s.select(body)


def listed_counts(spark, sf, k: int) -> DataFrame:
    """(qid, list_id, n_codes, n_pruned) of each query's nearest list."""
    q, b = models.v1(spark, sf)
    coarse, model = coarse1(spark, sf, k), models.pq1(spark, sf, 8, 256)
    codes = models.once(spark, (sf, "v1listed", k), lambda: packed.by_list(packed.encode_packed(b, model, coarse, residual=False).persist()).persist())
    return packed.listed_counts(codes, q, index.probes(q, coarse, 1), model, 10, 1)


@query(list_size_sql(8, "SELECT CAST(list_id AS BIGINT) AS list_id, count(DISTINCT qid) AS queries, count(*) AS n_codes, count(*) FILTER (WHERE pruned) AS n_pruned FROM pruned GROUP BY list_id"))
def w_list_size(spark, sf):
    """Each query scans one of eight lists: codes and pruned codes by list."""
    return listed_counts(spark, sf, 8).groupBy("list_id").agg(F.count("*").alias("queries"), F.sum("n_codes").alias("n_codes"), F.sum("n_pruned").alias("n_pruned"))


@query(list_size_sql(64, "SELECT count(DISTINCT list_id) AS lists, count(DISTINCT qid) AS queries, count(*) AS n_codes, count(*) FILTER (WHERE pruned) AS n_pruned FROM pruned"))
def w_large_bounded(spark, sf):
    """Many lists: every query scans one of sixty-four; shorter lists, less to prune."""
    return listed_counts(spark, sf, 64).agg(F.countDistinct("list_id").alias("lists"), F.countDistinct("qid").alias("queries"), F.sum("n_codes").alias("n_codes"), F.sum("n_pruned").alias("n_pruned"))


# -- nibble scan -------------------------------------------------------------------------------


def nibble_recall_sql(pairs: list[tuple[str, int, int, bool]]) -> str:
    """(name, m, k, nibble)"""
    s, out, seen = oracle.v0(), {}, {}
    for name, m, k, nib in pairs:
        if (m, k) not in seen:
            seen[m, k] = f"m{m}k{k}"
            pq_result(s, seen[m, k], m, k)
        out[name] = nibble_result(s, seen[m, k], m) if nib else f"{seen[m, k]}_res"
    return recalls_sql(s, out)


NIBBLES = [("plain 8x8", 8, 256, False), ("plain 16x4", 16, 16, False), ("nibble 16x4", 16, 16, True)]


@query(nibble_recall_sql(NIBBLES))
def w_nibble_exhaustive(spark, sf):
    """64-bit codes: eight-bit parts, four-bit parts, and four-bit parts with quantized tables."""
    return recalls({n: nibble(spark, sf, m) if nib else plain(spark, sf, m, k) for n, m, k, nib in NIBBLES}, truth0(spark, sf))


LONG = [*NIBBLES, ("plain 16x8", 16, 256, False), ("nibble 32x4", 32, 16, True)]


@query(nibble_recall_sql(LONG))
def w_nibble_unitnorm(spark, sf):
    """Codes of 64 and of 128 bits on unit vectors."""
    return recalls({n: nibble(spark, sf, m) if nib else plain(spark, sf, m, k) for n, m, k, nib in LONG}, truth0(spark, sf))


@query()
def w_nibble_opq(spark, sf):
    """The same with a learnt rotation before quantization."""
    q, b = models.v0(spark, sf)
    out = {}
    for name, m, bits, nib in (("plain 8x8", 8, 8, False), ("plain 16x4", 16, 4, False), ("nibble 16x4", 16, 4, True)):
        model = opq(spark, sf, m, bits)
        codes = packed.encode_packed(b, model)
        out[name] = packed.nibble_scan(codes, q, model, 100) if nib else packed.plain_scan(codes, q, model, 100)
    return recalls(out, truth0(spark, sf))


def floats(frame: DataFrame) -> DataFrame:
    return frame.select("vec_id", F.transform("e", lambda x: x.cast("double")).alias("e"))


def opq(spark, sf, m: int, bits: int):
    """Rotation and codebooks learnt on the vectors."""
    return models.once(spark, (sf, "opqw", m, bits), lambda: codebook.train_opq(floats(models.v0(spark, sf)[1]), m, bits, 4)[0])


def opq_lists(spark, sf, k: int, m: int, bits: int):
    """Lists, and a rotation with codebooks learnt on the residuals."""
    coarse = models.once(spark, (sf, "co0", k), lambda: codebook.train_kmeans(models.v0(spark, sf)[1], k, 3))
    model = models.once(spark, (sf, "opqi", k, m, bits), lambda: codebook.train_opq(floats(index.residuals(models.v0(spark, sf)[1], coarse)), m, bits, 4)[0])
    return coarse, model


IVF_CASES = (("plain 8x8", 8, 256, False), ("plain 16x4", 16, 16, False), ("nibble 16x4", 16, 16, True))


def ivf_recall_sql(k: int, ma: int = 3, rotated: bool = False) -> str:
    s = oracle.v0(rotated)
    oracle.pq(s, "co", "base", 64, 1, k, 3)
    oracle.centroid_lists(s, "cents", "co")
    oracle.components(s, "all_sub", "base", 64, 1)
    oracle.nearest(s, "all_list", "all_sub", "co_cb")
    s.add("own", f"SELECT v.vec_id, l.idx AS list_id, {oracle.minus('v.e', 'c.e')} AS e FROM base v JOIN all_list l USING (vec_id) JOIN cents c ON c.idx = l.idx")
    oracle.probes(s, ma)
    s.add("shifted", "SELECT qid, list_id, e FROM probes")
    out = {}
    for name, m, kk, nib in IVF_CASES:
        p = f"f{m}"
        if not nib:
            oracle.pq(s, p, "own", 64, m, kk, 3)
            oracle.encode(s, f"{p}_own", p, "own", 64, m)
            s.add(f"{p}_codes", f"SELECT vec_id, list_id, c FROM {p}_own JOIN own USING (vec_id)")
            oracle.tables(s, f"{p}_tabs", p, "shifted", 64, m, "qid, list_id")
            s.add(f"{p}_res", oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(m)} AS BIGINT) AS dist FROM {p}_codes c JOIN {p}_tabs t ON c.list_id = t.list_id", 50))
            out[name] = f"{p}_res"
        else:
            s.add("codes", f"SELECT * FROM {p}_codes")
            s.add("tabs", f"SELECT * FROM {p}_tabs")
            nibble_sql(50, 20, m, s=s, keys="qid, list_id")
            s.add("nibble_res", oracle.topk("SELECT qid, vec_id, dist FROM scored", 50))
            out[name] = "nibble_res"
    return recalls_sql(s, out, (1, 10, 50))


def ivf_recall(spark, sf, k: int, ma: int = 3, rotated: bool = False) -> DataFrame:
    q, b = models.v0_rotated(spark, sf) if rotated else models.v0(spark, sf)
    coarse = models.once(spark, (sf, "co0", k, rotated), lambda: codebook.train_kmeans(b, k, 3))
    probes = index.probes(q, coarse, ma)
    out = {}
    for name, m, kk, nib in IVF_CASES:
        model = models.once(spark, (sf, "ivfw", k, m, kk, rotated), lambda m=m, kk=kk: codebook.train_pq(index.residuals(b, coarse), m, int(np.log2(kk)), 3))
        codes = packed.encode_packed(b, model, coarse)
        out[name] = packed.nibble_scan(codes, q, model, 50, 20, probes=probes, centers=coarse) if nib else packed.plain_scan(codes, q, model, 50, probes, coarse)
    return recalls(out, measures.ground_truth(q, b, 64), (1, 10, 50))


@query(ivf_recall_sql(16))
def w_nibble_ivf_small(spark, sf):
    """Three of sixteen lists: eight-bit parts, four-bit parts, four-bit parts with quantized tables."""
    return ivf_recall(spark, sf, 16)


@query(ivf_recall_sql(32))
def w_nibble_ivf_fine(spark, sf):
    """Three of thirty-two lists: half the codes, some recall lost."""
    return ivf_recall(spark, sf, 32)


@query(ivf_recall_sql(16, rotated=True))
def w_nibble_ivf_rotated(spark, sf):
    """Vectors rotated (by a fixed rotation) before lists and codes are made."""
    return ivf_recall(spark, sf, 16, rotated=True)


@query()
def w_nibble_ivf_opq(spark, sf):
    """Lists with a rotation learnt on the residuals."""
    q, b = models.v0(spark, sf)
    out = {}
    for name, m, kk, nib in IVF_CASES:
        coarse, model = opq_lists(spark, sf, 16, m, int(np.log2(kk)))
        probes, codes = index.probes(q, coarse, 3), packed.encode_packed(b, model, coarse)
        out[name] = packed.nibble_scan(codes, q, model, 50, 20, probes=probes, centers=coarse) if nib else packed.plain_scan(codes, q, model, 50, probes, coarse)
    return recalls(out, truth0(spark, sf), (1, 10, 50))


HIGH = (("plain 16x8", 16, 256, False), ("plain 32x4", 32, 16, False), ("nibble 32x4", 32, 16, True))


def highdim_sql() -> str:
    s = oracle.v2()
    s.add("base", "SELECT * FROM v").add("queries", "SELECT vec_id AS qid, e FROM v WHERE vec_id % 50 = 0")
    out = {}
    for name, m, k, nib in HIGH:
        out[name] = nibble_result(s, f"h{m}", m) if nib else pq_result(s, f"h{m}", m, k, 128, 1)
    return recalls_sql(s, out)


@query(highdim_sql())
def w_nibble_highdim(spark, sf):
    """Text vectors of 128 dimensions and codes of 128 bits: eight-bit, four-bit, quantized tables."""
    q, b = T.split(models.once(spark, (sf, "v2"), lambda: T.vectors_documents(spark, sf).persist()))
    out = {}
    for name, m, k, nib in HIGH:
        model = models.once(spark, (sf, "v2", m, k), lambda m=m, k=k: codebook.train_pq(b, m, int(np.log2(k)), 1))
        codes = packed.encode_packed(b, model)
        out[name] = packed.nibble_scan(codes, q, model, 100) if nib else packed.plain_scan(codes, q, model, 100)
    return recalls(out, measures.ground_truth(q, b, 128))


def large_sql() -> str:
    s = v1_lists_sql(32).add("cents", "SELECT idx, list(c ORDER BY dim) AS e FROM co_cb GROUP BY idx")
    oracle.probes(s, 3)
    s.add("mine", f"SELECT v.vec_id, l.idx AS list_id, {oracle.minus('v.e', 'c.e')} AS e FROM base v JOIN own l USING (vec_id) JOIN cents c ON c.idx = l.idx")
    s.add("train_mine", "SELECT vec_id, e FROM mine WHERE vec_id % 101 = 0")
    oracle.pq(s, "fi", "train_mine", 8, 8, 16, 1)
    oracle.encode(s, "own_codes", "fi", "mine", 8, 8)
    s.add("codes", "SELECT vec_id, list_id, c FROM own_codes JOIN mine USING (vec_id)")
    s.add("shifted", "SELECT qid, list_id, e FROM probes")
    oracle.tables(s, "tabs", "fi", "shifted", 8, 8, "qid, list_id")
    s.add("plain_res", oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(8)} AS BIGINT) AS dist FROM codes c JOIN tabs t ON c.list_id = t.list_id", 100))
    nibble_sql(100, 20, 8, s=s, keys="qid, list_id")
    s.add("nibble_res", oracle.topk("SELECT qid, vec_id, dist FROM scored", 100))
    return recalls_sql(s, {"plain 8x4": "plain_res", "nibble 8x4": "nibble_res"})


@query(large_sql())
def w_nibble_large(spark, sf):
    """The large set: three of thirty-two lists, residual codes of 32 bits, plain and nibble scans."""
    q, b = models.v1(spark, sf)
    coarse = coarse1(spark, sf, 32)
    model = models.once(spark, (sf, "nl"), lambda: codebook.train_pq(index.residuals(models.v1_training(spark, sf), coarse), 8, 4, 1))
    codes, probes = packed.encode_packed(b, model, coarse).persist(), index.probes(q, coarse, 3)
    out = {"plain 8x4": packed.plain_scan(codes, q, model, 100, probes, coarse), "nibble 8x4": packed.nibble_scan(codes, q, model, 100, 20, probes=probes, centers=coarse)}
    return recalls(out, measures.ground_truth(q, b, 8))


# -- nested codebooks --------------------------------------------------------------------------

SHARES = (5, 10, 20, 40, 60)


def nested_run(spark, sf, r2: int, r: int = 100, m: int = 4, numbering: str = "ntile", rotated: bool = False):
    q, b = models.v0_rotated(spark, sf) if rotated else models.v0(spark, sf)
    model = models.nested0(spark, sf, m, 8, 4, numbering, rotated=rotated)
    codes = models.once(spark, (sf, "nestedcodes", m, numbering, rotated), lambda: packed.encode_packed(b, model).persist())
    found = packed.nested_candidates(codes, q, model, r2)
    return found, packed.rerank(found, q, model, r)


def share_of_base(spark, sf, share: int) -> int:
    return models.v0(spark, sf)[1].count() * share // 100


def r2_sql() -> str:
    parts = []
    for share in SHARES:
        r2 = f"((SELECT count(*) FROM base) * {share} // 100)"
        s = nested_sql(r2=r2).add("truths", TRUTHS)
        s.add("found", oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(4)} AS BIGINT) AS dist FROM cands JOIN codes c USING (vec_id) JOIN tabs t USING (qid)", 100))
        parts.append("SELECT * FROM (" + s.select(f"SELECT CAST({r2} AS BIGINT) AS r2, (SELECT count(*) FROM truths t JOIN cands c ON c.qid = t.qid AND c.vec_id = t.truth) AS candidate_hits, (SELECT count(*) FROM truths t JOIN found c ON c.qid = t.qid AND c.vec_id = t.truth) AS hits, (SELECT count(*) FROM cands) AS candidates") + ")")
    return " UNION ALL ".join(parts)


def r2_rows(spark, sf, numbering: str) -> DataFrame:
    truth, out = truth0(spark, sf).cache(), []
    for share in SHARES:
        r2 = share_of_base(spark, sf, share)
        found, result = nested_run(spark, sf, r2, numbering=numbering)
        row = measures.candidate_recall(found, truth).select(F.lit(r2).cast("long").alias("r2"), F.col("hits").alias("candidate_hits"))
        hits = measures.candidate_recall(result, truth).select("hits")
        out.append(row.crossJoin(hits).crossJoin(found.agg(F.count("*").alias("candidates"))))
    return union(out)


@query(r2_sql())
def w_r2_sweep(spark, sf):
    """More candidates, more recall of the first pass, more work for the second."""
    return r2_rows(spark, sf, "ntile")


@query()
def w_r2_sweep_same_size(spark, sf):
    """The same with the method's own equal-size clusters."""
    return r2_rows(spark, sf, "same_size")


def nested_plain_sql(m: int, rotated: bool = False) -> str:
    s = nested_sql(m=m, r2="((SELECT count(*) FROM base) * 40 // 100)", rotated=rotated)
    s.add("coarse_res", oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(m, 't.tt', 'l.c')} AS BIGINT) AS dist FROM low l, ctabs t", 100))
    s.add("fine_res", oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(m)} AS BIGINT) AS dist FROM codes c, tabs t", 100))
    s.add("nested_res", oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(m)} AS BIGINT) AS dist FROM cands JOIN codes c USING (vec_id) JOIN tabs t USING (qid)", 100))
    return recalls_sql(s, {"coarse": "coarse_res", "fine": "fine_res", "nested": "nested_res"})


def nested_plain(spark, sf, m: int, numbering: str = "ntile", rotated: bool = False) -> DataFrame:
    q, b = models.v0_rotated(spark, sf) if rotated else models.v0(spark, sf)
    model = models.nested0(spark, sf, m, 8, 4, numbering, rotated=rotated)
    codes = encode.encode_pq(b, model)
    low = PQModel(m, 4, 64, model.coarse, model.rotation)
    out = {
        "coarse": packed.plain_scan(packed.pack(scan.low_bits_codes(codes, m, 4), m, 4), q, low, 100),
        "fine": packed.plain_scan(packed.pack(codes, m, 8), q, model, 100),
        "nested": nested_run(spark, sf, share_of_base(spark, sf, 40), 100, m, numbering, rotated)[1],
    }
    return recalls(out, measures.ground_truth(q, b, 64))


@query(nested_plain_sql(4))
def w_nested_vs_plain(spark, sf):
    """Coarse alone, fine alone, and both in two passes."""
    return nested_plain(spark, sf, 4)


@query(nested_plain_sql(4, True))
def w_nested_rotated(spark, sf):
    """The same on rotated vectors (a fixed rotation)."""
    return nested_plain(spark, sf, 4, rotated=True)


@query(nested_plain_sql(2))
def w_nested_short(spark, sf):
    """The same with codes half as long."""
    return nested_plain(spark, sf, 2)


@query()
def w_nested_same_size(spark, sf):
    """The method's own equal-size clusters."""
    return nested_plain(spark, sf, 4, "same_size")


@query()
def w_nested_short_same_size(spark, sf):
    return nested_plain(spark, sf, 2, "same_size")


@query()
def w_nested_opq(spark, sf):
    """A learnt rotation, its codebooks nested by equal-size clusters; codes of 32 and 16 bits."""
    q, b = models.v0(spark, sf)
    out = {}
    for m in (4, 2):
        model = models.once(spark, (sf, "opqn", m), lambda m=m: codebook.nest(opq(spark, sf, m, 8), 4))
        codes = packed.encode_packed(b, model)
        out[f"fine {m}x8"] = packed.plain_scan(codes, q, model, 100)
        out[f"nested {m}x4,8"] = packed.rerank(packed.nested_candidates(codes, q, model, share_of_base(spark, sf, 40)), q, model, 100)
    return recalls(out, truth0(spark, sf))


PERMILLES = (1, 2, 5, 10, 20)


@query()
def w_nested_large(spark, sf):
    """Line items: candidate recall, recall after the rerank and candidates at small shares of the larger set."""
    q, b = models.v1(spark, sf)
    model = models.once(spark, (sf, "nested1"), lambda: codebook.nest(models.pq1(spark, sf, 4, 256), 4))
    codes, n = models.once(spark, (sf, "nested1codes"), lambda: packed.encode_packed(b, model).persist()), b.count()
    truth, out = measures.ground_truth(q, b, 8).cache(), []
    fine = measures.recall_at(packed.plain_scan(codes, q, model, 100), truth, (100,)).select(F.col("hits").alias("fine_hits"))
    for permille in PERMILLES:
        r2 = max(100, n * permille // 1000)
        found = packed.nested_candidates(codes, q, model, r2)
        hits = measures.recall_at(packed.rerank(found, q, model, 100), truth, (100,)).select("hits", "queries")
        seen = measures.candidate_recall(found, truth).select(F.col("hits").alias("candidate_hits"))
        out.append(hits.crossJoin(seen).crossJoin(fine).crossJoin(found.agg(F.count("*").alias("candidates"))).select(F.lit(r2).cast("long").alias("r2"), "*"))
    return union(out)


# -- applications ------------------------------------------------------------------------------


def retrieval_sql() -> str:
    docs = oracle.v2()
    items = oracle.v2(source="SELECT item_id AS vec_id, text FROM benchmark")
    a = docs.select("SELECT * FROM v")
    b = items.select("SELECT vec_id AS qid, e FROM v")
    return f"WITH d AS MATERIALIZED ({a}), q AS MATERIALIZED ({b}) " + oracle.topk(f"SELECT q.qid, d.vec_id, {oracle.l2('q.e', 'd.e')} AS dist FROM q, d", 3)


@query(retrieval_sql())
def w_retrieval(spark, sf):
    """Benchmark passages as query objects over the documents."""
    items = T.text_vectors(T.load(spark, sf, "benchmark").select(F.col("item_id").alias("qid"), "text"), ["qid"], "text")
    near = T.vectors_documents(spark, sf).crossJoin(F.broadcast(items.withColumnRenamed("e", "q"))).select("qid", "vec_id", l2sq(F.col("q"), F.col("e"), 128).alias("dist"))
    return top_k(near, 3, ["qid"], ["dist", "vec_id"])


@query(
    oracle.v0().add("near", oracle.topk(f"SELECT q.qid, v.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM queries q, base v WHERE q.qid <> v.vec_id", 5))
    .add("votes", "SELECT n.qid, l.label AS guess, count(*) AS n FROM near n JOIN embeddings l USING (vec_id) GROUP BY 1, 2")
    .add("best", "SELECT qid, guess FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY n DESC, guess) AS rk FROM votes) WHERE rk = 1")
    .select("SELECT count(*) AS n, count(*) FILTER (WHERE guess = label) AS correct FROM best JOIN embeddings ON vec_id = qid")
)
def w_nn_classifier(spark, sf):
    """Majority label of the five nearest neighbours."""
    q, b = models.v0(spark, sf)
    labels = T.load(spark, sf, "embeddings").select("vec_id", "label")
    near = top_k(b.crossJoin(F.broadcast(q.withColumnRenamed("e", "q"))).where("qid <> vec_id").select("qid", "vec_id", l2sq(F.col("q"), F.col("e"), 64).alias("dist")), 5, ["qid"], ["dist", "vec_id"])
    votes = near.join(labels, "vec_id").groupBy("qid", F.col("label").alias("guess")).agg(F.count("*").alias("n"))
    best = top_k(votes, 1, ["qid"], [F.col("n").desc(), F.col("guess")])
    return best.join(labels.withColumnRenamed("vec_id", "qid"), "qid").agg(F.count("*").alias("n"), F.count_if(F.col("guess") == F.col("label")).alias("correct"))


@query(
    "WITH spend AS MATERIALIZED (SELECT o_custkey AS custkey, p_brand AS brand, CAST(sum(CAST(floor(l_extendedprice) AS BIGINT)) AS BIGINT) AS spend FROM lineitem JOIN part ON p_partkey = l_partkey JOIN orders ON o_orderkey = l_orderkey GROUP BY 1, 2), "
    "dots AS MATERIALIZED (SELECT a.custkey AS qid, b.custkey, CAST(sum(CAST(a.spend // 1000 AS BIGINT) * CAST(b.spend // 1000 AS BIGINT)) AS BIGINT) AS dot FROM spend a JOIN spend b USING (brand) WHERE a.custkey % 50 = 0 AND a.custkey <> b.custkey GROUP BY 1, 2), "
    "near AS MATERIALIZED (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dot DESC, custkey) AS rk FROM dots) WHERE rk <= 5) "
    "SELECT n.qid, s.brand, CAST(sum(s.spend) AS BIGINT) AS score FROM near n JOIN spend s USING (custkey) WHERE NOT EXISTS (SELECT 1 FROM spend o WHERE o.custkey = n.qid AND o.brand = s.brand) GROUP BY 1, 2"
)
def w_recommender(spark, sf):
    """Brands that a customer's nearest profiles buy and the customer does not."""
    spend = T.profiles_customers(spark, sf).groupBy("custkey", "brand").agg(F.sum("spend").alias("spend")).persist()
    scaled = spend.select(F.col("custkey").alias("vec_id"), "brand", F.floor(F.col("spend") / 1000).cast("long").alias("x"))
    near = greatest_products(*T.split(profiles(scaled, "vec_id", "brand", "x", items_of(scaled, "brand"))), 5)
    bought = near.select("qid", F.col("vec_id").alias("custkey")).join(spend, "custkey").groupBy("qid", "brand").agg(F.sum("spend").alias("score"))
    return bought.join(spend.where("custkey % 50 = 0").select(F.col("custkey").alias("qid"), "brand"), ["qid", "brand"], "left_anti")


@query("WITH n AS (SELECT count(*) AS n FROM embeddings) SELECT kind, CAST(n * width AS BIGINT) AS bytes FROM n, (VALUES ('vectors', 256), ('pq 64 bit', 16), ('pq 32 bit', 12), ('e2lsh 3 tables', 72), ('lsb 2 trees', 32), ('c2lsh 8 functions', 128), ('sklsh 3 orders', 48)) t(kind, width)")
def w_index_memory(spark, sf):
    """Bytes of each structure: rows times key and id widths."""
    widths = [("vectors", 256), ("pq 64 bit", 16), ("pq 32 bit", 12), ("e2lsh 3 tables", 72), ("lsb 2 trees", 32), ("c2lsh 8 functions", 128), ("sklsh 3 orders", 48)]
    n = T.load(spark, sf, "embeddings").agg(F.count("*").alias("n"))
    return spark.createDataFrame(widths, "kind string, width long").crossJoin(F.broadcast(n)).select("kind", (F.col("n") * F.col("width")).alias("bytes"))
