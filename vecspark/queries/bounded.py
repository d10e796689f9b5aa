"""Queries of the bounded, nibble and nested scans."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.functions.bits import group_id
from vecspark.operators import codebook, encode, index, packed, scan
from vecspark.plans import costs
from vecspark.queries import models, oracle
from vecspark.queries.core import IVF_ADC, code_select, coded, imi_full_sql, long_codes, pq_sql, table_rows
from vecspark.queries.oracle import Sql
from vecspark.queries.registry import query
from vecspark.sources import tables as T

M, K, R = 8, 256, 10
ADC = f"SELECT qid, vec_id, CAST({oracle.adc(M)} AS BIGINT) AS dist FROM codes c, tabs t"


def bounded_sql(r: int = R, share: float = 0.01, g: int = 4, mode: str = "full", qmax: str = "prefix", s: Sql | None = None, m: int = M, keys: str = "qid", once: bool = False) -> Sql:
    """marks(qid, vec_id, dist, pruned) from codes(vec_id, c), tabs(qid, tt); keys may add list_id."""
    s = s or pq_sql(m, K, tabled=True)
    listed = "list_id" in keys
    over = "PARTITION BY list_id " if listed else ""
    join = "USING (list_id)" if listed else "ON true"
    s.add("placed", f"SELECT *, row_number() OVER ({over}ORDER BY vec_id) <= greatest({r}, ceil(count(*) OVER ({over.strip()}) * CAST({share} AS DOUBLE))) AS prefix FROM codes")
    s.add("heads", f"SELECT {'t.qid, t.list_id' if listed else 'qid'}, vec_id, CAST({oracle.adc(m)} AS BIGINT) AS dist FROM placed c JOIN tabs t {join} WHERE prefix")
    s.add("thrs", f"SELECT {keys}, max(dist) AS thr FROM (SELECT *, row_number() OVER (PARTITION BY {keys} ORDER BY dist, vec_id) AS rk FROM heads) WHERE rk <= {r} GROUP BY {keys}")
    top = "thr" if qmax == "prefix" else "(" + " + ".join(f"list_max(tt[{j + 1}])" for j in range(m)) + ")"
    s.add("lows", f"SELECT t.*, thr, CAST({top} AS BIGINT) AS top, list_min(list_transform(tt, lambda x: list_min(x))) AS qmin FROM tabs t JOIN thrs USING ({keys})")
    s.add("small", f"SELECT {keys}, tt, thr, top, qmin, list_transform(tt, lambda x: list_transform(x, lambda y: CASE WHEN top > qmin THEN least(((y - qmin) * 127) // (top - qmin), 127) ELSE 0 END)) AS qq FROM lows")
    s.add("minima", f"SELECT *, list_transform(qq, lambda x: list_transform(range(0, 16), lambda i: list_min(x[i * 16 + 1 : i * 16 + 16]))) AS mm FROM small")
    terms = [f"qq[{j + 1}][c.c[{j + 1}] + 1]" if j < g or mode == "quant_only" else f"mm[{j + 1}][c.c[{j + 1}] // 16 + 1]" for j in range(m)]
    s.add(
        "marks",
        f"SELECT t.qid, c.vec_id, {'c.list_id, ' if listed else ''}least({' + '.join(terms)}, 127) AS lb, CAST({oracle.adc(m)} AS BIGINT) AS dist, thr, top, qmin, prefix FROM placed c JOIN minima t {join}",
        once,
    )
    return s.add("pruned", f"SELECT *, (NOT prefix) AND top > qmin AND lb * (top - qmin) >= 127 * (thr - {m} * qmin) AS pruned FROM marks", once)


PRUNED = "SELECT qid, count(*) AS n_codes, count(*) FILTER (WHERE pruned) AS n_pruned, count(*) - count(*) FILTER (WHERE pruned) AS n_full, round(count(*) FILTER (WHERE pruned) * 100.0 / count(*), 6) AS pruned_pct FROM pruned GROUP BY qid"


def setup(spark, sf, r: int = R, share: float = 0.01):
    codes, tabs, model = coded(spark, sf, M, K)
    return scan.with_prefix(codes, share, None, r), tabs, model


WORKED = [[12, 3, 9, 1, 200, 14, 77, 5], [0, 15, 2, 7, 31, 8, 9, 250], [8, 8, 8, 8, 1, 2, 3, 4], [60, 20, 44, 3, 9, 9, 9, 9], [51, 31, 33, 12, 0, 0, 1, 1], [250, 241, 255, 240, 7, 7, 7, 7], [244, 255, 242, 243, 128, 64, 32, 16], [1, 2, 3, 17, 90, 91, 92, 93]]


@query(pq_sql(M, K).select("SELECT vec_id, CAST(((c[1] // 16 * 16 + c[2] // 16) * 16 + c[3] // 16) * 16 + c[4] // 16 AS BIGINT) AS grp, CAST(c[1] AS BIGINT) AS c0 FROM codes"))
def q_group_codes(spark, sf):
    codes, _, _ = coded(spark, sf, M, K)
    return encode.group_layout(codes, 4).select("vec_id", F.col("grp").cast("long").alias("grp"), F.col("c0").cast("long").alias("c0"))


@query(pq_sql(M, K).select("SELECT CAST(c[1] // 16 * 16 + c[2] // 16 AS BIGINT) AS grp, count(*) AS n FROM codes GROUP BY 1"))
def q_group_sizes(spark, sf):
    codes, _, _ = coded(spark, sf, M, K)
    return encode.group_codes(codes, 2).groupBy(F.col("grp").cast("long").alias("grp")).agg(F.count("*").alias("n"))


@query(costs.group_memory_sql())
def q_group_memory(spark, sf):
    """Least list for each number of grouped components, and bits left of the vectors' 64-bit codes."""
    return costs.group_memory(T.load(spark, sf, "embeddings"))


@query(pq_sql(M, K).select(code_select(8)))
def q_compact_codes(spark, sf):
    """Codes without the nibbles that their group shares, and back: nothing is lost."""
    codes, _, _ = coded(spark, sf, M, K)
    return long_codes(encode.expand_codes(encode.compact_codes(codes, M, 4), M, 4), M)


@query(pq_sql(M, K, coded=False, tabled=True).select("SELECT qid, CAST(h AS BIGINT) AS high, CAST(i AS BIGINT) AS low, tt[1][h * 16 + i + 1] AS dist FROM tabs, (SELECT unnest(range(0, 16)) AS h), (SELECT unnest(range(0, 16)) AS i)"))
def q_portion_tables(spark, sf):
    _, tabs, _ = coded(spark, sf, M, K)
    cut = F.explode(F.transform(F.sequence(F.lit(0), F.lit(15)), lambda h: F.struct(h.cast("long").alias("high"), scan.portion("t0", h).alias("t"))))
    return tabs.select("qid", cut.alias("x")).select("qid", "x.high", F.posexplode("x.t").alias("low", "dist")).withColumn("low", F.col("low").cast("long"))


@query(pq_sql(M, K, coded=False, tabled=True).select("SELECT qid, CAST(j AS BIGINT) AS part, CAST(h AS BIGINT) AS portion, list_min(tt[j + 1][h * 16 + 1 : h * 16 + 16]) AS least FROM tabs, (SELECT unnest(range(4, 8)) AS j), (SELECT unnest(range(0, 16)) AS h)"))
def q_min_tables(spark, sf):
    _, tabs, _ = coded(spark, sf, M, K)
    each = F.explode(F.array(*[F.struct(F.lit(j).cast("long").alias("part"), scan.min_table(f"t{j}").alias("t")) for j in range(4, 8)]))
    return tabs.select("qid", each.alias("x")).select("qid", "x.part", F.posexplode("x.t").alias("portion", "least")).withColumn("portion", F.col("portion").cast("long"))


@query()
def q_renumber(spark, sf):
    """How much nearer the minima come to their tables when portions are clusters: mean gap by numbering."""
    q, _ = models.v0(spark, sf)
    out = None
    for numbering in ("arbitrary", "ntile", "same_size"):
        model = models.pq0(spark, sf, M, K)
        model = model if numbering == "arbitrary" else codebook.renumber(model, 16, numbering)[0]
        tabs = index.lookup_tables(q, model)
        gap = F.aggregate(F.zip_with(F.flatten(F.transform(scan.min_table("t4"), lambda x: F.array_repeat(x, 16))), "t4", lambda a, b: b - a), F.lit(0).cast("long"), lambda s, x: s + x) / 256
        row = tabs.select(F.lit(numbering).alias("numbering"), gap.alias("gap")).groupBy("numbering").agg(F.avg("gap").alias("mean_gap"))
        out = row if out is None else out.unionByName(row)
    return out


@query(bounded_sql().select("SELECT qid, CAST(qmin AS BIGINT) AS qmin, CAST(thr AS BIGINT) AS qmax FROM lows"))
def q_quant_bounds(spark, sf):
    placed, tabs, _ = setup(spark, sf)
    thr = scan.prefix_thresholds(placed, tabs, M, R)
    return scan.with_bounds(tabs, M).join(thr, "qid").select("qid", "qmin", F.col("thr").alias("qmax"))


@query(bounded_sql().select("SELECT qid, CAST(j AS BIGINT) AS part, CAST(i AS BIGINT) AS idx, CAST(qq[j + 1][i + 1] AS BIGINT) AS bin FROM small, (SELECT unnest(range(0, 8)) AS j), (SELECT unnest(range(0, 256)) AS i)"))
def q_quantize_tables(spark, sf):
    placed, tabs, _ = setup(spark, sf)
    thr = scan.prefix_thresholds(placed, tabs, M, R)
    small = scan.quantize_tables(scan.with_bounds(tabs, M).join(thr, "qid"), M)
    each = F.explode(F.array(*[F.struct(F.lit(j).cast("long").alias("part"), F.col(f"q{j}").alias("t")) for j in range(M)]))
    return small.select("qid", each.alias("x")).select("qid", "x.part", F.posexplode("x.t").alias("idx", "bin")).withColumn("idx", F.col("idx").cast("long"))


@query(bounded_sql().select("SELECT qid, vec_id, CAST(lb AS BIGINT) AS lb FROM marks"))
def q_lower_bound(spark, sf):
    placed, tabs, _ = setup(spark, sf)
    return scan.bounded_marks(placed, tabs, M, R, 4).select("qid", "vec_id", "lb")


@query(pq_sql(M, K, tabled=True).select(oracle.topk(ADC, R)))
def q_bounded_topk(spark, sf):
    """The oracle is the plain scan: pruning must not change a row."""
    placed, tabs, _ = setup(spark, sf)
    return scan.bounded_topk(placed, tabs, M, R, 4)


@query(pq_sql(M, K, tabled=True).select(oracle.topk(ADC, R)))
def q_bounded_kernel(spark, sf):
    """Packed codes by group, group skipping and a running threshold: the same rows."""
    q, b = models.v0(spark, sf)
    model = codebook.renumber(models.pq0(spark, sf, M, K))[0]
    codes = packed.encode_packed(b, model).persist()
    return packed.bounded_scan(packed.grouped(codes, model, 4), q, model, R, 4, packed.prefix_tops(codes, q, model, R))


@query(pq_sql(M, K, tabled=True).select(oracle.topk(ADC, R)))
def q_bounded_portions_of_64(spark, sf):
    """Four portions of 64 entries a table: more parts can be grouped."""
    q, b = models.v0(spark, sf)
    model = codebook.renumber(models.pq0(spark, sf, M, K), 4)[0]
    codes = packed.encode_packed(b, model).persist()
    return packed.bounded_scan(packed.grouped(codes, model, 6, 6), q, model, R, 6, packed.prefix_tops(codes, q, model, R), 6)


@query(oracle.tables(oracle.encode(oracle.pq(oracle.v0(True), "p", "base", 64, M, K, 3), "codes", "p", "base", 64, M), "tabs", "p", "queries", 64, M).select(oracle.topk(ADC, R)))
def q_bounded_rotated(spark, sf):
    """The bounded scan over rotated vectors (a fixed rotation): the oracle is the plain scan."""
    q, b = models.v0_rotated(spark, sf)
    model = codebook.renumber(models.once(spark, (sf, "pqr", M, K), lambda: codebook.train_pq(b, M, 8, 3)))[0]
    codes = packed.encode_packed(b, model).persist()
    return packed.bounded_scan(packed.grouped(codes, model, 3), q, model, R, 3, packed.prefix_tops(codes, q, model, R))


@query()
def q_bounded_opq(spark, sf):
    """A learnt rotation: rows lost and gained by the bounded scan against the plain one (none)."""
    q, b = models.v0(spark, sf)
    floats = b.select("vec_id", F.transform("e", lambda x: x.cast("double")).alias("e"))
    model = codebook.renumber(models.once(spark, (sf, "opq", M), lambda: codebook.train_opq(floats, M, 8, 4)[0]))[0]
    codes = packed.encode_packed(b, model).persist()
    kept = packed.bounded_scan(packed.grouped(codes, model, 3), q, model, R, 3, packed.prefix_tops(codes, q, model, R)).select("qid", "rk", "vec_id")
    plain = packed.plain_scan(codes, q, model, R).select("qid", "rk", "vec_id")
    counts = [f.agg(F.count("*").alias(n)) for f, n in ((plain.exceptAll(kept), "lost"), (kept.exceptAll(plain), "extra"), (kept, "rows_kept"))]
    return counts[0].crossJoin(counts[1]).crossJoin(counts[2])


@query(pq_sql(M, K, tabled=True).select(oracle.topk(ADC, R)))
def q_bounded_renumbered(spark, sf):
    """Centroids renumbered by equal-size clusters: other codes, same distances."""
    q, b = models.v0(spark, sf)
    model = codebook.renumber(models.pq0(spark, sf, M, K))[0]
    placed = scan.with_prefix(encode.encode_pq(b, model), 0.01, None, R)
    return scan.bounded_topk(placed, index.lookup_tables(q, model), M, R, 4)


@query(bounded_sql().select(PRUNED))
def q_bounded_pruned(spark, sf):
    placed, tabs, _ = setup(spark, sf)
    return scan.pruned_counts(scan.bounded_marks(placed, tabs, M, R, 4))


@query(bounded_sql(mode="quant_only").select(PRUNED))
def q_bounded_quant_only(spark, sf):
    placed, tabs, _ = setup(spark, sf)
    return scan.pruned_counts(scan.bounded_marks(placed, tabs, M, R, 4, mode="quant_only"))


@query(bounded_sql(qmax="sum_max").select(PRUNED))
def q_bounded_sum_max(spark, sf):
    """Control: bins up to the sum of table maxima are wider and prune less."""
    placed, tabs, _ = setup(spark, sf)
    return scan.pruned_counts(scan.bounded_marks(placed, tabs, M, R, 4, qmax="sum_max"))


@query(bounded_sql(s=pq_sql(16, K, tabled=True), m=16).select(PRUNED))
def q_bounded_sixteen_parts(spark, sf):
    """Sixteen parts: four grouped, twelve with minima."""
    codes, tabs, _ = coded(spark, sf, 16, K)
    return scan.pruned_counts(scan.bounded_marks(scan.with_prefix(codes, 0.01, None, R), tabs, 16, R, 4))


@query(
    bounded_sql()
    .add("plain", oracle.topk(ADC, R))
    .add("kept", oracle.topk("SELECT qid, vec_id, dist FROM pruned WHERE NOT pruned", R))
    .select("SELECT (SELECT count(*) FROM (SELECT * FROM plain EXCEPT SELECT * FROM kept)) AS lost, (SELECT count(*) FROM (SELECT * FROM kept EXCEPT SELECT * FROM plain)) AS extra, (SELECT count(*) FROM kept) AS rows_kept")
)
def q_bounded_equals_adc(spark, sf):
    placed, tabs, _ = setup(spark, sf)
    kept, plain = scan.bounded_topk(placed, tabs, M, R, 4), scan.adc_topk(coded(spark, sf, M, K)[0], tabs, M, R)
    counts = [f.agg(F.count("*").alias(n)) for f, n in ((plain.exceptAll(kept), "lost"), (kept.exceptAll(plain), "extra"), (kept, "rows_kept"))]
    return counts[0].crossJoin(counts[1]).crossJoin(counts[2])


@query(
    bounded_sql()
    .add("stats", PRUNED)
    .select("SELECT round(quantile_cont(pruned_pct, 0.25), 4) AS q25, round(quantile_cont(pruned_pct, 0.5), 4) AS median, round(quantile_cont(pruned_pct, 0.75), 4) AS q75, round(avg(pruned_pct), 4) AS mean FROM stats")
)
def q_pruned_stats(spark, sf):
    stats = q_bounded_pruned(spark, sf)
    return stats.agg(*[F.round(F.percentile("pruned_pct", F.lit(p)), 4).alias(n) for p, n in ((0.25, "q25"), (0.5, "median"), (0.75, "q75"))], F.round(F.avg("pruned_pct"), 4).alias("mean"))


@query(
    pq_sql(M, K, tabled=True).select(
        "SELECT qid, CAST(a * 16 + b AS BIGINT) AS grp, CAST(list_min(tt[1][a * 16 + 1 : a * 16 + 16]) + list_min(tt[2][b * 16 + 1 : b * 16 + 16]) + " + " + ".join(f"list_min(tt[{j + 1}])" for j in range(2, 8)) + " AS BIGINT) AS least "
        "FROM tabs, (SELECT unnest(range(0, 16)) AS a), (SELECT unnest(range(0, 16)) AS b)"
    )
)
def q_group_pruning(spark, sf):
    """Least distance that any code of a group can have: whole groups may be skipped."""
    _, tabs, _ = coded(spark, sf, M, K)
    return scan.group_bounds(tabs, M, 2)


@query(costs.small_table_sql())
def q_small_table_plan(spark, sf):
    return costs.small_table_plan(T.load(spark, sf, "embeddings"))


@query(costs.lookup_cost_sql())
def q_lookup_cost(spark, sf):
    return costs.lookup_cost(T.load(spark, sf, "embeddings"))


@query(costs.memory_sql())
def q_memory_model(spark, sf):
    return costs.memory_model(T.load(spark, sf, "embeddings"))


SCORE_COLUMNS = (("l_quantity", "cast(l_quantity as bigint)", 50), ("l_discount", "cast(floor(l_discount * 100 + 0.5) as bigint)", 10), ("l_tax", "cast(floor(l_tax * 100 + 0.5) as bigint)", 8))


@query(
    "WITH coded AS (SELECT l_orderkey, l_linenumber, CAST(l_quantity AS BIGINT) AS a, CAST(floor(l_discount * 100 + 0.5) AS BIGINT) AS b, CAST(floor(l_tax * 100 + 0.5) AS BIGINT) AS c, l_extendedprice FROM lineitem), "
    "scored AS (SELECT CAST(l_orderkey AS BIGINT) AS l_orderkey, CAST(l_linenumber AS BIGINT) AS l_linenumber, (a * 37) % 101 + (b * 53) % 89 + (c * 29) % 97 AS score, CAST(floor(l_extendedprice * 100 + 0.5) AS BIGINT) AS cents FROM coded) "
    "SELECT * FROM scored ORDER BY score DESC, cents DESC, l_orderkey, l_linenumber LIMIT 20"
)
def q_topk_scored_columns(spark, sf):
    """Best rows by a sum of per-column scores: bucket maxima bound the sum and filter first."""
    from vecspark.operators.scored import topk_scored
    from vecspark.sources.tables import load

    items = load(spark, sf, "lineitem").select(F.col("l_orderkey").cast("long").alias("l_orderkey"), F.col("l_linenumber").cast("long").alias("l_linenumber"), *[F.expr(e).alias(f"k{i}") for i, (_, e, _) in enumerate(SCORE_COLUMNS)], F.floor(F.col("l_extendedprice") * 100 + 0.5).cast("long").alias("cents"))
    tables = [[(x * f) % mod for x in range(top + 1)] for (_, _, top), f, mod in zip(SCORE_COLUMNS, (37, 53, 29), (101, 89, 97), strict=True)]
    return topk_scored(items, tables, 20, ["cents"], ["l_orderkey", "l_linenumber"])


# -- nibble scan -------------------------------------------------------------------------------


def nibble_sql(r: int = R, count: int = 20, m: int = 16, k: int = 16, s: Sql | None = None, keys: str = "qid", bins: int = 127) -> Sql:
    s = s or pq_sql(m, k, tabled=True)
    listed = "list_id" in keys
    over = "PARTITION BY list_id " if listed else ""
    join = "USING (list_id)" if listed else "ON true"
    s.add("placed", f"SELECT *, row_number() OVER ({over}ORDER BY vec_id) <= greatest({r}, {count}) AS prefix FROM codes")
    s.add("heads", f"SELECT {'t.qid, t.list_id' if listed else 'qid'}, vec_id, CAST({oracle.adc(m)} AS BIGINT) AS dist FROM placed c JOIN tabs t {join} WHERE prefix")
    s.add("thrs", f"SELECT {keys}, max(dist) AS thr FROM (SELECT *, row_number() OVER (PARTITION BY {keys} ORDER BY dist, vec_id) AS rk FROM heads) WHERE rk <= {r} GROUP BY {keys}")
    s.add("lows", f"SELECT t.*, thr, list_min(list_transform(tt, lambda x: list_min(x))) AS qmin FROM tabs t JOIN thrs USING ({keys})")
    s.add("small", f"SELECT {keys}, thr, qmin, list_transform(tt, lambda x: list_transform(x, lambda y: CASE WHEN thr > qmin THEN least(((y - qmin) * {bins}) // (thr - qmin), {bins}) ELSE 0 END)) AS qq FROM lows")
    return s.add("scored", f"SELECT t.qid, c.vec_id, CAST(least({oracle.adc(m, 't.qq')}, {bins}) AS BIGINT) AS dist FROM placed c JOIN small t {join}")


NIBBLE = "SELECT qid, vec_id, dist FROM scored"


@query(pq_sql(16, 16).select(code_select(16)))
def q_pq4_encode(spark, sf):
    codes, _, _ = coded(spark, sf, 16, 16)
    return long_codes(codes, 16)


@query(pq_sql(16, 16, tabled=True).select(oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(16)} AS BIGINT) AS dist FROM codes c, tabs t", R)))
def q_adc_16x4(spark, sf):
    codes, tabs, _ = coded(spark, sf, 16, 16)
    return scan.adc_topk(codes, tabs, 16, R)


@query(nibble_sql().select("SELECT qid, CAST(j AS BIGINT) AS part, CAST(i AS BIGINT) AS idx, CAST(qq[j + 1][i + 1] AS BIGINT) AS bin FROM small, (SELECT unnest(range(0, 16)) AS j), (SELECT unnest(range(0, 16)) AS i)"))
def q_nibble_tables(spark, sf):
    codes, tabs, _ = coded(spark, sf, 16, 16)
    small = scan.nibble_tables(scan.with_prefix(codes, None, 20, R), tabs, 16, R)
    each = F.explode(F.array(*[F.struct(F.lit(j).cast("long").alias("part"), F.col(f"q{j}").alias("t")) for j in range(16)]))
    return small.select("qid", each.alias("x")).select("qid", "x.part", F.posexplode("x.t").alias("idx", "bin")).withColumn("idx", F.col("idx").cast("long"))


@query(pq_sql(16, 16).select("SELECT vec_id, " + ", ".join(f"CAST(c[{2 * j + 2}] * 16 + c[{2 * j + 1}] AS BIGINT) AS b{j}" for j in range(8)) + " FROM codes"))
def q_nibble_pack(spark, sf):
    codes, _, _ = coded(spark, sf, 16, 16)
    return encode.pack_nibble_codes(codes, 16).select("vec_id", *[F.col(f"b{j}").cast("long") for j in range(8)])


@query(pq_sql(16, 16).select(code_select(16)))
def q_nibble_unpack(spark, sf):
    codes, _, _ = coded(spark, sf, 16, 16)
    return long_codes(encode.unpack_nibble_codes(encode.pack_nibble_codes(codes, 16), 16), 16)


@query(
    pq_sql(16, 16).add("pos", "SELECT *, row_number() OVER (ORDER BY vec_id) - 1 AS pos FROM codes").select(
        "SELECT CAST(pos // 16 AS BIGINT) AS block, CAST(j AS BIGINT) AS part, string_agg(CAST(c[j + 1] AS VARCHAR), ',' ORDER BY pos) AS row FROM pos, (SELECT unnest(range(0, 16)) AS j) GROUP BY 1, 2"
    )
)
def q_block_transpose(spark, sf):
    codes, _, _ = coded(spark, sf, 16, 16)
    return encode.pack_blocks(codes, 16).select("block", "part", F.array_join(F.transform("row", lambda x: x.cast("string")), ",").alias("row"))


@query(nibble_sql().select(oracle.topk(NIBBLE, R)))
def q_nibble_topk(spark, sf):
    codes, tabs, _ = coded(spark, sf, 16, 16)
    small = scan.nibble_tables(scan.with_prefix(codes, None, 20, R), tabs, 16, R)
    return scan.nibble_topk(codes, small, 16, R).select("qid", "rk", "vec_id", "dist")


@query(nibble_sql().select(oracle.topk(NIBBLE, R)))
def q_nibble_kernel_x1(spark, sf):
    """Packed codes, sixteen bits a look-up, sums in bytes."""
    q, b = models.v0(spark, sf)
    model = models.pq0(spark, sf, 16, 16)
    return packed.nibble_scan(packed.encode_packed(b, model), q, model, R)


@query(nibble_sql().select(oracle.topk(NIBBLE, R)))
def q_nibble_kernel_x2(spark, sf):
    """Two components a step over columns of codes (the double-width form)."""
    codes, tabs, _ = coded(spark, sf, 16, 16)
    small = scan.nibble_tables(scan.with_prefix(codes, None, 20, R), tabs, 16, R)
    rows = [(r["qid"], [r[f"q{j}"] for j in range(16)]) for r in small.collect()]
    return scan.nibble_kernel(codes, rows, 16, R, 2)


@query(nibble_sql(m=8, k=64).select(oracle.topk(NIBBLE, R)))
def q_sixbit_topk(spark, sf):
    """Parts of six bits: 64-entry tables in the same scan."""
    codes, tabs, _ = coded(spark, sf, 8, 64)
    small = scan.nibble_tables(scan.with_prefix(codes, None, 20, R), tabs, 8, R)
    return scan.nibble_topk(codes, small, 8, R).select("qid", "rk", "vec_id", "dist")


def nibble_ivf_sql(ma: int, k: int = 8, m: int = 16, r: int = R, count: int = 20) -> Sql:
    s = oracle.probes(oracle.ivf(oracle.v0(), 64, k, m, 16), ma)
    s.add("shifted", "SELECT qid, list_id, e FROM probes")
    oracle.tables(s, "tabs", "fi", "shifted", 64, m, "qid, list_id")
    nibble_sql(r, count, m, s=s, keys="qid, list_id")
    return s


@query(nibble_ivf_sql(2).select(oracle.topk(NIBBLE, R)))
def q_nibble_ivf(spark, sf):
    """Each probed list has its own integer scale, as the lists are scanned one by one."""
    ivf = models.ivf0(spark, sf, 8, 16, 4)
    q, b = models.v0(spark, sf)
    tabs = ivf.tables(q, index.probes(q, ivf.coarse, 2))
    placed = scan.with_prefix(ivf.encode(b), None, 20, R, ("list_id",))
    small = scan.nibble_tables(placed, tabs, 16, R, ("list_id",))
    return scan.nibble_topk(placed, small, 16, R, ("list_id",)).select("qid", "rk", "vec_id", "dist")


def nibble_imi_sql() -> Sql:
    return nibble_sql(R, 20, 8, s=imi_full_sql(50), keys="qid, list_id")


@query(nibble_imi_sql().select(oracle.topk(NIBBLE, R)))
def q_nibble_imi(spark, sf):
    imi = models.imi0(spark, sf)
    q, b = models.v0(spark, sf)
    codes = imi.encode(b)
    tabs = imi.tables(q, imi.sequence(q, index.list_sizes(codes), 50))
    placed = scan.with_prefix(codes, None, 20, R, ("list_id",))
    return scan.nibble_topk(placed, scan.nibble_tables(placed, tabs, 8, R, ("list_id",)), 8, R, ("list_id",)).select("qid", "rk", "vec_id", "dist")


# -- nested codebooks --------------------------------------------------------------------------


def nested_sql(m: int = 4, k: int = 256, kc: int = 16, r2: int | str | None = None, fine: bool = True, iters: int = 3, rotated: bool = False) -> Sql:
    """Codebook p_cb renumbered (n_cb) so that idx % kc is the cluster; co_cb the clusters' floored means."""
    s = oracle.pq(oracle.v0(rotated), "p", "base", 64, m, k, iters)
    s.add("sums", "SELECT part, idx, sum(c) AS total FROM p_cb GROUP BY part, idx")
    s.add("ordered", f"SELECT part, idx, (row_number() OVER (PARTITION BY part ORDER BY total, idx) - 1) // {k // kc} AS cluster FROM sums")
    s.add("numbered", f"SELECT part, idx, cluster, (row_number() OVER (PARTITION BY part, cluster ORDER BY idx) - 1) * {kc} + cluster AS num FROM ordered")
    s.add("n_cb", "SELECT p.part, CAST(n.num AS BIGINT) AS idx, p.dim, p.c FROM p_cb p JOIN numbered n USING (part, idx)")
    s.add("co_cb", f"SELECT part, idx % {kc} AS idx, dim, CAST(floor(CAST(sum(c) AS DOUBLE) / count(*)) AS BIGINT) AS c FROM n_cb GROUP BY 1, 2, 3")
    oracle.encode(s, "codes", "n", "base", 64, m)
    oracle.tables(s, "ctabs", "co", "queries", 64, m)
    if fine:
        oracle.tables(s, "tabs", "n", "queries", 64, m)
    if r2:
        s.add("low", f"SELECT vec_id, list_transform(c, lambda x: x % {kc}) AS c, row_number() OVER (ORDER BY vec_id) <= {r2} AS prefix FROM codes")
        s.add("thrs", f"SELECT qid, max({oracle.adc(m)}) AS thr FROM low c, ctabs t WHERE prefix GROUP BY qid")
        s.add("lows", "SELECT t.*, thr, list_min(list_transform(tt, lambda x: list_min(x))) AS qmin FROM ctabs t JOIN thrs USING (qid)")
        s.add("small", "SELECT qid, list_transform(tt, lambda x: list_transform(x, lambda y: CASE WHEN thr > qmin THEN least(((y - qmin) * 255) // (thr - qmin), 255) ELSE 0 END)) AS qq FROM lows")
        s.add("buckets", f"SELECT * FROM (SELECT qid, vec_id, CAST({oracle.adc(m, 't.qq')} AS BIGINT) AS bucket FROM low c, small t) WHERE bucket <= 255")
        s.add("hist", "SELECT qid, bucket, sum(count(*)) OVER (PARTITION BY qid ORDER BY bucket) AS upto FROM buckets GROUP BY qid, bucket")
        s.add("cuts", f"SELECT qid, coalesce(min(bucket) FILTER (WHERE upto >= {r2}), max(bucket)) AS cutoff FROM hist GROUP BY qid")
        s.add("cands", "SELECT qid, vec_id, bucket FROM buckets JOIN cuts USING (qid) WHERE bucket <= cutoff")
    return s


R2 = 100


def nested(spark, sf, r2: int = R2, m: int = 4, b_coarse: int = 4, numbering: str = "ntile"):
    model = models.nested0(spark, sf, m, 8, b_coarse, numbering)
    q, b = models.v0(spark, sf)
    codes = encode.encode_pq(b, model)
    return q, codes, model, scan.first_pass(codes, index.lookup_tables(q, model, coarse=True), m, b_coarse, r2)


@query()
def q_nested_codebook(spark, sf):
    """Equal-size clusters of fine centroids: size of each cluster and mean distance to its coarse centroid."""
    model = models.nested0(spark, sf, numbering="same_size")
    rows = []
    for j in range(model.m):
        for c in range(16):
            own = model.books[j][c::16]
            rows.append((j, c, len(own), float(((own - model.coarse[j, c]) ** 2).sum(axis=1).mean())))
    return spark.createDataFrame(rows, "part long, cluster long, n long, mean_distance double")


@query(nested_sql(fine=False).select("SELECT CAST(part AS BIGINT) AS part, CAST(idx % 16 AS BIGINT) AS low, count(DISTINCT idx) AS n, CAST(max(d) AS BIGINT) AS largest FROM (SELECT f.part, f.idx, sum((f.c - o.c) * (f.c - o.c)) AS d FROM n_cb f JOIN co_cb o ON o.part = f.part AND o.dim = f.dim AND o.idx = f.idx % 16 GROUP BY 1, 2) GROUP BY 1, 2"))
def q_nested_property(spark, sf):
    """Low bits name the coarse centroid: each cluster's size and its farthest member."""
    model = models.nested0(spark, sf)
    rows = [(j, i, int(((c - model.coarse[j, i % 16]) ** 2).sum())) for j, book in enumerate(model.books) for i, c in enumerate(book)]
    return spark.createDataFrame(rows, "part long, idx long, d long").groupBy("part", (F.col("idx") % 16).alias("low")).agg(F.count("*").alias("n"), F.max("d").alias("largest"))


@query(nested_sql(fine=False, r2=R2).select("SELECT * FROM buckets"))
def q_nested_first_pass(spark, sf):
    return nested(spark, sf)[3]


@query(nested_sql(fine=False, r2=R2).select("SELECT qid, CAST(cutoff AS BIGINT) AS cutoff, (SELECT count(*) FROM cands x WHERE x.qid = cuts.qid) AS candidates FROM cuts"))
def q_capped_buckets(spark, sf):
    buckets = nested(spark, sf)[3]
    found = scan.candidates(buckets, R2).groupBy("qid").agg(F.count("*").alias("candidates"))
    return scan.capped_buckets(buckets, R2).join(found, "qid").select("qid", "cutoff", "candidates")


@query(nested_sql(fine=False, r2=R2).select("SELECT * FROM cands"))
def q_capped_kernel(spark, sf):
    """Buckets whose cap moves block by block within a task, then over all tasks."""
    q, b = models.v0(spark, sf)
    model = models.nested0(spark, sf)
    return packed.nested_candidates(packed.encode_packed(b, model), q, model, R2).select("qid", "vec_id", "bucket")


FINE = f"SELECT qid, vec_id, CAST({oracle.adc(4)} AS BIGINT) AS dist FROM cands JOIN codes c USING (vec_id) JOIN tabs t USING (qid)"


@query(nested_sql(r2=R2).select(oracle.topk(FINE, R)))
def q_nested_topk(spark, sf):
    """Candidates carry their codes; their fine tables are filled as codes name entries."""
    q, b = models.v0(spark, sf)
    model = models.nested0(spark, sf)
    return packed.rerank(packed.nested_candidates(packed.encode_packed(b, model), q, model, R2), q, model, R)


@query(nested_sql(r2=R2).select(oracle.topk(FINE, R)))
def q_nested_eager(spark, sf):
    """Whole fine tables instead of the entries that candidates name."""
    q, codes, model, buckets = nested(spark, sf)
    return scan.rerank(scan.candidates(buckets, R2), codes, q, model, R, "eager")


@query()
def q_nested_same_size(spark, sf):
    """The method's own numbering by equal-size clusters."""
    q, codes, model, buckets = nested(spark, sf, numbering="same_size")
    return scan.rerank(scan.candidates(buckets, R2), codes, q, model, R)


@query(nested_sql(fine=False, r2=R2).select("SELECT qid, count(*) AS entries, round(count(*) / 1024.0, 6) AS share FROM (SELECT DISTINCT qid, j, c.c[j + 1] FROM cands JOIN codes c USING (vec_id), (SELECT unnest(range(0, 4)) AS j)) GROUP BY qid"))
def q_lazy_table_entries(spark, sf):
    q, b = models.v0(spark, sf)
    model = models.nested0(spark, sf)
    touched = packed.rerank(packed.nested_candidates(packed.encode_packed(b, model), q, model, R2), q, model, R, entries=True)
    return touched.select("qid", F.col("filled").alias("entries"), F.round(F.col("filled") / F.lit(1024.0), 6).alias("share"))


TRUTH = f"SELECT qid, arg_min(vec_id, (dist, vec_id)) AS truth FROM (SELECT q.qid, v.vec_id, {oracle.l2('q.e', 'v.e')} AS dist FROM queries q, base v WHERE q.qid <> v.vec_id) GROUP BY qid"


@query(
    nested_sql(fine=False, r2=R2).add("truths", TRUTH).select("SELECT count(*) AS queries, count(c.vec_id) AS hits, round(count(c.vec_id) * 1.0 / count(*), 6) AS recall FROM truths t LEFT JOIN cands c ON c.qid = t.qid AND c.vec_id = t.truth")
)
def q_candidate_recall(spark, sf):
    from vecspark.operators.measures import candidate_recall, ground_truth

    _, _, _, buckets = nested(spark, sf)
    return candidate_recall(scan.candidates(buckets, R2), ground_truth(*models.v0(spark, sf), 64))


R2_GRID = (25, 50, 100, 200, 300)


def tune_sql() -> str:
    parts = []
    for r2 in R2_GRID:
        inner = nested_sql(fine=False, r2=r2).add("truths", TRUTH).select("SELECT count(c.vec_id) AS hits, count(*) AS queries FROM truths t LEFT JOIN cands c ON c.qid = t.qid AND c.vec_id = t.truth")
        parts.append(f"SELECT CAST({r2} AS BIGINT) AS r2, * FROM ({inner})")
    fine = nested_sql().add("truths", TRUTH).add("found", oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(4)} AS BIGINT) AS dist FROM codes c, tabs t", R)).select("SELECT count(f.vec_id) AS fine_hits FROM truths t LEFT JOIN found f ON f.qid = t.qid AND f.vec_id = t.truth")
    return f"WITH grid AS ({' UNION ALL '.join(parts)}), fine AS ({fine}) SELECT r2, hits, queries, fine_hits, CAST(CASE WHEN r2 = (SELECT min(r2) FROM grid, fine WHERE hits * 100 >= fine_hits * 105) THEN 1 ELSE 0 END AS BIGINT) AS chosen FROM grid, fine"


@query(tune_sql())
def q_tune_r2(spark, sf):
    """The least r2 whose candidates hold at least 5 % more true neighbours than the fine scan returns."""
    from vecspark.operators.measures import candidate_recall, ground_truth, recall_at

    q, b = models.v0(spark, sf)
    truth = ground_truth(q, b, 64).cache()
    out = None
    for r2 in R2_GRID:
        row = candidate_recall(scan.candidates(nested(spark, sf, r2)[3], r2), truth).select(F.lit(r2).cast("long").alias("r2"), "hits", "queries")
        out = row if out is None else out.unionByName(row)
    _, codes, model, _ = nested(spark, sf)
    fine = recall_at(scan.adc_topk(codes, index.lookup_tables(q, model), 4, R), truth, (R,)).select(F.col("hits").alias("fine_hits"))
    grid = out.crossJoin(F.broadcast(fine))
    least = grid.where("hits * 100 >= fine_hits * 105").agg(F.min("r2").alias("least"))
    return grid.crossJoin(F.broadcast(least)).select("r2", "hits", "queries", "fine_hits", F.coalesce(F.col("r2") == F.col("least"), F.lit(False)).cast("long").alias("chosen"))


@query(costs.two_codes_sql())
def q_two_codes_memory(spark, sf):
    """Bytes of the vectors' codes with separate coarse codes, and nested (coarse bits are the low bits)."""
    return costs.two_codes(T.load(spark, sf, "embeddings"))
