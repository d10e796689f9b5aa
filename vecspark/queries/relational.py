"""Queries of the relational, scalar, streaming and function surface around the methods."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecspark.functions import udfs, vectors
from vecspark.functions.bits import interleave
from vecspark.functions.ranking import ranked, top_k
from vecspark.operators import encode, index, scan
from vecspark.operators.exact import counts_within
from vecspark.queries import models, oracle
from vecspark.queries.core import ADC, EXACT_SQL, code_select, coded, exact, ivf_sql, long_codes, pq_sql
from vecspark.queries.registry import query
from vecspark.sources import tables as T
from vecspark.streaming import profiles

TOP10 = oracle.topk(ADC, 10)


@query(" UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in T.TABLES))
def o_scan_counts(spark, sf):
    out = None
    for name in T.TABLES:
        row = T.load(spark, sf, name).agg(F.count("*").alias("n")).select(F.lit(name).alias("name"), "n")
        out = row if out is None else out.unionByName(row)
    return out


@query(oracle.v0().select("SELECT vec_id, CAST(unnest(range(0, 64)) AS BIGINT) AS i, unnest(e) AS x FROM v"))
def o_explode_roundtrip(spark, sf):
    v = T.vectors_embeddings(spark, sf).select("vec_id", F.posexplode("e").alias("i", "x"))
    back = v.groupBy("vec_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda s: s["x"]).alias("e"))
    return back.select("vec_id", F.posexplode("e").alias("i", "x")).withColumn("i", F.col("i").cast("long"))


@query(oracle.v2().select("SELECT vec_id, CAST(len(list_filter(e, lambda x: x <> 0)) AS BIGINT) AS held, CAST(list_sum(e) AS BIGINT) AS total FROM v"))
def o_sparse_dense(spark, sf):
    v = T.vectors_documents(spark, sf).withColumn("sparse", vectors.sparse(F.col("e")))
    dense = vectors.dense(F.col("sparse"), 128)
    return v.select("vec_id", F.size("sparse").cast("long").alias("held"), F.aggregate(dense, F.lit(0).cast("long"), lambda s, x: s + x).alias("total"))


@query(oracle.v0().select(oracle.topk(f"SELECT * FROM ({EXACT_SQL}) JOIN (SELECT vec_id, label FROM embeddings WHERE label IN (1, 3, 5)) USING (vec_id)", 5)))
def o_filtered_knn_pre(spark, sf):
    """The attribute filter runs below the scan and reaches the files."""
    q, _ = models.v0(spark, sf)
    held = T.load(spark, sf, "embeddings").where(F.col("label").isin(1, 3, 5)).select("vec_id", vectors.fixed_point(F.col("embedding")).alias("e"))
    return top_k(exact(q, held, 64), 5, ["qid"], ["dist", "vec_id"])


@query(oracle.v0().add("near", oracle.topk(EXACT_SQL, 20)).select("SELECT qid, rk, vec_id, dist FROM near JOIN embeddings USING (vec_id) WHERE label = 3"))
def o_filtered_knn_post(spark, sf):
    q, b = models.v0(spark, sf)
    near = top_k(exact(q, b, 64), 20, ["qid"], ["dist", "vec_id"])
    return near.join(T.load(spark, sf, "embeddings").where("label = 3").select("vec_id"), "vec_id").select("qid", "rk", "vec_id", "dist")


@query(pq_sql(8, 16, tabled=True).add("near", TOP10).select("SELECT qid, vec_id, CAST(label AS BIGINT) AS label, dist FROM near JOIN embeddings USING (vec_id)"))
def o_join_metadata(spark, sf):
    codes, tabs, _ = coded(spark, sf)
    return scan.adc_topk(codes, tabs, 8, 10).join(T.load(spark, sf, "embeddings").select("vec_id", F.col("label").cast("long").alias("label")), "vec_id").select("qid", "vec_id", "label", "dist")


@query(oracle.v0().select(f"SELECT qid, count(*) AS n FROM ({EXACT_SQL}) WHERE dist < 26000000 GROUP BY qid"))
def o_theta_radius_join(spark, sf):
    """A join by a bound on distances, of which only counts are asked; distances are integers."""
    return counts_within(*models.v0(spark, sf), 26_000_000 - 1).select("qid", F.col("inside").alias("n"))


@query("SELECT a.vec_id AS a, b.vec_id AS b FROM embeddings a JOIN embeddings b ON b.vec_id BETWEEN a.vec_id + 1 AND a.vec_id + 3 WHERE a.label = b.label")
def o_range_join(spark, sf):
    """A range join by equal buckets: each row is listed under its bucket and the next."""
    v = T.load(spark, sf, "embeddings").select("vec_id", "label")
    x = v.select(F.col("vec_id").alias("a"), "label", F.floor(F.col("vec_id") / 4).alias("bucket"))
    y = v.select(F.col("vec_id").alias("b"), "label", F.explode(F.array(F.floor(F.col("vec_id") / 4), F.floor(F.col("vec_id") / 4) - 1)).alias("bucket"))
    return x.join(y, ["bucket", "label"]).where("b between a + 1 and a + 3").select("a", "b").distinct()


@query("SELECT e.event_id, CAST(coalesce((SELECT max(p.event_id) FROM events p WHERE p.user_id = e.user_id AND p.event_id < e.event_id), -1) AS BIGINT) AS before FROM events e")
def o_asof_join(spark, sf):
    """The last earlier event of the same user: places within users, and an equi-join on the place before."""
    e = ranked(T.load(spark, sf, "events").select("event_id", "user_id"), "event_id", "place", ("user_id",))
    before = e.select("user_id", (F.col("place") + 1).alias("place"), F.col("event_id").alias("before"))
    return e.join(before, ["user_id", "place"], "left").select("event_id", F.coalesce("before", F.lit(-1)).cast("long").alias("before"))


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def o_interval_join(spark, sf):
    e = T.load(spark, sf, "events").select("event_id", "user_id", "ts")
    x, y = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta")), e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"))
    return x.join(y, "user_id").where(F.expr("tb > ta and tb <= ta + interval 1 hour")).select("a", "b")


@query(oracle.v2().select("SELECT vec_id FROM v WHERE vec_id IN (SELECT doc_id FROM labels)"))
def o_semi_join(spark, sf):
    docs = T.load(spark, sf, "documents").where("length(text) > 0").select(F.col("doc_id").alias("vec_id"))
    return docs.join(T.load(spark, sf, "labels").select(F.col("doc_id").alias("vec_id")), "vec_id", "left_semi")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def o_anti_join(spark, sf):
    return T.load(spark, sf, "documents").select("doc_id").join(T.load(spark, sf, "labels").select("doc_id"), "doc_id", "left_anti")


@query(oracle.v0().select(oracle.topk(f"SELECT a.vec_id AS qid, b.vec_id, {oracle.l2('a.e', 'b.e')} AS dist FROM v a, v b WHERE a.vec_id <> b.vec_id AND a.vec_id % 50 = 0", 3)))
def o_knn_self_join(spark, sf):
    """Edges of the neighbour graph that leave every fiftieth node; no node is its own neighbour."""
    q, v = models.v0(spark, sf)
    return top_k(exact(q, v, 64).where("qid <> vec_id"), 3, ["qid"], ["dist", "vec_id"])


@query("SELECT count(*) AS n FROM nation a, nation b WHERE a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey")
def o_nested_loop_join(spark, sf):
    n = T.load(spark, sf, "nation")
    a, b = n.select(F.col("n_nationkey").alias("x"), F.col("n_regionkey").alias("rx")), n.select(F.col("n_nationkey").alias("y"), F.col("n_regionkey").alias("ry"))
    return a.join(F.broadcast(b), (F.col("x") < F.col("y")) & (F.col("rx") == F.col("ry"))).agg(F.count("*").alias("n"))


@query(ivf_sql().select("SELECT CAST(coalesce(list_id, -1) AS BIGINT) AS list_id, CAST(coalesce(label, -1) AS BIGINT) AS label, count(*) AS n FROM codes JOIN embeddings USING (vec_id) GROUP BY ROLLUP (list_id, label)"))
def o_list_rollup(spark, sf):
    codes = models.ivf0(spark, sf).encode(models.v0(spark, sf)[1]).join(T.load(spark, sf, "embeddings").select("vec_id", "label"), "vec_id")
    return codes.rollup("list_id", "label").agg(F.count("*").alias("n")).select(F.coalesce("list_id", F.lit(-1)).cast("long").alias("list_id"), F.coalesce("label", F.lit(-1)).cast("long").alias("label"), "n")


@query("SELECT coalesce(event_type, 'all') AS event_type, CAST(coalesce(h, -1) AS BIGINT) AS hour, count(*) AS n FROM (SELECT event_type, hour(ts) AS h FROM events) GROUP BY CUBE (event_type, h)")
def o_recall_cube(spark, sf):
    e = T.load(spark, sf, "events").select("event_type", F.hour("ts").alias("h"))
    return e.cube("event_type", "h").agg(F.count("*").alias("n")).select(F.coalesce("event_type", F.lit("all")).alias("event_type"), F.coalesce("h", F.lit(-1)).cast("long").alias("hour"), "n")


@query("SELECT coalesce(l_returnflag, '-') AS flag, coalesce(l_linestatus, '-') AS status, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), (l_returnflag, l_linestatus))")
def o_grouping_sets(spark, sf):
    T.load(spark, sf, "lineitem").select("l_returnflag", "l_linestatus").createOrReplaceTempView("lineitem_flags")
    return spark.sql("select coalesce(l_returnflag, '-') as flag, coalesce(l_linestatus, '-') as status, count(*) as n from lineitem_flags group by grouping sets ((l_returnflag), (l_linestatus), (l_returnflag, l_linestatus))")


@query(pq_sql(8, 16).select("SELECT count(DISTINCT c) AS codes, count(DISTINCT c[1]) AS firsts FROM codes"))
def o_distinct_codes(spark, sf):
    codes, _, _ = coded(spark, sf)
    return codes.agg(F.countDistinct(*encode.code_columns(8)).alias("codes"), F.countDistinct("c0").alias("firsts"))


@query(oracle.v0().select("SELECT CAST(label AS BIGINT) AS label, CAST(i AS BIGINT) AS i, CAST(floor(CAST(sum(x) AS DOUBLE) / count(*)) AS BIGINT) AS mean FROM (SELECT vec_id, unnest(range(0, 64)) AS i, unnest(e) AS x FROM v) JOIN embeddings USING (vec_id) GROUP BY label, i"))
def o_vector_mean(spark, sf):
    v = T.vectors_embeddings(spark, sf).join(T.load(spark, sf, "embeddings").select("vec_id", F.col("label").cast("long").alias("label")), "vec_id")
    means = v.groupBy("label").agg(F.array(*[F.floor(F.sum(F.col("e")[i]).cast("double") / F.count("*")).cast("long") for i in range(64)]).alias("m"))
    return means.select("label", F.posexplode("m").alias("i", "mean")).withColumn("i", F.col("i").cast("long"))


@query("SELECT l_returnflag AS flag, round(quantile_cont(l_extendedprice, 0.25), 4) AS q25, round(quantile_cont(l_extendedprice, 0.5), 4) AS median, round(quantile_cont(l_extendedprice, 0.95), 4) AS q95 FROM lineitem GROUP BY 1")
def o_percentiles(spark, sf):
    return T.load(spark, sf, "lineitem").groupBy(F.col("l_returnflag").alias("flag")).agg(*[F.round(F.percentile("l_extendedprice", F.lit(p)), 4).alias(n) for p, n in ((0.25, "q25"), (0.5, "median"), (0.95, "q95"))])


@query()
def o_approx_distinct(spark, sf):
    return T.load(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_quantity", 0.5, 1000).alias("median"))


@query(pq_sql(16, 16, tabled=True).add("near", f"SELECT qid, vec_id, CAST({oracle.adc(16)} AS BIGINT) // 1000000 AS dist FROM codes c, tabs t").select("SELECT * FROM (SELECT qid, vec_id, dist, rank() OVER w AS rk, dense_rank() OVER w AS drk FROM near WINDOW w AS (PARTITION BY qid ORDER BY dist)) WHERE drk <= 2"))
def o_rank_ties(spark, sf):
    codes, tabs, _ = coded(spark, sf, 16, 16)
    near = scan.with_tables(codes, tabs).select("qid", "vec_id", F.expr("cast(0 as bigint)").alias("z"), scan.adc(16).alias("d")).select("qid", "vec_id", F.floor(F.col("d") / 1_000_000).cast("long").alias("dist"))
    w = W.partitionBy("qid").orderBy("dist")
    return near.select("qid", "vec_id", "dist", F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("drk")).where("drk <= 2")


@query("SELECT vec_id, ntile(8) OVER (PARTITION BY label ORDER BY vec_id) AS part FROM embeddings")
def o_ntile_partitions(spark, sf):
    return T.load(spark, sf, "embeddings").select("vec_id", F.ntile(8).over(W.partitionBy("label").orderBy("vec_id")).cast("long").alias("part"))


@query(pq_sql(8, 16, tabled=True).add("near", TOP10).select("SELECT qid, rk, coalesce(dist - lag(dist) OVER (PARTITION BY qid ORDER BY rk), 0) AS gap FROM near"))
def o_gap_lag(spark, sf):
    codes, tabs, _ = coded(spark, sf)
    near = scan.adc_topk(codes, tabs, 8, 10)
    return near.select("qid", "rk", F.coalesce(F.col("dist") - F.lag("dist").over(W.partitionBy("qid").orderBy("rk")), F.lit(0)).alias("gap"))


@query("SELECT l_orderkey, CAST(l_linenumber AS BIGINT) AS line, l_partkey AS part, CAST(sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_quantity ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM lineitem")
def o_running_budget(spark, sf):
    w = W.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity").rowsBetween(W.unboundedPreceding, W.currentRow)
    return T.load(spark, sf, "lineitem").select("l_orderkey", F.col("l_linenumber").cast("long").alias("line"), F.col("l_partkey").alias("part"), F.sum("l_quantity").over(w).cast("long").alias("running"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day FROM (SELECT event_id, user_id, date_trunc('second', ts) AS ts FROM events)")
def o_range_frame(spark, sf):
    e = T.load(spark, sf, "events").select("event_id", "user_id", F.unix_timestamp(F.date_trunc("second", F.col("ts").cast("timestamp"))).alias("s"))
    return e.select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)).alias("day"))


@query("SELECT l_orderkey, CAST(l_linenumber AS BIGINT) AS line, CAST(floor(l_extendedprice * 100 + 0.5) AS BIGINT) AS cents FROM lineitem ORDER BY cents DESC, l_orderkey, line LIMIT 25")
def o_global_topk(spark, sf):
    x = T.load(spark, sf, "lineitem").select("l_orderkey", F.col("l_linenumber").cast("long").alias("line"), F.floor(F.col("l_extendedprice") * 100 + 0.5).cast("long").alias("cents"))
    return x.orderBy(F.col("cents").desc(), "l_orderkey", "line").limit(25)


@query("SELECT o_orderpriority AS priority, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS rk FROM orders) WHERE rk <= 3")
def o_group_topk(spark, sf):
    return top_k(T.load(spark, sf, "orders"), 3, ["o_orderpriority"], [F.col("o_totalprice").desc(), F.col("o_orderkey")]).select(F.col("o_orderpriority").alias("priority"), "o_orderkey")


@query(oracle.v0().select(f"SELECT qid, arg_min(vec_id, (dist, vec_id)) AS vec_id FROM ({EXACT_SQL}) GROUP BY qid"))
def o_argmin(spark, sf):
    q, b = models.v0(spark, sf)
    return exact(q, b, 64).groupBy("qid").agg(F.min_by("vec_id", F.struct("dist", "vec_id")).alias("vec_id"))




def both_sql():
    s = oracle.encode(oracle.pq(pq_sql(8, 16, tabled=True), "p2", "base", 64, 4, 16, 3), "codes2", "p2", "base", 64, 4)
    oracle.tables(s, "tabs2", "p2", "queries", 64, 4)
    s.add("a", TOP10)
    return s.add("b", oracle.topk(f"SELECT qid, vec_id, CAST({oracle.adc(4)} AS BIGINT) AS dist FROM codes2 c, tabs2 t", 10))


def both(spark, sf):
    a = scan.adc_topk(*coded(spark, sf)[:2], 8, 10).select("qid", "vec_id")
    return a, scan.adc_topk(*coded(spark, sf, 4, 16)[:2], 4, 10).select("qid", "vec_id")


@query(both_sql().select("SELECT qid, vec_id FROM a INTERSECT SELECT qid, vec_id FROM b"))
def o_result_overlap(spark, sf):
    a, b = both(spark, sf)
    return a.intersect(b)


@query(both_sql().select("SELECT qid, vec_id FROM a EXCEPT SELECT qid, vec_id FROM b"))
def o_lost_neighbours(spark, sf):
    a, b = both(spark, sf)
    return a.exceptAll(b)


@query(both_sql().select("SELECT qid, vec_id FROM a UNION SELECT qid, vec_id FROM b"))
def o_union_trees(spark, sf):
    a, b = both(spark, sf)
    return a.unionByName(b).distinct()


@query("SELECT doc_id, CAST(length(text) AS BIGINT) AS n_chars, CAST(len(string_split(text, chr(10))) AS BIGINT) AS n_lines, lower(substr(trim(text), 1, 20)) AS head, md5(text) AS md5 FROM documents")
def o_text_features(spark, sf):
    t = F.col("text")
    return T.load(spark, sf, "documents").select("doc_id", F.length(t).cast("long").alias("n_chars"), F.size(F.split(t, "\n", -1)).cast("long").alias("n_lines"), F.lower(F.substring(F.trim(t), 1, 20)).alias("head"), F.md5(t.cast("binary")).alias("md5"))


@query("SELECT vec_id, (vec_id & 15) AS low, (vec_id >> 4) AS high, xor(vec_id, 85) AS mixed, CAST(bit_count(vec_id) AS BIGINT) AS ones, (vec_id & 1) + ((label & 1) << 1) + (((vec_id >> 1) & 1) << 2) + (((label >> 1) & 1) << 3) AS z FROM (SELECT vec_id, CAST(label AS BIGINT) AS label FROM embeddings)")
def o_bit_codes(spark, sf):
    v = T.load(spark, sf, "embeddings").select("vec_id", F.col("label").cast("long").alias("label"))
    x = F.col("vec_id")
    return v.select("vec_id", x.bitwiseAND(15).alias("low"), F.shiftright(x, 4).alias("high"), x.bitwiseXOR(85).alias("mixed"), F.bit_count(x).cast("long").alias("ones"), interleave([F.col("label"), x], 2).alias("z"))


@query("SELECT event_type, CAST(hour(ts) AS BIGINT) AS hour, CAST(date_diff('day', DATE '2020-01-01', CAST(ts AS DATE)) AS BIGINT) AS day, count(*) AS n FROM events GROUP BY 1, 2, 3")
def o_event_hours(spark, sf):
    return T.load(spark, sf, "events").groupBy("event_type", F.hour("ts").cast("long").alias("hour"), F.datediff(F.to_date("ts"), F.lit("2020-01-01").cast("date")).cast("long").alias("day")).agg(F.count("*").alias("n"))


@query(oracle.v0().select("SELECT vec_id, list_min(e[1:8]) AS least, list_max(e) AS most, CAST(list_position(e, list_max(e)) AS BIGINT) AS at, CAST(list_sum(e) AS BIGINT) AS total FROM v"))
def o_array_tables(spark, sf):
    return T.vectors_embeddings(spark, sf).select("vec_id", F.array_min(F.slice("e", 1, 8)).alias("least"), F.array_max("e").alias("most"), F.array_position("e", F.array_max("e")).alias("at"), F.aggregate("e", F.lit(0).cast("long"), lambda s, x: s + x).alias("total"))


@query("SELECT json_extract_string(props, '$.k') AS k, count(*) AS n FROM events GROUP BY 1")
def o_props_json(spark, sf):
    return T.load(spark, sf, "events").groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n"))


@query("SELECT l_orderkey, count(*) AS n FROM lineitem WHERE l_extendedprice > (SELECT avg(l_extendedprice) * 1.5 FROM lineitem) GROUP BY 1")
def o_scalar_threshold(spark, sf):
    T.load(spark, sf, "lineitem").select("l_orderkey", "l_extendedprice").createOrReplaceTempView("lineitem_prices")
    return spark.sql("select l_orderkey, count(*) as n from lineitem_prices where l_extendedprice > (select avg(l_extendedprice) * 1.5 from lineitem_prices) group by 1")


@query("SELECT o_orderkey FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity >= 49)")
def o_exists(spark, sf):
    T.load(spark, sf, "orders").createOrReplaceTempView("orders_v")
    T.load(spark, sf, "lineitem").createOrReplaceTempView("lineitem_v")
    return spark.sql("select o_orderkey from orders_v o where exists (select 1 from lineitem_v where l_orderkey = o_orderkey and l_quantity >= 49)")


@query("SELECT CAST(vec_id % 10 AS BIGINT) AS fold, count(*) AS n FROM embeddings GROUP BY 1")
def o_split_sizes(spark, sf):
    return T.load(spark, sf, "embeddings").groupBy(F.pmod("vec_id", F.lit(10)).alias("fold")).agg(F.count("*").alias("n"))


# -- functions ---------------------------------------------------------------------------------


@query(pq_sql(8, 16).select(code_select(8)))
def u_encode_udf(spark, sf):
    b, model = models.v0(spark, sf)[1], models.pq0(spark, sf, 8, 16)
    coded_ = b.select("vec_id", udfs.encode_udf(model)("e").alias("c"))
    return coded_.select("vec_id", *[F.col("c")[j].alias(f"c{j}") for j in range(8)])


@query(pq_sql(8, 16, tabled=True).select(ADC))
def u_adc_udf(spark, sf):
    """Table-sum distance as an Arrow function of a code and the query's number."""
    q, b = models.v0(spark, sf)
    model = models.pq0(spark, sf, 8, 16)
    tables = {r["qid"]: np.array([r[f"t{j}"] for j in range(8)]) for r in index.lookup_tables(q, model).collect()}  # a batch of queries
    codes = encode.encode_pq(b, model).crossJoin(F.broadcast(q.select("qid")))
    return codes.select("qid", "vec_id", udfs.adc_udf(model, tables)(F.array(*encode.code_columns(8)), "qid").alias("dist"))


@query(oracle.v0().select("SELECT vec_id, CAST(unnest(range(0, 64)) AS BIGINT) AS pos, unnest(e) AS x FROM v"))
def u_components_udtf(spark, sf):
    udfs.register(spark)
    T.vectors_embeddings(spark, sf).createOrReplaceTempView("some_vectors")
    return spark.sql("select vec_id, cast(c.pos as bigint) as pos, c.x from some_vectors, lateral vector_components(e) c")


@query(oracle.v0().select("SELECT CAST(label AS BIGINT) AS label, CAST(i AS BIGINT) AS i, CAST(floor(avg(x)) AS BIGINT) AS mean FROM (SELECT vec_id, unnest(range(0, 64)) AS i, unnest(e) AS x FROM v) JOIN embeddings USING (vec_id) GROUP BY label, i"))
def u_vector_mean_udaf(spark, sf):
    v = T.vectors_embeddings(spark, sf).join(T.load(spark, sf, "embeddings").select("vec_id", F.col("label").cast("long").alias("label")), "vec_id")
    return v.groupBy("label").agg(udfs.vector_mean("e").alias("m")).select("label", F.posexplode("m").alias("i", "mean")).withColumn("i", F.col("i").cast("long"))


# -- streams -----------------------------------------------------------------------------------


@query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def s_tumbling(spark, sf):
    out = profiles.drain(profiles.tumbling(profiles.read_events(spark, sf)), "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@query("SELECT strftime(d - INTERVAL (k) DAY, '%Y-%m-%d') AS day, count(*) AS n FROM (SELECT date_trunc('day', ts) AS d, unnest([0, 1]) AS k FROM events) GROUP BY 1")
def s_sliding(spark, sf):
    out = profiles.drain(profiles.sliding(profiles.read_events(spark, sf)), "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n")


@query(
    "WITH marked AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), "
    "numbered AS (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM marked) SELECT user_id, CAST(epoch_us(min(ts)) AS BIGINT) AS start, count(*) AS n FROM numbered GROUP BY user_id, s"
)
def s_session(spark, sf):
    out = profiles.drain(profiles.sessions(profiles.read_events(spark, sf)), "complete")
    return out.select("user_id", F.unix_micros("start").alias("start"), "n")


@query("SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
def s_dedup(spark, sf):
    """The stream read twice over: repeated ids are dropped."""
    e = profiles.read_events(spark, sf).select("event_id", "ts")
    return profiles.drain(profiles.deduplicated(e.unionByName(e))).agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"))


@query("SELECT c_mktsegment AS segment, count(*) AS n FROM events JOIN customer ON c_custkey = user_id GROUP BY 1")
def s_static_join(spark, sf):
    static = T.load(spark, sf, "customer").select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("segment"))
    return profiles.drain(profiles.with_static(profiles.read_events(spark, sf).select("user_id", "ts"), static, "user_id")).groupBy("segment").agg(F.count("*").alias("n"))


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def s_stream_join(spark, sf):
    return profiles.drain(profiles.paired(profiles.read_events(spark, sf), profiles.read_events(spark, sf)))


@query()
def s_running_profiles(spark, sf):
    """Stateful totals by user; the last row of a user is its profile."""
    out = profiles.drain(profiles.running_profiles(profiles.read_events(spark, sf).select("user_id", "value")), "update")
    return out.groupBy("user_id").agg(F.max("n").alias("n"))
