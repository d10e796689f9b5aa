"""Scans of codes: plain, bounded, nibble and nested; declarative forms and Arrow kernels.

Tables of a batch of queries are small (queries x parts x centroids) and broadcast;
the codes stay where they are. Results are (qid, rk, vec_id, dist), ties by vec_id.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecspark.functions.ranking import prefix_ends, top_k
from vecspark.functions.vectors import total
from vecspark.operators.encode import code_columns
from vecspark.operators.index import lookup_tables
from vecspark.operators.codebook import PQModel
from vecspark.plans.kernels import joined, least_rows, map_batches

BROADCAST_BYTES = 256 << 20


def table_columns(m: int) -> list[str]:
    return [f"t{j}" for j in range(m)]


def adc(m: int, codes: str = "c", tables: str = "t") -> Column:
    """The table-sum distance: an unrolled sum of m look-ups."""
    return total([F.col(f"{tables}{j}")[F.col(f"{codes}{j}").cast("int")] for j in range(m)])


def adc_packed(packed: Column, m: int, b: int = 8) -> Column:
    """The same from one long that holds all codes (b * m at most 64 bits)."""
    return total([F.col(f"t{j}")[F.shiftrightunsigned(packed, b * j).bitwiseAND((1 << b) - 1).cast("int")] for j in range(m)])


def with_tables(codes: DataFrame, tables: DataFrame, keys: tuple[str, ...] = (), rows: int | None = None, row_bytes: int = 0) -> DataFrame:
    """Codes joined with the tables of the queries that look at them.

    ``rows`` and ``row_bytes``, if known, decide: small tables are broadcast, others are
    sent to their lists by a shuffle join on the list.
    """
    small = rows is None or rows * row_bytes <= BROADCAST_BYTES
    side = F.broadcast(tables) if small else tables
    return codes.join(side, list(keys)) if keys else codes.crossJoin(side)


def adc_topk(codes: DataFrame, tables: DataFrame, m: int, r: int, keys: tuple[str, ...] = ()) -> DataFrame:
    scored = with_tables(codes, tables, keys).select("qid", "vec_id", adc(m).alias("dist"))
    return top_k(scored, r, ["qid"], ["dist", "vec_id"])


def kernel_topk(codes: DataFrame, table_rows: list, m: int, r: int, variant: str = "columns", b: int = 8) -> DataFrame:
    """Arrow-kernel scan for tables held by the driver: [(qid, list_id or None, m x k array)].

    Variants that the paper measures, all with one result: ``columns`` (component by
    component), ``packed`` (one word, shifts), ``vertical`` (eight codes at a time),
    ``gather`` (one take over a block of transposed codes).
    """
    names = code_columns(m)
    listed = bool(table_rows) and table_rows[0][1] is not None
    integer = bool(table_rows) and np.issubdtype(np.asarray(table_rows[0][2]).dtype, np.integer)

    def make():
        tables = [(q, lst, np.asarray(t)) for q, lst, t in table_rows]

        def distances(c: np.ndarray, t: np.ndarray) -> np.ndarray:
            if variant == "gather":
                return t.ravel().take(c + (np.arange(m) * t.shape[1])[:, None]).sum(axis=0)
            if variant == "vertical":
                out = np.zeros(c.shape[1], t.dtype)
                for at in range(0, c.shape[1], 8):
                    for j in range(m):
                        out[at : at + 8] += t[j][c[j, at : at + 8]]
                return out
            if variant == "packed":
                word = np.zeros(c.shape[1], np.uint64)
                for j in range(m):
                    word |= c[j].astype(np.uint64) << np.uint64(b * j)
                mask = np.uint64((1 << b) - 1)
                return sum(t[j][((word >> np.uint64(b * j)) & mask).astype(np.int64)] for j in range(m))
            return sum(t[j][c[j]] for j in range(m))

        def each(batch):
            ids = batch["vec_id"].to_numpy(zero_copy_only=False)
            c = np.stack([batch[n].to_numpy(zero_copy_only=False) for n in names]).astype(np.int64)
            lists = batch["list_id"].to_numpy(zero_copy_only=False) if listed else None
            out = {"qid": [], "vec_id": [], "dist": []}
            for q, lst, t in tables:
                own = np.flatnonzero(lists == lst) if listed else slice(None)
                d, who = distances(c[:, own], t), ids[own]
                kept = least_rows(d, who, r)
                out["qid"].append(np.full(len(kept), q))
                out["vec_id"].append(who[kept])
                out["dist"].append(d[kept])
            return joined(out)

        return each

    part = map_batches(codes.select("vec_id", *(["list_id"] if listed else []), *names), make, f"qid long, vec_id long, dist {'long' if integer else 'double'}")
    return top_k(part, r, ["qid"], ["dist", "vec_id"])


# -- quantized tables --------------------------------------------------------------------------


def with_bounds(tables: DataFrame, m: int) -> DataFrame:
    """Adds qmin, the least entry over all tables."""
    return tables.withColumn("qmin", F.array_min(F.array(*[F.array_min(f"t{j}") for j in range(m)])) if m > 1 else F.array_min("t0"))


def prefix_thresholds(placed: DataFrame, tables: DataFrame, m: int, r: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """(qid, keys, thr): the r-th distance among the codes marked as prefix (the greatest if fewer)."""
    scored = with_tables(placed.where("prefix"), tables, keys).select("qid", *keys, "vec_id", adc(m).alias("dist"))
    return top_k(scored, r, ["qid", *keys], ["dist", "vec_id"]).groupBy("qid", *keys).agg(F.max("dist").alias("thr"))


def sum_of_maxima(tables: DataFrame, m: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """Control for the upper bound: no distance is greater, so the bins are wide."""
    return tables.select("qid", *keys, total([F.array_max(f"t{j}") for j in range(m)]).alias("thr"))


def quantized(x: Column, bins: int) -> Column:
    """Bins 0 .. bins-1 between qmin and thr, overflow = bins; exact floor division for integers."""
    return F.least(F.when(F.col("thr") > F.col("qmin"), F.floor(((x - F.col("qmin")) * bins) / (F.col("thr") - F.col("qmin")))).otherwise(F.lit(0)), F.lit(bins)).cast("long")


def quantize_tables(tables: DataFrame, m: int, bins: int = 127) -> DataFrame:
    """(.., t0 .., qmin, thr) -> adds q0 .. q{m-1}."""
    return tables.withColumns({f"q{j}": F.transform(f"t{j}", lambda x: quantized(x, bins)) for j in range(m)})


def min_table(table: str, width: int = 16, parts: int = 16) -> Column:
    """The least entry of each portion of a table."""
    return F.transform(F.sequence(F.lit(0), F.lit(parts - 1)), lambda i: F.array_min(F.slice(F.col(table), i * width + 1, F.lit(width))))


def portion(table: str, high: Column, width: int = 16) -> Column:
    """The entries of a table that codes with that high part can address."""
    return F.slice(F.col(table), high * width + 1, F.lit(width))


def small_tables(tables: DataFrame, m: int, g: int, low_bits: int = 4, bins: int = 127, mode: str = "full") -> DataFrame:
    """Quantized tables for the bounds: whole for the first g parts, portion minima for the others
    (``quant_only``: whole for all)."""
    width, parts = 1 << low_bits, 1 << (8 - low_bits)
    out = quantize_tables(tables, m, bins)
    if mode == "full":
        out = out.withColumns({f"q{j}": min_table(f"q{j}", width, parts) for j in range(g, m)})
    return out


def lower_bound(m: int, g: int, low_bits: int = 4, top: int = 127, mode: str = "full") -> Column:
    index = [F.col(f"c{j}").cast("int") if j < g or mode == "quant_only" else F.shiftright(F.col(f"c{j}").cast("int"), low_bits) for j in range(m)]
    return F.least(total([F.col(f"q{j}")[i] for j, i in enumerate(index)]), F.lit(top).cast("long"))


def with_prefix(codes: DataFrame, share: float | None, count: int | None = None, r: int = 1, keys: tuple[str, ...] = ()) -> DataFrame:
    """Marks the prefix: the first ceil(share * n) codes of each list in id order (or ``count``), r at least.

    Only the id that closes each prefix is looked for, so the codes stay where they are: the
    mark is a comparison of ids, a filter that a scan of stored codes can push down.
    """
    limit = F.greatest(F.lit(r), F.lit(count) if count is not None else F.ceil(F.col("_total") * F.lit(share))).cast("long")
    ends = prefix_ends(codes, "vec_id", limit, keys)
    if not keys:
        end = ends.first()
        return codes.withColumn("prefix", F.lit(False) if end is None else F.col("vec_id") <= F.lit(end["_end"]))
    joined = codes.join(F.broadcast(ends), list(keys))  # a row for each list
    return joined.withColumn("prefix", F.col("vec_id") <= F.col("_end")).drop("_end")


def bounded_marks(placed: DataFrame, tables: DataFrame, m: int, r: int, g: int, keys: tuple[str, ...] = (), mode: str = "full", low_bits: int = 4, qmax: str = "prefix") -> DataFrame:
    """Every (query, code) with its bound and whether the bound prunes it."""
    bounded = with_bounds(tables, m)
    thr = prefix_thresholds(placed, tables, m, r, keys)
    small = small_tables(bounded.join(F.broadcast(thr), ["qid", *keys]), m, g, low_bits, mode=mode)
    if qmax == "sum_max":  # bins over the whole range, pruning still by the prefix's threshold
        wide = bounded.join(F.broadcast(sum_of_maxima(tables, m, keys)), ["qid", *keys])
        small = small_tables(wide, m, g, low_bits, mode=mode).withColumnRenamed("thr", "top").join(F.broadcast(thr), ["qid", *keys])
    else:
        small = small.withColumn("top", F.col("thr"))
    joined = with_tables(placed, small, keys).withColumn("lb", lower_bound(m, g, low_bits, mode=mode))
    far = (F.col("lb") * (F.col("top") - F.col("qmin")) >= (F.col("thr") - m * F.col("qmin")) * 127) & (F.col("top") > F.col("qmin"))
    return joined.withColumn("pruned", ~F.col("prefix") & far)


def bounded_topk(placed: DataFrame, tables: DataFrame, m: int, r: int, g: int, keys: tuple[str, ...] = (), **how) -> DataFrame:
    """Exactly the plain scan's rows; only codes whose bound is low are summed."""
    kept = bounded_marks(placed, tables, m, r, g, keys, **how).where("not pruned")
    return top_k(kept.select("qid", "vec_id", adc(m).alias("dist")), r, ["qid"], ["dist", "vec_id"])


def pruned_counts(marks: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """(qid, n_codes, n_pruned, n_full, pruned_pct)."""
    out = marks.groupBy("qid", *keys).agg(F.count("*").alias("n_codes"), F.count_if("pruned").alias("n_pruned"))
    return out.withColumn("n_full", F.col("n_codes") - F.col("n_pruned")).withColumn("pruned_pct", F.round(F.col("n_pruned") * 100.0 / F.col("n_codes"), 6))


def group_bounds(tables: DataFrame, m: int, g: int) -> DataFrame:
    """The least distance any code of a group can have: (qid, grp, least) for all 16^g groups."""
    out = tables.select("qid", F.posexplode(min_table("t0")).alias("grp", "least"), *table_columns(m))
    for j in range(1, g):
        out = out.select("qid", "grp", "least", F.posexplode(min_table(f"t{j}")).alias("_i", "_v"), *table_columns(m))
        out = out.withColumn("grp", F.col("grp") * 16 + F.col("_i")).withColumn("least", F.col("least") + F.col("_v")).drop("_i", "_v")
    rest = total([F.array_min(f"t{j}") for j in range(g, m)]) if g < m else F.lit(0)
    return out.select("qid", F.col("grp").cast("long").alias("grp"), (F.col("least") + rest).alias("least"))


def bounded_kernel(codes: DataFrame, table_rows: list, thresholds: dict, m: int, r: int, g: int) -> DataFrame:
    """Kernel with a running threshold: each task starts from the prefix's threshold and lowers
    it as it finds nearer codes. Unsaturated bounds and a strict comparison keep ties exact."""
    names = code_columns(m)

    def make():
        states = []
        for q, _, t in table_rows:
            t = np.asarray(t)
            qmin, thr = int(t.min()), int(thresholds[q])
            width = thr - qmin
            small = np.minimum((t - qmin) * 127 // width, 127) if width > 0 else np.zeros_like(t)
            small = [small[j] if j < g else small[j].reshape(16, -1).min(axis=1) for j in range(m)]
            states.append([q, t, small, qmin, width, thr])

        def each(batch):
            ids = batch["vec_id"].to_numpy(zero_copy_only=False)
            c = np.stack([batch[n].to_numpy(zero_copy_only=False) for n in names]).astype(np.int64)
            out = {"qid": [], "vec_id": [], "dist": []}
            for state in states:
                q, t, small, qmin, width, thr = state
                bound = sum(s[c[j] if j < g else c[j] >> 4] for j, s in enumerate(small))
                near = np.flatnonzero(bound * width <= 127 * (thr - m * qmin)) if width > 0 else np.arange(len(ids))
                d = sum(t[j][c[j, near]] for j in range(m))
                kept = least_rows(d, ids[near], r)
                if len(kept) == r:
                    state[5] = min(thr, int(d[kept].max()))
                out["qid"].append(np.full(len(kept), q))
                out["vec_id"].append(ids[near][kept])
                out["dist"].append(d[kept])
            return joined(out)

        return each

    return top_k(map_batches(codes.select("vec_id", *names), make, "qid long, vec_id long, dist long"), r, ["qid"], ["dist", "vec_id"])


# -- nibble scan -------------------------------------------------------------------------------


def nibble_tables(placed: DataFrame, tables: DataFrame, m: int, r: int, keys: tuple[str, ...] = (), bins: int = 127) -> DataFrame:
    """Quantized tables (q0 ..) with qmin and thr from the prefix's codes."""
    thr = prefix_thresholds(placed, tables, m, r, keys)
    return quantize_tables(with_bounds(tables, m).join(F.broadcast(thr), ["qid", *keys]), m, bins)


def nibble_topk(codes: DataFrame, small: DataFrame, m: int, r: int, keys: tuple[str, ...] = (), top: int = 127) -> DataFrame:
    """Neighbours by the saturated integer sum; ``approx`` maps it back to a distance."""
    acc = F.least(total([F.col(f"q{j}")[F.col(f"c{j}").cast("int")] for j in range(m)]), F.lit(top).cast("long"))
    scored = with_tables(codes, small.select("qid", *keys, "qmin", "thr", *[f"q{j}" for j in range(m)]), keys).select("qid", "vec_id", acc.alias("dist"), "qmin", "thr")
    out = top_k(scored, r, ["qid"], ["dist", "vec_id"])
    return out.withColumn("approx", F.col("qmin") * m + F.col("dist") * (F.col("thr") - F.col("qmin")) / F.lit(float(top)))


def nibble_kernel(codes: DataFrame, small_rows: list, m: int, r: int, rows_per_step: int = 1) -> DataFrame:
    """uint8 kernel; ``rows_per_step`` = 2 adds two components a step (the double-width form)."""
    names = code_columns(m)

    def make():
        tables = [(q, np.asarray(t, np.uint8)) for q, t in small_rows]

        def each(batch):
            ids = batch["vec_id"].to_numpy(zero_copy_only=False)
            c = np.stack([batch[n].to_numpy(zero_copy_only=False) for n in names]).astype(np.int64)
            out = {"qid": [], "vec_id": [], "dist": []}
            for q, t in tables:
                acc = np.zeros(len(ids), np.uint16)
                for j in range(0, m, rows_per_step):
                    acc += t[j].take(c[j])
                    if rows_per_step == 2 and j + 1 < m:
                        acc += t[j + 1].take(c[j + 1])
                d = np.minimum(acc, 127).astype(np.int64)
                kept = least_rows(d, ids, r)
                out["qid"].append(np.full(len(kept), q))
                out["vec_id"].append(ids[kept])
                out["dist"].append(d[kept])
            return joined(out)

        return each

    return top_k(map_batches(codes.select("vec_id", *names), make, "qid long, vec_id long, dist long"), r, ["qid"], ["dist", "vec_id"])


# -- nested codebooks --------------------------------------------------------------------------


def low_bits_codes(codes: DataFrame, m: int, b_coarse: int) -> DataFrame:
    return codes.withColumns({f"c{j}": F.col(f"c{j}").bitwiseAND((1 << b_coarse) - 1) for j in range(m)})


def first_pass(codes: DataFrame, coarse_tables: DataFrame, m: int, b_coarse: int, r2: int) -> DataFrame:
    """Every code's bucket (qid, vec_id, bucket), buckets 0..255 only.

    Entries are quantized to 0..254 (overflow 255) between the least entry and the greatest
    coarse distance among the first r2 codes.
    """
    low = with_prefix(low_bits_codes(codes, m, b_coarse), None, r2, 1)
    scored = with_tables(low.where("prefix"), coarse_tables).select("qid", adc(m).alias("dist"))
    thr = scored.groupBy("qid").agg(F.max("dist").alias("thr"))
    small = quantize_tables(with_bounds(coarse_tables, m).join(F.broadcast(thr), "qid"), m, 255)
    bucket = total([F.col(f"q{j}")[F.col(f"c{j}").cast("int")] for j in range(m)])
    return with_tables(low.select("vec_id", *code_columns(m)), small).select("qid", "vec_id", bucket.alias("bucket")).where("bucket <= 255")


def capped_buckets(buckets: DataFrame, r2: int) -> DataFrame:
    """(qid, cutoff): the first bucket at which r2 codes are reached; histograms, no sort of codes."""
    counts = buckets.groupBy("qid", "bucket").agg(F.count("*").alias("n"))
    w = W.partitionBy("qid").orderBy("bucket")
    running = counts.withColumn("upto", F.sum("n").over(w))
    reached = running.where(F.col("upto") >= r2).groupBy("qid").agg(F.min("bucket").alias("cutoff"))
    last = counts.groupBy("qid").agg(F.max("bucket").alias("last"))
    return last.join(reached, "qid", "left").select("qid", F.coalesce("cutoff", "last").alias("cutoff"))


def candidates(buckets: DataFrame, r2: int) -> DataFrame:
    """Whole buckets up to the cutoff."""
    return buckets.join(F.broadcast(capped_buckets(buckets, r2)), "qid").where("bucket <= cutoff").select("qid", "vec_id", "bucket")


def capped_kernel(codes: DataFrame, small_rows: list, m: int, b_coarse: int, r2: int) -> DataFrame:
    """Kernel form: each batch keeps whole buckets up to its own cutoff, a superset that the
    second stage cuts again."""
    names = code_columns(m)

    def make():
        tables = [(q, np.asarray(t, np.int64)) for q, t in small_rows]

        def each(batch):
            ids = batch["vec_id"].to_numpy(zero_copy_only=False)
            c = np.stack([batch[n].to_numpy(zero_copy_only=False) for n in names]).astype(np.int64) & ((1 << b_coarse) - 1)
            out = {"qid": [], "vec_id": [], "bucket": []}
            for q, t in tables:
                acc = sum(t[j].take(c[j]) for j in range(m))
                upto = np.cumsum(np.bincount(np.minimum(acc, 256), minlength=257)[:256])
                cut = int(np.searchsorted(upto, r2)) if len(upto) and upto[-1] >= r2 else 255
                kept = np.flatnonzero(acc <= min(cut, 255))
                out["qid"].append(np.full(len(kept), q))
                out["vec_id"].append(ids[kept])
                out["bucket"].append(acc[kept])
            return joined(out)

        return each

    return candidates(map_batches(codes.select("vec_id", *names), make, "qid long, vec_id long, bucket long"), r2)


def lazy_entries(found: DataFrame, codes: DataFrame, m: int) -> DataFrame:
    """Distinct fine-table entries that candidates touch: (qid, part, idx)."""
    parts = F.explode(F.array(*[F.struct(F.lit(j).cast("long").alias("part"), F.col(f"c{j}").cast("long").alias("idx")) for j in range(m)]))
    return found.select("qid", "vec_id").join(codes, "vec_id").select("qid", parts.alias("x")).select("qid", "x.part", "x.idx").distinct()


def rerank(found: DataFrame, codes: DataFrame, queries: DataFrame, model: PQModel, r: int, tables: str = "lazy") -> DataFrame:
    """Fine distances of the candidates. ``lazy``: a kernel computes just the entries that the
    candidates' codes name; ``eager``: whole fine tables are made first."""
    m = model.m
    held = found.select("qid", "vec_id").join(codes, "vec_id")
    if tables == "eager":
        scored = held.join(F.broadcast(lookup_tables(queries, model)), "qid").select("qid", "vec_id", adc(m).alias("dist"))
        return top_k(scored, r, ["qid"], ["dist", "vec_id"])

    def make():
        def each(batch):
            from vecspark.plans.kernels import matrix

            x = np.stack(model.parts(matrix(batch)), axis=1)
            c = np.stack([batch[n].to_numpy(zero_copy_only=False) for n in code_columns(m)], axis=1)
            y = model.books[np.arange(m), c]
            return {"qid": batch["qid"], "vec_id": batch["vec_id"], "dist": ((x - y) ** 2).sum(axis=(1, 2))}

        return each

    scored = map_batches(held.join(F.broadcast(queries), "qid").select("qid", "vec_id", "e", *code_columns(m)), make, f"qid long, vec_id long, dist {model.number}")
    return top_k(scored, r, ["qid"], ["dist", "vec_id"])
