"""Cost models over the given vectors: look-ups and adds of their codes, small-table plans, bytes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# kind -> (index reads, table reads, adds) for m parts, as SQL over m.
SCAN_COSTS = {
    "plain": ("m", "m", "m"),
    "packed": ("1", "m", "m"),
    "gather": ("1", "m", "m"),
    "additive": ("m", "m + m * (m - 1) / 2", "m + m * (m - 1) / 2"),
    "additive_as_printed": ("m", "m + m * m / 2", "m + m * m / 2"),
    "tree": ("m", "m + m - 1", "m + m - 1"),
    "tree_as_printed": ("m", "2 * m", "2 * m"),
    "composite": ("m", "m", "m"),
    "nibble": ("m / 2", "m", "m"),
}


# (vec_id, d, parts m): the vectors that a scan with m parts can take, whose dimension m divides.
SCANNED = "SELECT len(embedding) AS d, m FROM embeddings, (SELECT CAST(unnest([{ms}]) AS BIGINT) AS m) WHERE len(embedding) % m = 0"


def scanned(vectors: DataFrame, ms: list[int]) -> DataFrame:
    """(d, m) of each vector and number of parts that divides its dimension."""
    rows = vectors.select(F.size("embedding").cast("long").alias("d"), F.explode(F.array(*[F.lit(m).cast("long") for m in ms])).alias("m"))
    return rows.where("d % m = 0")


def lookup_cost_sql() -> str:
    rows = " UNION ALL ".join(f"SELECT '{k}' AS kind, m, CAST(sum({i.replace('/', '//')}) AS BIGINT) AS index_reads, CAST(sum({t.replace('/', '//')}) AS BIGINT) AS table_reads, CAST(sum({a.replace('/', '//')}) AS BIGINT) AS adds FROM ms GROUP BY m" for k, (i, t, a) in SCAN_COSTS.items())
    return f"WITH ms AS MATERIALIZED ({SCANNED.format(ms='4, 8, 16, 32')}) {rows}"


def lookup_cost(vectors: DataFrame) -> DataFrame:
    """Reads and adds of a scan of all vectors' codes, by number of parts and kind."""
    each = F.explode(F.array(*[F.struct(F.lit(kind).alias("kind"), *[F.expr(f"cast({x.replace('/', 'div')} as bigint)").alias(n) for x, n in ((i, "index_reads"), (t, "table_reads"), (a, "adds"))]) for kind, (i, t, a) in SCAN_COSTS.items()]))
    rows = scanned(vectors, [4, 8, 16, 32]).select("m", each.alias("x")).select("m", "x.*")
    return rows.groupBy("kind", "m").agg(*[F.sum(n).alias(n) for n in ("index_reads", "table_reads", "adds")])


def bounded_cost(m: int, pruned: float, small_reads: float = 1.0) -> float:
    """Memory reads for a code: one word of small look-ups, and the plain reads of the codes kept."""
    return small_reads + (1 - pruned) * (1 + m)


def small_table_sql() -> str:
    return (
        f"WITH ms AS MATERIALIZED ({SCANNED.format(ms='8')}) "
        "SELECT kind, CAST(g AS BIGINT) AS g, count(*) AS vectors, CAST(sum(CASE kind WHEN 'product' THEN g WHEN 'additive' THEN g + g * g // 2 ELSE 2 * g END) AS BIGINT) AS grouped, "
        "CAST(sum(CASE kind WHEN 'product' THEN m - g WHEN 'additive' THEN m + m * m // 2 - g - g * g // 2 ELSE 2 * m - 2 * g END) AS BIGINT) AS minima "
        "FROM ms, (SELECT unnest(['product', 'additive', 'tree']) AS kind), (SELECT unnest(range(1, 5)) AS g) GROUP BY kind, g"
    )


def small_table_plan(vectors: DataFrame, m: int = 8) -> DataFrame:
    """Look-ups of all vectors' codes in tables whose portions groups share and in tables cut to minima, for each kind."""
    kinds = [("product", "{0}"), ("additive", "{0} + {0} * {0} div 2"), ("tree", "2 * {0}")]
    rows = [F.struct(F.lit(kind).alias("kind"), F.lit(g).cast("long").alias("g"), F.expr(f"cast({x.format(g)} as bigint)").alias("grouped"), F.expr(f"cast(({x.format('m')}) - ({x.format(g)}) as bigint)").alias("minima")) for kind, x in kinds for g in range(1, 5)]
    each = scanned(vectors, [m]).select(F.explode(F.array(*rows)).alias("x")).select("x.*")
    return each.groupBy("kind", "g").agg(F.count("*").alias("vectors"), F.sum("grouped").alias("grouped"), F.sum("minima").alias("minima"))


MEMORY = ((2, 16), (4, 8), (4, 16), (8, 8), (16, 4), (8, 16), (16, 8), (32, 4))


def memory_sql() -> str:
    rows = ", ".join(f"({m}, {b})" for m, b in MEMORY)
    return (
        f"SELECT CAST(m AS BIGINT) AS m, CAST(b AS BIGINT) AS b, CAST(sum(m * b // 8) AS BIGINT) AS code_bytes, CAST(4 * m * 2 ** b AS BIGINT) AS table_bytes, CAST(sum(4 * len(embedding)) // sum(m * b // 8) AS BIGINT) AS compression "
        f"FROM embeddings, (VALUES {rows}) t(m, b) WHERE len(embedding) % m = 0 GROUP BY m, b"
    )


def memory_model(vectors: DataFrame) -> DataFrame:
    """Bytes of all vectors' codes, of a query's tables, and how often the codes fit into the vectors' bytes."""
    kinds = F.explode(F.array(*[F.struct(F.lit(m).cast("long").alias("m"), F.lit(b).cast("long").alias("b")) for m, b in MEMORY]))
    each = vectors.select(F.size("embedding").cast("long").alias("d"), kinds.alias("x")).select("d", "x.*").where("d % m = 0")
    sized = each.groupBy("m", "b").agg(F.sum(F.expr("m * b div 8")).alias("code_bytes"), F.sum(F.col("d") * 4).alias("whole"))
    return sized.select("m", "b", "code_bytes", F.expr("cast(4 * m * power(2, b) as bigint)").alias("table_bytes"), F.expr("whole div code_bytes").alias("compression"))


def group_memory_sql() -> str:
    return (
        "WITH n AS (SELECT count(embedding) AS n FROM embeddings WHERE len(embedding) % 8 = 0) "
        "SELECT CAST(portions AS BIGINT) AS portions, CAST(g AS BIGINT) AS g, CAST(50 * portions ** g AS BIGINT) AS n_min, CAST(n * (8 * 8 - g * (8 - log2(256 / portions))) AS BIGINT) AS bits, CAST(n * 64 AS BIGINT) AS plain_bits "
        "FROM n, (SELECT unnest([4, 16]) AS portions), (SELECT unnest(range(1, 6)) AS g)"
    )


def group_memory(vectors: DataFrame) -> DataFrame:
    """Least list for each number of grouped parts, and bits of all vectors' 64-bit codes with and without it."""
    kinds = F.explode(F.array(*[F.struct(F.lit(p).cast("long").alias("portions"), F.lit(g).cast("long").alias("g")) for p in (4, 16) for g in range(1, 6)]))
    each = scanned(vectors, [8]).select(kinds.alias("x")).select("x.*")
    bits = (64 - F.col("g") * (8 - F.log2(256 / F.col("portions")))).cast("long")
    return each.groupBy("portions", "g").agg((50 * F.pow(F.first("portions"), F.first("g"))).cast("long").alias("n_min"), F.sum(bits).alias("bits"), F.sum(F.lit(64).cast("long")).alias("plain_bits"))


def two_codes_sql() -> str:
    return "SELECT kind, CAST(sum(len(embedding) // 16 * width) AS BIGINT) AS bytes FROM embeddings, (VALUES ('two codes', 3), ('nested', 2)) t(kind, width) GROUP BY kind"


def two_codes(vectors: DataFrame) -> DataFrame:
    """Bytes of all vectors' codes, a part for 16 dimensions: 16 bits with separate 8, and nested (the low bits)."""
    kinds = F.explode(F.array(*[F.struct(F.lit(k).alias("kind"), F.lit(w).cast("long").alias("width")) for k, w in (("two codes", 3), ("nested", 2))]))
    return vectors.select(F.size("embedding").cast("long").alias("d"), kinds.alias("x")).groupBy("x.kind").agg(F.sum(F.expr("d div 16 * x.width")).alias("bytes"))
