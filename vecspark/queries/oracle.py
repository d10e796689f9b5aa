"""Oracle SQL for DuckDB, composed of common table expressions; long integers throughout.

Training is written out (stride start, a few Lloyd steps), so the oracle needs nothing
from the Spark side.
"""

from __future__ import annotations

SCALE = 4096


class Sql:
    def __init__(self):
        self.parts: list[str] = []

    def add(self, name: str, body: str, once: bool = False) -> Sql:
        """``once``: read by one reader alone, so that nothing need be kept."""
        self.parts.append(f"{name} AS {'NOT ' if once else ''}MATERIALIZED ({body})")
        return self

    def select(self, body: str) -> str:
        return "WITH " + ",\n".join(self.parts) + "\n" + body


def v0(rotated: bool = False) -> Sql:
    s = Sql()
    s.add("v0", f"SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * {SCALE}) AS BIGINT)) AS e FROM embeddings")
    if rotated:
        from vecspark.operators.projection import FIXED, fixed_rotation

        s.add("turn", f"SELECT CAST({fixed_rotation(64, 5)} AS BIGINT[][]) AS r")
        s.add("v", f"SELECT vec_id, list_transform(r, lambda row: CAST(floor(CAST(list_sum(list_transform(list_zip(row, e), lambda z: z[1] * z[2])) AS DOUBLE) / {FIXED}) AS BIGINT)) AS e FROM v0, turn")
    else:
        s.add("v", "SELECT * FROM v0")
    s.add("base", "SELECT * FROM v")
    return s.add("queries", "SELECT vec_id AS qid, e FROM v WHERE vec_id % 50 = 0")


def v1() -> Sql:
    names = ["quantity", "extendedprice", "discount", "tax", "ship", "partkey", "suppkey", "linenumber"]
    s = Sql()
    s.add(
        "items",
        """SELECT l_orderkey * 8 + l_linenumber AS vec_id, CAST(floor(l_quantity * 100 + 0.5) AS BIGINT) AS quantity, CAST(floor(l_extendedprice * 100 + 0.5) AS BIGINT) AS extendedprice,
        CAST(floor(l_discount * 10000 + 0.5) AS BIGINT) AS discount, CAST(floor(l_tax * 10000 + 0.5) AS BIGINT) AS tax, date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) AS ship,
        l_partkey AS partkey, l_suppkey AS suppkey, CAST(l_linenumber AS BIGINT) AS linenumber FROM lineitem""",
    )
    means = ", ".join(f"min({n}) AS {n}" if n == "linenumber" else f"CAST(floor(CAST(sum({n}) AS DOUBLE) / count(*)) AS BIGINT) AS {n}" for n in names)
    s.add("means", f"SELECT CAST(vec_id AS BIGINT) AS vec_id, {means} FROM items GROUP BY vec_id")
    s.add("ends", "SELECT " + ", ".join(f"min({n}) AS {n}_low, max({n}) AS {n}_high" for n in names) + " FROM means")
    scaled = ", ".join(f"CAST(floor(CAST(({n} - {n}_low) * {SCALE} AS DOUBLE) / greatest({n}_high - {n}_low, 1)) AS BIGINT)" for n in names)
    s.add("v", f"SELECT vec_id, [{scaled}] AS e FROM means, ends")
    s.add("base", "SELECT * FROM v")
    return s.add("queries", "SELECT vec_id AS qid, e FROM v WHERE vec_id % 50 = 0")


def v2(d: int = 128, source: str = "SELECT doc_id AS vec_id, text FROM documents", keys: str = "vec_id") -> Sql:
    s = Sql().add("texts", f"SELECT * FROM ({source}) WHERE length(text) > 0")
    s.add("grams", f"SELECT {keys}, substr(text, CAST(i AS BIGINT), 3) AS gram, count(*) AS n FROM (SELECT *, unnest(range(1, greatest(length(text) - 2, 1) + 1)) AS i FROM texts) GROUP BY {keys}, gram")
    s.add("counts", f"SELECT {keys}, CAST(('0x' || substr(md5(gram), 1, 8)) AS BIGINT) % {d} AS b, CAST(sum(n) AS BIGINT) AS n FROM grams GROUP BY {keys}, b")
    s.add("norms", f"SELECT {keys}, CAST(floor(sqrt(CAST(sum(n * n) AS DOUBLE))) AS BIGINT) AS norm FROM counts GROUP BY {keys}")
    s.add("v", f"SELECT {keys}, list(CAST(floor(CAST(coalesce(n, 0) * {SCALE} AS DOUBLE) / greatest(norm, 1)) AS BIGINT) ORDER BY b) AS e FROM norms CROSS JOIN (SELECT unnest(range(0, {d})) AS b) LEFT JOIN counts USING ({keys}, b) GROUP BY {keys}")
    return s


def pq(s: Sql, p: str, src: str, d: int, m: int, k: int, iters: int) -> Sql:
    """{p}_sub and the codebook {p}_cb(part, idx, dim, c) trained on src(vec_id, e)."""
    components(s, f"{p}_sub", src, d, m)
    s.add(f"{p}_rank", f"SELECT vec_id, row_number() OVER (ORDER BY vec_id) - 1 AS rk, count(*) OVER () AS n FROM {src}")
    s.add(f"{p}_c0", f"SELECT u.part, CAST(i.idx AS BIGINT) AS idx, u.dim, u.x AS c FROM (SELECT unnest(range(0, {k})) AS idx) i JOIN {p}_rank r ON r.rk = (i.idx * r.n) // {k} JOIN {p}_sub u USING (vec_id)")
    for t in range(iters):
        nearest(s, f"{p}_a{t}", f"{p}_sub", f"{p}_c{t}")
        s.add(
            f"{p}_c{t + 1}",
            f"SELECT o.part, o.idx, o.dim, coalesce(u.c, o.c) AS c FROM {p}_c{t} o LEFT JOIN (SELECT a.part, a.idx, x.dim, CAST(floor(CAST(sum(x.x) AS DOUBLE) / count(*)) AS BIGINT) AS c FROM {p}_a{t} a JOIN {p}_sub x USING (vec_id, part) GROUP BY ALL) u USING (part, idx, dim)",
        )
    return s.add(f"{p}_cb", f"SELECT * FROM {p}_c{iters}")


def components(s: Sql, name: str, src: str, d: int, m: int, key: str = "vec_id") -> Sql:
    w = d // m
    return s.add(name, f"SELECT {key}, i // {w} AS part, i % {w} AS dim, x FROM (SELECT {key}, unnest(range(0, {d})) AS i, unnest(e) AS x FROM {src})")


def nearest(s: Sql, name: str, sub: str, cb: str, key: str = "vec_id") -> Sql:
    """name(key, part, idx): the nearest centroid, least index on ties."""
    return s.add(
        name,
        f"SELECT {key}, part, min(d * 65536 + idx) % 65536 AS idx FROM (SELECT x.{key}, x.part, c.idx, CAST(sum((x.x - c.c) * (x.x - c.c)) AS BIGINT) AS d FROM {sub} x JOIN {cb} c ON x.part = c.part AND x.dim = c.dim GROUP BY ALL) GROUP BY ALL",
    )


def encode(s: Sql, name: str, p: str, src: str, d: int, m: int) -> Sql:
    """name(vec_id, c list) under codebook {p}_cb."""
    components(s, f"{name}_sub", src, d, m)
    nearest(s, f"{name}_near", f"{name}_sub", f"{p}_cb")
    return s.add(name, f"SELECT vec_id, list(idx ORDER BY part) AS c FROM {name}_near GROUP BY vec_id")


def tables(s: Sql, name: str, p: str, src: str, d: int, m: int, keys: str = "qid") -> Sql:
    """name(keys, tt list of lists): squared distances to all centroids of {p}_cb."""
    w = d // m
    s.add(f"{name}_long", f"SELECT {keys}, x.part, c.idx, CAST(sum((x.x - c.c) * (x.x - c.c)) AS BIGINT) AS dist FROM (SELECT {keys}, i // {w} AS part, i % {w} AS dim, x FROM (SELECT {keys}, unnest(range(0, {d})) AS i, unnest(e) AS x FROM {src})) x JOIN {p}_cb c ON x.part = c.part AND x.dim = c.dim GROUP BY ALL")
    return s.add(name, f"SELECT {keys}, list(t ORDER BY part) AS tt FROM (SELECT {keys}, part, list(dist ORDER BY idx) AS t FROM {name}_long GROUP BY {keys}, part) GROUP BY {keys}")


def adc(m: int, t: str = "t.tt", c: str = "c.c") -> str:
    return "(" + " + ".join(f"{t}[{j + 1}][{c}[{j + 1}] + 1]" for j in range(m)) + ")"


def topk(source: str, r: int, extra: str = "") -> str:
    """Rows (qid, rk, vec_id, dist) of the r least by (dist, vec_id)."""
    return f"SELECT qid, rk, vec_id, dist{extra} FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, vec_id) AS rk FROM ({source})) WHERE rk <= {r}"


def centroid_lists(s: Sql, name: str, p: str) -> Sql:
    """name(idx, e): the one-part codebook {p}_cb as vectors."""
    return s.add(name, f"SELECT idx, list(c ORDER BY part, dim) AS e FROM {p}_cb GROUP BY idx")


def l2(a: str, b: str) -> str:
    return f"CAST(list_sum(list_transform(list_zip({a}, {b}), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS BIGINT)"


def minus(a: str, b: str) -> str:
    return f"list_transform(list_zip({a}, {b}), lambda z: z[1] - z[2])"


def ivf(s: Sql, d: int, k: int, m: int, kk: int, iters: int = 3, residual: bool = True, src: str = "base", train: str | None = None) -> Sql:
    """co_cb coarse; codes(vec_id, list_id, c) of residuals; cents(idx, e)."""
    pq(s, "co", train or src, d, 1, k, iters)
    centroid_lists(s, "cents", "co")

    def own(name: str, of: str) -> None:
        components(s, f"{name}_all", of, d, 1)
        nearest(s, f"{name}_list", f"{name}_all", "co_cb")
        s.add(name, f"SELECT v.vec_id, l.idx AS list_id, {minus('v.e', 'c.e') if residual else 'v.e'} AS e FROM {of} v JOIN {name}_list l USING (vec_id) JOIN cents c ON c.idx = l.idx")

    own("own", src)
    if train:
        own("own_train", train)
    pq(s, "fi", "own_train" if train else "own", d, m, kk, iters)
    encode(s, "own_codes", "fi", "own", d, m)
    return s.add("codes", "SELECT vec_id, list_id, c FROM own_codes JOIN own USING (vec_id)")


def probes(s: Sql, ma: int, name: str = "probes") -> Sql:
    s.add(f"{name}_all", f"SELECT q.qid, c.idx AS list_id, {l2('q.e', 'c.e')} AS dist, {minus('q.e', 'c.e')} AS e, q.e AS whole FROM queries q, cents c")
    return s.add(name, f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, list_id) AS rk FROM {name}_all) WHERE rk <= {ma}")
