"""Chat formatting with Spark expressions only.

A conversation becomes one string. Template::

    <s>[role]first text[+]second text</s><s>[role]...</s>

Turns are sorted by (turn, role, text); adjacent turns of one role share a block
and are set apart by ``[+]``. The control strings all hold ``<`` or ``[``; inside
roles and texts ``&``, ``<``, ``[`` and ``]`` are written as character references,
so no text can open, close or split a block, and reading back is exact.

Defined cases: null text is empty text; null role is the empty role; null turn
sorts first; a null conv_id is a conversation of its own; repeated rows stay
repeated; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# What is escaped, in the order of escaping.
ESCAPES = (("&", "&amp;"), ("<", "&lt;"), ("[", "&#91;"), ("]", "&#93;"))
OPEN, CLOSE, JOIN = "<s>", "</s>", "[+]"


def escape(text: Column) -> Column:
    for raw, safe in ESCAPES:
        text = F.replace(text, F.lit(raw), F.lit(safe))
    return text


def unescape(text: Column) -> Column:
    for raw, safe in reversed(ESCAPES):
        text = F.replace(text, F.lit(safe), F.lit(raw))
    return text


def format_conversations(turns: DataFrame) -> DataFrame:
    """(conv_id, turn, role, text) -> (conv_id, formatted).

    One grouped aggregation collects a conversation's turn structs; everything else
    is an expression over that array, so there is one shuffle of the turns.
    """
    turn = F.struct(
        F.col("turn").cast("long").alias("turn"),
        F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"),
        F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
    )
    grouped = turns.select(F.col("conv_id").cast("long").alias("conv_id"), turn.alias("t")).groupBy("conv_id").agg(F.array_sort(F.collect_list("t")).alias("turns"))
    safe = F.transform("turns", lambda t: F.struct(escape(t["role"]).alias("role"), escape(t["text"]).alias("text")))

    # A turn that follows one of its own role continues that block, any other opens a new one.
    def written(turns: Column) -> Column:
        return F.transform(
            turns,
            lambda t, i: F.concat(
                F.when(i == 0, F.concat(F.lit(f"{OPEN}["), t["role"], F.lit("]")))
                .when(F.get(turns, i - 1)["role"] == t["role"], F.lit(JOIN))
                .otherwise(F.concat(F.lit(f"{CLOSE}{OPEN}["), t["role"], F.lit("]"))),
                t["text"],
            ),
        )

    return grouped.select("conv_id", F.concat(F.array_join(let(safe, written), ""), F.lit(CLOSE)).alias("formatted"))


def let(value: Column, body) -> Column:
    """``body`` of a value computed once, however often the lambda's own lambdas name it."""
    return F.get(F.transform(F.array(value), body), 0)


CHUNK = 256


def starts(lengths: Column) -> Column:
    """Sums of the elements before each one. Sums of chunks first, then within the chunk, as an array
    that grows by one element a step would be copied at each."""
    chunks = F.transform(
        F.sequence(F.lit(0), F.greatest(F.ceil(F.size(lengths) / CHUNK).cast("int") - 1, F.lit(0))),
        lambda c: F.aggregate(F.slice(lengths, c * CHUNK + 1, F.lit(CHUNK)), F.lit(0).cast("long"), lambda s, x: s + x),
    )
    offsets = F.aggregate(
        chunks,
        F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<bigint>").alias("out")),
        lambda s, x: F.struct((s["at"] + x).alias("at"), F.concat(s["out"], F.array(s["at"])).alias("out")),
    )["out"]
    return let(
        offsets,
        lambda firsts: F.transform(
            lengths,
            lambda _, i: F.aggregate(F.slice(lengths, i - i % CHUNK + 1, i % CHUNK), F.get(firsts, F.floor(i / CHUNK).cast("int")), lambda s, x: s + x),
        ),
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """(conv_id, formatted) -> (conv_id, formatted, turns array<struct<role, text, start, length, byte, bytes>>).

    ``start`` (from 0) and ``length`` place a turn's escaped text within the string, ``byte`` and
    ``bytes`` within its UTF-8 form. Work grows in proportion to the string.
    """
    blocks = F.split(F.expr(f"substring(formatted, {len(OPEN) + 1}, length(formatted) - {len(OPEN) + len(CLOSE)})"), f"{CLOSE}{OPEN}", -1)

    # role] ... [+] ... : the role ends at the first bracket, which no escaped role or text holds.
    # Each text knows what stands before it (``lead``) since the text before, in characters and bytes.
    def pieces(b: Column, at: Column) -> Column:
        role = F.substring_index(F.substring(b, 2, 1 << 30), "]", 1)
        head = F.when(at == 0, F.lit(len(OPEN) + 2)).otherwise(F.lit(len(CLOSE) + len(OPEN) + 2))
        texts = F.split(F.substr(b, F.length(role) + 3), r"\[\+\]", -1)
        return let(
            F.struct(role.alias("role"), head.alias("head")),
            lambda h: F.transform(
                texts,
                lambda t, i: F.struct(
                    h["role"].alias("role"),
                    t.alias("text"),
                    F.when(i == 0, h["head"] + F.length(h["role"])).otherwise(F.lit(len(JOIN))).cast("long").alias("lead"),
                    F.when(i == 0, h["head"] + F.octet_length(h["role"])).otherwise(F.lit(len(JOIN))).cast("long").alias("lead_bytes"),
                    F.length(t).cast("long").alias("length"),
                    F.octet_length(t).cast("long").alias("bytes"),
                ),
            ),
        )

    def placed(p: Column) -> Column:
        def position(width: str, lead: str) -> Column:
            return let(F.transform(p, lambda x: x[lead] + x[width]), starts)

        return let(
            F.struct(position("length", "lead").alias("start"), position("bytes", "lead_bytes").alias("byte")),
            lambda at: F.transform(
                p,
                lambda x, i: F.struct(
                    unescape(x["role"]).alias("role"),
                    unescape(x["text"]).alias("text"),
                    (F.get(at["start"], i) + x["lead"]).alias("start"),
                    x["length"].alias("length"),
                    (F.get(at["byte"], i) + x["lead_bytes"]).alias("byte"),
                    x["bytes"].alias("bytes"),
                ),
            ),
        )

    return formatted.select("conv_id", "formatted", let(F.flatten(F.transform(blocks, pieces)), placed).alias("turns"))


def loss_mask(parsed: DataFrame, roles: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """Adds ``mask``: array of (start, length, byte, bytes) spans of the formatted string that carry loss."""
    mine = F.filter("turns", lambda t: t["role"].isin(*roles))
    return parsed.withColumn("mask", F.transform(mine, lambda t: F.struct(*[t[c].alias(c) for c in ("start", "length", "byte", "bytes")])))


def digest(masked: DataFrame) -> DataFrame:
    """What the formatted strings say when read back, as counts and digests."""
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    # Spans are cut by bytes: to find a character's place, a string is walked from its start.
    lost = let(
        F.col("formatted").cast("binary"),
        lambda whole: F.array_join(F.transform("mask", lambda m: unescape(F.substr(whole, (m["byte"] + 1).cast("int"), m["bytes"].cast("int")).cast("string"))), ""),
    )
    return masked.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said.cast("binary"), 256).alias("turns_sha256"),
        lost.alias("lost"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    ).select("conv_id", "n_turns", "turns_sha256", F.length("lost").cast("long").alias("loss_chars"), F.sha2(F.col("lost").cast("binary"), 256).alias("loss_sha256"), "formatted_chars")
