"""Language of web pages by Bayesian fusion of four kinds of evidence.

* text: hashed byte trigrams under a model of each language, tempered so that long
  texts do not count every trigram as independent;
* declared: the primary subtag of the markup's ``lang`` attribute;
* address: last label of the host with a language-like first path segment;
* host: shares of languages among the host's other pages, smoothed towards those of
  its domain, and these towards all pages.

How far declarations and addresses can be trusted, and the host shares, come from
grouped aggregation of the text posteriors over all pages. A page's own posterior is
taken out of its host's counts before they judge it.

Defined cases: null html is empty, null or malformed urls have the empty host; pages
without any evidence get the overall shares; repeated rows are pages of their own; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import html as entities
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.llm.common import Scratch, arrow_rows, bounded_sample, slices

BUCKETS = 1 << 16
NAME = re.compile(r"<(script|style)\b", re.I)
ENDS = {"script": re.compile(r"</script\s*>", re.I), "style": re.compile(r"</style\s*>", re.I)}
TAG = re.compile(r"<(html|meta)\b([^<>]*)>", re.I)
ATTRIBUTE = re.compile(r"([\w:-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>\"']+))")
SUBTAG = re.compile(r"\s*([A-Za-z]{2,8})(?![A-Za-z0-9])")
HOT = 200  # keys joined apart because each may hold 1/200 of the rows or more
SMALL = 100_000  # rows of a table that may be broadcast


def strip(page: str) -> str:
    """A page's text: comments, scripts, styles and tags become spaces. What is never closed is looked
    for once, so work grows in proportion to the page."""
    out, at, missing = [], 0, set()
    while (start := page.find("<", at)) >= 0:
        out.append(page[at:start])
        stop = -1
        if page.startswith("<!--", start) and "--" not in missing:
            stop = page.find("-->", start + 4) + 3
            if stop < 3:
                missing.add("--")
                stop = -1
        elif (name := NAME.match(page, start)) and (kind := name[1].lower()) not in missing:
            end = ENDS[kind].search(page, name.end())
            stop = end.end() if end else -1
            if not end:
                missing.add(kind)
        if stop < 0:
            stop = page.find(">", start) + 1
            if not stop:  # no tag closes any more
                out.append(page[start:])
                return " ".join(out)
        at = stop
    out.append(page[at:])
    return " ".join(out)


def declared_language(page: str) -> str:
    """The primary subtag that the markup declares: ``lang`` or ``xml:lang`` of the root, else the
    content-language of a meta element; empty if none."""
    meta = ""
    for tag in TAG.finditer(page):
        attributes = {name.lower(): a or b or c for name, a, b, c in ATTRIBUTE.findall(tag[2])}
        if tag[1].lower() == "html":
            for name in ("lang", "xml:lang"):
                if found := SUBTAG.match(attributes.get(name, "")):
                    return found[1].lower()
        elif not meta and (attributes.get("http-equiv") or attributes.get("name") or "").lower() in ("content-language", "language"):
            found = SUBTAG.match(attributes.get("content", ""))
            meta = found[1].lower() if found else ""
    return meta


def buckets(text: str) -> np.ndarray:
    """Hashed byte trigrams of the lower-case text with white space folded."""
    raw = np.frombuffer((" " + " ".join(text.lower().split()) + " ").encode(), np.uint8).astype(np.uint32)
    if len(raw) < 3:
        return np.zeros(0, np.uint32)
    return ((raw[:-2] << 16 | raw[1:-1] << 8 | raw[2:]) * np.uint32(2654435761)) >> np.uint32(16)


def _histograms():
    schema = pa.schema([("lang", pa.string()), ("counts", pa.binary())])

    def make():
        def each(batch: pa.RecordBatch):
            sums: dict[str, np.ndarray] = {}
            for lang, text in zip(batch["lang"].to_pylist(), batch["text"].to_pylist(), strict=True):
                sums.setdefault(lang, np.zeros(BUCKETS, np.int64))
                sums[lang] += np.bincount(buckets(text), minlength=BUCKETS)
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.string()), pa.array([s.tobytes() for s in sums.values()], pa.binary())], schema=schema)

        return each

    return make


class TextModel:
    """Log-probabilities of trigram buckets, one column for each language."""

    def __init__(self, langs: list[str], logs: np.ndarray, strength: float):
        self.langs, self.logs, self.strength = langs, logs, strength

    def __call__(self, text: str) -> tuple[np.ndarray, int]:
        """Log-likelihoods less their greatest, and the number of trigrams."""
        b = buckets(text)
        if not len(b):
            return np.zeros(len(self.langs)), 0
        total = self.logs[b].sum(axis=0, dtype=float)
        total *= min(1.0, self.strength / len(b))
        return total - total.max(), len(b)


def train(spark: SparkSession, documents: DataFrame, limit: int = 4000, smoothing: float = 0.5, strength: float = 60.0) -> TextModel:
    """``limit``: labelled documents used at most, which bounds the languages too;
    ``strength``: trigrams that a text's evidence counts as at most."""
    known = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang")).where("doc_id is not null and lang is not null")
    chosen = bounded_sample(known.groupBy("doc_id").agg(F.min("lang").alias("lang")), "doc_id", limit)
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id").coalesce(8)
    sums: dict[str, np.ndarray] = {}
    for r in arrow_rows(texts.select("lang", "text"), _histograms(), "lang string, counts binary").toLocalIterator():
        sums[r["lang"]] = sums.get(r["lang"], 0) + np.frombuffer(r["counts"], np.int64)
    langs = sorted(sums) or ["und"]
    table = np.stack([sums.get(k, np.zeros(BUCKETS)) for k in langs], axis=1) + smoothing
    return TextModel(langs, np.log(table / table.sum(axis=0)).astype(np.float32), strength)


def _read(model: TextModel):
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("declared", pa.string()), ("trigrams", pa.int64()), ("likelihood", pa.list_(pa.float64()))])

    def make():
        def each(batch: pa.RecordBatch):
            for part in slices(batch):
                declared, sizes, values = [], [], []
                for page in part.column(2).to_pylist():
                    declared.append(declared_language(page))
                    v, n = model(entities.unescape(strip(page)))
                    sizes.append(n)
                    values.append(v.tolist())
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(declared, pa.string()), pa.array(sizes, pa.int64()), pa.array(values, schema.field(4).type)], schema=schema)

        return each

    return make


def address(url: Column) -> dict[str, Column]:
    """Host, registered domain (last two labels) and suffix with a language-like path segment."""
    host = F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/@?#]*@)?([^/:?#]*)", 1))
    hint = F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"//[^/?#]*/([A-Za-z]{2})(?:[-_][A-Za-z]{2,4})?(?:[/?#]|$)", 1))
    return {"host": host, "domain": F.substring_index(host, ".", -2), "suffix": F.concat(F.substring_index(host, ".", -1), F.lit("/"), hint)}


def keyed(left: DataFrame, right: DataFrame, key: str, total: int) -> DataFrame:
    """Join on a key of which ``right`` has one row with its count in ``rows``. A right side of a
    checked size is broadcast; beyond it the keys that hold 1/HOT of the rows or more, HOT at
    most, are broadcast and only the rest is shuffled, so no key makes a long task."""
    if right.limit(SMALL + 1).count() <= SMALL:
        return left.join(F.broadcast(right.drop("rows")), key)
    hot = right.where(F.col("rows") * HOT >= total).drop("rows")
    cold = right.where(F.col("rows") * HOT < total).drop("rows")
    rest = left.join(F.broadcast(hot.select(key)), key, "left_anti")
    return left.join(F.broadcast(hot), key).unionByName(rest.join(cold, key))


def identify(spark: SparkSession, pages: DataFrame, model: TextModel, trust: float = 4.0, kinship: float = 4.0) -> DataFrame:
    """(page_id, url, html) -> (page_id, lang, confidence, text_lang, declared, suffix, host, trigrams).

    ``trust``: pseudo-counts behind the reliability of declarations and addresses;
    ``kinship``: pages that a parent's shares count as in its children's.
    """
    scratch = Scratch(spark, "language")
    langs, size = model.langs, len(model.langs)
    raw = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    read = arrow_rows(raw, _read(model), "page_id long, url string, declared string, trigrams long, likelihood array<double>")
    weights = [F.exp(F.get("likelihood", F.lit(i))) for i in range(size)]
    total = sum(weights[1:], weights[0])
    read = read.select("page_id", "url", "declared", "trigrams", "likelihood", *[c.alias(k) for k, c in address(F.col("url")).items()], *[(w / total).alias(f"p{i}") for i, w in enumerate(weights)])
    read = scratch.keep(read, "read")

    def tally(keys: list[str]) -> DataFrame:
        return read.groupBy(*keys).agg(F.count("*").alias("n"), *[F.sum(f"p{i}").alias(f"s{i}") for i in range(size)])

    # All sums come from one small table, grouped once by everything that is a key.
    whole = read.agg(F.count("*").alias("n"), *[F.coalesce(F.sum(f"p{i}"), F.lit(0.0)).alias(f"s{i}") for i in range(size)]).first()
    pages_n = whole["n"] or 1
    shares = [(whole[f"s{i}"] + 0.5) / (pages_n + 0.5 * size) for i in range(size)]

    def reliability(key: str) -> DataFrame:
        """log P(value of key | language), up to what is common to all languages."""
        t = tally([key])
        logs = [F.log((F.col(f"s{i}") + trust * F.col("n") / pages_n) / (F.lit(whole[f"s{i}"]) + trust)) for i in range(size)]
        return scratch.keep(t.select(key, F.col("n").alias("rows"), F.array(*logs).alias(f"{key}_log")), key)

    domains = tally(["domain"]).select("domain", *[((F.col(f"s{i}") + kinship * shares[i]) / (F.col("n") + kinship)).alias(f"d{i}") for i in range(size)])
    hosts = tally(["host", "domain"]).join(domains, "domain").select("host", F.col("n").alias("host_n"), F.array(*[F.col(f"s{i}") for i in range(size)]).alias("host_s"), F.array(*[F.col(f"d{i}") for i in range(size)]).alias("domain_p"))
    hosts = scratch.keep(hosts, "hosts")
    joined = keyed(read, hosts.withColumn("rows", F.col("host_n")), "host", pages_n)
    for key in ("declared", "suffix"):
        joined = keyed(joined, reliability(key), key, pages_n)

    def posterior(i: int) -> Column:
        own = F.col(f"p{i}")
        prior = (F.greatest(F.get("host_s", F.lit(i)) - own, F.lit(0.0)) + kinship * F.get("domain_p", F.lit(i))) / (F.col("host_n") - 1 + kinship)
        declared = F.when(F.col("declared") == "", F.lit(0.0)).otherwise(F.get("declared_log", F.lit(i)))
        return F.get("likelihood", F.lit(i)) + declared + F.get("suffix_log", F.lit(i)) + F.log(prior)

    logs = F.array(*[posterior(i) for i in range(size)])
    names = F.array(*[F.lit(k) for k in langs])
    text_best = F.array_position("likelihood", F.array_max("likelihood"))
    out = joined.withColumn("logs", logs).withColumn("top", F.array_max("logs"))
    return out.select(
        "page_id",
        F.get(names, (F.array_position("logs", F.col("top")) - 1).cast("int")).alias("lang"),
        F.round(1 / F.aggregate(F.transform("logs", lambda x: F.exp(x - F.col("top"))), F.lit(0.0), lambda s, x: s + x), 6).alias("confidence"),
        F.when(F.col("trigrams") > 0, F.get(names, (text_best - 1).cast("int"))).alias("text_lang"),
        "declared",
        "suffix",
        "host",
        "trigrams",
    )
