"""The registered queries of the training-data operators, with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.llm import chat, decontaminate, html_text, language_id, minhash, mpeg_audio, packing, quality, token_tree, toxicity
from vecspark.llm.common import table


def op1_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.leaks(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    model = language_id.train(spark, table(spark, sf_dir, "documents"))
    return language_id.identify(spark, table(spark, sf_dir, "pages"), model)


def op3_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mpeg_audio.media_columns(table(spark, sf_dir, "documents"))


def op4_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(spark, table(spark, sf_dir, "documents"), width=4, percent=80)


OP4_SQL = r"""
WITH RECURSIVE words AS MATERIALIZED (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), shingles AS MATERIALIZED (
  SELECT DISTINCT doc_id, array_to_string(w[i : i + 3], ' ') AS shingle
  FROM (SELECT doc_id, w, unnest(range(1, greatest(1, len(w) - 3) + 1)) AS i FROM words WHERE len(w) > 0)
), sizes AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id
), met AS MATERIALIZED (
  SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS common FROM shingles x JOIN shingles y USING (shingle) WHERE x.doc_id < y.doc_id GROUP BY ALL
), links AS MATERIALIZED (
  SELECT a, b FROM met JOIN sizes s ON s.doc_id = a JOIN sizes t ON t.doc_id = b WHERE 100 * common >= 80 * (s.n + t.n - common)
), edges AS MATERIALIZED (SELECT a, b FROM links UNION ALL SELECT b, a FROM links
), reach AS (
  SELECT a AS doc_id, a AS seen FROM edges
  UNION SELECT r.doc_id, e.b FROM reach r JOIN edges e ON e.a = r.seen
), least AS (SELECT doc_id, min(seen) AS component FROM reach GROUP BY doc_id)
SELECT doc_id, coalesce(n, 0)::BIGINT AS n_shingles, coalesce(component, doc_id)::BIGINT AS component_id, coalesce(component, doc_id) = doc_id AS kept
FROM documents LEFT JOIN sizes USING (doc_id) LEFT JOIN least USING (doc_id)
"""


def op5_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract_main_text(table(spark, sf_dir, "pages"))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of all documents, before and after an edit at the start and one in the middle of each."""
    trees = token_tree.token_trees(table(spark, sf_dir, "documents"))
    middle = F.floor(F.length(F.coalesce("text", F.lit(""))) / 2).cast("long")

    def edit(position, removed, inserted):
        return F.struct(position.alias("position"), F.lit(removed).cast("long").alias("removed"), F.lit(inserted).alias("inserted"))

    return token_tree.edited_counts(trees.withColumn("edits", F.array(edit(F.lit(0).cast("long"), 0, "Re: "), edit(middle, 12, " (edited) "))))


def op7_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    said = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    return chat.digest(chat.loss_mask(chat.read_back(chat.format_conversations(turns.unionByName(extra)))))


OP7_SQL = r"""
WITH rows AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]'
  UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'
), safe AS (
  SELECT *, replace(replace(replace(replace(text, '&', '&amp;'), '<', '&lt;'), '[', '&#91;'), ']', '&#93;') AS safe_text,
    replace(replace(replace(replace(role, '&', '&amp;'), '<', '&lt;'), '[', '&#91;'), ']', '&#93;') AS safe_role,
    lag(role) OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS before
  FROM rows
)
SELECT conv_id, count(*)::BIGINT AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  sum(length(safe_text) + CASE WHEN before IS NULL OR before <> role THEN length(safe_role) + 9 ELSE 3 END)::BIGINT AS formatted_chars
FROM safe GROUP BY conv_id
"""


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.train(spark, docs, table(spark, sf_dir, "labels"))
    return toxicity.with_folds(toxicity.score(docs, model), toxicity.PARTS, toxicity.HELD)


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(spark, table(spark, sf_dir, "documents"))


def op10_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = quality.train(spark, docs, table(spark, sf_dir, "labels"))
    return toxicity.with_folds(quality.score(docs, model), quality.PARTS, quality.HELD)


QUERIES = {
    f.__name__: f
    for f in (
        op1_benchmark_decontamination,
        op2_language_id,
        op3_media_columns,
        op4_minhash_near_dedup,
        op5_html_extraction,
        op6_token_counts,
        op7_chat_formatting,
        op8_toxicity,
        op9_packing,
        op10_quality_classifier,
    )
}
ORACLES = {"op4_minhash_near_dedup": OP4_SQL, "op7_chat_formatting": OP7_SQL}
