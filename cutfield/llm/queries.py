"""The registered queries of this subpackage: production parameters, whole tables, digest columns."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat_format, exact_dedup, line_dedup, packing, passage_quality, quality_rules, secret_scan, sentencepiece_bpe, simhash, substring_dedup
from .common import table


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.substring_dedup(table(spark, sf_dir, "documents"), with_text=False).drop("text")


def vocabulary(name: str) -> str:
    """Place of a public tokenizer file; it is installed on every machine and never copied here."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op2_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentencepiece_bpe.round_trip_digests(table(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    rules = quality_rules.learn_rules(docs, table(spark, sf_dir, "labels"))
    return quality_rules.quality_rules(docs, rules)


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(table(spark, sf_dir, "documents"), keep="largest")


def op5_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    extra = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit("</s>[INST] ok [/INST]").alias("text"))
    return chat_format.digests(chat_format.format_chats(chat_format.from_rows(rows.unionByName(extra))))


def op6_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secret_scan.scan(table(spark, sf_dir, "documents"))
    of = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    base = F.filter("spans", lambda s: s["kind"] != "random")
    return found.select("doc_id", of("assign"), of("access"), of("hex"), F.sha2(secret_scan.listed(base), 256).alias("base_sha256"), secret_scan.listed(F.col("spans")).alias("spans"))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.simhash_groups(table(spark, sf_dir, "documents"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup.line_dedup(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_lines", "n_removed", F.sha2("text", 256).alias("kept_sha256"))


def op9_passage_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return passage_quality.quality_scores(docs, passage_quality.fit(docs, table(spark, sf_dir, "labels")))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"), with_ids=False).drop("ids")


QUERIES = {
    "op1_substring_dedup": op1_substring_dedup,
    "op2_sentencepiece": op2_sentencepiece,
    "op3_quality_rules": op3_quality_rules,
    "op4_exact_dedup": op4_exact_dedup,
    "op5_chat_format": op5_chat_format,
    "op6_secret_scan": op6_secret_scan,
    "op7_simhash": op7_simhash,
    "op8_line_dedup": op8_line_dedup,
    "op9_passage_quality": op9_passage_quality,
    "op10_packing": op10_packing,
}

OP1_SQL = r"""
WITH w AS (
  SELECT doc_id, CASE WHEN regexp_matches(coalesce(text, ''), '[^\x20\x09-\x0D]')
    THEN regexp_extract_all(text, '[^\x20\x09-\x0D]+') ELSE []::VARCHAR[] END AS ws FROM documents
), g AS (
  SELECT doc_id, ws, unnest(range(1, len(ws) - 18)) AS i FROM w WHERE len(ws) >= 20
), later AS (
  SELECT doc_id, i FROM (
    SELECT doc_id, i, row_number() OVER (PARTITION BY ws[i:i+19] ORDER BY doc_id, i) AS k FROM g) WHERE k > 1
), gone AS (
  SELECT DISTINCT doc_id, i + unnest(range(0, 20)) AS i FROM later
), x AS (
  SELECT doc_id, unnest(ws) AS word, unnest(range(1, len(ws) + 1)) AS i FROM w
), s AS (
  SELECT x.doc_id, count(gone.i) AS n_removed,
         coalesce(string_agg(word, ' ' ORDER BY x.i) FILTER (WHERE gone.i IS NULL), '') AS t
  FROM x LEFT JOIN gone ON x.doc_id = gone.doc_id AND x.i = gone.i GROUP BY x.doc_id
)
SELECT w.doc_id, len(w.ws)::BIGINT AS n_words, coalesce(n_removed, 0)::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM w LEFT JOIN s USING (doc_id)
"""

OP4_SQL = """
WITH d AS (
  SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents
)
SELECT doc_id, max(doc_id) OVER (PARTITION BY t) AS keep_id, count(*) OVER (PARTITION BY t) AS group_size,
       doc_id = max(doc_id) OVER (PARTITION BY t) AS kept, sha256(t) AS text_sha256
FROM d
"""

_CONTROLS = ("<|", "|>", "</s>", "<s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "\\")
_ESCAPES = " + ".join(f"(len(t) - len(replace(t, '{c}', ''))) // {len(c)}" for c in _CONTROLS)
OP5_SQL = f"""
WITH c AS (
  SELECT conv_id, turn, role, coalesce(text, '') AS t FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'
), g AS (
  SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || t || chr(10), '' ORDER BY turn) AS whole,
         coalesce(string_agg(t, '' ORDER BY turn) FILTER (WHERE role = 'assistant'), '') AS said,
         sum(23 + len(role) + len(t) + {_ESCAPES})::BIGINT AS formatted_chars
  FROM c GROUP BY conv_id
)
SELECT conv_id, n_turns, sha256(whole) AS turns_sha256, len(said) AS loss_chars, sha256(said) AS loss_sha256, formatted_chars FROM g
"""

OP8_SQL = r"""
WITH l AS (
  SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents
), w AS (
  SELECT doc_id, i, ls[i:i+2] AS win FROM (SELECT doc_id, ls, unnest(range(1, len(ls) - 1)) AS i FROM l)
), later AS (
  SELECT doc_id, i FROM (
    SELECT doc_id, i, row_number() OVER (PARTITION BY win ORDER BY doc_id, i) AS k
    FROM w WHERE regexp_matches(array_to_string(win, chr(10)), '[^\x20\x09-\x0D]'))
  WHERE k > 1
), gone AS (
  SELECT DISTINCT doc_id, i + unnest([0, 1, 2]) AS i FROM later
), x AS (
  SELECT doc_id, unnest(range(1, len(ls) + 1)) AS i, unnest(ls) AS line FROM l
), s AS (
  SELECT x.doc_id, count(*) AS n_lines, count(gone.i) AS n_removed,
         coalesce(string_agg(line, chr(10) ORDER BY x.i) FILTER (WHERE gone.i IS NULL), '') AS t
  FROM x LEFT JOIN gone ON x.doc_id = gone.doc_id AND x.i = gone.i GROUP BY x.doc_id
)
SELECT doc_id, n_lines, n_removed, sha256(t) AS kept_sha256 FROM s
"""

ORACLE_SQL = {"op1_substring_dedup": OP1_SQL, "op4_exact_dedup": OP4_SQL, "op5_chat_format": OP5_SQL, "op8_line_dedup": OP8_SQL}
