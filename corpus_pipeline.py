"""A corpus pipeline: quality, repeated lines, near duplicates, secrets, packing.

Each stage takes (spark, docs, sf_dir) and works on all rows that its predecessor kept.  All but the last return the
columns of ``documents``; the last returns packed pieces.

In every stage null texts count as empty and stay null where the text does not change; a null id is passed on; repeated rows
are treated alike; columns beyond those of ``documents`` pass through, whatever their names; an empty table gives an empty
result; the length of a text is not bounded.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutfield.llm import line_dedup, packing, passage_quality, secret_scan, simhash
from cutfield.llm.common import SharedTable, table
from cutfield.llm.queries import vocabulary
from cutfield.storage import Tables


def _counted(docs: DataFrame) -> DataFrame:
    """``n_chars`` follows the text, where there is such a column."""
    return docs.withColumn("n_chars", F.char_length("text").cast("long")) if "n_chars" in docs.columns else docs


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the passage classifier scores at 0.3 or more; a null or empty text is scored like any other."""
    return passage_quality.keep_good(docs, passage_quality.fit(docs, table(spark, sf_dir, "labels")))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines of repeated three-line windows; ``n_chars`` follows.  A row without an id stays whole."""
    return _counted(line_dedup.remove_lines(docs))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without near duplicates (five-word similarity of 0.8 or more, candidates by ball hashing); the smallest ids stay."""
    return simhash.near_dedup(docs)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with their secrets redacted; ``n_chars`` follows, null for a null text."""
    return _counted(secret_scan.redact(docs))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 4096 ids, with the ids."""
    return packing.pack(docs, vocabulary("word_bpe_49k.json"))


STAGES = [("quality classifier", quality), ("line dedup", lines), ("simhash near-dedup", near_duplicates), ("secret scans", secrets), ("packing", pack)]

#: The first stage is learned and the third hashes with XXH64, which DuckDB lacks; a test holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages over ``documents``, each written and read again; a stage's tables go when the next one is written."""
    docs, held = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        with Tables(spark) as own:
            out = stage(spark, docs, sf_dir)
        done = SharedTable(out, name.replace(" ", "-"))
        own.drop()
        if held:
            held.drop()
        docs, held = done.read(), done
    return STAGES[-1][1](spark, docs, sf_dir)
