"""Line deduplication by overlapping windows of consecutive lines.  DataFrame functions only.

Every window of ``span`` consecutive lines is hashed to 128 bits.  The first place of each window, by
(document id, line number), is one map-side combined minimum over the corpus; only windows seen twice go
back to their documents, where the positions they cover are merged and dropped.  The few windows that hold over a
thousandth of all repeats learn their first place by a broadcast, so none of them gathers in one task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SharedTable, text_or_empty

#: Line numbers below this fit beside the document id in one decimal, so that a minimum stays in a fixed-width buffer.
LINE_LIMIT = 10**10


def _windows(docs: DataFrame, span: int) -> DataFrame:
    """doc_id, at (line number), h1, h2 for each window of ``span`` lines that has a word in it."""
    lines = docs.select("doc_id", F.split("body", "\n").alias("lines")).where(F.size("lines") >= span)

    def window(i):
        part = [F.get("lines", i + k) for k in range(span)]
        blank = F.btrim(F.concat(*part), F.lit(" \t\x0b\x0c\r")) == ""
        return F.struct(i.cast("long").alias("at"), blank.alias("blank"), F.xxhash64(F.lit(0), *part).alias("h1"), F.xxhash64(F.lit(1), *part).alias("h2"))

    found = lines.select("doc_id", F.explode(F.transform(F.sequence(F.lit(0), F.size("lines") - span), window)).alias("w"))
    return found.where(~F.col("w.blank")).select("doc_id", "w.at", "w.h1", "w.h2")


def later_windows(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", span: int = 3) -> DataFrame:
    """doc_id, at: each window whose lines also start earlier in the corpus."""
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("body")).where("doc_id is not null")
    windows = SharedTable(_windows(docs, span), "windows").read()  # hashed once
    place = (F.col("doc_id").cast("decimal(20,0)") * F.lit(LINE_LIMIT).cast("decimal(11,0)") + F.col("at")).cast("decimal(38,0)")
    windows = windows.withColumn("place", place)
    firsts = SharedTable(windows.groupBy("h1", "h2").agg(F.min("place").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1"), "firsts").read()
    share = max(1, (firsts.agg(F.sum("n")).first()[0] or 0) // 1000)
    hot = firsts.where(F.col("n") > share).select("h1", "h2", F.col("first").alias("hot"))  # fewer than a thousand, whatever the input
    windows = windows.join(F.broadcast(hot), ["h1", "h2"], "left")
    cold = firsts.where(F.col("n") <= share).drop("n")
    later = windows.where("hot is null").join(cold, ["h1", "h2"]).where("place > first")
    return windows.where("place > hot").select("doc_id", "at").unionAll(later.select("doc_id", "at"))


def line_dedup(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", span: int = 3) -> DataFrame:
    """``doc_id, n_lines, n_removed, text``: each document without the lines that a repeated window covers.

    A window is ``span`` consecutive lines (split at line feeds, equal when two 64-bit hashes of different seeds are)
    with a word in at least one of them.  The first window by (id, line number) stays; every line under a later one goes.
    Texts with fewer lines have no window and stay whole.  Null texts count as empty (one empty line).  Rows
    that share an id share its removals, so repeated rows stay equal; a null id has no place in the order and
    its row stays whole.  Other columns are ignored.  An empty input gives an empty result.
    """
    rows = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("body"))
    out = _without_later(rows, _gone(docs, id_col, text_col, span), "doc_id", "body", span)
    lines = F.size(F.split("body", "\n"))
    removed = F.when(F.col("_stay").isNull(), F.lit(0)).otherwise(lines - F.size("_stay"))
    return out.select("doc_id", lines.cast("long").alias("n_lines"), removed.cast("long").alias("n_removed"), F.col("_kept").alias("text"))


def _gone(docs: DataFrame, id_col: str, text_col: str, span: int) -> DataFrame:
    later = later_windows(docs, id_col=id_col, text_col=text_col, span=span)
    return later.groupBy(F.col("doc_id").alias("_id")).agg(F.collect_set("at").alias("_starts"))


def _without_later(rows: DataFrame, gone: DataFrame, id_col: str, text_col: str, span: int) -> DataFrame:
    """The rows with ``_stay`` (numbers of the lines that stay, null for all) and ``_kept`` (their text)."""
    covered = F.flatten(F.transform("_starts", lambda p: F.sequence(p, p + (span - 1))))
    lines = F.split(F.col(text_col), "\n")
    stay = F.array_except(F.sequence(F.lit(0).cast("long"), F.size(lines).cast("long") - 1), covered)
    out = rows.join(gone, F.col(id_col) == F.col("_id"), "left").withColumn("_stay", F.when(F.col("_starts").isNotNull(), stay))
    kept = F.when(F.col("_stay").isNull(), F.col(text_col)).otherwise(F.array_join(F.transform("_stay", lambda i: F.get(lines, i.cast("int"))), "\n"))
    return out.withColumn("_kept", kept)


def remove_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", span: int = 3) -> DataFrame:
    """All rows and columns of ``docs``, texts without the lines of later windows; null texts stay null."""
    names = docs.columns
    plain = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names)])  # clashing names stay apart
    id_, text = f"c{names.index(id_col)}", f"c{names.index(text_col)}"
    out = _without_later(plain, _gone(docs, id_col, text_col, span), id_, text, span)
    return out.select(*[(F.col("_kept") if c == text_col else F.col(f"c{i}")).alias(c) for i, c in enumerate(names)])
