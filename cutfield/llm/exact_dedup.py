"""Exact deduplication by 128-bit content hash with a byte comparison inside every group.  DataFrame functions only.

Rows are grouped by the MD5 of the normalised text.  Each group's representative text is compared, byte for
byte, with every other member, so a hash collision splits its group instead of dropping a document.  Groups
of any size are dealt over ``ceil(size / rows_per_salt)`` salts before texts are compared; group sizes come
from map-side combined counts, and the few groups that hold over a thousandth of all rows are dealt over parts even
before they learn their sizes.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SharedTable, ascii_lower, text_or_empty


def exact_dedup(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest", fold_case: bool = True, rows_per_salt: int = 256) -> DataFrame:
    """One row per input row: ``doc_id, keep_id, group_size, kept, text_sha256``.

    ``keep`` is ``smallest`` or ``largest``: which id of a group of equal texts stays.  Null texts count as
    empty.  Rows that share both id and text are all marked as the kept one, as nothing tells them apart; a
    row with a null id is kept only when its whole group has null ids.  Other columns are ignored, whatever
    their names.  An empty input gives an empty result.
    """
    best = {"smallest": F.min, "largest": F.max}[keep]
    text = text_or_empty(text_col)
    body = ascii_lower(text) if fold_case else text
    base = docs.select(F.col(id_col).alias("doc_id"), body.alias("body"))
    base = base.withColumn("key", F.coalesce(F.unhex(F.md5("body")), F.lit(b"")))  # never null, so that no filter computes it again
    groups = SharedTable(base.groupBy("key").agg(best("doc_id").alias("rep"), F.count(F.lit(1)).alias("size")), "groups").read()
    # groups of over a thousandth of all rows, fewer than a thousand whatever the input, meet their rows in as many parts as they have thousandths
    share = max(1, (groups.agg(F.sum("size")).first()[0] or 0) // 1000)
    groups = groups.withColumn("parts", F.ceil(F.col("size") / share).cast("int"))
    hot = F.broadcast(groups.where("parts > 1").select("key", "parts"))
    base = base.join(hot, "key", "left").select("doc_id", "body", "key", F.pmod(F.xxhash64("doc_id"), F.coalesce("parts", F.lit(1))).cast("int").alias("part"))
    groups = groups.select("key", "rep", "size", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"))

    salts = F.ceil(F.col("size") / F.lit(rows_per_salt)).cast("int")
    rows = base.join(groups, ["key", "part"]).withColumn("sha", F.sha2("body", 256))
    rows = rows.withColumn("body", F.when(F.col("size") > 1, F.col("body")))  # texts of single rows go no further
    rows = rows.withColumn("salt", F.pmod(F.xxhash64("doc_id"), salts).cast("int"))
    # an inequality, which only the representative meets: the texts are then dealt by key once, for both uses
    chosen = F.col("doc_id") <= F.col("rep") if keep == "smallest" else F.col("doc_id") >= F.col("rep")
    reps = base.join(groups, ["key", "part"]).where((F.col("size") > 1) & F.when(F.col("rep").isNull(), True).otherwise(chosen))
    reps = reps.groupBy("key", "size").agg(F.min("body").alias("rep_body"))  # repeated rows of one id, or all ids null
    reps = reps.select("key", "rep_body", F.explode(F.sequence(F.lit(0), salts - 1)).alias("salt"))
    seen = rows.join(reps, ["key", "salt"], "left").select("doc_id", "key", "rep", "size", "sha", F.when(F.col("size") > 1, ~F.col("body").eqNullSafe(F.col("rep_body"))).otherwise(False).alias("differs"))

    # A differing text has its own SHA-256; equal hash and equal SHA-256 with unequal bytes is the one case left, and
    # its rows stay apart because only rows that equal the representative join its class.
    tag = F.when(F.col("differs"), F.col("sha")).otherwise(F.lit("")).alias("tag")
    seen = SharedTable(seen.select("doc_id", "key", "sha", "size", "rep", tag), "exact").read()  # no texts from here on
    parts = F.ceil(F.col("size") / share).cast("int")
    seen = seen.withColumn("cell", F.pmod(F.xxhash64("doc_id"), parts).cast("int"))
    cells = F.explode(F.sequence(F.lit(0), parts - 1)).alias("cell")
    odd = seen.where("tag <> ''").groupBy("key", "tag", "size").agg(best("doc_id").alias("odd_rep"), F.count(F.lit(1)).alias("odd_size"))
    lost = odd.groupBy("key", "size").agg(F.sum("odd_size").alias("lost")).select("key", "lost", cells)
    odd = odd.select("key", "tag", "odd_rep", "odd_size", cells)
    out = seen.join(odd, ["key", "tag", "cell"], "left").join(lost, ["key", "cell"], "left")
    keep_id = F.when(F.col("tag") == "", F.col("rep")).otherwise(F.col("odd_rep"))
    size = F.when(F.col("tag") == "", F.col("size") - F.coalesce("lost", F.lit(0))).otherwise(F.col("odd_size"))
    return out.select("doc_id", keep_id.alias("keep_id"), size.cast("long").alias("group_size"), F.col("doc_id").eqNullSafe(keep_id).alias("kept"), F.col("sha").alias("text_sha256"))
