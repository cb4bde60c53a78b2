"""Exact de-duplication with skew-safe combining (DataFrame functions only).

Equal texts are combined three times, and each time the whole normalised text is part of the key, so a
digest alone never decides: within a task (map-side partial aggregation), per salted digest group, and
over the salts' winners. A group that holds a third of all rows therefore reaches the last stage as at
most ``salts`` rows.

Documents meet their group by SHA-256 of the content, a second hash and the length; of content itself only the comparing stages see it.

Defined cases: a null text counts as empty; empty texts are equal to each other; very long texts are one value each and are
hashed whole; a null id never wins over another id; an empty table gives an empty table. :func:`duplicate_groups` returns
a row for each row, and rows that repeat both id and text share its verdict. :func:`deduplicate` keeps one row of each text
whatever ids repeat: of rows that agree in id and text, one that is largest by all other columns' hash (equal rows by any).
Extra columns, whatever their names, are neither read nor returned by the former and are kept by the latter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SALTS = 32
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def lower_ascii(text: Column) -> Column:
    """A-Z as a-z, all else unchanged; null as empty. Pure ASCII texts take the faster built-in."""
    text = F.coalesce(text, F.lit(""))
    ascii_only = F.octet_length(text) == F.char_length(text)
    return F.when(ascii_only, F.lower(text)).otherwise(F.translate(text, _UPPER, _LOWER))


def _groups(rows: DataFrame, salts: int) -> DataFrame:
    """One row per text: digest, check, chars, keep_id, group_size. ``rows``: id, content, digest."""
    salted = rows.groupBy("digest", "content", F.pmod(F.xxhash64("id"), F.lit(salts)).alias("salt")).agg(
        F.max("id").alias("top"), F.count(F.lit(1)).alias("n")
    )
    groups = salted.groupBy("digest", "content").agg(F.max("top").alias("keep_id"), F.sum("n").alias("group_size"))
    # A second hash and the length stand in for the content where documents meet their group.
    return groups.select("digest", F.xxhash64("content").alias("check"), F.length("content").alias("chars"), "keep_id", "group_size")


def _hashed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    rows = docs.select(F.col(id_col).alias("id"), lower_ascii(F.col(text_col)).alias("content"))
    return rows.withColumn("digest", F.sha2("content", 256))


def duplicate_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = SALTS) -> DataFrame:
    """One row per document: id, keep_id, group_size, kept, text_sha256."""
    rows = _hashed(docs, id_col, text_col)
    ids = rows.select("id", "digest", F.xxhash64("content").alias("check"), F.length("content").alias("chars"))
    return ids.join(_groups(rows, salts), ["digest", "check", "chars"]).select(
        F.col("id").alias(id_col),
        "keep_id",
        "group_size",
        F.col("id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.col("digest").alias("text_sha256"),
    )


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = SALTS) -> DataFrame:
    """One row of each text, with all its columns: that of the largest id (null ids lose; ties by the row's hash, then any)."""
    first = _groups(_hashed(docs, id_col, text_col), salts)
    # The winner's id is part of the key, so a large group is not dealt to one task; rows that repeat it are ranked where they meet.
    first = first.select(F.coalesce("keep_id", F.lit(0)).alias("k"), F.isnull("keep_id").alias("no_id"), "digest", "check", "chars")
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"))
    row_id, content = F.col("row")[id_col], lower_ascii(F.col("row")[text_col])
    rows = rows.select(F.coalesce(row_id, F.lit(0)).alias("k"), F.isnull(row_id).alias("no_id"), F.sha2(content, 256).alias("digest"), F.xxhash64(content).alias("check"), F.length(content).alias("chars"), "row")
    stay = rows.join(first, first.columns, "left_semi")
    rank = F.row_number().over(Window.partitionBy(*first.columns).orderBy(F.xxhash64("row")))
    return stay.withColumn("rank", rank).where("rank = 1").select("row.*")
