"""Mixing sources to target weights by capped water-filling (DataFrame functions only).

Sources share ``factor`` times all words in proportion to their weights. A source whose share is above
``max_epochs`` times its size is clamped there and the excess goes to the others by weight, until no
share is above its cap. The level is found from prefix sums over sources ordered by cap per weight, which
gives what repeated clamping would.

Documents of a source are put in a seeded order. Each is taken ``floor(target / size of source)`` times in
whole, and the rest of the target is one more pass over the seeded order that stops at the target: whole
documents up to there and a fraction of the one at the boundary. Positions are running sums within
(source, bucket) on top of the buckets' totals, so that a source with a third of all rows is spread over
``16 ** BUCKET_DIGITS`` window groups.

Only a table with a row per source is ever ordered as a whole; it grows with the number of sources.

The sources' own totals are windowed in one task: a row per source (and bucket count), not per document.

Defined cases: very long texts are counted whole; a null or empty text has size 0 and is taken 0 times; a null source is a source of its
own, last in order; rows that repeat an id count each for themselves; an empty table gives an empty one.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from blindmatch.llm import storage
from blindmatch.llm.words import WORD

BUCKET_DIGITS = 3
WEIGHTS = (5, 2, 1)


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def water_fill(sizes: DataFrame, weights: Sequence[int] = WEIGHTS, factor: float = 1.5, max_epochs: int = 2) -> DataFrame:
    """``sizes``: source, source_size. Adds weight and target (double). Sources by code point, null last, take ``weights`` in turn."""
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    turn = F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights))) + 1
    everything = Window.partitionBy(F.lit(1))
    t = sizes.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), turn).cast("double"))
    t = t.withColumn("cap", (F.col("source_size") * max_epochs).cast("double"))
    t = t.withColumn("budget", F.sum("source_size").over(everything) * F.lit(float(factor)))
    rising = Window.partitionBy(F.lit(1)).orderBy((F.col("cap") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before, after = rising.rowsBetween(Window.unboundedPreceding, -1), rising.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    t = t.withColumn("_caps", F.coalesce(F.sum("cap").over(before), F.lit(0.0))).withColumn("_weights", F.sum("weight").over(after))
    t = t.withColumn("_full", F.col("cap") * F.col("_weights") <= (F.col("budget") - F.col("_caps")) * F.col("weight"))
    # Fullness is monotone in this order; what is left after all full sources is shared by weight.
    left = F.col("budget") - F.sum(F.when(F.col("_full"), F.col("cap")).otherwise(0.0)).over(everything)
    open_weight = F.sum(F.when(F.col("_full"), 0.0).otherwise(F.col("weight"))).over(everything)
    t = t.withColumn("_left", left).withColumn("_open", open_weight)
    target = F.when(F.col("_full"), F.col("cap")).otherwise(F.col("_left") * F.col("weight") / F.col("_open"))
    return t.select("source", "source_size", "weight", target.alias("target"))


def mix_sources(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    weights: Sequence[int] = WEIGHTS,
    factor: float = 1.5,
    max_epochs: int = 2,
    seed: int = 7,
) -> DataFrame:
    """One row per document: id, size, source_size, target, taken (words, repeats counted)."""
    return _taken(docs, id_col, text_col, source_col, weights, factor, max_epochs, seed).select(F.col("id").alias(id_col), "size", "source_size", "target", "taken")


def _taken(docs: DataFrame, id_col: str, text_col: str, source_col: str = "source", weights: Sequence[int] = WEIGHTS, factor: float = 1.5, max_epochs: int = 2, seed: int = 7) -> DataFrame:
    """One row per document: id, source, size, source_size, target, taken."""
    order = F.md5(F.concat_ws(":", F.lit(str(seed)), F.col(id_col).cast("string")))
    sized = docs.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), word_count(F.col(text_col)).alias("size"), order.alias("ord"))
    # Written once: the texts are read and counted only here.
    sized = storage.written(sized.withColumn("bucket", F.substring("ord", 1, BUCKET_DIGITS)), "sized")
    buckets = sized.groupBy("source", "bucket").agg(F.sum("size").alias("bucket_size"))
    totals = buckets.groupBy("source").agg(F.sum("bucket_size").alias("source_size"))
    targets = water_fill(totals, weights, factor, max_epochs)
    earlier = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    buckets = buckets.withColumn("_start", F.coalesce(F.sum("bucket_size").over(earlier), F.lit(0)))
    buckets = buckets.join(targets, buckets["source"].eqNullSafe(targets["source"])).select(
        buckets["source"], "bucket", "_start", "source_size", "target"
    )
    s, b = sized.alias("s"), buckets.alias("b")
    rows = s.join(b, F.col("s.source").eqNullSafe(F.col("b.source")) & (F.col("s.bucket") == F.col("b.bucket"))).select(
        "s.id", "s.source", "s.bucket", "s.ord", "s.size", "_start", "source_size", "target"
    )
    within = Window.partitionBy("source", "bucket").orderBy("ord", F.col("id").asc_nulls_last(), "size")
    within = within.rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("_at", F.col("_start") + F.coalesce(F.sum("size").over(within), F.lit(0)))
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    rows = rows.withColumn("_whole", whole)
    stop = F.round(F.col("target") - F.col("_whole") * F.col("source_size")).cast("long")
    part = F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), stop - F.col("_at")))
    return rows.select("id", "source", "size", "source_size", "target", (F.col("_whole") * F.col("size") + part).alias("taken"))


def mixed_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **how) -> DataFrame:
    """The mix itself, with the columns of ``docs``: each document once per whole repetition, and a
    fraction as its first words joined by single spaces.

    Rows of one source that repeat an id (null ids too) are mixed alike, each as often as the most taken of them, so ids should
    be unique. Empty texts are taken 0 times, so they leave."""
    taken = _taken(docs, id_col, text_col, source_col, **how).where("taken > 0")
    taken = taken.select("id", "source", F.floor(F.col("taken") / F.col("size")).cast("int").alias("times"), (F.col("taken") % F.col("size")).cast("int").alias("rest"))
    taken = taken.groupBy("id", "source").agg(F.max("times").alias("times"), F.max("rest").alias("rest"))
    # The input's row is one value, so none of its columns can clash with the ones added here.
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"))
    rows = rows.join(taken, F.col("row")[id_col].eqNullSafe(F.col("id")) & F.col("row")[source_col].eqNullSafe(F.col("source"))).where(F.octet_length(F.col("row")[text_col]) > 0)
    none = F.array().cast("array<int>")
    copies = F.when(F.col("times") > 0, F.array_repeat(F.lit(0), F.col("times"))).otherwise(none)
    copies = F.concat(copies, F.when(F.col("rest") > 0, F.array(F.col("rest"))).otherwise(none))
    rows = rows.select("row", F.explode(copies).alias("n"))
    text = F.col("row")[text_col]
    cut = F.concat_ws(" ", F.slice(F.regexp_extract_all(text, F.lit(WORD), F.lit(0)), F.lit(1), F.col("n")))
    return rows.select(*(F.when(F.col("n") > 0, cut).otherwise(text).alias(c) if c == text_col else F.col("row")[c].alias(c) for c in docs.columns))
