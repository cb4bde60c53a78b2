"""Quality, cost and disclosure measures. Pairs are counted by formulas of group sizes, never by joining pairs."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _pairs(n: Column) -> Column:
    return F.coalesce(F.sum(n * (n - 1) / 2), F.lit(0)).cast("long")


def quality_pairs(assigned: DataFrame, truth: DataFrame, s_m: int = 2) -> DataFrame:
    """tm, fm, fn over record pairs in clusters of at least ``s_m`` records. ``truth``: rec_id, entity_id. Clusters may not overlap."""
    return missed_pairs(found_pairs(assigned, truth, s_m), truth, s_m)


def found_pairs(assigned: DataFrame, truth: DataFrame, s_m: int = 2) -> DataFrame:
    """One row of tm, the pairs of one entity within clusters, and pairs, all of them."""
    joined = assigned.where(F.col("cluster_size") >= s_m).join(truth.select("rec_id", "entity_id"), "rec_id")
    both = joined.groupBy("block", "cluster_id", "entity_id").agg(F.count(F.lit(1)).alias("c"))
    found = both.groupBy("block", "cluster_id").agg(F.sum("c").alias("n"), F.sum(F.col("c") * (F.col("c") - 1) / 2).alias("t"))
    return found.agg(F.coalesce(F.sum("t"), F.lit(0)).cast("long").alias("tm"), _pairs(F.col("n")).alias("pairs"))


def missed_pairs(found: DataFrame, truth: DataFrame, s_m: int = 2) -> DataFrame:
    """Rows of tm and pairs, and other columns, with fm and fn."""
    b = truth.groupBy("entity_id").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= s_m).agg(_pairs(F.col("n")).alias("true_pairs"))
    out, tags = found.crossJoin(b), [c for c in found.columns if c not in ("tm", "pairs")]  # one row of true pairs
    return out.select(*tags, "tm", (F.col("pairs") - F.col("tm")).alias("fm"), F.greatest(F.lit(0), F.col("true_pairs") - F.col("tm")).alias("fn"))


def prf(counts: DataFrame) -> DataFrame:
    """precision, recall and f of a row of tm, fm, fn; 0 where undefined."""
    tm, fm, fn = F.col("tm"), F.col("fm"), F.col("fn")
    p = F.when(tm + fm > 0, tm / (tm + fm)).otherwise(0.0)
    r = F.when(tm + fn > 0, tm / (tm + fn)).otherwise(0.0)
    f = F.when(tm > 0, 2 * tm / (2 * tm + fm + fn)).otherwise(0.0)
    return counts.select("*", F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(f, 6).alias("f"))


def quality(assigned: DataFrame, truth: DataFrame, s_m: int = 2) -> DataFrame:
    return prf(quality_pairs(assigned, truth, s_m))


def quality_by_size(assigned: DataFrame, truth: DataFrame, sizes: Sequence[int]) -> DataFrame:
    """:func:`quality` by least size of a cluster, with s_m: clusters meet the truth once for all sizes, and pairs are summed by size."""
    joined = assigned.join(truth.select("rec_id", "entity_id"), "rec_id")
    both = joined.groupBy("block", "cluster_id", "cluster_size", "entity_id").agg(F.count(F.lit(1)).alias("c"))
    found = both.groupBy("block", "cluster_id", "cluster_size").agg(F.sum("c").alias("n"), F.sum(F.col("c") * (F.col("c") - 1) / 2).alias("t"))
    found = found.groupBy(F.col("cluster_size").alias("size")).agg(F.sum("t").cast("long").alias("tm"), _pairs(F.col("n")).alias("pairs"), F.lit(0).cast("long").alias("true_pairs"))
    held = truth.groupBy("entity_id").agg(F.count(F.lit(1)).alias("n"))
    held = held.groupBy(F.col("n").alias("size")).agg(F.lit(0).cast("long").alias("tm"), F.lit(0).cast("long").alias("pairs"), _pairs(F.col("n")).alias("true_pairs"))
    none = assigned.sparkSession.createDataFrame([(k, 0, 0, 0) for k in sizes], "size long, tm long, pairs long, true_pairs long")  # where there are none
    reached = F.filter(F.array(*map(F.lit, sizes)), lambda k: k <= F.col("size"))
    rows = found.union(held).union(none).select(F.explode(reached).alias("s_m"), "tm", "pairs", "true_pairs")
    rows = rows.groupBy("s_m").agg(*(F.sum(c).alias(c) for c in ("tm", "pairs", "true_pairs")))
    return prf(rows.select("s_m", "tm", (F.col("pairs") - F.col("tm")).alias("fm"), F.greatest(F.lit(0), F.col("true_pairs") - F.col("tm")).alias("fn")))


def quality_clusters(assigned: DataFrame, truth: DataFrame, s_m: int = 2) -> DataFrame:
    """Clusters that are an entity's records exactly, over found clusters and over true sets of at least ``s_m``."""
    c = assigned.where(F.col("cluster_size") >= s_m).join(truth.select("rec_id", "entity_id"), "rec_id")
    whole = truth.groupBy("entity_id").agg(F.count(F.lit(1)).alias("size"))
    per = c.groupBy("block", "cluster_id").agg(F.count(F.lit(1)).alias("n"), F.min("entity_id").alias("entity_id"), F.max("entity_id").alias("other"))
    hit = per.join(whole, "entity_id").where("entity_id = other and n = size")
    a = per.agg(F.count(F.lit(1)).alias("found"))
    b = hit.agg(F.count(F.lit(1)).alias("exact"))
    t = whole.where(F.col("size") >= s_m).agg(F.count(F.lit(1)).alias("true_sets"))
    return a.crossJoin(b).crossJoin(t)  # one row each


def truth_by_subset(truth: DataFrame) -> DataFrame:
    """Entities and true pairs by number of parties: held, entities, pairs."""
    n = truth.groupBy("entity_id").agg(F.count(F.lit(1)).alias("held"))
    return n.groupBy("held").agg(F.count(F.lit(1)).alias("entities"), (F.count(F.lit(1)) * F.col("held") * (F.col("held") - 1) / 2).cast("long").alias("pairs"))


def comparisons_bound(masked: DataFrame) -> DataFrame:
    """Record comparisons between parties inside blocks, and the worst-case formula p (p - 1) / 2 * n * n / b with means n and b."""
    per = masked.groupBy("block", "party").agg(F.count(F.lit(1)).alias("n"))
    block = per.groupBy("block").agg(F.sum("n").alias("s"), F.sum(F.col("n") * F.col("n")).alias("q"))
    made = block.agg(F.sum((F.col("s") * F.col("s") - F.col("q")) / 2).cast("long").alias("comparisons"), F.count(F.lit(1)).alias("b"))
    parties = masked.groupBy("party").agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)).alias("p"), F.max("n").alias("n"))
    return made.crossJoin(parties)  # one row each


def linkage_costs(masked: DataFrame) -> DataFrame:
    """One row of what a linkage costs by count: parties, records, blocks, the largest block, record comparisons, messages of masked
    records and block keys to the unit, bytes of masks, and bytes of all similarities of the largest block."""
    per = masked.groupBy("block", "party").agg(F.count(F.lit(1)).alias("n"), F.max(F.size("words")).alias("w"))
    block = per.groupBy("block").agg(F.sum("n").alias("s"), F.sum(F.col("n") * F.col("n")).alias("q"), F.count(F.lit(1)).alias("k"), F.max("w").alias("w"))
    inside = (F.col("s") * F.col("s") - F.col("q")) / 2
    out = block.agg(
        F.sum("s").alias("records"), F.count(F.lit(1)).alias("blocks"), F.max("s").alias("largest_block"), F.sum(inside).cast("long").alias("comparisons"),
        F.sum("k").alias("block_messages"), F.sum(F.col("s") * F.col("w") * 8).alias("mask_bytes"), (F.max(inside) * 8).cast("long").alias("largest_block_bytes"),
    )
    return out.select("records", "blocks", "largest_block", "comparisons", "block_messages", F.col("records").alias("record_messages"), "mask_bytes", "largest_block_bytes")


def communication(records: DataFrame, parties: list[int]) -> DataFrame:
    """Messages by number of parties that hold these records (with block) each: p * b block keys, p * n masked records, participants + 1 for each secure sum."""
    counted = records.groupBy("block").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("b"))
    rows = counted.select("n", "b", F.explode(F.array(*map(F.lit, parties))).alias("p"))
    return rows.select("p", (F.col("p") * F.col("b")).alias("block_messages"), (F.col("p") * F.col("n")).alias("record_messages"), (F.col("p") + 1).cast("long").alias("sum_messages"), F.col("p").cast("long").alias("sum_messages_stated"))


def cbf_memory(held: DataFrame, length: int) -> DataFrame:
    """Bits of the counting filters of all entities (held: p, one row an entity) by number of parties: l * ceil(log2 p) each, and l * ceil(log2 (p + 1)), which also holds the count p."""
    rows = held.groupBy("p").agg(F.count(F.lit(1)).alias("entities"))
    bits = lambda n: (F.ceil(F.log2(n)) * length * F.col("entities")).cast("long")
    return rows.select(F.col("p").cast("int").alias("p"), "entities", bits(F.col("p")).alias("stated_bits"), bits(F.col("p") + 1).alias("safe_bits"))
