"""Connected components of link tables of any key type, in a logarithmic number of rounds on written tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blindmatch.plans.lineage import cut


def _low_first(edges: DataFrame) -> DataFrame:
    return edges.where("u <> v").select(F.least("u", "v").alias("v"), F.greatest("u", "v").alias("u")).distinct()


def _stars(edges: DataFrame, only_lower: bool) -> DataFrame:
    """Each node's neighbours (or, with ``only_lower``, its lower ones and itself) hang on the lowest of them."""
    if only_lower:
        lowest = edges.groupBy("u").agg(F.min("v").alias("root"))
        hung = edges.join(lowest, "u").where("v <> root").select(F.col("v").alias("u"), F.col("root").alias("v"))
        return _low_first(hung.unionByName(lowest.select("u", F.col("root").alias("v"))))
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    lowest = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("root"))
    return _low_first(both.join(lowest, "u").where("v > u").select(F.col("v").alias("u"), F.col("root").alias("v")))


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """``edges``: u, v of one orderable type. Gives node, component: the lowest node of its component, for every node with a link to another.

    Alternating stars over all neighbours and over lower ones halve paths, so a chain of n nodes settles in about log n rounds; minima
    are partial aggregates before they are shuffled."""
    edges, before = cut(_low_first(edges), "links"), None
    for _ in range(most_rounds):
        edges = cut(_stars(_stars(edges, False), True), "links")
        now = tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == before:
            roots = edges.select("v").distinct().select(F.col("v").alias("node"), F.col("v").alias("component"))
            return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots)
        before = now
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")
