"""One-to-one mappings on edge tables: block, x, y, weight, and place where x is ordered by (place, x) and not by itself.

A block of up to ``TASK_EDGES`` edges is solved in one task. In larger ones, parts in which one side has a single vertex are solved
by an aggregate, and the others go to the solver part by part, so a task gets connected parts, not blocks.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blindmatch.operators.components import components
from blindmatch.operators.kernels import (
    _hungarian, best_mapping, best_partners, dense_parts, greedy_mapping, greedy_masks, heaviest_mapping, heaviest_masks, packed_words,
)
from blindmatch.plans.lineage import cut
from blindmatch.sources.tables import spread

#: Edges of a block that one task takes.
TASK_EDGES = 4_000_000
EDGE = "block string, x long, y long, weight double"


PAIR = "block string, x long, y long, z long, total long"


@dataclass(frozen=True)
class CloseEdges:
    """Edges of the masks of two sides that are never held as a table by those mappings that can do without: ``masked`` has block, side (0, 1),
    rec_id and words, edges are pairs of a block of a Dice of at least ``least``, and ``table`` gives them as rows."""

    masked: DataFrame
    least: float
    tiles: Callable[[DataFrame], DataFrame]
    table: Callable[[], DataFrame]

    def weighted(self, pairs: DataFrame) -> DataFrame:
        """block, x, y, weight of rows of :data:`PAIR`."""
        weight = F.round(2 * F.col("z") / F.col("total"), 9)
        return pairs.select("block", "x", "y", weight.alias("weight")).where(F.col("weight") >= self.least)

    def mapped(self, mapping) -> DataFrame:
        """A mapping of masks block by block."""
        # Blocks differ in their work by the square of their size, so tasks are many.
        parts = 16 * self.masked.sparkSession.sparkContext.defaultParallelism
        pairs = self.masked.repartition(parts, "block").groupBy("block").applyInArrow(_of_masks(mapping, self.least), PAIR)
        return self.weighted(pairs)


def _sides(table: pa.Table):
    """Ids and masks of both sides, in the order of the ids."""
    table = table.sort_by("rec_id")
    side, ids, words = table["side"].to_numpy(), table["rec_id"].to_numpy(), packed_words(table["words"])
    return tuple((ids[side == k], words[side == k]) for k in (0, 1))


def _pairs(table: pa.Table, a, u, b, v) -> pa.Table:
    z = np.bitwise_count(u & v).sum(axis=1, dtype=np.int64)
    total = np.bitwise_count(u).sum(axis=1, dtype=np.int64) + np.bitwise_count(v).sum(axis=1, dtype=np.int64)
    return pa.table({"block": table["block"].take(pa.array(np.zeros(len(a), np.int64))), "x": a, "y": b, "z": z, "total": total})


def _of_masks(mapping, least: float):
    def run(table: pa.Table) -> pa.Table:
        (a, u), (b, v) = _sides(table)
        i, j = mapping(u, v, least)
        return _pairs(table, a[i], u[i], b[j], v[j])

    return run


def _by_size(edges: DataFrame, in_task, schema: str, in_rounds, most: int) -> DataFrame:
    """Blocks of up to ``most`` edges by ``in_task`` (a function of one block's table), the others by ``in_rounds`` (of an edge table)."""
    edges = cut(edges, "edges")
    large = cut(edges.groupBy("block").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > most).select("block"), "large-blocks")

    def tasks(e: DataFrame) -> DataFrame:
        return spread(e, "block").groupBy("block").applyInArrow(in_task, schema)

    if large.isEmpty():
        return tasks(edges)
    return tasks(edges.join(large, "block", "left_anti")).union(in_rounds(edges.join(large, "block", "left_semi")))


def edge_parts(edges: DataFrame) -> DataFrame:
    """Adds part: the smallest x of the edge's connected part."""
    edges = cut(edges, "edges")
    node = lambda side, key: F.struct(F.col("block"), F.lit(side).alias("side"), F.col(key).alias("id"))
    parts = components(edges.select(node(0, "x").alias("u"), node(1, "y").alias("v"))).where("node.side = 0")
    parts = parts.select(F.col("node.block").alias("block"), F.col("node.id").alias("x"), F.col("component.id").alias("part"))
    return edges.join(parts, ["block", "x"]).select(*edges.columns, "part")


def _placed(edges: DataFrame) -> DataFrame:
    place = F.col("place") if "place" in edges.columns else F.lit(0)
    return edges.where("weight > 0").select("block", "x", "y", "weight", place.cast("int").alias("place"))


def _solve(mapping):
    def solve(table: pa.Table) -> pa.Table:
        table = table.sort_by([("place", "ascending"), ("x", "ascending"), ("y", "ascending")])
        x, place = table["x"].to_numpy(), table["place"].to_numpy()
        # Numbers of the left vertices in their order.
        left = np.cumsum(np.r_[False, (x[1:] != x[:-1]) | (place[1:] != place[:-1])])
        taken = mapping(left, table["y"].to_numpy(), table["weight"].to_numpy())
        return table.take(pa.array(taken)).select(["block", "x", "y", "weight"])

    return solve


def assign_optimal(edges: DataFrame | CloseEdges, task_edges: int = TASK_EDGES) -> DataFrame:
    """A mapping of the greatest total weight; edges of weight 0 or less are none."""
    if isinstance(edges, CloseEdges):
        edges = edges.table()
    return _by_size(_placed(edges), _solve(best_mapping), EDGE, _optimal_parts, task_edges)


def _optimal_parts(edges: DataFrame) -> DataFrame:
    parts = edge_parts(edges)
    sides = parts.groupBy("block", "part").agg(F.min("x").alias("x0"), F.max("x").alias("x1"), F.min("y").alias("y0"), F.max("y").alias("y1"))
    parts = parts.join(sides, ["block", "part"]).withColumn("star", (F.col("x0") == F.col("x1")) | (F.col("y0") == F.col("y1")))
    best = F.min_by(F.struct("x", "y", "weight"), F.struct(-F.col("weight"), "place", "x", "y")).alias("e")
    stars = parts.where("star").groupBy("block", "part").agg(best).select("block", "e.x", "e.y", "e.weight")
    rest = parts.where("not star").select("block", "part", "x", "y", "weight", "place").groupBy("block", "part").applyInArrow(_solve(best_mapping), EDGE)
    return stars.union(rest)


def assign_greedy(edges: DataFrame | CloseEdges, task_edges: int = TASK_EDGES) -> DataFrame:
    """x in order of its key takes its best free y."""
    if isinstance(edges, CloseEdges):
        return edges.mapped(greedy_masks)
    return _by_size(_placed(edges), _solve(greedy_mapping), EDGE, lambda e: edge_parts(e).groupBy("block", "part").applyInArrow(_solve(greedy_mapping), EDGE), task_edges)


def assign_best_first(edges: DataFrame | CloseEdges, task_edges: int = TASK_EDGES) -> DataFrame:
    """The heaviest free edge first (ties by x, then y); in large blocks by rounds that take all edges that are best on both sides."""
    if isinstance(edges, CloseEdges):
        return edges.mapped(heaviest_masks)
    return _by_size(_placed(edges), _solve(heaviest_mapping), EDGE, _best_first_rounds, task_edges)


def _best_first_rounds(left: DataFrame, most_rounds: int = 100) -> DataFrame:
    left = cut(left, "edges")
    taken = left.limit(0)
    order = [F.desc("weight"), "place", "x", "y"]
    for _ in range(most_rounds):
        rx = F.row_number().over(Window.partitionBy("block", "x").orderBy(*order))
        ry = F.row_number().over(Window.partitionBy("block", "y").orderBy(*order))
        both = cut(left.withColumn("rx", rx).withColumn("ry", ry).where("rx = 1 and ry = 1").drop("rx", "ry"), "taken")
        if not both.limit(1).count():
            return taken.select("block", "x", "y", "weight")
        taken = taken.union(both)
        left = left.join(both.select("block", "x").distinct(), ["block", "x"], "left_anti").join(both.select("block", "y").distinct(), ["block", "y"], "left_anti")
        left = cut(left.select("block", "x", "y", "weight", "place"), "edges")
    raise RuntimeError("mapping did not settle")


def assign_best_link(edges: DataFrame | CloseEdges) -> DataFrame:
    """Each y goes to its best x; an x may get several."""
    if isinstance(edges, CloseEdges):
        least = edges.least

        def link(table: pa.Table) -> pa.Table:
            (a, u), (b, v) = _sides(table)
            best = best_partners(u, v, least)[0]
            some = np.flatnonzero(best >= 0)
            return _pairs(table, a[best[some]], u[best[some]], b[some], v[some])

        # A tile gives the best of its own records only.
        edges = edges.weighted(edges.tiles(edges.masked).applyInArrow(link, PAIR))
    best = F.min_by(F.struct("x", "weight"), F.struct(-F.col("weight"), "x")).alias("e")
    return edges.where("weight > 0").groupBy("block", "y").agg(best).select("block", "e.x", "y", "e.weight")


def left_vertices(edges: DataFrame | CloseEdges) -> DataFrame:
    """block, x of the vertices with an edge."""
    if isinstance(edges, CloseEdges):
        least = edges.least

        def linked(table: pa.Table) -> pa.Table:
            (a, u), (_, v) = _sides(table)
            own = a[best_partners(u, v, least)[1]]
            return pa.table({"block": table["block"].take(pa.array(np.zeros(len(own), np.int64))), "x": own})

        edges = edges.tiles(edges.masked).applyInArrow(linked, "block string, x long")
    return edges.select("block", "x").distinct()


def unmatched(vertices: DataFrame, mapping: DataFrame, key: str) -> DataFrame:
    """Vertices of one side (block, key) without a partner."""
    return vertices.join(mapping.select("block", key), ["block", key], "left_anti")


def certify(edges: DataFrame | CloseEdges, task_edges: int = TASK_EDGES) -> DataFrame:
    """Per connected part: primal and dual totals of the optimal mapping, and the worst violation of u + v >= weight.

    Equal totals with no violation prove the mapping optimal without enumeration.
    """
    if isinstance(edges, CloseEdges):
        edges = edges.table()

    def prove(table: pa.Table) -> pa.Table:
        x, y, w = (table[c].to_numpy() for c in ("x", "y", "weight"))
        out = []
        for edges, dense, _ in dense_parts(x, y, w):
            pairs, u, v = _hungarian(dense)
            gap = float((u[:, None] + v[None, :] - dense)[dense > 0].min())
            out.append((int(x[edges].min()), float(sum(dense[p] for p in pairs)), float(u.sum() + v.sum()), min(gap, float(u.min()), float(v.min()))))
        part, primal, dual, slack = zip(*out)
        return pa.table({"block": table["block"].slice(0, 1).take(pa.array([0] * len(out))), "part": part, "primal": primal, "dual": dual, "slack": slack})

    schema = "block string, part long, primal double, dual double, slack double"
    in_rounds = lambda e: edge_parts(e).groupBy("block", "part").applyInArrow(prove, schema)
    return _by_size(edges.where("weight > 0").select("block", "x", "y", "weight"), prove, schema, in_rounds, task_edges)
