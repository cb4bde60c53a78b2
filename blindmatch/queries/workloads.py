"""The experiment workloads as tables that queries share, and their SQL."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, GroupedData, SparkSession
from pyspark.sql import functions as F

from blindmatch.functions import blocking, masks
from blindmatch.operators import kernels
from blindmatch.sources import roster as R
from blindmatch.sources.tables import spread

QI = R.QI


def parties(spark: SparkSession, sf_dir: str, p: int = 3, rate: int = 0, profile: str = "quarter") -> DataFrame:
    """W1 (quarter) or W2 (by_size), with W3's corruption at ``rate`` percent."""
    out = R.make_parties(R.roster(spark, sf_dir), p, profile)
    return R.corrupt(out, rate) if rate else out


def masked(people: DataFrame, block: str = "first_last", bits: bool = False, salt: str = "") -> DataFrame:
    """block, party, rec_id, words, ones (bits): record-level filters of the four attributes; the attributes are dropped."""
    return masks.encode_bf(blocking.with_block(people, block), QI, salt=salt, keep=("block", "party", "rec_id"), keep_bits=bits)


def truth(people: DataFrame) -> DataFrame:
    return people.select("party", "rec_id", "entity_id")


def pairs_in_blocks(m: DataFrame) -> DataFrame:
    """All pairs of records of different parties in a block: a_id, b_id, z, a_ones, b_ones."""
    m = spread(m, "block")
    a, b = m.alias("a"), m.alias("b")
    z = masks.common_ones(F.col("a.words"), F.col("b.words"))
    return a.join(b, (F.col("a.block") == F.col("b.block")) & (F.col("a.party") < F.col("b.party"))).select(
        F.col("a.block").alias("block"), F.col("a.rec_id").alias("a_id"), F.col("b.rec_id").alias("b_id"), z.cast("long").alias("z"), F.col("a.ones").alias("a_ones"), F.col("b.ones").alias("b_ones")
    )


def _compared(least: float):
    def compare(t: pa.Table) -> pa.Table:
        side, ids, words = t["side"].to_numpy(), t["rec_id"].to_numpy(), kernels.packed_words(t["words"])
        (a, u), (b, v) = ((ids[side == k], words[side == k]) for k in (0, 1))
        i, j, z = kernels.pairs_at_least(u, v, least - 1e-6)
        ones = [np.bitwise_count(w).sum(axis=1, dtype=np.int32) for w in (u, v)]
        block = t["block"].take(pa.array(np.zeros(len(i), np.int64)))
        return pa.table({"block": block, "a_id": a[i], "b_id": b[j], "z": z, "a_ones": ones[0][i], "b_ones": ones[1][j]})

    return compare


#: Records of a side that one task compares at once.
TILE_RECORDS = 8_192


def two_sides(m: DataFrame, first: int, second: int) -> DataFrame:
    """block, side, rec_id and words of the records of party ``first`` (side 0) and of party ``second`` (1)."""
    return m.where(F.col("party").isin(first, second)).select("block", (F.col("party") == second).cast("int").alias("side"), "rec_id", "words")


def tiles(m: DataFrame, tile: int = TILE_RECORDS) -> GroupedData:
    """Records of two sides by tile. Blocks are cut into tiles of both sides, all of which are compared, so a large block is many tasks' work."""
    n = m.groupBy("block").agg(*(F.greatest(F.lit(1), F.ceil(F.sum((F.col("side") == i).cast("long")) / tile)).cast("int").alias(f"n{i}") for i in (0, 1)))
    m = m.join(n, "block")
    own, every = (lambda k: F.array(F.pmod(F.xxhash64("rec_id"), F.col(k)).cast("int"))), (lambda k: F.sequence(F.lit(0), F.col(k) - 1))
    for i in (0, 1):
        m = m.withColumn(f"t{i}", F.explode(F.when(F.col("side") == i, own(f"n{i}")).otherwise(every(f"n{i}"))))
    return spread(m.select("block", "t0", "t1", "side", "rec_id", "words"), "block", "t0", "t1").groupBy("block", "t0", "t1")


def close_pairs(m: DataFrame, first: int, second: int, least: float, tile: int = TILE_RECORDS) -> DataFrame:
    """Pairs of a record of party ``first`` and one of party ``second`` in a block by at least ``least`` of Dice (a little less is let
    through), tile by tile: columns of :func:`pairs_in_blocks`."""
    return tiles(two_sides(m, first, second), tile).applyInArrow(_compared(least), "block string, a_id long, b_id long, z long, a_ones int, b_ones int")


def sql_people(p: int = 3, rate: int = 0, profile: str = "quarter") -> tuple[str, str]:
    """CTEs, and the name of the one with the records."""
    ctes = R.sql_parties(p, profile)
    return (f"{ctes},\n{R.sql_corrupt(rate)}", "corrupted") if rate else (ctes, "parties")


SQL_BLOCK = f"{blocking.sql_soundex('first_name')} || '-' || {blocking.sql_soundex('last_name')}"


def sql_masked(p: int = 3, rate: int = 0, extra: str = "entity_id", block: str = SQL_BLOCK) -> str:
    ctes, name = sql_people(p, rate)
    m = masks.sql_masked(name, QI, f"{block} AS block, {extra}", name="listed")
    return f"WITH {ctes},\n{m},\nmasked AS (SELECT *, len(bits) AS ones FROM listed)"


SQL_PAIRS = """pairs AS (
  SELECT a.block, a.rec_id AS a_id, b.rec_id AS b_id, len(list_intersect(a.bits, b.bits)) AS z, a.ones AS a_ones, b.ones AS b_ones, a.entity_id AS ea, b.entity_id AS eb
  FROM masked a JOIN masked b ON a.block = b.block AND a.party < b.party)"""
