"""Blocking keys and block statistics."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from blindmatch.plans.lineage import cut
from blindmatch.sources.tables import spread


def soundex_key(attrs: Sequence[str]) -> Column:
    """Phonetic key of one or more attributes; records with one code share a block."""
    return F.concat_ws("-", *(F.soundex(F.coalesce(F.col(a), F.lit(""))) for a in attrs))


def bucket_key(c: Column, width: float) -> Column:
    return F.floor(c / F.lit(width)).cast("string")


def with_block(df: DataFrame, kind: str = "first_last") -> DataFrame:
    keys = {"last": ["last_name"], "first_last": ["first_name", "last_name"]}
    if kind == "none":
        return df.withColumn("block", F.lit("all"))
    return df.withColumn("block", soundex_key(keys[kind]))


def multi_block(df: DataFrame, keys: Sequence[Column]) -> DataFrame:
    """A row per distinct key of a record: column block, prefixed by the key's number."""
    tagged = F.array(*(F.concat(F.lit(f"{i}:"), k) for i, k in enumerate(keys)))
    return df.withColumn("block", F.explode(F.array_distinct(tagged)))


def block_index(df: DataFrame) -> DataFrame:
    """The union of all parties' blocks: block, n_parties, n."""
    return df.groupBy("block", "party").count().groupBy("block").agg(F.count(F.lit(1)).alias("n_parties"), F.sum("count").alias("n"))


def block_stats(df: DataFrame) -> DataFrame:
    """One row: blocks, largest, candidate pairs between parties, all pairs, reduction ratio."""
    per = df.groupBy("block", "party").agg(F.count(F.lit(1)).alias("n")).groupBy("block").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("sq"))
    parties = df.groupBy("party").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n").alias("tn"), F.sum(F.col("n") * F.col("n")).alias("tsq"))
    got = per.agg(F.count(F.lit(1)).alias("blocks"), F.max("n").alias("largest"), F.sum((F.col("n") * F.col("n") - F.col("sq")) / 2).cast("long").alias("pairs"))
    out = got.crossJoin(parties).withColumn("all_pairs", ((F.col("tn") * F.col("tn") - F.col("tsq")) / 2).cast("long"))  # one row each
    return out.select("blocks", "largest", "pairs", "all_pairs", F.round(1 - F.col("pairs") / F.col("all_pairs"), 6).alias("reduction"))


def pairs_completeness(df: DataFrame) -> DataFrame:
    """True pairs that share a block over all true pairs, by counts and without joining pairs. Needs block and entity_id."""
    inside = df.groupBy("block", "entity_id").agg(F.count(F.lit(1)).alias("n")).agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("found"))
    total = df.groupBy("entity_id").agg(F.count(F.lit(1)).alias("n")).agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("true_pairs"))
    return inside.crossJoin(total).select("found", "true_pairs", F.round(F.col("found") / F.col("true_pairs"), 6).alias("completeness"))


def guard_blocks(df: DataFrame, k_min: int, policy: str = "merge") -> DataFrame:
    """Blocks of fewer than ``k_min`` records are suppressed, or merged under their key's first character, and suppressed if still small."""

    def sized(d: DataFrame) -> DataFrame:
        n = d.groupBy("block").agg(F.count(F.lit(1)).alias("_n"))
        return d.join(n, "block")

    if policy == "merge":
        df = sized(df).withColumn("block", F.when(F.col("_n") < k_min, F.concat(F.substring("block", 1, 1), F.lit("*"))).otherwise(F.col("block"))).drop("_n")
    elif policy != "suppress":
        raise ValueError(f"unknown policy {policy}")
    return sized(df).where(F.col("_n") >= k_min).drop("_n")


def noisy_block_counts(df: DataFrame, epsilon: float, seed: int = 7) -> DataFrame:
    """Block sizes with Laplace noise of scale 1 / epsilon from a seeded digest: block, n, noisy."""
    sizes = df.groupBy("block").agg(F.count(F.lit(1)).alias("n"))
    d = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("block"))), 1, 8), 16, 10).cast("double")
    u = (d + 0.5) / float(16**8) - 0.5
    noise = -F.signum(u) * F.log(1 - 2 * F.abs(u)) / epsilon
    return sizes.select("block", "n", F.greatest(F.lit(0.0), F.round(F.col("n") + noise)).cast("long").alias("noisy"))


#: Nodes whose ones a task holds at once.
HELD_NODES = 4096


def _node_ones(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """block, words to block, pos, c, n: how many of a task's n filters of a node have each position."""
    held: dict[str, np.ndarray] = {}

    def emit() -> pa.RecordBatch:
        counts = np.stack(list(held.values()))
        names = pa.array(list(held)).take(pa.array(np.repeat(np.arange(len(held)), counts.shape[1] - 1)))
        pos = np.tile(np.arange(1, counts.shape[1], dtype=np.int32), len(held))
        held.clear()
        n = np.repeat(counts[:, 0], counts.shape[1] - 1)
        return pa.RecordBatch.from_arrays([names, pa.array(pos), pa.array(counts[:, 1:].ravel()), pa.array(n)], ["block", "pos", "c", "n"])

    for batch in batches:
        if not batch.num_rows:
            continue
        names = batch.column(0).dictionary_encode()
        node, flat = names.indices.to_numpy(), batch.column(1)
        words = np.ascontiguousarray(flat.flatten().to_numpy()).view(np.uint8).reshape(len(flat), -1)
        for i, name in enumerate(names.dictionary.to_pylist()):
            own = words[node == i]
            c = np.concatenate([[len(own)], np.unpackbits(own, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)])
            held[name] = held[name] + c if name in held else c
        if len(held) > HELD_NODES:
            yield emit()
    if held:
        yield emit()


#: Records of a node whose subtree one task splits.
TREE_RECORDS = 16_384


def _subtree(min_size: int, max_size: int, levels: int | None):
    """The leaves of a node's records: splits as :func:`bit_tree` has them, in one task."""

    def run(table: pa.Table) -> pa.Table:
        flat, path = table["words"].combine_chunks(), table["block"][0].as_py()
        words = np.ascontiguousarray(flat.flatten().to_numpy()).view(np.uint8).reshape(len(flat), -1)
        bits = np.unpackbits(words, axis=1, bitorder="little")
        name, nodes = np.empty(len(flat), object), [(np.arange(len(flat)), path)]
        while nodes:
            own, path_ = nodes.pop()
            n, ones = len(own), None
            if n > max_size and (levels is None or len(path_) - len(path) < levels):
                ones = bits[own].sum(axis=0, dtype=np.int64)
                fits = (ones >= min_size) & (n - ones >= min_size)
            if ones is None or not fits.any():
                name[own] = path_
                continue
            side = bits[own, np.where(fits, np.abs(2 * ones - n), n + 1).argmin()] == 1
            nodes += [(own[~side], path_ + "0"), (own[side], path_ + "1")]
        return table.set_column(table.column_names.index("block"), "block", pa.array(name, pa.string()))

    return run


def bit_tree(masked: DataFrame, min_size: int, max_size: int, max_depth: int | None = None, task_records: int = TREE_RECORDS) -> DataFrame:
    """Multi-party bit-tree blocks of ``masked`` (with words): all parties' filters are split on the position whose share
    of ones is nearest to one half, until blocks are at most ``max_size``, or a split would leave fewer than ``min_size``.
    There is no limit on levels unless a caller gives ``max_depth``.

    Each level counts ones by node in its tasks, so rows are not exploded, and joins by node; the frontier's nodes are few, and are
    written first so that the join is chosen by their size. Only rows of nodes of more than ``task_records`` go on to another level; a
    smaller node's whole subtree is split in one task.
    """
    least, depth, done = max(1, min_size), 0, []
    rows = cut(masked.drop("bits").withColumn("block", F.lit("r")), "bit-tree")
    own = rows.columns
    while max_depth is None or depth < max_depth:
        ones = rows.select("block", "words").mapInArrow(_node_ones, "block string, pos int, c long, n long")
        ones = ones.groupBy("block", "pos").agg(F.sum("c").alias("c"), F.sum("n").alias("n"))
        split = (F.col("n") > max_size) & (F.col("c") >= least) & (F.col("n") - F.col("c") >= least)
        first = F.min(F.when(split, F.struct(F.abs(F.col("c") * 2 - F.col("n")).alias("off"), "pos")))["pos"]
        nodes = cut(ones.groupBy("block").agg(F.max("n").alias("n"), first.alias("pos")), "splits")
        marked = rows.join(nodes, "block")
        small = marked.where(F.col("n") <= task_records).select(own)
        levels = None if max_depth is None else max_depth - depth
        done.append(spread(small, "block").groupBy("block").applyInArrow(_subtree(least, max_size, levels), small.schema))
        done.append(marked.where((F.col("n") > task_records) & F.col("pos").isNull()).select(own))
        side = F.expr("shiftrightunsigned(element_at(words, cast((pos - 1) div 64 as int) + 1), (pos - 1) % 64) & 1").cast("string")
        rest = (F.col("n") > task_records) & F.col("pos").isNotNull()
        depth += 1
        if nodes.where(rest).isEmpty():
            break
        rows = cut(marked.where(rest).withColumn("block", F.concat("block", side)).select(own), "bit-tree")
    else:
        done.append(rows)
    return cut(reduce(lambda a, b: a.union(b), done), "bit-tree")


def block_risk(df: DataFrame, k: int = 5) -> DataFrame:
    """Exposure to frequency attacks: blocks and records below k, and the smallest block."""
    n = df.groupBy("block").agg(F.count(F.lit(1)).alias("n"))
    return n.agg(F.min("n").alias("smallest"), F.sum((F.col("n") < k).cast("long")).alias("small_blocks"), F.sum(F.when(F.col("n") < k, F.col("n")).otherwise(0)).alias("exposed"))


def party_order(df: DataFrame, ord: str = "size", seed: int = 7, quality_cols: Sequence[str] = ()) -> list[int]:
    """Order of parties: by size (largest first), at random (seeded) or by completeness. One row per party reaches the driver."""
    if ord == "size":
        key = -F.count(F.lit(1))
    elif ord == "random":
        key = F.first(F.md5(F.concat(F.lit(f"{seed}:"), F.col("party").cast("string"))))
    elif ord == "quality":
        filled = sum((F.col(c).isNotNull().cast("int") for c in quality_cols), F.lit(0))
        key = -F.avg(filled)
    else:
        raise ValueError(f"unknown order {ord}")
    rows = df.groupBy("party").agg(key.alias("k")).orderBy("k", "party").collect()
    return [r.party for r in rows]


def ranked_parties(df: DataFrame, key: Column) -> DataFrame:
    return df.groupBy("party").agg(key.alias("k")).select("party", F.row_number().over(Window.orderBy("k", "party")).alias("place"))


def sql_soundex(a: str) -> str:
    """Soundex of a lower-case string as Spark has it: h and w are skipped, other non-consonants separate."""
    rest = f"regexp_replace(regexp_replace(upper({a}), '[^A-Z]', 'A', 'g'), '(.)[HW]+', '\\1', 'g')"
    digits = f"translate({rest}, 'BFPVCGJKQSXZDTLMNRAEIOUYHW', '11112222222233455600000077')"
    runs = digits
    for d in "0123456":
        runs = f"regexp_replace({runs}, '{d}+', '{d}', 'g')"
    tail = f"replace(substr({runs}, 2), '0', '')"
    return f"CASE WHEN regexp_matches({a}, '^[A-Za-z]') THEN upper(substr({a}, 1, 1)) || rpad(substr({tail}, 1, 3), 3, '0') ELSE {a} END"
