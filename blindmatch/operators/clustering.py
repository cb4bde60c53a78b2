"""Clustering of masked records, one party after the other.

Masked records have block, party, rec_id, words and ones. Blocks are independent, so a block that fits a task is
clustered in one task after a single shuffle (``mode='block'``); larger ones go through rounds of joins
(``mode='distributed'``). ``mode='auto'`` routes by the blocks' counted sizes.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blindmatch.functions.blocking import party_order
from blindmatch.functions.masks import LENGTH, GramFilters, common_ones, encode_bf, encode_custom, tokens_of
from blindmatch.operators import kernels
from blindmatch.operators.assignment import assign_best_first, assign_greedy, assign_optimal
from blindmatch.operators.components import components
from blindmatch.operators.measures import found_pairs
from blindmatch.plans.lineage import cut
from blindmatch.sources.tables import spread

#: Records of a block that one task of early mapping takes; it holds similarities of ``kernels.HELD_MASKS`` different masks, and beyond, of close ones only.
TASK_RECORDS = 250_000
#: Records of a block of late mapping whose task holds the similarities of a part that close pairs link.
PART_RECORDS = 32_000
#: Records of a block of late mapping whose task holds all similarities of the block.
LATE_RECORDS = 4_000
#: Records of small blocks that a task of early mapping clusters together, and records that are sent to it at once.
BUNDLE_RECORDS, BUCKET_RECORDS = 1_000, 30_000
OUT = "block string, cluster_id long, party int, rec_id long, cluster_size int"


def _block_arrays(table: pa.Table):
    """Party, record ids and words of a block, in order of (party, record)."""
    table = table.sort_by([("party", "ascending"), ("rec_id", "ascending")])
    words = np.array(table["words"].to_pylist(), np.int64).view(np.uint64).reshape(table.num_rows, -1)
    return table["party"].to_numpy(), table["rec_id"].to_numpy(), words, table["block"][0].as_py()


def _assignments(block, party, rec, label) -> pa.Table:
    """``block``: one name, or a name a record."""
    seeds, inverse, size = np.unique(label, return_inverse=True, return_counts=True)
    return pa.table(
        {
            "block": pa.array([block] * len(rec)) if isinstance(block, str) or block is None else block,
            "cluster_id": rec[label].astype(np.int64),
            "party": party.astype(np.int32),
            "rec_id": rec.astype(np.int64),
            "cluster_size": size[inverse].astype(np.int32),
        }
    )


def _bundles(table: pa.Table):
    """Each large block of a task's records, and small ones together: rows in order of (block, party, record), and the number of each row's block
    (none where there is one). Blocks of a bundle never meet, and the order within a block is kept, so clusters are those of each block alone."""
    table = table.sort_by([("block", "ascending"), ("party", "ascending"), ("rec_id", "ascending")])
    number = table["block"].combine_chunks().dictionary_encode(null_encoding="encode").indices.to_numpy()
    starts = np.flatnonzero(np.r_[True, number[1:] != number[:-1]]).tolist()
    low = 0
    for start, end in zip(starts, [*starts[1:], len(number)]):
        if end - low >= BUNDLE_RECORDS or end == len(number):
            if start > low and end - low > BUNDLE_RECORDS:
                yield table.slice(low, start - low), _groups(number[low:start])
                low = start
            if end - low >= BUNDLE_RECORDS or end == len(number):
                yield table.slice(low, end - low), _groups(number[low:end])
                low = end


def _groups(number: np.ndarray) -> np.ndarray | None:
    return None if (number == number[0]).all() else number


def _early(order, s_t, how, mapping):
    def run(table: pa.Table) -> pa.Table:
        out = []
        for bundle, group in _bundles(table):
            party, rec, words = bundle["party"].to_numpy(), bundle["rec_id"].to_numpy(), kernels.packed_words(bundle["words"])
            sim = None if how == "cbf" else kernels.similarities(words, group)
            out.append(_assignments(bundle["block"].combine_chunks(), party, rec, kernels.early_block(party, order, sim, s_t, how, mapping, words, group=group)))
        return pa.concat_tables(out)

    return run


def _in_buckets(rows: DataFrame, n: int, run, schema: str) -> DataFrame:
    """``run`` on tables of whole blocks: blocks are dealt by their hash over buckets of about ``BUCKET_RECORDS`` of all ``n`` records, eight a core at least."""
    buckets = max(8 * rows.sparkSession.sparkContext.defaultParallelism, -(-n // BUCKET_RECORDS))
    bucket = F.pmod(F.xxhash64("block"), F.lit(buckets)).alias("bucket")
    return rows.select(bucket, "*").repartition(buckets, "bucket").groupBy("bucket").applyInArrow(run, schema)


def _by_task(rows: DataFrame, task_records: int) -> tuple[int, DataFrame | None]:
    """Number of records, and blocks of more than ``task_records``, if any."""
    sizes = cut(rows.groupBy("block").agg(F.count(F.lit(1)).alias("n")), "block-sizes")
    n, most = sizes.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.max("n"), F.lit(0))).first()
    return n, sizes.where(F.col("n") > task_records).select("block") if most > task_records else None


def _late(order, s_t, how, merge, leftover, rethreshold, most):
    def run(table: pa.Table) -> pa.Table:
        party, rec, words, block = _block_arrays(table)
        try:
            found = kernels.late_block(party, order, kernels.dice_matrix(words, words), s_t, how, merge, leftover, rethreshold, most, words)
        except kernels.BlockTooLarge as e:
            raise kernels.BlockTooLarge(f"block {block}: {e}; use finer blocks, merge='absorb' or a larger limit") from None
        label = np.zeros(len(rec), np.int64)
        for c in found:
            seed = min(c, key=lambda x: (order.index(party[x]), x))
            label[list(c)] = seed
        return _assignments(block, party, rec, label)

    return run


def _late_by_parts(order, s_t, how, leftover, rethreshold):
    """The same for whole blocks of a task, where a part that close pairs link is clustered by itself."""

    def run(table: pa.Table) -> pa.Table:
        out = []
        for bundle, group in _bundles(table):
            party, words = bundle["party"].to_numpy(), kernels.packed_words(bundle["words"])
            place = np.array([order.index(p) for p in party.tolist()])
            label = np.empty(len(party), np.int64)
            for c in kernels.late_parts(party, order, kernels.similarities(words, group), s_t, how, (leftover,), rethreshold)[0]:
                own = list(c)
                label[own] = own[int(place[own].argmin())]
            out.append(_assignments(bundle["block"].combine_chunks(), party, bundle["rec_id"].to_numpy(), label))
        return pa.concat_tables(out)

    return run


def _order(masked: DataFrame, ord) -> list[int]:
    return list(ord) if isinstance(ord, (list, tuple)) else party_order(masked, ord)


def cluster_early(masked: DataFrame, s_t: float = 0.8, ord="size", cluster_sim: str = "average", mapping: str = "optimal", mode: str = "auto", task_records: int = TASK_RECORDS) -> DataFrame:
    """Early mapping: each arriving party is mapped one-to-one onto the clusters before the next. With ``mapping='greedy'``, the greedy baseline."""
    order = _order(masked, ord)
    rows = masked.select("block", "party", "rec_id", "words")
    if mode == "distributed":
        return _early_rounds(rows, order, s_t, cluster_sim, mapping)
    n, large = _by_task(rows, task_records)
    in_tasks = lambda df: _in_buckets(df, n, _early(order, s_t, cluster_sim, mapping), OUT)
    if mode == "block" or large is None:
        return in_tasks(rows)
    return in_tasks(rows.join(large, "block", "left_anti")).union(_early_rounds(rows.join(large, "block", "left_semi"), order, s_t, cluster_sim, mapping))


def _pair_scores(members: DataFrame, new: DataFrame, how: str) -> DataFrame:
    """Edges of arrivals and clusters by the similarities of their pairs of records."""
    score = {"average": F.round(F.avg("s"), kernels.DIGITS), "min": F.min("s"), "max": F.max("s")}[how]
    a, b = members.alias("a"), new.alias("b")
    z = common_ones(F.col("a.words"), F.col("b.words"))
    total = F.col("a.ones") + F.col("b.ones")
    pairs = a.join(b, F.col("a.block") == F.col("b.block")).select(
        F.col("a.block").alias("block"), F.col("a.cluster_id").alias("x"), F.col("a.seed_place").alias("place"), F.col("b.rec_id").alias("y"), F.when(total > 0, 2 * z / total).otherwise(0.0).alias("s")
    )
    return pairs.groupBy("block", "x", "place", "y").agg(score.alias("weight"))


def _group_scores(members: DataFrame, new: DataFrame, how: str) -> DataFrame:
    """Edges by Dice of a cluster's counting filter with the arrival added: a cluster is its common words, its ones and its size."""
    both = F.array(*(F.bit_and(F.col("words")[i]) for i in range((LENGTH + 63) // 64)))
    clusters = members.groupBy("block", "cluster_id", "seed_place").agg(both.alias("words"), F.sum("ones").alias("ones"), F.count(F.lit(1)).alias("n"))
    a, b = clusters.alias("a"), new.alias("b")
    total = F.col("a.ones") + F.col("b.ones")
    dice = (F.col("a.n") + 1) * common_ones(F.col("a.words"), F.col("b.words")) / total
    return a.join(b, F.col("a.block") == F.col("b.block")).select(
        F.col("a.block").alias("block"), F.col("a.cluster_id").alias("x"), F.col("a.seed_place").alias("place"), F.col("b.rec_id").alias("y"), F.when(total > 0, F.round(dice, kernels.DIGITS)).otherwise(0.0).alias("weight")
    )


def cluster_early_resalted(remask, ord, s_t: float = 0.8, mapping: str = "optimal") -> DataFrame:
    """Early mapping on counting filters with a new encoding in each round: ``remask(i)`` gives the masked records of round i."""
    return _early_rounds(remask(0).select("block", "party", "rec_id", "words"), list(ord), s_t, "cbf", mapping, remask)


def cluster_early_reencoded(people: DataFrame, attrs, ord, s_t: float = 0.8, mapping: str = "optimal", salt: str = "round {}:", task_records: int = TASK_RECORDS) -> DataFrame:
    """The same where round i encodes the record-level filters of ``attrs`` with ``salt`` and i: a block's records are shuffled once, and encoded
    in its task for each round. ``people`` has block, party, rec_id and the attributes, and should be a written table."""
    order, rows = list(ord), people.select("block", "party", "rec_id", *attrs)
    n, large = _by_task(rows, task_records)

    def run(table: pa.Table) -> pa.Table:
        makers, out = [GramFilters(salt=salt.format(i)) for i in range(len(order))], []
        for bundle, group in _bundles(table):
            party, rec = bundle["party"].to_numpy(), bundle["rec_id"].to_numpy()
            values = [bundle[a].to_pylist() for a in attrs]
            label = kernels.early_block(party, order, None, s_t, "cbf", mapping, lambda i: makers[i](values, attrs), group=group)
            out.append(_assignments(bundle["block"].combine_chunks(), party, rec, label))
        return pa.concat_tables(out)

    if large is None:
        return _in_buckets(rows, n, run, OUT)
    rest = cut(rows.join(large, "block", "left_semi"), "large")
    remask = lambda i: encode_bf(rest, attrs, salt=salt.format(i), keep=("block", "party", "rec_id"))
    return _in_buckets(rows.join(large, "block", "left_anti"), n, run, OUT).union(cluster_early_resalted(remask, order, s_t, mapping))


def early_pair_counts(masked: DataFrame, thresholds, ord="size", cluster_sim: str = "average", mapping: str = "optimal", task_records: int = TASK_RECORDS) -> DataFrame:
    """threshold, tm, pairs: record pairs within clusters of early mapping by threshold, and those of one entity. ``masked`` has entity_id too.
    A block is shuffled once and its similarities are computed once for all thresholds; each threshold has a clustering of its own."""
    order, rows = _order(masked, ord), masked.select("block", "party", "rec_id", "words", "entity_id")
    n, large = _by_task(rows, task_records)
    twos = lambda sizes: int((sizes * (sizes - 1) // 2).sum())

    def run(table: pa.Table) -> pa.Table:
        counts = np.zeros((len(thresholds), 2), np.int64)
        for bundle, group in _bundles(table):
            party, words, entity = bundle["party"].to_numpy(), kernels.packed_words(bundle["words"]), np.unique(bundle["entity_id"].to_numpy(), return_inverse=True)[1]
            sim = None if cluster_sim == "cbf" else kernels.similarities(words, group)
            for i, s_t in enumerate(thresholds):
                label = kernels.early_block(party, order, sim, s_t, cluster_sim, mapping, words, group=group)
                counts[i] += twos(np.unique(label * len(label) + entity, return_counts=True)[1]), twos(np.bincount(label))
        return pa.table({"threshold": pa.array(thresholds, pa.float64()), "tm": counts[:, 0], "pairs": counts[:, 1]})

    schema = "threshold double, tm long, pairs long"
    if large is None:
        counts = _in_buckets(rows, n, run, schema)
    else:
        counts, rest = _in_buckets(rows.join(large, "block", "left_anti"), n, run, schema), cut(rows.join(large, "block", "left_semi"), "large")
        for s_t in thresholds:
            found = _early_rounds(rest.select("block", "party", "rec_id", "words"), order, s_t, cluster_sim, mapping)
            counts = counts.union(found_pairs(found, rest).select(F.lit(s_t).cast("double"), "tm", "pairs"))
    none = masked.sparkSession.createDataFrame([(float(s_t), 0, 0) for s_t in thresholds], schema)  # where there are no records
    return counts.union(none).groupBy("threshold").agg(F.sum("tm").alias("tm"), F.sum("pairs").alias("pairs"))


#: Ways of mapping by name: early with a mapping, or late with what is done with leftovers.
MAPPED = {"early": ("early", "optimal"), "late": ("late", "drop_subset"), "late_keep": ("late", "keep"), "greedy": ("early", "greedy")}


def mapping_pair_counts(masked: DataFrame, methods=tuple(MAPPED), s_t: float = 0.8, ord="size", cluster_sim: str = "average", task_records: int = PART_RECORDS) -> DataFrame:
    """method, tm, pairs: record pairs within clusters by way of mapping, and those of one entity. ``masked`` has entity_id too. A block is
    shuffled once and its similarities are computed once for all methods. Late mapping has no rounds of joins, so with it a block of more
    than ``task_records`` is an error that names the block."""
    order, rows = _order(masked, ord), masked.select("block", "party", "rec_id", "words", "entity_id")
    n, large = _by_task(rows, task_records)
    leftovers = [how for kind, how in map(MAPPED.get, methods) if kind == "late"]
    if large is not None and leftovers:
        raise kernels.BlockTooLarge(f"block {large.orderBy('block').first().block}: more than {task_records} records; use finer blocks")
    twos = lambda sizes: int((sizes * (sizes - 1) // 2).sum())

    def run(table: pa.Table) -> pa.Table:
        counts = np.zeros((len(methods), 2), np.int64)
        for bundle, group in _bundles(table):
            party, words, entity = bundle["party"].to_numpy(), kernels.packed_words(bundle["words"]), np.unique(bundle["entity_id"].to_numpy(), return_inverse=True)[1]
            sim = kernels.similarities(words, group)
            late = dict(zip(leftovers, kernels.late_parts(party, order, sim, s_t, cluster_sim, leftovers))) if leftovers else {}
            for i, (kind, how) in enumerate(map(MAPPED.get, methods)):
                if kind == "early":
                    label = kernels.early_block(party, order, sim, s_t, cluster_sim, how, words, group=group)
                else:
                    label = np.empty(len(party), np.int64)
                    for c in late[how]:
                        label[list(c)] = c[0]
                counts[i] += twos(np.unique(label * len(label) + entity, return_counts=True)[1]), twos(np.bincount(label))
        return pa.table({"method": pa.array(methods, pa.string()), "tm": counts[:, 0], "pairs": counts[:, 1]})

    schema = "method string, tm long, pairs long"
    if large is None:
        counts = _in_buckets(rows, n, run, schema)
    else:
        counts, rest = _in_buckets(rows.join(large, "block", "left_anti"), n, run, schema), cut(rows.join(large, "block", "left_semi"), "large")
        for name in methods:
            found = _early_rounds(rest.select("block", "party", "rec_id", "words"), order, s_t, cluster_sim, MAPPED[name][1])
            counts = counts.union(found_pairs(found, rest).select(F.lit(name), "tm", "pairs"))
    none = masked.sparkSession.createDataFrame([(name, 0, 0) for name in methods], schema)  # where there are no records
    return counts.union(none).groupBy("method").agg(F.sum("tm").alias("tm"), F.sum("pairs").alias("pairs"))


def _early_rounds(rows: DataFrame, order: list[int], s_t: float, how: str, mapping: str, remask=None) -> DataFrame:
    """The same by joins: a round scores arrivals against members by block, maps, and writes the clusters. With ``remask``, a round compares its own encoding of all records."""
    solve = {"optimal": assign_optimal, "greedy": assign_greedy, "best_first": assign_best_first}[mapping]
    place = F.element_at(F.map_from_arrays(F.array(*map(F.lit, order)), F.array(*map(F.lit, range(len(order))))), F.col("party"))
    rows = rows.withColumn("ones", common_ones(F.col("words"), F.col("words"))).withColumn("place", place)
    members = rows.where("place = 0").withColumn("cluster_id", F.col("rec_id")).withColumn("seed_place", F.lit(0))
    for i in range(1, len(order)):
        new = rows.where(F.col("place") == i)
        # Clusters are scanned by the place of their seeds, then by seed, as they are within a task.
        sides = [members, new]
        if remask:
            fresh = remask(i).select("rec_id", "words", "ones")
            sides = [x.drop("words", "ones").join(fresh, "rec_id") for x in sides]
        edges = (_group_scores if how == "cbf" else _pair_scores)(*sides, how).where(F.col("weight") >= s_t)
        seeds = members.select("block", F.col("cluster_id").alias("found"), "seed_place").distinct()
        taken = solve(edges).select("block", F.col("y").alias("rec_id"), F.col("x").alias("found"))
        taken = taken.join(seeds.withColumnRenamed("seed_place", "found_place"), ["block", "found"])
        arrived = new.join(taken, ["block", "rec_id"], "left").withColumn("cluster_id", F.coalesce("found", "rec_id"))
        members = cut(members.union(arrived.withColumn("seed_place", F.coalesce("found_place", F.lit(i))).select(*members.columns)), "clusters")
    size = members.groupBy("block", "cluster_id").agg(F.count(F.lit(1)).cast("int").alias("cluster_size"))
    return members.join(size, ["block", "cluster_id"]).select("block", "cluster_id", "party", "rec_id", "cluster_size")


def cluster_late(
    masked: DataFrame, s_t: float = 0.8, ord="size", cluster_sim: str = "average", merge: str = "per_edge", leftover: str = "drop_subset", rethreshold: bool = False, max_clusters_per_block: int | None = None, max_records_per_block: int | None = None
) -> DataFrame:
    """Late mapping: overlapping clusters over all parties first, then split, map and merge party by party.

    A block whose records exceed their limit, or whose overlapping clusters exceed ``max_clusters_per_block`` where one is given, stops the
    run with an error that names it; none is truncated.
    Records are counted before any similarity is computed. A task holds the similarities of a part that close pairs link, and without a limit
    of records a block may have ``PART_RECORDS``; with ``absorb``, counting filters or a limit of clusters it holds those of its block, of ``LATE_RECORDS`` at most.
    """
    order = _order(masked, ord)
    rows = masked.select("block", "party", "rec_id", "words")
    by_parts = merge == "per_edge" and cluster_sim != "cbf" and max_clusters_per_block is None
    most = max_records_per_block if max_records_per_block is not None else PART_RECORDS if by_parts else LATE_RECORDS
    sizes = cut(rows.groupBy("block").agg(F.count(F.lit(1)).alias("n")), "block-sizes")
    large = sizes.where(F.col("n") > most).orderBy(F.desc("n"), "block").first()
    if large:
        raise kernels.BlockTooLarge(f"block {large.block}: {large.n} records; the limit is {most}, use finer blocks")
    if by_parts:
        n = sizes.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        return _in_buckets(rows, n, _late_by_parts(order, s_t, cluster_sim, leftover, rethreshold), OUT)
    return spread(rows, "block").groupBy("block").applyInArrow(_late(order, s_t, cluster_sim, merge, leftover, rethreshold, max_clusters_per_block), OUT)


def clear_grams(people: DataFrame, attrs, keep=("block", "party", "rec_id"), most: int = 20_000) -> DataFrame:
    """Sets of grams themselves as packed words, one position for each gram that occurs, so nothing collides and any clustering runs on
    clear text. The grams' number is bounded by the alphabet; more than ``most`` is an error."""
    people = people.withColumn("_grams", tokens_of(attrs))
    grams = sorted(r[0] for r in people.select(F.explode("_grams").alias("g")).distinct().limit(most + 1).collect())
    if len(grams) > most:
        raise ValueError(f"more than {most} different grams")
    place = F.create_map(*(F.lit(x) for i, g in enumerate(grams, 1) for x in (g, i)))
    return encode_custom(people, F.array_sort(F.transform("_grams", lambda g: F.element_at(place, g))), len(grams), keep=keep)


def matches(assignments: DataFrame, s_m: int = 2) -> DataFrame:
    """Clusters of at least ``s_m`` members; with all parties as ``s_m``, entities that every party holds."""
    return assignments.where(F.col("cluster_size") >= s_m)


def extend(assignments: DataFrame, masked: DataFrame, new_party: int, s_t: float = 0.8, cluster_sim: str = "average", mapping: str = "optimal") -> DataFrame:
    """One more party for stored clusters; earlier rounds are not repeated. ``masked`` has the records of the clusters and of the new party."""

    def run(key, clusters: pa.Table, records: pa.Table) -> pa.Table:
        party, rec, words, block = _block_arrays(records)
        known = dict(zip(clusters["rec_id"].to_pylist(), clusters["cluster_id"].to_pylist()))
        by_seed: dict[int, list[int]] = {}
        for i in np.flatnonzero(party != new_party).tolist():
            by_seed.setdefault(known[rec[i]], []).append(i)
        index = {r: i for i, r in enumerate(rec.tolist())}
        label = np.arange(len(rec))
        for seed, m in by_seed.items():
            label[m] = index[seed]
        arrivals = np.flatnonzero(party == new_party)
        if by_seed and len(arrivals):
            seeds = sorted(by_seed, key=lambda s: index[s])
            flat = np.concatenate([np.array(by_seed[s]) for s in seeds])
            starts = np.cumsum([0, *(len(by_seed[s]) for s in seeds[:-1])])
            scores = kernels.cluster_scores(kernels.dice_matrix(words[arrivals], words[flat]), starts, cluster_sim)
            r, c = np.nonzero(scores >= s_t)
            for e in kernels.MAPPINGS[mapping](c, r, scores[r, c]):
                label[arrivals[r[e]]] = index[seeds[c[e]]]
        return _assignments(block, party, rec, label)

    return assignments.groupBy("block").cogroup(masked.select("block", "party", "rec_id", "words").groupBy("block")).applyInArrow(run, OUT)


def cluster_components(masked: DataFrame, s_t: float = 0.8) -> DataFrame:
    """The naive extension of two-party linkage: all pairs between parties of a block at ``s_t`` or more, and their components."""
    m = masked.select("block", "party", "rec_id", "words").withColumn("ones", common_ones(F.col("words"), F.col("words")))
    a, b = m.alias("a"), m.alias("b")
    z, total = common_ones(F.col("a.words"), F.col("b.words")), F.col("a.ones") + F.col("b.ones")
    # The length filter is implied by the threshold and cheaper than the common ones.
    pairs = a.join(b, (F.col("a.block") == F.col("b.block")) & (F.col("a.party") < F.col("b.party")))
    pairs = pairs.where(F.least("a.ones", "b.ones") * (2 - s_t) >= F.greatest("a.ones", "b.ones") * s_t).where((total > 0) & (2 * z / total >= s_t))
    pairs = pairs.select(F.col("a.block").alias("block"), F.col("a.rec_id").alias("u"), F.col("b.rec_id").alias("v"))
    node = lambda c: F.struct("block", F.col(c).alias("rec_id"))
    found = components(pairs.select(node("u").alias("u"), node("v").alias("v")))
    found = found.select("node.block", "node.rec_id", F.col("component.rec_id").alias("low"))
    label = m.select("block", "party", "rec_id").join(found, ["block", "rec_id"], "left").withColumn("cluster_id", F.coalesce("low", "rec_id")).drop("low")
    size = label.groupBy("block", "cluster_id").agg(F.count(F.lit(1)).cast("int").alias("cluster_size"))
    return label.join(size, ["block", "cluster_id"]).select("block", "cluster_id", "party", "rec_id", "cluster_size")


def split(clusters: DataFrame, party: int) -> DataFrame:
    """One party's records out of all clusters: unique singletons and unique remainders. ``clusters``: block, members (array of party, rec_id)."""
    own = F.filter("members", lambda m: m["party"] == party)
    rest = F.filter("members", lambda m: m["party"] != party)
    singles = clusters.select("block", F.explode(own).alias("m")).select("block", F.array("m").alias("members"))
    return singles.union(clusters.select("block", rest.alias("members")).where(F.size("members") > 0)).distinct()


def reveal(found: DataFrame, parties: DataFrame, cols: list[str]) -> DataFrame:
    """Agreed attributes of matched records only."""
    return found.select("cluster_id", "party", "rec_id").join(parties.select("party", "rec_id", *cols), ["party", "rec_id"])
