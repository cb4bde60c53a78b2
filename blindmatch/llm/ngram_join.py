"""Jaccard join of word shingles with count-vector R-trees.

A text's set is its distinct ``SHINGLE``-word shingles. Two texts link when 100 * overlap >= ``PERCENT`` * union.

1. Equal sets are one class, met by their size and two sums over their shingles; the rest works on one representative a class.
2. Cells. In any fixed order of all shingles, linked sets share one of the first n - ceil(PERCENT * n / 100) + 1 of
   either, so a set is routed to the cells of those. The order is by length in bytes, longest first, then by hash:
   long shingles have long words, which are rare, so few sets meet by chance. Cells with one member go (an
   aggregation); the others are the only places where links can be.
3. R-trees. Each set's shingles are hashed into ``GROUPS`` groups, and the groups' counts are its point. A cell's points are
   packed into an R-tree whose nodes hold coordinate-wise maxima. The sum of coordinate-wise minima of two points
   bounds their overlap, and the same sum with a node's maxima bounds that with every point below it, which prunes
   the search, as do the smallest and largest set below a node. Counts are bytes; two that are both full say nothing. The search grows groups: what a member reaches is taken out, so a cell with m similar members costs
   about m steps and gives m - 1 links, not all pairs.
4. Coarse counts say little of long sets, so candidate groups (components of those links) with sets of more than ``FULL_LOAD``
   shingles a group are searched again by R-trees of finer counts, ``FULL_LOAD`` shingles a group or fewer whatever the length;
   counts of twice as many groups fold into those of a shorter set.
5. Candidate groups are verified with the exact sets, again growing groups, so that every
   link between members of different groups is found and no copy is expanded into pairs.
6. Components of the verified links, joined back to all documents.

No step gathers an unbounded group. Cells of more than ``CELL_ROWS`` members, and candidate groups of more than
``GROUP_SHINGLES`` shingles, are first cut into bands of size, as linked sets differ by at most one band, and what is too
large still is cut into blocks by hash, each pair of blocks being a group of its own. Both are exact; the price, quadratic in
the number of blocks, falls only on cells with many different members of about one size. What verification holds at once is bounded
by ``2 * GROUP_SHINGLES`` shingles and the longest text.

Shingles compare by a 64-bit hash of their words' hashes: equality is that of hashes, not of words.

Defined cases: null and empty texts, and texts without words, have an empty set and link with nothing; texts of
fewer than ``SHINGLE`` words are one shingle; ids name texts (rows that repeat an id repeat its text, and each is
returned); rows with a null id come back with a null component; extra columns are not read; an empty table gives
an empty table.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blindmatch.llm import storage
from blindmatch.llm.components import connected_components
from blindmatch.llm.words import Words, chunks, lean, lower_ascii, mix, signed

SHINGLE = 4
PERCENT = 85
GROUPS = 128
CELL_ROWS = 16_384
GROUP_SHINGLES = 1 << 20
#: Shingles a group in the finer counts, and their bytes that one group of a search has.
FULL_LOAD = 16
FINE_BYTES = 4 << 20
LEAF, FAN = 32, 16
_FULL = np.uint8(255)


def shingle_sets(words: Words, k: int = SHINGLE, longest_first: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of a chunk, by document, then ascending or longest first; and ``first`` of each document among them."""
    hashes = words.hashes(lower_ascii(words.data))
    doc = words.doc()
    grams, inside = words.windows(hashes, k)
    until = np.concatenate([[0], np.cumsum(words.end - words.start)])
    length = (until[k:] - until[:-k])[inside] if len(grams) else np.zeros(0, np.int64)
    size = np.diff(words.first)
    short = np.flatnonzero((size > 0) & (size < k))
    values, owners, lengths = [grams[inside]], [doc[: len(grams)][inside]], [length]
    for j in range(1, k):  # whole texts of j words
        own = short[size[short] == j]
        if len(own):
            h = np.full(len(own), np.uint64(j))
            for i in range(j):
                h = mix(h * np.uint64(0xD6E8FEB86659FD93) + hashes[words.first[own] + i])
            values.append(h)
            owners.append(own)
            lengths.append(np.zeros(len(own), np.int64))
    value, owner = np.concatenate(values), np.concatenate(owners)
    order = np.lexsort((value, -np.concatenate(lengths), owner) if longest_first else (value, owner))
    value, owner = value[order], owner[order]
    keep = np.ones(len(value), bool)
    keep[1:] = (value[1:] != value[:-1]) | (owner[1:] != owner[:-1])
    value, owner = value[keep], owner[keep]
    return value, np.searchsorted(owner, np.arange(words.n_docs + 1))


def links(overlap, n_a, n_b, percent: int = PERCENT):
    """Whether that overlap of sets of those sizes is a link; with an upper bound of the overlap, whether it can be."""
    return (100 + percent) * overlap >= percent * (n_a + n_b)


# -- R-tree --------------------------------------------------------------------------------------------


class RTree:
    """A packed R-tree of count vectors: leaves of ``LEAF`` points in order of size and of the widest coordinates."""

    def __init__(self, points: np.ndarray, sizes: np.ndarray):
        spread = np.argsort(-points.astype(np.float32).var(axis=0), kind="stable")[:2]
        slab = np.argsort(np.argsort(sizes, kind="stable"), kind="stable") // (LEAF * FAN)
        self.order = np.lexsort((points[:, spread[1]], points[:, spread[0]], slab))
        self.points, self.sizes = points[self.order], sizes[self.order]
        self.levels = []
        high, small, large = self.points, self.sizes, self.sizes
        step = LEAF
        while len(high) > 1:
            cuts = np.arange(0, len(high), step)
            high, small, large = np.maximum.reduceat(high, cuts, axis=0), np.minimum.reduceat(small, cuts), np.maximum.reduceat(large, cuts)
            self.levels.append((high, small, large, step))
            step = FAN

    def search(self, point: np.ndarray, size: int, alive: np.ndarray, percent: int) -> np.ndarray:
        """Positions (in tree order) of points that are alive and may link with this one."""
        full = np.flatnonzero(point == _FULL)

        def may_link(nodes, high, small, large):
            nodes = nodes[(100 * large[nodes] >= percent * size) & (100 * size >= percent * small[nodes])]
            near = high[nodes]
            ok = links(np.minimum(near, point).sum(axis=1, dtype=np.int64), size, small[nodes], percent)
            return nodes[ok | (near[:, full] == _FULL).any(axis=1)] if len(full) else nodes[ok]

        nodes = np.zeros(1, np.int64) if self.levels else np.arange(len(self.points))
        for depth in range(len(self.levels) - 1, -1, -1):
            high, small, large, step = self.levels[depth]
            nodes = may_link(nodes, high, small, large)
            below = len(self.levels[depth - 1][0]) if depth else len(self.points)
            nodes = (nodes[:, None] * step + np.arange(step)).ravel()
            nodes = nodes[nodes < below]
        return may_link(nodes[alive[nodes]], self.points, self.sizes, self.sizes)


def grow_groups(n: int, reach) -> np.ndarray:
    """Group number of each of n members; ``reach(i, alive)`` gives members alive that i links with."""
    group, alive = np.full(n, -1), np.ones(n, bool)
    for seed in range(n):
        if not alive[seed]:
            continue
        alive[seed] = False
        group[seed] = seed
        queue = [seed]
        while queue:
            near = reach(queue.pop(), alive)
            if len(near):
                alive[near] = False
                group[near] = seed
                queue.extend(near.tolist())
    return group


def _stars(ids: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Links from each member to its group's smallest id."""
    order = np.lexsort((ids, group))
    g, i = group[order], ids[order]
    head = np.ones(len(g), bool)
    head[1:] = g[1:] != g[:-1]
    root = i[np.maximum.accumulate(np.where(head, np.arange(len(g)), 0))]
    return i[~head], root[~head]


def _small_cells(starts: np.ndarray, sizes: np.ndarray, ids, counts, points, percent):
    """All pairs of cells of up to 16 members at once: those that may link."""
    u, v = [], []
    for m in np.unique(sizes):
        at = starts[sizes == m]
        a, b = np.triu_indices(m, 1)
        for low in range(0, len(at), 20_000):
            left, right = (at[low : low + 20_000, None] + a).ravel(), (at[low : low + 20_000, None] + b).ravel()
            for cut in range(0, len(left), 100_000):
                i, j = left[cut : cut + 100_000], right[cut : cut + 100_000]
                sized = 100 * np.minimum(counts[i], counts[j]) >= percent * np.maximum(counts[i], counts[j])
                i, j = i[sized], j[sized]
                p, q = points[i], points[j]
                ok = links(np.minimum(p, q).sum(axis=1, dtype=np.int64), counts[i], counts[j], percent) | ((p == _FULL) & (q == _FULL)).any(axis=1)
                u.append(ids[i[ok]])
                v.append(ids[j[ok]])
    return u, v


def _cell_links(percent: int):
    """Links that the bound allows, from rows in order of their cell: (cell, band, low block, high block, id, n, point)."""

    def emit(keys, ids, counts, points) -> pa.RecordBatch:
        change = np.ones(len(ids), bool)
        change[1:] = (keys[1:] != keys[:-1]).any(axis=1)
        starts = np.flatnonzero(change)
        sizes = np.diff(np.append(starts, len(ids)))
        small = (sizes > 1) & (sizes <= 16)
        u, v = _small_cells(starts[small], sizes[small], ids, counts, points, percent)
        for s, m in zip(starts[sizes > 16].tolist(), sizes[sizes > 16].tolist()):
            tree = RTree(points[s : s + m], counts[s : s + m])
            group = grow_groups(m, lambda i, alive, t=tree: t.search(t.points[i], t.sizes[i], alive, percent))
            a, b = _stars(ids[s : s + m][tree.order], group)
            u.append(a)
            v.append(b)
        a, b = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (u, v))
        pairs = np.unique(np.stack([np.maximum(a, b), np.minimum(a, b)], axis=1), axis=0)
        return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["u", "v"])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            keys = np.stack([batch.column(i).to_numpy() for i in range(4)], axis=1)
            ids, counts = batch.column(4).to_numpy(), batch.column(5).to_numpy()
            points = np.frombuffer(b"".join(batch.column(6).to_pylist()), np.uint8).reshape(-1, GROUPS)
            part = (keys, ids, counts, points)
            held = part if held is None else tuple(np.concatenate(x) for x in zip(held, part))
            last = np.flatnonzero((held[0] != held[0][-1]).any(axis=1))
            done = int(last[-1]) + 1 if len(last) else 0
            if done > 1:
                yield emit(*(x[:done] for x in held))
                held = tuple(x[done:] for x in held)
        if held is not None:
            yield emit(*held)

    return lean(rows)


def _spans(start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All positions of spans one after another, and where each begins among them."""
    at = np.cumsum(size) - size
    return np.arange(int(size.sum())) + np.repeat(start - at, size), at


class ExactSets:
    """Sets of one candidate group, searched for exact links by lists of the sets' rarest shingles.

    In the order of the number of sets alive that have a shingle, linked sets share one of the first
    n - ceil(percent * n / 100) + 1 of either. Lists are made anew whenever half of the sets in them are gone.
    """

    def __init__(self, sets: list[np.ndarray], percent: int):
        self.percent = percent
        self.size = np.array([len(s) for s in sets], np.int64)
        self.flat = np.unique(np.concatenate(sets), return_inverse=True)[1].astype(np.int32)
        self.cuts = np.cumsum(self.size) - self.size
        self.head = self.size - (percent * self.size + 99) // 100 + 1
        self.mark = np.zeros(int(self.flat.max()) + 1, bool)
        self.listed = 2 * len(sets) + 2

    def _list(self, alive: np.ndarray) -> None:
        live = np.flatnonzero(alive)
        self.listed = len(live)
        shingles = self.flat[_spans(self.cuts[live], self.size[live])[0]]
        count = np.bincount(shingles, minlength=len(self.mark))
        self.rank = np.empty(len(count), np.int64)
        self.rank[np.argsort(count, kind="stable")] = np.arange(len(count))
        key = np.repeat(live, self.size[live]) * len(count) + self.rank[shingles]
        key.sort()
        place = np.arange(len(key)) - np.repeat(np.cumsum(self.size[live]) - self.size[live], self.size[live])
        own, rank = np.divmod(key[place < np.repeat(self.head[live], self.size[live])], len(count))
        order = np.argsort(rank, kind="stable")
        self.ranks, self.owners = rank[order], own[order]

    def reach(self, i: int, alive: np.ndarray) -> np.ndarray:
        """Members alive that link with member i."""
        if 2 * np.count_nonzero(alive) < self.listed:
            self._list(alive)
        mine = self.flat[self.cuts[i] : self.cuts[i] + self.size[i]]
        rare = np.sort(self.rank[mine])[: self.head[i]]
        low = np.searchsorted(self.ranks, rare)
        near = self.owners[_spans(low, np.searchsorted(self.ranks, rare, "right") - low)[0]]
        near = np.unique(near[alive[near]])
        size, n = self.size[near], self.size[i]
        near = near[100 * np.minimum(size, n) >= self.percent * np.maximum(size, n)]
        if not len(near):
            return near
        at, first = _spans(self.cuts[near], self.size[near])
        self.mark[mine] = True
        overlap = np.add.reduceat(self.mark[self.flat[at]], first, dtype=np.int64)
        self.mark[mine] = False
        return near[links(overlap, n, self.size[near], self.percent)]


def fine_level(size: np.ndarray) -> np.ndarray:
    """How often the number of groups is doubled for sets of these sizes."""
    load = np.maximum(size, 1) / (FULL_LOAD * GROUPS)
    return np.ceil(np.log2(np.maximum(load, 1))).astype(np.int64)


def folded(point: np.ndarray, level: int) -> np.ndarray:
    """Counts of more groups as counts of ``GROUPS << level``; what is full stays full."""
    return np.minimum(point.reshape(-1, GROUPS << level).sum(axis=0, dtype=np.int64), 255).astype(np.uint8)


def _fine_links(percent: int):
    """Links that finer counts allow within one candidate group: component, band, low, high, id, n, fine."""

    def rows(table: pa.Table) -> pa.Table:
        order = np.argsort(table["id"].to_numpy(), kind="stable")
        ids, size = table["id"].to_numpy()[order], table["n"].to_numpy()[order]
        points = [np.frombuffer(x.as_buffer(), np.uint8) for x in table["fine"]]
        points = [points[i] for i in order]
        level = np.array([(len(p) // GROUPS).bit_length() - 1 for p in points])
        trees = []
        # Sets that link are of one level or of neighbouring ones, and meet in the tree of the lower.
        for j in sorted(set(level.tolist()) | {x - 1 for x in level.tolist() if x}):
            own = np.flatnonzero((level == j) | (level == j + 1))
            tree = RTree(np.stack([folded(points[i], j) for i in own]), size[own])
            who, place = own[tree.order], np.full(len(ids), -1)
            place[who] = np.arange(len(who))
            trees.append((tree, who, place))

        def reach(i: int, alive: np.ndarray) -> np.ndarray:
            found = [who[tree.search(tree.points[place[i]], size[i], alive[who], percent)] for tree, who, place in trees if place[i] >= 0]
            return np.unique(np.concatenate(found))

        u, v = _stars(ids, grow_groups(len(ids), reach))
        return pa.table({"u": pa.array(u, pa.int64()), "v": pa.array(v, pa.int64())})

    return rows


def _verified_links(percent: int, k: int):
    def rows(table: pa.Table) -> pa.Table:
        ids, sets = table["id"].to_numpy(), []
        for column in table["text"].chunks:
            for _, _, words in chunks(column):
                value, first = shingle_sets(words, k)
                sets += [value[a:b] for a, b in zip(first, first[1:])]
        order = np.argsort(ids, kind="stable")
        u, v = _stars(ids[order], grow_groups(len(ids), ExactSets([sets[i] for i in order], percent).reach))
        return pa.table({"u": pa.array(u, pa.int64()), "v": pa.array(v, pa.int64())})

    return rows


# -- documents -----------------------------------------------------------------------------------------


def _digests(k: int):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low, high, words in chunks(batch.column(1)):
                value, first = shingle_sets(words, k)
                size = np.diff(first)
                sums = np.concatenate([np.zeros((2, 1), np.uint64), np.cumsum(np.stack([mix(value + np.uint64(1)), mix(value ^ np.uint64(1 << 33))]), axis=1)], axis=1)
                d1, d2 = sums[:, first[1:]] - sums[:, first[:-1]]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(low, high - low), pa.array(size.astype(np.int64)), pa.array(signed(d1.copy())), pa.array(signed(d2.copy()))], ["id", "n", "d1", "d2"]
                )

    return lean(rows)


def _cell_rows(percent: int, k: int):
    """Per representative: one row with its point and finer point (cell null), and one row for each of its cells."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for low, high, words in chunks(batch.column(1)):
                value, first = shingle_sets(words, k, longest_first=True)
                size = np.diff(first)
                owner = np.repeat(np.arange(high - low), size)
                place = np.arange(len(value)) - np.repeat(first[:-1], size)
                cell = place < (size - (percent * size + 99) // 100 + 1)[owner]
                counts = np.bincount(owner * GROUPS + (mix(value) % np.uint64(GROUPS)).astype(np.int64), minlength=(high - low) * GROUPS)
                points = np.minimum(counts, 255).astype(np.uint8).tobytes()
                n = int(cell.sum())
                fine = []
                for i, level in enumerate(fine_level(size).tolist()):
                    own = (mix(value[first[i] : first[i + 1]]) % np.uint64(GROUPS << level)).astype(np.int64) if level else None
                    fine.append(None if own is None else np.minimum(np.bincount(own, minlength=GROUPS << level), 255).astype(np.uint8).tobytes())
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.concatenate([ids[low:high], ids[low:high][owner[cell]]])),
                        pa.array(np.concatenate([np.zeros(high - low, np.int64), signed(value[cell])]), mask=np.arange(high - low + n) < high - low),
                        pa.array([points[i * GROUPS : (i + 1) * GROUPS] for i in range(high - low)] + [None] * n, pa.binary()),
                        pa.array(np.concatenate([size, size[owner[cell]]]).astype(np.int64)),
                        pa.array(fine + [None] * n, pa.binary()),
                    ],
                    ["id", "cell", "point", "n", "fine"],
                )

    return lean(rows)


def _bands(percent: int):
    """The two band groups of a set of ``n`` shingles: a group has the sets of two neighbouring bands of size, and sets that link are in one of them."""
    band = F.floor(F.log(F.col("n").cast("double")) / (1.01 * math.log(100 / percent))).cast("int")
    return F.array(band - 1, band)


def _dealt(rows: DataFrame, key: str, weight, hot: DataFrame, limit: int, percent: int) -> DataFrame:
    """A row for every group that a row is compared in: adds band, low and high. Rows are in one group each, but those of the keys of
    ``hot``, which alone are dealt over their band groups and, where these are above ``limit`` in weight, pairs of blocks."""
    one = lambda df: df.select("*", F.lit(-1).alias("band"), F.lit(0).alias("low"), F.lit(0).alias("high"))
    hot = storage.written(hot.select(key), "hot")
    if hot.isEmpty():
        return one(rows)
    names = rows.columns
    banded = rows.join(hot, key, "left_semi").select(*names, weight.alias("_w"), F.explode(_bands(percent)).alias("band"))
    blocks = banded.groupBy(key, "band").agg(F.ceil(F.sum("_w") / limit).cast("int").alias("_blocks"))
    df = banded.join(blocks, [key, "band"]).withColumn("_own", F.pmod(F.xxhash64("id"), F.col("_blocks")).cast("int"))
    df = df.withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("_blocks") - 1)))
    df = df.select(*names, "band", F.least("_own", "_other").alias("low"), F.greatest("_own", "_other").alias("high"))
    return one(rows.join(hot, key, "left_anti")).union(df)


def link_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = PERCENT, shingle: int = SHINGLE) -> DataFrame:
    """One row per document: id, n_shingles, component_id (smallest id reachable by links, itself included)."""
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    sets = storage.written(texts.mapInArrow(_digests(shingle), "id long, n long, d1 long, d2 long"), "sets")
    classes = sets.where("n > 0 and id is not null").groupBy("n", "d1", "d2").agg(F.min("id").alias("rep"))
    classes = storage.written(classes, "classes")
    reps = classes.select(F.col("rep").alias("id"))

    first_of_id = texts.where("id is not null and text is not null").join(reps, "id", "left_semi").dropDuplicates(["id"])
    cells = storage.written(first_of_id.mapInArrow(_cell_rows(percent, shingle), "id long, cell long, point binary, n long, fine binary"), "cells")
    routed = cells.where("cell is not null").select("cell", "id", "n")
    busy = storage.written(routed.groupBy("cell").agg(F.count(F.lit(1)).alias("m")).where("m > 1"), "busy")
    points = cells.where("cell is null").select("id", "point")
    hot = busy.where(F.col("m") > CELL_ROWS)
    members = _dealt(routed.join(busy.select("cell"), "cell"), "cell", F.lit(1), hot, CELL_ROWS, percent).join(points, "id")
    parts = members.sparkSession.conf.get("spark.sql.shuffle.partitions")
    at = ["cell", "band", "low", "high"]
    members = members.select(*at, "id", "n", "point").repartition(int(parts), *at).sortWithinPartitions(*at)
    may_link = members.mapInArrow(_cell_links(percent), "u long, v long")
    groups = storage.written(connected_components(may_link), "groups")
    points = cells.where("cell is null").select("id", "n", F.coalesce("fine", "point").alias("fine"))
    sized = groups.join(points.select("id", "n"), groups["node"] == F.col("id")).select("component", "id", "n")
    grouped = storage.written(sized, "grouped")
    # Groups with sets that are long for the coarse counts are cut by the finer ones.
    long = grouped.groupBy("component").agg(F.max("n").alias("top"), F.sum("n").alias("w")).where(F.col("top") > FULL_LOAD * GROUPS)
    long = storage.written(long, "long")
    if not long.isEmpty():
        weight, large = F.col("n") / (FULL_LOAD / 2), long.where(F.col("w") / (FULL_LOAD / 2) > FINE_BYTES)
        asked = _dealt(grouped.join(long.select("component"), "component"), "component", weight, large, FINE_BYTES, percent)
        asked = asked.select(*at[1:], "component", "id").join(points, "id").groupBy("component", *at[1:])
        finer = connected_components(asked.applyInArrow(_fine_links(percent), "u long, v long"))
        finer = finer.join(points.select("id", "n"), finer["node"] == F.col("id")).select("component", "id", "n")
        before, grouped = grouped, storage.written(grouped.join(long, "component", "left_anti").union(finer), "grouped")
        storage.forget(docs.sparkSession, before)
    for table in (cells, busy, groups, long):
        storage.forget(docs.sparkSession, table)
    large = grouped.groupBy("component").agg(F.sum("n").alias("w")).where(F.col("w") > GROUP_SHINGLES)
    grouped = _dealt(grouped, "component", F.col("n"), large, GROUP_SHINGLES, percent)
    asked = grouped.join(first_of_id, "id").select("component", "band", "low", "high", "id", "text")
    verified = asked.groupBy("component", "band", "low", "high").applyInArrow(_verified_links(percent, shingle), "u long, v long")
    found = connected_components(verified)

    named = classes.join(found, classes["rep"] == found["node"], "left").select("n", "d1", "d2", F.coalesce("component", "rep").alias("component_id"))
    out = sets.join(named, ["n", "d1", "d2"], "left")
    component = F.when(F.col("id").isNotNull(), F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("id")))
    return out.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), component.alias("component_id"))


def keep_one_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """The rows of ``docs`` without those that link, directly or not, with a smaller id."""
    found = link_documents(docs, id_col, text_col, **how)
    gone = found.where(F.col(id_col) > F.col("component_id")).select(F.col(id_col).alias("_gone"))
    return docs.join(gone, docs[id_col] == gone["_gone"], "left_anti")
