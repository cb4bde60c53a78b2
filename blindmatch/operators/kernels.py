"""Array kernels that run inside one task: similarities, one-to-one mappings and clustering of one block."""

from __future__ import annotations

import heapq

import numpy as np

#: Rounding of cluster similarities before a threshold, so that engines agree at its edge.
DIGITS = 12
TILE = 512


class BlockTooLarge(RuntimeError):
    """A block outgrew a stated limit; the caller has to route it elsewhere."""


def common_matrix(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Common ones of all rows of two arrays of packed words, in tiles that stay in a core's cache."""
    out = np.zeros((len(a), len(b)), np.uint16 if 64 * a.shape[1] < 2**16 else np.uint32)
    columns = np.ascontiguousarray(b.T)
    both, count = np.empty((8, 8 * TILE), np.uint64), np.empty((8, 8 * TILE), np.uint8)
    for i in range(0, len(a), 8):
        for j in range(0, len(b), 8 * TILE):
            own = out[i : i + 8, j : j + 8 * TILE]
            x, n = both[: own.shape[0], : own.shape[1]], count[: own.shape[0], : own.shape[1]]
            for w in range(a.shape[1]):
                np.bitwise_and(a[i : i + 8, w][:, None], columns[w, j : j + 8 * TILE], out=x)
                np.bitwise_count(x, out=n)
                np.add(own, n, out=own)
    return out


def dice_matrix(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Dice of all rows of two arrays of packed words, in tiles."""
    ones_a, ones_b = np.bitwise_count(a).sum(axis=1, dtype=np.int64), np.bitwise_count(b).sum(axis=1, dtype=np.int64)
    out, both = np.zeros((len(a), len(b))), common_matrix(a, b)
    for i in range(0, len(a), TILE):
        total = ones_a[i : i + TILE, None] + ones_b[None, :]
        np.divide(2 * both[i : i + TILE].astype(np.int64), total, out=out[i : i + TILE], where=total > 0)
    return out


#: Different masks of a block whose similarities a task holds at once; beyond, they are computed where they are asked for.
HELD_MASKS = 4_096


def similarities(words: np.ndarray, group: np.ndarray | None = None):
    """A function of rows and columns that gives Dice of their records. Records of equal masks share one row of similarities.
    With ``group`` (a number a record), records of different groups have 0."""
    own = np.ascontiguousarray(words)
    _, first, number = np.unique(own.view(np.dtype((np.void, own.itemsize * own.shape[1]))).ravel(), return_index=True, return_inverse=True)
    distinct = own[first]
    held = dice_matrix(distinct, distinct) if len(distinct) <= HELD_MASKS else None

    def sim(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        if held is not None:
            out = held[number[a]][:, number[b]]
        else:
            (u, i), (v, j) = (np.unique(number[x], return_inverse=True) for x in (a, b))
            out = dice_matrix(distinct[u], distinct[v])[i][:, j]
        if group is not None:
            out[group[a][:, None] != group[b]] = 0.0
        return out

    if held is None and group is None:
        sim.masks = distinct, number
    return sim


def _close_masks(a: np.ndarray, b: np.ndarray, least: float) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of all pairs of a Dice of at least ``least``, and some that are a little below it."""
    low_a, low_b = ((0.5 * least * _ones(x) - 0.01).astype(np.float32) for x in (a, b))
    found, step = [], max(1, HELD_PAIRS // max(1, len(b)))
    for i in range(0, len(a), step):
        r, c = np.nonzero(common_matrix(a[i : i + step], b) >= low_a[i : i + step, None] + low_b)
        found.append((r + i, c))
    return tuple(np.concatenate(x) for x in zip(*found))


def packed_words(column) -> np.ndarray:
    """Rows of packed words of a table's list column."""
    flat = column.combine_chunks()
    return np.ascontiguousarray(flat.flatten().to_numpy()).view(np.uint64).reshape(len(flat), -1)


def pairs_at_least(a: np.ndarray, b: np.ndarray, least: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows, columns and common ones of all pairs of a Dice of at least ``least``, tile by tile."""
    ones_a, ones_b = (np.bitwise_count(x).sum(axis=1, dtype=np.int32) for x in (a, b))
    columns = np.ascontiguousarray(b.T)
    found = []
    step = max(1, (TILE * TILE) // max(1, len(b)))
    for i in range(0, len(a), step):
        both = np.zeros((len(a[i : i + step]), len(b)), np.int32)
        for w in range(a.shape[1]):
            both += np.bitwise_count(a[i : i + step, w][:, None] & columns[w][None, :])
        r, c = np.nonzero((2 * both >= least * (ones_a[i : i + step, None] + ones_b[None, :])) & (both > 0))
        found.append((r + i, c, both[r, c].astype(np.int64)))
    return tuple(np.concatenate(x) for x in zip(*found)) if found else (np.zeros(0, np.int64),) * 3


def _dice_rows(a: np.ndarray, b: np.ndarray, ones_a: np.ndarray, ones_b: np.ndarray) -> np.ndarray:
    total = ones_a[:, None] + ones_b
    return np.divide(2 * common_matrix(a, b).astype(np.int32), total, out=np.zeros(total.shape), where=total > 0)


def _ones(a: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a).sum(axis=1, dtype=np.int32)


#: Dice of pairs that a task of masks holds at once.
HELD_PAIRS = 1 << 21
#: Distance of a threshold within which fractions of up to some thousands are equal to it.
NEAR = 1e-9


def best_partners(a: np.ndarray, b: np.ndarray, least: float) -> tuple[np.ndarray, np.ndarray]:
    """Row of ``a`` of the greatest Dice with each row of ``b`` (the first of equal ones; -1: none of at least ``least``), and whether a row
    of ``a`` has a Dice of at least ``least`` with any."""
    ones_a, ones_b = _ones(a), _ones(b)
    best, near = np.full(len(b), -1), np.zeros(len(a), bool)
    step = max(1, HELD_PAIRS // max(1, len(a)))
    for i in range(0, len(b) if len(a) else 0, step):
        dice = _dice_rows(b[i : i + step], a, ones_b[i : i + step], ones_a)
        top = dice.argmax(axis=1)
        some = dice[np.arange(len(top)), top] >= least - NEAR
        best[i : i + step][some] = top[some]
        near |= (dice >= least - NEAR).any(axis=0)
    return best, near


def greedy_masks(a: np.ndarray, b: np.ndarray, least: float) -> tuple[np.ndarray, np.ndarray]:
    """:func:`greedy_mapping` of rows of masks by Dice of at least ``least``, whose edges are computed some rows at a time and not held."""
    ones_a, ones_b, live = _ones(a), _ones(b), np.arange(len(b))
    rows, cols, i = [], [], 0
    while i < len(a) and len(live):
        step = min(TILE, max(1, HELD_PAIRS // len(live)))
        dice = _dice_rows(a[i : i + step], b[live], ones_a[i : i + step], ones_b[live])
        free = np.ones(len(live), bool)
        for k, own in enumerate(dice):
            j = int(own.argmax())
            if own[j] >= least - NEAR:
                rows.append(i + k)
                cols.append(int(live[j]))
                free[j], dice[k + 1 :, j] = False, -1.0
        live, i = live[free], i + step
    return np.array(rows, np.int64), np.array(cols, np.int64)


#: Partners that a row keeps while edges are taken by weight.
KEPT_PARTNERS = 64


def heaviest_masks(a: np.ndarray, b: np.ndarray, least: float, kept: int = KEPT_PARTNERS) -> tuple[np.ndarray, np.ndarray]:
    """:func:`heaviest_mapping` of rows of masks by Dice of at least ``least``. A row holds its first ``kept`` free partners; where these are
    all taken, its edges to what is free by then are computed anew."""
    ones_a, ones_b = _ones(a), _ones(b)
    free, live, words, ones = np.ones(len(b), bool), np.arange(len(b)), b, ones_b

    def first(dice: np.ndarray, whose: np.ndarray):
        """The first partners of a row, last one first, and whether they are all it has."""
        low = max(least - NEAR, np.partition(dice, len(dice) - kept)[len(dice) - kept]) if len(dice) > kept else least - NEAR
        some = np.flatnonzero(dice >= low)
        order = some[np.lexsort((some, -dice[some]))[:kept]]
        return list(zip((-dice[order]).tolist(), whose[order].tolist()))[::-1], len(order) < kept

    held, heap = {}, []
    step = min(TILE, max(1, HELD_PAIRS // max(1, len(b))))
    for i in range(0, len(a) if len(b) else 0, step):
        for k, own in enumerate(_dice_rows(a[i : i + step], b, ones_a[i : i + step], ones_b), i):
            found = first(own, live)
            if found[0]:
                held[k] = found
                w, y = found[0].pop()
                heap.append((w, k, y))
    heapq.heapify(heap)
    rows, cols, left = [], [], len(b)
    while heap and left:
        w, x, y = heapq.heappop(heap)
        if free[y]:
            rows.append(x)
            cols.append(y)
            free[y], left = False, left - 1
            del held[x]
            continue
        partners, whole = held[x]
        while partners and not free[partners[-1][1]]:
            partners.pop()
        if not partners and not whole:
            if 4 * left < 3 * len(live):
                live = np.flatnonzero(free)
                words, ones = b[live], ones_b[live]
            dice = _dice_rows(a[x : x + 1], words, ones_a[x : x + 1], ones)[0]
            dice[~free[live]] = -1.0
            partners, whole = held[x] = first(dice, live)
        if partners:
            w, y = partners.pop()
            heapq.heappush(heap, (w, x, y))
        else:
            del held[x]
    return np.array(rows, np.int64), np.array(cols, np.int64)


# -- mappings ------------------------------------------------------------------------------------------


def _numbered(x: np.ndarray) -> tuple[np.ndarray, int]:
    """Numbers of the values in their order, and how many there are."""
    if len(x) and (x.dtype.kind not in "iu" or x.min() < 0 or x.max() > 8 * len(x) + 1024):
        values, number = np.unique(x, return_inverse=True)
        return number, len(values)
    seen = np.zeros(int(x.max()) + 1 if len(x) else 0, bool)
    seen[x] = True
    place = np.cumsum(seen) - 1
    return place[x], int(seen.sum())


def _parts(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Component of each edge of a bipartite graph."""
    (i, rows), (j, cols) = _numbered(left), _numbered(right)
    root = np.arange(rows + cols)
    _link(root, i, j + rows)
    return _numbered(root[i])[0]


def _link(root: np.ndarray, i: np.ndarray, j: np.ndarray) -> None:
    """Give the ends of all edges one root, which is the smallest of what they link; ``root`` has roots of its own before and after."""
    while True:
        x, y = root[i], root[j]
        differ = x != y
        if not differ.any():
            return
        x, y = x[differ], y[differ]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while True:
            above = root[root]
            if (above == root).all():
                break
            root[:] = above


def _hungarian(weight: np.ndarray) -> tuple[list[tuple[int, int]], np.ndarray, np.ndarray]:
    """Maximum-weight matching of a dense part (0: no edge), with potentials u + v >= weight, all non-negative.

    Rows first take their heaviest free column, then outbid each other while that lowers no total, and the rest are placed by shortest
    augmenting paths on cost -weight. A row may stay unmatched at cost 0.
    """
    n, m = weight.shape
    cost = np.where(weight > 0, -weight, np.inf)
    best = cost.argmin(axis=1)
    u, v = np.minimum(cost[np.arange(n), best], 0.0), np.zeros(m)
    row_of = np.full(m, -1)
    some = np.flatnonzero(u < 0)
    taken, first = np.unique(best[some], return_index=True)
    row_of[taken] = some[first]
    free = np.setdiff1d(some, row_of[taken])[::-1].tolist()
    later: list[int] = []
    for _ in range(4 * n):
        if not free:
            break
        row = free.pop()
        reduced = cost[row] - v
        j = int(reduced.argmin())
        low = reduced[j]
        if low >= 0:
            u[row] = 0.0
            continue
        reduced[j] = np.inf
        second = min(float(reduced.min()), 0.0)
        before = int(row_of[j])
        if before >= 0 and second - low < 1e-12:
            later.append(row)
            continue
        v[j] -= second - low
        u[row], row_of[j] = second, row
        if before >= 0:
            free.append(before)
    for i in later + free:
        dist, prev, done = np.full(m, np.inf), np.full(m, -1), np.zeros(m, bool)
        open_dist = dist.copy()
        row, shift, last = i, 0.0, -1
        alone, alone_at = np.inf, -1
        while True:
            if shift - u[row] < alone:
                alone, alone_at = shift - u[row], last
            reach = cost[row] - v
            reach += shift - u[row]
            better = reach < open_dist - 1e-15
            better &= ~done
            np.copyto(dist, reach, where=better)
            np.copyto(open_dist, reach, where=better)
            prev[better] = last
            near = int(open_dist.argmin())
            if alone <= open_dist[near]:
                # The row that was reached by this column stays unmatched, and the column is free to be taken.
                shift, last = alone, alone_at
                break
            last, shift = near, open_dist[near]
            if row_of[last] < 0:
                break
            done[last], open_dist[last] = True, np.inf
            row = row_of[last]
        u[i] += shift
        seen = np.flatnonzero(done)
        u[row_of[seen]] += shift - dist[seen]
        v[seen] -= shift - dist[seen]
        while last >= 0:
            before = prev[last]
            row_of[last] = row_of[before] if before >= 0 else i
            last = before
    columns = np.flatnonzero(row_of >= 0)
    return sorted(zip(row_of[columns].tolist(), columns.tolist())), -u, -v


def _hungarian_edges(start: np.ndarray, cols: np.ndarray, weight: np.ndarray, m: int) -> tuple[list[tuple[int, int]], np.ndarray, np.ndarray]:
    """:func:`_hungarian` on the edges of rows one after another (from ``start`` on, columns rising), each with one at least; no matrix is held."""
    n, cost = len(start) - 1, -weight
    bounds = start.tolist()
    u, v, row_of = np.minimum.reduceat(cost, start[:-1]), np.zeros(m), np.full(m, -1)
    lowest = np.flatnonzero(cost == np.repeat(u, np.diff(start)))
    best = cols[lowest[np.searchsorted(lowest, start[:-1])]]
    taken, first = np.unique(best, return_index=True)
    row_of[taken] = first
    free = np.setdiff1d(np.arange(n), first)[::-1].tolist()
    later: list[int] = []
    for _ in range(4 * n):
        if not free:
            break
        row = free.pop()
        own = slice(bounds[row], bounds[row + 1])
        reduced = cost[own] - v[cols[own]]
        k = int(reduced.argmin())
        j, low = int(cols[own][k]), reduced[k]
        if low >= 0:
            u[row] = 0.0
            continue
        reduced[k] = np.inf
        second = min(float(reduced.min()), 0.0)
        before = int(row_of[j])
        if before >= 0 and second - low < 1e-12:
            later.append(row)
            continue
        v[j] -= second - low
        u[row], row_of[j] = second, row
        if before >= 0:
            free.append(before)
    for i in later + free:
        dist, prev, done = np.full(m, np.inf), np.full(m, -1), np.zeros(m, bool)
        open_dist = dist.copy()
        row, shift, last = i, 0.0, -1
        alone, alone_at = np.inf, -1
        while True:
            if shift - u[row] < alone:
                alone, alone_at = shift - u[row], last
            own = slice(bounds[row], bounds[row + 1])
            there = cols[own]
            reach = cost[own] - v[there] + (shift - u[row])
            better = (reach < open_dist[there] - 1e-15) & ~done[there]
            there, reach = there[better], reach[better]
            dist[there], open_dist[there], prev[there] = reach, reach, last
            near = int(open_dist.argmin())
            if alone <= open_dist[near]:
                shift, last = alone, alone_at
                break
            last, shift = near, open_dist[near]
            if row_of[last] < 0:
                break
            done[last], open_dist[last] = True, np.inf
            row = row_of[last]
        u[i] += shift
        seen = np.flatnonzero(done)
        u[row_of[seen]] += shift - dist[seen]
        v[seen] -= shift - dist[seen]
        while last >= 0:
            before = prev[last]
            row_of[last] = row_of[before] if before >= 0 else i
            last = before
    columns = np.flatnonzero(row_of >= 0)
    return sorted(zip(row_of[columns].tolist(), columns.tolist())), -u, -v


def _solved_edges(i: np.ndarray, j: np.ndarray, w: np.ndarray, n: int, m: int) -> tuple[list[tuple[int, int]], np.ndarray, np.ndarray]:
    """:func:`_solved` of distinct edges in order of (row, column)."""
    starts = lambda x, k: np.searchsorted(x, np.arange(k + 1))
    if n <= m:
        return _hungarian_edges(starts(i, n), j, w, m)
    order = np.lexsort((i, j))
    pairs, v, u = _hungarian_edges(starts(j[order], m), i[order], w[order], n)
    return sorted((x, y) for y, x in pairs), u, v


def _solved(dense: np.ndarray) -> tuple[list[tuple[int, int]], np.ndarray, np.ndarray]:
    """The same with the smaller side as rows, as each row is one search."""
    if dense.shape[0] <= dense.shape[1]:
        return _hungarian(dense)
    pairs, v, u = _hungarian(dense.T)
    return sorted((i, j) for j, i in pairs), u, v


def dense_parts(left, right, weight):
    """Each connected part: its edges' indices, and as a matrix (0: no edge; the heaviest of repeated ones) with the index of each cell's edge."""
    part = _parts(left, right)
    # The heaviest of repeated edges is written last.
    order = np.lexsort((weight, part))
    cuts = np.flatnonzero(np.r_[True, part[order][1:] != part[order][:-1]])
    for edges in np.split(order, cuts[1:]):
        rows, i = np.unique(left[edges], return_inverse=True)
        cols, j = np.unique(right[edges], return_inverse=True)
        dense, at = np.zeros((len(rows), len(cols))), np.full((len(rows), len(cols)), -1)
        dense[i, j], at[i, j] = weight[edges], edges
        yield edges, dense, at


#: Cells of a part's matrix; a larger part is mapped on its edges.
DENSE_CELLS = 1 << 21
#: Reduced weights below this are none.
TIGHT = 1e-10


def _first_of_best(weight: np.ndarray, pairs: list[tuple[int, int]], u: np.ndarray, v: np.ndarray) -> list[tuple[int, int]]:
    """Of all matchings of the greatest weight, the one whose edges come first in the order of (weight descending, row, column).

    These are the matchings of tight edges that cover every vertex with a potential, so an edge is taken if what it displaces can
    be covered again by an alternating path.
    """
    rows, cols = np.nonzero((weight > 0) & (u[:, None] + v[None, :] - weight <= TIGHT))
    return _first_of_tight(rows, cols, weight[rows, cols], pairs, u, v)


def _first_of_tight(rows: np.ndarray, cols: np.ndarray, weight: np.ndarray, pairs: list[tuple[int, int]], u: np.ndarray, v: np.ndarray) -> list[tuple[int, int]]:
    """The same of given tight edges."""
    if len(rows) == len(pairs):
        return pairs
    order = np.lexsort((cols, rows, -weight))
    edges = list(zip(rows[order].tolist(), cols[order].tolist()))
    near: tuple[dict, dict] = ({}, {})
    for i, j in edges:
        near[0].setdefault(i, []).append(j)
        near[1].setdefault(j, []).append(i)
    must = (u > TIGHT, v > TIGHT)
    mate = (dict(pairs), {j: i for i, j in pairs})
    fixed: tuple[set, set] = (set(), set())

    def cover(start: int, side: int, mates) -> bool:
        """Match a vertex by a path to a free vertex, or to one that may stay alone."""
        own, other = mates[side], mates[1 - side]
        came, queue = {}, [start]
        for x in queue:
            for y in near[side].get(x, ()):
                if y in came or y in fixed[1 - side]:
                    continue
                came[y] = x
                z = other.get(y)
                if z is not None and must[side][z]:
                    queue.append(z)
                    continue
                if z is not None:
                    del own[z]
                while True:
                    x = came[y]
                    was = own.get(x)
                    own[x], other[y] = y, x
                    if x == start:
                        return True
                    y = was
        return False

    for i, j in edges:
        if i in fixed[0] or j in fixed[1]:
            continue
        fixed[0].add(i)
        fixed[1].add(j)
        if mate[0].get(i) == j:
            continue
        tried = (dict(mate[0]), dict(mate[1]))
        alone_col, alone_row = tried[0].pop(i, None), tried[1].pop(j, None)
        tried[1].pop(alone_col, None)
        tried[0].pop(alone_row, None)
        ok = alone_col is None or not must[1][alone_col] or cover(alone_col, 1, tried)
        ok = ok and (alone_row is None or alone_row in tried[0] or not must[0][alone_row] or cover(alone_row, 0, tried))
        if ok:
            tried[0][i], tried[1][j] = j, i
            mate = tried
        else:
            fixed[0].remove(i)
            fixed[1].remove(j)
    return sorted(mate[0].items())


def _heaviest(x: np.ndarray, n: int, weight: np.ndarray, near: float = 0.0) -> np.ndarray:
    """Edges that are the heaviest of their vertex, or within ``near`` of it."""
    top = np.zeros(n)
    np.maximum.at(top, x, weight)
    return np.flatnonzero(weight >= top[x] - near)


def best_mapping(left, right, weight) -> np.ndarray:
    """Indices of the edges of a maximum-weight one-to-one mapping; of several, the one whose edges come first by (weight descending, left, right)."""
    left, right, weight = np.asarray(left), np.asarray(right), np.asarray(weight, float)
    if len(left) < 2:
        return np.arange(len(left))
    (i, rows), (j, cols), w = _numbered(left), _numbered(right), weight
    key, kept = i * cols + j, None
    if not (key[1:] > key[:-1]).all():
        # In order of (left, right), and the heaviest of repeated edges.
        kept = np.lexsort((-w, key))
        kept = kept[np.r_[True, key[kept][1:] != key[kept][:-1]]]
        i, j, w = i[kept], j[kept], w[kept]
    part = _parts(i, j)
    n_parts = int(part.max()) + 1
    part_i, part_j = np.zeros(rows, np.int64), np.zeros(cols, np.int64)
    part_i[i], part_j[j] = part, part
    sizes = np.bincount(part_i, minlength=n_parts), np.bincount(part_j, minlength=n_parts)
    # Parts with one vertex on a side take their heaviest edge, the first of equal ones.
    star = (sizes[0] == 1) | (sizes[1] == 1)
    heavy = np.flatnonzero(star[part])
    heavy = heavy[np.lexsort((heavy, -w[heavy], part[heavy]))]
    chosen = [heavy[np.diff(part[heavy], prepend=-1) > 0]]
    open_parts = ~star
    # If the heaviest edges of all vertices of a side are single and have different ends, they are the mapping: none has more than their sum.
    for x, n, y, m in ((j, cols, i, rows), (i, rows, j, cols)):
        if not open_parts.any():
            break
        heavy = _heaviest(x, n, w, TIGHT)
        good = open_parts.copy()
        good[part[heavy[w[heavy] <= TIGHT]]] = False
        for end, k in ((x, n), (y, m)):
            good[part[heavy[np.bincount(end[heavy], minlength=k)[end[heavy]] > 1]]] = False
        chosen.append(heavy[good[part[heavy]]])
        open_parts &= ~good
    if open_parts.any():
        edges = np.flatnonzero(open_parts[part])
        by_part = edges[np.argsort(part[edges], kind="stable")] if open_parts.sum() > 1 else edges
        cuts = np.flatnonzero(np.r_[True, part[by_part][1:] != part[by_part][:-1]])
        # Numbers of the vertices within their parts.
        local = []
        for of, size in zip((part_i, part_j), sizes):
            order, place = np.argsort(of, kind="stable"), np.empty(len(of), np.int64)
            place[order] = np.arange(len(of)) - np.repeat(np.cumsum(size) - size, size)
            local.append(place)
        for low, high in zip(cuts.tolist(), [*cuts[1:].tolist(), len(by_part)]):
            own = by_part[low:high]
            shape = sizes[0][part[own[0]]], sizes[1][part[own[0]]]
            r, c = local[0][i[own]], local[1][j[own]]
            if int(shape[0]) * int(shape[1]) > DENSE_CELLS:
                key = r * shape[1] + c
                order = np.argsort(key, kind="stable")
                own, r, c, key = own[order], r[order], c[order], key[order]
                pairs, u, v = _solved_edges(r, c, w[own], *map(int, shape))
                tight = np.flatnonzero(u[r] + v[c] - w[own] <= TIGHT)
                pairs = np.array(_first_of_tight(r[tight], c[tight], w[own[tight]], pairs, u, v), np.int64).reshape(-1, 2)
                chosen.append(own[np.searchsorted(key, pairs[:, 0] * shape[1] + pairs[:, 1])])
                continue
            dense, at = np.zeros(shape), np.full(shape, -1)
            dense[r, c], at[r, c] = w[own], own
            pairs = _first_of_best(dense, *_solved(dense))
            chosen.append(np.array([at[x] for x in pairs], np.int64))
    taken = np.concatenate(chosen)
    return np.sort(taken if kept is None else kept[taken])


def _in_order(order: np.ndarray, left, right) -> np.ndarray:
    """Edges in an order, each taken if both ends are free."""
    used_left, used_right, chosen = set(), set(), []
    for e, x, y in zip(order.tolist(), left[order].tolist(), right[order].tolist()):
        if x not in used_left and y not in used_right:
            used_left.add(x)
            used_right.add(y)
            chosen.append(e)
    return np.array(sorted(chosen), np.int64)


def greedy_mapping(left, right, weight) -> np.ndarray:
    """Left vertices in order of their key each take their best free partner (equal weights: smallest key)."""
    left, right, weight = np.asarray(left), np.asarray(right), np.asarray(weight, float)
    return _in_order(np.lexsort((right, -weight, left)), left, right)


def heaviest_mapping(left, right, weight) -> np.ndarray:
    """The heaviest free edge first; equal weights by left, then right."""
    left, right, weight = np.asarray(left), np.asarray(right), np.asarray(weight, float)
    return _in_order(np.lexsort((right, left, -weight)), left, right)


MAPPINGS = {"optimal": best_mapping, "greedy": greedy_mapping}


# -- clustering of one block ---------------------------------------------------------------------------


#: Similarities that scoring clusters holds at once.
SCORED = 1 << 21


def cluster_scores(sim: np.ndarray, starts: np.ndarray, how: str) -> np.ndarray:
    """Similarity of each arrival (row) to each cluster, whose members are columns from ``starts`` on."""
    if how == "average":
        sizes = np.diff(np.append(starts, sim.shape[1]))
        return np.round(np.add.reduceat(sim, starts, axis=1) / sizes, DIGITS)
    return (np.minimum if how == "min" else np.maximum).reduceat(sim, starts, axis=1)


def group_dice(words: np.ndarray) -> float:
    """Dice of all filters of a group, as their counting filter has it."""
    total = int(np.bitwise_count(words).sum())
    return len(words) * int(np.bitwise_count(np.bitwise_and.reduce(words, axis=0)).sum()) / total if total else 0.0


def _close_clusters(sim, arrivals: np.ndarray, flat: np.ndarray, starts: np.ndarray, how: str, s_t: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Arrivals, clusters and their similarities of at least ``s_t``; rows of arrivals are scored as many as a task holds at once."""
    sizes, found = np.diff(np.append(starts, len(flat))), []
    step = max(1, SCORED // len(flat))
    for at in range(0, len(arrivals), step):
        near = sim(arrivals[at : at + step], flat)
        if how == "average":
            scores = np.add.reduceat(near, starts, axis=1) / sizes
        else:
            scores = cluster_scores(near, starts, how)
        c, r = np.nonzero(scores.T >= s_t - 1e-9)
        w = np.round(scores[r, c], DIGITS) if how == "average" else scores[r, c]
        kept = w >= s_t
        found.append((r[kept] + at, c[kept], w[kept]))
    return tuple(np.concatenate(x) for x in zip(*found))


def _runs_of(keys: np.ndarray, sorted_: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each key the positions in an ordered array that have it: number of the key, and position."""
    low = np.searchsorted(sorted_, keys)
    size = np.searchsorted(sorted_, keys, "right") - low
    return np.repeat(np.arange(len(keys)), size), _runs(low, size)[0]


def _near_clusters(masks, arrivals: np.ndarray, flat: np.ndarray, starts: np.ndarray, how: str, s_t: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """:func:`_close_clusters` without a similarity of each arrival and member: an average, least or greatest similarity of at least ``s_t``
    needs a member that close, so only clusters of a close mask are scored. ``masks``: different masks, and the number of each record's."""
    words, number = masks
    sizes = np.diff(np.append(starts, len(flat)))
    own, theirs = np.unique(number[arrivals]), np.unique(number[flat])
    r, c = _close_masks(words[own], words[theirs], s_t - 1e-8)
    # Clusters with a record of the close mask.
    by_mask = np.argsort(number[flat], kind="stable")
    cluster = np.repeat(np.arange(len(starts)), sizes)[by_mask]
    which, at = _runs_of(theirs[c], number[flat][by_mask])
    pairs = np.unique(r[which] * len(starts) + cluster[at])
    r, c = pairs // len(starts), pairs % len(starts)
    ones, score, low = _ones(words), np.zeros(len(r)), 0
    # As many pairs at once as have some members in all.
    cuts = np.searchsorted(np.cumsum(sizes[c]), np.arange(SCORED // 16, int(sizes[c].sum()), SCORED // 16))
    for high in [*cuts.tolist(), len(r)]:
        if high > low:
            member, first = _runs(starts[c[low:high]], sizes[c[low:high]])
            x, y = np.repeat(own[r[low:high]], sizes[c[low:high]]), number[flat[member]]
            both, total = np.bitwise_count(words[x] & words[y]).sum(axis=1, dtype=np.int64), ones[x].astype(np.int64) + ones[y]
            near = np.divide(2 * both, total, out=np.zeros(len(x)), where=total > 0)
            if how == "average":
                score[low:high] = np.round(np.add.reduceat(near, first) / sizes[c[low:high]], DIGITS)
            else:
                score[low:high] = (np.minimum if how == "min" else np.maximum).reduceat(near, first)
            low = high
    kept = score >= s_t
    r, c, score = r[kept], c[kept], score[kept]
    by_mask = np.argsort(number[arrivals], kind="stable")
    which, at = _runs_of(own[r], number[arrivals][by_mask])
    r, c, score = by_mask[at], c[which], score[which]
    order = np.lexsort((r, c))
    return r[order], c[order], score[order]


def _close_groups(words: np.ndarray, arrivals: np.ndarray, flat: np.ndarray, starts: np.ndarray, s_t: float, group) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The same by Dice of a cluster's counting filter with the arrival added: a cluster is its common words, its ones and its size."""
    sizes = np.diff(np.append(starts, len(flat)))
    ones = np.bitwise_count(words).sum(axis=1, dtype=np.int64)
    common, total = np.bitwise_and.reduceat(words[flat], starts, axis=0), np.add.reduceat(ones[flat], starts)
    found, step = [], max(1, SCORED // len(starts))
    for at in range(0, len(arrivals), step):
        own = arrivals[at : at + step]
        both = (sizes + 1) * common_matrix(words[own], common).astype(np.int64)
        every = ones[own][:, None] + total
        scores = np.divide(both, every, out=np.zeros(both.shape), where=every > 0)
        if group is not None:
            scores[group[own][:, None] != group[flat[starts]]] = 0.0
        c, r = np.nonzero(scores.T >= s_t - 1e-9)
        w = np.round(scores[r, c], DIGITS)
        kept = w >= s_t
        found.append((r[kept] + at, c[kept], w[kept]))
    return tuple(np.concatenate(x) for x in zip(*found))


def early_block(party, order, sim, s_t=0.8, how="average", mapping="optimal", words=None, trace=None, group=None) -> np.ndarray:
    """Cluster number (index of the seed record) of each record. ``sim(rows, columns)`` gives pair similarities; ``how='cbf'`` needs ``words``,
    or a function that gives the words of a round by its place in ``order``. With ``group``, only records of one group meet."""
    party = np.asarray(party)
    label = np.full(len(party), -1)
    members: list[list[int]] = []
    for place, p in enumerate(order):
        arrivals = np.flatnonzero(party == p)
        if not len(arrivals):
            continue
        if members:
            flat = np.array([x for m in members for x in m])
            starts = np.cumsum([0, *map(len, members[:-1])])
            if how == "cbf":
                rows, cols, weight = _close_groups(words(place) if callable(words) else words, arrivals, flat, starts, s_t, group)
            elif s_t > 0 and getattr(sim, "masks", None) is not None:
                rows, cols, weight = _near_clusters(sim.masks, arrivals, flat, starts, how, s_t)
            else:
                rows, cols, weight = _close_clusters(sim, arrivals, flat, starts, how, s_t)
            taken = MAPPINGS[mapping](cols, rows, weight)
            if trace is not None:
                trace.append((p, len(rows), round(float(weight[taken].sum()), 6)))
            for c, a in zip(cols[taken].tolist(), arrivals[rows[taken]].tolist()):
                members[c].append(a)
            free = np.ones(len(arrivals), bool)
            free[rows[taken]] = False
            arrivals = arrivals[free]
        members += [[a] for a in arrivals.tolist()]
    for m in members:
        label[m] = m[0]
    return label


def _set_sim(sim: np.ndarray, members, record: int, how: str, words) -> float:
    if how == "cbf":
        return round(group_dice(words[[*members, record]]), DIGITS)
    x = sim[record, list(members)]
    return round(float(x.mean()), DIGITS) if how == "average" else float(x.min() if how == "min" else x.max())


def _member_sims(sim: np.ndarray, own: np.ndarray | None, clusters: np.ndarray, how: str) -> np.ndarray:
    """Similarity of clusters (members by party, -1: none) to the records that are columns of ``sim``: to all, or each to its ``own``."""
    combine, none = {"average": (np.add, 0.0), "min": (np.minimum, np.inf), "max": (np.maximum, -np.inf)}[how]
    padded = np.append(sim, np.full((1, sim.shape[1]), none), axis=0)
    pick = (lambda k: padded[clusters[:, k]]) if own is None else (lambda k: padded[clusters[:, k], own])
    out = pick(0)
    for k in range(1, clusters.shape[1]):
        out = combine(out, pick(k))
    if how != "average":
        return out
    n = (clusters >= 0).sum(axis=1)
    return np.round(out / (n[:, None] if own is None else n), DIGITS)


def _distinct(clusters: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct clusters in the order of their members' tuples, and the number of each row's. Records are below ``n``, and rise with the column."""
    last = clusters.shape[1] - 1 - np.argmax(clusters[:, ::-1] >= 0, axis=1)
    bits = (n + 1).bit_length()
    packed = []
    for k in range(clusters.shape[1]):
        # A gap is above all records if the tuple goes on, and below them if it has ended.
        c = clusters[:, k].astype(np.int64)
        code = np.where(c >= 0, c + 1, np.where(k < last, n + 1, 0)).astype(np.uint64)
        if k % (64 // bits):
            packed[-1] = packed[-1] << np.uint64(bits) | code
        else:
            packed.append(code)
    order = np.lexsort(packed[::-1])
    new = np.zeros(len(order), bool)
    new[:1] = True
    for w in packed:
        new[1:] |= w[order][1:] != w[order][:-1]
    number = np.empty(len(order), np.int64)
    number[order] = np.cumsum(new) - 1
    return clusters[order[new]], number


def _inside_another(clusters: np.ndarray, n: int) -> np.ndarray:
    """Whether each of distinct clusters is a proper subset of another: those of one pattern of parties are looked up among what
    clusters of its larger patterns have of these parties. Only largest ones are searched, as inclusion is transitive."""
    inside = np.zeros(len(clusters), bool)
    pattern = (clusters >= 0) @ (1 << np.arange(clusters.shape[1]))
    found, at = np.unique(pattern, return_inverse=True)
    rows = np.split(np.argsort(at, kind="stable"), np.cumsum(np.bincount(at, minlength=len(found)))[:-1])
    by_size = sorted(range(len(found)), key=lambda i: -int(found[i]).bit_count())
    code = np.append(np.random.default_rng(1).integers(0, 2**64, n, np.uint64), np.uint64(0))
    top: dict[int, np.ndarray] = {}
    for a in by_size:
        own = rows[a]
        columns = [k for k in range(clusters.shape[1]) if int(found[a]) >> k & 1]
        key = lambda r, c=columns: sum((code[clusters[r, k]] for k in c[1:]), code[clusters[r, c[0]]])
        for b, there in top.items():
            if not len(own):
                break
            if int(found[a]) & int(found[b]) != found[a] or not len(there):
                continue
            mine, theirs = key(own), key(there)
            # Equal codes count only if the members are equal.
            order = np.argsort(mine, kind="stable")
            low, high = np.searchsorted(mine[order], theirs), np.searchsorted(mine[order], theirs, "right")
            hit = np.flatnonzero(high > low)
            place, _ = _runs(low[hit], (high - low)[hit])
            d, c = np.repeat(there[hit], (high - low)[hit]), own[order[place]]
            same = (clusters[np.ix_(d, columns)] == clusters[np.ix_(c, columns)]).all(axis=1)
            inside[c[same]] = True
            own = own[~inside[own]]
        top[a] = own
    return inside


def _runs(start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All positions of runs one after another, and where each begins among them."""
    at = np.cumsum(size) - size
    return np.arange(int(size.sum())) + np.repeat(start - at, size), at


def _best_for_few(left: np.ndarray, right: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """:func:`best_mapping` where the right side has few vertices. Of m of them, each needs its first m edges only: beyond these, one of
    the first is free, and is no lighter and comes first."""
    order = np.lexsort((left, -weight, right))
    first = np.flatnonzero(np.r_[True, right[order][1:] != right[order][:-1]]) if len(order) else np.zeros(0, np.int64)
    place = np.arange(len(order)) - np.repeat(first, np.diff(np.append(first, len(order))))
    kept = np.sort(order[place < len(first)])
    return kept[best_mapping(left[kept], right[kept], weight[kept])]


def _late_arrays(party, order, sim, s_t, how, leftover, rethreshold, most, trace) -> list[tuple[int, ...]]:
    """:func:`late_block` with ``per_edge``, where a cluster has one record a party at most: clusters are rows of an array, a column a
    party. Records have to be in order of their party."""
    n, parties = len(party), np.unique(party).tolist()
    kind = np.int16 if n < 2**15 else np.int32
    tuples = lambda: sorted(tuple(x for x in c if x >= 0) for c in clusters.tolist())
    clusters = np.zeros((0, len(parties)), kind)

    def alone(records, column):
        out = np.full((len(records), len(parties)), -1, kind)
        out[:, column] = records
        return out

    present = [(p, parties.index(p), np.flatnonzero(party == p)) for p in order if p in parties]
    for i, (_, column, arrivals) in enumerate(present):
        if not i:
            clusters = alone(arrivals, column)
            continue
        found, step = [], max(1, SCORED // len(arrivals))
        for low in range(0, len(clusters), step):
            r, c = np.nonzero(_member_sims(sim[:, arrivals], None, clusters[low : low + step], how) >= s_t)
            found.append((r + low, c))
        r, c = (np.concatenate(x) for x in zip(*found))
        left = np.ones(len(clusters), bool)
        left[r] = False
        grown = clusters[r]
        grown[:, column] = arrivals[c]
        clusters = np.concatenate([clusters[left], grown, alone(np.delete(arrivals, np.unique(c)), column)])
        if most is not None and len(clusters) > most:
            raise BlockTooLarge(f"{len(clusters)} overlapping clusters")
    if trace is not None:
        trace.append(("A", tuples()))
    for p, column, own in present:
        mine = clusters[:, column].astype(np.int64)
        clusters[:, column] = -1
        some = (clusters >= 0).any(axis=1)
        clusters, mine = clusters[some], mine[some]
        sets, number = _distinct(clusters, n)
        has = np.flatnonzero(mine >= 0)
        weight = np.concatenate([_member_sims(sim, mine[e], clusters[e], how) for e in np.array_split(has, 1 + len(has) // SCORED)])
        edge = (weight > 0) & (weight >= s_t if rethreshold else True)
        left, right, weight = number[has][edge], mine[has][edge], weight[edge]
        taken = _best_for_few(left, right, weight)
        sets[left[taken], column] = right[taken]
        clusters = np.concatenate([sets, alone(np.setdiff1d(own, right[taken]), column)])
        if leftover == "drop_subset":
            clusters = clusters[~_inside_another(clusters, n)]
        if trace is not None:
            trace.append((p, len(left), round(float(weight[taken].sum()), 6), tuples()))
    return tuples()


class _Packed:
    """Clusters of one record a party at most as numbers: a field of bits a party, the first party highest, with 0 for none or the place of the
    record among those of its party, from 1. Records have to be in order of their party."""

    def __init__(self, party: np.ndarray):
        self.parties, self.first, self.count = (x.tolist() for x in np.unique(party, return_index=True, return_counts=True))
        bits = [(c + 1).bit_length() for c in self.count]
        self.bits = sum(bits)
        self.shift = [sum(bits[k + 1 :]) for k in range(len(bits))]
        self.field = [(1 << b) - 1 << x for b, x in zip(bits, self.shift)]
        self.kind = np.int16 if len(party) < 2**15 else np.int32

    def alone(self, column: int) -> np.ndarray:
        return np.arange(1, self.count[column] + 1, dtype=np.uint64) << self.shift[column]

    def rows(self, codes: np.ndarray, columns=None) -> np.ndarray:
        """Members of clusters by column, -1: none."""
        columns = range(len(self.parties)) if columns is None else columns
        out = np.empty((len(columns), len(codes)), self.kind)
        for x, k in zip(out, columns):
            place = (codes & self.field[k]) >> self.shift[k]
            x[:] = np.where(place > 0, place.astype(self.kind) + (self.first[k] - 1), -1)
        return out.T

    def in_order(self, codes: np.ndarray) -> np.ndarray:
        """Numbers in the order of the members' tuples: a gap is above all records if the tuple goes on."""
        out, later = codes.copy(), np.zeros(len(codes), bool)
        for k in reversed(range(len(self.parties))):
            some = (codes & self.field[k]) > 0
            out[later & ~some] |= self.count[k] + 1 << self.shift[k]
            later |= some
        return out

    def largest(self, codes: np.ndarray) -> np.ndarray:
        """Without the clusters that are proper subsets of another: those of one pattern of parties are looked up among what clusters of its
        larger patterns have of these parties. Only largest ones are searched, as inclusion is transitive."""
        pattern = np.zeros(len(codes), np.uint16 if len(self.parties) <= 16 else np.uint64)
        for k, x in enumerate(self.field):
            pattern |= ((codes & x) > 0).astype(pattern.dtype) << k
        codes = codes[np.argsort(pattern, kind="stable")]
        found, sizes = np.unique(pattern, return_counts=True)
        groups = dict(zip(found.tolist(), np.split(codes, np.cumsum(sizes)[:-1])))
        top: dict[int, np.ndarray] = {}
        for a in sorted(groups, key=lambda x: -x.bit_count()):
            own, fields = np.sort(groups[a]), sum(x for k, x in enumerate(self.field) if a >> k & 1)
            for b, there in top.items():
                if not len(own):
                    break
                if a & b != a or not len(there):
                    continue
                outside = np.ones(len(own), bool)
                for low in range(0, len(there), SCORED):
                    part = there[low : low + SCORED] & fields
                    at = np.searchsorted(own, part)
                    at[at == len(own)] = 0
                    outside[at[own[at] == part]] = False
                own = own[outside]
            top[a] = own
        return np.concatenate(list(top.values()))


def _late_packed(code: _Packed, order, sim, s_t, how, leftovers, rethreshold) -> list[list[tuple[int, ...]]]:
    """:func:`late_block` with ``per_edge`` for each of ``leftovers``, on clusters packed into 64 bits. They are extended, split and searched a
    part at a time, so that a task holds some numbers for each overlapping cluster. Overlapping clusters are found once for all ``leftovers``."""
    present = [(k, np.arange(code.first[k], code.first[k] + code.count[k])) for k in (code.parties.index(p) for p in order if p in code.parties)]
    overlapping = code.alone(present[0][0])
    for i, (column, arrivals) in enumerate(present[1:], 1):
        own, near, before = code.alone(column), sim[:, arrivals], sorted(k for k, _ in present[:i])
        found, free, step = [], np.ones(len(own), bool), max(1, SCORED // len(own))
        for low in range(0, len(overlapping), step):
            part = overlapping[low : low + step]
            r, c = np.nonzero(_member_sims(near, None, code.rows(part, before), how) >= s_t)
            left = np.ones(len(part), bool)
            left[r], free[c] = False, False
            found += [part[left], part[r] | own[c]]
        overlapping = np.concatenate([*found, own[free]])
    return [_late_rounds(code, present, overlapping, sim, s_t, how, x, rethreshold) for x in leftovers]


def _late_rounds(code: _Packed, present, overlapping, sim, s_t, how, leftover, rethreshold) -> list[tuple[int, ...]]:
    clusters = overlapping.copy()
    for column, own in present:
        shift, field, alone = code.shift[column], code.field[column], code.alone(column)
        # A record needs its first edges only, as many as the party has records; lighter ones than these are left out at once.
        least = np.zeros(len(own) + 1)
        left, right, weight = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0)
        for low in range(0, len(clusters), SCORED // 4):
            part = clusters[low : low + SCORED // 4]
            mine = ((part & field) >> shift).astype(np.int64)
            part &= ~np.uint64(field)
            has = np.flatnonzero((mine > 0) & (part > 0))
            w = _member_sims(sim, own[mine[has] - 1], code.rows(part[has]), how)
            edge = (w > 0) & (w >= (np.maximum(least[mine[has]], s_t) if rethreshold else least[mine[has]]))
            left, right, weight = np.append(left, part[has][edge]), np.append(right, mine[has][edge]), np.append(weight, w[edge])
            rank = np.lexsort((code.in_order(left), -weight, right))
            first = np.flatnonzero(np.diff(right[rank], prepend=-1))
            place = np.arange(len(rank)) - np.repeat(first, np.diff(np.append(first, len(rank))))
            last = rank[place == len(own) - 1]
            least[right[last]] = weight[last]
            kept = np.sort(rank[place < len(own)])
            left, right, weight = left[kept], right[kept], weight[kept]
        clusters.sort()
        new = clusters > 0
        new[1:] &= clusters[1:] != clusters[:-1]
        clusters = clusters[new]
        taken = _best_for_few(np.unique(code.in_order(left), return_inverse=True)[1], right, weight)
        clusters[np.searchsorted(clusters, left[taken])] |= alone[right[taken] - 1]
        clusters = np.concatenate([clusters, np.delete(alone, right[taken] - 1)])
        if leftover == "drop_subset":
            clusters = code.largest(clusters)
    return [tuple(x for x in c if x >= 0) for c in code.rows(clusters).tolist()]


#: Records of small parts that late mapping clusters together, and of a part that is small.
PART_RECORDS, SMALL_PART = 128, 24


def _close_parts(party: np.ndarray, sim, s_t: float) -> np.ndarray:
    """Part of each record: records of different parties are in one if a chain of pairs of about ``s_t`` or more links them."""
    root = np.arange(len(party))
    step = max(1, SCORED // max(1, len(party)))
    for low in range(0, len(party), step):
        rows = np.arange(low, min(low + step, len(party)))
        i, j = np.nonzero((sim(rows, np.arange(len(party))) >= s_t - 1e-9) & (party[rows][:, None] != party))
        _link(root, i + low, j)
    return root


def late_parts(party, order, sim, s_t=0.8, how="average", leftovers=("drop_subset",), rethreshold=False) -> list[list[tuple[int, ...]]]:
    """:func:`late_block` with ``per_edge`` for each of ``leftovers``; ``sim(rows, columns)`` gives pair similarities. An average, least or greatest
    similarity of at least ``s_t`` needs a close pair, so clusters stay in the parts that close pairs link, and each part is clustered by itself."""
    party = np.asarray(party)
    number = np.unique(_close_parts(party, sim, s_t), return_inverse=True)[1]
    size = np.bincount(number)
    alone = np.flatnonzero(size[number] == 1)
    out = [[(x,) for x in alone.tolist()] for _ in leftovers]
    by_part = np.lexsort((number, size[number]))[len(alone) :]
    cuts = np.flatnonzero(np.diff(number[by_part], prepend=-1))
    low = 0
    for start, end in zip(cuts.tolist(), [*cuts[1:].tolist(), len(by_part)]):
        if end < len(by_part) and size[number[by_part[end]]] <= SMALL_PART and end + size[number[by_part[end]]] - low <= PART_RECORDS:
            continue
        own = np.sort(by_part[low:end])
        own = own[np.argsort(party[own], kind="stable")]
        low, code, near = end, _Packed(party[own]), sim(own, own)
        if code.bits <= 64:
            found = _late_packed(code, order, near, s_t, how, leftovers, rethreshold)
        else:
            found = [_late_arrays(party[own], order, near, s_t, how, x, rethreshold, None, None) for x in leftovers]
        for all_, some in zip(out, found):
            all_ += [tuple(own[list(c)].tolist()) for c in some]
    return out


def late_block(party, order, sim: np.ndarray, s_t=0.8, how="average", merge="per_edge", leftover="drop_subset", rethreshold=False, most=None, words=None, trace=None, arrays=True) -> list[tuple[int, ...]]:
    """Disjoint clusters as sorted tuples of record indices. With ``most``, more overlapping clusters of the block are an error.
    Where it can, it works on arrays of clusters unless ``arrays`` is false; the clusters are the same."""
    party = np.asarray(party)
    if arrays and merge == "per_edge" and how != "cbf" and (np.diff(party) >= 0).all():
        if most is None and trace is None:
            return sorted(late_parts(party, order, lambda a, b: sim[np.ix_(a, b)], s_t, how, (leftover,), rethreshold)[0])
        return _late_arrays(party, order, sim, s_t, how, leftover, rethreshold, most, trace)
    clusters: list[tuple[int, ...]] = []
    for p in order:
        arrivals = np.flatnonzero(party == p).tolist()
        if not clusters:
            clusters = [(a,) for a in arrivals]
            continue
        edges = {c: [a for a in arrivals if _set_sim(sim, c, a, how, words) >= s_t] for c in clusters}
        used = {a for found in edges.values() for a in found}
        out = []
        for c, found in edges.items():
            if not found:
                out.append(c)
            elif merge == "absorb":
                out.append(tuple(sorted((*c, *found))))
            else:
                out += [tuple(sorted((*c, a))) for a in found]
        out += [(a,) for a in arrivals if a not in used]
        clusters = list(dict.fromkeys(out))
        if most is not None and len(clusters) > most:
            raise BlockTooLarge(f"{len(clusters)} overlapping clusters")
    if trace is not None:
        trace.append(("A", sorted(clusters)))
    for p in order:
        own = set(np.flatnonzero(party == p).tolist())
        rest: dict[tuple[int, ...], None] = {}
        weights: dict[tuple[int, tuple[int, ...]], float] = {}
        for c in clusters:
            remainder = tuple(x for x in c if x not in own)
            if remainder:
                rest[remainder] = None
                for x in set(c) & own:
                    weights[x, remainder] = _set_sim(sim, remainder, x, how, words)
        sets = sorted(rest)
        number = {s: i for i, s in enumerate(sets)}
        edges = [(number[s], x, w) for (x, s), w in sorted(weights.items()) if w > 0 and (not rethreshold or w >= s_t)]
        taken = best_mapping([e[0] for e in edges], [e[1] for e in edges], [e[2] for e in edges])
        joined = {edges[e][0]: edges[e][1] for e in taken}
        clusters = [tuple(sorted((*s, joined[i]))) if i in joined else s for i, s in enumerate(sets)]
        clusters += [(x,) for x in sorted(own - set(joined.values()))]
        if leftover == "drop_subset":
            clusters = drop_subsets(clusters)
        if trace is not None:
            trace.append((p, len(edges), round(sum(edges[e][2] for e in taken), 6), sorted(clusters)))
    return sorted(clusters)


def drop_subsets(clusters: list[tuple[int, ...]]) -> list[tuple[int, ...]]:
    """Without the clusters that are proper subsets of another."""
    having: dict[int, list[frozenset]] = {}
    for c in clusters:
        for x in c:
            having.setdefault(x, []).append(frozenset(c))
    return [c for c in clusters if not any(frozenset(c) < other for other in having[c[0]])]
