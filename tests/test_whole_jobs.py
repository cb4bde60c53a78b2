"""Whole results where a limit, a held table or rounds of joins stood before."""

import numpy as np
from pyspark.sql import functions as F

from blindmatch.functions import blocking, masks
from blindmatch.queries import workloads as W

SMALL = "/root/testdata/sf0.001"


def test_bit_tree_splits_until_sizes_stop_it_in_tasks_and_by_levels(spark):
    people = W.parties(spark, SMALL, 3, 20)
    m = masks.encode_bf(people, ("last_name", "zipcode"), keep_bits=True).cache()
    bits = {r.rec_id: set(r.bits) for r in m.collect()}
    want, todo = {}, [("r", list(bits))]
    while todo:
        node, ids = todo.pop()
        c = [(abs(2 * n - len(ids)), i) for i in range(1, 1001) if min(n := sum(i in bits[x] for x in ids), len(ids) - n) >= 2] if len(ids) > 4 else []
        if not c:
            want |= dict.fromkeys(ids, node)
            continue
        for side in (0, 1):
            todo.append((f"{node}{side}", [x for x in ids if (min(c)[1] in bits[x]) == side]))
    assert max(map(len, want.values())) > 7
    for held in (10**6, 30):
        got = blocking.bit_tree(m.drop("bits"), 2, 4, task_records=held)
        assert {r.rec_id: r.block for r in got.collect()} == want


def test_mappings_of_masks_are_those_of_their_edges(spark):
    """With few partners kept and small tiles, so that rows are computed anew and blocks are many tiles."""
    from functools import partial

    from blindmatch.operators import assignment, kernels
    from blindmatch.queries import linkage

    lazy = linkage.edges(spark, SMALL)
    table = lazy.table().cache()
    small = assignment.CloseEdges(lazy.masked, 0.55, partial(W.tiles, tile=3), None)
    rows = lambda df: sorted(map(tuple, df.collect()))
    for e in (lazy, small):
        assert rows(assignment.assign_best_link(e)) == rows(assignment.assign_best_link(table)) != []
        assert rows(assignment.left_vertices(e)) == rows(table.select("block", "x").distinct())
    assert rows(assignment.assign_greedy(small)) == rows(assignment.assign_greedy(table)) != []
    want = rows(assignment.assign_best_first(table))
    assert rows(assignment.assign_best_first(small)) == want
    assert rows(small.mapped(lambda a, b, least: kernels.heaviest_masks(a, b, least, kept=1))) == want


def test_late_mapping_of_blocks_beyond_a_held_matrix(spark):
    """A block of more than 4,000 records was an error; clusters are those of its parts, with the seeds of the order of parties."""
    from blindmatch.operators import clustering

    rng = np.random.default_rng(3)
    own = rng.integers(0, 2**62, (1400, 16))
    rows = [("b", p, p * 10_000 + i, [int(x) for x in own[i]]) for p in (1, 2, 3) for i in range(1400)]
    m = spark.createDataFrame(rows, "block string, party int, rec_id long, words array<long>")
    found = clustering.cluster_late(m, ord=[2, 3, 1]).collect()
    assert len(found) == 4200 and all(r.cluster_id == 20_000 + r.rec_id % 10_000 and r.cluster_size == 3 for r in found)


def test_quality_of_all_sizes_is_that_of_each(spark):
    from blindmatch.operators import clustering, measures

    people = W.parties(spark, SMALL, 5, 20)
    t = W.truth(people).cache()
    found = clustering.cluster_late(W.masked(people)).cache()
    got = {r.s_m: tuple(r)[1:] for r in measures.quality_by_size(found, t, range(2, 8)).collect()}
    assert got == {k: tuple(measures.quality(found, t, k).first()) for k in range(2, 8)}


def test_only_close_clusters_are_scored_and_none_is_missed(monkeypatch):
    from blindmatch.operators import kernels

    rng = np.random.default_rng(5)
    for t in range(40):
        n = int(rng.integers(2, 60))
        seeds = rng.integers(0, 2**63, (max(1, n // 4), 2)).astype(np.uint64)
        noise = np.bitwise_and.reduce(rng.integers(0, 2**63, (4, n, 2)).astype(np.uint64), axis=0) * (rng.random((n, 1)) < 0.7)
        words, party = seeds[rng.integers(0, len(seeds), n)] ^ noise.astype(np.uint64), rng.integers(1, 6, n)
        for how in ("average", "min", "max"):
            for s_t in (0.6, 0.8):
                monkeypatch.setattr(kernels, "HELD_MASKS", 10**6)
                want = kernels.early_block(party, [3, 1, 2, 5, 4], kernels.similarities(words), s_t, how)
                monkeypatch.setattr(kernels, "HELD_MASKS", 0)
                sim = kernels.similarities(words)
                assert sim.masks is not None
                assert (kernels.early_block(party, [3, 1, 2, 5, 4], sim, s_t, how) == want).all()


def test_large_parts_are_mapped_on_their_edges_as_on_a_matrix(monkeypatch):
    from blindmatch.operators import kernels

    rng = np.random.default_rng(6)
    for t in range(150):
        n, m = rng.integers(2, 25, 2)
        x, y = np.nonzero(rng.random((n, m)) < rng.choice([0.15, 0.4, 0.9]))
        w = rng.integers(1, 6, len(x)) / 7 if t % 2 else rng.random(len(x)) + 0.01
        monkeypatch.setattr(kernels, "DENSE_CELLS", 10**9)
        want = kernels.best_mapping(x, y, w).tolist()
        monkeypatch.setattr(kernels, "DENSE_CELLS", 0)
        assert kernels.best_mapping(x, y, w).tolist() == want
