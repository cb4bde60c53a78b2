"""Long chains, blocks above the limits, and the clear-text and global-attack operators on small tables."""

import numpy as np
import pytest

from blindmatch.operators import assignment, baselines, clustering, components, kernels


def test_chain_of_500_is_one_part_and_is_solved(spark):
    n = 250
    rows = [("b", i, i, 1.0 - i / 1000) for i in range(n)] + [("b", i, i + 1, 0.9 - i / 1000) for i in range(n)] + [("c", 1, 1, 0.5), ("c", 2, 9, 0.5)]
    edges = spark.createDataFrame(rows, assignment.EDGE)
    parts = {(r.block, r.x): r.part for r in assignment.edge_parts(edges).collect()}
    assert {p for (b, _), p in parts.items() if b == "b"} == {0} and parts[("c", 1)] == 1 and parts[("c", 2)] == 2
    best = assignment.assign_optimal(edges).where("block = 'b'").collect()
    left, right, weight = (np.array([r[i] for r in rows if r[0] == "b"]) for i in (1, 2, 3))
    assert sum(r.weight for r in best) == pytest.approx(weight[kernels.best_mapping(left, right, weight)].sum())
    assert len({r.x for r in best}) == len(best) == len({r.y for r in best})


def test_components_by_brute_force(spark):
    rng = np.random.default_rng(3)
    pairs = [(int(a), int(b)) for a, b in rng.integers(0, 120, (90, 2))]
    root = list(range(120))
    for _ in range(120):
        for a, b in pairs:
            root[a] = root[b] = min(root[a], root[b])
    got = {r.node: r.component for r in components.components(spark.createDataFrame(pairs, "u long, v long")).collect()}
    linked = {x for a, b in pairs if a != b for x in (a, b)}
    assert got == {x: root[x] for x in linked}
    assert components.components(spark.createDataFrame([], "u long, v long")).count() == 0


def masked(spark, n, parties=2):
    rows = [("b", p, p * 1000 + i, [int(x) for x in np.random.default_rng(i).integers(0, 2**62, 16)]) for p in range(1, parties + 1) for i in range(n)]
    return spark.createDataFrame(rows, "block string, party int, rec_id long, words array<long>")


def test_large_blocks_are_named_before_they_are_read(spark):
    with pytest.raises(kernels.BlockTooLarge, match="block b: 40 records"):
        clustering.cluster_late(masked(spark, 20), max_records_per_block=39)
    # Above the limit of a task, rounds give what tasks give.
    m = masked(spark, 12)
    a, b = (sorted(map(tuple, clustering.cluster_early(m, ord=[1, 2], task_records=t).collect())) for t in (100, 5))
    assert a == b and sum(1 for r in a if r[-1] == 2) == 24


def test_pruned_tuples_and_rings_are_guarded(spark):
    m = masked(spark, 6, 4).selectExpr("*", "500 AS ones")
    with pytest.raises(baselines.TooManyTuples):
        baselines.tuple_bf(m, [1, 2, 3, 4], 0.01, prune=True, max_tuples=30)
    with pytest.raises(baselines.TooManyTuples):
        baselines.ring_cbf(m, [1, 2, 3, 4], 0.01, r=2, max_tuples=40)


def test_late_arrays_give_what_loops_give():
    rng = np.random.default_rng(0)
    for t in range(120):
        p = int(rng.integers(2, 6))
        party = np.sort(rng.integers(1, p + 1, rng.integers(1, 13)))
        sim = np.triu(rng.choice([0, 0.3, 0.7, 0.8, 0.82, 0.9, 1.0], (len(party), len(party))), 1)
        sim, order = sim + sim.T, rng.permutation(np.arange(1, p + 1)).tolist()
        for how in ("average", "min", "max"):
            for leftover in ("drop_subset", "keep"):
                a, b = (kernels.late_block(party, order, sim, 0.75, how, leftover=leftover, rethreshold=bool(t % 2), arrays=x) for x in (True, False))
                assert a == b


def test_late_mapping_has_no_limit_on_clusters_unless_one_is_asked_for(spark):
    # 9 ** 4 overlapping clusters of one block.
    rows = [("b", p, p * 1000 + i, [2**62 - 1 - 2 ** (9 * (p - 1) + i)] * 16) for p in range(1, 5) for i in range(9)]
    m = spark.createDataFrame(rows, "block string, party int, rec_id long, words array<long>")
    for leftover in ("drop_subset", "keep"):
        found = clustering.cluster_late(m, ord=[1, 2, 3, 4], leftover=leftover).collect()
        assert sorted(r.rec_id for r in found) == sorted(r[2] for r in rows)
        assert len({(r.cluster_id, r.party) for r in found}) == 36
    with pytest.raises(Exception, match="block b: 6561 overlapping clusters"):
        clustering.cluster_late(m, ord=[1, 2, 3, 4], max_clusters_per_block=5000).collect()


def test_late_mapping_by_packed_parts_gives_what_loops_give():
    rng = np.random.default_rng(1)
    for t in range(60):
        p = int(rng.integers(2, 6))
        party = np.sort(rng.integers(1, p + 1, rng.integers(1, 16)))
        sim = np.triu(rng.choice([0, 0.3, 0.7, 0.8, 0.9, 1.0], (len(party), len(party)), p=[0.5, 0.1, 0.1, 0.1, 0.1, 0.1]), 1)
        sim, order = sim + sim.T, rng.permutation(np.arange(1, p + 1)).tolist()
        for how in ("average", "min", "max"):
            got = kernels.late_parts(party, order, lambda a, b: sim[np.ix_(a, b)], 0.75, how, ("drop_subset", "keep"), bool(t % 2))
            for leftover, found in zip(("drop_subset", "keep"), got):
                assert sorted(found) == kernels.late_block(party, order, sim, 0.75, how, leftover=leftover, rethreshold=bool(t % 2), arrays=False)


def test_late_mapping_holds_few_bytes_a_cluster():
    import tracemalloc

    # 8 ** 7 overlapping clusters, and a record of each party that is close to none.
    party = np.repeat(np.arange(1, 8), 9)
    near = (party[:, None] != party) * np.where(np.arange(63) % 9 == 8, 0.0, 1.0)
    sim = np.minimum(near, near.T)
    tracemalloc.start()
    try:
        found = kernels.late_block(party, list(range(1, 8)), sim)
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert found == kernels.late_block(party, list(range(1, 8)), sim, most=10**9)
    assert peak < 100 * 8**7
