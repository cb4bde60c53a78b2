"""Worked examples and exact references of the mappings and of both clustering protocols."""

import itertools
import random

import numpy as np

from blindmatch.operators import kernels as K


def sims(text, records):
    out = np.zeros((len(records), len(records)))
    at = {r: i for i, r in enumerate(records)}
    for item in text.split(","):
        pair, w = item.split()
        a, b = (at[int(x)] for x in pair.split("-"))
        out[a, b] = out[b, a] = float(w)
    return out


F4 = "11-22 .92, 11-23 .80, 13-23 .88, 13-22 .78, 14-21 .84, 11-31 .86, 22-31 .84, 11-32 .90, 22-32 .88, 12-32 .80, 13-33 .91, 23-33 .87, 12-43 .83, 32-43 .79, 13-41 .90, 23-41 .85, 33-41 .86, 14-42 .70, 21-42 .72, 34-42 .60"
R4 = [11, 12, 13, 14, 21, 22, 23, 31, 32, 33, 34, 41, 42, 43]
F5 = (
    "11-21 .60, 11-22 .84, 11-23 .50, 12-21 .92, 12-22 .70, 12-23 .88, 13-21 .50, 13-22 .50, 13-23 .92, 11-31 .88, 11-32 .60, 11-33 .84, 11-34 .88, 12-31 .60, 12-32 .88, "
    "12-33 .50, 12-34 .80, 13-31 .80, 13-32 .84, 13-33 .76, 13-34 .88, 21-31 .92, 21-32 .80, 21-33 .84, 21-34 .50, 22-31 .70, 22-32 .84, 22-33 .50, 22-34 .92, 23-31 .88, 23-32 .50, 23-33 .76, 23-34 .92"
)
R5 = [11, 12, 13, 21, 22, 23, 31, 32, 33, 34]


def early(text, records, mapping="optimal", s_t=0.75, trace=None):
    s = sims(text, records)
    party = [r // 10 for r in records]
    label = K.early_block(party, sorted(set(party)), lambda a, b: s[np.ix_(a, b)], s_t, "average", mapping, trace=trace)
    groups = {}
    for r, l in zip(records, label):
        groups.setdefault(l, []).append(r)
    return sorted(map(tuple, groups.values()))


def late(text, records, **how):
    party, trace = [r // 10 for r in records], []
    found = K.late_block(party, sorted(set(party)), sims(text, records), 0.75, trace=trace, **how)
    names = lambda cs: sorted(tuple(records[i] for i in c) for c in cs)
    return names(found), [(t[0], *t[1:-1], names(t[-1])) for t in trace]


def test_mapping_example():
    left, right, w = [1, 1, 2, 2, 3], [1, 2, 1, 2, 3], [0.9, 0.8, 0.9, 0.7, 0.9]
    assert round(sum(w[e] for e in K.greedy_mapping(left, right, w)), 6) == 2.5
    best = K.best_mapping(left, right, w)
    assert round(sum(w[e] for e in best), 6) == 2.6
    assert [(left[e], right[e]) for e in best] == [(1, 2), (2, 1), (3, 3)]


def test_early_example():
    trace = []
    got = early(F4, R4, trace=trace)
    assert [t[1:] for t in trace] == [(5, 2.64), (4, 2.54), (2, 1.68)]
    assert [c for c in got if len(c) >= 3] == [(11, 22, 31), (12, 32, 43), (13, 23, 33, 41)]
    trace = []
    got = early(F4, R4, "greedy", trace=trace)
    assert [c for c in got if len(c) >= 3] == [(11, 22, 32), (13, 23, 33, 41)] and trace[1][2] == 1.78


def test_late_example():
    for leftover in ("drop_subset", "keep"):
        got, trace = late(F5, R5, leftover=leftover)
        assert trace[0][1] == [(11, 22, 31), (11, 22, 34), (12, 21, 31), (12, 21, 32), (12, 23, 34), (13, 23, 31), (13, 23, 33), (13, 23, 34)]
        assert [t[1:3] for t in trace[1:]] == [(8, 2.66), (7, 2.76), (5, 2.72)]
        assert trace[1][3] == [(11, 22, 31), (12, 21, 32), (13, 23, 34), (21, 31), (22, 34), (23, 31), (23, 33)]
        assert got == [(11,), (12, 32), (13, 23), (21, 31), (22, 34), (33,)]
    assert late(F5, R5, merge="absorb")[0] == [(11, 22, 34), (12, 21, 31), (13, 23, 33), (32,)]
    assert early(F5, R5) == [(11, 22, 34), (12, 21, 32), (13, 23, 31), (33,)]


def brute(weight):
    n, m = weight.shape
    best = 0.0
    for size in range(min(n, m) + 1):
        for rows in itertools.combinations(range(n), size):
            for cols in itertools.permutations(range(m), size):
                w = [weight[i, j] for i, j in zip(rows, cols)]
                if all(x > 0 for x in w):
                    best = max(best, sum(w))
    return best


def test_optimal_is_optimal_and_certified():
    rng = random.Random(3)
    for _ in range(120):
        n, m = rng.randint(1, 5), rng.randint(1, 5)
        w = np.array([[rng.choice([0, 0, rng.random()]) for _ in range(m)] for _ in range(n)])
        left, right = np.nonzero(w)
        taken = K.best_mapping(left, right, w[left, right])
        total = w[left[taken], right[taken]].sum()
        assert abs(total - brute(w)) < 1e-9
        assert len(set(left[taken])) == len(taken) == len(set(right[taken]))
        greedy = K.greedy_mapping(left.tolist(), right.tolist(), w[left, right].tolist())
        assert w[left[greedy], right[greedy]].sum() <= total + 1e-9
        pairs, u, v = K._hungarian(w)
        assert abs(u.sum() + v.sum() - total) < 1e-9 and (u >= -1e-12).all() and (v >= -1e-12).all()
        assert (u[left] + v[right] >= w[left, right] - 1e-9).all()


def test_stress_shapes_and_partition():
    for p in (2, 3, 4):
        party = np.repeat(np.arange(1, p + 1), 5)
        same, apart = np.ones((5 * p, 5 * p)), np.eye(5 * p)
        label = K.early_block(party, range(1, p + 1), lambda a, b: same[np.ix_(a, b)])
        assert all((np.bincount(party[label == s]) <= 1).all() for s in set(label)) and len(set(label)) == 5
        assert len(set(K.early_block(party, range(1, p + 1), lambda a, b: apart[np.ix_(a, b)]))) == 5 * p
    rng = np.random.default_rng(1)
    for _ in range(40):
        party = rng.integers(1, 4, 9)
        s = rng.random((9, 9))
        s = (s + s.T) / 2
        for how in ({}, {"merge": "absorb"}, {"leftover": "keep"}):
            found = K.late_block(party, [1, 2, 3], s, 0.6, **how)
            assert sorted(x for c in found for x in c) == list(range(9))
            assert all(len({party[x] for x in c}) == len(c) for c in found)


def test_group_dice_is_pair_dice():
    rng = np.random.default_rng(2)
    w = rng.integers(0, 2**63, (6, 16)).astype(np.uint64)
    d = K.dice_matrix(w, w)
    assert np.allclose(np.diag(d), 1) and np.isclose(K.group_dice(w[[1, 4]]), d[1, 4])
    assert K.dice_matrix(np.zeros((1, 16), np.uint64), w)[0, 0] == 0.0


def test_blocks_above_what_a_task_holds_are_clustered_alike(monkeypatch):
    rng = np.random.default_rng(4)
    seeds = rng.integers(0, 2**63, (12, 4)).astype(np.uint64)
    words = seeds[rng.integers(0, 12, 90)] & ~(np.uint64(1) << rng.integers(0, 64, (90, 4)).astype(np.uint64))
    party, group = np.arange(90) % 5, np.sort(rng.integers(0, 3, 90))
    same = (group[:, None] == group) * K.dice_matrix(words, words)
    want = K.early_block(party, [3, 1, 4, 0, 2], lambda a, b: same[np.ix_(a, b)], 0.6).tolist()
    assert K.early_block(party, [3, 1, 4, 0, 2], K.similarities(words, group), 0.6).tolist() == want
    monkeypatch.setattr(K, "HELD_MASKS", 3)
    monkeypatch.setattr(K, "SCORED", 40)
    assert K.early_block(party, [3, 1, 4, 0, 2], K.similarities(words, group), 0.6).tolist() == want
    assert len(set(want)) < 90
