import numpy as np

from blindmatch.llm import components


def roots(pairs, n):
    root = list(range(n))
    for _ in range(n):
        for a, b in pairs:
            root[a] = root[b] = min(root[a], root[b])
    return root


def test_components_by_brute_force(spark, monkeypatch):
    rng = np.random.default_rng(8)
    pairs = [(int(a), int(b)) for a, b in rng.integers(0, 150, (110, 2))] + [(150 + i, 151 + i) for i in range(40)] + [(3, 3)]
    root = roots(pairs, 200)
    linked = {x for a, b in pairs if a != b for x in (a, b)}
    rows = [*pairs, *pairs[:5], (None, 4)]
    for held in (1 << 20, 3):
        monkeypatch.setattr(components, "HELD_LINKS", held)
        found = components.connected_components(spark.createDataFrame(rows, "u long, v long")).collect()
        assert sorted(map(tuple, found)) == sorted((x, root[x]) for x in linked)
    assert components.connected_components(spark.createDataFrame([], "u long, v long")).count() == 0
