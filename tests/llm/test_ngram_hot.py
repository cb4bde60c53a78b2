"""The n-gram join where cells and candidate groups are far above their limits: no link may be lost."""

import random

from blindmatch.llm import ngram_join
from tests.llm.test_operators import frame, jaccard_components


def hot_texts(seed=11):
    """Near copies of long texts, at several lengths, a passage that many texts share, and short copies."""
    rng = random.Random(seed)
    passage = [f"verylongpassageword{i:04d}" for i in range(30)]
    texts = []
    for size in (60, 70, 85, 100, 400, 2500):
        base = [f"w{rng.randrange(10**6)}" for _ in range(size)]
        for _ in range(12):
            body = list(base)
            for _ in range(rng.randrange(0, max(2, size // 40))):
                body[rng.randrange(size)] = f"edit{rng.randrange(10**6)}"
            texts.append(" ".join(body + passage[: rng.choice([0, 30])]))
    # A chain: each links with the next only.
    words = [f"c{i}" for i in range(400)]
    texts += [" ".join(words[6 * i : 6 * i + 150]) for i in range(30)]
    texts += [" ".join(passage + [f"tail{i}x{j}" for j in range(rng.randrange(5, 60))]) for i in range(40)]
    rng.shuffle(texts)
    return texts + [None, "", "one two", "One two"]


def test_hot_cells_and_groups_lose_no_link(spark, monkeypatch):
    texts = hot_texts()
    sets, roots = jaccard_components(texts, 4, 85)
    monkeypatch.setattr(ngram_join, "CELL_ROWS", 7)
    monkeypatch.setattr(ngram_join, "GROUP_SHINGLES", 900)
    got = {r.doc_id: r for r in ngram_join.link_documents(frame(spark, texts)).collect()}
    assert [(got[i].n_shingles, got[i].component_id) for i in range(len(texts))] == [(len(s), r) for s, r in zip(sets, roots)]


def test_finer_counts_keep_all_links(spark, monkeypatch):
    rng = random.Random(5)
    texts = []
    for size in (300, 340, 500, 900, 1000, 2400):
        base = [f"w{rng.randrange(10**6)}" for _ in range(size)]
        for cut in (0, 3, 5, 9, 20, 40):
            texts.append(" ".join(base[: size - cut * size // 200]))
        texts += [" ".join(f"w{rng.randrange(10**6)}" for _ in range(size)) + " averylongpassagewordsharedbyall anotherverylongwordsharedbyall andathirdverylongone andafourthverylongone" for _ in range(4)]
    monkeypatch.setattr(ngram_join, "FULL_LOAD", 1)
    sets, roots = jaccard_components(texts, 4, 85)
    for most in (ngram_join.FINE_BYTES, 700):
        monkeypatch.setattr(ngram_join, "FINE_BYTES", most)
        got = {r.doc_id: r for r in ngram_join.link_documents(frame(spark, texts)).collect()}
        assert [(got[i].n_shingles, got[i].component_id) for i in range(len(texts))] == [(len(s), r) for s, r in zip(sets, roots)]


def test_only_rows_of_hot_keys_are_dealt(spark):
    from pyspark.sql import functions as F

    rows = spark.range(300).selectExpr("if(id < 40, 7L, id) as cell", "id", "100 + id % 3 as n")
    hot = spark.createDataFrame([(7,)], "cell long")
    got = ngram_join._dealt(rows, "cell", F.lit(1), hot, 8, 85)
    cold = got.where("cell <> 7").collect()
    assert sorted(r.id for r in cold) == list(range(40, 300)) and {(r.band, r.low, r.high) for r in cold} == {(-1, 0, 0)}
    groups = {}
    for r in got.where("cell = 7").collect():
        groups.setdefault((r.band, r.low, r.high), set()).add(r.id)
    # Any two of the hot key meet in a group.
    assert all(any({a, b} <= g for g in groups.values()) for a in range(40) for b in range(a))
    assert got._jdf.queryExecution().optimizedPlan().toString().count("isnull(cuts") == 0
