"""Engines and modes against each other, on small tables."""

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from blindmatch.functions import masks
from blindmatch.operators import baselines, clustering
from blindmatch.queries import workloads as W
from blindmatch.sources import roster as R

SF = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="the given tables are absent")


def test_encoders_agree(spark):
    people = W.parties(spark, SF, 3, 40)
    people = people.unionByName(people.limit(3).withColumn("first_name", F.lit(None).cast("string")).withColumn("rec_id", F.col("rec_id") + 10**12))
    a = masks.encode_bf(people, R.QI, engine="arrow", keep=("rec_id",))
    b = masks.encode_bf(people, R.QI, engine="native", keep=("rec_id",))
    same = a.join(b.select("rec_id", F.col("words").alias("w"), F.col("ones").alias("o")), "rec_id").where("words = w and ones = o").count()
    assert same == people.count()


def test_empty_filter_and_short_strings(spark):
    df = spark.createDataFrame([(1, None, ""), (2, "a", "b")], "rec_id long, x string, y string")
    for engine in ("arrow", "native"):
        rows = masks.encode_bf(df, ("x", "y"), engine=engine, keep=("rec_id",)).collect()
        assert all(r.ones == 0 and set(r.words) == {0} for r in rows)


def test_modes_agree(spark):
    m = W.masked(W.parties(spark, SF, 3, 20), "last").cache()
    a = {r.rec_id: r.cluster_id for r in clustering.cluster_early(m, mode="block").collect()}
    b = {r.rec_id: r.cluster_id for r in clustering.cluster_early(m, mode="distributed").collect()}
    assert a == b and len(a) == m.count()


@pytest.mark.parametrize("how,mapping", [("average", "optimal"), ("average", "greedy"), ("cbf", "optimal"), ("cbf", "greedy")])
def test_modes_agree_where_party_order_differs_from_the_numbering(spark, how, mapping):
    m = W.masked(W.parties(spark, SF, 4, 40), "last").cache()
    run = lambda **k: {r.rec_id: r.cluster_id for r in clustering.cluster_early(m, s_t=0.6, ord=[3, 1, 4, 2], cluster_sim=how, mapping=mapping, **k).collect()}
    a = run(mode="block")
    assert a == run(mode="distributed") and len(a) == m.count()
    assert a == run(task_records=20)


def test_rounds_with_new_encodings(spark):
    people = W.parties(spark, SF, 4, 40).cache()
    order, made = [3, 1, 4, 2], []

    def remask(i, salt=str):
        made.append(i)
        return W.masked(people, "last", salt=salt(i))

    of = lambda df: {r.rec_id: r.cluster_id for r in df.collect()}
    fixed = of(clustering.cluster_early(W.masked(people, "last", salt="s"), s_t=0.6, ord=order, cluster_sim="cbf", mode="block"))
    assert of(clustering.cluster_early_resalted(lambda i: remask(i, lambda _: "s"), order, 0.6)) == fixed
    made.clear()
    found = of(clustering.cluster_early_resalted(remask, order, 0.6))
    assert made == [0, 1, 2, 3] and found.keys() == fixed.keys()


def test_tuple_guard(spark):
    m = W.masked(W.parties(spark, SF, 3), "none")
    with pytest.raises(baselines.TooManyTuples):
        baselines.tuple_bf(m, [1, 2, 3], max_tuples=1000)


def test_worked_similarities():
    z, a, b = 5, 7, 5
    assert round(2 * z / (a + b), 2) == 0.83
    counts = np.array([3] * 4 + [2, 2, 1, 1])
    assert round(3 * (counts == 3).sum() / counts.sum(), 2) == 0.67


def test_whole_documents(spark):
    import hashlib

    from blindmatch.queries.experiments import e12_whole_documents

    documents = spark.read.parquet(f"{SF}/documents.parquet")
    got = e12_whole_documents(spark, SF).first()
    assert (got.records, got.twice, got.same_party) == (documents.count(), 0, 0)
    # Texts that begin alike and end differently are no match; brute-force signs over all grams.
    texts = ["same start " * 8 + " ".join(f"{t}{i}" for i in range(300)) for t in "ab"] + ["one", "", None]
    df = spark.createDataFrame([(i % 2, i, t) for i, t in enumerate(texts)], "party int, rec_id long, text string")
    mask = {r.rec_id: r for r in masks.encode_texts(df, "text").collect()}
    m64 = 2**64 - 1
    for i, t in enumerate(texts):
        w = (t or "").split()
        total = [0] * 1024
        seeds = [int.from_bytes(hashlib.blake2b(g.encode(), digest_size=8).digest(), "little") for g in {" ".join(w[j : j + 3]) for j in range(max(1, len(w) - 2))} if g]
        for seed in seeds:
            for k in range(16):
                x = (seed + (k + 1) * 0x9E3779B97F4A7C15) & m64
                x = ((x ^ (x >> 30)) * 0xBF58476D1CE4E5B9) & m64
                x = ((x ^ (x >> 27)) * 0x94D049BB133111EB) & m64
                x ^= x >> 31
                for b in range(64):
                    total[64 * k + b] += 1 if x >> b & 1 else -1
        words = [sum(1 << b for b in range(64) if total[64 * k + b] > 0) for k in range(16)]
        assert [x & m64 for x in mask[i].words] == words and mask[i].ones == sum(x > 0 for x in total)
        assert mask[i].block == (f"{min(seeds):016x}" if seeds else "")
    both = [np.array(mask[i].words, np.int64).view(np.uint64) for i in (0, 1)]
    assert 2 * np.bitwise_count(both[0] & both[1]).sum() / sum(np.bitwise_count(x).sum() for x in both) < 0.85


def test_recursive_reach(spark):
    from blindmatch.queries.relational import recursive_reach

    orders = [(r.o_custkey, r.o_orderkey) for r in spark.read.parquet(f"{SF}/orders.parquet").select("o_custkey", "o_orderkey").collect()]
    want = {}
    for c, o in orders:
        n = sum(c == x and y > o for x, y in orders)
        if n:
            want[o] = n
    assert {r.u: r.reached for r in recursive_reach(spark, SF).collect()} == want
