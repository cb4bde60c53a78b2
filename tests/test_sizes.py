"""Work that has to spread over tasks, and results that have to hold on larger tables."""

from pyspark.sql import functions as F

from blindmatch.functions import masks
from blindmatch.queries import workloads as W
from blindmatch.sources import roster as R

SMALL = "/root/testdata/sf0.001"


def test_positions_and_attribute_filters_come_from_arrow(spark):
    people = spark.createDataFrame([(1, "anna", None), (2, "", "bo"), (3, "böb é", "annann"), (4, None, None)], "rec_id long, x string, y string")
    for how in ({"keep_bits": True}, {"level": "attribute"}, {"keep_bits": True, "length": 64, "hashes": 3, "salt": "s", "tagged": True}):
        a, b = (masks.encode_bf(people, ("x", "y"), engine=e, keep=("rec_id",), **how) for e in ("arrow", "native"))
        assert a.columns == b.columns
        assert sorted(map(str, a.collect())) == sorted(map(str, b.collect()))
        assert "MapInArrow" in a._jdf.queryExecution().executedPlan().toString()


def test_roster_is_spread(spark):
    assert R.roster(spark, SMALL).rdd.getNumPartitions() == 2 * spark.sparkContext.defaultParallelism


def test_close_pairs_in_tiles_are_all_close_pairs(spark):
    m = W.masked(W.parties(spark, SMALL, 3, 20), "last").withColumn("block", F.substring("block", 1, 1))
    whole = W.pairs_in_blocks(m.where("party < 3")).where("2 * z / (a_ones + b_ones) >= 0.55")
    want = sorted(map(tuple, whole.collect()))
    assert want
    for tile in (3, 10_000):
        got = W.close_pairs(m, 1, 2, 0.55, tile).where("2 * z / (a_ones + b_ones) >= 0.55")
        assert sorted(map(tuple, got.collect())) == want


def test_of_equal_mappings_the_first_is_taken():
    import itertools
    import random

    from blindmatch.operators import kernels

    def first(edges):
        order = sorted(range(len(edges)), key=lambda e: (-edges[e][2], edges[e][0], edges[e][1]))
        found = []

        def go(r, xs, ys, w, chosen):
            if r == len(order):
                found.append((-round(w, 9), chosen))
                return
            x, y, weight = edges[order[r]]
            if x not in xs and y not in ys:
                go(r + 1, xs | {x}, ys | {y}, w + weight, [*chosen, r])
            go(r + 1, xs, ys, w, chosen)

        go(0, frozenset(), frozenset(), 0.0, [])
        return sorted(order[r] for r in min(found)[1])

    some = random.Random(5)
    for _ in range(300):
        edges = [(x, y, some.choice([0.8, 0.85, 0.9, 1.0])) for x, y in some.sample(list(itertools.product(range(4), range(4))), some.randint(1, 9))]
        assert kernels.best_mapping(*zip(*edges)).tolist() == first(edges)


def test_blocks_in_tasks_and_in_parts_are_mapped_alike(spark):
    from blindmatch.operators import assignment

    edges = spark.range(400).selectExpr("concat('b', id % 3) as block", "id * 7 % 23 as x", "100 + id * 5 % 19 as y", "0.5 + (id * 37 % 400) / 1000 as weight")
    for f in (assignment.assign_optimal, assignment.assign_greedy, assignment.assign_best_first):
        a, b = f(edges), f(edges, task_edges=10)
        assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))
    a, b = (assignment.certify(edges, n).groupBy("block", "part").sum("primal") for n in (assignment.TASK_EDGES, 10))
    assert sorted((r[0], r[1], round(r[2], 9)) for r in a.collect()) == sorted((r[0], r[1], round(r[2], 9)) for r in b.collect())


def test_baselines_without_a_limit_do_the_whole_job(spark):
    import itertools

    from blindmatch.operators import baselines

    # 30^4 tuples of one block.
    word = spark.range(120).selectExpr("'b' as block", "cast(id % 4 + 1 as int) as party", "id as rec_id", "array(15L, if(id < 100, 255L, 15L)) as words", "if(id < 100, 12, 8) as ones")
    ones = {r.rec_id: r.ones for r in word.collect()}
    ids = [[i for i in range(120) if i % 4 == p] for p in range(4)]
    want = 0
    for t in itertools.product(*(sorted({ones[i] for i in own}) for own in ids)):
        n = 1
        for own, o in zip(ids, t):
            n *= sum(ones[i] == o for i in own)
        z = 12 if min(t) == 12 else 8
        want += n * (10 * z * 4 >= 7 * sum(t))
    for how in ({}, {"ring_filter": "bound"}):
        assert baselines.ring_cbf(word, [1, 2, 3, 4], 0.7, r=2, length=128, **how).count() == want
    assert "max_tuples" in baselines.tuple_bf.__code__.co_varnames and baselines.tuple_bf.__defaults__[2] is None


def test_cost_queries_read_tables(spark):
    from blindmatch.queries import QUERIES

    for name, table in (("communication_cost", "customer"), ("cbf_memory", "orders"), ("e10_cbf_cost", "customer")):
        assert f"{table}.parquet" in " ".join(QUERIES[name](spark, SMALL).inputFiles())


def test_tuple_counts_beyond_a_long_are_whole(spark):
    from blindmatch.operators import baselines

    m = spark.range(70_000).selectExpr("if(id % 2 = 0, 'a', 'b') as block", "cast(id % 14 / 2 + 1 as int) as party")
    n = {(r.block, r.party): r["count"] for r in m.groupBy("block", "party").count().collect()}
    got = {r.block: int(r.tuples) for r in baselines.tuple_counts(m, [1, 2, 3, 4, 5, 6, 7]).collect()}
    for b in "ab":
        want = 1
        for p in range(1, 8):
            want *= n[b, p]
        assert got[b] == want > 2**63


def test_bit_tree_counts_in_tasks_and_splits_as_counted_one_by_one(spark):
    from blindmatch.functions import blocking

    people = W.parties(spark, SMALL, 3, 20)
    m = masks.encode_bf(people, ("last_name", "zipcode"), keep_bits=True)
    bits = {r.rec_id: set(r.bits) for r in m.collect()}
    want = {"r": list(bits)}
    for _ in range(3):
        level = {}
        for node, ids in want.items():
            c = [(abs(2 * n - len(ids)), i) for i in range(1, 1001) if min(n := sum(i in bits[x] for x in ids), len(ids) - n) >= 10] if len(ids) > 40 else []
            for x in ids:
                level.setdefault(node + str(int(min(c)[1] in bits[x])) if c else node, []).append(x)
        want = level
    got = blocking.bit_tree(m.drop("bits"), 10, 40, 3)
    assert {r.rec_id: r.block for r in got.collect()} == {x: node for node, ids in want.items() for x in ids}


def test_counting_filters_from_words_are_those_of_positions(spark):
    people = W.parties(spark, SMALL, 5, 40)
    m = masks.encode_bf(people, R.QI, keep=("entity_id", "party", "rec_id"), keep_bits=True)
    m = m.withColumn("entity_id", F.when(F.col("entity_id") % 7 > 0, F.col("entity_id"))).withColumn("sex", (F.col("entity_id") % 2).cast("string"))
    for keys in (["entity_id"], ["sex", "party"]):
        a, b = masks.counting_filter(m, keys), masks.counting_filter(m.drop("words"), keys)
        assert a.dtypes == b.dtypes
        assert sorted(map(str, a.collect())) == sorted(map(str, b.collect()))
        assert "explode(bits" not in a._jdf.queryExecution().optimizedPlan().toString()
    n = m.where("entity_id is not null").groupBy("entity_id").agg(F.count(F.lit(1)).alias("m"))
    a = masks.dice_cbf(masks.counting_filter(m, ["entity_id"]), n, ["entity_id"])
    b = masks.dice_group(m.where("entity_id is not null"), ["entity_id"])
    assert sorted(map(str, a.select(*b.columns).collect())) == sorted(map(str, b.collect()))


def test_truth_of_a_setting_is_read_and_not_derived_for_each_measure(spark):
    from blindmatch.queries import experiments

    m, t = experiments._setting(spark, SMALL, 3, 20)
    assert t.count() == m.count() and "customer.parquet" not in " ".join(t.inputFiles())


def test_rounds_encoded_within_tasks_are_those_encoded_as_tables(spark):
    from blindmatch.functions import blocking
    from blindmatch.operators import clustering

    people = blocking.with_block(W.parties(spark, SMALL, 4, 40), "last").cache()
    order = [3, 1, 4, 2]
    want = clustering.cluster_early_resalted(lambda i: W.masked(people.drop("block"), "last", salt=f"round {i}:"), order, 0.6)
    want = sorted(map(tuple, want.collect()))
    for most in (10_000, 20):
        got = clustering.cluster_early_reencoded(people, R.QI, order, 0.6, task_records=most)
        assert sorted(map(tuple, got.collect())) == want
    assert "MapInArrow" not in clustering.cluster_early_reencoded(people, R.QI, order)._jdf.queryExecution().optimizedPlan().toString()


def test_pair_counts_of_all_thresholds_are_those_of_clusterings_one_by_one(spark):
    from blindmatch.functions import blocking
    from blindmatch.operators import clustering, measures

    people = blocking.with_block(W.parties(spark, SMALL, 4, 40), "last")
    m = masks.encode_bf(people, R.QI, keep=("block", "party", "rec_id", "entity_id")).cache()
    for how in ({}, {"task_records": 20}):
        got = measures.missed_pairs(clustering.early_pair_counts(m, [0.6, 0.8, 1.0], **how), W.truth(m))
        got = {r.threshold: (r.tm, r.fm, r.fn) for r in got.collect()}
        assert got == {x: tuple(measures.quality_pairs(clustering.cluster_early(m, s_t=x), W.truth(m)).first()) for x in (0.6, 0.8, 1.0)}


def test_pair_counts_of_all_mappings_are_those_of_clusterings_one_by_one(spark):
    import pytest

    from blindmatch.functions import blocking
    from blindmatch.operators import clustering, kernels, measures
    from blindmatch.queries.experiments import METHODS

    people = blocking.with_block(W.parties(spark, SMALL, 4, 40), "last")
    m = masks.encode_bf(people, R.QI, keep=("block", "party", "rec_id", "entity_id")).withColumn("block", F.substring("block", 1, 1)).cache()
    want = {n: tuple(measures.quality_pairs(f(m, s_t=0.6), W.truth(m)).first()) for n, f in METHODS.items()}
    assert len(set(want.values())) > 2
    for how in ({}, {"methods": ("early", "greedy"), "task_records": 20}):
        got = measures.missed_pairs(clustering.mapping_pair_counts(m, s_t=0.6, **how), W.truth(m)).collect()
        assert {r.method: (r.tm, r.fm, r.fn) for r in got} == {n: want[n] for n in how.get("methods", METHODS)}
    with pytest.raises(kernels.BlockTooLarge, match="more than 20 records"):
        clustering.mapping_pair_counts(m, task_records=20)


def test_mappings_are_not_all_left_to_one_plan(spark):
    from blindmatch.queries import QUERIES

    out = QUERIES["e1_quality"](spark, SMALL)
    assert "FlatMapGroupsInArrow" not in out._jdf.queryExecution().optimizedPlan().toString()
    assert {(r.p, r.corrupted, r.method) for r in out.collect()} == {(p, c, n) for p in (3, 5, 7, 10) for c in (0, 20, 40) for n in ("early", "late", "late_keep", "greedy")}
