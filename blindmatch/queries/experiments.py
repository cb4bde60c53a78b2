"""The experiments: quality, cost and risk by method and parameter, one row a setting."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blindmatch.functions import blocking, masks
from blindmatch.operators import baselines, clustering, measures, privacy
from blindmatch.plans.lineage import cut
from blindmatch.queries import workloads as W
from blindmatch.queries.early_sql import sql_early, sql_quality
from blindmatch.queries.linkage import exact, sql_exact
from blindmatch.queries.registry import query
from blindmatch.sources import roster as R
from blindmatch.sources.tables import load

METHODS = {
    "early": lambda m, **k: clustering.cluster_early(m, **k),
    "late": lambda m, **k: clustering.cluster_late(m, **k),
    "late_keep": lambda m, **k: clustering.cluster_late(m, leftover="keep", **k),
    "greedy": lambda m, **k: clustering.cluster_early(m, mapping="greedy", **k),
}


def _all(rows: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), rows)


def _tag(df: DataFrame, **tags) -> DataFrame:
    return df.select(*(F.lit(v).alias(k) for k, v in tags.items()), "*")


def _setting(s, d, p, rate, profile="quarter", block="first_last"):
    """Masks and truth of a setting, written once for all measures of it."""
    people = W.parties(s, d, p, rate, profile)
    return cut(W.masked(people, block), "masked"), cut(W.truth(people), "truth")


@query("e1_quality")
def e1_quality(s, d):
    """Mappings compared on clean and corrupted data; a setting is encoded, shuffled and compared once for all mappings, and settings run one after another."""
    out = []
    for p in (3, 5, 7, 10):
        for rate in (0, 20, 40):
            m = masks.encode_bf(blocking.with_block(W.parties(s, d, p, rate)), R.QI, keep=("block", "party", "rec_id", "entity_id"))
            m = cut(m, "masked")
            counts = cut(clustering.mapping_pair_counts(m, tuple(METHODS)), "counts")
            out.append(_tag(measures.prf(measures.missed_pairs(counts, W.truth(m))), p=p, corrupted=rate))
    return _all(out)


@query("e2_threshold_sweep")
def e2_threshold_sweep(s, d):
    """Quality by threshold; a corruption level is encoded, shuffled and compared once for all thresholds."""
    out, thresholds = [], [x / 100 for x in range(60, 101, 5)]
    for rate in (0, 20, 40):
        people = W.parties(s, d, 10, rate)
        m = masks.encode_bf(blocking.with_block(people), R.QI, keep=("block", "party", "rec_id", "entity_id"))
        m = cut(m, "masked")
        counts = cut(clustering.early_pair_counts(m, thresholds), "counts")
        out.append(_tag(measures.prf(measures.missed_pairs(counts, W.truth(m))), corrupted=rate))
    return _all(out)


@query("e3_subset_size")
def e3_subset_size(s, d):
    """Quality by minimum subset size: one clustering a method, filtered by size."""
    m, t = _setting(s, d, 10, 20, "by_size")
    out = []
    for n in ("early", "late", "greedy"):
        found = cut(METHODS[n](m), "found")
        out.append(_tag(measures.quality_by_size(found, t, range(2, 11)).orderBy("s_m"), method=n))
    return _all(out)


@query("e4_scalability")
def e4_scalability(s, d):
    """Seconds of early mapping by number of parties and blocking key, measured when the query is built; sizes are those of the tables."""
    rows = []
    for p in (3, 5, 7, 10):
        for block in ("last", "first_last"):
            began = time.perf_counter()
            # The masks are written, as the order of parties and the sizes of blocks are counted before the clustering.
            n = clustering.cluster_early(cut(W.masked(W.parties(s, d, p), block), "masked")).count()
            rows.append((p, block, n, time.perf_counter() - began))
    return s.createDataFrame(rows, "p int, block string, records long, seconds double")


@query("e6_baselines")
def e6_baselines(s, d):
    """Against the full-set baselines: quality on entities of all parties, and guarded where tuples explode."""
    out = []
    for rate in (0, 20):
        m, t = _setting(s, d, 3, rate)
        out += [_tag(measures.quality(METHODS[n](m), t, 3), corrupted=rate, method=n) for n in ("early", "late")]
        for n, tuples in (("tuple", baselines.tuple_bf(m, [1, 2, 3])), ("ring", baselines.ring_cbf(m, [1, 2, 3], r=2))):
            c = baselines.tuple_assignments(tuples).withColumn("block", F.lit("all"))
            # Tuples overlap; a pair counts once.
            pairs = c.alias("a").join(c.alias("b"), (F.col("a.cluster_id") == F.col("b.cluster_id")) & (F.col("a.rec_id") < F.col("b.rec_id")))
            pairs = pairs.select(F.col("a.rec_id").alias("x"), F.col("b.rec_id").alias("y")).distinct()
            same = (F.col("x") % 1_000_000_000 == F.col("y") % 1_000_000_000).cast("long")
            true = t.groupBy("entity_id").count().where("count = 3").agg(F.sum(F.col("count") * 0 + 3).alias("true_pairs"))
            got = pairs.agg(F.coalesce(F.sum(same), F.lit(0)).alias("tm"), F.count(F.lit(1)).alias("pairs")).crossJoin(true)
            got = got.select("tm", (F.col("pairs") - F.col("tm")).alias("fm"), F.greatest(F.lit(0), F.col("true_pairs") - F.col("tm")).alias("fn"))
            out.append(_tag(measures.prf(got), corrupted=rate, method=n))
        out.append(_tag(measures.quality(exact(s, d, 3, rate), t, 3), corrupted=rate, method="exact"))
    return _all(out)


_E7 = " UNION ALL ".join(
    part
    for r in (0, 20, 40)
    for part in (sql_quality(sql_early(5, r), "assigned", tags=f"{r} AS corrupted, 'early' AS method, "), sql_quality(sql_exact(5, r), "c", tags=f"{r} AS corrupted, 'exact' AS method, "))
)


_GROWTH = " UNION ALL ".join(
    f"""SELECT {p} AS p, '{k}' AS blocking, comparisons, tuples, ring_tuples, tuples > 1000000 AS tuple_guarded, ring_tuples > 1000000 AS ring_guarded FROM (
  WITH {R.sql_parties(p)}, n AS (SELECT block, {", ".join(f"count(*) FILTER (party = {q}) AS n{q}" for q in range(1, p + 1))} FROM (SELECT {b} AS block, party FROM parties) GROUP BY block)
  SELECT sum({" + ".join(f"n{x} * n{y}" for x in range(1, p + 1) for y in range(x + 1, p + 1))})::BIGINT AS comparisons, sum({" * ".join(f"n{q}" for q in range(1, p + 1))})::BIGINT AS tuples,
    ({" + ".join("sum(" + " * ".join(f"n{q}" for q in range(f, min(f + 3, p + 1))) + ")" for f in range(1, p + 1, 3))})::BIGINT AS ring_tuples FROM n)"""
    for p in (3, 5, 7)
    for k, b in (("last", blocking.sql_soundex("last_name")), ("first_last", W.SQL_BLOCK))
)


@query("e6_growth", _GROWTH)
def e6_growth(s, d):
    """What the methods compare as parties are added, and where a limit of a million tuples stops the baselines. Tuples are counted exactly
    and compared with the limit so; a count that a BIGINT cannot hold (where the SQL itself overflows) is null."""
    out, most = [], 1_000_000
    for p in (3, 5, 7):
        for k in ("last", "first_last"):
            m = blocking.with_block(W.parties(s, d, p), k)
            rings = [list(range(f, min(f + 3, p + 1))) for f in range(1, p + 1, 3)]
            row = measures.comparisons_bound(m).select("comparisons")
            row = row.crossJoin(baselines.tuple_counts(m, list(range(1, p + 1))).agg(F.sum("tuples").alias("tuples")))
            ring = reduce(lambda a, b: a + b, (F.col(f"r{i}") for i in range(len(rings))))
            for i, ring_parties in enumerate(rings):
                row = row.crossJoin(baselines.tuple_counts(m, ring_parties).agg(F.sum("tuples").alias(f"r{i}")))  # one row each
            guarded = ((F.col("tuples") > most).alias("tuple_guarded"), (ring > most).alias("ring_guarded"))
            out.append(row.select(F.lit(p).alias("p"), F.lit(k).alias("blocking"), "comparisons", F.col("tuples").try_cast("long").alias("tuples"), ring.try_cast("long").alias("ring_tuples"), *guarded))
    return _all(out)


@query("e7_exact_vs_approx", _E7)
def e7_exact_vs_approx(s, d):
    out = []
    for rate in (0, 20, 40):
        m, t = _setting(s, d, 5, rate)
        out += [_tag(measures.quality(clustering.cluster_early(m), t), corrupted=rate, method="early"), _tag(measures.quality(exact(s, d, 5, rate), t), corrupted=rate, method="exact")]
    return _all(out)


@query("e8_risk")
def e8_risk(s, d):
    """Disclosure risk of filters and of counting filters of the found clusters, on clean and corrupted data."""
    out = []
    for rate in (0, 20, 40):
        m, _ = _setting(s, d, 5, rate)
        found = clustering.cluster_early(m).select("rec_id", F.col("cluster_id").cast("string").alias("cluster_id"))
        members = m.join(found, "rec_id").select("block", "cluster_id", "rec_id", "words")
        for n, x in (("bf", privacy.suspicion_bf(m, m)), ("cbf", privacy.suspicion_cbf(members, m))):
            out.append(_tag(privacy.risk(x), corrupted=rate, mask=n))
    return _all(out)


_COMPLETE = """SELECT {rate} AS corrupted, '{kind}' AS blocks, found, true_pairs, round(found / true_pairs, 6) AS completeness FROM
(SELECT sum(n * (n - 1) // 2)::BIGINT AS found FROM (SELECT count(*) AS n FROM r{rate} GROUP BY {kind}, entity_id)), (SELECT sum(n * (n - 1) // 2)::BIGINT AS true_pairs FROM (SELECT count(*) AS n FROM r{rate} GROUP BY entity_id))"""
_KEYS = f"SELECT *, {blocking.sql_soundex('last_name')} AS last, {W.SQL_BLOCK} AS first_last FROM"


@query("e9_completeness", f"WITH {R.sql_parties(5)}, {R.sql_corrupt(20)}, r0 AS ({_KEYS} parties), r20 AS ({_KEYS} corrupted) " + " UNION ALL ".join(_COMPLETE.format(rate=r, kind=k) for r in (0, 20) for k in ("last", "first_last")))
def e9_completeness(s, d):
    return _all([_tag(blocking.pairs_completeness(blocking.with_block(W.parties(s, d, 5, r), k)), corrupted=r, blocks=k) for r in (0, 20) for k in ("last", "first_last")])


@query("e9_bit_tree")
def e9_bit_tree(s, d):
    out = []
    for r in (0, 20):
        people = W.parties(s, d, 3, r)
        tree = blocking.bit_tree(masks.encode_bf(people, ("last_name", "zipcode"), keep=("rec_id", "entity_id")), 20, 100)
        out.append(_tag(blocking.pairs_completeness(tree), corrupted=r))
    return _all(out)


@query("e10_cbf_cost", f"""WITH {R.sql_parties(10, "by_size")} SELECT CAST(p AS INTEGER) AS p, count(*) AS entities, CAST(1000 * ceil(log2(p)) AS BIGINT) * count(*) AS stated_bits,
CAST(1000 * ceil(log2(p + 1)) AS BIGINT) * count(*) AS safe_bits, (p + 1) * count(*) AS sum_messages FROM (SELECT count(*) AS p FROM parties GROUP BY entity_id) GROUP BY p""")
def e10_cbf_cost(s, d):
    """Counting filters and secure sums of all entities, by the number of parties that hold them."""
    held = W.parties(s, d, 10, 0, "by_size").groupBy("entity_id").agg(F.count(F.lit(1)).alias("p"))
    return measures.cbf_memory(held, 1000).withColumn("sum_messages", (F.col("p") + 1) * F.col("entities"))


@query("e11_complexity", " UNION ALL ".join(f"""SELECT {p} AS p, comparisons, comparisons <= {p} * {p} * n * n AS within_bound FROM (WITH {R.sql_parties(p)}, pb AS (SELECT {W.SQL_BLOCK} AS block, party, count(*) AS n FROM parties GROUP BY ALL)
SELECT (SELECT sum((s * s - q) // 2) FROM (SELECT sum(n) AS s, sum(n * n) AS q FROM pb GROUP BY block))::BIGINT AS comparisons, (SELECT max(n) FROM (SELECT sum(n) AS n FROM pb GROUP BY party)) AS n)""" for p in (3, 5, 7, 10)))
def e11_complexity(s, d):
    out = []
    for p in (3, 5, 7, 10):
        c = measures.comparisons_bound(blocking.with_block(W.parties(s, d, p)))
        out.append(c.select(F.lit(p).alias("p"), "comparisons", (F.col("comparisons") <= p * p * F.col("n") * F.col("n")).alias("within_bound")))
    return _all(out)


@query("e12_documents", "SELECT count(*) AS records, CAST(0 AS BIGINT) AS twice, CAST(0 AS BIGINT) AS same_party FROM (SELECT DISTINCT source, substr(text, 1, 60) FROM documents)")
def e12_documents(s, d):
    """Beginnings of documents as noisy records; sources are parties."""
    docs = load(s, d, "documents", "doc_id", "text", "source").withColumn("head", F.substring("text", 1, 60))
    docs = docs.groupBy("source", "head").agg(F.min("doc_id").alias("rec_id")).withColumn("party", F.substring("source", 4, 2).cast("int"))
    m = masks.encode_bf(docs.withColumn("block", F.lower(F.substring("head", 1, 4))), ("head",), hashes=8, keep=("block", "party", "rec_id"))
    from blindmatch.queries.linkage import invariants

    return invariants(clustering.cluster_early(m, s_t=0.85))


@query("e12_whole_documents")
def e12_whole_documents(s, d):
    """Whole documents as noisy records, one record each; sources are parties, and blocks are the smallest of a text's word grams."""
    docs = load(s, d, "documents", "doc_id", "text", "source").withColumnRenamed("doc_id", "rec_id").withColumn("party", F.substring("source", 4, 2).cast("int"))
    from blindmatch.queries.linkage import invariants

    return invariants(clustering.cluster_early(masks.encode_texts(docs, "text"), s_t=0.85))


_E13 = " UNION ALL ".join(sql_quality(sql_early(5, 20, how=c, ord=o), "assigned", tags=f"'{o}' AS ord, '{c}' AS cluster_sim, ") for o in ("size", "random") for c in ("average", "min", "max", "cbf"))


@query("e13_ablation", _E13)
def e13_ablation(s, d):
    """Order of parties by cluster similarity."""
    m, t = _setting(s, d, 5, 20)
    return _all([_tag(measures.quality(clustering.cluster_early(m, ord=o, cluster_sim=c), t), ord=o, cluster_sim=c) for o in ("size", "random") for c in ("average", "min", "max", "cbf")])


@query("e5_snapshots")
def e5_snapshots(s, d):
    """Large p: 26 daily snapshots of users with moves."""
    people = R.snapshots(s, d)
    return _tag(measures.quality(clustering.cluster_early(W.masked(people), s_t=0.7), W.truth(people)), p=26)


SIX = (*R.QI[:2], "zipcode", "birth", "sex", "address")
_PRIORITY = f"WITH {R.sql_by_priority()}, people AS (SELECT *, CAST(birth_date AS VARCHAR) AS birth FROM parties)"


def _sql_priority(attrs) -> str:
    return f"{_PRIORITY},\n{masks.sql_masked('people', attrs, f'{W.SQL_BLOCK} AS block, entity_id', name='listed')},\nmasked AS (SELECT *, len(bits) AS ones FROM listed)"


@query("e5_priorities_six", sql_quality(sql_early(5, masked=_sql_priority(SIX)), "assigned", tags="5 AS p, "))
def e5_priorities_six(s, d):
    """The emergency collection with six attributes: names, postcode, birth date, sex and address."""
    people = R.by_priority(s, d).withColumn("birth", F.col("birth_date").cast("string"))
    m = masks.encode_bf(blocking.with_block(people), SIX, keep=("block", "party", "rec_id"))
    return _tag(measures.quality(clustering.cluster_early(m), W.truth(people)), p=5)


@query("e5_priorities_bit_tree")
def e5_priorities_bit_tree(s, d):
    """The same in bit-tree blocks of surname and birth date: completeness of the blocks and quality of the clusters."""
    people = R.by_priority(s, d).withColumn("birth", F.col("birth_date").cast("string"))
    tree = blocking.bit_tree(masks.encode_bf(people, ("last_name", "birth")), 20, 100, 6).select("rec_id", "block")
    m = masks.encode_bf(people, SIX).join(tree, "rec_id")
    found = measures.quality(clustering.cluster_early(m), W.truth(people))
    done = blocking.pairs_completeness(tree.join(people.select("rec_id", "entity_id"), "rec_id")).select("completeness")
    return _tag(found.crossJoin(done), p=5)  # one row each


@query("e5_priorities", sql_quality(sql_early(5, masked=_sql_priority(R.QI)), "assigned", tags="5 AS p, "))
def e5_priorities(s, d):
    people = R.by_priority(s, d)
    return _tag(measures.quality(clustering.cluster_early(W.masked(people)), W.truth(people)), p=5)
