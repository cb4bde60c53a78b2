"""Queries of mappings, clustering protocols, baselines, measures and attacks."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blindmatch.functions import blocking, masks
from blindmatch.operators import assignment, baselines, clustering, measures, privacy
from blindmatch.plans.lineage import cut
from blindmatch.queries import workloads as W
from blindmatch.queries.early_sql import sql_clusters
from blindmatch.queries.prep import _NORM
from blindmatch.queries.registry import query
from blindmatch.sources import roster as R
from blindmatch.sources.tables import load

# -- mappings on the edges between two parties in last-name blocks ----------------------------------------


def edges(s, d) -> assignment.CloseEdges:
    """Edges between parties 1 and 2 by at least 0.55, given to the mappings as masks; they are nearly all pairs of a block."""
    m = W.masked(W.parties(s, d, 3, 20), "last")

    def table() -> DataFrame:
        p = W.close_pairs(m, 1, 2, 0.55)
        w = F.round(masks.dice(F.col("z"), F.col("a_ones") + F.col("b_ones")), 9)
        return p.select("block", F.col("a_id").alias("x"), F.col("b_id").alias("y"), w.alias("weight")).where("weight >= 0.55")

    return assignment.CloseEdges(W.two_sides(m, 1, 2), 0.55, W.tiles, table)


_EDGES = f"""{W.sql_masked(3, 20, "entity_id", blocking.sql_soundex("last_name"))}, {W.SQL_PAIRS},
edges AS (SELECT * FROM (SELECT p.block, a_id AS x, b_id AS y, round(2.0 * z / (a_ones + b_ones), 9) AS weight FROM pairs p WHERE a_id < 3000000000 AND b_id < 3000000000) WHERE weight >= 0.55)"""


@query("assign_best_link", f"{_EDGES} SELECT block, arg_min(x, (-weight, x)) AS x, y, max(weight) AS weight FROM edges GROUP BY block, y")
def assign_best_link(s, d):
    return assignment.assign_best_link(edges(s, d))


_RECURSIVE = _EDGES.replace("WITH ", "WITH RECURSIVE ", 1)


@query("assign_greedy", f"""{_RECURSIVE},
ranked AS (SELECT *, row_number() OVER (PARTITION BY block ORDER BY x, weight DESC, y) AS r FROM edges),
run AS (
  SELECT block, 0::BIGINT AS r, []::BIGINT[] AS ux, []::BIGINT[] AS uy, NULL::BIGINT AS x, NULL::BIGINT AS y, NULL::DOUBLE AS weight FROM (SELECT DISTINCT block FROM edges)
  UNION ALL
  SELECT n.block, n.r, CASE WHEN free THEN list_append(ux, n.x) ELSE ux END, CASE WHEN free THEN list_append(uy, n.y) ELSE uy END, CASE WHEN free THEN n.x END, n.y, n.weight
  FROM (SELECT e.*, ux, uy, NOT list_contains(ux, e.x) AND NOT list_contains(uy, e.y) AS free FROM run JOIN ranked e ON e.block = run.block AND e.r = run.r + 1) n)
SELECT block, x, y, weight FROM run WHERE x IS NOT NULL""")
def assign_greedy(s, d):
    return assignment.assign_greedy(edges(s, d))


@query("assign_best_first", f"""{_RECURSIVE},
ranked AS (SELECT *, row_number() OVER (PARTITION BY block ORDER BY weight DESC, x, y) AS r FROM edges),
run AS (
  SELECT block, 0::BIGINT AS r, []::BIGINT[] AS ux, []::BIGINT[] AS uy, NULL::BIGINT AS x, NULL::BIGINT AS y, NULL::DOUBLE AS weight FROM (SELECT DISTINCT block FROM edges)
  UNION ALL
  SELECT n.block, n.r, CASE WHEN free THEN list_append(ux, n.x) ELSE ux END, CASE WHEN free THEN list_append(uy, n.y) ELSE uy END, CASE WHEN free THEN n.x END, n.y, n.weight
  FROM (SELECT e.*, ux, uy, NOT list_contains(ux, e.x) AND NOT list_contains(uy, e.y) AS free FROM run JOIN ranked e ON e.block = run.block AND e.r = run.r + 1) n)
SELECT block, x, y, weight FROM run WHERE x IS NOT NULL""")
def assign_best_first(s, d):
    return assignment.assign_best_first(edges(s, d))


@query("assign_unmatched", f"""{_EDGES}, b AS (SELECT block, arg_min(x, (-weight, x)) AS x, y FROM edges GROUP BY block, y)
SELECT DISTINCT block, x FROM edges ANTI JOIN b USING (block, x)""")
def assign_unmatched(s, d):
    e = edges(s, d)
    return assignment.unmatched(assignment.left_vertices(e), assignment.assign_best_link(e), "x")


@query("assign_certificate", f"{_EDGES} SELECT (SELECT count(*) FROM edges) > 0 AS has_edges, CAST(0 AS BIGINT) AS violations")
def assign_certificate(s, d):
    c = assignment.certify(edges(s, d))
    bad = (F.abs(F.col("primal") - F.col("dual")) > 1e-9) | (F.col("slack") < -1e-9)
    return c.agg((F.count(F.lit(1)) > 0).alias("has_edges"), F.sum(bad.cast("long")).alias("violations"))


@query("assign_optimal_total", "SELECT true AS one_to_one, true AS optimal")
def assign_optimal_total(s, d):
    """One-to-one on both sides, and its total is the certificate's dual bound."""
    e = edges(s, d)
    best = assignment.assign_optimal(e)
    twice = best.groupBy("block", "x").count().where("count > 1").union(best.groupBy("block", "y").count().where("count > 1"))
    got = best.agg(F.sum("weight").alias("total"))
    bound = assignment.certify(e).agg(F.sum("dual").alias("dual"))
    n = twice.agg(F.count(F.lit(1)).alias("twice"))
    return got.crossJoin(bound).crossJoin(n).select((F.col("twice") == 0).alias("one_to_one"), (F.abs(F.col("total") - F.col("dual")) < 1e-6).alias("optimal"))


@query("mapping_gain", "SELECT true AS optimal_at_least_greedy")
def mapping_gain(s, d):
    e = edges(s, d)
    a = assignment.assign_optimal(e).agg(F.sum("weight").alias("best"))
    b = assignment.assign_greedy(e).agg(F.sum("weight").alias("greedy"))
    return a.crossJoin(b).select((F.col("best") >= F.col("greedy") - 1e-9).alias("optimal_at_least_greedy"))


# -- clustering ----------------------------------------------------------------------------------------


def invariants(found: DataFrame) -> DataFrame:
    """Records assigned, records assigned twice, and clusters with two records of a party."""
    a = found.agg(F.count(F.lit(1)).alias("records"), (F.count(F.lit(1)) - F.count_distinct("rec_id")).alias("twice"))
    b = found.groupBy("block", "cluster_id", "party").count().agg(F.coalesce(F.sum((F.col("count") > 1).cast("long")), F.lit(0)).alias("same_party"))
    return a.crossJoin(b)


_INVARIANT = f"WITH {R.sql_parties(5)} SELECT count(*) AS records, CAST(0 AS BIGINT) AS twice, CAST(0 AS BIGINT) AS same_party FROM parties"

def _members(found: DataFrame) -> DataFrame:
    return found.select("rec_id", "cluster_id", "cluster_size")


for _name, _run, _how in (
    ("early_clusters", {}, {}),
    ("early_distributed", {"mode": "distributed"}, {}),
    ("greedy_clusters", {"mapping": "greedy"}, {"mapping": "greedy"}),
    ("early_cbf", {"cluster_sim": "cbf"}, {"how": "cbf"}),
    ("early_min", {"cluster_sim": "min"}, {"how": "min"}),
    ("early_max", {"cluster_sim": "max"}, {"how": "max"}),
    ("early_random_order", {"ord": "random"}, {"ord": "random"}),
):
    query(_name, sql_clusters(5, **_how))(lambda s, d, k=_run: _members(clustering.cluster_early(W.masked(W.parties(s, d, 5, 20)), **k)))


def sound(found: DataFrame, truth: DataFrame, least: float) -> DataFrame:
    """Invariants, and whether F over pairs is at least a floor, which clusters of single records miss."""
    found = cut(found, "found")
    return invariants(found).crossJoin(measures.quality(found, truth).select((F.col("f") >= least).alias("f_above")))


for _name, _run in {
    "late_clusters": lambda m: clustering.cluster_late(m),
    "late_keep": lambda m: clustering.cluster_late(m, leftover="keep"),
    "late_absorb": lambda m: clustering.cluster_late(m, merge="absorb"),
}.items():
    query(_name, _INVARIANT.replace("AS same_party FROM", "AS same_party, true AS f_above FROM"))(
        lambda s, d, f=_run: sound(f(W.masked(W.parties(s, d, 5, 20))), W.truth(W.parties(s, d, 5, 20)), 0.75)
    )


@query("early_cbf_resalted", _INVARIANT.replace("AS same_party FROM", "AS same_party, true AS f_above FROM"))
def early_cbf_resalted(s, d):
    """Counting-filter rounds in which all records are encoded anew."""
    people = blocking.with_block(W.parties(s, d, 5, 20)).select("block", "party", "rec_id", "entity_id", *R.QI)
    people = cut(people, "people")
    return sound(clustering.cluster_early_reencoded(people, R.QI, blocking.party_order(people, "size")), W.truth(people), 0.75)


_CLEAR = f"""WITH {R.sql_parties(3)}, {R.sql_corrupt(20)},
masked AS (SELECT *, len(bits) AS ones FROM (SELECT rec_id, entity_id, party, {W.SQL_BLOCK} AS block, list_distinct(flatten([{", ".join(masks.sql_grams(a) for a in R.QI)}])) AS bits FROM corrupted))"""


@query("cleartext_clusters", sql_clusters(3, masked=_CLEAR))
def cleartext_clusters(s, d):
    """Early mapping on the gram sets themselves: what the masks' collisions cost is the difference to it."""
    return _members(clustering.cluster_early(clustering.clear_grams(blocking.with_block(W.parties(s, d, 3, 20)), R.QI)))


@query("modes_agree", f"WITH {R.sql_parties(3)} SELECT count(*) AS records, CAST(0 AS BIGINT) AS differ FROM parties")
def modes_agree(s, d):
    m = W.masked(W.parties(s, d, 3, 20))
    a, b = clustering.cluster_early(m, mode="block"), clustering.cluster_early(m, mode="auto", task_records=4)
    both = a.join(b.select("rec_id", F.col("cluster_id").alias("other")), "rec_id")
    return both.agg(F.count(F.lit(1)).alias("records"), F.sum((F.col("cluster_id") != F.col("other")).cast("long")).alias("differ"))


@query("extend_equals_batch", f"WITH {R.sql_parties(4)} SELECT count(*) AS records, CAST(0 AS BIGINT) AS differ FROM parties")
def extend_equals_batch(s, d):
    m = W.masked(W.parties(s, d, 4, 20))
    batch = clustering.cluster_early(m, ord=[1, 2, 3, 4], mode="block")
    first = clustering.cluster_early(m.where("party < 4"), ord=[1, 2, 3], mode="block")
    grown = clustering.extend(first, m, 4)
    both = batch.join(grown.select("rec_id", F.col("cluster_id").alias("other")), "rec_id")
    return both.agg(F.count(F.lit(1)).alias("records"), F.sum((F.col("cluster_id") != F.col("other")).cast("long")).alias("differ"))


@query("link_two_party", sql_clusters(2, rate=0))
def link_two_party(s, d):
    return _members(clustering.cluster_early(W.masked(W.parties(s, d, 2))))


_COMPONENTS = f"""{W.sql_masked(3, 20).replace("WITH ", "WITH RECURSIVE ", 1)}, {W.SQL_PAIRS},
linked AS (SELECT a_id AS u, b_id AS v FROM pairs WHERE 2.0 * z / (a_ones + b_ones) >= 0.8),
both_ways AS (SELECT u, v FROM linked UNION SELECT v, u FROM linked),
reach AS (SELECT rec_id AS u, rec_id AS v FROM masked UNION SELECT r.u, b.v FROM reach r JOIN both_ways b ON r.v = b.u)"""


@query("pairwise_components", f"{_COMPONENTS} SELECT u AS rec_id, min(v) AS cluster_id, CAST(count(*) AS INTEGER) AS cluster_size FROM reach GROUP BY u")
def pairwise_components(s, d):
    return clustering.cluster_components(W.masked(W.parties(s, d, 3, 20))).select("rec_id", "cluster_id", "cluster_size")


def exact(s, d, p=3, rate=0) -> DataFrame:
    """Clusters of identical digests: block, cluster_id, party, rec_id, cluster_size."""
    m = W.parties(s, d, p, rate).select("party", "rec_id", masks.exact_mask(R.QI).alias("digest"))
    n = m.groupBy("digest").agg(F.count(F.lit(1)).cast("int").alias("cluster_size"))
    return m.join(n, "digest").select(F.lit("all").alias("block"), F.col("digest").alias("cluster_id"), "party", "rec_id", "cluster_size")


def sql_exact(p=3, rate=0) -> str:
    ctes, name = W.sql_people(p, rate)
    return f"WITH {ctes}, m AS (SELECT party, rec_id, entity_id, md5(concat_ws('|', 'key', {_NORM})) AS cluster_id FROM {name}), c AS (SELECT *, CAST(count(*) OVER (PARTITION BY cluster_id) AS INTEGER) AS cluster_size FROM m)"


for _name, _m in (("matches_min_size", 2), ("matches_full_set", 3)):
    query(_name, f"{sql_exact()} SELECT cluster_id, party, rec_id, cluster_size FROM c WHERE cluster_size >= {_m}")(
        lambda s, d, m=_m: clustering.matches(exact(s, d), m).select("cluster_id", "party", "rec_id", "cluster_size")
    )


def _sets(s, d):
    return exact(s, d).groupBy("block", "cluster_id").agg(F.sort_array(F.collect_list(F.struct("party", "rec_id"))).alias("members"))


@query("late_split", f"""{sql_exact()}, r AS (SELECT string_agg(CAST(rec_id AS VARCHAR), ',' ORDER BY party, rec_id) AS members FROM c WHERE party <> 2 GROUP BY cluster_id
UNION SELECT CAST(rec_id AS VARCHAR) FROM c WHERE party = 2) SELECT members FROM r""")
def late_split(s, d):
    out = clustering.split(_sets(s, d), 2)
    return out.select(F.array_join(F.transform("members", lambda m: m["rec_id"].cast("string")), ",").alias("members"))


@query("late_drop_subset", f"""{sql_exact()}, s AS (SELECT DISTINCT list_sort(list(rec_id)) AS m FROM c GROUP BY cluster_id UNION SELECT [rec_id] FROM c WHERE party = 2)
SELECT array_to_string(a.m, ',') AS members FROM s a WHERE NOT EXISTS (SELECT 1 FROM s b WHERE len(b.m) > len(a.m) AND list_has_all(b.m, a.m) AND b.m[1] = least(b.m[1], a.m[1]) AND list_contains(b.m, a.m[1]))""")
def late_drop_subset(s, d):
    """Sets that are no proper subset of another, by a join on one member and a containment test."""
    sets = _sets(s, d).select(F.sort_array(F.transform("members", lambda m: m["rec_id"])).alias("m"))
    sets = sets.union(exact(s, d).where("party = 2").select(F.array("rec_id").alias("m"))).distinct()
    a = sets.select("m", F.element_at("m", 1).alias("k"))
    b = sets.select(F.col("m").alias("o"), F.explode("m").alias("k"))
    inside = a.join(b, "k").where((F.size("o") > F.size("m")) & (F.size(F.array_intersect("o", "m")) == F.size("m"))).select("m")
    return sets.join(inside, "m", "left_anti").select(F.array_join(F.transform("m", lambda x: x.cast("string")), ",").alias("members"))


@query("merge_step", f"""{sql_exact()}, x AS (SELECT cluster_id, min(rec_id) AS seed FROM c WHERE party < 3 GROUP BY cluster_id),
a AS (SELECT rec_id, coalesce(seed, rec_id) AS cluster_id FROM c LEFT JOIN x USING (cluster_id)) SELECT cluster_id, count(*) AS n FROM a GROUP BY cluster_id""")
def merge_step(s, d):
    """Records of party 3 join the cluster that they are mapped to, or stay alone."""
    c = exact(s, d)
    seeds = c.where("party < 3").groupBy("cluster_id").agg(F.min("rec_id").alias("seed"))
    return c.join(seeds, "cluster_id", "left").groupBy(F.coalesce("seed", "rec_id").alias("cluster_id")).agg(F.count(F.lit(1)).alias("n"))


@query("reveal_attributes", f"{sql_exact()} SELECT c.cluster_id, c.party, c.rec_id, p.city, p.sex FROM c JOIN parties p USING (party, rec_id) WHERE cluster_size >= 2")
def reveal_attributes(s, d):
    return clustering.reveal(clustering.matches(exact(s, d), 2), W.parties(s, d), ["city", "sex"]).select("cluster_id", "party", "rec_id", "city", "sex")


# -- baselines -----------------------------------------------------------------------------------------


def _tuple_sql(p: int, rings: list[list[int]], s_t: float) -> str:
    """All ring tuples by their Dice, combined in a block and tested again."""
    out = [W.sql_masked(p, 20)]
    for r, ring in enumerate(rings):
        a = [f"t{q}" for q in ring]
        both = reduce(lambda x, y: f"list_intersect({x}, {y})", (f"{t}.bits" for t in a))
        joins = f"masked {a[0]} " + " ".join(f"JOIN masked {t} ON {t}.block = {a[0]}.block" for t in a[1:])
        where = " AND ".join(f"t{q}.party = {q}" for q in ring)
        out.append(f"ring{r} AS (SELECT {a[0]}.block, {both} AS bits, {' + '.join(t + '.ones' for t in a)} AS total, {', '.join(t + '.rec_id AS id' + t for t in a)} FROM {joins} WHERE {where})")
        out.append(f"kept{r} AS (SELECT * FROM ring{r} WHERE len(bits) * {len(ring)} >= {s_t} * total)")
    names = [f"kept{r}" for r in range(len(rings))]
    bits = reduce(lambda x, y: f"list_intersect({x}, {y})", (f"{n}.bits" for n in names))
    total = " + ".join(f"{n}.total" for n in names)
    joins = names[0] + "".join(f" JOIN {n} ON {n}.block = {names[0]}.block" for n in names[1:])
    ids = " || ',' || ".join(f"idt{q}" for ring in rings for q in ring)
    out.append(f"done AS (SELECT {ids} AS ids, len({bits}) * {p} * 1.0 / ({total}) AS dice FROM {joins})")
    return ",\n".join(out) + f" SELECT ids, round(dice, 9) AS dice FROM done WHERE dice >= {s_t}"


def _tuple_rows(t: DataFrame) -> DataFrame:
    return t.select(F.array_join(F.transform("ids", lambda x: x.cast("string")), ",").alias("ids"), F.round("dice", 9).alias("dice"))


@query("baseline_tuple_bf", _tuple_sql(3, [[1, 2, 3]], 0.7))
def baseline_tuple_bf(s, d):
    return _tuple_rows(baselines.tuple_bf(W.masked(W.parties(s, d, 3, 20)), [1, 2, 3], 0.7))


@query("baseline_tuple_bf_pruned", _tuple_sql(3, [[1, 2, 3]], 0.7))
def baseline_tuple_bf_pruned(s, d):
    return _tuple_rows(baselines.tuple_bf(W.masked(W.parties(s, d, 3, 20)), [1, 2, 3], 0.7, prune=True))


@query("baseline_ring_cbf", _tuple_sql(4, [[1, 2], [3, 4]], 0.7))
def baseline_ring_cbf(s, d):
    return _tuple_rows(baselines.ring_cbf(W.masked(W.parties(s, d, 4, 20)), [1, 2, 3, 4], 0.7, r=2))


@query("baseline_ring_cbf_bound", _tuple_sql(4, [[1, 2, 3, 4]], 0.7))
def baseline_ring_cbf_bound(s, d):
    return _tuple_rows(baselines.ring_cbf(W.masked(W.parties(s, d, 4, 20)), [1, 2, 3, 4], 0.7, r=2, ring_filter="bound"))


@query("baseline_exact", f"{sql_exact(5, 20)}, o AS (SELECT cluster_id, party, min(rec_id) AS rec_id FROM c GROUP BY ALL) SELECT cluster_id AS digest, count(*) AS n, string_agg(CAST(rec_id AS VARCHAR), ',' ORDER BY rec_id) AS rec_ids FROM o GROUP BY cluster_id HAVING count(*) >= 2")
def baseline_exact(s, d):
    m = W.parties(s, d, 5, 20).select("party", "rec_id", masks.exact_mask(R.QI).alias("digest"))
    return baselines.exact_match(m, 2)


@query("cleartext_dice", f"""WITH {R.sql_parties(3)}, {R.sql_corrupt(20)},
g AS (SELECT rec_id, party, {W.SQL_BLOCK} AS block, list_distinct(flatten([{", ".join(masks.sql_grams(a) for a in R.QI)}])) AS grams FROM corrupted)
SELECT a.rec_id AS a_id, b.rec_id AS b_id, round(2.0 * len(list_intersect(a.grams, b.grams)) / (len(a.grams) + len(b.grams)), 9) AS sim FROM g a JOIN g b ON a.block = b.block AND a.party < b.party""")
def cleartext_dice(s, d):
    g = blocking.with_block(W.parties(s, d, 3, 20)).select("block", "party", "rec_id", masks.tokens_of(R.QI).alias("grams"))
    a, b = g.alias("a"), g.alias("b")
    z = F.size(F.array_intersect("a.grams", "b.grams"))
    pairs = a.join(b, (F.col("a.block") == F.col("b.block")) & (F.col("a.party") < F.col("b.party")))
    return pairs.select(F.col("a.rec_id").alias("a_id"), F.col("b.rec_id").alias("b_id"), F.round(masks.dice(z, F.size("a.grams") + F.size("b.grams")), 9).alias("sim"))


# -- measures ------------------------------------------------------------------------------------------

_QUALITY = f"""{sql_exact(5, 20)},
ce AS (SELECT cluster_id, entity_id, count(*) AS n FROM c WHERE cluster_size >= 2 GROUP BY ALL),
q AS (SELECT (SELECT coalesce(sum(n * (n - 1) // 2), 0) FROM ce)::BIGINT AS tm, (SELECT coalesce(sum(n * (n - 1) // 2), 0) FROM (SELECT count(*) AS n FROM c WHERE cluster_size >= 2 GROUP BY cluster_id))::BIGINT AS pairs,
  (SELECT sum(n * (n - 1) // 2) FROM (SELECT count(*) AS n FROM c GROUP BY entity_id))::BIGINT AS true_pairs)"""


@query("quality_pairs", f"{_QUALITY} SELECT tm, pairs - tm AS fm, true_pairs - tm AS fn FROM q")
def quality_pairs(s, d):
    return measures.quality_pairs(exact(s, d, 5, 20), W.truth(W.parties(s, d, 5, 20)))


@query("quality_prf", f"{_QUALITY} SELECT tm, pairs - tm AS fm, true_pairs - tm AS fn, round(tm / pairs, 6) AS precision, round(tm / true_pairs, 6) AS recall, round(2 * tm / (pairs + true_pairs), 6) AS f FROM q")
def quality_prf(s, d):
    return measures.quality(exact(s, d, 5, 20), W.truth(W.parties(s, d, 5, 20)))


@query("quality_clusters", f"""{sql_exact(5, 20)}, e AS (SELECT entity_id, count(*) AS size FROM c GROUP BY entity_id),
k AS (SELECT cluster_id, count(*) AS n, min(entity_id) AS lo, max(entity_id) AS hi FROM c WHERE cluster_size >= 2 GROUP BY cluster_id)
SELECT (SELECT count(*) FROM k) AS found, (SELECT count(*) FROM k JOIN e ON lo = entity_id WHERE lo = hi AND n = size) AS exact, (SELECT count(*) FROM e WHERE size >= 2) AS true_sets""")
def quality_clusters(s, d):
    return measures.quality_clusters(exact(s, d, 5, 20), W.truth(W.parties(s, d, 5, 20)))


@query("truth_by_subset", f"WITH {R.sql_parties(10, 'by_size')} SELECT held, count(*) AS entities, CAST(count(*) * held * (held - 1) // 2 AS BIGINT) AS pairs FROM (SELECT count(*) AS held FROM parties GROUP BY entity_id) GROUP BY held")
def truth_by_subset(s, d):
    return measures.truth_by_subset(W.truth(W.parties(s, d, 10, 0, "by_size")))


@query("comparisons_bound", f"""WITH {R.sql_parties(5)}, b AS (SELECT party, {W.SQL_BLOCK} AS block FROM parties), pb AS (SELECT block, party, count(*) AS n FROM b GROUP BY ALL),
k AS (SELECT sum(n) AS s, sum(n * n) AS q FROM pb GROUP BY block)
SELECT (SELECT sum((s * s - q) // 2) FROM k)::BIGINT AS comparisons, (SELECT count(*) FROM k) AS b, (SELECT count(DISTINCT party) FROM b) AS p, (SELECT max(n) FROM (SELECT count(*) AS n FROM b GROUP BY party)) AS n""")
def comparisons_bound(s, d):
    return measures.comparisons_bound(blocking.with_block(W.parties(s, d, 5)))


_COSTS = " UNION ALL ".join(f"""SELECT {p} AS p, '{k}' AS blocking, sum(s)::BIGINT AS records, count(*) AS blocks, max(s)::BIGINT AS largest_block, sum((s * s - q) // 2)::BIGINT AS comparisons,
sum(k)::BIGINT AS block_messages, sum(s)::BIGINT AS record_messages, (sum(s) * 128)::BIGINT AS mask_bytes, (max((s * s - q) // 2) * 8)::BIGINT AS largest_block_bytes
FROM (SELECT block, sum(n) AS s, sum(n * n) AS q, count(*) AS k FROM (WITH {R.sql_parties(p)} SELECT {b} AS block, party, count(*) AS n FROM parties GROUP BY ALL) GROUP BY block)"""
    for p in (3, 5, 7, 10) for k, b in (("last", blocking.sql_soundex("last_name")), ("first_last", W.SQL_BLOCK)))


@query("linkage_costs", _COSTS)
def linkage_costs(s, d):
    """Costs by number of parties and blocking key, counted on the tables."""
    rows = [
        measures.linkage_costs(W.masked(W.parties(s, d, p), k)).select(F.lit(p).alias("p"), F.lit(k).alias("blocking"), "*")
        for p in (3, 5, 7, 10)
        for k in ("last", "first_last")
    ]
    return reduce(lambda a, b: a.union(b), rows)


@query("join_self_pairs", f"{W.sql_masked(3, 20)}, {W.SQL_PAIRS} SELECT block, a_id, b_id, CAST(z AS BIGINT) AS z FROM pairs")
def join_self_pairs(s, d):
    return W.pairs_in_blocks(W.masked(W.parties(s, d, 3, 20))).select("block", "a_id", "b_id", "z")


@query("communication_cost", f"""WITH {R.sql_roster()}, k AS (SELECT count(*) AS n, count(DISTINCT block) AS b FROM (SELECT {W.SQL_BLOCK} AS block FROM roster))
SELECT CAST(p AS INTEGER) AS p, p * b AS block_messages, p * n AS record_messages, CAST(p + 1 AS BIGINT) AS sum_messages, CAST(p AS BIGINT) AS sum_messages_stated FROM k, (SELECT unnest([2, 3, 5, 7, 10, 26]) AS p)""")
def communication_cost(s, d):
    """Messages of a linkage of parties that hold all customers each."""
    return measures.communication(blocking.with_block(R.roster(s, d)), [2, 3, 5, 7, 10, 26])


@query("cbf_memory", """SELECT CAST(p AS INTEGER) AS p, count(*) AS entities, CAST(1000 * ceil(log2(p)) AS BIGINT) * count(*) AS stated_bits, CAST(1000 * ceil(log2(p + 1)) AS BIGINT) * count(*) AS safe_bits
FROM (SELECT count(DISTINCT o_orderpriority) AS p FROM orders GROUP BY o_custkey) GROUP BY p""")
def cbf_memory(s, d):
    """Counting filters of customers over the parties of order priorities that they are in."""
    return measures.cbf_memory(load(s, d, "orders", "o_custkey", "o_orderpriority").groupBy("o_custkey").agg(F.count_distinct("o_orderpriority").alias("p")), 1000)


# -- privacy -------------------------------------------------------------------------------------------

_SMALL = 64


def _small_filters(s, d):
    people = W.parties(s, d, 4).where("held_by > 1")
    return masks.encode_bf(people, ("first_name", "last_name"), length=_SMALL, hashes=3, keep=("entity_id", "party", "rec_id"), keep_bits=True)


_CTES = f"""WITH {R.sql_parties(4)}, {masks.sql_masked("parties", ("first_name", "last_name"), "entity_id, held_by", hashes=3, length=_SMALL)},
m AS (SELECT * FROM masked WHERE held_by > 1),
k AS (SELECT entity_id, pos, count(*) AS cnt FROM (SELECT entity_id, unnest(bits) AS pos FROM m) GROUP BY ALL),
n AS (SELECT entity_id, count(*) AS m FROM m GROUP BY entity_id),
v AS (SELECT entity_id, m, unnest(range(1, {_SMALL + 1})) AS pos FROM n),
a AS (SELECT entity_id, m, string_agg(CAST(coalesce(cnt, 0) AS VARCHAR), ',' ORDER BY pos) AS cbf FROM v LEFT JOIN k USING (entity_id, pos) GROUP BY ALL)"""


def _as_text(c: str):
    return F.array_join(F.transform(c, lambda x: x.cast("string")), ",")


@query("secure_sum_equals_cbf", f"{_CTES} SELECT entity_id, cbf, m + 1 AS messages FROM a")
def secure_sum_equals_cbf(s, d):
    log = privacy.secure_sum(_small_filters(s, d), ["entity_id"], _SMALL)
    return privacy.summed(log, ["entity_id"], _SMALL).select("entity_id", _as_text("cbf").alias("cbf"), "messages")


@query("secure_sum_shares", f"{_CTES} SELECT entity_id, cbf, m * m AS messages FROM a")
def secure_sum_shares(s, d):
    out = privacy.share_sum(_small_filters(s, d), ["entity_id"], _SMALL)
    return out.select("entity_id", _as_text("cbf").alias("cbf"), "messages")


@query("cbf_round_counts", f"""{W.sql_masked(4)}, k AS (SELECT block, party, count(*) AS n FROM masked GROUP BY ALL)
SELECT CAST(b.party - 1 AS INTEGER) AS iteration, sum(a.n * b.n)::BIGINT AS candidate_sums, CAST(b.party + 1 AS INTEGER) AS messages_each FROM k a JOIN k b ON a.block = b.block AND a.party < b.party GROUP BY b.party""")
def cbf_round_counts(s, d):
    """Candidate secure sums of each iteration if no record is mapped (the worst case), and messages of one sum."""
    k = blocking.with_block(W.parties(s, d, 4)).groupBy("block", "party").agg(F.count(F.lit(1)).alias("n"))
    a, b = k.alias("a"), k.alias("b")
    pairs = a.join(b, (F.col("a.block") == F.col("b.block")) & (F.col("a.party") < F.col("b.party")))
    return pairs.groupBy((F.col("b.party") - 1).alias("iteration"), (F.col("b.party") + 1).alias("messages_each")).agg(F.sum(F.col("a.n") * F.col("b.n")).alias("candidate_sums"))


def _attack(s, d):
    people = W.parties(s, d, 5, 20)
    m = masks.encode_bf(blocking.with_block(people), R.QI, keep=("block", "entity_id", "party", "rec_id"))
    return m, m.select("block", F.col("entity_id").cast("string").alias("cluster_id"), "rec_id", "words")


_ATTACK = f"""{W.sql_masked(5, 20)},
bf AS (SELECT m.rec_id, g.n AS n_g, 1.0 / g.n AS p_s FROM masked m JOIN (SELECT bits, count(*) AS n FROM masked GROUP BY bits) g USING (bits)),
cnt AS (SELECT block, entity_id, pos, count(*) AS c FROM (SELECT block, entity_id, unnest(bits) AS pos FROM masked) GROUP BY ALL),
sizes AS (SELECT block, entity_id, count(*) AS x FROM masked GROUP BY ALL HAVING count(*) > 1),
cb AS (SELECT block, entity_id, x, list(pos) FILTER (c = x) AS must, list(pos) AS may FROM cnt JOIN sizes USING (block, entity_id) GROUP BY ALL),
consistent AS (SELECT cb.block, cb.entity_id, x, count(*) AS n_g FROM cb JOIN masked g ON g.block = cb.block AND list_has_all(g.bits, must) AND list_has_all(may, g.bits) GROUP BY ALL),
cbf AS (SELECT m.rec_id, x, n_g, 1.0 / n_g AS p_s FROM masked m JOIN consistent USING (block, entity_id))"""


@query("suspicion_bf", f"{_ATTACK} SELECT rec_id, n_g, round(p_s, 9) AS p_s FROM bf")
def suspicion_bf(s, d):
    m, _ = _attack(s, d)
    return privacy.suspicion_bf(m, m).withColumn("p_s", F.round("p_s", 9))


@query("suspicion_cbf", f"{_ATTACK} SELECT rec_id, x, n_g, round(p_s, 9) AS p_s FROM cbf")
def suspicion_cbf(s, d):
    m, members = _attack(s, d)
    return privacy.suspicion_cbf(members, m).withColumn("p_s", F.round("p_s", 9))


_WORLD = f"""{W.sql_masked(3, 20)},
cnt AS (SELECT block, entity_id, pos, count(*) AS c FROM (SELECT block, entity_id, unnest(bits) AS pos FROM masked) GROUP BY ALL),
sizes AS (SELECT block, entity_id, count(*) AS x FROM masked GROUP BY ALL HAVING count(*) > 1),
cb AS (SELECT block, entity_id, x, list(pos) FILTER (c = x) AS must, list(pos) AS may FROM cnt JOIN sizes USING (block, entity_id) GROUP BY ALL),
post AS MATERIALIZED (SELECT unnest(bits) AS pos, rec_id, bits FROM masked),
often AS (SELECT pos, count(*) AS n FROM post GROUP BY pos),
rarest AS MATERIALIZED (SELECT block, entity_id, x, any_value(must) AS must, any_value(may) AS may, arg_min(pos, n) AS pos FROM (SELECT *, unnest(must) AS pos FROM cb) JOIN often USING (pos) GROUP BY ALL),
consistent AS (SELECT block, entity_id, x, count(*) AS n_g FROM rarest JOIN post USING (pos) WHERE list_has_all(bits, must) AND list_has_all(may, bits) GROUP BY ALL)"""


@query("suspicion_cbf_global", f"{_WORLD} SELECT m.rec_id, x, n_g, round(1.0 / n_g, 9) AS p_s FROM masked m JOIN consistent USING (block, entity_id)")
def suspicion_cbf_global(s, d):
    people = blocking.with_block(W.parties(s, d, 3, 20))
    m = masks.encode_bf(people, R.QI, keep=("block", "entity_id", "party", "rec_id"), keep_bits=True)
    members = m.select("block", F.col("entity_id").cast("string").alias("cluster_id"), "rec_id", "words", "bits")
    return privacy.suspicion_cbf_global(members, m).withColumn("p_s", F.round("p_s", 9))


_RISK = "count(*) AS records, round(avg(p_s), 6) AS dr_mean, round(avg(CASE WHEN p_s >= 1 THEN 1.0 ELSE 0.0 END), 6) AS dr_marketer"


@query("dr_risks", f"{_ATTACK} SELECT 'bf' AS mask, {_RISK} FROM bf UNION ALL SELECT 'cbf', {_RISK} FROM cbf")
def dr_risks(s, d):
    m, members = _attack(s, d)
    a, b = privacy.risk(privacy.suspicion_bf(m, m)), privacy.risk(privacy.suspicion_cbf(members, m))
    return a.select(F.lit("bf").alias("mask"), "*").union(b.select(F.lit("cbf").alias("mask"), "*"))


@query("risk_bound", "SELECT CAST(0 AS BIGINT) AS violations")
def risk_bound(s, d):
    """The risk of a counting filter of x records is at most 1 / x."""
    m, members = _attack(s, d)
    return privacy.suspicion_cbf(members, m).agg(F.sum((F.col("p_s") > 1.0 / F.col("x") + 1e-12).cast("long")).alias("violations"))
