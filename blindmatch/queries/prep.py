"""Queries of preparation, masks, similarities, blocking and workloads."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import Window

from blindmatch.functions import blocking, masks
from blindmatch.queries import workloads as W
from blindmatch.queries.registry import query
from blindmatch.sources import roster as R
from blindmatch.sources.tables import load


def text(c, sep=","):
    return F.array_join(F.transform(c, lambda x: x.cast("string")), sep)


COLS = ["party", "rec_id", "entity_id", "held_by", *R.QI, "sex", "address", "cast(birth_date as string) as birth_date", "amount"]
SQL_COLS = "party, rec_id, entity_id, held_by, first_name, last_name, city, zipcode, sex, address, CAST(birth_date AS VARCHAR) AS birth_date, amount"

for _name, _p, _rate, _profile in (("parties_w1", 5, 0, "quarter"), ("parties_w2", 10, 0, "by_size"), ("corrupt_20", 5, 20, "quarter"), ("corrupt_40", 5, 40, "quarter")):
    _ctes, _from = W.sql_people(_p, _rate, _profile)
    query(_name, f"WITH {_ctes} SELECT {SQL_COLS} FROM {_from}")(lambda s, d, a=(_p, _rate, _profile): W.parties(s, d, *a).selectExpr(*COLS))


@query("parties_snapshots", f"WITH {R.sql_snapshots()} SELECT party, rec_id, entity_id, first_name, last_name, city, zipcode FROM parties")
def parties_snapshots(s, d):
    return R.snapshots(s, d).select("party", "rec_id", "entity_id", *R.QI)


@query("parties_priority", f"WITH {R.sql_by_priority()} SELECT party, rec_id, entity_id, first_name, last_name, city, zipcode, sex FROM parties")
def parties_priority(s, d):
    return R.by_priority(s, d).select("party", "rec_id", "entity_id", *R.QI, "sex")


def dedup(df, keys, order):
    """One row a key, the first in order."""
    return df.withColumn("_r", F.row_number().over(Window.partitionBy(*keys).orderBy(*order))).where("_r = 1").drop("_r")


@query("dedup_party", "SELECT o_orderpriority AS party, o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderpriority, o_custkey ORDER BY o_orderdate DESC, o_orderkey) = 1")
def dedup_party(s, d):
    o = load(s, d, "orders", "o_orderpriority", "o_custkey", "o_orderkey", "o_orderdate").withColumnRenamed("o_orderpriority", "party")
    return dedup(o, ["party", "o_custkey"], [F.desc("o_orderdate"), "o_orderkey"]).select("party", "o_custkey", "o_orderkey")


@query("normalise_attrs", "SELECT c_custkey, trim(regexp_replace(regexp_replace(lower('  ' || c_name || '  X-' || c_mktsegment || '. '), '[^a-z0-9 ]', '', 'g'), ' +', ' ', 'g')) AS name FROM customer")
def normalise_attrs(s, d):
    c = load(s, d, "customer", "c_custkey", "c_name", "c_mktsegment")
    return c.select("c_custkey", masks.normalise(F.concat(F.lit("  "), "c_name", F.lit("  X-"), "c_mktsegment", F.lit(". "))).alias("name"))


@query("qgrams", f"WITH {R.sql_roster()} SELECT entity_id, array_to_string(list_sort({masks.sql_grams('city')}), ',') AS grams FROM roster")
def qgrams(s, d):
    return R.roster(s, d).select("entity_id", text(F.array_sort(masks.qgrams(F.col("city")))).alias("grams"))


@query("numeric_neighbours", "SELECT c_custkey, array_to_string(list_transform(range(CAST(floor(c_acctbal / 100.0) AS BIGINT) - 2, CAST(floor(c_acctbal / 100.0) AS BIGINT) + 3), lambda x: CAST(x AS VARCHAR)), ',') AS cells FROM customer")
def numeric_neighbours(s, d):
    return load(s, d, "customer", "c_custkey", "c_acctbal").select("c_custkey", text(masks.neighbours(F.col("c_acctbal"), 100.0, 2)).alias("cells"))


@query("bf_positions", f"WITH {R.sql_roster()} SELECT entity_id, array_to_string({masks.sql_positions(masks.sql_grams('last_name'))}, ',') AS positions FROM roster")
def bf_positions(s, d):
    return R.roster(s, d).select("entity_id", text(masks.positions(masks.qgrams(F.col("last_name")))).alias("positions"))


@query("bf_encode", f"{W.sql_masked()} SELECT rec_id, ones, array_to_string(bits, ',') AS bits FROM masked")
def bf_encode(s, d):
    return W.masked(W.parties(s, d), bits=True).select("rec_id", F.col("ones").cast("long"), text(F.col("bits")).alias("bits"))


@query("bf_packed_ones", f"{W.sql_masked()} SELECT rec_id, ones, ones AS packed_ones FROM masked")
def bf_packed_ones(s, d):
    return W.masked(W.parties(s, d)).select("rec_id", F.col("ones").cast("long"), masks.ones_of(F.col("words")).cast("long").alias("packed_ones"))


_TAGGED = "[" + ", ".join(f"list_transform({masks.sql_grams(a)}, lambda g: '{a}:' || g)" for a in R.QI) + "]"


@query("bf_record_level", f"WITH {R.sql_roster()} SELECT entity_id, len({masks.sql_positions(f'flatten({_TAGGED})')}) AS ones FROM roster")
def bf_record_level(s, d):
    return masks.encode_bf(R.roster(s, d), R.QI, tagged=True, keep=("entity_id",)).select("entity_id", F.col("ones").cast("long"))


@query("bf_attribute_level", f"WITH {R.sql_roster()} SELECT entity_id, " + ", ".join(f"len({masks.sql_positions(masks.sql_grams(a))}) AS {a}" for a in R.QI) + " FROM roster")
def bf_attribute_level(s, d):
    m = masks.encode_bf(R.roster(s, d), R.QI, level="attribute", keep=("entity_id",))
    return m.select("entity_id", *(masks.ones_of(F.col("words")[a]).cast("long").alias(a) for a in R.QI))


@query("salted_encodings_differ", f"WITH {W.sql_people()[0]} SELECT count(*) AS records, CAST(0 AS BIGINT) AS equal FROM parties")
def salted_encodings_differ(s, d):
    people = W.parties(s, d)
    a, b = (masks.encode_bf(people, R.QI, salt=f"run:{i}", keep=("rec_id",)) for i in (1, 2))
    both = a.join(b.select("rec_id", F.col("words").alias("other")), "rec_id")
    return both.agg(F.count(F.lit(1)).alias("records"), F.sum((F.col("words") == F.col("other")).cast("long")).alias("equal"))


@query("embedding_sign_mask", "SELECT vec_id, len(p) AS ones, array_to_string(p, ',') AS positions FROM (SELECT vec_id, list_filter(range(1, len(embedding) + 1), lambda i: embedding[i] > 0) AS p FROM embeddings)")
def embedding_sign_mask(s, d):
    e = load(s, d, "embeddings", "vec_id", "embedding").withColumn("bits", masks.sign_bits(F.col("embedding")))
    m = masks.encode_custom(e, F.col("bits"), 64, keep=("vec_id", ))
    return m.join(e, "vec_id").select("vec_id", F.bit_count(F.col("words").getItem(0)).cast("long").alias("ones"), text(F.col("bits")).alias("positions"))


_NORM = ", ".join(f"trim(regexp_replace(regexp_replace(lower({a}), '[^a-z0-9 ]', '', 'g'), ' +', ' ', 'g'))" for a in R.QI)


@query("exact_mask", f"WITH {R.sql_parties(3)} SELECT rec_id, md5(concat_ws('|', 'key', {_NORM})) AS digest FROM parties")
def exact_mask(s, d):
    return W.parties(s, d).select("rec_id", masks.exact_mask(R.QI).alias("digest"))


@query("bf_fill_rate", f"{W.sql_masked()} SELECT count(*) AS records, round(avg(ones) / 1000, 6) AS fill, max(ones) AS most FROM masked")
def bf_fill_rate(s, d):
    m = W.masked(W.parties(s, d))
    return m.agg(F.count(F.lit(1)).alias("records"), F.round(F.avg("ones") / 1000, 6).alias("fill"), F.max("ones").cast("long").alias("most"))


# -- similarities --------------------------------------------------------------------------------------

_PAIRS = {
    "dice_pairs": (lambda z, a, b: masks.dice(z, a + b), "2.0 * z / (a_ones + b_ones)"),
    "jaccard_pairs": (masks.jaccard, "z * 1.0 / (a_ones + b_ones - z)"),
    "overlap_pairs": (masks.overlap, "z * 1.0 / least(a_ones, b_ones)"),
}
for _name, (_f, _sql) in _PAIRS.items():
    query(_name, f"{W.sql_masked()}, {W.SQL_PAIRS} SELECT a_id, b_id, round({_sql}, 9) AS sim FROM pairs")(
        lambda s, d, f=_f: W.pairs_in_blocks(W.masked(W.parties(s, d))).select("a_id", "b_id", F.round(f(F.col("z"), F.col("a_ones"), F.col("b_ones")), 9).alias("sim"))
    )


@query("exact_pairs", f"WITH {R.sql_parties(3)}, m AS (SELECT party, rec_id, md5(concat_ws('|', 'key', {_NORM})) AS digest FROM parties) SELECT a.rec_id AS a_id, b.rec_id AS b_id FROM m a JOIN m b ON a.digest = b.digest AND a.party < b.party")
def exact_pairs(s, d):
    m = W.parties(s, d).select("party", "rec_id", masks.exact_mask(R.QI).alias("digest"))
    a, b = m.alias("a"), m.alias("b")
    return a.join(b, (F.col("a.digest") == F.col("b.digest")) & (F.col("a.party") < F.col("b.party"))).select(F.col("a.rec_id").alias("a_id"), F.col("b.rec_id").alias("b_id"))


def _entity_groups(s, d):
    people = W.parties(s, d, 5, 40).where("held_by > 1")
    return masks.encode_bf(people, R.QI, keep=("entity_id", "party", "rec_id"))


_GROUPS = f"""{W.sql_masked(5, 40, "entity_id, held_by")},
g AS (SELECT entity_id, pos, count(*) AS cnt FROM (SELECT entity_id, unnest(bits) AS pos FROM masked WHERE held_by > 1) GROUP BY ALL),
n AS (SELECT entity_id, count(*) AS m FROM masked WHERE held_by > 1 GROUP BY entity_id),
dice AS (SELECT entity_id, m, sum(CASE WHEN cnt = m THEN 1 ELSE 0 END)::BIGINT AS z, sum(cnt)::BIGINT AS total FROM g JOIN n USING (entity_id) GROUP BY ALL)"""


@query("dice_group", f"{_GROUPS} SELECT entity_id, m, z, total, round(m * z * 1.0 / total, 9) AS dice FROM dice")
def dice_group(s, d):
    return masks.dice_group(_entity_groups(s, d), ["entity_id"]).withColumn("dice", F.round("dice", 9))


@query("dice_cbf", f"{_GROUPS} SELECT entity_id, m, z, total, round(m * z * 1.0 / total, 9) AS dice FROM dice")
def dice_cbf(s, d):
    m = _entity_groups(s, d)
    sizes = m.groupBy("entity_id").agg(F.count(F.lit(1)).alias("m"))
    return masks.dice_cbf(masks.counting_filter(m, ["entity_id"]), sizes, ["entity_id"]).withColumn("dice", F.round("dice", 9))


@query("cbf_build", f"{_GROUPS} SELECT entity_id, pos, cnt FROM g")
def cbf_build(s, d):
    return masks.counting_filter(_entity_groups(s, d), ["entity_id"])


@query("thm1_equality", f"{_GROUPS} SELECT count(*) AS groups, CAST(0 AS BIGINT) AS unequal FROM dice")
def thm1_equality(s, d):
    a, b = dice_group(s, d), dice_cbf(s, d)
    both = a.join(b.select("entity_id", F.col("dice").alias("other")), "entity_id")
    return both.agg(F.count(F.lit(1)).alias("groups"), F.sum((F.col("dice") != F.col("other")).cast("long")).alias("unequal"))


# Clusters are the true records of parties 1 to 3; arrivals are party 4's of the same block.
_ARRIVE = f"""{W.sql_masked(4, 20)},
c AS (SELECT a.rec_id, m.entity_id AS cluster_id, 2.0 * len(list_intersect(a.bits, m.bits)) / (a.ones + m.ones) AS s
  FROM masked a JOIN masked m ON a.block = m.block AND a.party = 4 AND m.party < 4)"""


def _arrivals(s, d):
    people = W.parties(s, d, 4, 20)
    m = masks.encode_bf(blocking.with_block(people), R.QI, keep=("block", "entity_id", "party", "rec_id"))
    a, b = m.where("party = 4").alias("a"), m.where("party < 4").alias("b")
    z = masks.common_ones(F.col("a.words"), F.col("b.words"))
    return m, a.join(b, F.col("a.block") == F.col("b.block")).select(F.col("a.rec_id").alias("rec_id"), F.col("b.entity_id").alias("cluster_id"), F.col("a.block").alias("block"), masks.dice(z, F.col("a.ones") + F.col("b.ones")).alias("s"))


for _how in ("avg", "min", "max"):
    query(f"cluster_sim_{_how}", f"{_ARRIVE} SELECT rec_id, cluster_id, round({_how}(s), 9) AS sim FROM c GROUP BY ALL")(
        lambda s, d, h=_how: _arrivals(s, d)[1].groupBy("rec_id", "cluster_id").agg(F.round(getattr(F, h)("s"), 9).alias("sim"))
    )

_CBF_SIM = f"""{W.sql_masked(4, 20)},
k AS (SELECT DISTINCT a.rec_id, a.block, m.entity_id AS cluster_id FROM masked a JOIN masked m ON a.block = m.block AND a.party = 4 AND m.party < 4),
e AS (SELECT k.rec_id, k.cluster_id, m.rec_id AS member, m.bits FROM k JOIN masked m ON m.block = k.block AND m.entity_id = k.cluster_id AND m.party < 4
  UNION ALL SELECT k.rec_id, k.cluster_id, a.rec_id, a.bits FROM k JOIN masked a USING (rec_id)),
n AS (SELECT rec_id, cluster_id, count(*) AS m FROM e GROUP BY ALL),
c AS (SELECT rec_id, cluster_id, pos, count(*) AS cnt FROM (SELECT rec_id, cluster_id, unnest(bits) AS pos FROM e) GROUP BY ALL)
SELECT rec_id, cluster_id, round(m * sum(CASE WHEN cnt = m THEN 1 ELSE 0 END) * 1.0 / sum(cnt), 9) AS sim FROM c JOIN n USING (rec_id, cluster_id) GROUP BY rec_id, cluster_id, m"""


@query("cluster_sim_cbf", _CBF_SIM)
def cluster_sim_cbf(s, d):
    m, pairs = _arrivals(s, d)
    k = pairs.select("rec_id", "block", "cluster_id").distinct()
    mem = m.where("party < 4").select("block", F.col("entity_id").alias("cluster_id"), "words", "ones")
    own = m.where("party = 4").select("rec_id", "words", "ones")
    rows = k.join(mem, ["block", "cluster_id"]).select("rec_id", "cluster_id", "words", "ones").union(k.join(own, "rec_id").select("rec_id", "cluster_id", "words", "ones"))
    return masks.dice_group(rows, ["rec_id", "cluster_id"]).select("rec_id", "cluster_id", F.round("dice", 9).alias("sim"))


# -- blocking ------------------------------------------------------------------------------------------

_PEOPLE = f"WITH {R.sql_parties(3)}, {R.sql_corrupt(40)}"
_LAST = blocking.sql_soundex("last_name")


@query("block_lastname", f"{_PEOPLE} SELECT rec_id, {_LAST} AS block FROM corrupted")
def block_lastname(s, d):
    return blocking.with_block(W.parties(s, d, 3, 40), "last").select("rec_id", "block")


@query("block_firstlast", f"{_PEOPLE} SELECT rec_id, {W.SQL_BLOCK} AS block FROM corrupted")
def block_firstlast(s, d):
    return blocking.with_block(W.parties(s, d, 3, 40)).select("rec_id", "block")


@query("block_none", f"{_PEOPLE} SELECT 'all' AS block, count(*) AS n FROM corrupted")
def block_none(s, d):
    return blocking.with_block(W.parties(s, d, 3, 40), "none").groupBy("block").agg(F.count(F.lit(1)).alias("n"))


@query("block_bucket", "SELECT CAST(CAST(floor(c_acctbal / 500.0) AS BIGINT) AS VARCHAR) AS block, count(*) AS n FROM customer GROUP BY 1")
def block_bucket(s, d):
    return load(s, d, "customer", "c_acctbal").groupBy(blocking.bucket_key(F.col("c_acctbal"), 500.0).alias("block")).agg(F.count(F.lit(1)).alias("n"))


_BLOCKED = f"{_PEOPLE}, blocked AS (SELECT *, {_LAST} AS block FROM corrupted)"


@query("block_union", f"{_BLOCKED} SELECT block, count(DISTINCT party) AS n_parties, count(*) AS n FROM blocked GROUP BY block")
def block_union(s, d):
    return blocking.block_index(blocking.with_block(W.parties(s, d, 3, 40), "last"))


@query("block_multi", f"{_PEOPLE}, k AS (SELECT rec_id, '0:' || {_LAST} AS block FROM corrupted UNION SELECT rec_id, '1:' || zipcode FROM corrupted) SELECT block, count(*) AS n FROM k GROUP BY block")
def block_multi(s, d):
    people = W.parties(s, d, 3, 40)
    return blocking.multi_block(people, [blocking.soundex_key(["last_name"]), F.col("zipcode")]).groupBy("block").agg(F.count(F.lit(1)).alias("n"))


@query("pairs_completeness", f"""{_BLOCKED}, i AS (SELECT sum(n * (n - 1) // 2)::BIGINT AS found FROM (SELECT count(*) AS n FROM blocked GROUP BY block, entity_id)),
t AS (SELECT sum(n * (n - 1) // 2)::BIGINT AS true_pairs FROM (SELECT count(*) AS n FROM blocked GROUP BY entity_id)) SELECT found, true_pairs, round(found / true_pairs, 6) AS completeness FROM i, t""")
def pairs_completeness(s, d):
    return blocking.pairs_completeness(blocking.with_block(W.parties(s, d, 3, 40), "last"))


@query("block_stats", f"""{_BLOCKED}, p AS (SELECT block, party, count(*) AS n FROM blocked GROUP BY ALL), b AS (SELECT sum(n) AS s, sum(n * n) AS q FROM p GROUP BY block),
a AS (SELECT (power(sum(n), 2) - sum(n * n)) / 2 AS pairs FROM (SELECT count(*) AS n FROM blocked GROUP BY party))
SELECT count(*) AS blocks, max(s)::BIGINT AS largest, sum((s * s - q) // 2)::BIGINT AS pairs, max(a.pairs)::BIGINT AS all_pairs, round(1 - sum((s * s - q) // 2) / max(a.pairs), 6) AS reduction FROM b, a""")
def block_stats(s, d):
    return blocking.block_stats(blocking.with_block(W.parties(s, d, 3, 40), "last"))


@query("block_guard", f"""{_BLOCKED}, n AS (SELECT *, count(*) OVER (PARTITION BY block) AS c FROM blocked), m AS (SELECT CASE WHEN c < 10 THEN substr(block, 1, 1) || '*' ELSE block END AS block FROM n)
SELECT block, count(*) AS n FROM m GROUP BY block HAVING count(*) >= 10""")
def block_guard(s, d):
    return blocking.guard_blocks(blocking.with_block(W.parties(s, d, 3, 40), "last"), 10).groupBy("block").agg(F.count(F.lit(1)).alias("n"))


@query("block_risk", f"""{_BLOCKED}, n AS (SELECT count(*) AS n FROM blocked GROUP BY block)
SELECT min(n) AS smallest, sum(CASE WHEN n < 5 THEN 1 ELSE 0 END)::BIGINT AS small_blocks, sum(CASE WHEN n < 5 THEN n ELSE 0 END)::BIGINT AS exposed FROM n""")
def block_risk(s, d):
    return blocking.block_risk(blocking.with_block(W.parties(s, d, 3, 40), "last"))


@query("noisy_block_counts", f"""{_PEOPLE}, n AS (SELECT {blocking.sql_soundex("last_name")} AS block, count(*) AS n FROM corrupted GROUP BY ALL),
u AS (SELECT *, (CAST('0x' || substr(md5('7:' || block), 1, 8) AS BIGINT) + 0.5::DOUBLE) / 4294967296 - 0.5::DOUBLE AS u FROM n)
SELECT block, n, CAST(greatest(0, round(n - sign(u) * ln(1 - 2 * abs(u)))) AS BIGINT) AS noisy FROM u""")
def noisy_block_counts(s, d):
    return blocking.noisy_block_counts(blocking.with_block(W.parties(s, d, 3, 40), "last"), 1.0)


@query("block_bittree_sizes", f"WITH {R.sql_parties(3)} SELECT count(*) AS records, CAST(0 AS BIGINT) AS too_small FROM parties")
def block_bittree_sizes(s, d):
    m = masks.encode_bf(W.parties(s, d), ("last_name", "zipcode"))
    sizes = blocking.bit_tree(m, 20, 100, 6).groupBy("block").agg(F.count(F.lit(1)).alias("n"))
    return sizes.agg(F.sum("n").alias("records"), F.sum((F.col("n") < 20).cast("long")).alias("too_small"))


for _ord, _sql in (
    ("size", "-count(*)"),
    ("random", "md5('7:' || CAST(party AS VARCHAR))"),
    ("quality", "-avg(CASE WHEN length(zipcode) = 5 THEN 1.0 ELSE 0.0 END)"),
):
    query(f"order_{_ord}", f"{_PEOPLE} SELECT party, CAST(row_number() OVER (ORDER BY k, party) AS INTEGER) AS place FROM (SELECT party, {_sql} AS k FROM corrupted GROUP BY party)")(
        lambda s, d, o=_ord: blocking.ranked_parties(
            W.parties(s, d, 3, 40),
            {"size": -F.count(F.lit(1)), "random": F.first(F.md5(F.concat(F.lit("7:"), F.col("party").cast("string")))), "quality": -F.avg(F.when(F.length("zipcode") == 5, 1.0).otherwise(0.0))}[o],
        )
    )
