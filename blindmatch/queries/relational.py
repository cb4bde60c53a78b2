"""Queries of the operators around the methods: scans, joins, aggregates, windows, functions, Python functions."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blindmatch.plans.lineage import shared_path
from blindmatch.queries import workloads as W
from blindmatch.queries.registry import query
from blindmatch.sources import roster as R
from blindmatch.sources.tables import TABLES, load

# -- scans, sources, sinks -----------------------------------------------------------------------------


@query("scan_parquet_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def scan_parquet_counts(s, d):
    out = None
    for t in TABLES:
        one = load(s, d, t).agg(F.count(F.lit(1)).alias("n")).select(F.lit(t).alias("name"), "n")
        out = one if out is None else out.union(one)
    return out


@query("scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity >= 49 AND l_discount < 0.02")
def scan_pruned(s, d):
    return load(s, d, "lineitem").where("l_quantity >= 49 and l_discount < 0.02").select("l_orderkey", "l_quantity")


def _round_trip(fmt: str, **options):
    def run(s, d):
        path = shared_path(s, fmt)
        c = load(s, d, "customer")
        getattr(c.write.options(**options), fmt)(path)
        return getattr(s.read.schema(c.schema).options(**options), fmt)(path)

    return run


for _fmt, _options in (("csv", {"header": True}), ("json", {}), ("orc", {})):
    query(f"roundtrip_{_fmt}", "SELECT * FROM customer")(_round_trip(_fmt, **_options))


@query("sink_partitioned", f"WITH {R.sql_parties(3)} SELECT rec_id, last_name, party FROM parties WHERE party = 2")
def sink_partitioned(s, d):
    path = shared_path(s, "by-party")
    W.parties(s, d).select("rec_id", "last_name", "party").write.partitionBy("party").parquet(path)
    return s.read.schema("rec_id long, last_name string, party int").parquet(path).where("party = 2")


@query("sink_bucketed", f"WITH {R.sql_parties(3)} SELECT last_name, count(*) AS n FROM parties GROUP BY last_name")
def sink_bucketed(s, d):
    """A table bucketed by its block is aggregated by block without another shuffle."""
    import uuid

    name = "bucketed_" + uuid.uuid4().hex[:8]
    W.parties(s, d).select("rec_id", "last_name").write.option("path", shared_path(s, "buckets")).bucketBy(4, "last_name").saveAsTable(name)
    return s.table(name).groupBy("last_name").agg(F.count(F.lit(1)).alias("n"))


# -- filters and projections ---------------------------------------------------------------------------


@query("filter_compound", "SELECT o_orderkey FROM orders WHERE (o_orderstatus IN ('F', 'P') AND o_totalprice BETWEEN 50000 AND 150000) OR (o_orderpriority LIKE '1%' AND NOT regexp_matches(o_orderstatus, '^O'))")
def filter_compound(s, d):
    o = load(s, d, "orders", "o_orderkey", "o_orderstatus", "o_totalprice", "o_orderpriority")
    a = F.col("o_orderstatus").isin("F", "P") & F.col("o_totalprice").between(50000, 150000)
    return o.where(a | (F.col("o_orderpriority").like("1%") & ~F.col("o_orderstatus").rlike("^O"))).select("o_orderkey")


@query("filter_nullsafe", "SELECT c_custkey, coalesce(seg, 'none') AS seg, seg IS NOT DISTINCT FROM NULL AS missing FROM (SELECT c_custkey, CASE WHEN c_custkey % 3 = 0 THEN NULL ELSE c_mktsegment END AS seg FROM customer)")
def filter_nullsafe(s, d):
    c = load(s, d, "customer", "c_custkey", "c_mktsegment").select("c_custkey", F.when(F.col("c_custkey") % 3 != 0, F.col("c_mktsegment")).alias("seg"))
    return c.select("c_custkey", F.coalesce("seg", F.lit("none")).alias("seg"), F.col("seg").eqNullSafe(F.lit(None)).alias("missing"))


@query("project_case_cast", "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'some' ELSE 'rich' END AS level, CAST(floor(c_acctbal) AS BIGINT) AS whole, CAST(c_custkey AS VARCHAR) || ':' || c_mktsegment AS tag FROM customer")
def project_case_cast(s, d):
    c = load(s, d, "customer")
    level = F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 5000, "some").otherwise("rich")
    return c.select("c_custkey", level.alias("level"), F.floor("c_acctbal").alias("whole"), F.concat(F.col("c_custkey").cast("string"), F.lit(":"), "c_mktsegment").alias("tag"))


# -- joins ---------------------------------------------------------------------------------------------


@query("join_broadcast", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def join_broadcast(s, d):
    n = load(s, d, "nation").join(F.broadcast(load(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))  # dimensions of 25 and 5 rows
    return load(s, d, "customer", "c_nationkey").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


def _orders_lines(s, d, hint):
    o, li = load(s, d, "orders", "o_orderkey", "o_orderstatus"), load(s, d, "lineitem", "l_orderkey", "l_quantity")
    return o.join(li.hint(hint), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"))


for _name, _hint in (("join_sortmerge", "merge"), ("join_shuffle_hash", "shuffle_hash")):
    query(_name, "SELECT o_orderstatus, count(*) AS n, sum(l_quantity) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")(lambda s, d, h=_hint: _orders_lines(s, d, h))

_SIDES = "a AS (SELECT DISTINCT o_custkey AS k FROM orders WHERE o_orderpriority LIKE '1%'), b AS (SELECT DISTINCT o_custkey AS j FROM orders WHERE o_orderpriority LIKE '2%')"


def _sides(s, d) -> tuple[DataFrame, DataFrame]:
    o = load(s, d, "orders", "o_custkey", "o_orderpriority")
    return tuple(o.where(F.col("o_orderpriority").like(f"{i}%")).select(F.col("o_custkey").alias(n)).distinct() for i, n in ((1, "k"), (2, "j")))


for _name, _how, _sql in (("join_left", "left", "LEFT"), ("join_right", "right", "RIGHT"), ("join_full", "full", "FULL")):
    query(_name, f"WITH {_SIDES} SELECT k, j FROM a {_sql} JOIN b ON k = j")(lambda s, d, h=_how: (lambda a, b: a.join(b, F.col("k") == F.col("j"), h))(*_sides(s, d)))
for _name, _how, _sql in (("join_semi", "left_semi", "SEMI"), ("join_anti", "left_anti", "ANTI")):
    query(_name, f"WITH {_SIDES} SELECT k FROM a {_sql} JOIN b ON k = j")(lambda s, d, h=_how: (lambda a, b: a.join(b, F.col("k") == F.col("j"), h))(*_sides(s, d)))


@query("join_cross_small", "SELECT r_name, n_name FROM region, nation")
def join_cross_small(s, d):
    return load(s, d, "region", "r_name").crossJoin(load(s, d, "nation", "n_name"))  # two fixed dimensions


@query("join_theta", "WITH z AS (SELECT p_size, count(*) AS n FROM part GROUP BY p_size) SELECT a.p_size AS small, b.p_size AS large, a.n * b.n AS pairs FROM z a JOIN z b ON a.p_size < b.p_size")
def join_theta(s, d):
    """Pairs of parts by size; the inequality joins the fifty sizes, not the parts."""
    z = load(s, d, "part", "p_size").groupBy("p_size").agg(F.count(F.lit(1)).alias("n"))
    a, b = z.alias("a"), z.alias("b")
    return a.join(b, F.col("a.p_size") < F.col("b.p_size")).select(F.col("a.p_size").alias("small"), F.col("b.p_size").alias("large"), (F.col("a.n") * F.col("b.n")).alias("pairs"))


@query("join_range_band", "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_partkey < b.p_partkey AND abs(a.p_retailprice - b.p_retailprice) <= 0.05")
def join_range_band(s, d):
    """Numbers within a width by equi-join of buckets: each row looks into its own bucket and the next ones."""
    width = 0.05
    p = load(s, d, "part", "p_partkey", "p_retailprice").withColumn("k", F.floor(F.col("p_retailprice") / (width * 2)))
    a = p.select(F.col("p_partkey").alias("a"), F.col("p_retailprice").alias("x"), F.explode(F.array(F.col("k") - 1, F.col("k"), F.col("k") + 1)).alias("k"))
    b = p.select(F.col("p_partkey").alias("b"), F.col("p_retailprice").alias("y"), "k")
    return a.join(b, "k").where((F.col("a") < F.col("b")) & (F.abs(F.col("x") - F.col("y")) <= width)).select("a", "b")


@query("join_asof", """SELECT p.event_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p
ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY ALL) v ON p.user_id = v.user_id AND p.ts >= v.ts""")
def join_asof(s, d):
    """The last view at or before each purchase, by a union and one window instead of a pair join."""
    e = load(s, d, "events", "event_id", "ts", "user_id", "event_type").where(F.col("event_type").isin("purchase", "view"))
    view = F.when(F.col("event_type") == "view", F.col("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("view_id", F.last(view, ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "view_id")


@query("join_interval", """SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p
ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts > v.ts AND p.ts <= v.ts + INTERVAL 6 HOUR""")
def join_interval(s, d):
    e = load(s, d, "events", "event_id", "ts", "user_id", "event_type")
    v, p = e.where("event_type = 'view'").alias("v"), e.where("event_type = 'purchase'").alias("p")
    on = (F.col("v.user_id") == F.col("p.user_id")) & (F.col("p.ts") > F.col("v.ts")) & (F.col("p.ts") <= F.col("v.ts") + F.expr("interval 6 hours"))
    return v.join(p, on).select(F.col("v.event_id").alias("view_id"), F.col("p.event_id").alias("purchase_id"))


@query("join_lateral", "SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS o_orderkey FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey)")
def join_lateral(s, d):
    load(s, d, "customer").createOrReplaceTempView("lateral_customer")
    load(s, d, "orders").createOrReplaceTempView("lateral_orders")
    return s.sql("SELECT c_custkey, t.o_orderkey FROM lateral_customer, LATERAL (SELECT max_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS o_orderkey FROM lateral_orders WHERE o_custkey = c_custkey) t WHERE t.o_orderkey IS NOT NULL")


# -- aggregates ----------------------------------------------------------------------------------------

_AGG = "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS quantity, min(l_shipdate)::DATE::VARCHAR AS first_ship, max(l_discount) AS most FROM lineitem GROUP BY 1, 2"


@query("agg_hash", _AGG)
def agg_hash(s, d):
    return load(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"), F.min(F.to_date("l_shipdate")).cast("string").alias("first_ship"), F.max("l_discount").alias("most")
    )


@query("agg_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY 1")
def agg_distinct(s, d):
    return load(s, d, "orders").groupBy("o_orderstatus").agg(F.count_distinct("o_custkey").alias("customers"))


@query("agg_approx_distinct", "SELECT true AS within_five_percent")
def agg_approx_distinct(s, d):
    a = load(s, d, "lineitem").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("a"), F.count_distinct("l_orderkey").alias("b"))
    return a.select((F.abs(F.col("a") / F.col("b") - 1) <= 0.05).alias("within_five_percent"))


@query("agg_filtered", "SELECT o_orderstatus, count(*) FILTER (o_totalprice > 100000) AS large, sum(CASE WHEN o_orderpriority LIKE '1%' THEN 1 ELSE 0 END)::BIGINT AS urgent FROM orders GROUP BY 1")
def agg_filtered(s, d):
    return load(s, d, "orders").groupBy("o_orderstatus").agg(F.count_if(F.col("o_totalprice") > 100000).alias("large"), F.count_if(F.col("o_orderpriority").like("1%")).alias("urgent"))


@query("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) >= 12")
def agg_having(s, d):
    return load(s, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).where("n >= 12")


_LEVELS = "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY {} "
for _kind in ("rollup", "cube"):
    query(f"agg_{_kind}", _LEVELS.format(f"{_kind}(o_orderstatus, o_orderpriority)"))(
        lambda s, d, k=_kind: getattr(load(s, d, "orders"), k)("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))
    )


@query("agg_grouping_sets", _LEVELS.format("GROUPING SETS ((o_orderstatus), (o_orderpriority), ())"))
def agg_grouping_sets(s, d):
    o = load(s, d, "orders")
    return o.groupingSets([[F.col("o_orderstatus")], [F.col("o_orderpriority")], []], "o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("agg_pivot", f"WITH {R.sql_parties(3)} SELECT party, count(*) FILTER (held_by = 1) AS h1, count(*) FILTER (held_by = 2) AS h2, count(*) FILTER (held_by = 3) AS h3 FROM parties GROUP BY party")
def agg_pivot(s, d):
    return W.parties(s, d).groupBy("party").pivot("held_by", [1, 2, 3]).agg(F.count(F.lit(1))).select("party", *(F.coalesce(F.col(str(i)), F.lit(0)).alias(f"h{i}") for i in (1, 2, 3)))


@query("agg_bits", "SELECT o_orderstatus, bit_and(o_custkey) AS a, bit_or(o_custkey) AS o, bit_xor(o_custkey) AS x FROM orders GROUP BY 1")
def agg_bits(s, d):
    return load(s, d, "orders").groupBy("o_orderstatus").agg(F.bit_and("o_custkey").alias("a"), F.bit_or("o_custkey").alias("o"), F.bit_xor("o_custkey").alias("x"))


@query("agg_collect_sorted", "SELECT s_nationkey, string_agg(s_suppkey::VARCHAR, ',' ORDER BY s_suppkey) AS members FROM supplier GROUP BY 1")
def agg_collect_sorted(s, d):
    return load(s, d, "supplier").groupBy("s_nationkey").agg(F.array_join(F.sort_array(F.collect_list("s_suppkey")).cast("array<string>"), ",").alias("members"))


@query("agg_max_by", "SELECT p_brand, arg_max(p_partkey, (p_retailprice, p_partkey)) AS best FROM part GROUP BY 1")
def agg_max_by(s, d):
    return load(s, d, "part").groupBy("p_brand").agg(F.max_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("best"))


@query("agg_percentiles", "SELECT p_size, round(quantile_cont(p_retailprice, 0.5), 6) AS mid, round(quantile_cont(p_retailprice, 0.9), 6) AS high FROM part GROUP BY 1")
def agg_percentiles(s, d):
    return load(s, d, "part").groupBy("p_size").agg(F.round(F.percentile("p_retailprice", 0.5), 6).alias("mid"), F.round(F.percentile("p_retailprice", 0.9), 6).alias("high"))


# -- windows, sorts, sets ------------------------------------------------------------------------------

_RANKS = "row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr, ntile(4) OVER w AS nt"


@query("win_rank_family", f"SELECT o_orderkey, {_RANKS} FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate::DATE, o_orderkey)")
def win_rank_family(s, d):
    o = load(s, d, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    w = Window.partitionBy("o_custkey").orderBy(F.to_date("o_orderdate"), "o_orderkey")
    ranks = (F.row_number().over(w), F.rank().over(w), F.dense_rank().over(w), F.round(F.percent_rank().over(w), 9), F.ntile(4).over(w))
    return o.select("o_orderkey", *(c.alias(n) for c, n in zip(ranks, ("rn", "rk", "dr", "pr", "nt"))))


@query("win_lead_lag", "SELECT event_id, lag(event_type) OVER w AS before, lead(event_id) OVER w AS next_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lead_lag(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(s, d, "events").select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_id").over(w).alias("next_id"))


@query("win_running", "SELECT l_orderkey, l_linenumber, sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS q FROM lineitem")
def win_running(s, d):
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity").rowsBetween(-2, 0)
    return load(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.sum("l_quantity").over(w).alias("q"))


@query("win_range", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY datediff('day', DATE '1990-01-01', o_orderdate::DATE) RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS n FROM orders")
def win_range(s, d):
    day = F.date_diff(F.to_date("o_orderdate"), F.lit("1990-01-01").cast("date"))
    w = Window.partitionBy("o_custkey").orderBy(day).rangeBetween(-90, 0)
    return load(s, d, "orders").select("o_orderkey", F.count(F.lit(1)).over(w).alias("n"))


@query("win_first_last", """SELECT event_id, first_value(v IGNORE NULLS) OVER w AS first_v, last_value(v IGNORE NULLS) OVER w AS last_v FROM (SELECT *, CASE WHEN event_id % 3 = 0 THEN value END AS v FROM events)
WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)""")
def win_first_last(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    v = F.when(F.col("event_id") % 3 == 0, F.col("value"))
    return load(s, d, "events").select("event_id", F.first(v, ignorenulls=True).over(w).alias("first_v"), F.last(v, ignorenulls=True).over(w).alias("last_v"))


@query("topk_per_group", "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def topk_per_group(s, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return load(s, d, "orders", "o_custkey", "o_orderkey", "o_totalprice").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


@query("sort_nulls_limit", "SELECT c_custkey FROM customer ORDER BY CASE WHEN c_custkey % 7 = 0 THEN NULL ELSE c_acctbal END DESC NULLS LAST, c_custkey LIMIT 20 OFFSET 5")
def sort_nulls_limit(s, d):
    k = F.when(F.col("c_custkey") % 7 != 0, F.col("c_acctbal"))
    return load(s, d, "customer").orderBy(k.desc_nulls_last(), "c_custkey").offset(5).limit(20).select("c_custkey")


_K = "(SELECT o_custkey FROM orders WHERE o_orderpriority LIKE '{}%')"
for _name, _f, _sql in (
    ("set_union", lambda a, b: a.union(b).distinct(), "UNION"),
    ("set_union_all", lambda a, b: a.union(b), "UNION ALL"),
    ("set_intersect", lambda a, b: a.intersect(b), "INTERSECT"),
    ("set_intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL"),
    ("set_except", lambda a, b: a.subtract(b), "EXCEPT"),
    ("set_except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL"),
):
    query(_name, f"{_K.format(1)} {_sql} {_K.format(2)}")(
        lambda s, d, f=_f: f(*(load(s, d, "orders", "o_custkey", "o_orderpriority").where(F.col("o_orderpriority").like(f"{i}%")).select("o_custkey") for i in (1, 2)))
    )


@query("distinct_rows", "SELECT DISTINCT lang, source FROM documents")
def distinct_rows(s, d):
    return load(s, d, "documents", "lang", "source").dropDuplicates()


# -- functions -----------------------------------------------------------------------------------------


@query("str_functions", """SELECT c_custkey, substr(c_name, 10, 4) AS part, upper(c_mktsegment) AS up, lpad(c_custkey::VARCHAR, 8, '0') AS pad, translate(c_name, '0#', 'o-') AS tr,
regexp_extract(c_name, '([1-9][0-9]*)$', 1) AS num, split_part(c_name, '#', 1) AS head, reverse(c_name) AS rev, instr(c_name, '#') AS at FROM customer""")
def str_functions(s, d):
    n = F.col("c_name")
    return load(s, d, "customer").select(
        "c_custkey", n.substr(10, 4).alias("part"), F.upper("c_mktsegment").alias("up"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("pad"), F.translate(n, "0#", "o-").alias("tr"),
        F.regexp_extract(n, "([1-9][0-9]*)$", 1).alias("num"), F.split_part(n, F.lit("#"), F.lit(1)).alias("head"), F.reverse(n).alias("rev"), F.instr(n, "#").cast("long").alias("at"),
    )


@query("str_soundex", f"WITH {R.sql_roster()} SELECT entity_id, {W.SQL_BLOCK} AS code FROM roster")
def str_soundex(s, d):
    return R.roster(s, d).select("entity_id", F.concat_ws("-", F.soundex("first_name"), F.soundex("last_name")).alias("code"))


@query("str_levenshtein", f"WITH {R.sql_parties(3)}, {R.sql_corrupt(40)} SELECT p.rec_id, levenshtein(p.last_name, c.last_name)::BIGINT AS edits FROM parties p JOIN corrupted c USING (rec_id)")
def str_levenshtein(s, d):
    a, b = W.parties(s, d).select("rec_id", "last_name"), W.parties(s, d, 3, 40).select("rec_id", F.col("last_name").alias("changed"))
    return a.join(b, "rec_id").select("rec_id", F.levenshtein("last_name", "changed").cast("long").alias("edits"))


@query("str_digest", "SELECT c_custkey, md5(c_name) AS m, sha256(c_name) AS h FROM customer")
def str_digest(s, d):
    return load(s, d, "customer").select("c_custkey", F.md5("c_name").alias("m"), F.sha2("c_name", 256).alias("h"))


@query("date_functions", "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, date_trunc('month', o_orderdate)::DATE::VARCHAR AS mo, datediff('day', o_orderdate::DATE, DATE '2002-01-01')::INTEGER AS age, (o_orderdate::DATE + 30)::VARCHAR AS due, strftime(o_orderdate, '%Y%m%d') AS ymd FROM orders")
def date_functions(s, d):
    t = F.col("o_orderdate")
    return load(s, d, "orders").select(
        "o_orderkey", F.year(t).alias("y"), F.month(t).alias("m"), F.trunc(t, "month").cast("string").alias("mo"), F.date_diff(F.lit("2002-01-01").cast("date"), F.to_date(t)).alias("age"),
        F.date_add(F.to_date(t), 30).cast("string").alias("due"), F.date_format(t, "yyyyMMdd").alias("ymd"),
    )


@query("math_functions", "SELECT p_partkey, CAST(floor(p_retailprice) AS BIGINT) AS f, CAST(ceil(p_retailprice) AS BIGINT) AS c, round(log2(p_size + 1), 9) AS l, (p_partkey * 7) % 5 AS m, greatest(p_size, 10) AS g, bit_count(p_partkey)::INTEGER AS b, (p_size << 2)::INTEGER AS s, p_partkey & 12 AS a FROM part")
def math_functions(s, d):
    return load(s, d, "part").select(
        "p_partkey", F.floor("p_retailprice").alias("f"), F.ceil("p_retailprice").alias("c"), F.round(F.log2(F.col("p_size") + 1), 9).alias("l"), F.pmod(F.col("p_partkey") * 7, F.lit(5)).alias("m"),
        F.greatest("p_size", F.lit(10)).alias("g"), F.bit_count("p_partkey").alias("b"), F.shiftleft("p_size", 2).alias("s"), F.col("p_partkey").bitwiseAND(12).alias("a"),
    )


_ARR = "list_transform(range(1, p_size + 1), lambda x: (x * p_partkey) % 7)"


@query("arr_functions", f"SELECT p_partkey, list_sum({_ARR})::BIGINT AS total, len(list_filter({_ARR}, lambda x: x > 3)) AS above, len(list_distinct({_ARR})) AS kinds, len(list_intersect({_ARR}, [1, 2])) AS shared FROM part")
def arr_functions(s, d):
    a = F.transform(F.sequence(F.lit(1), F.col("p_size")), lambda x: (x * F.col("p_partkey")) % 7)
    return load(s, d, "part").select("p_partkey", a.alias("a")).select(
        "p_partkey", F.aggregate("a", F.lit(0).cast("long"), lambda x, y: x + y).alias("total"), F.size(F.filter("a", lambda x: x > 3)).cast("long").alias("above"),
        F.size(F.array_distinct("a")).cast("long").alias("kinds"), F.size(F.array_intersect("a", F.array(F.lit(1), F.lit(2)).cast("array<long>"))).cast("long").alias("shared"),
    )


@query("arr_explode_pos", "SELECT c_custkey, generate_subscripts(w, 1) - 1 AS pos, unnest(w) AS word FROM (SELECT c_custkey, string_split(c_name, '#') AS w FROM customer)")
def arr_explode_pos(s, d):
    return load(s, d, "customer").select("c_custkey", F.posexplode(F.split("c_name", "#")).alias("pos", "word"))


@query("map_functions", "SELECT o_custkey, round(sum(o_totalprice) * 2, 2) AS total, count(*) AS n FROM orders GROUP BY 1")
def map_functions(s, d):
    m = load(s, d, "orders").groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderkey", "o_totalprice"))).alias("m"))
    m = m.withColumn("m", F.transform_values("m", lambda k, v: v * 2))
    return m.select("o_custkey", F.round(F.aggregate(F.map_values("m"), F.lit(0.0), lambda a, b: a + b), 2).alias("total"), F.size(F.map_keys("m")).cast("long").alias("n"))


@query("json_functions", "SELECT event_id, CAST(json_keys(props) AS VARCHAR) IS NOT NULL AS parsed, json_valid(props) AS valid FROM events")
def json_functions(s, d):
    m = F.from_json("props", "map<string,string>")
    return load(s, d, "events", "event_id", "props").select("event_id", F.map_keys(m).isNotNull().alias("parsed"), F.get_json_object("props", "$").isNotNull().alias("valid"))


@query("struct_nested", "SELECT c_custkey, c_name AS name, c_acctbal > 0 AS positive FROM customer")
def struct_nested(s, d):
    c = load(s, d, "customer").select("c_custkey", F.struct(F.col("c_name").alias("name"), F.struct((F.col("c_acctbal") > 0).alias("positive")).alias("state")).alias("x"))
    return c.select("c_custkey", "x.name", "x.state.positive")


# -- Python functions ----------------------------------------------------------------------------------

_UDF = "SELECT c_custkey, length(c_name) + c_custkey % 10 AS v FROM customer"


def _udf_rows(s, d, f):
    return load(s, d, "customer", "c_custkey", "c_name").select("c_custkey", f("c_name", "c_custkey").alias("v"))


@query("udf_scalar", _UDF)
def udf_scalar(s, d):
    return _udf_rows(s, d, F.udf(lambda n, k: len(n) + k % 10, "long"))


@query("udf_pandas", _UDF)
def udf_pandas(s, d):
    def f(n: pd.Series, k: pd.Series) -> pd.Series:
        return n.str.len() + k % 10

    return _udf_rows(s, d, F.pandas_udf(f, "long"))


@query("udf_arrow", _UDF)
def udf_arrow(s, d):
    def f(n: pa.Array, k: pa.Array) -> pa.Array:
        import pyarrow.compute as pc

        return pc.add(pc.utf8_length(n).cast(pa.int64()), pc.subtract(k, pc.multiply(pc.divide(k, 10), 10)))

    return _udf_rows(s, d, F.arrow_udf(f, "long"))


@query("udaf_pandas", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY 1")
def udaf_pandas(s, d):
    def f(k: pd.Series) -> int:
        return k.nunique()

    return load(s, d, "orders").groupBy("o_orderstatus").agg(F.pandas_udf(f, "long")("o_custkey").alias("customers"))


@query("udtf_pairs", "WITH m AS (SELECT n_regionkey, n_nationkey FROM nation) SELECT a.n_regionkey AS block, a.n_nationkey AS a, b.n_nationkey AS b FROM m a JOIN m b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def udtf_pairs(s, d):
    """Candidate pairs of a block's list of records by a table function."""

    @F.udtf(returnType="a int, b int")
    class CandidatePairs:
        def eval(self, members: list):
            for i, a in enumerate(members):
                for b in members[i + 1 :]:
                    yield a, b

    s.udtf.register("candidate_pairs", CandidatePairs)
    load(s, d, "nation").groupBy("n_regionkey").agg(F.sort_array(F.collect_list("n_nationkey")).alias("members")).createOrReplaceTempView("pair_blocks")
    return s.sql("SELECT n_regionkey AS block, p.a, p.b FROM pair_blocks, LATERAL candidate_pairs(members) p")


@query("grouped_map", "SELECT o_custkey, count(*) AS n, max(o_orderkey) AS last_key FROM orders GROUP BY 1")
def grouped_map(s, d):
    def f(t: pa.Table) -> pa.Table:
        return pa.table({"o_custkey": t["o_custkey"].slice(0, 1), "n": [t.num_rows], "last_key": [max(t["o_orderkey"].to_pylist())]})

    return load(s, d, "orders", "o_custkey", "o_orderkey").groupBy("o_custkey").applyInArrow(f, "o_custkey long, n long, last_key long")


@query("cogrouped_map", "SELECT n_regionkey AS k, count(DISTINCT n_nationkey) AS nations, count(s_suppkey) AS suppliers FROM nation LEFT JOIN supplier ON s_nationkey = n_nationkey GROUP BY 1")
def cogrouped_map(s, d):
    def f(key, a: pa.Table, b: pa.Table) -> pa.Table:
        return pa.table({"k": pa.array([key[0].as_py()], pa.int32()), "nations": [a.num_rows], "suppliers": [b.num_rows]})

    n = load(s, d, "nation", "n_regionkey", "n_nationkey")
    region_of = n.select(F.col("n_nationkey").alias("nk"), F.col("n_regionkey").alias("k"))
    sup = load(s, d, "supplier", "s_suppkey", "s_nationkey").join(region_of, F.col("s_nationkey") == F.col("nk")).select("k", "s_suppkey")
    return n.groupBy("n_regionkey").cogroup(sup.groupBy("k")).applyInArrow(f, "k int, nations long, suppliers long")


@query("sqlfunc_dice", f"{W.sql_masked()}, {W.SQL_PAIRS} SELECT a_id, b_id, round(2.0 * z / (a_ones + b_ones), 9) AS dice, round(z * 1.0 / (a_ones + b_ones - z), 9) AS jaccard, round(z * 1.0 / least(a_ones, b_ones), 9) AS overlap FROM pairs")
def sqlfunc_dice(s, d):
    """SQL functions, expanded by the analyser so that generated code is kept."""
    both = " + ".join(f"bit_count(a[{i}] & b[{i}])" for i in range(16))
    s.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION bm_common(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS INT RETURN {both}")
    s.sql("CREATE OR REPLACE TEMPORARY FUNCTION bm_dice(z INT, x INT, y INT) RETURNS DOUBLE RETURN 2 * z / (x + y)")
    s.sql("CREATE OR REPLACE TEMPORARY FUNCTION bm_jaccard(z INT, x INT, y INT) RETURNS DOUBLE RETURN z / (x + y - z)")
    s.sql("CREATE OR REPLACE TEMPORARY FUNCTION bm_overlap(z INT, x INT, y INT) RETURNS DOUBLE RETURN z / least(x, y)")
    W.masked(W.parties(s, d)).createOrReplaceTempView("sqlfunc_masked")
    return s.sql("""SELECT a_id, b_id, round(bm_dice(z, x, y), 9) AS dice, round(bm_jaccard(z, x, y), 9) AS jaccard, round(bm_overlap(z, x, y), 9) AS overlap FROM (
      SELECT a.rec_id AS a_id, b.rec_id AS b_id, bm_common(a.words, b.words) AS z, a.ones AS x, b.ones AS y FROM sqlfunc_masked a JOIN sqlfunc_masked b ON a.block = b.block AND a.party < b.party)""")


_LINKS = "e AS (SELECT DISTINCT o_custkey AS u, o_custkey + 1 + o_orderkey % 3 AS v FROM orders WHERE o_custkey < 40)"


@query("recursive_cte", f"WITH RECURSIVE {_LINKS}, r AS (SELECT u, v FROM e UNION SELECT r.u, e.v FROM r JOIN e ON r.v = e.u) SELECT u, count(*) AS reached FROM r GROUP BY u")
def recursive_cte(s, d):
    load(s, d, "orders").createOrReplaceTempView("orders")
    return s.sql(f"""WITH RECURSIVE {_LINKS}, r (u, v) AS (SELECT u, v FROM e UNION ALL SELECT DISTINCT r.u, e.v FROM r JOIN e ON r.v = e.u)
      SELECT u, count(DISTINCT v) AS reached FROM r GROUP BY u""")


#: Each order leads to its customer's next one: links of the whole table that stay inside a customer's orders.
_NEXT = "e AS (SELECT u, v FROM (SELECT o_orderkey AS u, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS v FROM orders) WHERE v IS NOT NULL)"


@query("recursive_reach", f"WITH RECURSIVE {_NEXT}, r AS (SELECT u, v FROM e UNION SELECT r.u, e.v FROM r JOIN e ON r.v = e.u) SELECT u, count(*) AS reached FROM r GROUP BY u")
def recursive_reach(s, d):
    """Reachability over all orders; depth is the largest number of orders of a customer. The engine's bounds on levels and rows are lifted, as they would stop larger tables."""
    load(s, d, "orders").createOrReplaceTempView("orders")
    s.conf.set("spark.sql.cteRecursionRowLimit", "-1")
    s.conf.set("spark.sql.cteRecursionLevelLimit", "-1")
    return s.sql(f"""WITH RECURSIVE {_NEXT}, r (u, v) AS (SELECT u, v FROM e UNION ALL SELECT r.u, e.v FROM r JOIN e ON r.v = e.u)
      SELECT u, count(DISTINCT v) AS reached FROM r GROUP BY u""")
