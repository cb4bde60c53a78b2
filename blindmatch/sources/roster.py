"""Person-like rosters, parties and corruption, derived from the given tables by digests.

Every value is a function of md5(entity:attribute), so the same roster can be rebuilt in SQL. All steps are
narrow: memberships come from a sorted array, not from a window.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from blindmatch.sources.tables import load, spread

SYLLABLES = ("ba", "ce", "di", "fo", "gu", "ha", "je", "ki", "lo", "mu", "na", "pe", "ri", "so", "tu", "va")
SUFFIXES = ("ville", "ton", "burg", "ford")
QI = ("first_name", "last_name", "city", "zipcode")


def digest(*parts: Column | str) -> Column:
    return F.md5(F.concat_ws(":", *(F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts)))


def hex_int(d: Column, start: int, n: int) -> Column:
    return F.conv(F.substring(d, start, n), 16, 10).cast("long")


def _name(entity: Column, attr: str) -> Column:
    d = digest(entity, attr)
    syllables = F.array(*map(F.lit, SYLLABLES))
    skewed = F.least(hex_int(d, 1, 1), hex_int(d, 2, 1)).cast("int")
    return F.concat(F.element_at(syllables, skewed + 1), F.element_at(syllables, hex_int(d, 3, 1).cast("int") + 1))


def roster(spark: SparkSession, sf_dir: str) -> DataFrame:
    """entity_id, first_name, last_name, city, zipcode, sex, address, birth_date, amount: one row per customer."""
    c = spread(load(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_acctbal"), "c_custkey")
    n = load(spark, sf_dir, "nation", "n_nationkey", "n_name")
    e = F.col("c_custkey")
    suffix = F.element_at(F.array(*map(F.lit, SUFFIXES)), (hex_int(digest(e, "city"), 1, 1) % 4 + 1).cast("int"))
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).select(  # 25 nations, a fixed dimension
        e.alias("entity_id"),
        _name(e, "first").alias("first_name"),
        _name(e, "last").alias("last_name"),
        F.concat(F.lower("n_name"), suffix).alias("city"),
        F.lpad((hex_int(digest(e, "zip"), 1, 6) % 100000).cast("string"), 5, "0").alias("zipcode"),
        F.when(hex_int(digest(e, "sex"), 1, 1) % 2 == 0, "f").otherwise("m").alias("sex"),
        F.concat((hex_int(digest(e, "addr"), 1, 4) % 900 + 1).cast("string"), F.lit(" "), _name(e, "street"), F.lit(" street")).alias("address"),
        F.date_add(F.lit("1940-01-01").cast("date"), (hex_int(digest(e, "born"), 1, 6) % 25000).cast("int")).alias("birth_date"),
        F.col("c_acctbal").alias("amount"),
    )


def make_parties(people: DataFrame, p: int, profile: str = "quarter", f_all: int = 25, f_subset: int = 25) -> DataFrame:
    """Adds party, rec_id and held_by (number of parties of the entity): one row per record.

    ``quarter``: ``f_all`` percent of entities are in all parties, ``f_subset`` percent in 2 to p - 1, the rest in one.
    ``by_size``: five percent for each subset size from 2 to p, the rest in one.
    """
    d = digest(F.col("entity_id"), "class")
    u, v = hex_int(d, 1, 6) % 100, hex_int(d, 7, 6)
    if profile == "quarter":
        some = (v % (p - 2) + 2) if p > 2 else F.lit(1)
        held = F.when(u < f_all, F.lit(p)).when(u < f_all + f_subset, some).otherwise(F.lit(1))
    elif profile == "by_size":
        held = F.when(u < 5 * (p - 1), F.floor(u / 5) + 2).otherwise(F.lit(1))
    else:
        raise ValueError(f"unknown profile {profile}")
    ranked = F.array_sort(F.transform(F.sequence(F.lit(1), F.lit(p)), lambda i: F.struct(digest(F.col("entity_id"), "party", i).alias("d"), i.alias("party"))))
    out = people.withColumn("held_by", held.cast("int"))
    out = out.withColumn("party", F.explode(F.transform(F.slice(ranked, F.lit(1), F.col("held_by")), lambda s: s["party"])))
    return out.withColumn("rec_id", F.col("party").cast("long") * 1_000_000_000 + F.col("entity_id"))


def corrupt(parties: DataFrame, rate: int, attrs: tuple[str, ...] = QI) -> DataFrame:
    """Change one attribute of ``rate`` percent of the records of entities in two or more parties: insert, delete,
    substitute, transpose, an OCR or a phonetic confusion, all by digest. Adds corrupted (boolean)."""
    d = digest(F.col("entity_id"), F.col("party"), "corrupt")
    chosen = (F.col("held_by") > 1) & (hex_int(d, 1, 6) % 100 < rate)
    which, how, at, letter = (hex_int(d, a, 4) for a in (7, 11, 15, 19))
    out = parties.withColumn("corrupted", chosen)
    for i, attr in enumerate(attrs):
        v = F.col(attr)
        n = F.length(v)
        pos = (at % n + 1).cast("int")
        ch = F.char(letter % 26 + 97)
        left, right = v.substr(F.lit(1), pos - 1), v.substr(pos + 1, n)
        near = F.least(pos, n - 1)
        swapped = F.concat(v.substr(F.lit(1), near - 1), v.substr(near + 1, F.lit(1)), v.substr(near, F.lit(1)), v.substr(near + 2, n))
        ocr = F.replace(F.translate(v, "ols", "015"), F.lit("m"), F.lit("rn"))
        spoken = F.translate(F.replace(v, F.lit("f"), F.lit("ph")), "czy", "ksi")
        changed = (
            F.when(how % 6 == 0, F.concat(left, v.substr(pos, F.lit(1)), ch, right))
            .when(how % 6 == 1, F.concat(left, right))
            .when(how % 6 == 2, F.concat(left, ch, right))
            .when(how % 6 == 3, swapped)
            .when(how % 6 == 4, ocr)
            .otherwise(spoken)
        )
        out = out.withColumn(attr, F.when(chosen & (which % len(attrs) == i), changed).otherwise(v))
    return out


def snapshots(spark: SparkSession, sf_dir: str, p: int = 26) -> DataFrame:
    """Parties are the first ``p`` days of ``events``, one record per user and day; zipcode and address move after a day of the user's own."""
    e = load(spark, sf_dir, "events", "ts", "user_id").withColumn("party", F.dayofmonth("ts")).where(F.col("party") <= p)
    seen = e.groupBy("party", "user_id").agg(F.max("ts").alias("last_ts"))
    people = roster(spark, sf_dir).withColumn("uid", F.col("entity_id"))
    seen = seen.join(people, seen.user_id == people.uid).drop("uid", "user_id", "last_ts")
    moved = F.col("party") > hex_int(digest(F.col("entity_id"), "move"), 1, 4) % (2 * p)
    zipcode = F.lpad((hex_int(digest(F.col("entity_id"), "zip2"), 1, 6) % 100000).cast("string"), 5, "0")
    out = seen.withColumn("zipcode", F.when(moved, zipcode).otherwise(F.col("zipcode")))
    return out.withColumn("rec_id", F.col("party").cast("long") * 1_000_000_000 + F.col("entity_id"))


def by_priority(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five parties by order priority; a customer is in those where they ordered."""
    o = load(spark, sf_dir, "orders", "o_custkey", "o_orderpriority").distinct()
    people = roster(spark, sf_dir)
    out = o.join(people, o.o_custkey == people.entity_id)
    out = out.withColumn("party", F.substring("o_orderpriority", 1, 1).cast("int")).drop("o_custkey", "o_orderpriority")
    return out.withColumn("rec_id", F.col("party").cast("long") * 1_000_000_000 + F.col("entity_id"))


# -- the same rules in DuckDB's SQL --------------------------------------------------------------------


def _sql_hex(d: str, start: int, n: int) -> str:
    return f"CAST('0x' || substr({d}, {start}, {n}) AS BIGINT)"


def _sql_name(attr: str) -> str:
    d = f"md5(c_custkey || ':{attr}')"
    syllables = "[" + ", ".join(f"'{s}'" for s in SYLLABLES) + "]"
    return f"{syllables}[least({_sql_hex(d, 1, 1)}, {_sql_hex(d, 2, 1)}) + 1] || {syllables}[{_sql_hex(d, 3, 1)} + 1]"


def sql_roster() -> str:
    def h(attr: str, start: int, n: int) -> str:
        return _sql_hex(f"md5(c_custkey || ':{attr}')", start, n)

    suffixes = "[" + ", ".join(f"'{s}'" for s in SUFFIXES) + "]"
    return f"""roster AS (
  SELECT c_custkey AS entity_id, {_sql_name("first")} AS first_name, {_sql_name("last")} AS last_name,
    lower(n_name) || {suffixes}[{h("city", 1, 1)} % 4 + 1] AS city, lpad(CAST({h("zip", 1, 6)} % 100000 AS VARCHAR), 5, '0') AS zipcode,
    CASE WHEN {h("sex", 1, 1)} % 2 = 0 THEN 'f' ELSE 'm' END AS sex,
    CAST({h("addr", 1, 4)} % 900 + 1 AS VARCHAR) || ' ' || {_sql_name("street")} || ' street' AS address,
    DATE '1940-01-01' + CAST({h("born", 1, 6)} % 25000 AS INTEGER) AS birth_date, c_acctbal AS amount
  FROM customer JOIN nation ON c_nationkey = n_nationkey)"""


def sql_parties(p: int, profile: str = "quarter", f_all: int = 25, f_subset: int = 25) -> str:
    u, v = (_sql_hex("md5(entity_id || ':class')", a, 6) for a in (1, 7))
    if profile == "quarter":
        some = f"{v} % {p - 2} + 2" if p > 2 else "1"
        held = f"CASE WHEN {u} % 100 < {f_all} THEN {p} WHEN {u} % 100 < {f_all + f_subset} THEN {some} ELSE 1 END"
    else:
        held = f"CASE WHEN {u} % 100 < {5 * (p - 1)} THEN CAST(floor(({u} % 100) / 5.0) AS BIGINT) + 2 ELSE 1 END"
    return f"""{sql_roster()},
parties AS (
  SELECT * EXCLUDE (r), CAST(party AS BIGINT) * 1000000000 + entity_id AS rec_id FROM (
    SELECT roster.*, CAST({held} AS INTEGER) AS held_by, CAST(party AS INTEGER) AS party, row_number() OVER (PARTITION BY entity_id ORDER BY md5(entity_id || ':party:' || party)) AS r
    FROM roster, (SELECT unnest(range(1, {p + 1})) AS party)) WHERE r <= held_by)"""


def sql_corrupt(rate: int, attrs: tuple[str, ...] = QI) -> str:
    d = "md5(entity_id || ':' || party || ':corrupt')"
    out = []
    for i, a in enumerate(attrs):
        pos, ch = f"CAST({_sql_hex(d, 15, 4)} % length({a}) + 1 AS INTEGER)", f"chr(CAST({_sql_hex(d, 19, 4)} % 26 + 97 AS INTEGER))"
        near = f"least({pos}, length({a}) - 1)"
        how = f"{_sql_hex(d, 11, 4)} % 6"
        left, right = f"{a}[1:{pos} - 1]", f"substr({a}, {pos} + 1)"
        out.append(f"""CASE WHEN NOT hit OR {_sql_hex(d, 7, 4)} % {len(attrs)} <> {i} THEN {a}
      WHEN {how} = 0 THEN {left} || substr({a}, {pos}, 1) || {ch} || {right}
      WHEN {how} = 1 THEN {left} || {right}
      WHEN {how} = 2 THEN {left} || {ch} || {right}
      WHEN {how} = 3 THEN {a}[1:{near} - 1] || substr({a}, {near} + 1, 1) || substr({a}, {near}, 1) || substr({a}, {near} + 2)
      WHEN {how} = 4 THEN replace(translate({a}, 'ols', '015'), 'm', 'rn')
      ELSE translate(replace({a}, 'f', 'ph'), 'czy', 'ksi') END AS {a}""")
    return f"""hits AS (SELECT *, held_by > 1 AND {_sql_hex(d, 1, 6)} % 100 < {rate} AS hit FROM parties),
corrupted AS (SELECT * REPLACE ({", ".join(out)}) RENAME (hit AS corrupted) FROM hits)"""


def sql_snapshots(p: int = 26) -> str:
    moved = f"party > {_sql_hex("md5(entity_id || ':move')", 1, 4)} % {2 * p}"
    zip2 = f"lpad(CAST({_sql_hex("md5(entity_id || ':zip2')", 1, 6)} % 100000 AS VARCHAR), 5, '0')"
    return f"""{sql_roster()},
parties AS (
  SELECT * REPLACE (CASE WHEN {moved} THEN {zip2} ELSE zipcode END AS zipcode), CAST(party AS BIGINT) * 1000000000 + entity_id AS rec_id
  FROM (SELECT DISTINCT CAST(day(ts) AS INTEGER) AS party, user_id FROM events WHERE day(ts) <= {p}) JOIN roster ON user_id = entity_id)"""


def sql_by_priority() -> str:
    return f"""{sql_roster()},
parties AS (
  SELECT roster.*, party, CAST(party AS BIGINT) * 1000000000 + entity_id AS rec_id
  FROM (SELECT DISTINCT o_custkey, CAST(substr(o_orderpriority, 1, 1) AS INTEGER) AS party FROM orders) JOIN roster ON o_custkey = entity_id)"""
