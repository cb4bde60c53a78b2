"""Secure summation of filters, and linkage attacks on what a linkage unit sees.

The protocol is simulated in one trust domain: its outcome, messages and costs are computed, not its secrecy.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blindmatch.functions.masks import LENGTH


def dense(bits: Column, length: int) -> Column:
    """A filter as an array of 0 and 1."""
    return F.transform(F.sequence(F.lit(1), F.lit(length)), lambda i: F.array_contains(bits, i).cast("long"))


def random_vector(seed: Column | str, length: int, modulus: int = 1_000_003) -> Column:
    """Seeded integers from digests, at least 1."""
    s = F.lit(seed) if isinstance(seed, str) else seed
    return F.transform(F.sequence(F.lit(1), F.lit(length)), lambda i: F.conv(F.substring(F.md5(F.concat(s, F.lit(":"), i.cast("string"))), 1, 8), 16, 10).cast("long") % modulus + 1)


def secure_sum(filters: DataFrame, keys: list[str], length: int, seed: str = "r") -> DataFrame:
    """Message log of a ring sum: keys, step, sender, receiver, payload; the last receiver is the linkage unit, 0.

    ``filters``: keys, party, bits. The unit sends a random vector to the first party; each adds its filter and passes
    on; the last returns the sum. A group has at most as many rows as there are parties.
    """
    start = random_vector(F.concat_ws(":", F.lit(seed), *(F.col(k).cast("string") for k in keys)), length)
    g = filters.select(*keys, F.struct("party", dense(F.col("bits"), length).alias("v")).alias("f")).groupBy(*keys).agg(F.sort_array(F.collect_list("f")).alias("fs"))
    g = g.withColumn("start", start)
    first = F.array(F.struct(F.lit(1).alias("step"), F.lit(0).alias("sender"), F.element_at("fs", 1)["party"].alias("receiver"), F.col("start").alias("payload")))

    def add(log: Column, f: Column) -> Column:
        last = F.element_at(log, -1)
        following = F.try_element_at("fs", last["step"] + 1)["party"]
        message = F.struct((last["step"] + 1).alias("step"), f["party"].alias("sender"), F.coalesce(following, F.lit(0)).alias("receiver"), F.zip_with(last["payload"], f["v"], lambda x, y: x + y).alias("payload"))
        return F.concat(log, F.array(message))

    log = g.select(*keys, F.explode(F.aggregate("fs", first, add)).alias("m"))
    return log.select(*keys, "m.step", "m.sender", "m.receiver", "m.payload")


def summed(log: DataFrame, keys: list[str], length: int, seed: str = "r") -> DataFrame:
    """The linkage unit's result: the last message without its random vector: keys, cbf (array), messages."""
    start = random_vector(F.concat_ws(":", F.lit(seed), *(F.col(k).cast("string") for k in keys)), length)
    last = log.groupBy(*keys).agg(F.max_by("payload", "step").alias("total"), F.count(F.lit(1)).alias("messages"))
    return last.select(*keys, F.zip_with("total", start, lambda x, r: x - r).alias("cbf"), "messages")


def share_sum(filters: DataFrame, keys: list[str], length: int, seed: str = "s", modulus: int = 1 << 40) -> DataFrame:
    """Collusion-resistant variant: each party splits its filter into random additive shares, one for each party; only sums of
    shares are published. keys, cbf, messages (m * (m - 1) shares and m sums)."""
    f = filters.select(*keys, "party", dense(F.col("bits"), length).alias("v"))
    holders = f.select(*keys, F.col("party").alias("holder"))
    pairs = f.join(holders, keys)
    name = F.concat_ws(":", F.lit(seed), *(F.col(k).cast("string") for k in keys), F.col("party").cast("string"), F.col("holder").cast("string"))
    pairs = pairs.withColumn("r", F.when(F.col("party") != F.col("holder"), random_vector(name, length)))
    # The own share is the filter less the shares given away.
    given = pairs.where("r is not null").select(*keys, "party", "holder", F.posexplode("r").alias("pos", "x"))
    own = f.select(*keys, "party", F.posexplode("v").alias("pos", "x"))
    kept = own.union(given.select(*keys, "party", "pos", -F.col("x"))).groupBy(*keys, F.col("party").alias("holder"), "pos").agg(F.sum("x").alias("x"))
    held = kept.union(given.select(*keys, "holder", "pos", "x")).groupBy(*keys, "holder", "pos").agg(F.pmod(F.sum("x"), F.lit(modulus)).alias("x"))
    total = held.groupBy(*keys, "pos").agg(F.pmod(F.sum("x"), F.lit(modulus)).alias("cnt"))
    m = f.groupBy(*keys).agg(F.count(F.lit(1)).alias("m"))
    cbf = total.groupBy(*keys).agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "cnt"))), lambda s: s["cnt"]).alias("cbf"))
    return cbf.join(m, keys).select(*keys, "cbf", (F.col("m") * F.col("m")).alias("messages"))


# -- attacks -------------------------------------------------------------------------------------------


def suspicion_bf(masked: DataFrame, world: DataFrame) -> DataFrame:
    """Linkage attack on filters: n_g records of the global table have the same filter. rec_id, n_g, p_s."""
    key = F.array_join(F.transform("words", lambda w: w.cast("string")), ",")
    known = world.groupBy(F.md5(key).alias("m")).agg(F.count(F.lit(1)).alias("n_g"))
    own = masked.select("rec_id", F.md5(key).alias("m")).join(known, "m", "left")
    return own.select("rec_id", F.coalesce("n_g", F.lit(0)).alias("n_g"), F.when(F.col("n_g") > 0, 1.0 / F.col("n_g")).otherwise(0.0).alias("p_s"))


def suspicion_cbf(members: DataFrame, world: DataFrame, length: int = LENGTH) -> DataFrame:
    """Linkage attack on counting filters of clusters (block, cluster_id, rec_id, words): a global record is consistent when it has
    every position of full count and none of count 0. rec_id, x, n_g, p_s; clusters of one record are left out.

    The join is by block, so the attacker's candidates are the global records of the same block.
    """
    n = (length + 63) // 64
    w = [F.col("words").getItem(i) for i in range(n)]
    g = members.groupBy("block", "cluster_id").agg(
        F.count(F.lit(1)).alias("x"), *(F.bit_and(c).alias(f"a{i}") for i, c in enumerate(w)), *(F.bit_or(c).alias(f"o{i}") for i, c in enumerate(w))
    )
    g = g.where("x > 1")
    must = F.array(*(F.col(f"a{i}") for i in range(n)))
    may = F.array(*(F.col(f"o{i}") for i in range(n)))
    g = g.select("block", "cluster_id", "x", must.alias("must"), may.alias("may"))
    t = world.select("block", "words")
    ok = None
    for i in range(n):
        v = F.col("words").getItem(i)
        one = (v.bitwiseAND(F.col("must").getItem(i)) == F.col("must").getItem(i)) & (v.bitwiseOR(F.col("may").getItem(i)) == F.col("may").getItem(i))
        ok = one if ok is None else ok & one
    hits = g.join(t, "block").where(ok).groupBy("block", "cluster_id", "x").agg(F.count(F.lit(1)).alias("n_g"))
    out = members.select("block", "cluster_id", "rec_id").join(hits, ["block", "cluster_id"])
    return out.select("rec_id", "x", "n_g", (1.0 / F.col("n_g")).alias("p_s"))


def suspicion_cbf_global(members: DataFrame, world: DataFrame) -> DataFrame:
    """The same attack on all global records, whatever their block. ``members``: block, cluster_id, rec_id, words, bits; ``world``: words, bits.

    A consistent record has every position of full count, so it is enough to look where the rarest of them is set: clusters meet records
    by that position, an equi-join, and are then tested. Equal filters of the world are counted once, with their number."""
    distinct = world.groupBy("words").agg(F.count(F.lit(1)).alias("n"), F.first("bits").alias("bits"))
    often = distinct.select(F.explode("bits").alias("pos"), "n").groupBy("pos").agg(F.sum("n").alias("often"))
    sizes = members.groupBy("block", "cluster_id").agg(F.count(F.lit(1)).alias("x")).where("x > 1")
    counted = members.select("block", "cluster_id", F.explode("bits").alias("pos")).groupBy("block", "cluster_id", "pos").agg(F.count(F.lit(1)).alias("c"))
    counted = counted.join(sizes, ["block", "cluster_id"]).join(often, "pos", "left").withColumn("often", F.coalesce("often", F.lit(0)))
    rare = F.min_by("pos", F.when(F.col("c") == F.col("x"), F.struct("often", "pos")))
    found = counted.groupBy("block", "cluster_id", "x").agg(
        rare.alias("rarest"), F.collect_list(F.when(F.col("c") == F.col("x"), F.col("pos"))).alias("must"), F.collect_list("pos").alias("may")
    )
    asked = distinct.select("n", "bits", F.explode("bits").alias("rarest"))
    subset = lambda a, b: F.size(F.array_except(a, b)) == 0
    hits = found.join(asked, "rarest").where(subset("must", "bits") & subset("bits", "may"))
    hits = hits.groupBy("block", "cluster_id", "x").agg(F.sum("n").alias("n_g"))
    out = members.select("block", "cluster_id", "rec_id").join(hits, ["block", "cluster_id"])
    return out.select("rec_id", "x", "n_g", (1.0 / F.col("n_g")).alias("p_s"))


def risk(suspicion: DataFrame) -> DataFrame:
    """Mean and marketer disclosure risk: records, dr_mean, dr_marketer."""
    return suspicion.agg(F.count(F.lit(1)).alias("records"), F.round(F.avg("p_s"), 6).alias("dr_mean"), F.round(F.avg((F.col("p_s") >= 1.0).cast("double")), 6).alias("dr_marketer"))


