"""Masks: grams, hash positions, Bloom and counting filters as columns, and their set similarities.

A filter has three shapes: ``bits`` (sorted distinct positions from 1), ``words`` (packed 64-bit words, what
is compared) and ``ones`` (number of positions set).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blindmatch.sources.tables import spread

LENGTH, HASHES, GRAM = 1000, 30, 2
#: Grams whose masks a task remembers.
GRAM_MEMO = 200_000


def normalise(c: Column) -> Column:
    """Lower case, letters, digits and single spaces only, trimmed."""
    return F.trim(F.regexp_replace(F.regexp_replace(F.lower(c), "[^a-z0-9 ]", ""), " +", " "))


def qgrams(c: Column, q: int = GRAM, pad: bool = False) -> Column:
    """Distinct substrings of length q; with ``pad``, the ends are marked by q - 1 underscores. Null and short strings have none."""
    if pad:
        c = F.concat(F.lit("_" * (q - 1)), c, F.lit("_" * (q - 1)))
    n = F.length(c) - q + 1
    starts = F.when(n > 0, F.sequence(F.lit(1), F.greatest(n, F.lit(1)))).otherwise(F.array().cast("array<int>"))
    return F.array_distinct(F.coalesce(F.transform(starts, lambda i: c.substr(i, F.lit(q))), F.array().cast("array<string>")))


def neighbours(c: Column, step: float, width: int) -> Column:
    """Grid cells within ``width`` steps of a number's own, as strings; null has none."""
    own = F.floor(c / F.lit(step))
    cells = F.transform(F.sequence(own - width, own + width), lambda x: x.cast("string"))
    return F.coalesce(cells, F.array().cast("array<string>"))


def positions(tokens: Column, length: int = LENGTH, hashes: int = HASHES, salt: str = "", hash_name: str = "md5") -> Column:
    """Sorted distinct positions of the tokens by double hashing; ``xxhash64`` is faster, ``md5`` exists in other engines too."""

    def of(token: Column) -> Column:
        if hash_name == "md5":
            d = F.md5(F.concat(F.lit(salt), token))
            a, b = (F.conv(F.substring(d, s, 7), 16, 10).cast("long") for s in (1, 8))
        else:
            a, b = (F.shiftrightunsigned(F.xxhash64(F.concat(F.lit(salt + x), token)), 33) for x in ("a", "b"))
        pair = F.array(F.struct(a.alias("a"), b.alias("b")))
        return F.flatten(F.transform(pair, lambda h: F.transform(F.sequence(F.lit(0), F.lit(hashes - 1)), lambda j: ((h["a"] + j * h["b"]) % length + 1).cast("int"))))

    return F.array_sort(F.array_distinct(F.flatten(F.transform(tokens, of))))


def pack(bits: Column, length: int = LENGTH) -> Column:
    """64-bit words of a filter; position 1 is the lowest bit of the first word."""
    n_words = (length + 63) // 64

    def word(w: Column) -> Column:
        own = F.filter(bits, lambda b: F.floor((b - 1) / 64) == w)
        return F.aggregate(own, F.lit(0).cast("long"), lambda acc, b: acc.bitwiseOR(F.expr("1L") * F.call_function("shiftleft", F.lit(1).cast("long"), ((b - 1) % 64).cast("int"))))

    return F.transform(F.sequence(F.lit(0), F.lit(n_words - 1)), word)


def tokens_of(attrs: Sequence[str], q: int = GRAM, tagged: bool = False) -> Column:
    """Grams of all attributes together; ``tagged`` puts the attribute's name into each."""

    def part(a: str) -> Column:
        return F.transform(qgrams(F.col(a), q), lambda g: F.concat(F.lit(a + ":"), g)) if tagged else qgrams(F.col(a), q)

    parts = [part(a) for a in attrs]
    return F.array_distinct(F.flatten(F.array(*parts)))


def _filter_of(bits: Column, length: int) -> Column:
    """bits, words and ones as one struct: the lambda's variable keeps the positions from being computed for each use."""
    return F.element_at(F.transform(F.array(bits), lambda b: F.struct(b.alias("bits"), pack(b, length).alias("words"), F.size(b).alias("ones"))), 1)


def _lists(values: np.ndarray, size: int) -> pa.ListArray:
    return pa.ListArray.from_arrays(np.arange(0, values.size + 1, size, dtype=np.int32), pa.array(values.ravel()))


class GramFilters:
    """Filters of records as packed words: a gram's mask is hashed once, a record's filter is the union of its grams' masks."""

    def __init__(self, length: int = LENGTH, hashes: int = HASHES, q: int = GRAM, salt: str = "", tagged: bool = False):
        self.length, self.hashes, self.q, self.salt, self.tagged = length, hashes, q, salt, tagged
        self.n_words = (length + 63) // 64
        self.forget()

    def forget(self) -> None:
        self.known: dict[str, int] = {}
        self.table = np.zeros((1024, self.n_words), np.uint64)

    def _mask_of(self, gram: str) -> int:
        i = self.known[gram] = len(self.known)
        if i == len(self.table):
            self.table = np.concatenate([self.table, np.zeros_like(self.table)])
        d = hashlib.md5((self.salt + gram).encode()).hexdigest()
        at = (int(d[:7], 16) + np.arange(self.hashes) * int(d[7:14], 16)) % self.length
        np.bitwise_or.at(self.table[i], at // 64, np.uint64(1) << (at % 64).astype(np.uint64))
        return i

    def __call__(self, values: list[list], names: Sequence[str]) -> np.ndarray:
        if len(self.known) > GRAM_MEMO:
            self.forget()
        known, q, index, sizes = self.known, self.q, [], []
        for record in zip(*values):
            grams = {(f"{a}:" if self.tagged else "") + v[i : i + q] for a, v in zip(names, record) if v is not None for i in range(len(v) - q + 1)}
            index += [known[g] if g in known else self._mask_of(g) for g in grams]
            sizes.append(len(grams))
        words = np.zeros((len(sizes), self.n_words), np.uint64)
        full = np.flatnonzero(sizes)
        if len(full):
            starts = np.cumsum(sizes) - sizes
            words[full] = np.bitwise_or.reduceat(self.table[index], starts[full], axis=0)
        return words


def _encode_arrow(df: DataFrame, kept: Sequence[str], attrs: Sequence[str], length: int, hashes: int, q: int, salt: str, tagged: bool, keep_bits: bool = False, by_attribute: bool = False) -> DataFrame:
    """The same filters from Arrow batches: a gram's mask is hashed once a task, a record's filter is the union of its grams' masks."""
    n_words = (length + 63) // 64
    schema = df.select(*kept).schema
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in schema)
    made = "words map<string,array<long>>" if by_attribute else ("bits array<int>, " if keep_bits else "") + "words array<long>, ones int"

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        filters = GramFilters(length, hashes, q, salt, tagged)
        for batch in batches:
            values = [batch.column(len(kept) + j).to_pylist() for j in range(len(attrs))]
            own = [batch.column(i) for i in range(len(kept))]
            if by_attribute:
                words = np.stack([filters([v], [a]) for a, v in zip(attrs, values)], axis=1)
                keys = pa.array(list(attrs) * batch.num_rows, pa.string())
                starts = pa.array(np.arange(0, len(attrs) * batch.num_rows + 1, len(attrs), dtype=np.int32))
                maps = pa.MapArray.from_arrays(starts, keys, _lists(words.view(np.int64), n_words))
                yield pa.RecordBatch.from_arrays([*own, maps], [*kept, "words"])
                continue
            words = filters(values, attrs)
            ones = np.bitwise_count(words).sum(axis=1, dtype=np.int32)
            out = [_lists(words.view(np.int64), n_words), pa.array(ones)]
            if keep_bits:
                at = np.nonzero(np.unpackbits(words.view(np.uint8), axis=1, bitorder="little"))[1].astype(np.int32) + 1
                out.insert(0, pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum(ones)]).astype(np.int32), pa.array(at, pa.int32())))
            yield pa.RecordBatch.from_arrays([*own, *out], [*kept, *(["bits"] if keep_bits else []), "words", "ones"])

    return df.select(*kept, *attrs).mapInArrow(rows, f"{fields}, {made}")


def encode_bf(
    df: DataFrame, attrs: Sequence[str], length: int = LENGTH, hashes: int = HASHES, q: int = GRAM, level: str = "record", salt: str = "",
    tagged: bool = False, hash_name: str = "md5", keep: Sequence[str] = ("party", "rec_id"), keep_bits: bool = False, engine: str = "arrow",
) -> DataFrame:
    """Filters of records; the attributes themselves are dropped. ``attribute`` level gives a map of words by attribute.

    ``engine='native'`` uses higher-order functions only, and is taken where another hash is asked for.
    """
    kept = [c for c in keep if c in df.columns]
    if level == "record":
        if engine == "arrow" and hash_name == "md5":
            return _encode_arrow(df, kept, attrs, length, hashes, q, salt, tagged, keep_bits)
        bits = positions(tokens_of(attrs, q, tagged), length, hashes, salt, hash_name)
        out = df.select(*kept, _filter_of(bits, length).alias("f"))
        return out.select(*kept, *(["f.bits"] if keep_bits else []), "f.words", "f.ones")
    if level != "attribute":
        raise ValueError(f"unknown level {level}")
    if engine == "arrow" and hash_name == "md5":
        return _encode_arrow(df, kept, attrs, length, hashes, q, salt, False, by_attribute=True)
    filters = []
    for a in attrs:
        filters += [F.lit(a), _filter_of(positions(qgrams(F.col(a), q), length, hashes, salt, hash_name), length)["words"]]
    return df.select(*kept, F.create_map(*filters).alias("words"))


def encode_custom(df: DataFrame, bits: Column, length: int, keep: Sequence[str] = ("party", "rec_id")) -> DataFrame:
    """Any mask: ``bits`` is an expression of sorted distinct positions."""
    kept = [c for c in keep if c in df.columns]
    return df.select(*kept, _filter_of(bits, length).alias("f")).select(*kept, "f.words", "f.ones")


def _spread(x: np.ndarray) -> np.ndarray:
    """A 64-bit mixing step (wrapping products and shifts)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def text_mask(text: str | None, size: int = 3, n_words: int = 16) -> tuple[str, np.ndarray]:
    """Smallest gram's digest, and the signs of the sum of all word grams' vectors of -1 and 1: a whole text of any length in one fixed mask.

    Texts of fewer words are one gram; a text without words has an empty mask and the block ''.
    """
    w = (text or "").lower().split()
    grams = {" ".join(w[i : i + size]) for i in range(max(1, len(w) - size + 1))} if w else set()
    if not grams:
        return "", np.zeros(n_words, np.uint64)
    seeds = np.array(sorted(int.from_bytes(hashlib.blake2b(g.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little") for g in grams), np.uint64)
    total = np.zeros(64 * n_words, np.int64)
    step = np.arange(1, n_words + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for at in range(0, len(seeds), 4096):
        part = seeds[at : at + 4096]
        bits = np.unpackbits(_spread(part[:, None] + step[None, :]).view(np.uint8), axis=1, bitorder="little")
        total += 2 * bits.sum(axis=0, dtype=np.int64) - len(part)
    return f"{int(seeds[0]):016x}", np.packbits(total > 0, bitorder="little").view(np.uint64)


def encode_texts(df: DataFrame, text: str, keep: Sequence[str] = ("party", "rec_id")) -> DataFrame:
    """block, words and ones of whole texts (see :func:`text_mask`), one row per row of ``df``; the texts are dropped."""
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.select(*keep).schema)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made = [text_mask(t.as_py()) for t in batch.column(len(keep))]
            words = pa.array([w.view(np.int64).tolist() for _, w in made], pa.list_(pa.int64()))
            ones = pa.array([int(np.bitwise_count(w).sum()) for _, w in made], pa.int32())
            columns = [*(batch.column(i) for i in range(len(keep))), pa.array([b for b, _ in made], pa.string()), words, ones]
            yield pa.RecordBatch.from_arrays(columns, [*keep, "block", "words", "ones"])

    return df.select(*keep, text).mapInArrow(rows, f"{fields}, block string, words array<long>, ones int")


def sign_bits(vector: Column) -> Column:
    """Positions of a vector's positive entries."""
    return F.filter(F.sequence(F.lit(1), F.size(vector)), lambda i: F.element_at(vector, i) > 0)


def exact_mask(attrs: Sequence[str], key: str = "key") -> Column:
    """A keyed digest of the normalised attributes."""
    return F.md5(F.concat_ws("|", F.lit(key), *(F.coalesce(normalise(F.col(a)), F.lit("")) for a in attrs)))


# -- similarities --------------------------------------------------------------------------------------


def common_ones(a: Column, b: Column, length: int = LENGTH) -> Column:
    """Positions set in both, unrolled so that it stays in generated code."""
    terms = [F.bit_count(a.getItem(i).bitwiseAND(b.getItem(i))) for i in range((length + 63) // 64)]
    out = terms[0]
    for t in terms[1:]:
        out = out + t
    return out


def ones_of(words: Column, length: int = LENGTH) -> Column:
    return common_ones(words, words, length)


def dice(z: Column, total: Column, m: int | Column = 2) -> Column:
    """m * z / total, 0 for empty filters."""
    return F.when(total > 0, z * m / total).otherwise(F.lit(0.0))


def jaccard(z: Column, a: Column, b: Column) -> Column:
    return F.when(a + b > 0, z / (a + b - z)).otherwise(F.lit(0.0))


def overlap(z: Column, a: Column, b: Column) -> Column:
    return F.when(F.least(a, b) > 0, z / F.least(a, b)).otherwise(F.lit(0.0))


def dice_group(df: DataFrame, keys: Sequence[str], length: int = LENGTH) -> DataFrame:
    """Dice of all filters of each group: keys, m, z, total, dice. Words are combined by bit_and, so partial aggregates are 16 numbers."""
    n = (length + 63) // 64
    g = df.groupBy(*keys).agg(
        F.count(F.lit(1)).alias("m"), F.sum("ones").alias("total"), *(F.bit_and(F.col("words").getItem(i)).alias(f"_w{i}") for i in range(n))
    )
    z = sum((F.bit_count(f"_w{i}") for i in range(1, n)), F.bit_count("_w0"))
    return g.select(*keys, "m", z.cast("long").alias("z"), "total").withColumn("dice", dice(F.col("z"), F.col("total"), F.col("m")))


#: Rows whose positions are unpacked at once.
UNPACKED = 2048


def _changes(keys: list[pa.Array]) -> np.ndarray:
    """Whether each row's keys differ from those of the row before it (the first row's do)."""
    out = np.zeros(len(keys[0]), bool)
    out[:1] = True
    for k in keys:
        a, b = k.slice(1), k.slice(0, len(k) - 1)
        other = pc.or_(pc.fill_null(pc.not_equal(a, b), False), pc.xor(pc.is_null(a), pc.is_null(b)))
        out[1:] |= other.to_numpy(zero_copy_only=False)
    return out


def _summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Keys and words, in order of the keys, to keys, pos, cnt; a group may go over batches."""
    held = None

    def rows(keys: list[pa.Array], counts: np.ndarray) -> pa.RecordBatch:
        group, pos = np.nonzero(counts)
        own = [k.take(pa.array(group)) for k in keys]
        return pa.RecordBatch.from_arrays([*own, pa.array(pos.astype(np.int32) + 1), pa.array(counts[group, pos])], names)

    for whole in batches:
        names = [*whole.schema.names[:-1], "pos", "cnt"]
        for low in range(0, whole.num_rows, UNPACKED):
            batch = whole.slice(low, UNPACKED)
            flat, keys = batch.column(batch.num_columns - 1), [batch.column(i) for i in range(batch.num_columns - 1)]
            words = np.ascontiguousarray(flat.flatten().to_numpy()).view(np.uint8).reshape(len(flat), -1)
            starts = np.flatnonzero(_changes(keys))
            counts = np.add.reduceat(np.unpackbits(words, axis=1, bitorder="little"), starts, axis=0, dtype=np.int64)
            keys = [k.take(pa.array(starts)) for k in keys]
            if held is not None:
                if _changes([pa.concat_arrays([h, k.slice(0, 1)]) for h, k in zip(held[0], keys)])[1]:
                    yield rows(*held)
                else:
                    counts[0] += held[1][0]
            if len(starts) > 1:
                yield rows([k.slice(0, len(k) - 1) for k in keys], counts[:-1])
            held = [k.slice(len(k) - 1) for k in keys], counts[-1:]
    if held is not None:
        yield rows(*held)


def counting_filter(df: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Sparse counting filter of each group from ``words``, or from ``bits`` where there are none: keys, pos, cnt.

    From words, a group's records are dealt to one task as they are and summed there in order of the keys, batch by batch."""
    if "words" not in df.columns:
        return df.select(*keys, F.explode("bits").alias("pos")).groupBy(*keys, "pos").agg(F.count(F.lit(1)).alias("cnt"))
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.select(*keys).schema)
    return spread(df.select(*keys, "words"), *keys).sortWithinPartitions(*keys).mapInArrow(_summed, f"{fields}, pos int, cnt long")


def dice_cbf(cbf: DataFrame, sizes: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Dice from counting filters (keys, pos, cnt) and group sizes (keys, m): keys, m, z, total, dice. Positions are first counted by their count."""
    by_count = cbf.groupBy(*keys, "cnt").agg(F.count(F.lit(1)).alias("k")).join(sizes, list(keys))
    z = F.sum(F.when(F.col("cnt") == F.col("m"), F.col("k")).otherwise(0))
    g = by_count.groupBy(*keys, "m").agg(z.cast("long").alias("z"), F.sum(F.col("cnt") * F.col("k")).alias("total"))
    return g.withColumn("dice", dice(F.col("z"), F.col("total"), F.col("m")))


# -- SQL of the masks ----------------------------------------------------------------------------------


def sql_grams(a: str, q: int = GRAM) -> str:
    return f"list_distinct(list_transform(range(1, greatest(length({a}) - {q - 2}, 1)), lambda i: substr({a}, i, {q})))"


def sql_positions(tokens: str, length: int = LENGTH, hashes: int = HASHES, salt: str = "") -> str:
    d = f"md5('{salt}' || t)"
    return (
        f"list_sort(list_distinct(flatten(list_transform({tokens}, lambda t: list_transform(range(0, {hashes}), lambda j: "
        f"CAST((CAST('0x' || substr({d}, 1, 7) AS BIGINT) + j * CAST('0x' || substr({d}, 8, 7) AS BIGINT)) % {length} + 1 AS INTEGER))))))"
    )


def sql_masked(source: str, attrs: Sequence[str], extra: str = "", salt: str = "", hashes: int = HASHES, length: int = LENGTH, name: str = "masked") -> str:
    grams = ", ".join(sql_grams(a) for a in attrs)
    return f"{name} AS (SELECT party, rec_id, {extra + ', ' if extra else ''}{sql_positions(f'list_distinct(flatten([{grams}]))', length, hashes, salt)} AS bits FROM {source})"
