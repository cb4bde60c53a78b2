"""Byte-level BPE encoding and decoding with a given rank file.

Encoding folds ranked merges with Spark higher-order functions: :func:`encode_words` takes a table of
distinct words, spells each as an array of bytes and folds "join the adjacent pair of lowest rank" over it,
with the ranks as one literal map (sharded by CRC-32 so that a lookup scans a few entries). The words are
the most frequent of the whole corpus, at most ``DICTIONARY_WORDS`` of at most ``DICTIONARY_BYTES`` bytes each,
which bounds the folded dictionary that tasks get at about 12 MB; they are chosen by a threshold from a histogram of the
counts, so no task sorts them. Tasks then look every match of the
pattern up; a word outside the dictionary goes through the same merges in the task (with a heap where it is long)
and is remembered there, up to ``MEMO_WORDS`` words. Folding every distinct word in the JVM gives the
same ids at many times the cost; the README has the measured figures.

Decoding concatenates the binary pieces of the ids: :func:`decode_documents` takes them from one Arrow array of pieces,
where those of a text lie side by side; :func:`decode_ids` does the same to a column, from a literal array of pieces.

Bytes travel as hexadecimal strings in the fold, where concatenation of strings is that of bytes. The plan has the map of ranks
once, as the driver keeps the text of every plan that it has run.

The split pattern's matches are found from the classes of code points (letter, number, space, other), all
texts of a chunk at once; tests hold it against the pattern itself.

Defined cases: null and empty texts have no ids and decode to no bytes; repeated rows are encoded each;
special tokens are ordinary text; extra columns are not read; an empty table gives an empty table. Null ids decode to null, and an
id without a piece stops decoding with an error.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import json
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from blindmatch.llm import storage
from blindmatch.llm.words import give_back, lean, text_buffers

SHARDS = 1 << 13
DICTIONARY_WORDS = 1 << 17
DICTIONARY_BYTES = 48
MEMO_WORDS = 200_000
CHUNK_CHARS = 1 << 20
#: Contractions that the split pattern takes before anything else.
CONTRACTIONS = ("'s", "'t", "'re", "'ve", "'m", "'ll", "'d")
_NONE = 2**31 - 1


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(piece): int(rank) for piece, rank in map(bytes.split, lines)}


# -- the split pattern ---------------------------------------------------------------------------------

_LETTER, _NUMBER, _SPACE, _OTHER, _EDGE = range(5)


def code_point_classes() -> np.ndarray:
    """The class of every code point, as the pattern's properties have it."""
    points = np.array([c for c in range(0x110000) if not 0xD800 <= c < 0xE000], np.uint32)
    text = points.tobytes().decode("utf-32-le")
    out = np.full(0x110000, _OTHER, np.uint8)
    for kind, name in ((_LETTER, r"\p{L}+"), (_NUMBER, r"\p{N}+"), (_SPACE, r"\p{White_Space}+")):
        for m in regex.finditer(name, text):
            out[points[m.start() : m.end()]] = kind
    return out


def split_starts(points: np.ndarray, kinds: np.ndarray) -> np.ndarray:
    """Starts of the pattern's matches. ``kinds`` has _EDGE at separators, which are matches of their own."""
    n = len(points)
    if not n:
        return np.zeros(0, np.int64)
    start = np.ones(n, bool)
    start[1:] = kinds[1:] != kinds[:-1]
    edge = kinds == _EDGE
    start |= edge
    space = kinds == _SPACE
    # The last white space before visible text leaves its run; a plain space joins what follows.
    last = space.copy()
    last[:-1] &= ~space[1:] & ~edge[1:]
    last[-1] = False
    start[last] = True
    joins = np.flatnonzero(last & (points == 0x20))
    start[joins + 1] = False
    # Contractions, where a match can start at the apostrophe.
    quotes = np.flatnonzero((points[:-1] == 0x27) & start[:-1] & (kinds[1:] == _LETTER))
    for q in quotes.tolist():
        ahead = points[q + 1 : q + 3]
        two = "".join(map(chr, ahead))
        size = 2 if two[0] in "stmd" else 3 if two in ("re", "ve", "ll") else 0
        if size:
            start[q + 1 : q + size] = False
            if q + size < n and kinds[q + size] == _LETTER:
                start[q + size] = True
    return np.flatnonzero(start)


def split_chunk(texts: list[str], classes: np.ndarray) -> tuple[list[str], np.ndarray]:
    """Matches of all texts in order, and where each text's begin and end among them."""
    joined = "\0".join(texts) + "\0"
    points = np.frombuffer(joined.encode("utf-32-le"), np.uint32)
    kinds = classes[points]
    ends = np.cumsum([len(t) + 1 for t in texts]) - 1
    kinds[ends] = _EDGE
    starts = split_starts(points, kinds)
    bounds = np.searchsorted(starts, ends)
    at = starts.tolist()
    words = [joined[a:b] for a, b in zip(at, at[1:] + [len(joined)])]
    return words, np.concatenate([[0], bounds + 1])


def _text_chunks(column: pa.Array) -> Iterator[list[str]]:
    _, offsets = text_buffers(column)
    low = 0
    while low < len(column):
        high = int(np.searchsorted(offsets, offsets[low] + CHUNK_CHARS, side="right")) - 1
        high = min(max(high, low + 1), len(column))
        yield [x or "" for x in column.slice(low, high - low).to_pylist()]
        low = high


# -- merges --------------------------------------------------------------------------------------------


def merge_word(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of one word: the word itself where it has a rank, else merges by lowest rank, leftmost first."""
    if word in ranks:
        return [ranks[word]]
    if len(word) > 128:
        return _merge_long(word, ranks)
    parts = [word[i : i + 1] for i in range(len(word))]
    get = ranks.get
    pairs = [get(a + b, _NONE) for a, b in zip(parts, parts[1:])]
    while pairs:
        best = min(pairs)
        if best == _NONE:
            break
        i = pairs.index(best)
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
        del pairs[i]
        if i < len(pairs):
            pairs[i] = get(parts[i] + parts[i + 1], _NONE)
        if i:
            pairs[i - 1] = get(parts[i - 1] + parts[i], _NONE)
    return [ranks[p] for p in parts]


def _merge_long(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The same for long words: a heap of pairs over a linked list, n log n."""
    n = len(word)
    end = list(range(1, n + 1))  # of the part that starts at i; 0 once it is merged away
    before = list(range(-1, n - 1))
    heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(word[i : i + 2])) is not None]
    heapq.heapify(heap)
    while heap:
        _, i, stop = heapq.heappop(heap)
        j = end[i]
        if not j or j >= n or end[j] != stop:
            continue
        end[i], end[j] = stop, 0
        if stop < n:
            before[stop] = i
            if (r := ranks.get(word[i : end[stop]])) is not None:
                heapq.heappush(heap, (r, i, end[stop]))
        if (h := before[i]) >= 0 and (r := ranks.get(word[h:stop])) is not None:
            heapq.heappush(heap, (r, h, stop))
    return [ranks[word[i : end[i]]] for i in range(n) if end[i]]


def _let(value: Column, body) -> Column:
    """``body(value)`` with the value computed once; a lambda's variable is the only local there is."""
    return F.element_at(F.transform(F.array(value), body), 1)


def rank_table(ranks: dict[bytes, int]) -> Column:
    """The ranks as one literal: an array of small maps from hexadecimal pieces."""
    shards: list[dict[str, int]] = [{} for _ in range(SHARDS)]
    for piece, rank in ranks.items():
        key = piece.hex().upper()
        shards[zlib.crc32(key.encode()) % SHARDS][key] = rank
    return F.from_json(F.lit(json.dumps(shards)), "array<map<string,int>>")


def rank_of(table: Column, key: Column) -> Column:
    """The rank of a hexadecimal column, or null."""
    shard = F.pmod(F.crc32(key.cast("binary")), F.lit(SHARDS)).cast("int")
    return F.try_element_at(F.try_element_at(table, shard + 1), key)


def _folded(spelled: Column, table: Column) -> Column:
    """Ids of a column of hexadecimal words, by a fold that joins the adjacent parts of lowest rank."""

    def step(parts: Column, _: Column) -> Column:
        n = F.size(parts)
        joined = F.zip_with(F.slice(parts, F.lit(1), n - 1), F.slice(parts, F.lit(2), n - 1), lambda a, b: F.coalesce(rank_of(table, F.concat(a, b)), F.lit(_NONE)))

        def apply(found: Column) -> Column:
            def at(i: Column) -> Column:
                merged = F.array(F.concat(F.element_at(parts, i), F.element_at(parts, i + 1)))
                return F.concat(F.slice(parts, F.lit(1), i - 1), merged, F.slice(parts, i + 2, n))

            lowest = F.array_min(found)
            return F.when(lowest < _NONE, _let(F.array_position(found, lowest).cast("int"), at)).otherwise(parts)

        return F.when(n < 2, parts).otherwise(_let(joined, apply))

    n_bytes = (F.length(spelled) / 2).cast("int")
    byte_parts = F.when(n_bytes > 0, F.transform(F.sequence(F.lit(1), F.greatest(n_bytes, F.lit(1))), lambda i: F.substring(spelled, i * 2 - 1, F.lit(2))))
    byte_parts = F.coalesce(byte_parts, F.array().cast("array<string>"))
    turns = F.slice(byte_parts, 2, F.greatest(n_bytes, F.lit(1)))  # one fewer than bytes
    parts = F.aggregate(turns, byte_parts, step)
    whole = rank_of(table, spelled)
    return F.when(whole.isNotNull(), F.array(whole)).otherwise(F.transform(parts, lambda p: rank_of(table, p)))


def encode_words(words: DataFrame, ranks: dict[bytes, int], word_col: str = "word") -> DataFrame:
    """Adds ``ids`` (array<int>) to a table of distinct words, by a fold of ranked merges. Null: no ids."""
    spelled = F.hex(F.encode(F.coalesce(F.col(word_col), F.lit("")), "UTF-8"))
    return words.withColumn("ids", _let(rank_table(ranks), lambda table: _folded(spelled, table)))


def decode_ids(ids: Column, ranks: dict[bytes, int]) -> Column:
    """The bytes of an array of ids: its pieces, concatenated. An id without a piece is an error."""
    pieces = [""] * (max(ranks.values()) + 1)
    for piece, rank in ranks.items():
        pieces[rank] = piece.hex()
    literal = F.from_json(F.lit(json.dumps(pieces)), "array<string>")
    return F.unhex(F.array_join(F.transform(ids, lambda i: F.element_at(literal, i + 1)), ""))


def piece_array(ranks: dict[bytes, int]) -> pa.Array:
    """The piece of each id, null where there is none."""
    pieces: list[bytes | None] = [None] * (max(ranks.values()) + 1)
    for piece, rank in ranks.items():
        pieces[rank] = piece
    return pa.array(pieces, pa.large_binary())


def decoded(ids: pa.ListArray, pieces: pa.Array) -> list[bytes | None]:
    """The bytes of each list of ids: its pieces, which ``take`` lays side by side."""
    taken = pieces.take(ids.flatten())
    if taken.null_count:
        raise ValueError("an id has no piece")
    until = np.concatenate([[0], np.cumsum(ids.value_lengths().fill_null(0).to_numpy())])
    ends = np.frombuffer(taken.buffers()[1], np.int64) if len(taken) else np.zeros(1, np.int64)
    data, cuts = taken.buffers()[2], ends[until].tolist()
    raw = memoryview(data) if data is not None else memoryview(b"")
    return [bytes(raw[a:b]) if ok else None for a, b, ok in zip(cuts, cuts[1:], ids.is_valid().to_pylist())]


# -- documents -----------------------------------------------------------------------------------------


def count_words(docs: DataFrame, text_col: str, classes) -> DataFrame:
    """How often each match of the split pattern occurs in the corpus: counted in tasks, then summed."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter[str] = Counter()

        def flush() -> pa.RecordBatch:
            batch = pa.RecordBatch.from_arrays([pa.array(seen.keys(), pa.string()), pa.array(seen.values(), pa.int64())], ["word", "n"])
            seen.clear()
            return batch

        for batch in batches:
            for texts in _text_chunks(batch.column(0)):
                words, _ = split_chunk(texts, classes.value)
                seen.update(words)
                if len(seen) > MEMO_WORDS:
                    yield flush()
        if seen:
            yield flush()

    found = docs.select(F.col(text_col)).mapInArrow(lean(rows), "word string, n long")
    return found.where(F.octet_length("word") <= DICTIONARY_BYTES).groupBy("word").agg(F.sum("n").alias("n"))


def most_frequent(counted: DataFrame, most: int) -> DataFrame:
    """Words (word, n) that occur often: those above the lowest threshold that at most ``most`` words pass."""
    level = F.floor(F.log2("n") * 16).cast("int")  # about 4 % apart; a level for each count up to 20
    levels = sorted(counted.groupBy(level.alias("level")).agg(F.count(F.lit(1)).alias("words")).collect(), reverse=True)
    total, least = 0, None
    for r in levels:
        total += r.words
        if total > most:
            break
        least = r.level
    return counted.where(level >= least) if least is not None else counted.limit(0)


def _encoder(docs: DataFrame, ranks: dict[bytes, int], text_col: str):
    """For mapInArrow over (id, text): id, ids, n_tokens, ids_sha256, a batch for each chunk of texts."""
    context = docs.sparkSession.sparkContext
    classes = context.broadcast(code_point_classes())
    counted = storage.written(count_words(docs, text_col, classes), "words")
    frequent = most_frequent(counted, DICTIONARY_WORDS)
    folded = encode_words(frequent.select("word"), ranks).toArrow().combine_chunks()
    storage.forget(docs.sparkSession, counted)
    # Arrow buffers, not objects: each worker makes its own table of them.
    stream = pa.BufferOutputStream()
    with pa.ipc.new_stream(stream, folded.schema) as out:
        out.write_table(folded)
    known = context.broadcast(stream.getvalue().to_pybytes())
    merges = context.broadcast(ranks)
    del folded, stream
    give_back()

    def folded_words() -> dict[str, bytes]:
        with pa.ipc.open_stream(known.value) as stream:
            table = stream.read_all()
        return {w: np.array(i, "<u4").tobytes() for w, i in zip(table["word"].to_pylist(), table["ids"].to_pylist())}

    schema = pa.schema([("id", pa.int64()), ("ids", pa.list_(pa.int32())), ("n_tokens", pa.int64()), ("ids_sha256", pa.string())])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, rare, order = folded_words(), {}, merges.value
        for batch in batches:
            low = 0
            for texts in _text_chunks(batch.column(1)):
                words, bounds = split_chunk(texts, classes.value)
                if len(rare) > MEMO_WORDS:
                    rare.clear()
                for w in set(words).difference(table, rare):
                    rare[w] = np.array(merge_word(w.encode(), order), "<u4").tobytes()
                packed = [table[w] if w in table else rare[w] for w in words]
                bounds = bounds.tolist()
                parts = [b"".join(packed[a : b - 1]) for a, b in zip(bounds, bounds[1:])]
                ids = pa.py_buffer(b"".join(parts))
                sizes = [len(p) // 4 for p in parts]
                offsets = pa.py_buffer(np.cumsum([0, *sizes]).astype(np.int32).tobytes())
                values = pa.Array.from_buffers(pa.int32(), sum(sizes), [None, ids])
                lists = pa.ListArray.from_buffers(pa.list_(pa.int32()), len(parts), [None, offsets], children=[values])
                digests = [hashlib.sha256(p).hexdigest() for p in parts]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(low, len(parts)), lists, pa.array(sizes, pa.int64()), pa.array(digests)], schema=schema)
                low += len(parts)

    return rows


def encode_documents(docs: DataFrame, ranks: dict[bytes, int], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, ids (array<int>), n_tokens, ids_sha256 (of little-endian 32-bit ids)."""
    asked = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col))
    out = asked.mapInArrow(lean(_encoder(docs, ranks, text_col)), "id long, ids array<int>, n_tokens long, ids_sha256 string")
    return out.withColumnRenamed("id", id_col)


def _decoder(spark: SparkSession, ranks: dict[bytes, int]):
    """For chunks of lists of ids: what :func:`decoded` gives, from pieces that a worker lays out once a task."""
    shared = spark.sparkContext.broadcast(ranks)

    def run(columns: Iterator[pa.ListArray]) -> Iterator[list[bytes | None]]:
        pieces = piece_array(shared.value)
        for ids in columns:
            yield decoded(ids, pieces)

    return run


def decode_documents(coded: DataFrame, ranks: dict[bytes, int], id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """One row per row of ``coded``: id, decoded (binary)."""
    decode = _decoder(coded.sparkSession, ranks)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[pa.Array] = []

        def lists() -> Iterator[pa.ListArray]:
            for batch in batches:
                kept.append(batch.column(0))
                yield batch.column(1)

        for found in decode(lists()):
            yield pa.RecordBatch.from_arrays([kept.pop(), pa.array(found, pa.binary())], ["id", "decoded"])

    asked = coded.select(F.col(id_col).cast("long").alias("id"), F.col(ids_col).cast("array<int>"))
    return asked.mapInArrow(lean(rows), "id long, decoded binary").withColumnRenamed("id", id_col)


def encode_and_decode(docs: DataFrame, ranks: dict[bytes, int], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, n_tokens, ids_sha256, decoded_sha256 (of the bytes that the ids decode to).

    A task decodes the ids of each chunk that it has encoded, so ids are not sent back to the JVM."""
    encode, decode = _encoder(docs, ranks, text_col), _decoder(docs.sparkSession, ranks)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coded: list[pa.RecordBatch] = []

        def lists() -> Iterator[pa.ListArray]:
            for batch in encode(batches):
                coded.append(batch)
                yield batch.column(1)

        for found in decode(lists()):
            done = coded.pop()
            digests = pa.array([hashlib.sha256(x).hexdigest() for x in found])
            yield pa.RecordBatch.from_arrays([done.column(0), done.column(2), done.column(3), digests], ["id", "n_tokens", "ids_sha256", "decoded_sha256"])

    asked = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col))
    return asked.mapInArrow(lean(rows), "id long, n_tokens long, ids_sha256 string, decoded_sha256 string").withColumnRenamed("id", id_col)
