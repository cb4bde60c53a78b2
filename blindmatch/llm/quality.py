"""Quality rules: base rules, and a hashed n-gram log-likelihood ratio of trusted target to raw corpus.

Words and word pairs of a text are hashed into ``BUCKETS`` features. Two multinomials over the features are
counted: the raw corpus over all documents, and the trusted target over at most
``TRUSTED`` labelled documents (those of smallest hashed id; the bound is for the fit only). A feature's ratio is that of its trusted
count to the count that its share of the raw corpus would give, each with ``PRIOR`` added, so features without evidence have a
ratio near 0, whatever the numbers of buckets and of different words. A document's
score is the mean log ratio over its features, so long texts score like short ones, and a document is kept
where it passes the base rules and scores at least ``THRESHOLD``; nothing is random.

The counts are two arrays of ``BUCKETS`` numbers, summed in tasks before they are shuffled (buckets that a task has not
seen are not sent); what reaches the driver has at most that fixed size.

Defined cases: very long texts are judged whole, one at a time; null and empty texts have no words, score 0 and fail the base rules; with no trusted
document the ratio is 0 for every text and only the base rules decide; rows that repeat an id are each
judged and counted; labels with null ids are ignored; extra columns are kept by :func:`keep_good`.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blindmatch.llm.words import Words, chunks, give_back, lean, mix

BUCKETS = 1 << 20
TRUSTED = 20_000
#: Buckets of a batch that a task sends.
SENT = 1 << 15
#: Pseudo-counts of a feature, both for its trusted and for its expected count.
PRIOR = 4
THRESHOLD = -0.1
MIN_WORDS = 50
_SYMBOLS = np.zeros(256, bool)
_SYMBOLS[list(b"#*$%&|<>")] = True


def _features(words: Words) -> tuple[np.ndarray, np.ndarray]:
    """Bucket and document of each word and word pair."""
    hashes, doc = words.hashes(), words.doc()
    pairs, inside = words.windows(hashes, 2)
    bucket = np.concatenate([mix(hashes + np.uint64(1)), pairs[inside]]) % np.uint64(BUCKETS)
    return bucket.astype(np.int64), np.concatenate([doc, doc[: len(pairs)][inside]])


def _segment_sums(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(values, dtype=np.int64)])
    return total[offsets[1:]] - total[offsets[:-1]]


def base_counts(words: Words) -> dict[str, np.ndarray]:
    """n_words, word_chars, n_symbols, n_dup_lines and n_repeat_words of each document of a chunk."""
    first, n = words.first, words.n_docs
    size = np.diff(first)
    # Code points are bytes that do not continue one.
    points = np.concatenate([[0], np.cumsum((words.data & 0xC0) != 0x80, dtype=np.int64)])
    chars = _segment_sums(points[words.end] - points[words.start], first)
    symbols = _segment_sums(_SYMBOLS[words.data], words.offsets)
    raw, lines = words.data.tobytes(), np.zeros(n, np.int64)
    for d in range(n):
        seen = raw[words.offsets[d] : words.offsets[d + 1]].split(b"\n")
        if len(seen) > 1:
            seen = [x for x in seen if x.split()]
            lines[d] = len(seen) - len(set(seen))
    windows, inside = words.windows(words.hashes(), 3)
    doc = words.doc()
    repeated = np.zeros(len(words) + 1, np.int64)
    if inside.any():
        at = np.flatnonzero(inside)
        key = mix(windows[at] + mix(doc[at].astype(np.uint64)))
        _, inverse, count = np.unique(key, return_inverse=True, return_counts=True)
        at = at[count[inverse] > 1]
        np.add.at(repeated, at, 1)
        np.add.at(repeated, at + 3, -1)
    covered = _segment_sums(np.cumsum(repeated[:-1]) > 0, first)
    return {"n_words": size, "word_chars": chars, "n_symbols": symbols, "n_dup_lines": lines, "n_repeat_words": covered}


def fit_ratio(docs: DataFrame, trusted: DataFrame | None, id_col: str = "doc_id", text_col: str = "text") -> np.ndarray:
    """Log ratio of the two multinomials by feature. ``trusted``: a table of ids, of which at most ``TRUSTED`` are used."""
    chosen: set[int] = set()
    if trusted is not None:
        ids = trusted.select(F.col(id_col).cast("long").alias("id")).where("id is not null").distinct()
        chosen = set(ids.orderBy(F.xxhash64("id"), "id").limit(TRUSTED).toArrow()["id"].to_pylist())
    known = docs.sparkSession.sparkContext.broadcast(np.array(sorted(chosen), np.int64))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((2, BUCKETS), np.int64)
        for batch in batches:
            good = np.isin(batch.column(0).fill_null(-(2**63)).to_numpy(), known.value)
            for low, high, words in chunks(batch.column(1)):
                bucket, doc = _features(words)
                counts[0] += np.bincount(bucket, minlength=BUCKETS)
                counts[1] += np.bincount(bucket[good[low:high][doc]], minlength=BUCKETS)
        seen = np.flatnonzero(counts[0])
        for at in range(0, len(seen), SENT):
            some = seen[at : at + SENT]
            yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(counts[0][some]), pa.array(counts[1][some])], ["bucket", "raw", "good"])

    counted = docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(lean(rows), "bucket long, raw long, good long")
    table = counted.groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("good").alias("good")).toArrow()
    raw, good = np.zeros(BUCKETS), np.zeros(BUCKETS)
    at = table["bucket"].to_numpy()
    raw[at] = table["raw"].to_numpy()
    good[at] = table["good"].to_numpy()
    del table, at
    give_back()
    expected = raw * (good.sum() / max(raw.sum(), 1))
    return np.log((good + PRIOR) / (expected + PRIOR))


_COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def judge(docs: DataFrame, trusted: DataFrame | None, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, keep_columns: bool = False) -> DataFrame:
    """One row per document: id, the base counts, score, base_failed, kept; with ``keep_columns`` also the columns of ``docs``, prefixed ``in_``."""
    ratio = docs.sparkSession.sparkContext.broadcast(fit_ratio(docs, trusted, id_col, text_col))
    # Columns that are kept travel once: the text among them is also the one that is judged.
    sent = [F.col(c).alias(f"in_{c}") for c in docs.columns] if keep_columns else [F.col(text_col).alias("judged")]
    text_at = 1 + ([c.lower() for c in docs.columns].index(text_col.lower()) if keep_columns else 0)
    back = 1 if keep_columns else 2
    asked = docs.select(F.col(id_col).cast("long").alias("id"), *sent)
    verdict = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, score double, base_failed boolean, kept boolean"
    extra = "".join(f", `{f.name}` {f.dataType.simpleString()}" for f in asked.schema.fields[back:])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low, high, words in chunks(batch.column(text_at)):
                counts = base_counts(words)
                bucket, doc = _features(words)
                total = np.bincount(doc, ratio.value[bucket], minlength=high - low)
                score = total / np.maximum(np.bincount(doc, minlength=high - low), 1)
                failed = (counts["n_words"] < MIN_WORDS) | (100 * counts["n_repeat_words"] > 50 * counts["n_words"])
                part = batch.slice(low, high - low)
                columns = [pa.array(counts[c].astype(np.int64)) for c in _COUNTS]
                columns += [pa.array(score), pa.array(failed), pa.array(~failed & (score >= threshold))]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), *columns, *(part.column(i) for i in range(back, part.num_columns))],
                    ["id", *_COUNTS, "score", "base_failed", "kept", *part.schema.names[back:]],
                )

    return asked.mapInArrow(lean(rows), f"id long, {verdict}{extra}").withColumnRenamed("id", id_col)


def keep_good(docs: DataFrame, trusted: DataFrame | None, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` that are kept, with all their columns."""
    judged = judge(docs, trusted, id_col, text_col, threshold, keep_columns=True).where("kept")
    return judged.select(*(F.col(f"in_{c}").alias(c) for c in docs.columns))
