"""Removal of repeated word windows by De Bruijn compaction.

A window of ``k`` consecutive words is an edge between its two (k-1)-word nodes. An edge that also starts
in a document with a smaller id is removed there, with all words it covers.

1. Anchors. Each window has an anchor: the smallest hash among its ``ANCHOR``-word grams, so equal windows
   have equal anchors. Anchors seen in one document only cannot be on a repeated edge and go. They are counted
   by their upper 48 bits, where a collision only keeps an anchor that could go (one aggregation of about two rows per nine words, with partial aggregation before the shuffle).
2. Paths. Consecutive edges on one anchor occurrence form a nonbranching path; it is compacted into one
   row with the digest of its word sequence, its edges' hashes and its source coordinates.
3. Joins. Equal paths meet by digest: all but the smallest document's are repeated as wholes. The distinct
   paths are opened into edges once, each edge gets the smallest document it starts in, and paths whose
   edges also start earlier inside another path get those edges back through a join.
4. Coordinates. Removed edges go back to their documents as (start, length) spans, where the kept words are
   assembled and counted.

Equality is that of hashes, not of words: paths compare by (anchor, path) and edges by (anchor, edge), 64 bits each part. Both
parts come from one 64-bit hash a word, so two words of equal hashes are one word here; different windows of words with different
hashes need the same anchor, that is a shared gram, and a collision of their edges.

Hot passages: a path or edge that a third of all documents share is a partial aggregate before it is
shuffled; where occurrences meet their verdict the join is a sort-merge join that adaptive execution can split.

Defined cases: null and empty texts have no words and give the digest of the empty string; texts shorter
than ``k`` words have no window; rows that repeat an id are apart by their text, and never remove each
other's words (no smaller id); rows with a null id lose nothing and remove nothing; extra columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blindmatch.llm import storage
from blindmatch.llm.words import Words, chunks, mix, signed

K = 13
ANCHOR = 6
_CUT = np.uint64(16)


def _anchored(words: Words, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Edge hash and anchor of each window by its first word, and which windows stay in one document."""
    hashes = words.hashes()
    edges, inside = words.windows(hashes, k)
    n = len(edges)
    if not n:
        return edges, edges, inside
    grams, _ = words.windows(hashes, ANCHOR)
    anchors = grams[:n].copy()
    for j in range(1, k - ANCHOR + 1):
        np.minimum(anchors, grams[j : j + n], out=anchors)
    return edges, anchors, inside


def _runs(anchors: np.ndarray, inside: np.ndarray, keep: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of runs of kept windows with one anchor. Windows that cross documents end a run."""
    ok = inside if keep is None else inside & keep
    same = np.zeros(len(anchors) + 1, bool)
    same[1:-1] = ok[1:] & ok[:-1] & (anchors[1:] == anchors[:-1])
    start = np.flatnonzero(ok & ~same[:-1])
    end = np.flatnonzero(ok & ~same[1:]) + 1
    return start, end


def _anchor_rows(k: int):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            for low, high, words in chunks(batch.column(1)):
                _, anchors, inside = _anchored(words, k)
                start, _ = _runs(anchors, inside)
                if len(start):
                    doc = ids[low:high][words.doc()[start]]
                    yield pa.RecordBatch.from_arrays([pa.array(signed(anchors[start] >> _CUT)), pa.array(doc, pa.int64())], ["anchor", "id"])

    return rows


def _path_rows(k: int):
    schema = pa.schema([("path", pa.int64()), ("anchor", pa.int64()), ("id", pa.int64()), ("text_key", pa.int32()), ("start", pa.int32()), ("n", pa.int32()), ("edges", pa.binary())])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, keys = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            wanted = batch.column(3)
            for low, high, words in chunks(batch.column(2)):
                edges, anchors, inside = _anchored(words, k)
                if not len(edges):
                    continue
                doc = words.doc()
                known = wanted.slice(low, high - low)
                flat = known.flatten().to_numpy(zero_copy_only=False).view(np.uint64)
                # Membership by document: the list's document index is mixed into both sides.
                sizes = np.diff(np.frombuffer(known.buffers()[1], np.int32)[known.offset : known.offset + len(known) + 1])
                left = mix((anchors >> _CUT) + mix(doc[: len(anchors)].astype(np.uint64)))
                right = mix(flat + mix(np.repeat(np.arange(len(known)), sizes).astype(np.uint64)))
                start, end = _runs(anchors, inside, np.isin(left, right))
                if not len(start):
                    continue
                size = end - start
                # A path's digest sums its edges, each mixed with its place.
                place = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
                flat_edges = edges[np.repeat(start, size) + place]
                at = np.cumsum(size) - size
                path = mix(np.add.reduceat(mix(flat_edges + mix(place.astype(np.uint64) + np.uint64(1))), at) + size.astype(np.uint64))
                raw = pa.py_buffer(np.ascontiguousarray(flat_edges).tobytes())
                offsets = pa.py_buffer((8 * np.append(at, size.sum())).astype(np.int32).tobytes())
                blobs = pa.BinaryArray.from_buffers(pa.binary(), len(start), [None, offsets, raw])
                owner = doc[start]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(signed(path)),
                        pa.array(signed(anchors[start])),
                        pa.array(ids[low:high][owner], pa.int64()),
                        pa.array(keys[low:high][owner], pa.int32()),
                        pa.array((start - words.first[owner]).astype(np.int32)),
                        pa.array(size.astype(np.int32)),
                        blobs,
                    ],
                    schema=schema,
                )

    return rows


def _edge_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row per edge of each path: its place is its order in the path."""
    for batch in batches:
        if not batch.num_rows:
            continue
        edges = np.frombuffer(b"".join(batch.column(3).to_pylist()), np.int64)
        size = np.array([len(x) // 8 for x in batch.column(3).to_pylist()])
        place = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
        repeated = [np.repeat(batch.column(i).to_numpy(zero_copy_only=False), size) for i in range(3)]
        yield pa.RecordBatch.from_arrays(
            [pa.array(x) for x in (*repeated, edges, place.astype(np.int32))], ["path", "anchor", "first_id", "edge", "place"]
        )


def _kept_rows(k: int):
    schema = pa.schema([("id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept", pa.string()), ("kept_sha256", pa.string())])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for low, high, words in chunks(batch.column(1)):
                spans = batch.column(2).slice(low, high - low).to_pylist()
                gone = np.zeros(len(words) + 1, np.int32)
                for d in range(high - low):
                    base = words.first[d]
                    for span in spans[d] or ():
                        for place in span["places"] if span["places"] is not None else (-1,):
                            first = base + span["start"] + max(place, 0)
                            gone[first] += 1
                            gone[first + (k if place >= 0 else span["n"] + k - 1)] -= 1
                keep = np.cumsum(gone[:-1]) == 0
                raw = words.data.tobytes()
                for d in range(high - low):
                    a, b = words.first[d], words.first[d + 1]
                    stay = np.flatnonzero(keep[a:b]) + a
                    text = b" ".join([raw[s:e] for s, e in zip(words.start[stay].tolist(), words.end[stay].tolist())])
                    out.append((b - a, b - a - len(stay), text, hashlib.sha256(text).hexdigest()))
            columns = list(zip(*out)) or [(), (), (), ()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array(columns[i], pa.int64()) for i in (0, 1)), pa.array(columns[2], pa.binary()).cast(pa.string()), pa.array(columns[3], pa.string())],
                schema=schema,
            )

    return rows


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = K) -> DataFrame:
    """One row per document: id, n_words, n_removed, kept (the kept words joined by one space), kept_sha256."""
    if k < ANCHOR:
        raise ValueError(f"k has to be at least {ANCHOR}")
    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    named = texts.where("id is not null")
    occurrences = named.mapInArrow(_anchor_rows(k), "anchor long, id long")
    repeated = occurrences.groupBy("anchor").agg(F.min("id").alias("low"), F.max("id").alias("high")).where("low < high").select("anchor")
    repeated = storage.written(repeated, "anchors")

    # Anchors that a document shares with others, as one list a document; its size is bounded by the text's.
    shared = occurrences.join(repeated, "anchor").groupBy("id").agg(F.collect_set("anchor").alias("anchors"))
    keyed = named.select("id", F.hash("text").alias("text_key"), "text").join(shared, "id")
    paths = keyed.select("id", "text_key", "text", "anchors").mapInArrow(
        _path_rows(k), "path long, anchor long, id long, text_key int, start int, n int, edges binary"
    )
    paths = storage.written(paths, "paths")
    storage.forget(docs.sparkSession, repeated)

    # A distinct path is known by (anchor, path); its first document keeps it unless single edges start earlier.
    distinct = paths.groupBy("path", "anchor").agg(F.min("id").alias("first_id"), F.min("edges").alias("edges"))
    opened = distinct.select("path", "anchor", "first_id", "edges").mapInArrow(_edge_rows, "path long, anchor long, first_id long, edge long, place int")
    opened = storage.written(opened, "edges")
    origin = opened.groupBy("anchor", "edge").agg(F.min("first_id").alias("origin"), F.max("first_id").alias("last"))
    origin = origin.where("origin < last").select("anchor", "edge", "origin")
    inner = opened.join(origin, ["anchor", "edge"]).where("origin < first_id")
    inner = storage.written(inner.groupBy("path", "anchor").agg(F.sort_array(F.collect_list("place")).alias("places")), "inner")
    storage.forget(docs.sparkSession, opened)

    firsts = paths.groupBy("path", "anchor").agg(F.min("id").alias("first_id")).join(inner, ["path", "anchor"], "left")
    spans = paths.select("path", "anchor", "id", "text_key", "start", "n").join(firsts, ["path", "anchor"]).where("first_id < id or places is not null")
    span = F.struct("start", "n", F.when(F.col("first_id") == F.col("id"), F.col("places")).alias("places"))
    spans = storage.written(spans.groupBy("id", "text_key").agg(F.collect_list(span).alias("spans")), "spans")
    storage.forget(docs.sparkSession, paths)
    storage.forget(docs.sparkSession, inner)

    t = texts.withColumn("text_key", F.hash("text"))
    out = t.join(spans, ["id", "text_key"], "left").select("id", "text", "spans")
    out = out.mapInArrow(_kept_rows(k), "id long, n_words long, n_removed long, kept string, kept_sha256 string")
    return out.withColumnRenamed("id", id_col)
