"""WARC archives with revisit resolution.

Headers (page id, payload digest and size) are shuffled by digest, without payloads. Of the records with one
payload of at least ``MIN_PAYLOAD`` bytes, that with the smallest id is the original; the others are joined to
it and become revisits that refer to it. The digests' groups are partial aggregates before the shuffle, and
the join back is one that adaptive execution can split, so a payload that a third of all records share is
not gathered anywhere.

Archives are written by Spark's text writer, whose separator is the end of a WARC record, so that any
file system of the cluster and its commit protocol are used; each part is one gzipped WARC/1.1 file with
fresh headers. A file holds records of one class of payload size, and so many that it stays far below what one value may have.
They are read back as binary files, decompressed piece by piece and parsed by Content-Length; revisits are then resolved by a
join of their WARC-Refers-To with the originals' record ids, which are made of page id and payload digest.

Defined cases: a null html is an empty payload; empty and small payloads are all responses; a null or empty URL is
written as ``about:blank`` and line ends in URLs are percent-encoded; a page id that repeats with other payloads has a record for each,
decided by (id, payload); rows that repeat a page id with one payload are all responses (none has a smaller id) and share a record
id; rows with a null id are responses, come back with a null id and are never referred to; very long payloads have
files of their own; extra columns are not read; an empty table gives an empty archive and an empty result.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from blindmatch.llm import storage

MIN_PAYLOAD = 100
RECORD_END = "\r\n\r\n"
#: Payload bytes up to which so many records make a file; a file is read back as one (compressed) value.
FILE_CLASSES = ((64 << 10, 5_000), (4 << 20, 200), (1 << 31, 1))
_PIECE = 1 << 20
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_HTTP_HEAD = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"


def _record_id(page: Column, digest: Column) -> Column:
    d = F.md5(F.concat_ws(":", F.lit("page"), F.coalesce(page.cast("string"), F.lit("")), digest))
    parts = [F.substring(d, a, n) for a, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))]
    return F.concat(F.lit("<urn:uuid:"), F.concat_ws("-", *parts), F.lit(">"))


def classify(pages: DataFrame, id_col: str = "page_id", payload_col: str = "html", min_payload: int = MIN_PAYLOAD) -> DataFrame:
    """One row per record, without payloads: id, digest, payload_bytes, refers_to (null for responses)."""
    payload = F.coalesce(F.col(payload_col), F.lit(""))
    heads = pages.select(F.col(id_col).alias("id"), F.sha2(payload, 256).alias("digest"), F.octet_length(payload).cast("long").alias("payload_bytes"))
    shared = heads.where(F.col("payload_bytes") >= min_payload).groupBy("digest").agg(F.min("id").alias("original"), F.max("id").alias("last"))
    shared = shared.where("original < last").select("digest", "original")
    refers = F.when((F.col("id") > F.col("original")) & (F.col("payload_bytes") >= min_payload), F.col("original"))
    return heads.join(shared, "digest", "left").select("id", "digest", "payload_bytes", refers.alias("refers_to"))


def write_archive(pages: DataFrame, path: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", date: str = "2024-01-01T00:00:00Z", min_payload: int = MIN_PAYLOAD) -> None:
    """Write WARC files to the folder ``path``: responses with payloads, and revisits without."""
    payload = F.coalesce(F.col(payload_col), F.lit(""))
    rows = pages.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), payload.alias("payload")).withColumn("digest", F.sha2("payload", 256))
    verdicts = classify(pages, id_col, payload_col, min_payload).where("refers_to is not null").select("id", "digest", "refers_to").distinct()
    verdicts = storage.written(verdicts, "revisits")
    url = F.regexp_replace(F.regexp_replace(F.col("url"), "\r", "%0D"), "\n", "%0A")
    url = F.when(F.length(url) > 0, url).otherwise(F.lit("about:blank"))
    revisit = F.col("refers_to").isNotNull()
    block = F.when(revisit, F.lit(_HTTP_HEAD)).otherwise(F.concat(F.lit(_HTTP_HEAD), F.col("payload")))
    fields = [
        F.lit("WARC/1.1"),
        F.concat(F.lit("WARC-Type: "), F.when(revisit, F.lit("revisit")).otherwise(F.lit("response"))),
        F.concat(F.lit("WARC-Record-ID: "), _record_id(F.col("id"), F.col("digest"))),
        F.concat(F.lit("WARC-Date: "), F.lit(date)),
        F.concat(F.lit("WARC-Target-URI: "), url),
        F.concat(F.lit("WARC-Payload-Digest: sha256:"), F.col("digest")),
        F.concat(F.lit("X-Page-Id: "), F.col("id").cast("string")),
        F.when(revisit, F.concat(F.lit("WARC-Refers-To: "), _record_id(F.col("refers_to"), F.col("digest")))),
        F.when(revisit, F.lit("WARC-Profile: " + REVISIT_PROFILE)),
        F.lit("Content-Type: application/http; msgtype=response"),
        F.concat(F.lit("Content-Length: "), F.octet_length(block).cast("string")),
    ]
    record = F.concat(F.concat_ws("\r\n", *fields), F.lit("\r\n\r\n"), block)
    low = -1
    for high, most in FILE_CLASSES:
        size = F.octet_length("payload")
        part = rows.where((size > low) & (size <= high)).join(verdicts, ["id", "digest"], "left").select(record.alias("value"))
        part.write.mode("append").option("lineSep", RECORD_END).option("maxRecordsPerFile", most).option("compression", "gzip").text(path)
        low = high
    storage.forget(pages.sparkSession, verdicts)


def unzipped(data: bytes) -> Iterator[bytes]:
    """A gzip file of any number of members, in pieces."""
    member = zlib.decompressobj(31)
    for at in range(0, len(data), _PIECE):
        piece = data[at : at + _PIECE]
        while piece:
            out = member.decompress(piece, 4 * _PIECE)
            if out:
                yield out
            piece = member.unconsumed_tail
            if member.eof:
                piece, member = member.unused_data, zlib.decompressobj(31)


def parse_records(pieces: Iterable[bytes]) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields and block of each record of one file, of which a record and a piece are held at once."""
    held, source, at = bytearray(), iter(pieces), 0

    def until(n: int) -> bool:
        """Whether ``n`` bytes are held."""
        while len(held) < n:
            piece = next(source, None)
            if piece is None:
                return False
            held.extend(piece)
        return True

    while until(1):
        while (stop := held.find(b"\r\n\r\n")) < 0:
            if not until(len(held) + 1):
                raise ValueError(f"record at byte {at} has no end of its header")
        version, *lines = held[:stop].decode("utf-8").split("\r\n")
        if not version.startswith("WARC/"):
            raise ValueError(f"no WARC record at byte {at}")
        fields = dict(line.split(": ", 1) for line in lines)
        begin = stop + 4
        end = begin + int(fields["Content-Length"])
        if not until(end + 4) or held[end : end + 4] != b"\r\n\r\n":
            raise ValueError(f"record at byte {at} does not end where its length says")
        yield fields, bytes(held[begin:end])
        del held[: end + 4]
        at += end + 4


def read_archive(spark: SparkSession, path: str) -> DataFrame:
    """One row per record: page_id, record_type, record_id, refers_to_id, url, stated_digest, payload (null for revisits), payload_digest and payload_bytes of what was read."""
    schema = pa.schema([(n, pa.string()) for n in ("record_type", "record_id", "refers_to_id", "url", "stated_digest", "payload_digest")] + [("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload", pa.binary())])

    def batch_of(out: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out), schema)], schema=schema)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for blob in batch.column(0):
                out, size = [], 0
                for fields, block in parse_records(unzipped(blob.as_py())):
                    payload = None
                    if fields["WARC-Type"] == "response":
                        payload = block[block.index(b"\r\n\r\n") + 4 :]
                    page = fields.get("X-Page-Id")
                    out.append((
                        fields["WARC-Type"], fields["WARC-Record-ID"], fields.get("WARC-Refers-To"), fields["WARC-Target-URI"],
                        fields["WARC-Payload-Digest"].removeprefix("sha256:"), None if payload is None else hashlib.sha256(payload).hexdigest(),
                        None if page is None else int(page), None if payload is None else len(payload), payload,
                    ))
                    size += len(block)
                    if size > 4 << 20:
                        yield batch_of(out)
                        out, size = [], 0
                if out:
                    yield batch_of(out)

    fields = "record_type string, record_id string, refers_to_id string, url string, stated_digest string, payload_digest string, page_id long, payload_bytes long, payload binary"
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")
    return files.mapInArrow(rows, fields)


def resolve_revisits(records: DataFrame) -> DataFrame:
    """One row per record: page_id, payload_bytes, payload_digest, record_type, refers_to; revisits have those of their originals."""
    originals = records.where("record_type = 'response'").select(
        F.col("record_id").alias("_id"), F.col("page_id").alias("_page"), F.col("payload_bytes").alias("_bytes"), F.col("payload_digest").alias("_digest")
    )
    originals = originals.dropDuplicates(["_id"])
    # Responses refer to nothing; in the join their null keys would meet in one task.
    whole = records.where("record_type = 'response'").select("page_id", "payload_bytes", "payload_digest", "record_type", F.lit(None).cast("long").alias("refers_to"))
    again = records.where("record_type <> 'response'")
    again = again.join(originals, again["refers_to_id"] == originals["_id"], "left")
    return whole.union(again.select("page_id", F.col("_bytes").alias("payload_bytes"), F.col("_digest").alias("payload_digest"), "record_type", F.col("_page").alias("refers_to")))


def round_trip(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html") -> DataFrame:
    """Write ``pages`` as archives in the shared folder, read them back and resolve the revisits."""
    spark = pages.sparkSession
    path = storage.new_path(spark, "warc")
    write_archive(pages, path, id_col, url_col, payload_col)
    heads = read_archive(spark, path).select("record_type", "record_id", "refers_to_id", "page_id", "payload_bytes", "payload_digest")
    return resolve_revisits(storage.written(heads, "warc-heads")).withColumnRenamed("page_id", id_col)
