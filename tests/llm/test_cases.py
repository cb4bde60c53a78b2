"""Repeated and null ids, equal rows, clashing columns and empty tables, for every operator and pipeline stage."""

import hashlib

import pytest
from pyspark.sql import functions as F

from blindmatch.llm import exact_dedup, html_wrappers, mixture, ngram_join, quality, secret_scan, substring_dedup, url_filter, warc
from tests.llm.test_operators import WORD


def test_deduplicate_decides_by_row(spark):
    rows = [(5, "a", 1), (6, "a", 2), (5, "b", 3), (5, "A", 4), (5, "B", 5), (5, "B", 5), (None, "c", 6), (None, "c", 7), (7, "c", 8), (None, "d", 9), (8, None, 10), (9, "", 11)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, digest int")
    kept = [tuple(r) for r in exact_dedup.deduplicate(docs).collect()]
    texts = sorted((t or "").lower() for _, t, _ in kept)
    assert texts == ["", "a", "b", "c", "d"]
    by = {(t or "").lower(): (i, d) for i, t, d in kept}
    assert by["a"] == (6, 2) and by["c"] == (7, 8) and by[""] == (9, 11) and by["d"] == (None, 9) and by["b"][0] == 5
    groups = exact_dedup.duplicate_groups(docs).collect()
    assert len(groups) == len(rows)
    for r in groups:
        same = [i for i, t, _ in rows if hashlib.sha256((t or "").lower().encode()).hexdigest() == r.text_sha256]
        assert r.group_size == len(same) and r.keep_id == max((i for i in same if i is not None), default=None)
    assert exact_dedup.deduplicate(docs.limit(0)).count() == 0


def test_mixing_with_clashing_columns(spark):
    rows = [(i, " ".join(f"w{j}" for j in range(5 + i % 7)), f"s{i % 3}" if i % 5 else None, 1, 2, 3, 4, "x") for i in range(60)]
    rows += [(None, "n n n", "s0", 1, 2, 3, 4, "x"), (None, "m m m m", "s1", 1, 2, 3, 4, "x"), (3, None, "s0", 1, 2, 3, 4, "x"), (61, "", None, 1, 2, 3, 4, "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, _id int, _times int, _rest int, _words int, row string")
    out = mixture.mixed_rows(docs)
    assert out.columns == docs.columns
    got = out.collect()
    assert all(r._words == 4 and r._id == 1 and r.text for r in got)
    taken = {}
    for r in got:
        taken[r.source] = taken.get(r.source, 0) + len(WORD.findall(r.text))
    target = {r.source: r.t for r in mixture.mix_sources(docs).join(docs.select("doc_id", "source").distinct(), "doc_id").groupBy("source").agg(F.max("target").alias("t")).collect()}
    assert all(abs(taken[s] - t) <= 1 for s, t in target.items())


@pytest.mark.parametrize("sizes", [{"a": 100, "b": 10, "c": 1000}, {"a": 7, None: 50, "b": 0}, {"x": 5}])
def test_water_filling_by_repeated_clamping(spark, sizes):
    """Shares by weight, clamped again and again until none is above its cap."""
    names = sorted((s for s in sizes if s is not None)) + [s for s in sizes if s is None]
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    budget, full = 1.5 * sum(sizes.values()), {}
    while True:
        left, open_ = budget - sum(full.values()), [s for s in names if s not in full]
        share = {s: left * weight[s] / sum(weight[x] for x in open_) for s in open_}
        over = [s for s in open_ if share[s] >= 2 * sizes[s]]
        if not over:
            break
        full |= {s: 2.0 * sizes[s] for s in over}
        if len(full) == len(names):
            share = {}
            break
    frame = spark.createDataFrame(list(sizes.items()), "source string, source_size long")
    got = {r.source: r.target for r in mixture.water_fill(frame).collect()}
    assert got == pytest.approx(full | share)


def test_warc_keeps_every_payload_of_a_repeated_id(spark, monkeypatch):
    a, b, c = "a" * 200, "b" * 300, "é" * 5000
    rows = [(1, "u", a, 1), (7, "u", a, 1), (7, "v", b, 1), (8, "w", b, 1), (9, "x", c, 1), (9, "x", c, 1), (10, "x", c, 1), (None, "n", a, 1), (None, None, None, 1)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, digest int")
    monkeypatch.setattr(warc, "FILE_CLASSES", ((250, 2), (1000, 1), (1 << 31, 1)))
    got = sorted((str(r.page_id), r.payload_digest, r.payload_bytes, r.record_type, str(r.refers_to)) for r in warc.round_trip(pages).collect())
    want = []
    for i, _, h, _ in rows:
        h = (h or "").encode()
        low = min((j for j, _, g, _ in rows if (g or "").encode() == h and j is not None), default=None)
        again = i is not None and len(h) >= 100 and low < i
        want.append((str(i), hashlib.sha256(h).hexdigest(), len(h), "revisit" if again else "response", str(low) if again else "None"))
    assert got == sorted(want)
    assert warc.round_trip(pages.limit(0)).count() == 0


def test_archives_are_read_in_pieces(monkeypatch):
    import gzip

    monkeypatch.setattr(warc, "_PIECE", 7)
    record = lambda body: b"WARC/1.1\r\nContent-Length: %d\r\n\r\n%s\r\n\r\n" % (len(body), body)
    bodies = [b"", b"x" * 50, b"WARC/1.1\r\n\r\n" * 3]
    data = gzip.compress(record(bodies[0]) + record(bodies[1])) + gzip.compress(record(bodies[2]))
    assert [b for _, b in warc.parse_records(warc.unzipped(data))] == bodies
    with pytest.raises(ValueError):
        list(warc.parse_records([record(b"abc")[:-2]]))


@pytest.mark.parametrize(
    "run",
    [
        lambda s, d: url_filter.judge_urls(s.createDataFrame([], "page_id long, url string, fetch_day int"), s.createDataFrame([], "list_key string, day int, action string")),
        lambda s, d: secret_scan.scan(d),
        lambda s, d: html_wrappers.extract(s.createDataFrame([], "page_id long, url string, html string")),
        lambda s, d: quality.judge(d, None),
        lambda s, d: substring_dedup.remove_repeats(d),
        lambda s, d: ngram_join.keep_one_each(d),
    ],
)
def test_empty_tables(spark, run):
    assert run(spark, spark.createDataFrame([], "doc_id long, text string, source string")).count() == 0


def test_null_and_repeated_ids(spark):
    """Every row comes back, rows with a null id without taking part."""
    long = " ".join(f"w{i}" for i in range(60))
    rows = [(None, long, "a"), (None, None, "a"), (1, long, "a"), (2, long, None), (2, long, None), (3, long + " tail", "b"), (4, "password = hunter2hunter2", "b")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    ids = sorted(str(r[0]) for r in rows)
    for out in (ngram_join.link_documents(docs), substring_dedup.remove_repeats(docs), secret_scan.scan(docs), quality.judge(docs, docs), mixture.mix_sources(docs), exact_dedup.duplicate_groups(docs)):
        assert sorted(str(r.doc_id) for r in out.collect()) == ids
    links = {(r.doc_id, r.component_id) for r in ngram_join.link_documents(docs).collect()}
    assert {(1, 1), (2, 1), (3, 1), (None, None)} <= links
    removed = {(r.doc_id, r.n_removed) for r in substring_dedup.remove_repeats(docs).collect()}
    assert {(1, 0), (2, 60), (3, 60), (None, 0)} <= removed
