"""Corpus operators on small tables with nulls, ties, repeated rows, empty tables and clashing columns."""

import hashlib
import os
import random
import re
from collections import Counter

import pytest
from pyspark.sql import functions as F

from blindmatch.llm import exact_dedup, html_wrappers, mixture, ngram_join, quality, secret_scan, substring_dedup, url_filter, warc

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def frame(spark, texts, extra="id long, text_key string, kept string, n long, source string"):
    rows = [(i, t, i, "x", "y", 1, f"s{i % 3}" if i % 5 else None) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, f"doc_id long, text string, {extra}")


def corpus(seed=1, n=60):
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(400)]
    shared = [rng.choice(words) for _ in range(40)]
    texts = [None, "", "  \n", "one", "One", "É é", "é É", "a b c"]
    for i in range(n):
        body = [rng.choice(words) for _ in range(rng.choice([5, 30, 120]))]
        if i % 3 == 0:
            at = rng.randrange(len(body))
            body[at:at] = shared[: rng.choice([12, 13, 14, 40])]
        texts.append(" ".join(body))
        if i % 4 == 0:
            copy = list(body)
            copy[rng.randrange(len(copy))] = "changed"
            texts += [" ".join(copy), " ".join(body).upper()]
    return texts + ["deep " * 3000]


def test_exact_dedup(spark):
    texts = corpus()
    low = ["".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "") for t in texts]
    got = {r.doc_id: r for r in exact_dedup.duplicate_groups(frame(spark, texts)).collect()}
    for i, t in enumerate(low):
        same = [j for j, u in enumerate(low) if u == t]
        assert (got[i].keep_id, got[i].group_size, got[i].kept) == (max(same), len(same), i == max(same))
        assert got[i].text_sha256 == hashlib.sha256(t.encode()).hexdigest()
    assert exact_dedup.deduplicate(frame(spark, texts)).count() == len(set(low))
    assert exact_dedup.duplicate_groups(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_substring_dedup(spark):
    texts = corpus(2)
    words = [WORD.findall(t or "") for t in texts]
    first = {}
    for i, w in enumerate(words):
        for j in range(len(w) - 12):
            first.setdefault(tuple(w[j : j + 13]), i)
    got = {r.doc_id: r for r in substring_dedup.remove_repeats(frame(spark, texts)).collect()}
    assert len(got) == len(texts)
    for i, w in enumerate(words):
        gone = {k for j in range(len(w) - 12) if first[tuple(w[j : j + 13])] < i for k in range(j, j + 13)}
        kept = " ".join(x for j, x in enumerate(w) if j not in gone)
        assert (got[i].n_words, got[i].n_removed, got[i].kept) == (len(w), len(gone), kept)
    assert substring_dedup.remove_repeats(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def jaccard_components(texts, k, percent):
    sets = []
    for t in texts:
        t = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
        w = WORD.findall(t)
        sets.append({tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set()))
    root = list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(sets)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return sets, [find(i) for i in range(len(texts))]


def test_ngram_join(spark):
    texts = corpus(3)
    base = " ".join(f"v{i}" for i in range(200))
    texts += [base.replace(f"v{i} ", f"u{i} ") for i in range(0, 100, 2)]  # one group of near copies
    for k, percent in ((4, 85), (5, 80)):
        sets, roots = jaccard_components(texts, k, percent)
        got = {r.doc_id: r for r in ngram_join.link_documents(frame(spark, texts), percent=percent, shingle=k).collect()}
        assert [(got[i].n_shingles, got[i].component_id) for i in range(len(texts))] == [(len(s), r) for s, r in zip(sets, roots)]
    assert ngram_join.link_documents(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_rtree_finds_all_that_the_bound_allows():
    import numpy as np

    rng = np.random.default_rng(4)
    points = rng.integers(0, 4, (300, ngram_join.GROUPS)).astype(np.uint16)
    points[150:] = points[:150]
    points[150:, 0] += 1
    sizes = points.sum(axis=1).astype(np.int64)
    tree = ngram_join.RTree(points, sizes)
    for i in range(0, 300, 7):
        found = set(tree.order[tree.search(points[i].astype(np.int32), sizes[i], np.ones(300, bool), 85)].tolist())
        bound = np.minimum(points, points[i]).sum(axis=1)
        assert found == set(np.flatnonzero(ngram_join.links(bound, sizes[i], sizes)).tolist())


def test_mixing(spark):
    df = frame(spark, corpus(5))
    got = mixture.mix_sources(df).join(df.select("doc_id", "source"), "doc_id").collect()
    by = {}
    for r in got:
        assert 0 <= r.taken <= 2 * r.size
        by.setdefault(r.source, []).append(r)
    assert abs(sum(rs[0].target for rs in by.values()) - 1.5 * sum(r.size for r in got)) < 1e-6
    for rs in by.values():
        assert abs(sum(r.taken for r in rs) - rs[0].target) <= 1
    rows = mixture.mixed_rows(df)
    assert rows.columns == df.columns
    assert sum(len(WORD.findall(r.text)) for r in rows.collect()) == sum(r.taken for r in got)
    assert mixture.mix_sources(df.limit(0)).count() == 0


def base_rules(text):
    w = WORD.findall(text or "")
    windows = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    covered = {j for i in range(len(w) - 2) if windows[tuple(w[i : i + 3])] > 1 for j in range(i, i + 3)}
    lines = [x for x in (text or "").split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(covered)


def test_quality(spark):
    texts = corpus(6) + ["a b c a b c a b c\n\n \nx\nx\ny & z <b> ##\nx", "é漢 字| w\nw\n"]
    df = frame(spark, texts)
    good = df.select("doc_id").where("doc_id % 2 = 0")
    for trusted in (good, None, good.limit(0)):
        for r in quality.judge(df, trusted).collect():
            n, chars, symbols, lines, repeats = base_rules(texts[r.doc_id])
            assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (n, chars, symbols, lines, repeats)
            assert r.base_failed == (n < 50 or 100 * repeats > 50 * n)
            assert not (r.base_failed and r.kept)
    assert quality.keep_good(df, good).columns == df.columns
    assert quality.judge(df.limit(0), good).count() == 0


def test_secrets(spark):
    texts = [
        None, "", 'password = "hunter2hunter2"', "token: abc", "AKIA" + "A1" * 10, "x" + "0f" * 12 + "g", "MyApi_Key='abcdefgh' tokenſ: aaaaaaa",
        'seed = "Zx81kQp0w9Lm"\nuser = "bob"\ndb_pwd = seed\n', "client:\n  credentials: Qw3rTy77Zz\n  color: Qw3rTy77Zy\n", 'part = "Ab12cd" + "x"\nauth_signature = part + tail\n',
    ]
    got = {r.doc_id: r for r in secret_scan.scan(frame(spark, texts)).collect()}
    for i, t in enumerate(texts):
        t = t or ""
        base = [(m.start(), 0, m.end(), "assign") for m in re.finditer(r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", t) if len(m[2]) >= 6]
        base += [(m.start(), 1, m.end(), "access") for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 20] + [(m.start(), 2, m.end(), "hex") for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 24]
        text = ",".join(f"{k}:{a}:{b}" for a, _, b, k in sorted(base))
        assert got[i].base_sha256 == hashlib.sha256(text.encode()).hexdigest()
    assert [got[i].n_literal for i in (7, 8, 9)] == [1, 1, 1]
    assert got[7].spans == "literal:8:20"


@pytest.mark.parametrize("sf", ["0.001", "0.01", "0.1"])
def test_quality_tells_junk_at_every_size(spark, sf):
    from blindmatch.llm import queries

    folder = f"/root/testdata/sf{sf}"
    if not os.path.isdir(folder):
        pytest.skip("the given tables are absent")
    judged = queries.op8_quality_rules(spark, folder).where("not base_failed").join(queries.table(spark, folder, "labels"), "doc_id")
    n = {r.quality: (r["n"], r.kept) for r in judged.groupBy("quality").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("kept").cast("int")).alias("kept")).collect()}
    assert n[0][1] <= 0.01 * n[0][0] and n[1][1] >= 0.98 * n[1][0]


@pytest.mark.parametrize(
    "text",
    [
        '{"user": "bob", "db_pwd": "@"}', 'a = 1; pwd = "@"; b = 2', 'connect(host="h", pwd="@")', "x:\n  - pwd: @\n", 'private static final String PASSPHRASE = "@";', 'const pwd: string = "@"',
        'pwd: Optional[str] = "@"', 'char pwd[] = "@";', 'cfg["pwd"] = "@"', 'other = pwd = "@"', "opts=pwd=@", "host=db;pwd=@;x=1", 's="@";user="b";f(pwd=s)', '{"a":"b=","c":[1,{"pwd":"@"}]}', "private key: '@'",
    ],
)
def test_every_pair_of_a_line(text):
    secret = "Zx81kQp0w9Lm"
    at = text.index("@")
    assert (at, at + len(secret), "literal") in secret_scan.all_spans(text.replace("@", secret))[1]


def test_all_literals_that_flow_through_a_name():
    text = "".join(f's{i} = "Zq{i:05d}xYzAb"\n' for i in range(200)) + "whole = " + " + ".join(f"s{i}" for i in range(200)) + "\ndb_pwd = whole\n"
    assert len(secret_scan.lexed_spans(text)) == 200
    assert secret_scan.lexed_spans('if pwd == "Zx81kQp0w9Lm" and pwd != "Zx81kQp0w9Ln": pass') == []


def test_warc(spark):
    big = "<p>" + "é" * 200
    pages = [(1, "http://a/\r\nx", big, "z"), (2, None, big, "z"), (3, "", None, "z"), (4, "http://b", "", "z"), (5, "http://c", "x" * 99, "z"), (6, "http://c", "x" * 99, "z"), (7, "http://d", "WARC/1.1\r\n\r\n" * 20, "z"), (None, "http://n", big, "z")]
    got = warc.round_trip(spark.createDataFrame(pages, "page_id long, url string, html string, record_type string")).collect()
    by = {r.page_id: r for r in got}
    assert len(got) == len(pages) and by[2].record_type == "revisit" and by[2].refers_to == 1
    for i, _, h, _ in pages:
        h = (h or "").encode()
        assert by[i].payload_digest == hashlib.sha256(h).hexdigest() and by[i].payload_bytes == len(h)
    assert Counter(r.record_type for r in got) == {"response": 7, "revisit": 1}


def test_html(spark):
    page = "<html><head><title>t</title><script>x</script></head><body><nav>menu</nav><div class=ad>buy</div><article><h1>T&amp;t</h1><p>a <b>b</b>c<br>d<p>e&nbsp;f</article><footer>f</footer></body></html>"
    rows = [(i, f"http://h/{i}", page.replace("a ", f"a{i} "), "x") for i in range(5)] + [(9, None, None, "x"), (10, "bad", "plain &lt;text", "x"), (11, "http://h/q", "<p>cut <a hre", "x")]
    got = {r.page_id: r for r in html_wrappers.extract(spark.createDataFrame(rows, "page_id long, url string, html string, text string")).collect()}
    assert got[3].text == "T&t a3 bc d e f" and got[3].n_chars == len(got[3].text)
    assert (got[9].text, got[10].text, got[11].text) == ("", "plain <text", "cut")


def test_wrapper_groups():
    pages = ["<ul><li>a</li></ul><p>x</p>", "<ul><li>a</li><li>b</li><li>c</li></ul><p>y</p>", "<ul><li>d</li></ul><b>z</b><p>w</p>"]
    wrapper = html_wrappers.infer_wrapper(pages)
    kinds = {x[0] for x in wrapper}
    assert "?" in kinds and "#slot" in kinds


def test_wrappers_decide_inside_and_outside_of_articles(spark):
    def page(i):
        return f"<body><article><p>story {i} {'long ' * i}</p><div class='box'>Read more here</div><p class='note'>All rights</p></article><div class='x'>fixed</div></body>"

    # h: template in articles, on more pages than any sample; t: the wrapper's slot outweighs a short article; two: a host with two pages.
    rows = [(i, f"http://h/{i}", page(i)) for i in range(40)]
    rows += [(100 + i, f"http://t/{i}", f"<article>ad{i}</article><div class='post'>{'tale ' * 20}{i}</div>") for i in range(4)]
    rows += [(200 + i, f"http://two/{i}", f"<div class='intro'>Welcome to all</div><div class='post'>text {i}</div>") for i in range(2)]
    # Template after more than 2,000 tokens; equal pages, which have no slot.
    rows += [(300 + i, f"http://deep/{i}", "<div class='post'>" + f"<p>x{i}</p>" * 1500 + "</div><div class='post'><div class='end'>The end</div></div>") for i in range(3)]
    rows += [(400 + i, f"http://same/{i}", "<body><article>one text</article></body>") for i in range(3)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    got = {r.page_id: r.text for r in html_wrappers.extract(df).collect()}
    for i in range(40):
        assert got[i] == f"story {i} {'long ' * i}".strip()
    for i in range(4):
        assert got[100 + i] == "tale " * 20 + str(i)
    assert [got[200 + i] for i in range(2)] == ["text 0", "text 1"]
    assert [got[300 + i] for i in range(3)] == [" ".join([f"x{i}"] * 1500) for i in range(3)]
    assert [got[400 + i] for i in range(3)] == ["one text"] * 3


def test_url_filter(spark):
    entries = [("bad.example", 10, "add"), ("bad.example", 20, "remove"), ("a.b.example", 5, "add"), ("c.example/x", 1, "add"), ("t.example", 3, "add"), ("t.example", 3, "remove"), (None, 1, "add")]
    urls = [("http://www.bad.example/p", 9), ("http://www.bad.example/p", 10), ("http://bad.example", 19), ("http://bad.example", 20), ("https://u:p@a.b.example:8/x", 6), ("http://c.example/x/y", 2), ("http://c.example/z", 2), (None, 2), ("t.example", 4), ("http://t.example?q", 4)]
    got = url_filter.judge_urls(
        spark.createDataFrame([(i, u, d, "k") for i, (u, d) in enumerate(urls)], "page_id long, url string, fetch_day int, host string"), spark.createDataFrame(entries, "list_key string, day int, action string")
    )
    assert [r.blocked for r in got.orderBy("page_id").collect()] == [False, True, True, False, True, True, False, False, False, True]
    assert got.where(F.col("page_id") == 1).first().matched_key == "bad.example"


def test_pipeline_stages(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    texts = [t for t in corpus(7) if t]
    docs = spark.createDataFrame([(i, t, "en", f"s{i % 3}", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    kept = pipeline.distinct_documents(spark, docs, "").collect()
    assert len(kept) == len({t.lower() if t.isascii() else t for t in texts})
    near = pipeline.one_of_each_group(spark, docs, "")
    _, roots = jaccard_components(texts, 5, 80)
    assert sorted(r.doc_id for r in near.collect()) == sorted(set(roots) | {i for i, r in enumerate(roots) if r == i})
    assert near.columns == docs.columns


def test_exact_sets_find_the_groups_of_all_pairs():
    import numpy as np

    rng = np.random.default_rng(2)
    for percent in (80, 85):
        sets = []
        for _ in range(40):
            base = rng.choice(3000, rng.integers(1, 100), replace=False)
            for _ in range(rng.integers(1, 9)):
                part = base[rng.random(len(base)) > 0.05 * rng.integers(0, 4)]
                sets.append(np.unique(np.concatenate([part if len(part) else base[:1], rng.choice(3000, rng.integers(0, 4))])).astype(np.uint64))
        plain = [set(s.tolist()) for s in sets]
        linked = np.array([[a is not b and ngram_join.links(len(a & b), len(a), len(b), percent) for b in plain] for a in plain])
        found = ngram_join.grow_groups(len(sets), ngram_join.ExactSets(sets, percent).reach)
        assert (found == ngram_join.grow_groups(len(sets), lambda i, alive: np.flatnonzero(linked[i] & alive))).all()
