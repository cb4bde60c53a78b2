import hashlib
import random

import numpy as np
import pyarrow as pa
import public_tokenizers as P
import pytest
import regex
import tiktoken
from pyspark.sql import functions as F

from blindmatch.llm import bpe


@pytest.fixture(scope="module")
def ranks():
    return bpe.load_ranks(P.path("byte_bpe_multi_50k.tiktoken"))


@pytest.fixture(scope="module")
def reference(ranks):
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def odd_texts(n=400):
    rng = random.Random(5)
    bits = ["'s", "'ll", "'re", "'", " ", "  ", "\n", "\t", " ", " ", "\x1c", "\x85", "stop", "été", "ñ", "12", "½", "٣", "!", "...", "漢字", "😀", "'S", "'st", "\0", "é", "Ⅷ", "_"]
    return ["".join(rng.choice(bits) for _ in range(rng.randint(0, 12))) for _ in range(n)]


def test_split_is_the_pattern():
    classes = bpe.code_point_classes()
    texts = odd_texts(3000)
    words, bounds = bpe.split_chunk(texts, classes)
    for text, a, b in zip(texts, bounds, bounds[1:]):
        assert words[a : b - 1] == regex.findall(P.PATTERN, text)


def test_long_words_merge_alike(ranks, reference):
    for word in ("a" * 5000, "abcé" * 300, "".join(random.Random(1).choice("abcdefgh") for _ in range(3000))):
        assert bpe.merge_word(word.encode(), ranks) == reference.encode_ordinary(word)
        assert bpe._merge_long(word[:90].encode(), ranks) == bpe.merge_word(word[:90].encode(), ranks)


def test_fold_of_words(spark, ranks, reference):
    words = sorted({w for t in odd_texts(200) for w in regex.findall(P.PATTERN, t)} | {"", "onthereheing", " verheit"})
    df = spark.createDataFrame([(w,) for w in words] + [(None,)], "word string")
    for row in bpe.encode_words(df, ranks).collect():
        assert row.ids == (reference.encode_ordinary(row.word) if row.word else [])


def test_documents(spark, ranks, reference):
    texts = [*odd_texts(), None, "", "dup", "dup", "long " * 4000 + "x" * 3000]
    df = spark.createDataFrame([(i, t, "extra") for i, t in enumerate(texts)], "doc_id long, text string, ids string")
    got = {r.doc_id: r for r in bpe.encode_and_decode(df, ranks).collect()}
    assert len(got) == len(texts)
    for i, t in enumerate(texts):
        ids = reference.encode_ordinary(t or "")
        assert got[i].n_tokens == len(ids)
        assert got[i].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()


def test_decoding_is_a_concatenation(spark, ranks):
    row = spark.range(1).select(bpe.decode_ids(F.array(F.lit(0), F.lit(5)), ranks).alias("b"), bpe.decode_ids(F.array().cast("array<int>"), ranks).alias("e")).first()
    by_rank = {v: k for k, v in ranks.items()}
    assert bytes(row.b) == by_rank[0] + by_rank[5] and bytes(row.e) == b""


def test_decoding_tables(spark, ranks):
    by_rank = {v: k for k, v in ranks.items()}
    rows = [(1, [0, 5, 300, 49_000]), (2, []), (3, None), (3, [7]), (None, [7, 7])]
    coded = spark.createDataFrame(rows, "doc_id long, ids array<int>")
    got = sorted((str(r.doc_id), None if r.decoded is None else bytes(r.decoded)) for r in bpe.decode_documents(coded, ranks).collect() if r.decoded is not None)
    assert got == sorted((str(i), b"".join(by_rank[x] for x in ids)) for i, ids in rows if ids is not None)
    assert bpe.decode_documents(coded.where("ids is null"), ranks).first().decoded is None
    cut = pa.array([[1], [2, 3], None, [], [4]], pa.list_(pa.int32())).slice(1, 3)
    assert bpe.decoded(cut, bpe.piece_array(ranks)) == [by_rank[2] + by_rank[3], None, b""]
    with pytest.raises((ValueError, IndexError)):
        bpe.decoded(pa.array([[10**9]], pa.list_(pa.int32())), bpe.piece_array(ranks))


def test_empty_table(spark, ranks):
    assert bpe.encode_and_decode(spark.createDataFrame([], "doc_id long, text string"), ranks).count() == 0
