import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from graphparts.llm import bpe, bpe_expressions
from graphparts.llm.tokens import default_pattern, fast_encoder, vocabulary

PATH = vocabulary("byte_bpe_50k.tiktoken")
ODD = [None, "", " ", "a", "'s 're\n\n x y   Ⅷ٣ \x00 <|endoftext|>", "a" * 700, " \t\n" * 20, "日本語 emoji 👍🏽 ñ　 x\x85\xa0y\x1c z", "\x01\x01,\x01", "it's DON'T 12345 ***%%%  tail  "]


def want(text):
    ids = fast_encoder(PATH, default_pattern()).encode_ordinary(text or "")
    raw = (text or "").encode()
    return len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(raw).hexdigest()


@pytest.mark.parametrize("style", [bpe, bpe_expressions])
def test_equals_library(spark, style):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").collect()][:60]
    docs += [(10_000 + i, t) for i, t in enumerate(ODD)] + [(None, "x y"), (5_000, "same"), (5_000, "same")]
    df = spark.createDataFrame([(*d, "e") for d in docs], "doc_id bigint, text string, ids string")
    expected = sorted(((i, *want(t)) for i, t in docs), key=str)
    assert sorted((tuple(r) for r in style.encode_and_decode(df).collect()), key=str) == expected
    assert style.encode_and_decode(df.limit(0)).collect() == []


@pytest.mark.parametrize("words", [0, 40])
def test_table_of_frequent_words_never_changes_ids(spark, words):
    df = spark.createDataFrame([(i, t) for i, t in enumerate(ODD + ["the same words and the same words again"] * 3)], "doc_id bigint, text string")
    got = {r.doc_id: r.ids for r in bpe_expressions.with_ids(df, dictionary_words=words).collect()}
    encode = fast_encoder(PATH, default_pattern()).encode_ordinary
    assert got == {r.doc_id: encode(r.text or "") for r in df.collect()}
    back = bpe_expressions.with_ids(df, dictionary_words=words).select("text", bpe_expressions.decoded(F.col("ids"), PATH).alias("b")).collect()
    assert all(bytes(r.b).decode() == (r.text or "") for r in back)


def test_perfect_hash():
    h = np.random.default_rng(1).integers(-(2**63), 2**63 - 1, 5000)
    moved, slot, slots = bpe_expressions.perfect_hash(h)
    assert len(set(slot.tolist())) == 5000 and slot.max() < slots


def test_fold_of_short_and_long_words():
    r, e = np.random.default_rng(2), bpe.Encoder(PATH, default_pattern(), words=3)
    encode = fast_encoder(PATH, default_pattern()).encode_ordinary
    for n in [*range(1, 60), 200, 1000]:
        for letters in ("ab", "etaoin", "abcdefghijklmnopqrstuvwxyz"):
            w = "".join(r.choice(list(letters), n))
            assert e.fold(w.encode()) == e._fold_long(w.encode()) == encode(w)
    assert e.decode(encode("ñ 👍")) == "ñ 👍".encode()


def test_ids_as_arrays(spark):
    df = spark.createDataFrame(list(enumerate(ODD)), "doc_id bigint, text string")
    encode = fast_encoder(PATH, default_pattern()).encode_ordinary
    assert {r.doc_id: r.ids for r in bpe.with_ids(df).collect()} == {i: encode(t or "") for i, t in enumerate(ODD)}
