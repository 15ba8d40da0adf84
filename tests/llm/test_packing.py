import random
import zlib
from itertools import combinations

import numpy as np
from tokenizers import Tokenizer

from graphparts.llm import packing, tokens


def library():
    t = Tokenizer.from_file(tokens.vocabulary("byte_bpe_50k.json"))
    t.encode_special_tokens = True
    return t


def test_fullest_is_best():
    r = random.Random(7)
    for _ in range(200):
        items = [r.randrange(1, 40) for _ in range(r.randrange(0, 9))]
        counts = {n: items.count(n) for n in items}
        room = r.randrange(0, 90)
        best = max(sum(c) for k in range(len(items) + 1) for c in combinations(items, k) if sum(c) <= room)
        got = packing.fullest(counts, room)
        assert sum(n * m for n, m in got.items()) == best and all(m <= counts[n] for n, m in got.items())


def test_plan_uses_every_piece_once():
    r = random.Random(8)
    for capacity in (10, 64, 1024):
        counts = {n: r.randrange(0, 50) for n in r.sample(range(1, capacity + 1), min(capacity, 60))}
        bins, seen = {}, {n: [] for n in counts}
        for n, first, last, each, sequence, place in packing.plan(counts, capacity):
            for rank in range(first, last + 1):
                seen[n].append(rank)
                bins.setdefault(sequence + (rank - first) // each, []).append((place + (rank - first) % each * n, n))
        assert all(sorted(v) == list(range(counts[n])) for n, v in seen.items())
        for b in bins.values():
            at = 0
            for offset, n in sorted(b):
                assert offset == at
                at += n
            assert at <= capacity
        total = sum(n * c for n, c in counts.items())
        assert len(bins) <= -(-total // capacity) * 1.05 + sum(c for n, c in counts.items() if 2 * n > capacity)


def check(got, docs, lib, capacity=1024):
    ids = {}
    for i, t in docs:
        ids.setdefault(i, []).append([*lib.encode(t or "", add_special_tokens=False).ids, 2])
    bins = {}
    total = {}
    for r in got:
        assert any(r.ids_crc32 == zlib.crc32(np.array(x[r.start : r.start + r.length], "<u4").tobytes()) for x in ids[r.doc_id])
        assert r.length == capacity or r.piece == 0
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
        total[r.doc_id] = total.get(r.doc_id, 0) + r.length
    assert total == {i: sum(map(len, x)) for i, x in ids.items()}
    for b in bins.values():
        at = 0
        for offset, n in sorted(b):
            assert offset == at
            at += n
        assert at <= capacity
    free = []
    for n in sorted((r.length for r in got), reverse=True):  # first fit, longest first
        k = next((k for k, f in enumerate(free) if f >= n), None)
        if k is None:
            free.append(capacity)
            k = -1
        free[k] -= n
    return len(bins), len(free)


def test_pack(spark):
    r = random.Random(9)
    word = lambda: "".join(r.choice("abcdeñé") for _ in range(r.randrange(1, 8)))
    docs = [(i, " ".join(word() for _ in range(r.choice([1, 5, 50, 200, 900])))) for i in range(120)]
    docs += [(500, None), (501, ""), (502, "<|endoftext|> x"), (503, "a " * 1023), (504, "a " * 1022), (505, "a " * 2047), (None, "b")] + [(600, "same row")] * 5
    df = spark.createDataFrame([(*d, 3) for d in docs], "doc_id bigint, text string, length int")
    for capacity in (1024, 16):
        bins, first_fit = check(packing.pack(df, capacity=capacity).collect(), docs, library(), capacity)
        assert bins <= first_fit
    assert packing.pack(df.limit(0)).collect() == []


def test_encoders_agree():
    import pyarrow.parquet as pq

    texts = pq.read_table("/root/testdata/sf0.01/documents.parquet").column("text").to_pylist()[:300]
    fast = tokens.fast_encoder(tokens.vocabulary("byte_bpe_50k.json"), tokens.default_pattern())
    odd = ["'s 're\n\n x y   Ⅷ٣ \x00 <|endoftext|>", "a" * 3000, " \t\n" * 50, "日本語 emoji 👍🏽"]
    assert [fast.encode_ordinary(t) for t in texts + odd] == [e.ids for e in library().encode_batch(texts + odd, add_special_tokens=False)]
