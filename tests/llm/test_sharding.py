import random
import zlib

import duckdb

from graphparts.llm import sharding as s

SCHEMA = "doc_id bigint, text string, shard string"


def check(got, docs, shards, overhead=8):
    want = {}
    for i, t in docs:
        size = len((t or "").encode()) + overhead
        want.setdefault(i, []).append((size, zlib.crc32((t or "").encode())))
    assert len(got) == len(docs)
    for r in got:
        assert (r.size, r.text_crc32) in want[r.doc_id] and r.law == "bytes" and r.grown_shard is None
    by = {}
    for r in got:
        by.setdefault(r.shard, []).append(r)
    for rows in by.values():
        assert sorted(r.slot for r in rows) == list(range(len(rows)))
    sums = [sum(r.size for r in by.get(k, [])) for k in range(shards)]
    largest = max((r.size for r in got), default=0)
    assert max(sums) - min(sums) <= 2 * largest
    return sums


def test_equal_bytes_with_a_hot_text(spark):
    r = random.Random(5)
    docs = [(i, "x" * r.randrange(0, 900)) for i in range(600)] + [(i, "hot text" * 20) for i in range(600, 900)]
    docs += [(2000, None), (2001, ""), (2002, "ñ" * 50)]
    df = spark.createDataFrame([(*d, "z") for d in docs], SCHEMA)
    for shards in (1, 5, 24):
        check(s.equal_byte_shards(df, shards=shards).collect(), docs, shards)
    loose = s.equal_byte_shards(df, shards=8, tolerance=0.2).collect()
    sums = [sum(x.size for x in loose if x.shard == k) for k in range(8)]
    mean = sum(sums) / 8
    assert all(abs(v - mean) < 0.45 * mean for v in sums)


def test_splitters_are_exact(spark):
    r = random.Random(6)
    for n in (1, 7, 300):
        keys = [(r.choice([r.randrange(2**60), r.randrange(5), (3 << 40) + r.randrange(9)]), r.randrange(1, 50)) for _ in range(n)]
        cuts = s.splitters(spark.createDataFrame(keys, "key bigint, size bigint"), 9)
        total = sum(v for _, v in keys)
        for k, _ in keys:
            assert sum(c <= k for c in cuts) == sum(v for j, v in keys if j < k) * 9 // total


def test_edges(spark):
    df = spark.createDataFrame([], SCHEMA)
    assert s.equal_byte_shards(df).collect() == []
    same = spark.createDataFrame([(1, "a", "q"), (1, "a", "q"), (None, None, None), (None, "b", None)], SCHEMA)
    got = s.equal_byte_shards(same).collect()
    assert len(got) == 4 and len({(r.shard, r.slot) for r in got}) == 4
    carried = s.shard(same, shards=2).collect()
    assert set(carried[0].asDict()) == {"doc_id", "text", "size", "shard", "slot"} and len(carried) == 4


def test_equals_sql(spark):
    path = "/root/testdata/sf0.01/documents.parquet"
    rows = duckdb.sql(f"""
        WITH k AS (SELECT doc_id, strlen(text) + 8 AS size, ('0x' || substr(md5(text), 1, 10))::BIGINT * 1048576 + ('0x' || substr(md5(doc_id::VARCHAR), 1, 5))::BIGINT AS key FROM '{path}'),
        c AS (SELECT *, sum(size) OVER (ORDER BY key RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) - sum(size) OVER (PARTITION BY key) AS before, sum(size) OVER () AS total FROM k)
        SELECT doc_id, (before * 24 // total)::INT FROM c""").fetchall()
    got = s.equal_byte_shards(spark.read.parquet(path)).collect()
    assert {(r.doc_id, r.shard) for r in got} == set(rows)
