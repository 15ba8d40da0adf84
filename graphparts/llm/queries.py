"""One query for each operator, over its whole table with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from graphparts.llm.common import table


def op1_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphparts.llm.secret_scan import labelled_findings, scan, train

    return scan(table(spark, sf_dir, "documents"), train(labelled_findings(spark, 8000, wide=True), wide=True), wide=True)


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphparts.llm.substring_dedup import remove_repeats

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return remove_repeats(docs, digest_only=True).select("doc_id", "n_words", "n_removed", "kept_sha256")


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphparts.llm.quality_mil import quality

    return quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphparts.llm.sharding import equal_byte_shards

    return equal_byte_shards(table(spark, sf_dir, "documents"))


def op5_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphparts.llm.bpe import encode_and_decode

    return encode_and_decode(table(spark, sf_dir, "documents"))


def op6_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphparts.llm.ngram_join import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphparts.llm.packing import pack

    return pack(table(spark, sf_dir, "documents"))


def op8_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphparts.llm.media_ts import media_digests

    return media_digests(table(spark, sf_dir, "documents"))


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphparts.llm.langid import identify

    return identify(table(spark, sf_dir, "documents"))


def op10_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from graphparts.llm.embed_dedup import near_duplicate_vectors

    return near_duplicate_vectors(table(spark, sf_dir, "embeddings"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: v for k, v in sorted(globals().items()) if k.startswith("op") and callable(v)}


OP2_SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
win AS (SELECT doc_id, i, md5(array_to_string(w[i:i + 34], ' ')) AS k
        FROM (SELECT doc_id, w, unnest(range(1, len(w) - 33)) AS i FROM d)),
hit AS (SELECT doc_id, i FROM win WHERE k IN (SELECT k FROM win GROUP BY k HAVING count(*) > 1)),
gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + 35)) AS pos FROM hit),
word AS (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS pos FROM d),
kept AS (SELECT doc_id, string_agg(w[pos], ' ' ORDER BY pos) AS t, count(*) AS n
         FROM word ANTI JOIN gone USING (doc_id, pos) GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(n, 0))::BIGINT AS n_removed,
       sha256(coalesce(t, '')) AS kept_sha256
FROM d LEFT JOIN kept USING (doc_id)
"""

OP4_SQL = """
WITH RECURSIVE step AS (SELECT i, 0 AS k, i AS c FROM range(256) t(i) UNION ALL SELECT i, k + 1, CASE WHEN c % 2 = 1 THEN xor(c // 2, 3988292384) ELSE c // 2 END FROM step WHERE k < 8),
crc AS (SELECT list(c ORDER BY i) AS t FROM step WHERE k = 8),
d AS (SELECT doc_id, coalesce(text, '') AS text, strlen(coalesce(text, '')) AS n, hex(encode(coalesce(text, ''))) AS hx FROM documents),
k AS (SELECT doc_id, n + 8 AS size,
        xor(list_reduce(list_transform(range(0, n), lambda i: ('0x' || substr(hx, 2 * i + 1, 2))::BIGINT), lambda a, b: xor(a // 256, t[xor(a, b) % 256 + 1]), 4294967295::BIGINT), 4294967295) AS text_crc32,
        ('0x' || substr(md5(text), 1, 10))::BIGINT * 1048576 + ('0x' || substr(md5(doc_id::VARCHAR), 1, 5))::BIGINT AS key
      FROM d, crc),
c AS (SELECT *, sum(size) OVER (ORDER BY key RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) - sum(size) OVER (PARTITION BY key) AS before, sum(size) OVER () AS total FROM k),
s AS (SELECT *, (before * 24 // total)::INT AS shard FROM c)
SELECT doc_id, size::BIGINT AS size, text_crc32, 'bytes' AS law, shard, row_number() OVER (PARTITION BY shard ORDER BY key % 64, key, doc_id, text_crc32) - 1 AS slot, NULL::INT AS grown_shard FROM s
"""

OP6_SQL = r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
t AS (SELECT md5(array_to_string(w, ' ')) AS k, min(doc_id) AS id, count(*) AS copies, any_value(w) AS w FROM d WHERE doc_id IS NOT NULL AND len(w) > 0 GROUP BY 1),
g AS MATERIALIZED (SELECT DISTINCT id, md5(unnest(CASE WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END)) AS s FROM t),
n AS (SELECT id, count(*) AS n FROM g GROUP BY id),
c AS (SELECT x.id AS a, y.id AS b, count(*) AS c FROM g x JOIN g y USING (s) WHERE x.id < y.id GROUP BY ALL),
half AS (SELECT a, b FROM c JOIN n x ON x.id = a JOIN n y ON y.id = b WHERE c >= 0.8 * (x.n + y.n - c) - 1e-9),
link AS MATERIALIZED (SELECT a, b FROM half UNION ALL SELECT b, a FROM half),
reach AS (SELECT DISTINCT a, a AS r FROM link UNION SELECT l.a, reach.r FROM reach JOIN link l ON l.b = reach.a),
low AS (SELECT a, min(r) AS c FROM reach GROUP BY a),
deg AS (SELECT a, count(*) AS texts, sum(t.copies) AS documents FROM link JOIN t ON t.id = link.b GROUP BY a)
SELECT d.doc_id, coalesce(t.id, d.doc_id) AS text_id, coalesce(low.c, t.id, d.doc_id) AS class_id, (coalesce(documents, 0) + coalesce(copies, 1) - 1)::BIGINT AS n_links,
       coalesce(texts, 0)::BIGINT AS n_texts, d.doc_id = coalesce(low.c, t.id, d.doc_id) AS kept
FROM d LEFT JOIN t ON d.doc_id IS NOT NULL AND t.k = md5(array_to_string(d.w, ' ')) LEFT JOIN low ON low.a = t.id LEFT JOIN deg ON deg.a = t.id
"""

OP10_SQL = """
WITH RECURSIVE ok AS (
  SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0 AND vec_id IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
    AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
link AS (SELECT a.vec_id AS a, b.vec_id AS b FROM ok a JOIN ok b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
         WHERE list_cosine_similarity(a.e, b.e) >= 0.95),
reach AS (SELECT DISTINCT a, a AS r FROM link UNION SELECT l.a, reach.r FROM reach JOIN link l ON l.b = reach.a),
low AS (SELECT a, min(r) AS c FROM reach GROUP BY a),
deg AS (SELECT a, count(*) AS n FROM link GROUP BY a)
SELECT vec_id, coalesce(n, 0)::BIGINT AS n_links, coalesce(c, vec_id) AS component_id, vec_id = coalesce(c, vec_id) AS kept
FROM embeddings LEFT JOIN low ON low.a = vec_id LEFT JOIN deg ON deg.a = vec_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_substring_dedup": OP2_SQL, "op4_sharding": OP4_SQL, "op6_ngram_jaccard_join": OP6_SQL, "op10_embedding_near_dedup": OP10_SQL}
