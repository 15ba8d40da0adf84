"""What several of the training-data operators share."""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphparts.plans.scratch import dropped, shared_folder, written  # noqa: F401


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold_column(doc_id: str = "doc_id") -> Column:
    """crc32 of the decimal doc_id, modulo 3; 1 marks a held-out row (null ids: null)."""
    return F.crc32(F.col(doc_id).cast("string")).cast("bigint") % 3


def held_out_column(doc_id: str = "doc_id") -> Column:
    return F.coalesce(fold_column(doc_id) == 1, F.lit(False))


def utf8(text: str | None) -> bytes:
    return b"" if text is None else text.encode("utf-8", "surrogatepass")


def pieces(batch: pa.RecordBatch, rows: int) -> Iterator[pa.RecordBatch]:
    """``batch`` in consecutive pieces of at most ``rows`` rows that share its memory."""
    for begin in range(0, batch.num_rows, rows):
        yield batch.slice(begin, rows)


def mapped(df: DataFrame, function: Callable[[pa.RecordBatch], dict | None], schema: str, rows: int = 1 << 31) -> DataFrame:
    """``df`` batch by batch through ``function``, which returns columns by name and sees at most ``rows`` rows at once, so that what it makes of them is bounded."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    arrow = to_arrow_schema(StructType.fromDDL(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for piece in pieces(batch, rows):
                if (out := function(piece)) is None:
                    continue
                yield pa.RecordBatch.from_arrays([pa.array(out[f.name], type=f.type) for f in arrow], schema=arrow)

    return df.mapInArrow(run, schema)


def crc32(data: bytes) -> int:
    return zlib.crc32(data) & 0xFFFFFFFF


#: Odd 64-bit multipliers (fixed values) for mixing.
MIX_A, MIX_B = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of unsigned 64-bit values."""
    x = x ^ (x >> np.uint64(30))
    x = x * MIX_A
    x = x ^ (x >> np.uint64(27))
    x = x * MIX_B
    return x ^ (x >> np.uint64(31))


def word_hashes(words: list[bytes]) -> np.ndarray:
    import xxhash

    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


def odd_constants(n: int, seed: int) -> np.ndarray:
    return mix(np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed)) | np.uint64(1)


def hashed_sample(df: DataFrame, n: int, key: str, size: Column | None = None, max_bytes: int = 64 << 20) -> DataFrame:
    """The rows of ``df`` with the ``n`` smallest hashes of ``key`` (ties may add some).

    Only hashes are ranked; the other columns are read once the cut is known. With ``size``, the bytes of
    a row, ties add none, and rows end where they come to ``max_bytes`` together; larger rows are passed over.
    """
    h = F.xxhash64(F.lit(7), F.col(key))
    cut = df.select(h.alias("h")).orderBy("h").limit(n).agg(F.max("h")).first()[0]
    near = df.where(h <= F.lit(cut)) if cut is not None else df.limit(0)
    if size is None or cut is None:
        return near
    sized = written(near.withColumn("_gp_h", h).withColumn("_gp_b", F.coalesce(size.cast("bigint"), F.lit(0))), "sample").where(F.col("_gp_b") <= max_bytes)
    total = k = 0
    for row in sized.select("_gp_h", "_gp_b").orderBy("_gp_h", "_gp_b").limit(n).collect():  # n rows of two numbers
        total += row._gp_b
        if total > max_bytes:
            break
        k += 1
    return sized.orderBy("_gp_h", "_gp_b").limit(k).drop("_gp_h", "_gp_b")
