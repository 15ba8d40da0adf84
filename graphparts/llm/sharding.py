"""Shards of equal bytes by histogram sort.

Rows are ordered by a 60-bit key: 40 bits of the text's hash, so that equal texts lie
together, then 20 bits of the document's. The splitters are found without sorting: each
round counts the exact bytes in every bin between probes, over all partitions at once,
keeps for each splitter the one bin that holds its target, and sets new probes inside that
bin only, until no bin is larger than the tolerance or holds more than one key. What
comes to the driver is bounded by the number of shards and probes, never by the data. Then
every row's shard is known from its key alone, and one exchange brings the rows of a shard
together and numbers them.

With tolerance 0 the splitters are exact: a key belongs to shard ``floor(b * shards / total)``,
b being the bytes of all smaller keys. A text that holds more than a shard's share is split
between neighbouring shards by its documents' keys.

Defined results: a null text has no bytes but its row weighs ``overhead``; rows with equal key
(repeated rows) stay in one shard; an empty table gives an empty table; other columns are
carried along by :func:`shard`, where columns named like results are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphparts.llm.common import written
from graphparts.llm.numbering import numbered

KEY_BITS, TEXT_BITS = 60, 40
#: Parts of a shard that are sorted apart to number its rows; slots follow from it.
PARTS = 64


def key_column(doc_id: str, text: str) -> Column:
    """The sort key, from md5 digests, so that any engine can compute it."""
    front = lambda c, digits: F.conv(F.substring(F.md5(c.cast("binary")), 1, digits), 16, 10).cast("bigint")
    of_text = front(F.coalesce(F.col(text), F.lit("")), TEXT_BITS // 4)
    of_doc = front(F.coalesce(F.col(doc_id).cast("string"), F.lit("")), (KEY_BITS - TEXT_BITS) // 4)
    return F.shiftleft(of_text, KEY_BITS - TEXT_BITS) + of_doc


def splitters(rows: DataFrame, shards: int, *, tolerance: float = 0.0, probe_bits: int = 8) -> list[int]:
    """For shards 1.. the smallest key of each, from ``rows(key, size)``; an unused shard has the next one's.

    ``tolerance`` is the share of a shard by which a splitter may miss its target.
    """
    total = rows.agg(F.sum("size")).first()[0]
    if not total:
        return [0] * (shards - 1)
    # A splitter is the first key whose smaller keys reach its target, so open bins are (low, low + width), bytes before.
    targets = [-(-total * i // shards) for i in range(1, shards)]
    slack = int(total * tolerance / shards)
    found: dict[int, int] = {}
    open_bins: dict[int, list[tuple[int, int]]] = {0: [(i, t) for i, t in enumerate(targets)]}
    before = {0: 0}
    shift = KEY_BITS
    while open_bins:
        step = min(probe_bits if shift < KEY_BITS else probe_bits + 4, shift)
        inside = rows if shift == KEY_BITS else rows.where(F.shiftright("key", shift).isin(list(open_bins)))
        shift -= step
        bins = inside.groupBy(F.shiftright("key", shift).alias("bin")).agg(F.sum("size").alias("size"), F.min("key").alias("low"), F.max("key").alias("high"))
        counted: dict[int, list] = {}
        for r in bins.collect():  # at most 2 ** step rows for each open bin, and one open bin for each splitter
            counted.setdefault(r.bin >> step, []).append(r)
        following: dict[int, list[tuple[int, int]]] = {}
        begun: dict[int, int] = {}
        for parent, wanted in open_bins.items():
            run, members = before[parent], sorted(counted[parent], key=lambda r: r.bin)
            edges = []
            for r in members:
                edges.append((run, r))
                run += r.size
            for i, target in wanted:
                begin, r = next(((b, r) for b, r in edges if b + r.size >= target), edges[-1])
                if begin + r.size - target <= slack or r.low == r.high or shift == 0:
                    found[i] = r.high + 1
                elif target - begin <= slack:
                    found[i] = r.low
                else:
                    following.setdefault(r.bin, []).append((i, target))
                    begun[r.bin] = begin
        open_bins, before = following, begun
    return [found[i] for i in range(shards - 1)]


def shard(df: DataFrame, *, shards: int = 24, doc_id: str = "doc_id", text: str = "text", overhead: int = 8, tolerance: float = 0.0, carry: list[str] | None = None) -> DataFrame:
    """``carry`` columns (all by default) with ``size, shard, slot``; slots are gapless from 0 within a shard."""
    carry = [c for c in (df.columns if carry is None else carry) if c not in ("size", "shard", "slot", "_key", "_part")]
    size = (F.octet_length(F.coalesce(F.col(text), F.lit(""))) + overhead).cast("bigint").alias("size")
    sized = df.select(*(F.col(f"`{c}`") for c in carry), size, key_column(doc_id, text).alias("_key"))
    cuts = splitters(written(sized.select(F.col("_key").alias("key"), "size"), "keys"), shards, tolerance=tolerance)
    return _dealt(sized, cuts, shards, [F.col(f"`{c}`") for c in carry])


def _dealt(sized: DataFrame, cuts: list[int], shards: int, order: list[Column]) -> DataFrame:
    # The number of splitters at or below the key.
    number = sum(((F.col("_key") >= F.lit(c).cast("bigint")).cast("int") for c in cuts), F.lit(0))
    placed = sized.withColumn("shard", number).withColumn("_part", F.col("_key") % F.lit(PARTS))
    return numbered(placed, ["shard"], "_part", [F.col("_key"), *order], "slot").drop("_key", "_part")


def equal_byte_shards(docs: DataFrame, *, shards: int = 24, doc_id: str = "doc_id", text: str = "text", overhead: int = 8, tolerance: float = 0.0) -> DataFrame:
    """``doc_id, size, text_crc32, law, shard, slot, grown_shard`` of every row, by the law ``bytes``.

    The texts are read once; what the rounds and the exchange move is a few numbers a row.
    """
    body = F.coalesce(F.col(text), F.lit(""))
    slim = written(
        docs.select(
            F.col(doc_id).alias("doc_id"),
            (F.octet_length(body) + overhead).cast("bigint").alias("size"),
            F.crc32(body.cast("binary")).alias("text_crc32"),
            key_column(doc_id, text).alias("_key"),
        ),
        "keys",
    )
    cuts = splitters(slim.select(F.col("_key").alias("key"), "size"), shards, tolerance=tolerance)
    placed = _dealt(slim, cuts, shards, [F.col("doc_id"), F.col("text_crc32")])
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
