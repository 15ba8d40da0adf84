"""Packing documents into sequences by minimum bin slack.

A document is its token ids and an end mark. One longer than a sequence is cut into whole
sequences; what is left over is its first piece. Only the number of pieces of each length
matters for the packing: at most one count for each possible length goes to the
driver, whatever the size of the corpus. There each sequence starts with the longest
length left, and a bitset subset-sum over the available lengths finds the fullest
combination that completes it; the combination is taken as often as the counts allow and
removed. Pieces are then numbered within their length and looked up in that plan.

Defined results: a null or empty text is its end mark alone; repeated rows are packed one by
one; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.llm.common import crc32, mapped, written
from graphparts.llm.numbering import numbered
from graphparts.llm.tokens import default_pattern, fast_encoder, vocabulary

_PIECE = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint"


def fullest(counts: dict[int, int], room: int) -> dict[int, int]:
    """How many of each length fill ``room`` as far as any available combination can."""
    lengths = [n for n in sorted(counts, reverse=True) if n <= room and counts[n]]
    goal = 1 << room
    inside = (goal << 1) - 1
    reach, layers = 1, []
    for n in lengths:
        left, step = min(counts[n], room // n), 1
        before = reach
        while left:  # copies in powers of two
            take = min(step, left)
            reach |= reach << (take * n) & inside
            left -= take
            step *= 2
        layers.append((n, before))
        if reach & goal:
            break
    total, chosen = reach.bit_length() - 1, {}
    for n, before in reversed(layers):
        while not before >> total & 1:
            chosen[n] = chosen.get(n, 0) + 1
            total -= n
    return chosen


def plan(counts: dict[int, int], capacity: int) -> list[tuple[int, int, int, int, int, int]]:
    """Rows ``(length, first, last, each, sequence, place)``: how the pieces of a length are placed.

    The pieces of ``length`` numbered ``first`` to ``last`` go ``each`` to a sequence, from ``sequence`` on, at
    offset ``place`` and after.
    """
    left = {n: c for n, c in counts.items() if c}
    used = dict.fromkeys(left, 0)
    out, sequence = [], 0
    while left:
        longest = max(left)
        left[longest] -= 1
        combination = fullest(left, capacity - longest)
        left[longest] += 1
        combination[longest] = combination.get(longest, 0) + 1
        times, place = min(left[n] // m for n, m in combination.items()), 0
        for n, m in sorted(combination.items(), reverse=True):
            out.append((n, used[n], used[n] + times * m - 1, m, sequence, place))
            used[n] += times * m
            left[n] -= times * m
            place += n * m
            if not left[n]:
                del left[n]
        sequence += times
    return out


def pieces(docs: DataFrame, *, tokenizer: str, pattern: str, capacity: int, end: int, doc_id: str, text: str) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32`` of every piece of every document."""

    def run(batch: pa.RecordBatch) -> dict:
        encode = fast_encoder(tokenizer, pattern).encode_ordinary
        out: dict = {k: [] for k in ("doc_id", "piece", "start", "length", "ids_crc32")}
        for i, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            ids = np.array([*encode(t or ""), end], "<u4")
            head = len(ids) % capacity or capacity
            edges = [0, *range(head, len(ids) + 1, capacity)]
            for k, (a, b) in enumerate(zip(edges, edges[1:], strict=False)):
                for name, v in zip(out, (i, k, a, b - a, crc32(ids[a:b].tobytes())), strict=True):
                    out[name].append(v)
        return out

    return mapped(docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text")), run, _PIECE)


def pack(docs: DataFrame, *, tokenizer: str | None = None, pattern: str | None = None, capacity: int = 1024, end: int = 2, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``pieces`` with ``sequence_id`` and ``offset``, in as few sequences as the plan finds."""
    tokenizer = tokenizer or vocabulary("byte_bpe_50k.json")
    cut = written(pieces(docs, tokenizer=tokenizer, pattern=pattern or default_pattern(), capacity=capacity, end=end, doc_id=doc_id, text=text), "pieces")
    counts = {r.length: r.n for r in cut.groupBy("length").agg(F.count("*").alias("n")).collect()}  # one row a length: at most ``capacity``
    rows = pd.DataFrame(plan(counts, capacity), columns=["length", "first", "last", "each", "sequence", "place"], dtype="int64")
    spark = docs.sparkSession
    wanted = "length bigint, first bigint, last bigint, each bigint, sequence bigint, place bigint"
    plans = spark.createDataFrame(rows, wanted) if len(rows) else spark.createDataFrame([], wanted)
    parts = max(8, int(spark.conf.get("spark.sql.shuffle.partitions")) // 4)
    dealt = cut.withColumn("_part", F.pmod(F.xxhash64("doc_id", "piece", F.col("ids_crc32")), F.lit(parts)))
    ranked = numbered(dealt, ["length"], "_part", [F.col("doc_id"), F.col("piece"), F.col("ids_crc32")], "_rank").alias("r")
    # The plan's rows are bounded by the lengths and their combinations, not by the corpus.
    found = ranked.join(F.broadcast(plans.alias("p")), (F.col("r.length") == F.col("p.length")) & F.col("_rank").between(F.col("first"), F.col("last")))
    nth = F.col("_rank") - F.col("first")
    return found.select(
        "doc_id",
        "piece",
        "start",
        F.col("r.length").alias("length"),
        "ids_crc32",
        (F.col("sequence") + F.expr("(_rank - first) div each")).alias("sequence_id"),
        (F.col("place") + nth % F.col("each") * F.col("r.length")).alias("offset"),
    )
