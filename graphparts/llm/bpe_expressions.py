"""Byte-level BPE by built-in higher-order functions.

Words are cut by the vocabulary's pattern. A word is an array of byte tokens over which merges
are folded: each step finds the adjacent pair of the lowest rank and joins it, until no pair has
a rank. Ranks come from a literal table: the pairs ``(left, right)`` whose joined bytes are a
token, laid out by a perfect hash, so that one look at one slot tells. Distinct frequent words are folded once and put, with their ids, into a second
literal table of the same kind; the other words of a text are folded where they stand,
so no word leaves its row and nothing is shuffled. Decoding joins the bytes of the ids.

``dictionary_words`` and ``dictionary_docs`` bound the table of frequent words and the rows it is
counted on; they change the speed only, never an id. Defined results: a null text is
the empty text, with no ids; repeated rows are encoded each; other columns pass through
:func:`with_ids`, where a column named ``ids`` is replaced.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import lru_cache, reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphparts.llm.common import hashed_sample
from graphparts.llm.tokens import default_pattern, read_ranks, vocabulary

# The code points of Unicode white space, as ranges of a character class.
SPACES = r"\t-\r \x85\xA0  -     　"
_NONE = 1 << 30

#: Words of more ids are not put into the table of frequent words.
PACKED = 6


def java_pattern(pattern: str) -> str:
    """``pattern`` with white space spelled out, as Java's ``\\s`` is ASCII only."""
    out, i, inside = [], 0, False
    while i < len(pattern):
        two = pattern[i : i + 2]
        if two == r"\s":
            out.append(SPACES if inside else f"[{SPACES}]")
        elif two == r"\S":
            out.append(f"[^{SPACES}]")
        elif two[0] == "\\":
            out.append(two)
        else:
            inside = two[0] == "[" or inside and two[0] != "]"
            out.append(two[0])
            i -= 1
        i += 2
    return "".join(out)


def perfect_hash(hashes: np.ndarray, load: int = 3) -> tuple[np.ndarray, np.ndarray, int]:
    """Displacements of buckets and the slot of every hash, such that no two hashes share a slot; slots are a power of two."""
    slots = 1 << max(4, (len(hashes) * load - 1).bit_length())
    buckets = slots // 8
    h = hashes.astype(np.uint64)
    bucket = (h & np.uint64(buckets - 1)).astype(np.int64)
    base, stride = ((h >> np.uint64(20)) & np.uint64(slots - 1)).astype(np.int64), ((h >> np.uint64(42)) & np.uint64(slots - 1)).astype(np.int64) | 1
    taken, slot, moved = np.zeros(slots, bool), np.zeros(len(h), np.int64), np.zeros(buckets, np.int64)
    order = np.argsort(bucket, kind="stable")
    edges = np.searchsorted(bucket[order], np.arange(buckets + 1))
    for b in np.argsort(-(edges[1:] - edges[:-1]), kind="stable"):
        members = order[edges[b] : edges[b + 1]]
        if not len(members):
            break
        d = 0
        while True:
            at = (base[members] + d * stride[members]) & (slots - 1)
            if not taken[at].any() and len(np.unique(at)) == len(at):
                break
            d += 1
        taken[at], slot[members], moved[b] = True, at, d
    return moved, slot, slots


def _slot(key: Column, moved: Column, buckets: int, slots: int) -> Column:
    """Where the perfect hash puts ``key``."""

    def at(h: Column) -> Column:
        part = lambda shift: F.shiftrightunsigned(h, shift).bitwiseAND(F.lit(slots - 1).cast("bigint"))
        move = F.get(moved, h.bitwiseAND(F.lit(buckets - 1).cast("bigint")).cast("int")).cast("bigint")
        return (part(20) + move * part(42).bitwiseOR(F.lit(1).cast("bigint"))).bitwiseAND(F.lit(slots - 1).cast("bigint")).cast("int")

    return _bound(F.xxhash64(key), at)


@lru_cache(maxsize=2)
def pair_table(path: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[bytes]]:
    """Displacements and slots of the pairs, as ``(left << 17 | right) << 17 | joined``; the ids of the 256 bytes; the bytes of every id."""
    import struct

    import xxhash

    ranks = read_ranks(path)
    pairs = []
    for token, joined in ranks.items():
        for k in range(1, len(token)):
            a, b = ranks.get(token[:k]), ranks.get(token[k:])
            if a is not None and b is not None:
                pairs.append((a << 17 | b, joined))
    keys = np.array([k for k, _ in pairs])
    # The hash of Spark's xxhash64 for one whole number.
    hashes = np.array([xxhash.xxh64_intdigest(struct.pack("<q", k), seed=42) for k, _ in pairs], np.uint64)
    moved, slot, slots = perfect_hash(hashes)
    table = np.full(slots, -1, np.int64)
    table[slot] = keys << 17 | np.array([j for _, j in pairs])
    pieces = [b""] * (max(ranks.values()) + 1)
    for token, i in ranks.items():
        pieces[i] = token
    return moved, table, np.array([ranks[bytes([b])] for b in range(256)]), pieces


def _numbers(values, kind: str = "int") -> Column:
    """A literal array: a constant that the optimizer computes once."""
    return F.split(F.lit(",".join(map(str, values))), ",").cast(f"array<{kind}>")


def _bound(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once, as a lambda's variable."""
    return F.get(F.transform(F.array(value), body), 0)


def folded(word: Column, tables: Column, tables_shape: tuple[int, int]) -> Column:
    """The ids of one word; ``tables`` has the fields ``moved, table, byte_ids``."""
    moved, table, byte_ids = tables["moved"], tables["table"], tables["byte_ids"]
    buckets, slots = tables_shape
    letters = F.filter(F.split(F.decode(F.encode(word, "UTF-8"), "ISO-8859-1"), ""), lambda c: c != "")
    start = F.transform(letters, lambda c: F.get(byte_ids, F.ascii(c)))

    def rank(a: Column, b: Column) -> Column:
        def match(key: Column) -> Column:
            return _bound(F.get(table, _slot(key, moved, buckets, slots)), lambda x: F.when(F.shiftright(x, 17) == key, x.bitwiseAND(F.lit((1 << 17) - 1).cast("bigint")).cast("int")).otherwise(_NONE))

        return _bound(F.shiftleft(a.cast("bigint"), 17) + b, match)

    def step(ids: Column, _: Column) -> Column:
        ranks = F.transform(F.slice(ids, F.lit(2), F.size(ids)), lambda b, i: rank(F.get(ids, i), b))

        def join(r: Column) -> Column:
            return _bound(
                F.array_min(r),
                lambda low: F.when(F.coalesce(low, F.lit(_NONE)) == _NONE, ids).otherwise(
                    _bound(F.array_position(r, low).cast("int"), lambda p: F.concat(F.slice(ids, F.lit(1), p - 1), F.array(low), F.slice(ids, p + 2, F.size(ids))))
                ),
            )

        return _bound(ranks, join)

    return F.aggregate(F.slice(start, F.lit(2), F.size(start)), start, step)


def _tables(path: str) -> tuple[Column, tuple[int, int]]:
    moved, table, byte_ids, _ = pair_table(path)
    return F.struct(_numbers(moved).alias("moved"), _numbers(table, "bigint").alias("table"), _numbers(byte_ids).alias("byte_ids")), (len(moved), len(table))


def words_of(text: Column, pattern: str) -> Column:
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(java_pattern(pattern)), F.lit(0))


def frequent_words(docs: DataFrame, *, path: str, pattern: str, text: str, doc_id: str, words: int, rows: int) -> list[tuple[str, int, list[int]]]:
    """At most ``words`` distinct words of at most about ``rows`` documents, folded, with their hashes."""
    counted = hashed_sample(docs, rows, doc_id).select(F.explode(words_of(F.col(text), pattern)).alias("word")).groupBy("word").agg(F.count("*").alias("n"))
    chosen = counted.where((F.col("n") > 1) & ~F.col("word").contains("\x01")).orderBy(F.desc("n"), "word").limit(words)
    spread = chosen.select("word").repartition(max(2, docs.sparkSession.sparkContext.defaultParallelism))
    tables, shape = _tables(path)
    ids = spread.select("word", F.xxhash64("word").alias("h"), _bound(tables, lambda t: folded(F.col("word"), t, shape)).alias("ids"))
    return [(r.word, r.h, r.ids) for r in ids.where(F.size("ids") <= PACKED).collect()]  # bounded by ``words``


def with_ids(
    docs: DataFrame,
    *,
    path: str | None = None,
    pattern: str | None = None,
    text: str = "text",
    doc_id: str = "doc_id",
    dictionary_words: int = 120_000,
    dictionary_docs: int = 15_000,
) -> DataFrame:
    """``docs`` with ``ids``, the token ids of ``text`` as an array of ints."""
    path, pattern = path or vocabulary("byte_bpe_50k.tiktoken"), pattern or default_pattern()
    known = frequent_words(docs, path=path, pattern=pattern, text=text, doc_id=doc_id, words=dictionary_words, rows=dictionary_docs)
    moved, slot, slots = perfect_hash(np.array([h for _, h, _ in known], np.int64))
    # The ids of a word are packed into two numbers: how many, then 17 bits each.
    names, packed = [""] * slots, np.zeros((2, slots), np.int64)
    for (word, _, ids), s in zip(known, slot.tolist(), strict=True):
        names[s] = word
        packed[0, s] = len(ids) | sum(i << 3 + 17 * k for k, i in enumerate(ids[:3]))
        packed[1, s] = sum(i << 17 * k for k, i in enumerate(ids[3:]))
    dictionary = F.struct(
        F.split(F.lit("\x01".join(names)), "\x01", -1).alias("word"),
        _numbers(packed[0], "bigint").alias("low"),
        _numbers(packed[1], "bigint").alias("high"),
        _numbers(moved).alias("moved"),
    )

    def unpacked(low: Column, high: Column) -> Column:
        cut = lambda x, shift: F.shiftright(x, shift).bitwiseAND(F.lit((1 << 17) - 1).cast("bigint")).cast("int")
        each = [cut(low, 3), cut(low, 20), cut(low, 37), cut(high, 0), cut(high, 17), cut(high, 34)]
        n = low.bitwiseAND(F.lit(7).cast("bigint"))
        return reduce(lambda c, k: c.when(n == k, F.array(*each[:k])), range(2, PACKED + 1), F.when(n == 1, F.array(each[0])))

    tables_of_pairs, shape = _tables(path)

    def look_up(word: Column, d: Column) -> Column:
        return _bound(_slot(word, d["moved"], len(moved), slots), lambda s: F.when(F.get(d["word"], s) == word, unpacked(F.get(d["low"], s), F.get(d["high"], s))))

    def encoded(tables: Column) -> Column:
        return F.flatten(F.transform(words_of(F.col(text), pattern), lambda w: F.coalesce(look_up(w, tables["d"]), folded(w, tables["t"], shape))))

    return docs.withColumn("ids", _bound(F.struct(dictionary.alias("d"), tables_of_pairs.alias("t")), encoded))


def decoded(ids: Column, path: str) -> Column:
    """The bytes of an array of ids."""
    pieces = F.split(F.lit(",".join(p.hex() for p in pair_table(path)[3])), ",", -1)
    return F.unhex(_bound(pieces, lambda p: F.array_join(F.transform(ids, lambda i: F.get(p, i)), "")))


def encode_and_decode(docs: DataFrame, *, path: str | None = None, doc_id: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256`` of every row."""
    path = path or vocabulary("byte_bpe_50k.tiktoken")
    found = with_ids(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text")), path=path, **options)
    digest = lambda ids: F.struct(
        F.size(ids).cast("bigint").alias("n_tokens"), F.sha2(F.array_join(ids.cast("array<string>"), " "), 256).alias("ids_sha256"), F.sha2(decoded(ids, path), 256).alias("decoded_sha256")
    )
    return found.select("doc_id", _bound(F.col("ids"), digest).alias("x")).select("doc_id", "x.*")
