"""Exact removal of word windows that occur more than once, behind a count-min sketch.

Documents are dealt into blocks once. Three passes over the blocks follow, and only small
requests and bit maps travel between them:

1. Each block sketches its windows. A window is hashed by its *anchor*, the least hash
   among its 8-word grams, so equal windows always count in the same cells while some
   fourteen neighbouring windows share one count. A block's partial sketch is its non-zero
   cells; the partial sketches of all blocks are merged slab by slab of the cell space and
   each block gets back one bit per cell it asked about: does the merged counter reach two?
   The least counter over the rows never underestimates, so no repeated window is lost.
2. Windows estimated as repeated are digested (128 bits of their words), counted once per
   block and grouped exactly; each block gets one bit per digest.
3. Each block removes the covered words.

Whole documents that are copies of each other are counted by one digest in pass 1: all
their windows are repeated, and only the first block that holds the text sends them on.
A window that a third of all rows share therefore costs one entry per block, not per row.

Defined results: a null or wordless text has no words and keeps none; repeated rows are
documents of their own, so copies of at least a window's length lose every word; an empty
table gives an empty table. Other columns pass through; a column with the name of a result
is replaced.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.llm.common import mix, odd_constants, utf8, word_hashes

_BLOCK, _REQUEST = "_gp_block", "slab int, block int, width int, keys binary, multi binary"
_ANSWER = "block int, slab int, repeated binary, first binary"


@dataclass(frozen=True)
class Plan:
    window: int
    gram: int
    rows: int
    bits: int
    slabs: int
    column: int  # place of the text

    @property
    def key_type(self) -> type:
        return np.uint32 if self.bits <= 32 else np.uint64


def _segments(keys: np.ndarray, width: int, bits: int, slabs: int) -> np.ndarray:
    """Where each slab's share of the sorted keys ends."""
    top = (keys[:, 0] >> np.uint64(32)) if width == 16 else keys.astype(np.uint64)
    slab = (top * np.uint64(slabs)) >> np.uint64(32 if width == 16 else bits)
    return np.searchsorted(slab, np.arange(1, slabs + 1, dtype=np.uint64), "left")


def _distinct(keys: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct keys, the sum of weights of each, and each row's place among them."""
    order = np.lexsort((keys[:, 1], keys[:, 0])) if keys.ndim == 2 else np.argsort(keys, kind="stable")
    k = keys[order]
    new = np.ones(len(k), bool)
    new[1:] = (k[1:] != k[:-1]).any(axis=1) if keys.ndim == 2 else k[1:] != k[:-1]
    rank = np.cumsum(new) - 1
    place = np.empty(len(k), np.int64)
    place[order] = rank
    return k[new], np.bincount(rank, weight[order], int(new.sum())), place


def _requests(base: int, block: int, keys: np.ndarray, totals: np.ndarray, p: Plan) -> list[dict]:
    width = keys.itemsize * (keys.shape[1] if keys.ndim == 2 else 1)
    out, begin = [], 0
    for slab, end in enumerate(_segments(keys, width, p.bits, p.slabs)):
        if end > begin:
            out.append({"slab": base * p.slabs + slab, "block": block, "width": width, "keys": keys[begin:end].tobytes(), "multi": np.packbits(totals[begin:end] >= 2).tobytes()})
        begin = end
    return out


def _answers(base: int, keys: np.ndarray, found: dict, p: Plan) -> tuple[np.ndarray, np.ndarray]:
    width = keys.itemsize * (keys.shape[1] if keys.ndim == 2 else 1)
    repeated, first, begin = np.zeros(len(keys), bool), np.zeros(len(keys), bool), 0
    for slab, end in enumerate(_segments(keys, width, p.bits, p.slabs)):
        if end > begin:
            r, f = found[base * p.slabs + slab]
            repeated[begin:end] = np.unpackbits(np.frombuffer(r, np.uint8), count=end - begin)
            first[begin:end] = np.unpackbits(np.frombuffer(f, np.uint8), count=end - begin)
        begin = end
    return repeated, first


def _merge(requests: pa.Table) -> pa.Table:
    """Counters of one slab, summed over the blocks; each block learns which reach two."""
    r = requests.sort_by("block")
    width = r.column("width")[0].as_py()
    kind = {4: np.uint32, 8: np.uint64, 16: np.uint64}[width]
    parts = [np.frombuffer(k, kind) for k in r.column("keys").to_pylist()]
    parts = [k.reshape(-1, 2) for k in parts] if width == 16 else parts
    sizes = [len(k) for k in parts]
    multi = np.concatenate([np.unpackbits(np.frombuffer(m, np.uint8), count=n) for m, n in zip(r.column("multi").to_pylist(), sizes, strict=True)])
    _, totals, place = _distinct(np.concatenate(parts), 1 + multi)
    lowest = np.full(len(totals), len(place), np.int64)
    np.minimum.at(lowest, place, np.arange(len(place)))
    repeated, first = totals[place] >= 2, lowest[place] == np.arange(len(place))
    ends = np.cumsum(sizes)[:-1]
    return pa.table(
        {
            "block": r.column("block"),
            "slab": r.column("slab"),
            "repeated": pa.array([np.packbits(x).tobytes() for x in np.split(repeated, ends)], pa.binary()),
            "first": pa.array([np.packbits(x).tobytes() for x in np.split(first, ends)], pa.binary()),
        }
    )


class Block:
    """The words of a block's documents, end to end, and what is derived from them."""

    def __init__(self, texts: list[str | None], p: Plan):
        import xxhash

        self.p = p
        self.docs = [utf8(t).split() for t in texts]
        self.n_words = np.fromiter(map(len, self.docs), np.int64, len(self.docs))
        self.begin = np.concatenate([[0], np.cumsum(self.n_words)])
        words = [w for d in self.docs for w in d]
        self.joined = b" ".join(words)
        self.at = np.concatenate([[0], np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)])
        self.long = np.flatnonzero(self.n_words >= p.window)
        starts = [np.arange(self.begin[d], self.begin[d + 1] - p.window + 1) for d in self.long]
        self.start = np.concatenate(starts) if starts else np.zeros(0, np.int64)
        self.owner = np.repeat(self.long, [len(s) for s in starts])
        self._anchors(word_hashes(words) if len(self.start) else np.zeros(0, np.uint64))
        digests = [xxhash.xxh3_128_digest(self.slice(self.begin[d], self.begin[d + 1])) for d in self.long]
        self.text_keys, self.text_totals, self.text_place = _distinct(_as_keys(digests), np.ones(len(digests)))

    def slice(self, a: int, b: int) -> bytes:
        return self.joined[self.at[a] : self.at[b] - 1]

    def _anchors(self, h: np.ndarray) -> None:
        p = self.p
        if not len(self.start):
            self.anchor_of, values = np.zeros(0, np.int64), np.zeros(0, np.uint64)
        else:
            n = len(h) - p.gram + 1
            grams = np.zeros(n, np.uint64)
            for j, c in enumerate(odd_constants(p.gram, 1)):
                grams += h[j : j + n] * c
            value, place, length, span = mix(grams), np.arange(n), 1, p.window - p.gram + 1
            while length < span:
                shift = min(length, span - length)
                later = value[shift:] < value[:-shift]
                place = np.where(later, place[shift:], place[:-shift])
                value = np.where(later, value[shift:], value[:-shift])
                length += shift
            chosen = place[self.start]
            spots, self.anchor_of = np.unique(chosen, return_inverse=True)
            values = mix(grams[spots])
        self.cells = []
        for c in odd_constants(p.rows, 2):
            cell = (mix(values * c) >> np.uint64(64 - p.bits)).astype(p.key_type)
            self.cells.append(_distinct(cell, np.ones(len(cell))))

    def sketch(self, block: int) -> list[dict]:
        out = _requests(p_rows := self.p.rows, block, self.text_keys, self.text_totals, self.p)
        for r, (keys, totals, _) in enumerate(self.cells):
            out += _requests(r, block, keys, totals, self.p)
        assert p_rows == len(self.cells)
        return out

    def estimated(self, found: dict) -> None:
        """Which windows may be repeated, by the merged sketch, as digests with their counts."""
        import xxhash

        hot = np.ones(len(self.cells[0][2]), bool)
        for r, (keys, _, place) in enumerate(self.cells):
            hot &= _answers(r, keys, found, self.p)[0][place]
        copied, first = _answers(self.p.rows, self.text_keys, found, self.p)
        self.copied = np.zeros(len(self.docs), bool)
        sends = np.zeros(len(self.docs), bool)
        seen: set[int] = set()
        for d, k in zip(self.long.tolist(), self.text_place.tolist(), strict=True):
            self.copied[d] = copied[k]
            sends[d] = first[k] and k not in seen
            seen.add(k)
        mine = hot[self.anchor_of] & sends[self.owner] if len(self.start) else np.zeros(0, bool)
        self.sent = self.start[mine]
        a, b, joined = self.at[self.sent].tolist(), (self.at[self.sent + self.p.window] - 1).tolist(), self.joined
        digests = [xxhash.xxh3_128_digest(joined[i:j]) for i, j in zip(a, b, strict=True)]
        weight = 1 + self.copied[self.owner[mine]]
        self.window_keys, self.window_totals, self.window_place = _distinct(_as_keys(digests), weight)

    def windows(self, block: int) -> list[dict]:
        return _requests(self.p.rows + 1, block, self.window_keys, self.window_totals, self.p)

    def removed(self, found: dict) -> np.ndarray:
        """A mask over all words."""
        repeated = _answers(self.p.rows + 1, self.window_keys, found, self.p)[0][self.window_place]
        edge = np.zeros(self.begin[-1] + 1, np.int64)
        np.add.at(edge, self.sent[repeated], 1)
        np.add.at(edge, self.sent[repeated] + self.p.window, -1)
        mask = np.cumsum(edge)[:-1] > 0
        for d in np.flatnonzero(self.copied):
            mask[self.begin[d] : self.begin[d + 1]] = True
        return mask


def _as_keys(digests: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(digests), ">u8").astype(np.uint64).reshape(-1, 2)


def _found(answers: pa.Table) -> dict:
    c = answers.to_pydict()
    return {s: (r, f) for s, r, f in zip(c["slab"], c["repeated"], c["first"], strict=True)}


_REQUEST_TYPE = pa.schema([("slab", pa.int32()), ("block", pa.int32()), ("width", pa.int32()), ("keys", pa.binary()), ("multi", pa.binary())])


def _load(t: pa.Table, p: Plan) -> tuple[Block, int]:
    return Block(t.column(p.column).to_pylist(), p), t.column(_BLOCK)[0].as_py()


def remove_repeats(
    df: DataFrame,
    *,
    text: str = "text",
    window: int = 35,
    gram: int = 8,
    rows: int = 2,
    block_docs: int = 1024,
    slab_docs: int = 40_000,
    digest_only: bool = False,
    prefix: str = "",
) -> DataFrame:
    """``df`` with ``n_words``, ``n_removed`` and the kept words; ``prefix`` goes before the new columns' names.

    The kept words replace ``text`` (joined by single spaces), or with ``digest_only`` the
    column ``kept_sha256`` takes the place of ``text``. ``block_docs`` bounds what a block
    holds on average, ``slab_docs`` what a slab of the sketch serves; the sketch has
    about a thousand cells for each document in each of its ``rows``.
    """
    spark = df.sparkSession
    n_docs = df.count()
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    blocks = max(1, min(parts, n_docs), -(-n_docs // block_docs))
    slabs = max(1, min(blocks, 64), -(-n_docs // slab_docs))
    results = [f"{prefix}{c}" for c in ("n_words", "n_removed", *(("kept_sha256",) if digest_only else ()))]
    names = [c for c in df.columns if c not in results and c != _BLOCK]
    p = Plan(window, min(gram, window), rows, min(48, max(20, (n_docs * 1024).bit_length())), slabs, names.index(text))
    # A block follows from a row's values and its partition, so it is the same when a lost task runs again, in whatever order.
    told = [f"`{f.name}`" for f in df.schema if f.name in names and not f.dataType.simpleString().startswith(("map", "variant"))]
    dealt = df.select(*(F.col(f"`{c}`") for c in names)).withColumn(_BLOCK, F.pmod(F.xxhash64(*told, F.spark_partition_id()), F.lit(blocks)).cast("int"))
    grouped = dealt.groupBy(_BLOCK)

    def sketch(t: pa.Table) -> pa.Table:
        block, number = _load(t, p)
        return pa.Table.from_pylist(block.sketch(number), schema=_REQUEST_TYPE)

    def windows(t: pa.Table, answers: pa.Table) -> pa.Table:
        if not t.num_rows:
            return pa.Table.from_pylist([], schema=_REQUEST_TYPE)
        block, number = _load(t, p)
        block.estimated(_found(answers))
        return pa.Table.from_pylist(block.windows(number), schema=_REQUEST_TYPE)

    kept_type = next(f for f in dealt.schema if f.name == text)
    outs = [f for f in dealt.schema if f.name not in (_BLOCK,) and not (digest_only and f.name == text)]
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in outs), *(f"`{c}` {t}" for c, t in zip(results, ("bigint", "bigint", "string"), strict=False))])
    assert kept_type.dataType.simpleString() == "string", "the text column must be a string"

    def cut(t: pa.Table, answers: pa.Table) -> pa.Table:
        block, _ = _load(t, p)
        found = _found(answers)
        block.estimated(found)
        mask = block.removed(found)
        n_removed, kept = [], []
        for d, words in enumerate(block.docs):
            gone = mask[block.begin[d] : block.begin[d + 1]]
            n_removed.append(n := int(gone.sum()))
            if n:
                words = [w for w, g in zip(words, gone.tolist(), strict=True) if not g]
            joined = b" ".join(words)
            kept.append(hashlib.sha256(joined).hexdigest() if digest_only else joined.decode("utf-8", "surrogatepass"))
        cols = {f.name: t.column(f.name) for f in outs}
        cols |= {} if digest_only else {text: pa.array(kept, pa.string())}
        counts = (pa.array(block.n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(kept, pa.string()))
        return pa.table(cols | dict(zip(results, counts, strict=False)))

    marked = grouped.applyInArrow(sketch, _REQUEST).groupBy("slab").applyInArrow(_merge, _ANSWER)
    asked = grouped.cogroup(marked.groupBy("block")).applyInArrow(windows, _REQUEST)
    exact = asked.groupBy("slab").applyInArrow(_merge, _ANSWER)
    return grouped.cogroup(marked.unionByName(exact).groupBy("block")).applyInArrow(cut, schema)
