"""Byte-level BPE over Arrow batches: ranked merges folded over the byte arrays of distinct words.

Words are cut by the vocabulary's pattern. Each distinct word is folded once by a process
(until its table of words is full and starts anew): the adjacent pair whose joined bytes have the lowest rank
is joined, again and again, until no pair has one. Decoding joins the bytes of the ids.
The texts stay in their partitions; nothing is shuffled.

The same fold as built-in higher-order functions over literal rank tables is in
:mod:`graphparts.llm.bpe_expressions`; it gives the same ids and costs several times as much.

Defined results: a null text is the empty text, with no ids; repeated rows are encoded each;
other columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import heapq
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.llm.common import mapped
from graphparts.llm.tokens import default_pattern, read_ranks, vocabulary


class Encoder:
    """Ids of texts and back, by the ranks of one vocabulary file."""

    def __init__(self, path: str, pattern: str, words: int = 300_000):
        import regex

        self.ranks = read_ranks(path)
        self.pieces = [b""] * (max(self.ranks.values()) + 1)
        for token, i in self.ranks.items():
            self.pieces[i] = token
        self.cut = regex.compile(pattern).findall
        self.most = words
        self.known: dict[str, bytes] = {}

    def fold(self, word: bytes) -> list[int]:
        """The ids of one word."""
        ranks = self.ranks
        if (whole := ranks.get(word)) is not None:
            return [whole]
        if len(word) > 48:
            return self._fold_long(word)
        parts = [word[i : i + 1] for i in range(len(word))]
        none = len(self.pieces)
        pairs = [ranks.get(word[i : i + 2], none) for i in range(len(word) - 1)]
        while pairs and (low := min(pairs)) < none:
            i = pairs.index(low)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del pairs[i]
            if i:
                pairs[i - 1] = ranks.get(parts[i - 1] + parts[i], none)
            if i < len(pairs):
                pairs[i] = ranks.get(parts[i] + parts[i + 1], none)
        return [ranks[p] for p in parts]

    def _fold_long(self, word: bytes) -> list[int]:
        """The same with a heap of pairs, for words too long to look through at every step."""
        ranks, n = self.ranks, len(word)
        end = list(range(1, n + 1))  # of the part that starts at i; 0 once it is joined to an earlier one
        before = list(range(-1, n - 1))
        heap = [(r, i, i + 1, i + 2) for i in range(n - 1) if (r := ranks.get(word[i : i + 2])) is not None]
        heapq.heapify(heap)
        while heap:
            _, a, b, c = heapq.heappop(heap)
            if end[a] != b or b >= n or end[b] != c:
                continue  # one of the two has changed since
            end[a], end[b] = c, 0
            if c < n:
                before[c] = a
                if (r := ranks.get(word[a : end[c]])) is not None:
                    heapq.heappush(heap, (r, a, c, end[c]))
            if (p := before[a]) >= 0 and (r := ranks.get(word[p:c])) is not None:
                heapq.heappush(heap, (r, p, a, c))
        out, i = [], 0
        while i < n:
            out.append(ranks[word[i : end[i]]])
            i = end[i]
        return out

    def text_ids(self, text: str | None) -> bytes:
        """The decimal ids of a whole text, joined by one space."""
        known, out = self.known, []
        for word in self.cut(text or ""):
            ids = known.get(word)
            if ids is None:
                if len(known) >= self.most:
                    known.clear()
                ids = known[word] = b" ".join(b"%d" % i for i in self.fold(word.encode("utf-8", "surrogatepass")))
            out.append(ids)
        return b" ".join(out)

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.pieces.__getitem__, ids))


@lru_cache(maxsize=2)
def encoder(path: str, pattern: str) -> Encoder:
    return Encoder(path, pattern)


def with_ids(docs: DataFrame, *, path: str | None = None, pattern: str | None = None, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``doc_id`` and ``ids``, the token ids of every whole text."""
    path, pattern = path or vocabulary("byte_bpe_50k.tiktoken"), pattern or default_pattern()

    def run(batch: pa.RecordBatch) -> dict:
        e = encoder(path, pattern)
        return {"doc_id": batch.column(0), "ids": [list(map(int, e.text_ids(t).split())) for t in batch.column(1).to_pylist()]}

    return mapped(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text")), run, f"doc_id {docs.schema[doc_id].dataType.simpleString()}, ids array<int>")


def encode_and_decode(docs: DataFrame, *, path: str | None = None, pattern: str | None = None, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256`` of every row."""
    path, pattern = path or vocabulary("byte_bpe_50k.tiktoken"), pattern or default_pattern()

    def run(batch: pa.RecordBatch) -> dict:
        e = encoder(path, pattern)
        out: dict = {"doc_id": batch.column(0), "n_tokens": [], "ids_sha256": [], "decoded_sha256": []}
        for t in batch.column(1).to_pylist():
            joined = e.text_ids(t)
            ids = list(map(int, joined.split()))
            out["n_tokens"].append(len(ids))
            out["ids_sha256"].append(hashlib.sha256(joined).hexdigest())
            out["decoded_sha256"].append(hashlib.sha256(e.decode(ids)).hexdigest())
        return out

    plain = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text"))
    return mapped(plain, run, f"doc_id {docs.schema[doc_id].dataType.simpleString()}, n_tokens bigint, ids_sha256 string, decoded_sha256 string")
