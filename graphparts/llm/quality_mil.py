"""Document quality by attention-based multiple-instance learning.

A document is a bag of passages of ``PASSAGE`` words; only the document has a label. Every
passage is described by how it is written (shares of letter classes, symbols, cases, word
lengths, repeated words), encoded by a learned layer, and given a weight by gated attention
(a tanh branch times a sigmoid branch, softmax over the document's passages). The weighted
sum of the encodings is scored by a logistic layer. All layers are learned together from
document labels, on the driver, from a bounded sample of labelled documents.

Labels, language, source and doc_id never enter a score. Defined results: a null or
wordless text has one passage of zeros and gets whatever score the model gives that;
unlabelled or null-labelled rows are not learned from; with no labelled row, or labels of
one kind only, every score is that kind's share (0.5 without labels). Repeated rows get the same score each,
and labels that differ for one doc_id are learned from side by side; a score of exactly 0.5
is predicted 1; a very long text is encoded whole, passage by passage; an empty table gives an empty table;
other columns, whatever their names, are ignored by :func:`score` and kept by :func:`keep`.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.llm.common import fold_column, hashed_sample, held_out_column, mapped, odd_constants, pieces, utf8, written

PASSAGE = 64
_KINDS = ("space", "newline", "lower", "upper", "digit", "stop", "comma", "shout", "pipe", "symbol", "bracket", "quote", "other", "beyond")


def _kind_of_byte() -> np.ndarray:
    of = np.full(256, _KINDS.index("other"), np.int32)
    of[128:] = _KINDS.index("beyond")
    for kind, chars in (("space", " \t\r\x0b\x0c"), ("newline", "\n"), ("stop", "."), ("comma", ",;:"), ("shout", "!?"), ("pipe", "|"), ("symbol", "#$%&*@^~+=_\\/"), ("bracket", "()[]{}<>"), ("quote", "'\"`-")):
        for c in chars:
            of[ord(c)] = _KINDS.index(kind)
    of[ord("a") : ord("z") + 1] = _KINDS.index("lower")
    of[ord("A") : ord("Z") + 1] = _KINDS.index("upper")
    of[ord("0") : ord("9") + 1] = _KINDS.index("digit")
    return of


_OF = _kind_of_byte()
_GAP = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
N_FEATURES = len(_KINDS) + 9


def encode(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """The features of all passages, end to end, and the number of passages of each text."""
    raw = [utf8(t) for t in texts]
    data = np.frombuffer(b" ".join(raw) + b" ", np.uint8)
    ends = np.cumsum([len(r) + 1 for r in raw])
    gap = _GAP[data]
    first = ~gap
    first[1:] &= gap[:-1]
    start = np.flatnonzero(first)  # of words
    doc = np.searchsorted(ends, start, "right")
    n_words = np.bincount(doc, minlength=len(raw))
    n_passages = np.maximum(1, -(-n_words // PASSAGE))
    base = np.cumsum(n_passages) - n_passages
    if not len(start):
        return np.zeros((int(n_passages.sum()), N_FEATURES)), n_passages
    nth = np.arange(len(start)) - (np.cumsum(n_words) - n_words)[doc]
    passage = base[doc] + nth // PASSAGE
    total = int(n_passages.sum())

    # Bytes belong to the passage of the last word begun before them in their text; blanks before its first word to none.
    spans = np.diff(np.append(start, len(data)))
    of_byte = np.repeat(passage, spans)
    tail = data[start[0] :]
    own_text = np.repeat(np.arange(len(raw), dtype=np.int32), np.diff(ends, prepend=0))[start[0] :] == np.repeat(doc, spans)
    counts = np.bincount((of_byte * len(_KINDS) + _OF[tail])[own_text], minlength=total * len(_KINDS)).reshape(total, -1).astype(float)
    words = np.bincount(passage, minlength=total).astype(float)

    solid = ~gap[start[0] :]
    word_of = np.repeat(np.arange(len(start)), spans)
    length = np.bincount(word_of, solid, len(start))
    upper = np.bincount(word_of, _OF[tail] == _KINDS.index("upper"), len(start))
    odd = np.bincount(word_of, np.isin(_OF[tail], [_KINDS.index(k) for k in ("shout", "pipe", "symbol", "bracket", "digit")]), len(start))
    offset = np.arange(len(tail)) - np.repeat(start - start[0], spans)
    power = odd_constants(64, 31)
    values = np.where(solid, (tail.astype(np.uint64) + np.uint64(1)) * power[np.minimum(offset, 63)], np.uint64(0))
    word = np.add.reduceat(values, start - start[0])

    order = np.lexsort((word, passage))
    w, p = word[order], passage[order]
    new = np.ones(len(w), bool)
    new[1:] = (w[1:] != w[:-1]) | (p[1:] != p[:-1])
    distinct = np.bincount(p, new, total)
    follows = np.zeros(len(word))
    follows[1:] = (word[1:] == word[:-1]) & (passage[1:] == passage[:-1])

    some = np.maximum(words, 1)
    size = np.maximum(counts.sum(axis=1), 1)
    mean = np.bincount(passage, length, total) / some
    spread = np.sqrt(np.maximum(np.bincount(passage, length**2, total) / some - mean**2, 0))
    own = np.column_stack(
        [
            mean,
            spread,
            distinct / some,
            np.bincount(passage, follows, total) / some,
            np.bincount(passage, (upper == length) & (length > 1), total) / some,
            np.bincount(passage, (upper > 0) & (upper < length), total) / some,
            np.bincount(passage, odd > 0, total) / some,
            np.bincount(passage, length > 20, total) / some,
            np.log1p(words),
        ]
    )
    return np.hstack([np.sqrt(counts / size[:, None]), own]), n_passages


def portions(texts: list[str | None], chars: int = 300_000) -> Iterator[list[str | None]]:
    """Consecutive texts, about ``chars`` characters together, so that memory is bounded by the longest text."""
    begin, held = 0, 0
    for k, t in enumerate(texts):
        held += len(t or "")
        if held >= chars:
            yield texts[begin : k + 1]
            begin, held = k + 1, 0
    if begin < len(texts):
        yield texts[begin:]


@dataclass
class Model:
    mean: np.ndarray
    scale: np.ndarray
    weights: dict[str, np.ndarray]
    constant: float | None = None

    def forward(self, x: np.ndarray, n: np.ndarray) -> dict[str, np.ndarray]:
        w = self.weights
        begin = np.cumsum(n) - n
        h = np.tanh(x @ w["enc"] + w["enc_b"])
        t, s = np.tanh(h @ w["att_t"]), 1 / (1 + np.exp(-(h @ w["att_s"])))
        e = (t * s) @ w["att"]
        e = np.exp(e - np.repeat(np.maximum.reduceat(e, begin), n))
        a = e / np.repeat(np.add.reduceat(e, begin), n)
        z = np.add.reduceat(a[:, None] * h, begin)
        return {"h": h, "t": t, "s": s, "a": a, "z": z, "y": 1 / (1 + np.exp(-(z @ w["out"] + w["out_b"])))}

    def scores(self, texts: list[str | None]) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(texts), self.constant)
        x, n = encode(texts)
        return self.forward((x - self.mean) / self.scale, n)["y"]

    def attention(self, text: str | None) -> np.ndarray:
        """The weight of every passage of one text."""
        x, n = encode([text])
        return self.forward((x - self.mean) / self.scale, n)["a"]


def gradients(m: Model, x: np.ndarray, n: np.ndarray, y: np.ndarray, weight: np.ndarray) -> dict[str, np.ndarray]:
    """Of the weighted log loss, by the chain rule through the attention."""
    f, w = m.forward(x, n), m.weights
    g = (f["y"] - y) * weight / weight.sum()
    dz = g[:, None] * w["out"][None, :]
    dz_each, begin = np.repeat(dz, n, axis=0), np.cumsum(n) - n
    da = (dz_each * f["h"]).sum(axis=1)
    de = f["a"] * (da - np.repeat(np.add.reduceat(f["a"] * da, begin), n))
    gate = f["t"] * f["s"]
    dgate = de[:, None] * w["att"][None, :]
    dt, ds = dgate * f["s"] * (1 - f["t"] ** 2), dgate * f["t"] * f["s"] * (1 - f["s"])
    dh = f["a"][:, None] * dz_each + dt @ w["att_t"].T + ds @ w["att_s"].T
    pre = dh * (1 - f["h"] ** 2)
    return {"enc": x.T @ pre, "enc_b": pre.sum(axis=0), "att_t": f["h"].T @ dt, "att_s": f["h"].T @ ds, "att": gate.T @ de, "out": f["z"].T @ g, "out_b": g.sum(keepdims=True)}


def train(texts: list[str | None], labels: np.ndarray, *, hidden: int = 24, gate: int = 12, epochs: int = 40, rate: float = 0.01, seed: int = 5) -> Model:
    labels = np.asarray(labels, float)
    if len(set(labels.tolist())) < 2:
        return Model(np.zeros(0), np.zeros(0), {}, float(labels.mean()) if len(labels) else 0.5)
    encoded = [encode(part) for part in portions(texts)]
    x, n = np.concatenate([e[0] for e in encoded]), np.concatenate([e[1] for e in encoded])
    mean, scale = x.mean(axis=0), x.std(axis=0) + 1e-3
    x = (x - mean) / scale
    r = np.random.default_rng(seed)
    m = Model(
        mean,
        scale,
        {
            "enc": r.normal(0, x.shape[1] ** -0.5, (x.shape[1], hidden)),
            "enc_b": np.zeros(hidden),
            "att_t": r.normal(0, hidden**-0.5, (hidden, gate)),
            "att_s": r.normal(0, hidden**-0.5, (hidden, gate)),
            "att": r.normal(0, gate**-0.5, gate),
            "out": r.normal(0, hidden**-0.5, hidden),
            "out_b": np.zeros(1),
        },
    )
    begin = np.cumsum(n) - n
    first = {k: np.zeros_like(v) for k, v in m.weights.items()}
    second = {k: np.zeros_like(v) for k, v in m.weights.items()}
    step, size = 0, 128
    for epoch in range(epochs):
        order = r.permutation(len(n))
        for at in range(0, len(n), size):
            pick = order[at : at + size]
            rows = np.concatenate([np.arange(begin[d], begin[d] + n[d]) for d in pick])
            g = gradients(m, x[rows], n[pick], labels[pick], np.ones(len(pick)))
            step += 1
            pace = rate * (1 - epoch / epochs)
            for k, v in m.weights.items():
                d = g[k] + 1e-4 * v
                first[k] = 0.9 * first[k] + 0.1 * d
                second[k] = 0.999 * second[k] + 0.001 * d * d
                v -= pace * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
    return m


def fit(docs: DataFrame, labels: DataFrame, *, text: str = "text", doc_id: str = "doc_id", label: str = "quality", max_docs: int = 3000, max_bytes: int = 64 << 20, **options) -> Model:
    """Learn from at most ``max_docs`` labelled rows and ``max_bytes`` of text, those of the smallest hashed doc_id."""
    marks = labels.where(F.col(label).isNotNull() & F.col(doc_id).isNotNull()).select(F.col(doc_id).alias("_id"), F.col(label).cast("double").alias("_label")).distinct()
    chosen = hashed_sample(marks, max_docs, "_id")
    found = written(docs.select(F.col(doc_id).alias("_id"), F.col(text).cast("string").alias("_text")).join(F.broadcast(chosen.limit(max_docs)), "_id"), "labelled")
    rows = hashed_sample(found, max_docs, "_id", F.octet_length("_text"), max_bytes).toPandas()
    rows = rows.sort_values(["_id", "_text", "_label"], kind="stable")
    return train(rows["_text"].tolist(), rows["_label"].to_numpy(), **options)


def score(df: DataFrame, model: Model, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc_id, held_out, score, predicted)`` for every row of ``df``."""
    shared = df.sparkSession.sparkContext.broadcast(model)

    def run(batch: pa.RecordBatch) -> dict:
        y = np.concatenate([shared.value.scores(part) for part in portions(batch.column(2).to_pylist())])
        return {"doc_id": batch.column(0), "held_out": batch.column(1), "score": y, "predicted": (y >= 0.5).astype(np.int32)}

    return mapped(
        df.select(F.col(doc_id).alias("doc_id"), held_out_column(doc_id).alias("held_out"), F.col(text).cast("string").alias("text")),
        run,
        f"doc_id {df.schema[doc_id].dataType.simpleString()}, held_out boolean, score double, predicted int",
    )


def quality(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """Learn from labels of rows that are not held out, and score every row."""
    return score(docs, fit(docs, labels.where(fold_column() != 1), **options))


def keep(df: DataFrame, model: Model, *, text: str = "text", least: float = 0.5) -> DataFrame:
    """The rows of ``df``, unchanged, whose text scores ``least`` or more."""
    shared = df.sparkSession.sparkContext.broadcast(model)
    place = df.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for piece in pieces(batch, 512):
                y = np.concatenate([shared.value.scores(part) for part in portions(piece.column(place).to_pylist(), 150_000)])
                yield piece.filter(pa.array(y >= least))

    return df.mapInArrow(run, df.schema)
