"""Language identification, words first.

A model holds, per language, the log frequency of known words and of character n-grams of
every length up to ``max_n``. A text is scored word by word: a known word gives its log
frequencies; an unseen word is cut into the longest n-grams that are known, backing off to
shorter ones where they are not, down to a floor. The scores of all words of the whole
text are summed and turned into a posterior.

Defined results: a null text, or one without a letter, is ``und`` with score 0. Rows with
a null language are never learned from. With no labelled row at all every text is ``und``. Repeated rows
get the same result each; of languages with equal scores the first in the order of their names is
taken; a very long text is read whole, word by distinct word; an empty table gives an empty table; other columns,
whatever their names, are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.llm.common import fold_column, hashed_sample, held_out_column, mapped

WORD = re.compile(r"[^\W\d_]+")
UNDETERMINED = "und"


def words_of(text: str) -> Counter:
    """The runs of letters of ``text`` in lower case; numerals such as ``Ⅷ`` or ``½`` are no letters and part them."""
    counts = Counter(WORD.findall(text.lower()))
    for w in [w for w in counts if not w.isalpha()]:
        n = counts.pop(w)
        for part in "".join(c if c.isalpha() else " " for c in w).split():
            counts[part] += n
    return counts


@dataclass
class Model:
    """Known words and n-grams as rows of two tables with a column for each language."""

    languages: list[str]
    words: dict[str, int]
    word_logs: np.ndarray
    grams: dict[str, int]
    gram_logs: np.ndarray
    floor: np.ndarray
    max_n: int

    def unseen(self, word: str) -> np.ndarray:
        """Back off: walk over the word by the longest known n-grams."""
        marked = f"<{word}>"
        total, at, steps = np.zeros(len(self.languages)), 0, 0
        while at < len(marked):
            for n in range(min(self.max_n, len(marked) - at), 0, -1):
                if (hit := self.grams.get(marked[at : at + n])) is not None:
                    total += self.gram_logs[hit]
                    break
            else:
                n = 1
                total += self.floor
            at += max(1, n - 1) if at + n < len(marked) else n
            steps += 1
        return total / max(1, steps)

    def scores(self, text: str | None, cache: dict[str, np.ndarray]) -> tuple[str, float]:
        if not text or not self.languages:
            return UNDETERMINED, 0.0
        counts = words_of(text)
        if not counts:
            return UNDETERMINED, 0.0
        total, places, often = np.zeros(len(self.languages)), [], []
        for w, n in counts.items():
            if (place := self.words.get(w)) is not None:
                places.append(place)
                often.append(n)
                continue
            if (row := cache.get(w)) is None:
                row = self.unseen(w)
                if len(cache) < 50_000:
                    cache[w] = row
            total += n * row
        if places:
            total += np.array(often) @ self.word_logs[places]
        total -= total.max()
        chance = np.exp(total)
        best = int(chance.argmax())
        return self.languages[best], float(chance[best] / chance.sum())


def fit(labelled: DataFrame, *, text: str = "text", lang: str = "lang", doc_id: str = "doc_id", max_docs: int = 4000, max_bytes: int = 64 << 20, max_words: int = 60_000, max_n: int = 5) -> Model:
    """Learn from ``max_docs`` labelled rows and ``max_bytes`` of text at most, those of the smallest hashed doc_id.

    ``max_words`` bounds the words and the n-grams kept for each language.
    """
    usable = labelled.where(F.col(text).isNotNull() & F.col(lang).isNotNull())
    rows = hashed_sample(usable.select(doc_id, text, lang), max_docs, doc_id, F.octet_length(text), max_bytes).select(text, lang).toArrow()
    words: dict[str, Counter] = {}
    for t, language in zip(rows.column(0).to_pylist(), rows.column(1).to_pylist(), strict=True):
        words.setdefault(language, Counter()).update(words_of(t))
    languages = sorted(k for k, v in words.items() if v)
    grams = {k: Counter() for k in languages}
    for k in languages:
        for w, c in words[k].items():
            marked = f"<{w}>"
            for n in range(1, max_n + 1):
                for i in range(len(marked) - n + 1):
                    grams[k][marked[i : i + n]] += c

    def logs(counts: dict[str, Counter], least: int) -> tuple[dict[str, int], np.ndarray]:
        kept = sorted({w for k in languages for w, c in counts[k].most_common(max_words) if c >= least})
        totals = np.array([sum(counts[k].values()) + len(kept) + 1 for k in languages], float)
        table = np.array([[counts[k][w] for k in languages] for w in kept], float).reshape(len(kept), len(languages))
        return {w: i for i, w in enumerate(kept)}, np.log((table + 0.5) / totals)

    floor = np.array([np.log(0.5 / (sum(grams[k].values()) + 1)) for k in languages])
    return Model(languages, *logs(words, 2), *logs(grams, 1), floor, max_n)


def predict(df: DataFrame, model: Model, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc_id, held_out, lang_pred, score)`` for every row of ``df``."""
    shared = df.sparkSession.sparkContext.broadcast(model)

    def run(batch: pa.RecordBatch) -> dict:
        m, cache = shared.value, {}
        found = [m.scores(t, cache) for t in batch.column(2).to_pylist()]
        return {"doc_id": batch.column(0), "held_out": batch.column(1), "lang_pred": [f[0] for f in found], "score": [f[1] for f in found]}

    return mapped(
        df.select(F.col(doc_id).alias("doc_id"), held_out_column(doc_id).alias("held_out"), F.col(text).cast("string").alias("text")),
        run,
        f"doc_id {df.schema[doc_id].dataType.simpleString()}, held_out boolean, lang_pred string, score double",
    )


def identify(df: DataFrame, **options) -> DataFrame:
    """Learn from the rows that are not held out and predict every row."""
    return predict(df, fit(df.where(fold_column() != 1), **options))
