import hashlib
import random
import re
from collections import Counter

import pytest

from graphparts.llm.substring_dedup import remove_repeats


def brute(texts, window):
    words = [re.findall(r"[^\x20\x09-\x0D]+", t or "") for t in texts]
    seen = Counter(tuple(w[i : i + window]) for w in words for i in range(len(w) - window + 1))
    out = []
    for w in words:
        gone = set()
        for i in range(len(w) - window + 1):
            if seen[tuple(w[i : i + window])] > 1:
                gone.update(range(i, i + window))
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return out


def rows_of(spark, rows, **options):
    df = spark.createDataFrame(rows, "doc_id bigint, text string, n_words string, block int")
    got = remove_repeats(df, digest_only=True, **options).collect()
    return sorted(((r.doc_id is None, r.doc_id or 0, r.n_words, r.n_removed, r.kept_sha256) for r in got), key=str)


@pytest.mark.parametrize("window,gram", [(5, 3), (35, 8), (2, 8)])
def test_equals_brute_force(spark, window, gram):
    r = random.Random(window)
    pool = [" ".join(r.choice("abcdefg") + str(r.randrange(9)) for _ in range(r.randrange(window, 3 * window))) for _ in range(6)]
    texts = [None, "", "  \n", "one", "x " * 90, "y\x0b y\x1cz y " * 40, "ñ " * window]
    for _ in range(60):
        own = [f"w{r.randrange(10**6)}" for _ in range(r.randrange(1, 80))]
        at = r.randrange(len(own) + 1)
        texts.append(" ".join([*own[:at], r.choice(pool), *own[at:]]))
    texts += [texts[20]] * 9 + [texts[21] + "\n"] + ["whole copy of few words"] * 3
    rows = [(i, t, "x", 1) for i, t in enumerate(texts)]
    want = sorted(((False, i, *b) for i, b in enumerate(brute(texts, window))), key=str)
    assert rows_of(spark, rows, window=window, gram=gram) == want
    assert rows_of(spark, rows, window=window, gram=gram, block_docs=3, slab_docs=10) == want


def test_repeated_rows_nulls_and_empty(spark):
    long = " ".join(map(str, range(50)))
    got = rows_of(spark, [(None, long, None, None), (7, long, None, None), (7, long, None, None), (None, None, None, None)])
    assert [g[2:4] for g in got if g[2]] == [(50, 50)] * 3
    assert rows_of(spark, []) == []


def test_text_is_replaced(spark):
    shared = " ".join(map(str, range(40)))
    df = spark.createDataFrame([(1, f"a  b {shared}\tc", "en"), (2, f"{shared} d", "en")], "doc_id bigint, text string, lang string")
    got = {r.doc_id: (r.text, r.lang, r.n_removed) for r in remove_repeats(df).collect()}
    assert got == {1: ("a b c", "en", 40), 2: ("d", "en", 40)}
