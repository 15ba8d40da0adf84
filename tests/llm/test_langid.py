from graphparts.llm import langid


def test_backoff_and_edges(spark):
    rows = [(i, t, g, 1) for i, (t, g) in enumerate([("the house and the garden", "en"), ("la casa y el perro la casa", "es")] * 30)]
    extra = [(None, "the house", "en", 1), (900, None, "es", 1), (901, "12 !?", None, 1), (902, "housegarden thegarden", None, 1), (903, "casaperro", None, 1)]
    df = spark.createDataFrame(rows + extra, "doc_id bigint, text string, lang string, score int")
    got = {r.doc_id: r for r in langid.identify(df).collect()}
    assert got[900].lang_pred == got[901].lang_pred == "und" and got[900].score == 0
    assert got[902].lang_pred == "en" and got[903].lang_pred == "es"
    assert all(got[i].lang_pred == g for i, (_, _, g, _) in enumerate(rows))
    assert langid.identify(df.limit(0)).collect() == []
    assert {r.lang_pred for r in langid.predict(df, langid.fit(df.where("lang = 'xx'"))).collect()} == {"und"}


def test_held_out(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    want = {r.doc_id: r.lang for r in docs.collect()}
    marks = [r.lang_pred == want[r.doc_id] for r in langid.identify(docs).collect() if r.held_out]
    assert sum(marks) / len(marks) > 0.97


def test_numerals_are_no_letters(spark):
    rows = [(i, t, g) for i, (t, g) in enumerate([("the house and the garden", "en"), ("la casa y el perro", "es")] * 20)]
    odd = {900: "½ ²", 901: "①", 902: "Ⅷ 12", 903: "", 904: None, 905: "_-_ 3"}
    df = spark.createDataFrame(rows + [(i, t, None) for i, t in odd.items()], "doc_id bigint, text string, lang string")
    got = {x.doc_id: (x.lang_pred, x.score) for x in langid.identify(df).collect()}
    assert all(got[i] == ("und", 0.0) for i in odd)
    assert langid.words_of("The m² ²a½b C") == {"the": 1, "m": 1, "a": 1, "b": 1, "c": 1}


def slow_scores(model, text):
    """The method once more, word by word with plain dictionaries."""
    import math
    import unicodedata

    letters = "".join(c if unicodedata.category(c)[0] == "L" else " " for c in text.lower()).split()
    total = [0.0] * len(model.languages)
    for w in letters:
        if w in model.words:
            row = [float(x) for x in model.word_logs[model.words[w]]]
        else:
            marked, at, pieces = f"<{w}>", 0, []
            while at < len(marked):
                n = next((n for n in range(min(model.max_n, len(marked) - at), 0, -1) if marked[at : at + n] in model.grams), None)
                pieces.append([float(x) for x in (model.floor if n is None else model.gram_logs[model.grams[marked[at : at + n]]])])
                n = n or 1
                at += max(1, n - 1) if at + n < len(marked) else n
            row = [sum(p[k] for p in pieces) / len(pieces) for k in range(len(total))]
        total = [a + b for a, b in zip(total, row, strict=True)]
    if not letters:
        return "und", 0.0
    top = max(total)
    chance = [math.exp(x - top) for x in total]
    return model.languages[total.index(top)], max(chance) / sum(chance)


def test_equals_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    model = langid.fit(docs.where("doc_id % 2 = 0"))
    rows = [(x.doc_id, x.text) for x in docs.collect()] + [(10**6, "zzqx unseenword ½ the"), (10**6 + 1, "la maison " * 100_000)]
    got = {x.doc_id: x for x in langid.predict(spark.createDataFrame(rows, "doc_id bigint, text string"), model).collect()}
    for i, t in rows:
        lang, score = slow_scores(model, t or "")
        assert got[i].lang_pred == lang and abs(got[i].score - score) < 1e-6


def test_repeated_clashing_and_empty(spark):
    df = spark.createDataFrame([(1, "the house", "en", "x"), (1, "the house", "en", "x"), (None, "la casa", "es", None)], "doc_id bigint, text string, lang string, lang_pred string")
    got = langid.identify(df)
    assert got.columns == ["doc_id", "held_out", "lang_pred", "score"] and got.count() == 3
    assert langid.fit(df, max_docs=1).languages and len(langid.fit(df, max_bytes=3).languages) == 0
