import random

from graphparts.llm.ngram_join import near_duplicates, without_near_duplicates


def grams(t):
    w = (t or "").split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def brute(rows):
    sets = [(i, grams(t)) for i, t in rows if i is not None]
    links = {i: set() for i, _ in sets}
    for k, (i, a) in enumerate(sets):
        for j, b in sets[:k]:
            if a and b and i != j and len(a & b) >= 0.8 * len(a | b):
                links[i].add(j)
                links[j].add(i)
    out = {}
    for i in links:
        todo, seen = [i], {i}
        while todo:
            for j in links[todo.pop()] - seen:
                seen.add(j)
                todo.append(j)
        out[i] = (min(seen), len(links[i]))
    return out


def fixture():
    r = random.Random(4)
    word = lambda: r.choice("abcdefghij") + str(r.randrange(300))
    rows, n = [], 0
    passage = [word() for _ in range(14)]
    for _ in range(60):
        base = [word() for _ in range(r.choice([2, 5, 9, 40, 120, 400]))]
        if r.random() < 0.5:
            base = passage + base
        for _ in range(r.choice([1, 1, 2, 3, 6])):
            w = list(base)
            for _ in range(r.choice([0, 0, 1, 2, 4])):
                w[r.randrange(len(w))] = word()
            rows.append((n, " ".join(w)))
            n += 1
    big = [word() for _ in range(150)]
    for _ in range(120):
        w = list(big)
        for _ in range(r.randrange(5)):
            w[r.randrange(len(w))] = word()
        rows.append((n, " ".join(w)))
        n += 1
    return rows + [(n, ""), (n + 1, None), (n + 2, " \n"), (n + 3, "x " * 30), (n + 4, "x " * 60)]


def test_equals_brute_force(spark):
    rows = fixture()
    want = brute(rows)
    df = spark.createDataFrame([(*x, 1, 2) for x in rows], "doc_id bigint, text string, rep int, n int")
    for options in ({}, {"bucket_limit": 8, "tile": 20}):
        got = {r.doc_id: (r.class_id, r.n_links) for r in near_duplicates(df, **options).collect()}
        assert got == want


def test_edges(spark):
    schema = "doc_id bigint, text string"
    assert near_duplicates(spark.createDataFrame([], schema)).collect() == []
    got = near_duplicates(spark.createDataFrame([(None, "a b c d e f"), (5, "a b c d e f"), (5, "a b c d e f"), (9, "a b  c d e f"), (None, None)], schema)).collect()
    assert sorted((r.doc_id, r.class_id, r.n_links, r.kept) for r in got if r.doc_id) == [(5, 5, 2, False), (5, 5, 2, True), (9, 5, 2, False)]  # one row of the class stays
    assert [(r.class_id, r.n_links, r.kept) for r in got if r.doc_id is None] == [(None, 0, True)] * 2


def hot_pairs(n=1000):
    """Pairs at similarity 0.8, the worst size ratio, whose shared shingles (words) are each in some 200 documents; no others link."""
    r = random.Random(8)
    rows = []
    for k in range(n):
        words = r.sample(range(400), 40)
        rows += [(2 * k, " ".join(f"w{x}" for x in words)), (2 * k + 1, " ".join(f"w{x}" for x in words[:32]))]
    return rows


def test_recall_where_all_shingles_are_hot(spark):
    rows = hot_pairs()
    got = {r.doc_id: r.n_links for r in near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string"), size=1, bucket_limit=1).collect()}
    found = sum(got[i] > 0 and got[i + 1] > 0 for i in range(0, len(rows), 2)) / (len(rows) / 2)
    print(f"recall {found:.5f}")
    assert found >= 0.9985  # one of 1,000 pairs may miss


def test_one_id_with_several_texts(spark):
    r = random.Random(3)
    base = [f"w{r.randrange(500)}" for _ in range(60)]
    near = " ".join([*base[:59], "other"])
    a, b, c = " ".join(base), "another text of its own with some words", "a third one that nobody else has at all"
    schema = "doc_id bigint, text string, kept boolean, _nj_row int"
    rows = [(1, a), (1, b), (2, near), (5, a), (5, b), (7, c), (7, c)]
    df = spark.createDataFrame([(*x, None, 3) for x in rows], schema)
    got = sorted((x.doc_id, x.class_id, x.n_links) for x in near_duplicates(df).collect())
    assert got == sorted([(1, 1, 2), (1, 1, 1), (2, 1, 2), (5, 1, 2), (5, 1, 1), (7, 7, 1), (7, 7, 1)])
    left = without_near_duplicates(df.drop("_nj_row"))
    assert sorted((x.doc_id, x.text) for x in left.collect()) == sorted([(1, a), (1, b), (7, c)]) and left.columns == ["doc_id", "text", "kept"]
    for rows in ([(1, "A"), (1, "B"), (2, "C"), (3, "C")], [(5, "A"), (5, "B"), (2, "B")]):
        left = without_near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
        assert {x.text for x in left} == {t for _, t in rows} and len(left) == len({t for _, t in rows})


def test_texts_of_a_megabyte(spark):
    r = random.Random(5)
    long = [f"w{r.randrange(10**6)}" for _ in range(150_000)]
    rows = [(1, " ".join(long)), (2, " ".join([*long[:-9], "end"])), (3, "x " * 400_000)]
    got = {x.doc_id: (x.class_id, x.n_links) for x in near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert got == {1: (1, 1), 2: (1, 1), 3: (3, 0)}


def test_recall_at_the_threshold_on_given_documents(spark):
    """Ids divisible by 20 against all rows, by brute force."""
    rows = [(x.doc_id, x.text) for x in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()]
    sets = {i: grams(t) for i, t in rows}
    want = {i: sum(j != i and bool(s) and bool(o) and len(s & o) >= 0.8 * len(s | o) for j, o in sets.items()) for i, s in sets.items() if i % 20 == 0}
    got = {x.doc_id: x.n_links for x in near_duplicates(spark.read.parquet("/root/testdata/sf0.01/documents.parquet")).collect()}
    assert sum(want.values()) > 5 and {i: got[i] for i in want} == want
