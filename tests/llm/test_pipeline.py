import random
from collections import Counter

import corpus_pipeline as c


def documents(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t)) for i, t in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")


def test_stages_on_planted_documents(spark, tmp_path):
    real = {r.doc_id: r.text for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()}
    good = [real[r.doc_id] for r in spark.read.parquet("/root/testdata/sf0.01/labels.parquet").collect() if r.quality == 1 and len(real[r.doc_id]) > 900][:40]
    r = random.Random(1)
    near = good[3].split()
    near[len(near) // 2] = "changed"
    passage = " ".join(f"{r.choice(['the', 'and', 'of'])}er{r.randrange(99)}" for _ in range(60))
    rows = [(i, t) for i, t in enumerate(good)]
    rows += [(100, good[0]), (101, " ".join(near)), (102, good[5] + "\n" + passage), (103, good[6] + " " + passage), (104, "BUY!! NOW!! " * 90), (105, good[7] + " password=82da0c4f9f2588bda2")]
    rows += [(106, None), (107, ""), (None, good[8]), (9, good[9])]
    rows = [(i if i is None else i + 100_000, t) for i, t in rows]
    docs = documents(spark, [*real.items(), *rows])
    picked = lambda df: [x for x in df.collect() if x.doc_id is None or x.doc_id >= 100_000]
    labels = "/root/testdata/sf0.01"
    stages = dict(c.STAGES)
    kept = stages["quality classifier"](spark, docs, labels)
    ids = Counter(x.doc_id for x in picked(kept))
    assert 100_104 not in ids and all(100_000 + i in ids for i in range(40)) and ids[100_009] == 2
    planted = documents(spark, rows)
    left = stages["n-gram Jaccard join"](spark, planted, labels)
    ids = Counter(x.doc_id for x in left.collect())
    assert 100_100 not in ids and 100_101 not in ids and ids[100_009] == 1 and ids[None] == 1 and left.columns == docs.columns
    cut = {x.doc_id: x for x in stages["substring dedup"](spark, left, labels).collect()}
    for i in (100_102, 100_103):
        assert i not in cut or passage not in cut[i].text and cut[i].n_chars == len(cut[i].text)
    clean = {x.doc_id: x.text for x in stages["secret scans"](spark, planted, labels).collect()}
    assert clean[100_105].endswith("password=[SECRET]") and all(clean[100_000 + i] == good[i] for i in range(9))
    packed = stages["best-fit packing"](spark, left, labels)
    assert {x.doc_id for x in packed.collect()} == set(ids) | {None}


def test_run_and_empty_documents(spark, tmp_path):
    for name in ("documents", "labels"):
        spark.read.parquet(f"/root/testdata/sf0.001/{name}.parquet").limit(0).write.parquet(str(tmp_path / f"{name}.parquet"))
    assert c.run(spark, str(tmp_path)).collect() == []
    got = c.run(spark, "/root/testdata/sf0.001").collect()
    assert got and {len([k for k in STAGE if k]) for STAGE in c.STAGES} == {2}


def test_near_duplicate_stage_keeps_every_text(spark):
    stage = dict(c.STAGES)["n-gram Jaccard join"]
    for rows in ([(1, "A"), (1, "B"), (2, "C"), (3, "C")], [(5, "A"), (5, "B"), (2, "B")], [(None, "A"), (None, "A"), (4, None), (4, "")]):
        left = [(x.doc_id, x.text) for x in stage(spark, documents(spark, rows), "").collect()]
        assert {t for _, t in left} == {t for _, t in rows}


def test_columns_of_the_same_names_pass(spark):
    names = ["findings", "n_words", "n_removed", "kept", "class_id", "score", "media", "size"]
    docs = documents(spark, [(1, "a password=82da0c4f9f2588bda2 here"), (2, None), (None, ""), (1, "another text")])
    docs = docs.selectExpr("*", *(f"'{n}' AS {n}" for n in names))
    for name, stage in c.STAGES[:-1]:
        out = stage(spark, docs, "/root/testdata/sf0.001")
        assert out.columns == docs.columns, name
        assert all(x[n] == n for x in out.collect() for n in names), name
        assert stage(spark, docs.limit(0), "/root/testdata/sf0.001").collect() == []


def test_python_sees_few_rows_at_once(spark):
    from graphparts.llm.common import mapped

    rows = spark.range(0, 1000, 1, 2)
    got = mapped(rows, lambda b: {"id": b.column(0), "n": [b.num_rows] * b.num_rows}, "id bigint, n int", 64).collect()
    assert sorted(r.id for r in got) == list(range(1000)) and max(r.n for r in got) == 64


def test_quality_stage_keeps_the_same_rows_in_pieces(spark):
    import numpy as np

    from graphparts.llm.quality_mil import fit, keep

    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{n}.parquet") for n in ("documents", "labels"))
    model = fit(docs, labels)
    rows = docs.select("doc_id", "text").collect()
    wanted = sorted(r.doc_id for r in rows if np.asarray(model.scores([r.text]))[0] >= 0.5)
    assert len(rows) > 512 and sorted(r.doc_id for r in keep(docs.coalesce(1), model).collect()) == wanted
