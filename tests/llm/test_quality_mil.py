import numpy as np

from graphparts.llm import quality_mil as q


def test_features_by_hand():
    x, n = q.encode(["Aa bb, bb bb |", None, "", "w " * 130, "ñ"])
    assert n.tolist() == [1, 1, 1, 3, 1]
    assert x.shape == (7, q.N_FEATURES)
    own = x[0, len(q._KINDS) :]
    assert own[0] == (2 + 3 + 2 + 2 + 1) / 5
    assert own[2] == 4 / 5 and own[3] == 1 / 5  # distinct: Aa, "bb,", bb, |; one word repeats its neighbour
    assert not x[1].any() and not x[2].any()
    assert np.isclose(x[3, len(q._KINDS) + 2], 1 / 64)


def test_gradients_match_differences():
    r = np.random.default_rng(0)
    m = q.train(["aa bb " * 80, "AA!! BB!!", "c d", "X| Y|"], np.array([1, 0, 1, 0]), epochs=1, hidden=5, gate=3)
    x, n = r.normal(size=(7, q.N_FEATURES)), np.array([3, 1, 3])
    y, weight = np.array([1.0, 0.0, 1.0]), np.array([1.0, 2.0, 1.0])

    def loss():
        p = m.forward(x, n)["y"]
        return -(weight * (y * np.log(p) + (1 - y) * np.log(1 - p))).sum() / weight.sum()

    g = q.gradients(m, x, n, y, weight)
    for k, v in m.weights.items():
        flat = v.reshape(-1)
        for i in range(0, len(flat), max(1, len(flat) // 5)):
            keep = flat[i]
            flat[i] = keep + 1e-6
            up = loss()
            flat[i] = keep - 1e-6
            down = loss()
            flat[i] = keep
            assert np.isclose((up - down) / 2e-6, g[k].reshape(-1)[i], atol=1e-6), k


def test_held_out_accuracy_and_edges(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    odd = spark.createDataFrame([(None, "a text", "en", "s", 1), (10**9, None, None, None, None), (10**9 + 1, "", "en", "s", 0)], docs.schema)
    got = q.quality(docs.unionByName(odd), labels)
    rows = {r.doc_id: r for r in got.collect()}
    assert len(rows) == docs.count() + 3 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in rows.values())
    marks = [(rows[r.doc_id].predicted == r.quality) for r in labels.collect() if rows[r.doc_id].held_out]
    assert sum(marks) / len(marks) > 0.95


def test_no_labels(spark):
    docs = spark.createDataFrame([(1, "a"), (2, None)], "doc_id bigint, text string")
    none = spark.createDataFrame([], "doc_id bigint, quality int")
    assert [r.score for r in q.quality(docs, none).collect()] == [0.5, 0.5]
    one = spark.createDataFrame([(1, 1), (2, 1), (3, None)], "doc_id bigint, quality int")
    assert {r.score for r in q.score(docs, q.fit(docs, one)).collect()} == {1.0}
    assert q.quality(docs.limit(0), one).collect() == []


def slow_score(m, text):
    """The model's score by plain loops over passages."""
    import math

    x, _ = q.encode([text])
    w, hidden, scores = m.weights, [], []
    for row in (x - m.mean) / m.scale:
        h = [math.tanh(sum(row[i] * w["enc"][i, j] for i in range(len(row))) + w["enc_b"][j]) for j in range(len(w["enc_b"]))]
        gate = [math.tanh(sum(a * b for a, b in zip(h, w["att_t"][:, k], strict=True))) / (1 + math.exp(-sum(a * b for a, b in zip(h, w["att_s"][:, k], strict=True)))) for k in range(len(w["att"]))]
        hidden.append(h)
        scores.append(sum(a * b for a, b in zip(gate, w["att"], strict=True)))
    weight = [math.exp(s - max(scores)) for s in scores]
    z = [sum(a * h[j] for a, h in zip(weight, hidden, strict=True)) / sum(weight) for j in range(len(hidden[0]))]
    return 1 / (1 + math.exp(-(sum(a * b for a, b in zip(z, w["out"], strict=True)) + w["out_b"][0])))


def test_equals_brute_force_and_edges(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.001/labels.parquet")
    m = q.fit(docs, labels, epochs=3)
    rows = [(x.doc_id, x.text, 0.25) for x in docs.collect()][:60] + [(None, None, 1.0), (7, "", 1.0), (7, "", 1.0), (8, "very long text, " * 60_000, 1.0)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, score double")
    got = q.score(df, m).collect()
    assert len(got) == len(rows) and got[0].asDict().keys() == {"doc_id", "held_out", "score", "predicted"}
    for r, (i, t, _) in zip(got, rows, strict=True):
        if len(t or "") < 100_000:
            assert r.doc_id == i and abs(r.score - slow_score(m, t)) < 1e-9
    kept = q.keep(df, m, least=0.0)
    assert kept.columns == df.columns and kept.count() == len(rows)
    hot = spark.createDataFrame([(1, "a b c")] * 500 + [(2, "d " * 99)], "doc_id bigint, text string")
    mixed = spark.createDataFrame([(1, 1), (2, 0), (2, 0), (None, 1)], "doc_id bigint, quality int")
    assert q.fit(hot, mixed, max_docs=10).constant is not None or q.fit(hot, mixed, max_docs=10).weights
