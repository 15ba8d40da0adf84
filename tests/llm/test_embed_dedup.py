import random

import numpy as np

from graphparts.llm import embed_dedup as e


def brute(rows):
    sound = {i: np.array(x, float) for i, x in rows if i is not None and x and all(v is not None and np.isfinite(v) for v in x) and any(x)}
    links = {i: set() for i, _ in rows if i is not None}
    ids = list(sound)
    for k, i in enumerate(ids):
        for j in ids[:k]:
            a, b = sound[i], sound[j]
            if len(a) == len(b) and a @ b / np.sqrt((a @ a) * (b @ b)) >= 0.95:
                links[i].add(j)
                links[j].add(i)
    out = {}
    for i in links:
        todo, seen = [i], {i}
        while todo:
            for j in links[todo.pop()] - seen:
                seen.add(j)
                todo.append(j)
        out[i] = (len(links[i]), min(seen), min(seen) == i)
    return out


def test_bound_is_rigorous():
    r = np.random.default_rng(1)
    x = r.normal(size=(300, 33))
    x[100:200] = x[:100] + r.normal(size=(100, 33)) * 0.2
    x /= np.linalg.norm(x, axis=1)[:, None]
    q = e.quantised(x)
    i, j = e.possible_pairs(q, q, 0.95)
    found = set(zip(i.tolist(), j.tolist(), strict=True))
    assert {tuple(p) for p in np.argwhere(x @ x.T >= 0.95).tolist()} <= found
    assert (x @ x.T)[i, j].min() > 0.95 - 0.05


def test_equals_brute_force(spark):
    r = random.Random(3)
    f = lambda x: [float(np.float32(v)) for v in x]
    rows = []
    for _ in range(80):
        base = [r.gauss(0, 1) for _ in range(24)]
        for _ in range(r.choice([1, 1, 2, 4])):
            rows.append((len(rows), f([b + r.gauss(0, 0.22) for b in base])))
    rows += [(len(rows) + k, x) for k, x in enumerate([rows[3][1], rows[3][1], None, [], [0.0] * 24, [float("nan")] * 24, [1.0, None], [float("inf")] * 24, [1.0, 2.0], [2.0, 4.0], [1e30] * 24, [1e-30] * 24])]
    df = spark.createDataFrame([(*x, 5) for x in rows], "vec_id bigint, embedding array<float>, rep int")
    for tile in (4096, 30):
        got = {x.vec_id: (x.n_links, x.component_id, x.kept) for x in e.near_duplicate_vectors(df, tile=tile).collect()}
        assert got == brute(rows)
    assert e.near_duplicate_vectors(df.limit(0)).collect() == []
    odd = spark.createDataFrame([(None, [1.0]), (4, [1.0]), (4, [1.0])], "vec_id bigint, embedding array<float>")
    assert sorted((x.n_links, x.component_id or 0) for x in e.near_duplicate_vectors(odd).collect()) == [(0, 0), (1, 4), (1, 4)]


def test_a_large_group_of_near_copies(spark):
    r = np.random.default_rng(5)
    x = np.concatenate([r.normal(size=32) + r.normal(size=(700, 32)) * 0.05, r.normal(size=(300, 32))])
    df = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "vec_id bigint, embedding array<double>")
    u = x / np.linalg.norm(x, axis=1)[:, None]
    near = (u @ u.T >= 0.95).sum(axis=1) - 1
    for tile in (8192, 300):
        got = {y.vec_id: y for y in e.near_duplicate_vectors(df, tile=tile).collect()}
        assert [got[k].n_links for k in range(1000)] == near.tolist()
        assert all(got[k].component_id == 0 for k in range(700)) and all(got[k].kept for k in range(700, 1000))


def test_joining_keeps_a_forest():
    r = np.random.default_rng(2)
    for n, m in ((50, 30), (50, 400), (1, 0)):
        a, b = r.integers(0, n, m), r.integers(0, n, m)
        label = np.arange(n)
        edges = [x for at in range(0, m, 100) for x in e._joining(label, a[at : at + 100], b[at : at + 100])]
        want = np.arange(n)
        for _ in range(n):
            np.minimum.at(want, a, want[b])
            np.minimum.at(want, b, want[a])
        assert label.tolist() == want.tolist() and len(edges) == n - len(set(want.tolist()))
