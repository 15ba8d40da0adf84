import pytest
from pyspark.sql import functions as F

from graphparts.functions.hashing import portable_hash, portable_hash_of
from graphparts.operators import analytics, distribution, metrics, spmv
from graphparts.operators.components import connected_components
from graphparts.operators.graph import graph_of, induced, stats
from graphparts.sources import builders


def edges(spark, pairs):
    return spark.createDataFrame(pairs, "src bigint, dst bigint")


def parts(spark, of):
    return spark.createDataFrame(sorted(of.items()), "v bigint, part int")


CLIQUES = [(a, b) for k in (0, 4) for a in range(k, k + 4) for b in range(a + 1, k + 4)] + [(3, 4)]
PATH = [(k, k + 1) for k in range(7)]
STAR = [(0, k) for k in range(1, 8)]
GRID = [(4 * r + c, 4 * r + c + 1) for r in range(4) for c in range(3)] + [(4 * r + c, 4 * r + c + 4) for r in range(3) for c in range(4)]


@pytest.mark.parametrize(
    "graph,n,label,p,want",
    [
        (CLIQUES, 8, lambda v: v // 4, 2, (1, 1, 0.076923, 0.153846, 1.0, 1.0)),
        (CLIQUES, 8, lambda v: v % 2, 2, (9, 9, 0.692308, 1.384615, 1.0, 1.0)),
        (PATH, 8, lambda v: v // 4, 2, (1, 1, 0.142857, 0.285714, 1.0, 1.0)),
        (PATH, 8, lambda v: v % 2, 2, (7, 7, 1.0, 2.0, 0.0, 1.0)),
        (PATH, 8, lambda v: v // 2, 4, (3, 2, 0.428571, 1.142857, 1.0, 1.142857)),
        (STAR, 8, lambda v: v // 4, 2, (4, 4, 0.571429, 1.142857, 2.0, 1.428571)),
        (GRID, 16, lambda v: v // 8, 2, (4, 4, 0.166667, 0.333333, 1.0, 1.0)),
        (GRID, 16, lambda v: v // 8 * 2 + v % 4 // 2, 4, (8, 4, 0.333333, 0.666667, 1.0, 1.0)),
    ],
)
def test_measures_of_hand_graphs(spark, graph, n, label, p, want):
    q = metrics.quality(graph_of(edges(spark, graph)), parts(spark, {v: label(v) for v in range(n)}), p).first()
    assert (q.cut, q.max_cut, q.edge_cut_ratio, q.scaled_max_cut, q.internal_imbalance, q.incident_imbalance) == want
    assert q.n == n and q.m == len(graph)


def test_edges_are_made_canonical(spark):
    g = graph_of(edges(spark, [(1, 2), (2, 1), (1, 2), (3, 3), (None, 4), (5, None)]), spark.createDataFrame([(9,), (1,)], "v bigint"))
    assert [tuple(r)[:2] for r in g.edges.collect()] == [(1, 2)]
    assert {r.v: r.deg for r in g.vertices.collect()} == {1: 1, 2: 1, 9: 0}
    assert g.arcs.count() == 2 and induced(g, spark.createDataFrame([(1,), (9,)], "v bigint")).sizes() == (2, 0)


def test_empty_graph(spark):
    g = graph_of(edges(spark, []))
    assert tuple(stats(g).first()) == (0, 0, None, None, 0)
    assert metrics.part_vertices(parts(spark, {}) if False else spark.createDataFrame([], "v bigint, part int"), 3).count() == 3
    assert connected_components(g.edges).collect() == []


def test_validity_finds_every_fault(spark):
    g = graph_of(edges(spark, PATH))
    bad = spark.createDataFrame([(0, 0), (1, 0), (1, 1), (2, 7), (3, -1), (4, None), (99, 0)], "v bigint, part int")
    assert tuple(metrics.validate(g, bad, 2).first()) == (3, 1, 1, 3)


def test_hash_is_the_same_everywhere(spark):
    rows = spark.range(0, 1_400_000, 7).select((F.col("id") + 3).alias("x")).select(portable_hash("x", 42).alias("h"))
    assert rows.agg(F.sum("h")).first()[0] == 214746468820833
    assert rows.first().h == portable_hash_of(3, 42)


def test_blocks_and_running_sums(spark):
    g = graph_of(edges(spark, STAR + [(100, 200), (200, 300)]))
    v = {r.v: r.label for r in distribution.labels(g.vertices, 3, "vertex_block").collect()}
    assert sorted(v.values()) == [0, 0, 0, 0, 1, 1, 1, 1, 2, 2, 2] and all(v[a] <= v[b] for a in v for b in v if a < b)
    e = {r.v: r.label for r in distribution.labels(g.vertices, 3, "edge_block").collect()}
    assert e[0] == 0 and all(e[a] <= e[b] for a in e for b in e if a < b)
    with pytest.raises(ValueError):
        distribution.labels(g.vertices, 0, "random")
    with pytest.raises(ValueError):
        distribution.labels(g.vertices, 2, "unknown")


def test_exchange_sends_each_label_once(spark):
    g = graph_of(edges(spark, CLIQUES))
    own = spark.createDataFrame([(v, v // 4) for v in range(8)], "v bigint, owner int")
    subs = distribution.subscribers(g, own)
    assert sorted((r.u, r.owner) for r in subs.collect()) == [(3, 1), (4, 0)]
    sent = distribution.route(parts(spark, {3: 1, 0: 1}), subs).collect()
    assert [(r.owner, r.v, r.part) for r in sent] == [(1, 3, 1)]


def test_components(spark):
    for pairs in (PATH + [(20, 21), (21, 22)], [(k, k + 1) for k in range(50, 0, -1)], STAR):
        got = {r.v: r.component for r in connected_components(edges(spark, pairs)).collect()}
        of = {v: v for p in pairs for v in p}
        for _ in pairs:
            for a, b in pairs:
                of[a] = of[b] = min(of[a], of[b])
        assert got == of


def test_analytics_of_small_graphs(spark):
    g = graph_of(edges(spark, PATH), spark.createDataFrame([(50,)], "v bigint")).stored()
    assert sum(r.rank for r in analytics.pagerank(g, 20).collect()) == pytest.approx(1, abs=1e-6)
    assert analytics.approx_diameter(graph_of(edges(spark, PATH)).stored(), 4) == 7
    cores = {r.v: r.core for r in analytics.kcore(graph_of(edges(spark, CLIQUES + [(0, 90)])).stored(), approximate=False).collect()}
    assert cores[90] == 1 and all(cores[v] == 3 for v in range(8))
    assert {r.component for r in analytics.wcc(g).collect()} == {0, 50}
    ring = edges(spark, [(1, 2), (2, 3), (3, 1), (3, 4), (4, 5), (5, 4), (6, 1)])
    assert sorted(r.v for r in analytics.largest_scc(ring).collect()) == [1, 2, 3]
    h = {r.v: r.harmonic for r in analytics.harmonic(g, 100).collect()}
    assert h[0] == pytest.approx(sum(1 / k for k in range(1, 8)), abs=1e-5) and h[50] == 0


def test_products_do_not_depend_on_layout(spark):
    g = graph_of(edges(spark, GRID)).stored()
    a, x = spmv.symmetric(g), g.vertices.select(F.col("v").alias("i"), F.col("v").cast("double").alias("x"))
    plain = sorted(map(tuple, spmv.multiply(a, x).collect()))
    p = parts(spark, {v: v % 4 for v in range(16)})
    for laid in (spmv.layout_1d(a, p), spmv.layout_2d(a, p, 2, 2)):
        assert sorted(map(tuple, spmv.multiply(laid.select("i", "j", "a"), x).collect())) == plain
        assert spmv.comm_stats(laid).first().nonzeros == 2 * len(GRID)
    assert spmv.comm_stats(spmv.layout_2d(a, p, 2, 2)).first().max_partners <= 2
    assert spmv.grid(12) == (3, 4) and spmv.grid(7) == (1, 7)


def test_performance_ratio(spark):
    runs = spark.createDataFrame([("t1", "a", 2.0), ("t1", "b", 4.0), ("t2", "a", 9.0), ("t2", "b", None)], "test string, method string, cut double")
    assert {r.method: (r.ratio, r.tests) for r in metrics.performance_ratio(runs, "cut").collect()} == {"a": (1.0, 2), "b": (2.0, 1)}
    assert {r.method: r.tests for r in metrics.performance_ratio(runs, "cut", True).collect()} == {"a": 1, "b": 1}
    assert metrics.per_core_ratio(2.0, 16) == 8.0


def test_frequent_lines_stay_in_the_graph(spark, tmp_path):
    from graphparts.sources import builders

    line = "a line that very many documents share"
    spark.createDataFrame([(i, line) for i in range(60)] + [(70, "a line of two documents only"), (71, "a line of two documents only")], "doc_id bigint, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {(r.src, r.dst) for r in builders.graph(spark, str(tmp_path), "doc_lines_whole").edges.collect()}
    assert got == {(0, i) for i in range(1, 60)} | {(70, 71)}


def test_analytics_queries_run_in_full(spark, monkeypatch):
    from graphparts import graph_queries as q

    path = graph_of(edges(spark, [(i, i + 1) for i in range(20)]))
    monkeypatch.setattr(q, "main_graph", lambda *a: path)
    assert {r.core for r in q.QUERIES["kcore_whole"](spark, "").collect()} == {1}
    asked = []
    monkeypatch.setattr(q.analytics, "approx_diameter", lambda g, rounds=10: asked.append(rounds) or 20)
    monkeypatch.setattr(q.analytics, "harmonic", lambda g, k: asked.append(k))
    q.QUERIES["diameter"](spark, "")
    q.QUERIES["harmonic_100"](spark, "")
    assert asked == [10, 100]


def test_pages_of_a_frequent_path_are_all_linked(spark):
    """The pages of a path in several tiles have the same links as those in one, each pair once a path."""
    d = "/root/testdata/sf0.001"
    links = [(r.page_id, r.path) for r in builders.page_links(spark, d).collect()]
    pages = {}
    for page, path in links:
        pages.setdefault(path, []).append(page)
    wanted = {(a, b) for x in pages.values() for a in x for b in x if a < b}
    assert max(map(len, pages.values())) == 6
    for most in (2, 1000):
        found = [(min(r), max(r)) for r in builders.page_shared(spark, d, most).collect()]
        assert set(found) == wanted
        assert len(found) == sum(len(x) * (len(x) - 1) // 2 for x in pages.values())


def test_queries_of_the_library_itself_read_given_tables(spark):
    """Generators, schedules and measures work on rows of the tables, so another table gives another result."""
    from graphparts import graph_queries as q

    def read(name, d):
        return q.QUERIES[name](spark, d).inputFiles()

    for name in ("gen_rmat", "gen_er", "gen_hd", "gen_mesh", "gen_planted", "mult_schedule", "mult_variants", "speedup", "absolute_speedup", "random_cut_expectation", "udtf_grid"):
        assert any(f.endswith(("orders.parquet", "customer.parquet", "lineitem.parquet")) for f in read(name, "/root/testdata/sf0.001")), name


def test_searches_from_many_sources_share_each_level(spark):
    """Over 64 sources, two numbers of bits: the same counts as searches that keep a row for each source and vertex, also with a last level."""
    from graphparts.operators.analytics import bfs_levels, reach_counts

    g = graph_of(spark.range(90).selectExpr("id as src", "(id * 7 + 1) % 90 as dst").union(spark.range(200, 204).selectExpr("id as src", "id + 1 as dst"))).stored()
    sources = g.vertices.where("v < 70 or v > 199").selectExpr("v as source")
    for most in (0, 2):
        rows = sorted(map(tuple, reach_counts(g, sources, most).collect()))
        assert rows == sorted(map(tuple, bfs_levels(g.arcs, sources, most).groupBy("source", "dist").count().collect()))
    assert reach_counts(g, sources.limit(0)).count() == 0


def test_a_stored_graph_computes_its_edges_once(spark):
    """Vertices are made of the stored edges: the edges' own plan runs once, isolated vertices and weights included."""
    seen = spark.sparkContext.accumulator(0)

    def told(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    edges = spark.range(100).selectExpr("id as src", "id + 1 as dst").mapInArrow(told, "src bigint, dst bigint")
    for given in (None, spark.createDataFrame([(500, 3), (4, 2)], "v bigint, w bigint")):
        before = seen.value
        g = graph_of(edges, given).stored()
        assert seen.value - before == 100 and g.vertices.count() == 101 + (given is not None) and g.edges.count() == 100


def test_largest_scc_leaves_weak_components_that_hold_no_larger_one(spark, monkeypatch):
    from graphparts.operators import analytics

    pairs = [(10 * k + a, 10 * k + b) for k in range(6) for a, b in ((0, 1), (1, 2), (2, 0))] + [(100, 101), (101, 100)]
    calls, plain = [], analytics.bfs_levels
    monkeypatch.setattr(analytics, "bfs_levels", lambda *a: calls.append(1) or plain(*a))
    got = analytics.largest_scc(spark.createDataFrame(pairs, "src bigint, dst bigint"))
    assert sorted(r.v for r in got.collect()) == [0, 1, 2] and len(calls) == 2
    larger = pairs + [(200 + k, 200 + (k + 1) % 5) for k in range(5)]
    assert sorted(r.v for r in analytics.largest_scc(spark.createDataFrame(larger, "src bigint, dst bigint")).collect()) == [200, 201, 202, 203, 204]
