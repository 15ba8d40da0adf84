import itertools

import numpy as np
import pyarrow as pa
import pytest

from graphparts.operators import distribution, metrics
from graphparts.operators.graph import graph_of
from graphparts.plans import baselines, initial, worker
from graphparts.plans.config import PartitionConfig
from graphparts.plans.partitioner import _Run, next_bias, partition
from graphparts.plans.sweeps import histogram
from graphparts.sources import builders, generators

from tests.test_graph import CLIQUES, PATH, edges, parts

SF = "/root/testdata/sf0.001"
QUICK = {"outer": 1, "balance": 1, "refine": 2, "n_workers": 2}


def labels(df):
    return {r.v: r.part for r in df.collect()}


def facts(r):
    g, p = r.graph, r.p
    assert tuple(metrics.validate(g, r.parts, p).first()) == (0, 0, 0, 0)
    rows = metrics.part_sizes(g, r.parts, p).collect()
    n, m = g.sizes()
    assert sum(x.vertices for x in rows) == n and sum(x.cut for x in rows) % 2 == 0
    assert sum(x.internal for x in rows) + sum(x.cut for x in rows) // 2 == m
    return rows


def test_schedule():
    c = PartitionConfig(n_workers=16)
    assert [c.mult(t) for t in (0, 15, 30, 45)] == [4.0, 8.0, 12.0, 16.0] and c.mult(44) == pytest.approx(15.733333, abs=1e-6)
    assert PartitionConfig(n_workers=16, schedule_end="inclusive").mult(44) == 16 and PartitionConfig(multiplier=False).mult(3) == 1
    assert next_bias(1, 1, False) == (2, 1) and next_bias(2, 1, True) == (2, 2) and next_bias(2, 1, True, False) == (2, 1)


@pytest.mark.parametrize("wrong", [{"init": "none"}, {"x": -1.0}, {"n_workers": 0}, {"executor": "thread"}, {"quota": "all"}])
def test_wrong_settings_are_refused(wrong):
    with pytest.raises(ValueError):
        PartitionConfig(**wrong)


def test_wrong_part_counts(spark):
    g = graph_of(edges(spark, PATH))
    with pytest.raises(ValueError):
        partition(g, 0)
    with pytest.raises(ValueError):
        initial.grow(g, 9)


def test_one_part_and_more_parts_than_vertices(spark):
    g = graph_of(edges(spark, PATH))
    assert partition(g, 1, **QUICK, mode="vertex").quality().first().cut == 0
    facts(partition(g, 12, **QUICK, mode="vertex", init="random"))


def test_clique_pair_reaches_the_optimum(spark):
    g = graph_of(edges(spark, CLIQUES)).stored()
    best = min(sum((a in s) != (b in s) for a, b in CLIQUES) for s in map(set, itertools.combinations(range(8), 4)))
    r = partition(g, 2, parts=parts(spark, {0: 0, 1: 0, 2: 0, 3: 1, 4: 0, 5: 1, 6: 1, 7: 1}), executor="worker", n_workers=1, multiplier=False, mode="vertex", rat_v=0.25, outer=2, balance=1, refine=3)
    assert best == 1 and r.quality().first().cut == best


def test_set_and_delta_agree_whatever_the_shuffle(spark):
    g = builders.graph(spark, SF, "cust_part").stored()
    out = []
    before = spark.conf.get("spark.sql.shuffle.partitions")
    for executor, shuffle in (("set", 4), ("delta", 4), ("set", 1), ("delta", 7)):
        spark.conf.set("spark.sql.shuffle.partitions", shuffle)
        out.append(labels(partition(g, 3, executor=executor, **QUICK).parts))
    spark.conf.set("spark.sql.shuffle.partitions", before)
    assert all(x == out[0] for x in out)


def test_refinement_by_one_worker_never_raises_the_cut(spark):
    g = builders.graph(spark, SF, "supp_part").stored()
    run = _Run(g, 4, PartitionConfig(executor="worker", n_workers=1, multiplier=False), baselines.random(g, 4))
    cuts = [metrics.quality(g, run.parts, 4).first().cut]
    for t in range(3):
        run.one("vertex_refine", t)
        cuts.append(metrics.quality(g, run.parts, 4).first().cut)
    assert cuts == sorted(cuts, reverse=True) and cuts[-1] < cuts[0]


def test_admission_keeps_the_limit_when_tight(spark):
    g = builders.graph(spark, SF, "supp_part").stored()
    run = _Run(g, 4, PartitionConfig(n_workers=3, x=1.0, y=1.0), baselines.random(g, 4))
    for t, kind in enumerate(["vertex_balance", "vertex_refine", "vertex_refine"]):
        before = metrics.part_vertices(run.parts, 4).agg({"vertices": "max"}).first()[0]
        run.one(kind, t)
        after = metrics.part_vertices(run.parts, 4).agg({"vertices": "max"}).first()[0]
        assert after <= max(before, run.imb_v)


def test_growth_from_the_frontier_equals_a_full_scan(spark):
    from pyspark.sql import functions as F

    g = builders.graph(spark, SF, "fk_tree").stored()
    now = labels(initial.draw_roots(g, 3, 42))
    near = {}
    for r in g.arcs.collect():
        near.setdefault(r.v, set()).add(r.u)
    sweep = 0
    while True:
        offers = [(v, q) for v in near if v not in now for q in {now[u] for u in near[v] if u in now}]
        if not offers:
            break
        chosen = labels(initial._any_part(spark.createDataFrame(offers, "v bigint, part int"), 42 + sweep))
        now |= chosen
        sweep += 1
    got = labels(initial._spread(g, initial.draw_roots(g, 3, 42), 42, 0, initial._any_part))
    assert got == now and F is not None


def test_whole_partition_on_a_chain_beats_random(spark):
    g = builders.graph(spark, SF, "order_chain").stored()
    r = partition(g, 4, init="vertex_block", executor="worker", **QUICK)
    facts(r)
    q, b = r.quality().first(), metrics.quality(g, baselines.random(g, 4), 4).first()
    assert q.edge_cut_ratio < 0.6 * b.edge_cut_ratio and q.vertex_imbalance <= 1.25
    assert r.history_frame().count() == len(r.history)


@pytest.mark.parametrize("coarsen", ["matching", "clusters"])
def test_multilevel(spark, coarsen):
    g = graph_of(generators.planted(spark, 4, 40, 5, 1)).stored()
    got = baselines.multilevel(g, 4, coarsen, rat=0.1, coarsest=40, levels=3, refine=2)
    assert tuple(metrics.validate(g, got, 4).first()) == (0, 0, 0, 0)
    assert metrics.quality(g, got, 4).first().cut < metrics.quality(g, baselines.random(g, 4), 4).first().cut


def test_contraction_keeps_weights_and_cuts(spark):
    g = graph_of(edges(spark, CLIQUES)).stored()
    coarse = baselines.contract(g, spark.createDataFrame([(v, v // 2) for v in range(8)], "v bigint, coarse bigint"))
    assert coarse.vertices.agg({"w": "sum"}).first()[0] == 8
    assert coarse.edges.agg({"w": "sum"}).first()[0] == len(CLIQUES) - 4
    assert labels(baselines.solve_small(coarse, 2, 0.1).withColumnRenamed("part", "part")) in ({0: 0, 1: 0, 2: 1, 3: 1}, {0: 1, 1: 1, 2: 0, 3: 0})


def test_histogram_counts_arcs(spark):
    g = graph_of(edges(spark, CLIQUES)).stored()
    h = histogram(g, parts(spark, {v: v // 4 for v in range(8)}))
    assert h.agg({"n": "sum"}).first()[0] == 2 * len(CLIQUES)


def test_generators_have_their_shape(spark):
    assert generators.rmat(spark, 10, 8).count() > 4500
    far = generators.high_diameter(spark, 300, 5).selectExpr("max(dst - src)").first()[0]
    assert far <= 4 and generators.mesh3d(spark, 3, 3, 3).count() == 158


def test_partition_queries_run_the_whole_schedule(monkeypatch):
    from graphparts import graph_queries as q

    seen = []
    monkeypatch.setattr(q.builders, "graph", lambda *a: None)
    monkeypatch.setattr(q, "partition", lambda g, p, **o: seen.append(PartitionConfig(**o)))
    monkeypatch.setattr(q.baselines, "single_node", lambda g, p, **o: seen.append(PartitionConfig(**o)))
    for make in q._partitions().values():
        make(None, "")
    assert len(seen) == 11 and {(c.outer, c.balance, c.refine, c.early_stop) for c in seen} == {(3, 5, 10, False)}


def visited(ids, near, deg, live, start, p, kind, imb, re=1.0, rc=1.0):
    """One worker's sweep by plain loops, each vertex against the sizes as they are then."""
    size = [list(x) for x in start]
    top = [max(max(size[0]), imb[0]), max(max(size[1]), imb[1]), max(size[2])]
    attract = lambda t, x: max(t / max(x, 1) - 1, 0.0)
    edge, balance = kind.startswith("edge"), kind.endswith("balance")
    for v in ids:
        n, score, x = [0] * p, [0.0] * p, live[v]
        for u in near[v]:
            n[live[u]] += 1
            score[live[u]] += deg[u] if balance else 1
        for i in range(p):
            if balance:
                score[i] *= re * attract(top[1], size[1][i]) + rc * attract(top[2], size[2][i]) if edge else attract(imb[0], size[0][i])
            over = size[0][i] + 1 > top[0] or edge and (size[1][i] + n[i] > top[1] or size[2][i] + deg[v] - 2 * n[i] > top[2])
            if over and i != x:
                score[i] = 0
        y = score.index(max(score))
        if max(score) > 0 and score[x] < max(score):
            live[v] = y
            for i, sign in ((x, -1), (y, 1)):
                size[0][i] += sign
                size[1][i] += sign * n[i]
                size[2][i] += sign * (deg[v] - 2 * n[i])
    return live


@pytest.mark.parametrize("offset", [0, 2**60])
def test_one_worker_equals_plain_loops(spark, offset):
    from pyspark.sql import functions as F

    base = builders.graph(spark, SF, "supp_part")
    g = graph_of(base.edges.select((F.col("src") + offset).alias("src"), (F.col("dst") + offset).alias("dst"))).stored()
    near = {}
    for r in g.arcs.collect():
        near.setdefault(r.v, []).append(r.u)
    ids, deg, p = sorted(near), {v: len(u) for v, u in near.items()}, 3
    live = {v: (v - offset) * 7 % 11 % p for v in ids}
    run = _Run(g, p, PartitionConfig(executor="worker", n_workers=1, multiplier=False, blocks=10**6), parts(spark, live))
    for t, kind in enumerate(["vertex_balance", "vertex_refine", "edge_balance", "edge_refine"]):
        sizes = [[sum(x == i for x in live.values()) for i in range(p)]]
        sizes.append([sum(live[u] == live[v] == i for v in ids for u in near[v]) // 2 for i in range(p)])
        sizes.append([sum(live[v] == i != live[u] for v in ids for u in near[v]) for i in range(p)])
        run.known = None
        run.one(kind, t)
        assert (run.history[-1]["max_v"], run.history[-1]["max_e"], run.history[-1]["max_c"]) == tuple(map(max, sizes))
        live = visited(ids, near, deg, dict(live), sizes, p, kind, (run.imb_v, run.imb_e), 1.0, 1.0)
        assert labels(run.parts) == live
        run.re = run.rc = 1.0


def test_ids_above_two_to_the_53_are_kept_apart(spark):
    for offset in (0, 2**60):
        clique = [(a, b) for k in (0, 12) for a in range(k, k + 12) for b in range(a + 1, k + 12)]
        g = graph_of(edges(spark, [(a + offset, b + offset) for a, b in clique])).stored()
        mixed = {v + offset: int(v in (0, 1, 2, 3, 4, 5, 6, 12, 13, 14, 15, 16)) for v in range(24)}
        r = partition(g, 2, executor="worker", mode="vertex", n_workers=3, outer=1, balance=1, refine=6, rat_v=0.5, parts=parts(spark, mixed), release="none")
        assert r.quality().first().cut == 0


@pytest.mark.parametrize("executor", ["worker", "set"])
def test_release_meets_the_limits(spark, executor):
    g = builders.graph(spark, SF, "fk_tree").stored()
    lop = g.vertices.selectExpr("v", "cast(if(v % 5 < 4, 0, v % 3) as int) as part")
    r = partition(g, 3, executor=executor, mode="vertex_edge", n_workers=4, outer=1, balance=0, refine=0, parts=lop)
    q = metrics.limits(g, r.parts, 3).first()
    facts(r)
    assert q.max_vertices <= q.vertex_limit and (q.max_edges <= q.edge_limit or executor == "set")
    assert {h["stage"] for h in r.history} <= {"vertex_release", "edge_release"}


def test_a_sweep_exchanges_labels_only(spark):
    """The layout is not shuffled again: the plan of a sweep has one exchange, of the labels and messages."""
    g = builders.graph(spark, SF, "supp_part").stored()
    run = _Run(g, 4, PartitionConfig(executor="worker"), baselines.random(g, 4))
    sent = run.workers.state.where("kind < 2")
    plan = run.workers.layout.groupBy("owner").cogroup(sent.groupBy("owner")).applyInArrow(lambda a, b: a, run.workers.layout.schema)
    text = plan._jdf.queryExecution().executedPlan().toString()
    assert text.count("ENSURE_REQUIREMENTS") == 1 and text.count("InMemoryRelation") == 1, text  # what stands below the relation is kept


def test_arcs_of_a_worker_are_laid_out_in_chunks(spark, monkeypatch):
    """No task that builds them sees a worker's arcs all at once, and the parts are the same for chunks of any size; weights of 1 are left out."""
    from graphparts.plans import worker

    g = builders.graph(spark, SF, "cust_supp").stored()
    found = []
    for chunk in (1 << 20, 300):
        monkeypatch.setattr(worker, "_CHUNK", chunk)
        owners = distribution.owners(g, 3)
        laid = worker.layout(g, worker.sides(g, owners)).where("chunk >= 0").selectExpr("owner", "length(idx) div 4 as arcs", "w").collect()
        assert sum(r.arcs for r in laid) == 2 * g.edges.count() and all(r.w is None for r in laid)
        degree = g.vertices.selectExpr("max(deg)").first()[0]
        assert all(r.arcs < chunk + degree for r in laid) and (len(laid) == 3) == (chunk > 300)
        found.append(labels(partition(g, 3, executor="worker", **{**QUICK, "n_workers": 3}).parts))
    assert found[0] == found[1]


def test_arcs_of_few_vertices_are_exchanged_once(spark):
    """Where the vertices are few their places go to all executors, and the layout joins arcs without a shuffle or a sort of them; the parts are those of the other way."""
    from graphparts.plans import worker

    g = builders.graph(spark, SF, "cust_supp").stored()
    owners = distribution.owners(g, 3)
    text = worker.layout(g, worker.sides(g, owners, 3), 3)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" not in text and "ShuffledHashJoin" not in text and text.count("BroadcastHashJoin") >= 2, text


def test_parts_do_not_depend_on_how_arcs_are_joined(spark, monkeypatch):
    from graphparts.plans import skew, worker

    g = builders.graph(spark, SF, "cust_supp").stored()
    few = labels(partition(g, 3, executor="worker", **{**QUICK, "n_workers": 3}).parts)
    monkeypatch.setattr(skew, "SMALL", 0)
    monkeypatch.setattr(worker, "SMALL", 0)
    assert labels(partition(g, 3, executor="worker", **{**QUICK, "n_workers": 3}).parts) == few


def test_groups_of_large_rows_come_in_small_batches(spark):
    import pyarrow as pa

    from graphparts.plans.scratch import small_batches, written

    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before, rows = spark.conf.get(name, None), spark.range(64).selectExpr("id % 2 as k", "cast(repeat('x', 1000000) as binary) as b")
    count = lambda a, b: pa.table({"n": pa.array([a.column("b").num_chunks])})
    with small_batches(spark):
        found = written(rows.groupBy("k").cogroup(rows.groupBy("k")).applyInArrow(count, "n bigint"))
    assert all(r.n >= 3 for r in found.collect())
    assert spark.conf.get(name, None) == before


def test_runs_of_one_graph_share_their_start(spark, monkeypatch):
    from graphparts.plans import experiments, initial
    from graphparts.plans.partitioner import partition

    g = experiments.named(spark, "/root/testdata/sf0.001", "fk_tree")
    own = partition(g, 3, **experiments.QUICK, n_workers=2)
    calls, plain = [], initial.start
    monkeypatch.setattr(initial, "start", lambda *a: calls.append(a) or plain(*a))
    rows = [experiments._partitioned("fk_tree", g, 3, n_workers=k) for k in (1, 2)]
    q = own.quality().first()
    assert len(calls) == 1 and (rows[1][6], rows[1][7]) == (q.cut, q.max_cut)


@pytest.mark.parametrize(
    "options",
    [
        {"mode": "vertex"},
        {"mode": "multi", "edge_measure": "incident"},
        {"mode": "vertex_edge", "quota": "strict", "own_mask": True, "vertex_score": "count", "y": 1.0},
    ],
)
def test_arrays_and_tables_make_the_same_sets(spark, monkeypatch, options):
    """``set`` and ``delta`` through the workers' arrays, with ids above 2^53 and weights, equal the plans over tables, releases included."""
    far = graph_of(generators.planted(spark, 3, 30, 5, 2))
    shifted = far.edges.selectExpr(*(f"if({c} % 3 = 0, {c} + {1 << 60}, {c}) as {c}" for c in ("src", "dst")), "1 + (src + dst) % 3 as w")
    ends = shifted.selectExpr("explode(array(src, dst)) as v").distinct().selectExpr("v", "1 + v % 2 as w")
    g = graph_of(shifted, ends).stored()
    lop = g.vertices.selectExpr("v", "cast(if(v % 5 < 3, 0, v % 3) as int) as part")
    found = []
    for most, executor in ((-1, "set"), (worker.MOST_ARCS, "set"), (worker.MOST_ARCS, "delta")):
        monkeypatch.setattr(worker, "MOST_ARCS", most)
        r = partition(g, 3, executor=executor, parts=lop, outer=1, balance=1, refine=1, n_workers=3, **options)
        facts(r)
        found.append((labels(r.parts), [(h["stage"], h["moves"], h["max_v"], h["re"], h["rc"]) for h in r.history]))
    assert any(moves for _, moves, *_ in found[0][1])
    assert found[1] == found[0] and found[2] == found[0]


def test_a_kept_histogram_is_the_counted_one(spark):
    g = builders.graph(spark, SF, "supp_part").stored()
    run = _Run(g, 4, PartitionConfig(executor="delta", n_workers=3), baselines.random(g, 4))
    assert run.workers is not None
    for t, kind in enumerate(("vertex_balance", "vertex_refine")):
        assert run.one(kind, t)
    rows = lambda df: sorted(map(tuple, df.select("v", "part", "n", "dsum").collect()))
    assert rows(run.histogram()) == rows(histogram(g, run.parts))


@pytest.mark.parametrize("top, widths", [(5, [2, 2]), (1 << 20, [4, 4]), (1 << 40, [8, 8])])
def test_a_histogram_is_packed_without_loss(top, widths):
    held = np.array([[[0, top], [1, 2], [top, 0]], [[top, 0], [0, 0], [3, top]]], np.int64)
    kept, found = worker._packed(held)
    assert found == widths and len(kept) == 12 * widths[0]
    assert (worker._unpacked(pa.py_buffer(kept), found, 3) == held).all()


def test_the_grid_of_multipliers_reaches_both_ends(spark, monkeypatch):
    """Every X gives balance sweeps of its own: with one balance sweep all were made at Y, and the stage on edges was left out."""
    from graphparts.plans import experiments

    seen, plain = [], experiments.partition

    def one(g, p, cfg, parts):
        seen.append(cfg)
        return plain(g, p, cfg, parts, outer=1, balance=0, refine=0, release="none")

    monkeypatch.setattr(experiments, "partition", one)
    rows = experiments.WORKLOADS["w10_multiplier_grid"](spark, SF).collect()
    sweeps = [o * 15 + k for o in range(3) for k in range(5)]
    assert len(rows) == 9 and len({tuple(c.mult(t) for t in sweeps) for c in seen}) == 9
    assert {(c.mode, c.outer, c.balance, c.refine, c.early_stop) for c in seen} == {("multi", 3, 5, 10, False)}
    assert spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch") != "8m"


def test_analytics_by_layout_run_in_full_on_arcs_placed_once(spark, monkeypatch):
    from graphparts.plans import experiments

    path, asked = graph_of(edges(spark, PATH)).stored(), []
    monkeypatch.setattr(experiments, "named", lambda *a: path)
    monkeypatch.setattr(experiments, "layouts", lambda g, p, **o: asked.append(("layouts", o["outer"], o["balance"], o["refine"], o["early_stop"])) or {"random": (baselines.random(g, p), 0.0)})

    def stub(name, column):
        def run(x, *a, **o):
            asked.append((name, x.edges.storageLevel.useDisk, *a, *o.items()))
            return path.vertices.selectExpr("v", f"v as {column}")

        monkeypatch.setattr(experiments.analytics, name, run)

    for name, column in (("pagerank", "rank"), ("label_propagation", "community"), ("kcore", "core"), ("harmonic", "harmonic")):
        stub(name, column)
    rows = experiments.WORKLOADS["w11_analytics_by_layout"](spark, SF).collect()
    assert [r.analytic for r in rows] == ["pagerank", "labels", "wcc", "kcore", "harmonic", "scc"]
    assert asked == [("layouts", 3, 5, 10, False), ("pagerank", True, 10), ("label_propagation", True, 5), ("kcore", True), ("harmonic", True, 100)]


def test_multilevel_coarsens_a_star_to_the_end(spark, monkeypatch):
    """Around hubs neighbours leave one pair each; leaves are paired too, and no workload limits the levels."""
    from graphparts.plans import experiments

    g = graph_of(spark.range(600).selectExpr("id % 3 as src", "id + 10 as dst")).stored()
    alone = baselines.matching(g)
    more = [(r.v, r.mate) for r in baselines.pairs_around(g, alone, most=50).collect()]
    ends = [x for pair in more for x in pair] + [x for r in alone.collect() for x in (r.v, r.mate)]
    assert len(ends) == len(set(ends)) and len(ends) > 560 and all(a < b and (a - b) % 3 == 0 for a, b in more)
    solved, asked, plain = [], [], baselines.solve_small
    monkeypatch.setattr(baselines, "solve_small", lambda x, *a: solved.append(x.vertices.count()) or plain(x, *a))
    whole = baselines.multilevel
    monkeypatch.setattr(baselines, "multilevel", lambda *a, **o: asked.append(o) or whole(*a, **o, coarsest=160))
    row = experiments._other("star", g, 4, "multilevel_matching")
    assert solved[0] <= 160 and asked == [{}] and row[-1]
