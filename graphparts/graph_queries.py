"""Queries for methods, variants, baselines, measures and workloads, with SQL where it can be said in SQL; the README lists what is not built."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphparts import sql_text as sql
from graphparts.functions import udx
from graphparts.functions.hashing import portable_hash
from graphparts.operators import analytics, distribution, metrics, spmv
from graphparts.operators.graph import Graph, degree_histogram, graph_of, hubs, stats
from graphparts.plans import baselines, experiments, initial
from graphparts.plans import sweeps as sw
from graphparts.plans.config import PartitionConfig
from graphparts.plans.partitioner import PartitionResult, _Run, partition
from graphparts.plans.scratch import shared_folder
from graphparts.sources import builders, files, generators
from graphparts.streaming import edges as streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

P, N, SEED = 4, 4, 11
MAIN = "supp_part"


def query(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def main_graph(spark: SparkSession, d: str) -> Graph:
    return builders.graph(spark, d, MAIN)


def start(g: Graph, p: int = P) -> DataFrame:
    return baselines.random(g, p, SEED)


START = sql.random_parts(P, SEED)
OWNERS = sql.random_parts(N, distribution.RANDOM_SEED, "owners", "owner")

# --- graphs -------------------------------------------------------------------------------

for _name in builders.BUILDERS:
    query(f"g_{_name}", sql.graph(_name) + "SELECT src, dst FROM edges")(lambda s, d, n=_name: builders.graph(s, d, n).edges.select("src", "dst"))

query("g_degree_stats", sql.graph(MAIN) + "SELECT count(*) AS n, (sum(deg) // 2)::BIGINT AS m, round(2 * (sum(deg) // 2) / count(*), 6) AS d_avg_arcs, round((sum(deg) // 2) / count(*), 6) AS d_avg_edges, max(deg) AS d_max FROM vertices")(lambda s, d: stats(main_graph(s, d)))
query("g_degree_hist", sql.graph(MAIN) + "SELECT deg, count(*) AS n FROM vertices GROUP BY deg")(lambda s, d: degree_histogram(main_graph(s, d)))
query("g_hubs_topk", sql.graph(MAIN) + "SELECT v, deg FROM vertices ORDER BY deg DESC, v LIMIT 20")(lambda s, d: hubs(main_graph(s, d), 20))

# --- distribution and exchange ---------------------------------------------------------------

query("own_random", sql.graph(MAIN, OWNERS) + "SELECT * FROM owners")(lambda s, d: distribution.owners(main_graph(s, d), N))
query("own_vertex_block", sql.graph(MAIN, sql.block(N, "vertex", "owners", "owner")) + "SELECT * FROM owners")(lambda s, d: distribution.owners(main_graph(s, d), N, "vertex_block"))
query("own_edge_block", sql.graph(MAIN, sql.block(N, "edge", "owners", "owner")) + "SELECT * FROM owners")(lambda s, d: distribution.owners(main_graph(s, d), N, "edge_block"))
_GHOSTS = "ghosts AS (SELECT DISTINCT a.owner, x.u FROM arcs x JOIN owners a ON a.v = x.v JOIN owners b ON b.v = x.u WHERE a.owner <> b.owner)"
_CHANGED = f"changed AS (SELECT v, part FROM parts WHERE {sql.h('v', 1)} % 3 = 0)"


def _setup(s: SparkSession, d: str) -> tuple[Graph, DataFrame, DataFrame, DataFrame]:
    g = main_graph(s, d)
    own = distribution.owners(g, N)
    changed = start(g).where(portable_hash("v", 1) % 3 == 0)
    return g, own, distribution.subscribers(g, own), changed


query("ghosts", sql.graph(MAIN, OWNERS, _GHOSTS) + "SELECT * FROM ghosts")(lambda s, d: distribution.ghosts(main_graph(s, d), distribution.owners(main_graph(s, d), N)))
query("subscribers", sql.graph(MAIN, OWNERS, _GHOSTS) + "SELECT u, owner FROM ghosts")(lambda s, d: _setup(s, d)[2])
query("boundary_pairs", sql.graph(MAIN, OWNERS) + "SELECT a.owner AS owner_v, b.owner AS owner_u, count(*) AS edges FROM arcs x JOIN owners a ON a.v = x.v JOIN owners b ON b.v = x.u WHERE a.owner <> b.owner GROUP BY ALL")(
    lambda s, d: distribution.boundary_pairs(main_graph(s, d), distribution.owners(main_graph(s, d), N))
)


@query("exchange_messages", sql.graph(MAIN, OWNERS, START, _GHOSTS, _CHANGED) + "SELECT g.owner, c.v, c.part FROM changed c JOIN ghosts g ON g.u = c.v")
def exchange_messages(s: SparkSession, d: str) -> DataFrame:
    _, _, subs, changed = _setup(s, d)
    return distribution.route(changed, subs)


@query("exchange_matrix", sql.graph(MAIN, OWNERS, START, _GHOSTS, _CHANGED) + "SELECT o.owner AS source, g.owner AS target, count(*) AS messages, count(*) * 2 AS values FROM changed c JOIN ghosts g ON g.u = c.v JOIN owners o ON o.v = c.v GROUP BY ALL")
def exchange_matrix(s: SparkSession, d: str) -> DataFrame:
    _, own, subs, changed = _setup(s, d)
    return distribution.exchange_matrix(changed, own, subs)


# --- starts ----------------------------------------------------------------------------------

query("init_random", sql.graph(MAIN, sql.random_parts(P, 42)) + "SELECT * FROM parts")(lambda s, d: initial.start(main_graph(s, d), P, "random"))
query("init_vertex_block", sql.graph(MAIN, sql.block(P, "vertex")) + "SELECT * FROM parts")(lambda s, d: initial.start(main_graph(s, d), P, "vertex_block"))
query("init_edge_block", sql.graph(MAIN, sql.block(P, "edge")) + "SELECT * FROM parts")(lambda s, d: initial.start(main_graph(s, d), P, "edge_block"))
query("init_roots", sql.graph(MAIN, *sql.grown(P, 42, 0)[0]) + "SELECT v, part FROM roots")(lambda s, d: initial.draw_roots(main_graph(s, d), P, 42))
query("init_grow", sql.graph(MAIN, *sql.grown(P, 42, 10)[0]) + "SELECT * FROM parts")(lambda s, d: initial.grow(main_graph(s, d).stored(), P, 42))
query("init_grow_capped", sql.graph("fk_tree", *sql.grown(P, 42, 2)[0]) + "SELECT * FROM parts")(lambda s, d: initial.grow(builders.graph(s, d, "fk_tree").stored(), P, 42, max_sweeps=2))
query("init_bfs_grow", sql.graph(MAIN, *sql.grown(P, 42, 10, True)[0]) + "SELECT * FROM parts")(lambda s, d: initial.bfs(main_graph(s, d).stored(), P, 42))
query("init_grow_majority", sql.graph(MAIN, *sql.grown(P, 42, 10, "majority")[0]) + "SELECT * FROM parts")(lambda s, d: initial.start(main_graph(s, d).stored(), P, "grow_majority", 42))
query("init_lp_3", sql.graph(MAIN, *sql.majority(3)) + f"SELECT v, ({sql.h('part', 42)} % {P})::INT AS part FROM lab3")(lambda s, d: initial.label_prop(main_graph(s, d).stored(), P, 42, 3))

# --- sweeps ----------------------------------------------------------------------------------

CFG = PartitionConfig(n_workers=N)


_NUMBERED = "SELECT o_orderkey % 46 AS t, count(*) AS orders FROM orders GROUP BY ALL"


def _numbered(s: SparkSession, d: str) -> DataFrame:
    """The orders as the work of 46 sweeps, dealt by key: ``(t, orders)``."""
    return builders.table(s, d, "orders").groupBy((F.col("o_orderkey") % 46).alias("t")).agg(F.count("*").alias("orders"))


@query("mult_schedule", f"SELECT t, orders, 16 * ((1.0::DOUBLE - 0.25::DOUBLE) * (t / 45) + 0.25::DOUBLE) AS mult FROM ({_NUMBERED})")
def mult_schedule(s: SparkSession, d: str) -> DataFrame:
    return _numbered(s, d).select("t", "orders", PartitionConfig(n_workers=16).mult(F.col("t")).alias("mult"))


@query("mult_variants", f"SELECT x, y, t, orders, 16 * ((x - y) * (t / 45) + y) AS mult FROM (VALUES (1.0::DOUBLE, 0.25::DOUBLE), (0.5, 0.5), (0.25, 1.0), (2.0, 0.0)) v(x, y), ({_NUMBERED}) WHERE t < 45 AND t % 5 = 0")
def mult_variants(s: SparkSession, d: str) -> DataFrame:
    t = _numbered(s, d).where("t < 45 and t % 5 = 0")
    made = [F.struct(F.lit(x).alias("x"), F.lit(y).alias("y"), "t", "orders", PartitionConfig(n_workers=16, x=x, y=y).mult(F.col("t")).alias("mult")) for x, y in ((1.0, 0.25), (0.5, 0.5), (0.25, 1.0), (2.0, 0.0))]
    return t.select(F.explode(F.array(*made)).alias("r")).select("r.*")


def _sweep_sql(kinds: list[str], select: str, quota: str = "apportion", by: str = "degree") -> str:
    return sql.graph(MAIN, START, OWNERS, *sql.sweeps(kinds, P, N, sql.factors(len(kinds)), quota=quota, by=by)) + select


def _sweeps(s: SparkSession, d: str, kinds: list[str], **options) -> _Run:
    g = main_graph(s, d)
    run = _Run(g, P, PartitionConfig(**{"n_workers": N, **options}), start(g))
    for t, kind in enumerate(kinds):
        run.one(kind, t)
    return run


def _ramp(s: SparkSession, d: str) -> DataFrame:
    run = _sweeps(s, d, ["edge_balance"] * 3)
    return s.createDataFrame([(k, h["re"], h["rc"]) for k, h in enumerate([*run.history, {"re": run.re, "rc": run.rc}])], "sweep int, re double, rc double")


for _name, _kinds in {
    "balance_sweep1": ["vertex_balance"],
    "balance_sweep3": ["vertex_balance"] * 3,
    "refine_sweep1": ["vertex_refine"],
    "refine_sweep3": ["vertex_refine"] * 3,
    "balance_then_refine": ["vertex_balance", "vertex_balance", "vertex_refine"],
    "edge_balance_sweep1": ["edge_balance"],
    "edge_refine_sweep1": ["edge_refine"],
    "edge_balance_sweep3": ["edge_balance"] * 3,
    "edge_balance_then_refine": ["edge_balance", "edge_balance", "edge_refine"],
}.items():
    query(_name, _sweep_sql(_kinds, f"SELECT * FROM parts{len(_kinds)}"))(lambda s, d, k=_kinds: _sweeps(s, d, k).parts)
query("balance_sweep_count", _sweep_sql(["vertex_balance"] * 2, "SELECT * FROM parts2", by="count"))(lambda s, d: _sweeps(s, d, ["vertex_balance"] * 2, vertex_score="count").parts)
query("edge_bias_ramp", _sweep_sql(["edge_balance"] * 3, " UNION ALL ".join(f"SELECT {k} AS sweep, re, rc FROM bias{k}" for k in range(4))))(lambda s, d: _ramp(s, d))
query("strict_quota_sweep1", _sweep_sql(["vertex_refine"], "SELECT * FROM parts1", "strict"))(lambda s, d: _sweeps(s, d, ["vertex_refine"], quota="strict").parts)
query("delta_sweep3", _sweep_sql(["vertex_balance", "vertex_refine", "vertex_refine"], "SELECT * FROM parts3"))(lambda s, d: _sweeps(s, d, ["vertex_balance", "vertex_refine", "vertex_refine"], executor="delta").parts)
query("hist_full", _sweep_sql(["vertex_refine"], "SELECT * FROM hist0"))(lambda s, d: sw.histogram(main_graph(s, d), start(main_graph(s, d))))
query("hist_delta", _sweep_sql(["vertex_balance", "vertex_refine"], "SELECT * FROM hist1"))(lambda s, d: _sweeps(s, d, ["vertex_balance"], executor="delta").histogram())


@query("part_state", _sweep_sql(["vertex_balance"], "SELECT part, sv, se, sc, wt, room FROM (SELECT part, sv, 0::BIGINT AS se, 0::BIGINT AS sc, wt, room FROM state0)"))
def part_state(s: SparkSession, d: str) -> DataFrame:
    g = main_graph(s, d)
    n = g.vertices.count()
    stage = sw.Stage("vertex_balance", 0, 0, metrics.max_vertices(n, P, 0.1), 0.0)
    return s.createDataFrame(sw.part_state(sw.sizes(g.vertices, start(g), P), stage, CFG), "part int, sv bigint, se bigint, sc bigint, wt double, room bigint")


_GAIN = """, own AS (SELECT h.v, h.n FROM hist0 h JOIN parts q ON q.v = h.v AND q.part = h.part)
SELECT h.v, q.part AS old, h.part AS new, -coalesce(o.n, 0) AS old_edges, h.n AS new_edges, 2 * coalesce(o.n, 0) - d.deg AS old_cut, d.deg - 2 * h.n AS new_cut, coalesce(o.n, 0) - h.n AS cut
FROM hist0 h JOIN parts q ON q.v = h.v AND q.part <> h.part JOIN vertices d ON d.v = h.v LEFT JOIN own o ON o.v = h.v"""
query("move_gain", sql.graph(MAIN, START, OWNERS, *sql.sweeps(["vertex_refine"], P, N, [0.25])).rstrip() + _GAIN)(lambda s, d: sw.move_gain(sw.histogram(main_graph(s, d), start(main_graph(s, d))), main_graph(s, d).vertices, start(main_graph(s, d))))

# --- whole partitions --------------------------------------------------------------------------

#: The schedule is the configuration's own: 3 rounds of 5 + 10 sweeps a stage.
WHOLE = {"n_workers": N}


def _partitions() -> dict[str, Callable[[SparkSession, str], PartitionResult]]:
    on = lambda name: lambda s, d: builders.graph(s, d, name)
    g = on("cust_supp")
    return {
        "partition_mm": lambda s, d: partition(g(s, d), P, executor="worker", **WHOLE),
        "partition_mm_doc_lines": lambda s, d: partition(on("doc_lines")(s, d), P, executor="worker", **WHOLE),
        "partition_mm_fk_tree": lambda s, d: partition(on("fk_tree")(s, d), P, executor="worker", **WHOLE),
        "partition_mm_chain": lambda s, d: partition(on("order_chain")(s, d), P, executor="worker", init="vertex_block", **WHOLE),
        "partition_single": lambda s, d: partition(g(s, d), P, executor="worker", mode="vertex", rat_v=0.03, **WHOLE),
        "partition_two_constraint": lambda s, d: partition(g(s, d), P, executor="worker", mode="vertex_edge", **WHOLE),
        "partition_set": lambda s, d: partition(g(s, d), P, executor="set", mode="vertex", **WHOLE),
        "partition_delta": lambda s, d: partition(g(s, d), P, executor="delta", mode="vertex", **WHOLE),
        "partition_block_balance": lambda s, d: partition(g(s, d), P, executor="worker", mode="vertex", init="vertex_block", stages=("vertex_balance",), **WHOLE),
        "partition_chain": lambda s, d: partition(on("order_chain")(s, d), P, executor="worker", mode="vertex", init="vertex_block", **WHOLE),
        "baseline_single_node": lambda s, d: baselines.single_node(g(s, d), P, **{**WHOLE, "n_workers": 1}),
    }


_DONE: dict[tuple[str, str, str], PartitionResult] = {}


def partitioned(s: SparkSession, d: str, name: str) -> PartitionResult:
    """The named partition, made once in a session: its measures, facts and history are read from the same written parts."""
    key = (s.sparkContext.applicationId, d, name)
    if key not in _DONE:
        _DONE[key] = _partitions()[name](s, d)
    return _DONE[key]


def _facts(r: PartitionResult) -> DataFrame:
    """One row of truths: assigned, in range, the identities of sizes and cuts, within the limits, and no part cut more than with random parts."""
    g, parts, p, cfg = r.graph, r.parts, r.p, r.config
    s = metrics.part_sizes(g, parts, p)
    sums = s.agg(F.sum("vertices").alias("v"), F.sum("internal").alias("i"), F.sum("incident").alias("d"), F.sum("cut").alias("c"), F.min((F.col("incident") == 2 * F.col("internal") + F.col("cut")).cast("int")).alias("e"))
    valid = metrics.validate(g, parts, p)
    n, m = g.sizes()
    held = metrics.limits(g, parts, p, cfg.rat_v, cfg.rat_e)
    random = metrics.quality(g, baselines.random(g, p, SEED), p).select(F.col("max_cut").alias("random_cut"))
    return sums.crossJoin(valid).crossJoin(held).crossJoin(random).select(
        (F.col("missing") + F.col("strangers") + F.col("repeated") + F.col("outside") == 0).alias("valid"),
        (F.col("v") == n).alias("all_vertices"),
        (F.col("i") + F.col("c") / 2 == m).alias("all_edges"),
        (F.col("d") == 2 * m).alias("all_ends"),
        (F.col("e") == 1).alias("ends_add_up"),
        (F.col("max_vertices") <= F.col("vertex_limit")).alias("vertex_ok"),
        ((F.col("max_edges") <= F.col("edge_limit")) | F.lit(cfg.mode == "vertex")).alias("edge_ok"),
        ((F.col("max_cut") <= F.col("random_cut")) | F.lit(cfg.mode != "multi")).alias("max_cut_not_above_random"),
    )  # one row each


#: Edges are limited where the mode has two constraints, the largest cut where it has two objectives; true elsewhere.
_TRUE = "SELECT true AS valid, true AS all_vertices, true AS all_edges, true AS all_ends, true AS ends_add_up, true AS vertex_ok, true AS edge_ok, true AS max_cut_not_above_random"

for _name in _partitions():
    query(_name)(lambda s, d, n=_name: partitioned(s, d, n).quality())
    query(f"{_name}_facts", _TRUE)(lambda s, d, n=_name: _facts(partitioned(s, d, n)))

query("partition_history")(lambda s, d: partitioned(s, d, "partition_mm").history_frame())
_LEVELS: dict[tuple[str, str, str], DataFrame] = {}


def _multilevel(s: SparkSession, d: str, name: str) -> tuple[Graph, DataFrame]:
    """The key tree and its parts by the named coarsening, made once in a session."""
    g, key = builders.graph(s, d, "fk_tree"), (s.sparkContext.applicationId, d, name)
    if key not in _LEVELS:
        _LEVELS[key] = baselines.multilevel(g, P, name, levels=4)
    return g, _LEVELS[key]


def _multilevel_facts(s: SparkSession, d: str, name: str) -> DataFrame:
    """Every vertex in one part in range, no part over 3 %, and under half of the cut of random parts."""
    g, parts = _multilevel(s, d, name)
    cut = lambda q, label: metrics.quality(g, q, P).select(F.col("cut").alias(label))
    row = metrics.validate(g, parts, P).crossJoin(metrics.limits(g, parts, P, 0.03)).crossJoin(cut(parts, "cut")).crossJoin(cut(start(g), "random_cut"))
    return row.select(
        (F.col("missing") + F.col("strangers") + F.col("repeated") + F.col("outside") == 0).alias("valid"),
        (F.col("max_vertices") <= F.col("vertex_limit")).alias("vertex_ok"),
        (2 * F.col("cut") < F.col("random_cut")).alias("far_below_random"),
    )  # one row each


for _name in ("matching", "clusters"):
    query(f"multilevel_{_name}")(lambda s, d, n=_name: metrics.quality(*_multilevel(s, d, n), P))
    query(f"multilevel_{_name}_facts", "SELECT true AS valid, true AS vertex_ok, true AS far_below_random")(lambda s, d, n=_name: _multilevel_facts(s, d, n))


@query("matching_facts", "SELECT true AS disjoint, true AS along_edges, true AS some")
def matching_facts(s: SparkSession, d: str) -> DataFrame:
    g = builders.graph(s, d, "fk_tree").stored()
    pairs = baselines.matching(g)
    ends = pairs.select(F.explode(F.array("v", "mate")).alias("x")).groupBy("x").count()
    twice = ends.where("count > 1").count()
    stray = pairs.select(F.col("v").alias("src"), F.col("mate").alias("dst")).join(g.edges, ["src", "dst"], "left_anti").count()
    return s.createDataFrame([(twice == 0, stray == 0, pairs.count() > 0)], "disjoint boolean, along_edges boolean, some boolean")


@query("contract_facts", sql.graph(MAIN, START) + "SELECT part::BIGINT AS v, count(*) AS w FROM parts GROUP BY part")
def contract_facts(s: SparkSession, d: str) -> DataFrame:
    g = main_graph(s, d)
    return baselines.contract(g, start(g).select("v", F.col("part").cast("bigint").alias("coarse"))).vertices.select("v", "w")


# --- measures ------------------------------------------------------------------------------------

_SIZED = sql.graph(MAIN, START, sql.sizes(P))
query("part_vertices", _SIZED + "SELECT part, vertices FROM sized")(lambda s, d: metrics.part_vertices(start(main_graph(s, d)), P))
query("part_edges", _SIZED + "SELECT part, internal AS edges FROM sized")(lambda s, d: metrics.part_edges(main_graph(s, d), start(main_graph(s, d)), P))
query("part_edges_incident", _SIZED + "SELECT part, incident AS edges FROM sized")(lambda s, d: metrics.part_edges(main_graph(s, d), start(main_graph(s, d)), P, "incident"))
query("part_cut", _SIZED + "SELECT part, cut FROM sized")(lambda s, d: metrics.part_cut(main_graph(s, d), start(main_graph(s, d)), P))
query("cut_edges", _SIZED + "SELECT src, dst, s AS part_s, d AS part_d FROM ep WHERE s <> d")(lambda s, d: metrics.cut_edges(main_graph(s, d), start(main_graph(s, d))))
query("objectives", _SIZED + "SELECT (sum(cut) // 2)::BIGINT AS cut, max(cut) AS max_cut FROM sized")(lambda s, d: metrics.quality(main_graph(s, d), start(main_graph(s, d)), P).select("cut", "max_cut"))
for _name, _label, _make in (
    ("quality_random", START, lambda g: start(g)),
    ("quality_vertex_block", sql.block(P, "vertex"), lambda g: baselines.vertex_block(g, P)),
    ("quality_edge_block", sql.block(P, "edge"), lambda g: baselines.edge_block(g, P)),
):
    query(_name, sql.graph(MAIN, _label, sql.sizes(P)) + sql.quality(P))(lambda s, d, f=_make: metrics.quality(main_graph(s, d), f(main_graph(s, d)), P))
query("validate_parts", sql.graph(MAIN) + "SELECT 0::BIGINT AS missing, 0::BIGINT AS strangers, 0::BIGINT AS repeated, 0::BIGINT AS outside")(lambda s, d: metrics.validate(main_graph(s, d), start(main_graph(s, d)), P))
query("quotient_matrix", _SIZED + "SELECT least(s, d) AS a, greatest(s, d) AS b, count(*) AS edges FROM ep GROUP BY ALL")(lambda s, d: metrics.quotient(main_graph(s, d), start(main_graph(s, d))))
query("communication", _SIZED + "SELECT (SELECT count(*) FROM (SELECT DISTINCT src, d FROM ep WHERE s <> d UNION SELECT DISTINCT dst, s FROM ep WHERE s <> d)) AS messages, (SELECT count(DISTINCT v) FROM (SELECT src AS v FROM ep WHERE s <> d UNION ALL SELECT dst FROM ep WHERE s <> d)) AS senders, (SELECT count(*) FROM ep WHERE s <> d) AS cut")(
    lambda s, d: metrics.communication(main_graph(s, d), start(main_graph(s, d)))
)


def _cut_of(p: int, label: str, k: int) -> list[str]:
    return [label.replace("parts AS", f"parts{k} AS"), f"cut{k} AS (SELECT count(*) AS c FROM edges e JOIN parts{k} a ON a.v = e.src JOIN parts{k} b ON b.v = e.dst WHERE a.part <> b.part)"]


def _perf_sql() -> str:
    ctes, rows, k = [], [], 0
    for p in (2, 4, 8):
        for method, label in (("random", sql.random_parts(p, SEED)), ("vertex_block", sql.block(p, "vertex")), ("edge_block", sql.block(p, "edge"))):
            ctes += _cut_of(p, label, k)
            rows.append(f"SELECT {p} AS test, '{method}' AS method, c::DOUBLE AS x FROM cut{k}")
            k += 1
    return sql.graph(MAIN, *ctes, f"runs AS ({' UNION ALL '.join(rows)})") + "SELECT method, round(exp(avg(ln(x / best))), 6) AS ratio, count(*) AS tests FROM (SELECT *, min(x) OVER (PARTITION BY test) AS best FROM runs) GROUP BY method"


@query("perf_ratio", _perf_sql())
def perf_ratio(s: SparkSession, d: str) -> DataFrame:
    g, runs = main_graph(s, d).stored(), None
    for p in (2, 4, 8):
        for method, make in (("random", lambda g, p: start(g, p)), ("vertex_block", baselines.vertex_block), ("edge_block", baselines.edge_block)):
            one = metrics.cut_edges(g, make(g, p)).agg(F.count("*").alias("cut")).select(F.lit(p).alias("test"), F.lit(method).alias("method"), "cut")
            runs = one if runs is None else runs.unionByName(one)
    return metrics.performance_ratio(runs, "cut")


_RUNS = "SELECT l_returnflag AS graph, l_linestatus AS method, l_linenumber AS workers, sum(l_quantity) AS seconds FROM lineitem GROUP BY ALL"


def _measured(s: SparkSession, d: str) -> DataFrame:
    """Runs as ``lineitem`` gives them, ``(graph, method, workers, seconds)``: return flag, line status, line number, sum of quantities."""
    return builders.table(s, d, "lineitem").groupBy(F.col("l_returnflag").alias("graph"), F.col("l_linestatus").alias("method"), F.col("l_linenumber").alias("workers")).agg(F.sum("l_quantity").alias("seconds"))


@query("speedup", f"SELECT graph, method, workers, seconds, round(base / seconds, 6) AS speedup, round(base * least / (seconds * workers), 6) AS efficiency FROM (SELECT *, arg_min(seconds, workers) OVER w AS base, min(workers) OVER w AS least FROM ({_RUNS}) WINDOW w AS (PARTITION BY graph, method))")
def speedup(s: SparkSession, d: str) -> DataFrame:
    return metrics.speedups(_measured(s, d))


_WHOLE = "SELECT l_returnflag AS graph, sum(l_quantity) AS single FROM lineitem GROUP BY ALL"


@query("absolute_speedup", f"SELECT graph, workers, r.seconds, round(single / r.seconds, 6) AS absolute_speedup, round(workers / (single / r.seconds), 6) AS per_core_ratio FROM (SELECT graph, workers, sum(seconds) AS seconds FROM ({_RUNS}) GROUP BY ALL) r JOIN ({_WHOLE}) x USING (graph)")
def absolute_speedup(s: SparkSession, d: str) -> DataFrame:
    """The runs of all methods against one that does the whole work."""
    runs = _measured(s, d).groupBy("graph", "workers").agg(F.sum("seconds").alias("seconds"))
    return metrics.absolute_speedups(runs, runs.groupBy("graph").agg(F.sum("seconds").alias("single")))


@query("random_cut_expectation", sql.graph(MAIN) + "SELECT p::INT AS p, (p - 1) / p AS expected, m * ((p - 1) / p) AS edges FROM (VALUES (2), (4), (8), (16)) r(p), (SELECT count(*) AS m FROM edges)")
def random_cut_expectation(s: SparkSession, d: str) -> DataFrame:
    """The share of edges that random parts cut, and how many of the graph's that is."""
    shares = F.array(*(F.struct(F.lit(p).alias("p"), F.lit(metrics.random_cut_expectation(p)).alias("expected")) for p in (2, 4, 8, 16)))
    return main_graph(s, d).edges.agg(F.count("*").alias("m")).select("m", F.explode(shares).alias("r")).select("r.p", "r.expected", (F.col("m") * F.col("r.expected")).alias("edges"))


# --- analytics -------------------------------------------------------------------------------------

_SOURCES = f"SELECT v AS source FROM vertices ORDER BY {sql.h('v', 13)}, v LIMIT 20"
query("bfs_levels", sql.graph(MAIN, *sql.levels("SELECT min(v) AS source FROM vertices", 10)) + "SELECT * FROM bfs")(lambda s, d: analytics.bfs_levels(main_graph(s, d).stored().arcs, main_graph(s, d).vertices.agg(F.min("v").alias("source"))))
query("harmonic", sql.graph(MAIN, *sql.levels(_SOURCES, 10)) + "SELECT source AS v, round(sum(CASE WHEN dist > 0 THEN 1 / dist ELSE 0 END), 6) AS harmonic FROM bfs GROUP BY source")(lambda s, d: analytics.harmonic(main_graph(s, d).stored(), 20))
query("kcore_approx", sql.graph(MAIN, *sql.cores([1, 2, 4, 8, 16, 32, 64, 128, 256, 512], 2)) + "SELECT * FROM cored")(lambda s, d: analytics.kcore(main_graph(s, d).stored(), [1, 2, 4, 8, 16, 32, 64, 128, 256, 512], max_rounds=2))
query("harmonic_100", sql.graph(MAIN, *sql.levels(_SOURCES.replace("LIMIT 20", "LIMIT 100"), 10)) + "SELECT source AS v, round(sum(CASE WHEN dist > 0 THEN 1 / dist ELSE 0 END), 6) AS harmonic FROM bfs GROUP BY source")(lambda s, d: analytics.harmonic(main_graph(s, d).stored(), 100))
# Peeled to the fixed point, over doubling thresholds up to the largest degree; the SQL peels 12 rounds a threshold, which is enough at sf0.01.
query("kcore_whole", sql.graph(MAIN, *sql.cores([1 << k for k in range(12)], 12)) + "SELECT * FROM cored")(lambda s, d: analytics.kcore(main_graph(s, d).stored()))
query("lp_communities", sql.graph("doc_lines", *sql.majority(3)) + "SELECT v, part AS community FROM lab3")(lambda s, d: analytics.label_propagation(builders.graph(s, d, "doc_lines").stored(), 3))
query("lp_communities_whole", sql.graph("doc_lines_whole", *sql.majority(3)) + "SELECT v, part AS community FROM lab3")(lambda s, d: analytics.label_propagation(builders.graph(s, d, "doc_lines_whole").stored(), 3))
query("pagerank", sql.graph(MAIN, *sql.ranks(3)) + "SELECT v, round(rank, 9) AS rank FROM r3")(lambda s, d: analytics.pagerank(main_graph(s, d).stored(), 3))
query("wcc", "SELECT o_orderkey AS v, min(o_orderkey) OVER (PARTITION BY o_custkey) AS component FROM orders QUALIFY count(*) OVER (PARTITION BY o_custkey) > 1")(lambda s, d: analytics.wcc(builders.graph(s, d, "order_chain").stored()))
query("diameter", sql.graph(MAIN, *sql.farthest(10, 8)) + f"SELECT greatest({', '.join(f'(SELECT max(dist) FROM far{k})' for k in range(10))}) AS diameter")(lambda s, d: s.createDataFrame([(analytics.approx_diameter(main_graph(s, d).stored()),)], "diameter int"))
_USER = "ua AS MATERIALIZED (SELECT DISTINCT user_id AS src, nxt AS dst FROM (SELECT user_id, lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS nxt FROM events) WHERE nxt IS NOT NULL AND user_id <> nxt)"
query("g_user_arcs", f"WITH {_USER} SELECT src, dst FROM ua")(builders.user_arcs)
query(
    "largest_scc",
    f"""WITH RECURSIVE {_USER},
top AS (SELECT v FROM (SELECT src AS v, count(*) AS o FROM ua GROUP BY src) JOIN (SELECT dst AS v, count(*) AS i FROM ua GROUP BY dst) USING (v) ORDER BY o * i DESC, v LIMIT 1),
fwd AS (SELECT v FROM top UNION SELECT u.dst FROM fwd JOIN ua u ON u.src = fwd.v), bwd AS (SELECT v FROM top UNION SELECT u.src FROM bwd JOIN ua u ON u.dst = bwd.v)
SELECT v FROM fwd INTERSECT SELECT v FROM bwd""",
)(lambda s, d: analytics.largest_scc(builders.user_arcs(s, d)))

# --- sparse matrix times vector ----------------------------------------------------------------------

_X = f"x0 AS MATERIALIZED (SELECT v AS i, ({sql.h('v', 3)} % 10)::DOUBLE AS x FROM vertices)"


def _product(k: int) -> str:
    return f"x{k + 1} AS MATERIALIZED (SELECT a.v AS i, sum(q.x) AS x FROM arcs a JOIN x{k} q ON q.i = a.u GROUP BY a.v)"


def _vector(g: Graph) -> DataFrame:
    return g.vertices.select(F.col("v").alias("i"), (portable_hash("v", 3) % 10).cast("double").alias("x"))


query("spmv_1", sql.graph(MAIN, _X, _product(0)) + "SELECT * FROM x1")(lambda s, d: spmv.multiply(spmv.symmetric(main_graph(s, d)), _vector(main_graph(s, d))))
query("spmv_power3", sql.graph(MAIN, _X, *(_product(k) for k in range(3))) + "SELECT * FROM x3")(lambda s, d: spmv.power(spmv.symmetric(main_graph(s, d).stored()), _vector(main_graph(s, d)), 3, normalise=False))
_LAID = "laid AS MATERIALIZED (SELECT a.v AS i, a.u AS j, {process} AS process, p.part AS part_i, q.part AS part_j FROM arcs a JOIN parts p ON p.v = a.v JOIN parts q ON q.v = a.u)"
_ONE, _TWO = _LAID.format(process="p.part"), _LAID.format(process="(p.part % 2 + 2 * (q.part // 2))::INT")
_COMM = """, ex AS (SELECT DISTINCT process, j, part_j AS other FROM laid WHERE part_j <> process), fo AS (SELECT DISTINCT process, i, part_i AS other FROM laid WHERE part_i <> process)
SELECT (SELECT count(*) FROM ex) AS expand, (SELECT count(*) FROM fo) AS fold, coalesce((SELECT max(k) FROM (SELECT count(*) AS k FROM (SELECT process, other FROM ex UNION SELECT process, other FROM fo) GROUP BY process)), 0) AS max_partners,
  (SELECT count(*) FROM laid) AS nonzeros, (SELECT max(z) FROM (SELECT count(*) AS z FROM laid GROUP BY process)) AS max_nonzeros"""
_laid1 = lambda s, d: spmv.layout_1d(spmv.symmetric(main_graph(s, d)), start(main_graph(s, d)))
_laid2 = lambda s, d: spmv.layout_2d(spmv.symmetric(main_graph(s, d)), start(main_graph(s, d)), *spmv.grid(P))
query("layout_1d", sql.graph(MAIN, START, _ONE) + "SELECT i, j, process FROM laid")(lambda s, d: _laid1(s, d).select("i", "j", "process"))
query("layout_2d", sql.graph(MAIN, START, _TWO) + "SELECT i, j, process FROM laid")(lambda s, d: _laid2(s, d).select("i", "j", "process"))
query("comm_1d", sql.graph(MAIN, START, _ONE).rstrip() + _COMM)(lambda s, d: spmv.comm_stats(_laid1(s, d)))
query("comm_2d", sql.graph(MAIN, START, _TWO).rstrip() + _COMM)(lambda s, d: spmv.comm_stats(_laid2(s, d)))

# --- generators --------------------------------------------------------------------------------------

_edges = lambda df: df.select("src", "dst")


def _counters(s: SparkSession, d: str) -> DataFrame:
    """The orders' keys, which the generators draw by."""
    return builders.table(s, d, "orders").select(F.col("o_orderkey").alias("id"))


def _points(s: SparkSession, d: str) -> DataFrame:
    """The customers' keys as the points of a grid."""
    return builders.table(s, d, "customer").select(F.col("c_custkey").alias("id"))


def _top(s: SparkSession, d: str) -> int:
    return _counters(s, d).agg(F.coalesce(F.max("id"), F.lit(0))).first()[0]


query("gen_rmat", sql.rmat(16))(lambda s, d: _edges(generators.rmat(s, 16, 8, counters=_counters(s, d))))
query("gen_er", sql.erdos_renyi())(lambda s, d: _edges(generators.erdos_renyi(s, max(_counters(s, d).count() // 8, 1), 8, counters=_counters(s, d))))
query("gen_hd", sql.high_diameter(8))(lambda s, d: _edges(generators.high_diameter(s, _top(s, d) // 8 + 1, 8, counters=_counters(s, d))))
query("gen_mesh", sql.mesh3d(7, 6))(lambda s, d: _edges(generators.mesh3d(s, 7, 6, _points(s, d).agg(F.coalesce(F.max("id"), F.lit(0))).first()[0] // 42 + 1, _points(s, d))))
query("gen_planted", sql.planted(50, 6, 1))(lambda s, d: _edges(generators.planted(s, _top(s, d) // 350 + 1, 50, 6, 1, counters=_counters(s, d))))

# --- what a user needs around them --------------------------------------------------------------------


@query("asof_event", "SELECT p.event_id, v.event_id AS before FROM events p ASOF JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY ALL) v ON p.user_id = v.user_id AND p.ts >= v.ts WHERE p.event_type = 'purchase'")
def asof_event(s: SparkSession, d: str) -> DataFrame:
    """The last view at or before each purchase of the same user, by one sort of a user's events."""
    e = builders.table(s, d, "events").where(F.col("event_type").isin("view", "purchase")).select("user_id", "ts", "event_id", (F.col("event_type") == "purchase").alias("wanted"))
    line = Window.partitionBy("user_id").orderBy("ts", "wanted").rowsBetween(Window.unboundedPreceding, 0)
    last = e.withColumn("last", F.max(F.when(~F.col("wanted"), F.struct("ts", "event_id"))).over(line))
    return last.where("wanted and last is not null").select("event_id", F.col("last.event_id").alias("before"))


@query("range_coactivity", "SELECT a.user_id AS a, b.user_id AS b, count(*) AS n FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id < b.user_id AND abs(epoch(a.ts) - epoch(b.ts)) <= 60 GROUP BY ALL")
def range_coactivity(s: SparkSession, d: str) -> DataFrame:
    """Users active within a minute of each other: a range join by buckets of its width."""
    e = builders.table(s, d, "events").select("user_id", "event_type", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("second"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t")).withColumn("bucket", F.floor(F.col("second") / 60))
    other = e.select("event_type", F.col("user_id").alias("b"), F.col("t").alias("t_b"), F.explode(F.array(F.col("bucket") - 1, F.col("bucket"), F.col("bucket") + 1)).alias("bucket"))
    near = e.join(other, ["event_type", "bucket"]).where((F.col("user_id") < F.col("b")) & (F.abs(F.col("t") - F.col("t_b")) <= 60_000_000))
    return near.groupBy(F.col("user_id").alias("a"), "b").agg(F.count("*").alias("n"))


query("anti_unassigned", sql.graph(MAIN, *sql.grown(P, 42, 1)[0]) + "SELECT v FROM vertices WHERE v NOT IN (SELECT v FROM all1)")(lambda s, d: main_graph(s, d).vertices.select("v").join(initial._spread(main_graph(s, d).stored(), initial.draw_roots(main_graph(s, d), P, 42), 42, 1, initial._any_part), "v", "left_anti"))
query("outer_compare", sql.graph(MAIN, START, sql.block(P, "vertex", "other")) + "SELECT a.part AS first, b.part AS second, count(*) AS n FROM parts a FULL JOIN other b USING (v) GROUP BY ALL")(
    lambda s, d: start(main_graph(s, d)).withColumnRenamed("part", "first").join(baselines.vertex_block(main_graph(s, d), P).withColumnRenamed("part", "second"), "v", "full").groupBy("first", "second").agg(F.count("*").alias("n"))
)
query("setops_moved", sql.graph(MAIN, START, sql.block(P, "vertex", "other")) + "SELECT v, part FROM parts EXCEPT SELECT v, part FROM other")(lambda s, d: start(main_graph(s, d)).exceptAll(baselines.vertex_block(main_graph(s, d), P)))
query("rollup_degree", sql.graph(MAIN, START) + "SELECT part, (v % 2)::INT AS kind, count(*) AS n, sum(deg)::BIGINT AS deg FROM parts JOIN vertices USING (v) GROUP BY ROLLUP (part, kind)")(
    lambda s, d: start(main_graph(s, d)).join(main_graph(s, d).vertices, "v").rollup("part", (F.col("v") % 2).cast("int").alias("kind")).agg(F.count("*").alias("n"), F.sum("deg").alias("deg"))
)
query("pivot_parts", _SIZED + "SELECT s, count(*) FILTER (d = 0) AS p0, count(*) FILTER (d = 1) AS p1, count(*) FILTER (d = 2) AS p2, count(*) FILTER (d = 3) AS p3 FROM ep GROUP BY s")(
    lambda s, d: metrics.edge_parts(main_graph(s, d), start(main_graph(s, d))).groupBy(F.col("part_s").alias("s")).pivot("part_d", [0, 1, 2, 3]).count().na.fill(0).withColumnsRenamed({str(k): f"p{k}" for k in range(4)})
)
query("cube_cut_by_nation", """WITH e AS (SELECT c_nationkey AS a, s_nationkey AS b FROM (SELECT DISTINCT o_custkey, l_suppkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey) JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey)
SELECT a, b, count(*) AS edges FROM e GROUP BY CUBE (a, b)""")(
    lambda s, d: builders.table(s, d, "lineitem").select("l_orderkey", "l_suppkey").join(builders.table(s, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).select("o_custkey", "l_suppkey").distinct()
    .join(builders.table(s, d, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").alias("a")), "o_custkey").join(builders.table(s, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").alias("b")), "l_suppkey")
    .cube("a", "b").agg(F.count("*").alias("edges"))
)
query("json_props", "SELECT event_id, (props->>'k')::INT AS k FROM events WHERE (props->>'k')::INT >= 50")(lambda s, d: builders.table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k")).where("k >= 50"))
query("array_dot", "SELECT vec_id, round(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[]), 5) AS norm FROM embeddings")(
    lambda s, d: builders.table(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x), 5).alias("norm"))
)
query("udtf_grid", sql.graph(MAIN, sql.random_parts(6, SEED)) + "SELECT part, (part % 2)::INT AS row, (part // 2)::INT AS col, count(*) AS vertices FROM parts GROUP BY part")(
    lambda s, d: udx.GridCells(F.lit(6), F.lit(2)).join(start(main_graph(s, d), 6).groupBy("part").agg(F.count("*").alias("vertices")), "part").select("part", "row", "col", "vertices")
)
query("udaf_gini", _SIZED + f"SELECT round(sum((2 * k - {P} - 1) * vertices) / ({P} * sum(vertices)), 9) AS gini FROM (SELECT vertices, row_number() OVER (ORDER BY vertices) AS k FROM sized)")(
    lambda s, d: metrics.part_vertices(start(main_graph(s, d)), P).agg(udx.gini()(F.col("vertices")).alias("g")).select(F.round("g", 9).alias("gini"))
)
query("degree_percentiles", sql.graph(MAIN) + "SELECT v, deg, round((rank() OVER (ORDER BY deg) - 1) / (SELECT count(*) - 1 FROM vertices), 9) AS share FROM vertices")(
    lambda s, d: main_graph(s, d).vertices.join(degree_histogram(main_graph(s, d)).withColumn("below", F.coalesce(F.sum("n").over(Window.orderBy("deg").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))), "deg")
    .crossJoin(main_graph(s, d).vertices.agg((F.count("*") - 1).alias("rest"))).select("v", "deg", F.round(F.col("below") / F.col("rest"), 9).alias("share"))
)
_LINE = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"


@query("window_chain", f"""SELECT o_orderkey, row_number() {_LINE} AS nth, ntile(4) {_LINE} AS quarter, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS urgent, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS level,
  coalesce(date_diff('day', lag(o_orderdate) {_LINE}::DATE, o_orderdate::DATE), -1)::INT AS days, sum((o_totalprice * 100)::BIGINT) {_LINE}::BIGINT AS spent,
  max((o_totalprice * 100)::BIGINT) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS top3, first(o_orderkey) {_LINE} AS first_order,
  round(cume_dist() {_LINE}, 9) AS share FROM orders""")
def window_chain(s: SparkSession, d: str) -> DataFrame:
    """A customer's orders in a line: places, tiles, ranks, gaps, running sums and frames, over one sort for each order of rows."""
    o = builders.table(s, d, "orders")
    line, level = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    cents = F.round(F.col("o_totalprice") * 100).cast("bigint")
    return o.select(
        "o_orderkey", F.row_number().over(line).cast("bigint").alias("nth"), F.ntile(4).over(line).cast("bigint").alias("quarter"), F.rank().over(level).cast("bigint").alias("urgent"), F.dense_rank().over(level).cast("bigint").alias("level"),
        F.coalesce(F.date_diff(F.col("o_orderdate").cast("date"), F.lag("o_orderdate").over(line).cast("date")), F.lit(-1)).alias("days"), F.sum(cents).over(line.rowsBetween(Window.unboundedPreceding, 0)).alias("spent"),
        F.max(cents).over(line.rowsBetween(-2, 0)).alias("top3"), F.first("o_orderkey").over(line).alias("first_order"), F.round(F.cume_dist().over(line), 9).alias("share"),
    )


query("degree_summary", sql.graph(MAIN) + "SELECT (v % 2)::INT AS kind, count(DISTINCT deg) AS degrees, round(quantile_cont(deg, 0.5), 6) AS median, round(quantile_cont(deg, 0.9), 6) AS high, round(stddev_pop(deg), 6) AS spread, min(deg) AS least, arg_max(v, struct_pack(d := deg, v := -v)) AS hub FROM vertices GROUP BY kind")(
    lambda s, d: main_graph(s, d).vertices.groupBy((F.col("v") % 2).cast("int").alias("kind")).agg(F.countDistinct("deg").alias("degrees"), F.round(F.percentile("deg", 0.5), 6).alias("median"), F.round(F.percentile("deg", 0.9), 6).alias("high"), F.round(F.stddev_pop("deg"), 6).alias("spread"), F.min("deg").alias("least"), F.max_by("v", F.struct("deg", -F.col("v"))).alias("hub"))
)

for _name in files.FORMATS:

    @query(f"file_{_name}", sql.graph(MAIN) + "SELECT src, dst, 1::BIGINT AS w FROM edges")
    def _written_and_read(s: SparkSession, d: str, fmt=_name) -> DataFrame:
        path = f"{shared_folder(s)}/file-{fmt}-{uuid.uuid4().hex}"
        files.write_edges(main_graph(s, d), path, fmt)
        return files.read_edges(s, path, fmt)


for _name in ("vector", "parquet"):

    @query(f"file_parts_{_name}", sql.graph(MAIN, START) + "SELECT * FROM parts")
    def _parts_written_and_read(s: SparkSession, d: str, fmt=_name) -> DataFrame:
        path = f"{shared_folder(s)}/parts-{fmt}-{uuid.uuid4().hex}"
        files.write_parts(start(main_graph(s, d)), path, fmt)
        return files.read_parts(s, path, fmt)


query("stream_edges", "SELECT user_id, date_trunc('hour', ts) AS hour, count(*) AS events FROM events GROUP BY ALL")(lambda s, d: streams.drained(streams.hourly_edges(streams.event_stream(s, d)), "hourly").select("user_id", F.col("hour").cast("timestamp_ntz").alias("hour"), "events"))

query("stream_sliding", "SELECT user_id, hour, count(*) AS events FROM (SELECT user_id, unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS hour FROM events) GROUP BY ALL")(lambda s, d: streams.drained(streams.sliding_edges(streams.event_stream(s, d)), "sliding").select("user_id", F.col("hour").cast("timestamp_ntz").alias("hour"), "events"))
query("stream_sessions", """SELECT user_id, min(ts) AS begun, count(*) AS events FROM (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM
  (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s""")(lambda s, d: streams.drained(streams.session_edges(streams.event_stream(s, d)), "sessions").select("user_id", F.col("begun").cast("timestamp_ntz").alias("begun"), "events"))
_USER_PART = f"({sql.h('user_id', SEED)} % {P})::INT"
query("stream_alert", f"SELECT part, events, round(events * {P} / total, 6) AS imbalance, events * {P} > 1.02 * total AS alert FROM (SELECT {_USER_PART} AS part, count(*) AS events FROM events GROUP BY ALL), (SELECT count(*) AS total FROM events)")(
    lambda s, d: streams.alerts(streams.drained(streams.part_load(streams.event_stream(s, d).select(F.col("user_id").alias("v")), builders.table(s, d, "events").select(F.col("user_id").alias("v")).distinct().select("v", (portable_hash("v", SEED) % P).cast("int").alias("part"))), "load"), P, 0.02)
)
query("stream_late", "SELECT count(*) AS late FROM (SELECT ts, max(ts) OVER (ORDER BY event_id * 48271 % 10007, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM events) WHERE ts < top - INTERVAL 20 DAY")(
    lambda s, d: streams.late_rows(builders.table(s, d, "events").withColumn("at", F.struct(F.col("event_id") * 48271 % 10007, "event_id")), "at", "ts", 20 * 86400).agg(F.count("*").alias("late"))
)
query("stream_assign")(
    lambda s, d: streams.drained(streams.assign_online(streams.event_stream(s, d).select((F.col("user_id") % 3).cast("int").alias("bucket"), F.col("user_id").alias("v"), (F.col("event_id") % 150).alias("u")), P, 1000), "assigned", "append")
)

# --- experiment workloads -------------------------------------------------------------------------------

for _name in experiments.WORKLOADS:
    query(_name)(lambda s, d, n=_name: experiments.once(s, d, n))
