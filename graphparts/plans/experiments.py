"""The experiment workloads, each a function that returns its rows.

Settings default to sizes that a laptop finishes in about a minute; every one is a parameter.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphparts.functions.hashing import portable_hash
from graphparts.operators import analytics, metrics, spmv
from graphparts.operators.graph import Graph, graph_of, stats
from graphparts.plans import baselines, initial
from graphparts.plans.config import PartitionConfig
from graphparts.plans.partitioner import PartitionResult, partition
from graphparts.plans.scratch import written
from graphparts.plans.skew import hashed
from graphparts.sources import builders, generators

RUN = (
    "graph string, method string, p int, n_workers int, x double, y double, cut bigint, max_cut bigint, edge_cut_ratio double, scaled_max_cut double, "
    "vertex_imbalance double, internal_imbalance double, incident_imbalance double, seconds double, ok boolean"
)
#: One round of one balance and two refinement sweeps; options of any workload override it.
QUICK = {"executor": "worker", "outer": 1, "balance": 1, "refine": 2, "early_stop": True}
#: The default schedule, without an early stop.
WHOLE = {"executor": "worker", "outer": 3, "balance": 5, "refine": 10, "early_stop": False}


_GRAPHS: dict[tuple[str, str, str], Graph] = {}


def named(spark: SparkSession, d: str, name: str) -> Graph:
    """A graph of the tables, or a generated one: ``rmat``, ``er``, ``hd`` of 1,024 vertices, ``mesh``; stored once in a session."""
    key = (spark.sparkContext.applicationId, d, name)
    if key not in _GRAPHS:
        _GRAPHS[key] = _named(spark, d, name)
    return _GRAPHS[key]


def _named(spark: SparkSession, d: str, name: str) -> Graph:
    made = {"rmat": lambda: generators.rmat(spark, 10, 8), "er": lambda: generators.erdos_renyi(spark, 1024, 8), "hd": lambda: generators.high_diameter(spark, 1024, 8), "mesh": lambda: generators.mesh3d(spark, 12, 9, 9)}
    return (graph_of(made[name]()) if name in made else builders.graph(spark, d, name)).stored()


def _row(graph: str, method: str, p: int, n: int, x: float, y: float, g: Graph, parts: DataFrame, seconds: float) -> tuple:
    q = metrics.quality(g, parts, p).first()
    return (graph, method, p, n, x, y, q.cut, q.max_cut, q.edge_cut_ratio, q.scaled_max_cut, q.vertex_imbalance, q.internal_imbalance, q.incident_imbalance, round(seconds, 3), True)


#: Starts made in a session with the seconds each took; a start does not depend on the workers.
_STARTS: dict[tuple, tuple[DataFrame, float]] = {}


def _started(g: Graph, p: int, cfg: PartitionConfig) -> tuple[DataFrame, float]:
    key = (g.edges.sparkSession.sparkContext.applicationId, *g.edges.inputFiles()[:1], p, cfg.init, cfg.seed, cfg.init_max_sweeps)
    if key not in _STARTS:
        began = time.time()
        _STARTS[key] = (written(initial.start(g, p, cfg.init, cfg.seed, cfg.init_max_sweeps), "start"), time.time() - began)
    return _STARTS[key]


def _partitioned(graph: str, g: Graph, p: int, method: str = "distributed", **options) -> tuple:
    """A run with the seconds of its start, which runs of one stored graph share."""
    cfg = PartitionConfig(**{**QUICK, **options})
    parts, seconds = _started(g, p, cfg) if g.kept else (None, 0.0)
    r: PartitionResult = partition(g, p, cfg, parts)
    return _row(graph, method, p, r.config.n_workers, r.config.x, r.config.y, g, r.parts, seconds + r.seconds)


def _other(graph: str, g: Graph, p: int, method: str, rat: float = 0.1, **options) -> tuple:
    began = time.time()
    quick = {k: v for k, v in QUICK.items() if k != "executor"}
    make: dict[str, Callable[[], DataFrame]] = {
        "random": lambda: baselines.random(g, p),
        "vertex_block": lambda: baselines.vertex_block(g, p),
        "edge_block": lambda: baselines.edge_block(g, p),
        "single_node": lambda: baselines.single_node(g, p, **{**quick, "rat_v": rat, **options}).parts,
        "multilevel_matching": lambda: baselines.multilevel(g, p, "matching", rat),
        "multilevel_clusters": lambda: baselines.multilevel(g, p, "clusters", rat),
    }
    parts = make[method]()
    return _row(graph, method, p, 1, 0.0, 0.0, g, parts, time.time() - began)


def guarded(graph: str, method: str, p: int, run: Callable[[], tuple]) -> tuple:
    """The row of ``run``, or where it fails (memory, say) a row without measures that is not ok: the method did not complete the test."""
    try:
        return run()
    except Exception as e:  # noqa: BLE001
        if isinstance(e, (ValueError, TypeError)):
            raise
        return (graph, method, p, *([None] * (RUN.count(",") - 3)), False)


#: Runs made in a session, which several workloads report from.
_MADE: dict[tuple, tuple] = {}


def method_row(graph: str, g: Graph, p: int, method: str, **options) -> tuple:
    key = (g.edges.sparkSession.sparkContext.applicationId, *g.edges.inputFiles()[:1], graph, p, method, tuple(sorted(options.items())))
    if key not in _MADE:
        _MADE[key] = guarded(graph, method, p, lambda: _partitioned(graph, g, p, **options) if method == "distributed" else _other(graph, g, p, method, **options))
    return _MADE[key]


def _runs(spark: SparkSession, rows: Iterable[tuple]) -> DataFrame:
    return spark.createDataFrame(list(rows), RUN)


def strong_scaling(spark: SparkSession, d: str, graphs=("fk_tree",), p: int = 8, workers=(1, 2, 4)) -> DataFrame:
    """One graph and part count, more and more workers."""
    return _runs(spark, (method_row(n, named(spark, d, n), p, "distributed", n_workers=k) for n in graphs for k in workers))


def absolute_speedup(spark: SparkSession, d: str, graphs=("fk_tree",), p: int = 8, workers=(1, 2, 4)) -> DataFrame:
    """More and more workers against the single-node predecessor."""
    runs = strong_scaling(spark, d, graphs, p, workers).select("graph", F.col("n_workers").alias("workers"), "seconds")
    single = _runs(spark, (method_row(n, named(spark, d, n), p, "single_node") for n in graphs))
    return metrics.absolute_speedups(runs, single.select("graph", F.col("seconds").alias("single")))


def relative_speedup(spark: SparkSession, d: str, **options) -> DataFrame:
    return metrics.speedups(strong_scaling(spark, d, **options).select("graph", "method", F.col("n_workers").alias("workers"), "seconds"))


def weak_scaling(spark: SparkSession, d: str, per_worker: int = 256, workers=(2, 4), d_avg=(4, 8), kinds=("rmat", "er", "hd")) -> DataFrame:
    """As many vertices for each worker, and as many parts as workers."""
    make = {
        "rmat": lambda n, k: generators.rmat(spark, n.bit_length() - 1, k),
        "er": lambda n, k: generators.erdos_renyi(spark, n, k),
        "hd": lambda n, k: generators.high_diameter(spark, n, k),
    }
    return _runs(spark, (_partitioned(f"{kind}_{k}", graph_of(make[kind](per_worker * w, k)).stored(), w, n_workers=w) for kind in kinds for k in d_avg for w in workers))


def capacity(spark: SparkSession, d: str, bytes_per_arc: int = 16, label_bytes: int = 12, graphs=("supp_part", "cust_supp")) -> DataFrame:
    """What the state and one exchange weigh, if one label in a hundred changes: a model, not a run, for graphs of the tables and at the published sizes."""
    sizes = [(n, *named(spark, d, n).sizes()) for n in graphs] + [(f"2^{v} vertices, 2^{e} edges", 1 << v, 1 << e) for v, e in ((25, 29), (30, 36), (34, 39), (34, 40))]
    rows = [(n, float(2 * e * bytes_per_arc) / 1e12, float(v * label_bytes) / 1e12, float(2 * e * bytes_per_arc) / 1e14) for n, v, e in sizes]
    return spark.createDataFrame(rows, "size string, arcs_tb double, labels_tb double, patch_tb double")


def partitioners(spark: SparkSession, d: str, graphs=("fk_tree",), ps=(4,), methods=("distributed", "single_node", "multilevel_matching")) -> DataFrame:
    """Times and cuts of the partitioners side by side."""
    return _runs(spark, (method_row(n, g, p, m) for n in graphs for g in [named(spark, d, n)] for p in ps for m in methods))


def quality_by_parts(spark: SparkSession, d: str, graphs=("fk_tree", "hd"), ps=(2, 8), methods=("random", "vertex_block", "distributed")) -> DataFrame:
    return partitioners(spark, d, graphs, ps, methods)


def performance_ratios(runs: DataFrame, value: str = "cut", only_complete: bool = False) -> DataFrame:
    return metrics.performance_ratio(runs.select(F.concat_ws("/", "graph", "p").alias("test"), "method", value), value, only_complete)


def quality_by_workers(spark: SparkSession, d: str, graphs=("fk_tree",), p: int = 8, workers=(1, 4)) -> DataFrame:
    """The distributed partitioner with more workers, beside block and random labels."""
    rows = []
    for n in graphs:
        g = named(spark, d, n)
        rows += [method_row(n, g, p, "distributed", n_workers=k) for k in workers] + [method_row(n, g, p, m) for m in ("vertex_block", "random")]
    return _runs(spark, rows)


def single_objective(spark: SparkSession, d: str, graphs=("fk_tree",), ps=(4,)) -> DataFrame:
    """One constraint of 3 % and one objective, four partitioners."""
    rows = []
    for n in graphs:
        g = named(spark, d, n)
        for p in ps:
            rows.append(_partitioned(n, g, p, mode="vertex", rat_v=0.03))
            rows.append(_other(n, g, p, "single_node", 0.03, mode="vertex"))
            rows += [_other(n, g, p, m, 0.03) for m in ("multilevel_matching", "multilevel_clusters")]
    return _runs(spark, rows)


def multiplier_grid(spark: SparkSession, d: str, graph: str = "fk_tree", xs=(0.0, 1.0), ys=(0.0, 0.25), p: int = 4, n_workers: int = 4, at_once: int = 3) -> DataFrame:
    """Every X with every Y by the whole schedule of both stages, as the multiplier goes from Y to X over it; ``at_once`` runs share the cores, so their seconds are no times of single runs."""
    g = named(spark, d, graph)
    _started(g, p, PartitionConfig(**WHOLE))  # made before the runs that share it
    with ThreadPoolExecutor(at_once) as pool:
        rows = list(pool.map(lambda xy: _partitioned(graph, g, p, **WHOLE, x=xy[0], y=xy[1], n_workers=n_workers), [(x, y) for x in xs for y in ys]))
    return _runs(spark, rows)


def grid_summary(runs: DataFrame, tolerance: float = 1.15) -> DataFrame:
    """Mean balance of all runs, and mean cuts of those within ``tolerance`` of balance."""
    fits = F.col("vertex_imbalance") <= tolerance
    return runs.groupBy("x", "y").agg(F.avg("vertex_imbalance").alias("vertex_imbalance"), F.avg("internal_imbalance").alias("edge_imbalance"), F.avg(F.when(fits, F.col("edge_cut_ratio"))).alias("edge_cut_ratio"), F.avg(F.when(fits, F.col("scaled_max_cut"))).alias("scaled_max_cut"), F.sum(fits.cast("int")).alias("kept"))


def layouts(g: Graph, p: int, **options) -> dict[str, tuple[DataFrame, float]]:
    """Edge block, vertex block, random, and the partitioner started from blocks; with the seconds each took."""
    out = {}
    for name, make in (("edge_block", baselines.edge_block), ("vertex_block", baselines.vertex_block), ("random", baselines.random)):
        began = time.time()
        out[name] = (written(make(g, p), "parts"), time.time() - began)
    r = partition(g, p, **{**QUICK, "init": "vertex_block", **options})
    return out | {"distributed": (r.parts, r.seconds)}


def end_to_end(runs: DataFrame) -> DataFrame:
    """Per layout the time of all analytics with that of the partition, and its share of the slowest layout's."""
    total = runs.groupBy("layout").agg(F.round(F.sum("seconds") + F.max("partition_seconds"), 3).alias("seconds"), F.max("messages").alias("messages"))
    slowest = total.agg(F.max("seconds").alias("top"))  # one row
    return total.crossJoin(F.broadcast(slowest)).select("layout", "messages", "seconds", F.round(F.col("seconds") / F.col("top"), 3).alias("share"))


def mean_gain(runs: DataFrame, base: str = "random", kind: str = "1d") -> DataFrame:
    """Over all graphs and part counts the geometric mean of what the base layout needs over what each one needs, in time and in entries sent."""
    b = runs.where((F.col("layout") == base) & (F.col("kind") == kind)).select("graph", "p", F.col("seconds").alias("s0"), F.col("sent").alias("n0"))
    mean = lambda x: F.round(F.exp(F.avg(F.log(x))), 4)
    return runs.join(b, ["graph", "p"]).groupBy("layout", "kind").agg(mean(F.col("s0") / F.col("seconds")).alias("time_gain"), mean(F.col("n0") / F.greatest("sent", F.lit(1))).alias("sent_gain"), F.count("*").alias("tests"))


def analytics_by_layout(spark: SparkSession, d: str, graph: str = "fk_tree", p: int = 4, iterations: int = 10, sweeps: int = 5, sources: int = 100) -> DataFrame:
    """Messages of a superstep, and time of six analytics on the adjacency laid out each way; results must not differ.

    The partitioner runs its whole schedule. Arcs are placed once a layout, which counts with its making, and stay where they are on the executors' disks.
    """
    g, rows = named(spark, d, graph), []
    for name, (parts, seconds) in layouts(g, p, **WHOLE).items():
        c = metrics.communication(g, parts).first()
        began = time.time()
        placed = g.edges.join(hashed(parts.select(F.col("v").alias("src"), "part"), g.vertices.count()), "src").repartitionById(p, F.col("part")).drop("part").persist(StorageLevel.DISK_ONLY)
        placed.count()
        laid, seconds = Graph(placed, g.vertices, True), seconds + time.time() - began
        for what, run in (
            ("pagerank", lambda x: analytics.pagerank(x, iterations).agg(F.sum(F.round(F.col("rank") * 1e6)))),
            ("labels", lambda x: analytics.label_propagation(x, sweeps).agg(F.sum(portable_hash("community", 1)))),
            ("wcc", lambda x: analytics.wcc(x).agg(F.sum(portable_hash("component", 1)))),
            ("kcore", lambda x: analytics.kcore(x).agg(F.sum("core"))),
            ("harmonic", lambda x: analytics.harmonic(x, sources).agg(F.round(F.sum("harmonic"), 3))),
            ("scc", lambda x: analytics.largest_scc(analytics.directed(x)).agg(F.count("*"))),
        ):
            began = time.time()
            value = run(laid).first()[0]
            rows.append((name, what, c.messages, c.cut, float(value), round(time.time() - began, 3), round(seconds, 3)))
        placed.unpersist()
    return spark.createDataFrame(rows, "layout string, analytic string, messages bigint, cut bigint, value double, seconds double, partition_seconds double")


def products_by_layout(spark: SparkSession, d: str, graphs=("cust_supp",), ps=(4,), products: int = 2) -> DataFrame:
    """What 1D and 2D products send for each layout, and the time of ``products`` of them."""
    rows = []
    for n in graphs:
        g = named(spark, d, n)
        matrix = spmv.symmetric(g)
        x = g.vertices.select(F.col("v").alias("i"), F.lit(1.0).alias("x"))
        for p in ps:
            for name, (parts, _) in layouts(g, p).items():
                for kind, laid in (("1d", spmv.layout_1d(matrix, parts)), ("2d", spmv.layout_2d(matrix, parts, *spmv.grid(p)))):
                    c = spmv.comm_stats(laid).first()
                    placed = laid.repartitionById(p, F.col("process")).select("i", "j", "a")
                    began = time.time()
                    spmv.power(placed, x, products).agg(F.sum("x")).first()
                    rows.append((n, p, name, kind, c.expand + c.fold, c.max_partners, c.max_nonzeros, round(time.time() - began, 3)))
    return spark.createDataFrame(rows, "graph string, p int, layout string, kind string, sent bigint, max_partners bigint, max_nonzeros bigint, seconds double")


def graph_table(spark: SparkSession, d: str, graphs=("supp_part", "fk_tree", "conv_turns"), rounds: int = 2) -> DataFrame:
    """Sizes, degrees and approximate diameter of graphs."""
    rows = []
    for n in graphs:
        g = named(spark, d, n)
        s = stats(g).first()
        rows.append((n, s.n, s.m, s.d_avg_arcs, s.d_max, analytics.approx_diameter(g, rounds)))
    return spark.createDataFrame(rows, "graph string, n bigint, m bigint, d_avg double, d_max bigint, diameter int")


def starts(spark: SparkSession, d: str, graphs=("fk_tree",), p: int = 4, inits=("grow", "label_prop", "bfs", "random", "vertex_block", "edge_block")) -> DataFrame:
    """The same partitioner from every start."""
    return _runs(spark, (_partitioned(n, named(spark, d, n), p, method=i, init=i, mode="vertex", init_max_sweeps=40) for n in graphs for i in inits))


_FRAMES: dict[tuple[str, str, str], DataFrame] = {}


def once(spark: SparkSession, d: str, name: str) -> DataFrame:
    """The rows of a workload, made once in a session."""
    key = (spark.sparkContext.applicationId, d, name)
    if key not in _FRAMES:
        made = WORKLOADS[name](spark, d)
        _FRAMES[key] = spark.createDataFrame(made.collect(), made.schema)  # a few rows
    return _FRAMES[key]


_TWO = ("cust_supp", "fk_tree")

WORKLOADS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "w1_strong_scaling": lambda s, d: strong_scaling(s, d, graphs=_TWO, p=8, workers=(1, 2, 4, 8)),
    "w2_weak_scaling": lambda s, d: weak_scaling(s, d, workers=(1, 2, 4), d_avg=(8,)),
    "w3_capacity": capacity,
    "w4_partitioners": lambda s, d: partitioners(s, d, graphs=_TWO, ps=(8,)),
    "w4_partitioners_full": lambda s, d: _runs(s, [method_row("cust_supp", named(s, d, "cust_supp"), 8, m, outer=3, balance=5, refine=10, early_stop=False) for m in ("distributed", "single_node")]),
    "w5_relative_speedup": lambda s, d: relative_speedup(s, d, graphs=_TWO, workers=(1, 2, 4, 8)),
    "w5_absolute_speedup": lambda s, d: absolute_speedup(s, d, graphs=_TWO, workers=(1, 2, 4, 8)),
    "w6_quality_by_parts": lambda s, d: quality_by_parts(s, d, graphs=_TWO, ps=(2, 8), methods=("random", "vertex_block", "distributed", "single_node", "multilevel_matching")),
    "w7_performance_ratios": lambda s, d: performance_ratios(once(s, d, "w6_quality_by_parts")),
    "w7_max_cut_ratios": lambda s, d: performance_ratios(once(s, d, "w6_quality_by_parts"), "max_cut"),
    "w8_quality_by_workers": lambda s, d: quality_by_workers(s, d, graphs=_TWO, p=8, workers=(1, 2, 4, 8)),
    "w9_single_objective": lambda s, d: single_objective(s, d, graphs=("cust_supp",), ps=(4,)),
    "w10_multiplier_grid": lambda s, d: grid_summary(multiplier_grid(s, d, graph="cust_supp", xs=(0.0, 1.0, 2.0), ys=(0.0, 0.25, 1.0), p=8)),
    "w11_analytics_by_layout": lambda s, d: analytics_by_layout(s, d, graph="cust_supp"),
    "w11_end_to_end": lambda s, d: end_to_end(once(s, d, "w11_analytics_by_layout")),
    "w12_products_by_layout": lambda s, d: products_by_layout(s, d, graphs=("cust_supp",), ps=(4,), products=2),
    "w12_mean_gain": lambda s, d: mean_gain(once(s, d, "w12_products_by_layout")),
    "w13_graph_table": lambda s, d: graph_table(s, d, graphs=("supp_part", "cust_supp", "page_shared", "rmat")),
    "w14_starts": lambda s, d: starts(s, d, graphs=("cust_supp",), inits=("grow", "grow_majority", "label_prop", "bfs", "random", "vertex_block")),
}


def main() -> None:
    """``python -m graphparts.plans.experiments WORKLOAD SF_DIR``"""
    import sys

    spark = SparkSession.builder.config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    WORKLOADS[sys.argv[1]](spark, sys.argv[2]).show(200, False)


if __name__ == "__main__":
    main()
