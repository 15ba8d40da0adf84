"""Times the headline queries at ``$BENCH_SF_DIR`` on ``local[$BENCH_CPUS]`` and prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")

from pyspark.sql import SparkSession  # noqa: E402

from graphparts import graph_queries as q  # noqa: E402
from graphparts.operators import metrics  # noqa: E402
from graphparts.plans import baselines  # noqa: E402
from graphparts.plans.partitioner import partition  # noqa: E402
from graphparts.sources import builders  # noqa: E402

#: Queries that scan, join, sweep, exchange and multiply, each over its whole table.
NAMES = "g_supp_part g_degree_stats ghosts exchange_matrix init_grow balance_sweep1 refine_sweep1 edge_balance_sweep1 delta_sweep3 quality_random quality_vertex_block communication pagerank harmonic spmv_1 comm_2d".split()


#: Fewer sweeps than the defaults (3 rounds of 5 and 10), as in earlier benches; one run has the whole schedule.
SHORT = {"outer": 1, "balance": 2, "refine": 3, "early_stop": True}


def main() -> None:
    d = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}
    figures: dict[str, float] = {}

    def timed(name: str, run) -> object:
        began = time.time()
        out = run()
        times[name] = round(time.time() - began, 3)
        print(name, times[name], file=sys.stderr, flush=True)
        return out

    spark.range(1000).selectExpr("sum(id)").collect()
    for name in NAMES:
        timed(name, lambda n=name: q.QUERIES[n](spark, d).write.format("noop").mode("overwrite").save())
    p = 8
    g = builders.graph(spark, d, "cust_supp").stored()
    for name, run in (
        ("partition_multi_full_schedule", lambda: partition(g, p, executor="worker").parts),
        ("partition_multi", lambda: partition(g, p, executor="worker", **SHORT).parts),
        ("partition_single_objective", lambda: partition(g, p, executor="worker", mode="vertex", rat_v=0.03, **SHORT).parts),
        ("single_node", lambda: baselines.single_node(g, p, mode="vertex", **SHORT).parts),
        ("vertex_block", lambda: baselines.vertex_block(g, p)),
        ("random", lambda: baselines.random(g, p)),
    ):
        done = timed(name, run)
        row = metrics.quality(g, done, p).first()
        figures |= {f"{name}_edge_cut_ratio": row.edge_cut_ratio, f"{name}_scaled_max_cut": row.scaled_max_cut, f"{name}_vertex_imbalance": row.vertex_imbalance, f"{name}_edge_imbalance": row.internal_imbalance}
        if name.startswith("partition_multi"):
            held = metrics.limits(g, done, p).first()
            figures |= {f"{name}_within_limits": held.max_vertices <= held.vertex_limit and held.max_edges <= held.edge_limit}
    chain = builders.graph(spark, d, "order_chain").stored()
    for name, run in (("partition_chain", lambda: partition(chain, p, executor="worker", init="vertex_block", **SHORT).parts), ("random_chain", lambda: baselines.random(chain, p))):
        figures[f"{name}_edge_cut_ratio"] = metrics.quality(chain, timed(name, run), p).first().edge_cut_ratio
    n, m = g.sizes()
    print(json.dumps({"metric": "total time of the headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": d.rstrip("/").rpartition("sf")[2], "graph": {"n": n, "m": m, "p": p}, "quality": figures}), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
