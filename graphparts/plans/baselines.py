"""What the partitioner is compared with: random and block labels, one asynchronous worker, and multilevel schemes."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphparts.functions.hashing import portable_hash
from graphparts.operators.distribution import labels
from graphparts.operators.graph import Graph
from graphparts.plans.config import PartitionConfig
from graphparts.plans.partitioner import PartitionResult, partition
from graphparts.plans.scratch import written


def random(g: Graph, p: int, seed: int = 11) -> DataFrame:
    return labels(g.vertices, p, "random", seed).withColumnRenamed("label", "part")


def vertex_block(g: Graph, p: int) -> DataFrame:
    return labels(g.vertices, p, "vertex_block").withColumnRenamed("label", "part")


def edge_block(g: Graph, p: int) -> DataFrame:
    return labels(g.vertices, p, "edge_block").withColumnRenamed("label", "part")


def single_node(g: Graph, p: int, init: str = "label_prop", **options) -> PartitionResult:
    """The shared-memory predecessor: one worker, sizes updated at once, no multiplier."""
    return partition(g, p, PartitionConfig(executor="worker", n_workers=1, multiplier=False, init=init, keep="last"), **options)


def matching(g: Graph, seed: int = 5, rounds: int = 3) -> DataFrame:
    """``(v, mate)`` with v < mate: edges that both ends prefer, heaviest first, ties by hash; repeated on the unmatched rest."""
    edges = g.edges
    out = None
    for k in range(rounds):
        key = portable_hash(portable_hash("src", seed + k) + F.col("dst"), seed)
        both = edges.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("u")), F.struct(F.col("dst").alias("v"), F.col("src").alias("u")))).alias("x"), "w", key.alias("h"))
        best = both.groupBy("x.v").agg(F.max_by("x.u", F.struct("w", "h", "x.u")).alias("u"))
        mutual = best.join(best.select(F.col("v").alias("u"), F.col("u").alias("v")), ["v", "u"]).where("v < u").select("v", F.col("u").alias("mate"))
        found = written(mutual, "matching")
        out = found if out is None else out.unionByName(found)
        taken = found.select(F.explode(F.array("v", "mate")).alias("t"))
        edges = edges.join(taken.withColumnRenamed("t", "src"), "src", "left_anti").join(taken.withColumnRenamed("t", "dst"), "dst", "left_anti")
    return out


def pairs_around(g: Graph, paired: DataFrame, seed: int = 7, most: int = 1000) -> DataFrame:
    """``(v, mate)`` with v < mate: vertices outside ``paired(v, mate)`` that lean on one neighbour, by weight, then hash.

    Around a hub only one vertex finds a mate among its neighbours; the others are paired with each other. Those of a
    neighbour of more than ``most`` are dealt into tiles, of which each leaves one at most.
    """
    free = g.vertices.select("v").join(paired.select(F.explode(F.array("v", "mate")).alias("v")), "v", "left_anti")
    leans = g.arcs.join(free, "v").groupBy("v").agg(F.max_by("u", F.struct("w", portable_hash("u", seed), "u")).alias("u"))
    leans = written(leans.withColumn("h", portable_hash("v", seed + 1)), "leans")
    tiles = leans.groupBy("u").agg(F.ceil(F.count("*") / most).cast("int").alias("tiles"))
    dealt = leans.join(tiles, "u").withColumn("tile", F.pmod("h", "tiles"))
    line = Window.partitionBy("u", "tile").orderBy("h", "v")
    near = dealt.withColumn("nth", F.row_number().over(line)).withColumn("other", F.lead("v").over(line)).where("nth % 2 = 1 and other is not null")
    return near.select(F.least("v", "other").alias("v"), F.greatest("v", "other").alias("mate"))


def clusters(g: Graph, cap: float, sweeps: int = 3, seed: int = 5) -> DataFrame:
    """``(v, coarse)``: label propagation in which no cluster may weigh more than ``cap``.

    Joiners of a cluster are taken by the strength of their tie while its weight allows; only every
    second vertex, by hash and sweep, may leave in a sweep.
    """
    now = g.vertices.select("v", F.col("w").alias("vw"), F.col("v").alias("coarse"))
    for k in range(sweeps):
        tie = g.arcs.join(now.select(F.col("v").alias("u"), F.col("coarse").alias("theirs")), "u").groupBy("v", "theirs").agg(F.sum("w").alias("n"))
        weights = now.groupBy("coarse").agg(F.sum("vw").alias("total"))
        mine = now.where(portable_hash(F.col("v") + k, seed) % 2 == 0)
        options = tie.join(mine, "v").join(weights.withColumnRenamed("coarse", "theirs"), "theirs").where((F.col("theirs") == F.col("coarse")) | (F.col("total") + F.col("vw") <= cap))
        best = options.groupBy("v").agg(F.max_by(F.struct("theirs", "n", "vw", "total", "coarse"), F.struct("n", F.col("theirs") == F.col("coarse"), -F.col("theirs"))).alias("b")).where("b.theirs <> b.coarse").select("v", "b.*")
        line = Window.partitionBy("theirs").orderBy(F.desc("n"), "v").rowsBetween(Window.unboundedPreceding, 0)
        moves = best.withColumn("used", F.sum("vw").over(line)).where(F.col("total") + F.col("used") <= cap).select("v", F.col("theirs").alias("new"))
        now = written(now.join(moves, "v", "left").select("v", "vw", F.coalesce("new", "coarse").alias("coarse")), "clusters")
    return now.select("v", "coarse")


def contract(g: Graph, mapping: DataFrame) -> Graph:
    """The graph on ``mapping(v, coarse)``: weights of merged vertices and of parallel edges are summed."""
    s, d = mapping.select(F.col("v").alias("src"), F.col("coarse").alias("a")), mapping.select(F.col("v").alias("dst"), F.col("coarse").alias("b"))
    e = g.edges.join(s, "src").join(d, "dst").where("a <> b")
    edges = e.groupBy(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).agg(F.sum("w").alias("w"))
    weight = g.vertices.join(mapping, "v").groupBy("coarse").agg(F.sum("w").alias("w"))
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("v"), "w"), F.struct(F.col("dst").alias("v"), "w"))).alias("x"))
    deg = ends.groupBy("x.v").agg(F.sum("x.w").alias("deg"))
    vertices = weight.withColumnRenamed("coarse", "v").join(deg, "v", "left").select("v", F.coalesce("deg", F.lit(0)).cast("bigint").alias("deg"), F.col("w").cast("bigint").alias("w"))
    return Graph(edges, vertices).stored()


def _weighted_degrees(g: Graph) -> Graph:
    """Degrees as sums of weights, which is what gains are counted in."""
    return contract(g, g.vertices.select("v", F.col("v").alias("coarse")))


def solve_small(g: Graph, p: int, rat: float, seed: int = 3) -> DataFrame:
    """The coarsest graph, of bounded size, in one task: greedy growth by weight, then moves that lower the cut."""
    both = g.arcs.withColumn("one", F.lit(0)).join(g.vertices.select("v", F.col("w").alias("vw")), "v", "full").withColumn("one", F.lit(0)).select("one", "v", "vw", "u", "w")

    def run(t: pa.Table) -> pa.Table:
        ids = np.unique(t.column("v").to_numpy())
        place = {int(v): k for k, v in enumerate(ids)}
        near: list[dict[int, float]] = [{} for _ in ids]
        vw = np.zeros(len(ids))
        for v, x, u, w in zip(*(t.column(c).to_pylist() for c in ("v", "vw", "u", "w")), strict=True):
            vw[place[v]] = x
            if u is not None:
                near[place[v]][place[u]] = w
        most, target = max((1 + rat) * vw.sum() / p, vw.max()), vw.sum() / p
        r = np.random.default_rng(seed)
        best, best_cut = None, np.inf
        for _ in range(4):
            part = np.full(len(ids), -1)
            size = np.zeros(p)
            for i in range(p - 1):
                free = np.flatnonzero(part < 0)
                if not len(free):
                    break
                front = {int(r.choice(free)): 0.0}
                while front and size[i] < target:
                    k = max(front, key=lambda j: (front[j], -j))
                    front.pop(k)
                    if size[i] + vw[k] > most:
                        continue
                    part[k] = i
                    size[i] += vw[k]
                    for j, w in near[k].items():
                        if part[j] < 0:
                            front[j] = front.get(j, 0.0) + w
                    if not front and size[i] < target and (free := np.flatnonzero(part < 0)).size:
                        front = {int(free[0]): 0.0}
            rest = np.flatnonzero(part < 0)
            for k in rest:
                fit = [i for i in range(p) if size[i] + vw[k] <= most] or list(range(p))
                i = p - 1 if p - 1 in fit else min(fit, key=lambda j: size[j])
                part[k] = i
                size[i] += vw[k]
            for _ in range(10):
                moved = False
                for k in range(len(ids)):
                    tie = np.zeros(p)
                    for j, w in near[k].items():
                        tie[part[j]] += w
                    gain = tie - tie[part[k]]
                    gain[(size + vw[k] > most) & (np.arange(p) != part[k])] = -1
                    i = int(gain.argmax())
                    if gain[i] > 0 or size[part[k]] > most and gain[i] >= 0 and i != part[k]:
                        size[part[k]] -= vw[k]
                        size[i] += vw[k]
                        part[k] = i
                        moved = True
                if not moved:
                    break
            cut = sum(w for k in range(len(ids)) for j, w in near[k].items() if part[j] != part[k])
            if cut < best_cut:
                best, best_cut = part.copy(), cut
        return pa.table({"v": pa.array(ids, pa.int64()), "part": pa.array(best, pa.int32())})

    return both.groupBy("one").applyInArrow(run, "v bigint, part int")


def multilevel(g: Graph, p: int, coarsen: str = "matching", rat: float = 0.03, coarsest: int = 2000, levels: int = 0, refine: int = 4, n_workers: int = 4) -> DataFrame:
    """``(v, part)``: coarsen, solve the coarsest graph, project back and refine at every level.

    ``coarsest`` bounds what the one task that solves it receives; coarsening goes on until it is met, or for
    ``levels`` (0: without a limit). Where it stalls above it, it stops, and the coarsest graph then starts from a growth in Spark.
    """
    if coarsen not in ("matching", "clusters"):
        raise ValueError(f"unknown coarsening: {coarsen}")
    graphs, maps = [_weighted_degrees(g)], []
    n = graphs[0].vertices.count()
    total = graphs[0].vertices.agg(F.sum("w")).first()[0] or 0
    while n > max(coarsest, 2 * p) and (not levels or len(maps) < levels):
        now = graphs[-1]
        if coarsen == "matching":
            pairs = matching(now)
            pairs = pairs.unionByName(pairs_around(now, pairs))
            mapping = now.vertices.select("v").join(pairs.select(F.col("mate").alias("v"), F.col("v").alias("coarse")), "v", "left").select("v", F.coalesce("coarse", "v").alias("coarse"))
        else:
            mapping = clusters(now, max(total / (p * 20), 2))
        mapping = written(mapping, "mapping")
        following = contract(now, mapping)
        k = following.vertices.count()
        if k > 0.95 * n:
            break
        graphs.append(following)
        maps.append(mapping)
        n = k
    bounded = n <= 10 * max(coarsest, 2 * p)
    parts = written(solve_small(graphs[-1], p, rat), "parts") if bounded else None
    cfg = PartitionConfig(mode="vertex", outer=1, balance=1 if parts is None else 0, refine=refine, rat_v=rat, executor="worker", n_workers=n_workers, x=1.0, y=1.0)
    parts = partition(graphs[-1], p, cfg, parts).parts
    for fine, mapping in zip(graphs[-2::-1], maps[::-1], strict=True):
        projected = mapping.join(parts.withColumnRenamed("v", "coarse"), "coarse").select("v", "part")
        parts = partition(fine, p, cfg, projected, balance=0).parts
    return parts
