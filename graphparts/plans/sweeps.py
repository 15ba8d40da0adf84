"""Balance and refinement sweeps over all vertices at once.

A sweep scores every part in a vertex's neighbourhood against the sizes at its start, picks the
best, and admits the proposals of each worker into each part up to its share of what the part
may still take. Labels of the whole graph never leave Spark: the driver sees p rows of sizes.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphparts.operators.graph import Graph
from graphparts.plans.config import PartitionConfig


@dataclass
class Sizes:
    """Per part: vertex weight, internal edge weight (or incident), cut edge weight."""

    sv: list[int]
    se: list[int]
    sc: list[int]

    def maxima(self, imb_v: float, imb_e: float) -> tuple[float, float, int]:
        return max(max(self.sv), imb_v), max(max(self.se), imb_e), max(self.sc)


def histogram(g: Graph, parts: DataFrame) -> DataFrame:
    """``(v, part, n, dsum)``: weight of edges, and sum of degrees, towards each part in a vertex's neighbourhood."""
    theirs = parts.select(F.col("v").alias("u"), "part").join(g.vertices.select(F.col("v").alias("u"), F.col("deg").alias("deg_u")), "u")
    return g.arcs.join(theirs, "u").groupBy("v", "part").agg(F.sum("w").alias("n"), F.sum(F.col("w") * F.col("deg_u")).alias("dsum"))


def patch(g: Graph, moved: DataFrame) -> DataFrame:
    """What the moves ``(v, old, new)`` change in the histogram, only along the arcs of moved vertices."""
    x = moved.select(F.col("v").alias("u"), "old", "new").join(g.vertices.select(F.col("v").alias("u"), F.col("deg").alias("deg_u")), "u").join(g.arcs, "u")
    two = F.explode(F.array(F.struct(F.col("old").alias("part"), F.lit(-1).alias("sign")), F.struct(F.col("new").alias("part"), F.lit(1).alias("sign"))))
    y = x.select("v", "w", "deg_u", two.alias("x"))
    return y.select("v", "x.part", (F.col("w") * F.col("x.sign")).alias("n"), (F.col("w") * F.col("deg_u") * F.col("x.sign")).alias("dsum"))


def patched(hist: DataFrame, changes: DataFrame) -> DataFrame:
    both = hist.unionByName(changes).groupBy("v", "part").agg(F.sum("n").alias("n"), F.sum("dsum").alias("dsum"))
    return both.where("n <> 0")


def sizes(vertices: DataFrame, parts: DataFrame, p: int, hist: DataFrame | None = None, measure: str = "internal") -> Sizes:
    """Sizes of all parts, p rows on the driver; edges and cut only where a histogram is given."""
    v = parts.join(vertices.select("v", F.col("w").alias("vw")), "v")
    if hist is None:
        rows = v.groupBy("part").agg(F.sum("vw").alias("sv"), F.lit(0).alias("se"), F.lit(0).alias("sc")).collect()
    else:
        around = hist.select("v", F.col("part").alias("theirs"), "n").join(parts, "v")
        inside = F.sum(F.when(F.col("theirs") == F.col("part"), F.col("n")).otherwise(0))
        every = around.groupBy("part").agg(inside.alias("i"), F.sum("n").alias("d"))
        edges = (F.col("i") / 2 if measure == "internal" else F.col("d")).cast("bigint")
        counted = v.groupBy("part").agg(F.sum("vw").alias("sv")).join(every, "part", "left")
        rows = counted.select("part", "sv", F.coalesce(edges, F.lit(0)).alias("se"), F.coalesce(F.col("d") - F.col("i"), F.lit(0)).alias("sc")).collect()
    out = Sizes([0] * p, [0] * p, [0] * p)
    for r in rows:
        out.sv[r.part], out.se[r.part], out.sc[r.part] = int(r.sv), int(r.se), int(r.sc)
    return out


def weight(target: float, size: float) -> float:
    """How strongly an underweight part attracts; 0 at or over the target."""
    return max(target / max(size, 1) - 1, 0.0)


@dataclass
class Stage:
    """What a sweep needs beside the graph."""

    kind: str  # vertex_balance, vertex_refine, edge_balance, edge_refine
    t: int
    sweep: int
    imb_v: float
    imb_e: float
    re: float = 1.0
    rc: float = 1.0


def part_state(s: Sizes, stage: Stage, cfg: PartitionConfig) -> pd.DataFrame:
    """p rows: sizes, weights, and how many vertices all workers together may add."""
    max_v, max_e, max_c = s.maxima(stage.imb_v, stage.imb_e)
    f = cfg.factor(stage.t) if cfg.multiplier else 1.0 / cfg.n_workers
    rows = []
    for i, (sv, se, sc) in enumerate(zip(s.sv, s.se, s.sc, strict=True)):
        room = math.floor((max_v - sv) / f) if f > 0 else 1 << 40
        w = weight(stage.imb_v, sv) if stage.kind.startswith("vertex") else stage.re * weight(max_e, se) + stage.rc * weight(max_c, sc)
        rows.append((i, sv, se, sc, w, max(room, 0)))
    return pd.DataFrame(rows, columns=["part", "sv", "se", "sc", "wt", "room"])


def _gains(measure: str) -> tuple[Column, Column]:
    """What one vertex adds to the edges and to the cut of the part it moves to."""
    edges = F.col("n") if measure == "internal" else F.col("deg")
    return edges.alias("add_e"), (F.col("deg") - 2 * F.col("n")).alias("add_c")


def proposals(hist: DataFrame, vertices: DataFrame, parts: DataFrame, owners: DataFrame, s: Sizes, stage: Stage, cfg: PartitionConfig) -> DataFrame:
    """``(v, old, new, gain, owner, vw, add_e, add_c)`` of the vertices that would rather be elsewhere."""
    spark = parts.sparkSession
    max_v, max_e, max_c = s.maxima(stage.imb_v, stage.imb_e)
    state = F.broadcast(spark.createDataFrame(part_state(s, stage, cfg)[["part", "sv", "se", "sc", "wt"]], "part int, sv bigint, se bigint, sc bigint, wt double"))
    about = parts.withColumnRenamed("part", "old").join(vertices.select("v", "deg", F.col("w").alias("vw")), "v").join(owners, "v")
    x = hist.join(about, "v").join(state, "part")
    edge_stage = stage.kind.startswith("edge")
    add_e, add_c = _gains(cfg.edge_measure)
    fits = F.col("sv") + F.col("vw") <= F.lit(float(max_v))
    if edge_stage:
        fits = fits & (F.col("se") + add_e <= F.lit(float(max_e))) & (F.col("sc") + add_c <= F.lit(max_c))
    own = F.col("part") == F.col("old")
    base = F.col("dsum") if (cfg.edge_score if edge_stage else cfg.vertex_score) == "degree" else F.col("n")
    score = (base * F.col("wt") if stage.kind.endswith("balance") else F.col("n")).cast("double")
    scored = x.where(fits if cfg.own_mask else fits | own).select("v", "old", "owner", "vw", "part", score.alias("score"), own.alias("own"), add_e, add_c)
    best = scored.groupBy("v").agg(
        F.max_by(F.struct("part", "score", "old", "owner", "vw", "add_e", "add_c"), F.struct("score", "own", -F.col("part"))).alias("b"),
        F.coalesce(F.max(F.when(F.col("own"), F.col("score"))), F.lit(0.0)).alias("own_score"),
    )
    wanted = best.where("b.part <> b.old and b.score > 0")
    return wanted.select("v", "b.old", F.col("b.part").alias("new"), (F.col("b.score") - F.col("own_score")).alias("gain"), "b.owner", "b.vw", "b.add_e", "b.add_c")


def admitted(wanted: DataFrame, s: Sizes, stage: Stage, cfg: PartitionConfig) -> DataFrame:
    """``(v, old, new, owner)`` of the proposals within each worker's share, best gains first."""
    n = cfg.n_workers
    max_v, max_e, max_c = s.maxima(stage.imb_v, stage.imb_e)
    state = F.broadcast(wanted.sparkSession.createDataFrame(part_state(s, stage, cfg)[["part", "sv", "se", "sc", "room"]].rename(columns={"part": "new"}), "new int, sv bigint, se bigint, sc bigint, room bigint"))
    line = Window.partitionBy("owner", "new").orderBy(F.desc("gain"), "v").rowsBetween(Window.unboundedPreceding, 0)
    x = wanted.join(state, "new").withColumn("used", F.sum("vw").over(line))
    if cfg.quota == "strict":
        ok = F.col("sv") + F.lit(cfg.mult(stage.t)) * (F.col("used") - F.col("vw")) + F.col("vw") <= F.lit(float(max_v))
    else:
        extra = (F.col("owner") + F.col("new") + stage.sweep) % n < F.col("room") % n
        ok = F.col("used") <= F.expr(f"room div {n}") + extra.cast("bigint")
    if stage.kind.startswith("edge"):
        x = x.withColumn("used_e", F.sum("add_e").over(line)).withColumn("used_c", F.sum("add_c").over(line))
        m = F.lit(cfg.mult(stage.t))
        ok = ok & (F.col("se") + m * F.col("used_e") <= F.lit(float(max_e))) & (F.col("sc") + m * F.col("used_c") <= F.lit(float(max_c)))
    return x.where(ok).select("v", "old", "new", "owner")


def share(total: int, n: int, owner: int, part: int, sweep: int) -> int:
    """What one of ``n`` workers may take of ``total``: whole shares that add up to it, the odd ones to workers in turn."""
    return total // n + int((owner + part + sweep) % n < total % n)


def released(hist: DataFrame, vertices: DataFrame, parts: DataFrame, owners: DataFrame, s: Sizes, limit_v: int, limit_e: float, by_edge: bool, n: int, sweep: int) -> DataFrame | None:
    """``(v, old, new, owner)``: vertices forced out of parts over their limit, those of the weakest ties first.

    Every worker lets its share of the excess go and fills its share of the room in other parts, ranking only its
    own vertices of one part, so no part ends over ``limit_v`` that was not before. None where nothing is over or nothing fits.
    """
    p = len(s.sv)
    over = [math.ceil(max(x - limit_e, 0)) if by_edge else max(x - limit_v, 0) for x in (s.se if by_edge else s.sv)]
    room = [0 if over[i] else max(limit_v - s.sv[i], 0) for i in range(p)]
    if not sum(over) or not sum(room):
        return None
    leave = [(k, i, share(over[i], n, k, i, sweep)) for k in range(n) for i in range(p) if over[i]]
    slots = []
    for k in range(n):
        end = 0
        for i in sorted(range(p), key=lambda i: -room[i]):
            if free := share(room[i], n, k, i, sweep):
                slots.append((k, i, end, end := end + free))
    spark = parts.sparkSession
    out = F.broadcast(spark.createDataFrame(leave, "owner int, old int, leave bigint"))
    into = F.broadcast(spark.createDataFrame(slots, "owner int, new int, low bigint, high bigint"))  # at most a row for each worker and part
    here = hist.select("v", F.col("part").alias("old"), F.col("n").alias("here"))
    mine = parts.withColumnRenamed("part", "old").join(owners, "v").join(out, ["owner", "old"]).join(vertices.select("v", F.col("w").alias("vw")), "v").join(here, ["v", "old"], "left").withColumn("here", F.coalesce("here", F.lit(0)))
    line = Window.partitionBy("owner", "old").orderBy("here", "v").rowsBetween(Window.unboundedPreceding, 0)
    amount = F.col("here") if by_edge else F.col("vw")
    going = (mine.where("here > 0") if by_edge else mine).withColumn("gone", F.sum(amount).over(line) - amount).where("gone < leave")
    placed = going.withColumn("at", F.sum("vw").over(Window.partitionBy("owner").orderBy("old", "here", "v").rowsBetween(Window.unboundedPreceding, 0)))
    return placed.join(into, "owner").where("at > low and at <= high").select("v", "old", "new", "owner")


def moved(parts: DataFrame, moves: DataFrame) -> DataFrame:
    """``parts`` after the moves."""
    return parts.join(moves.select("v", "new"), "v", "left").select("v", F.coalesce("new", "part").alias("part"))


def move_gain(hist: DataFrame, vertices: DataFrame, parts: DataFrame) -> DataFrame:
    """For every vertex and other part in its neighbourhood, what a single move changes in edges and cut of both parts and in all.

    Exact for one move; neighbours that move together have to be counted anew.
    """
    own = hist.join(parts, ["v", "part"]).select("v", F.col("n").alias("here"))
    x = hist.join(parts.withColumnRenamed("part", "old"), "v").where("part <> old").join(own, "v", "left").join(vertices.select("v", "deg"), "v").withColumn("here", F.coalesce("here", F.lit(0)))
    return x.select(
        "v", "old", F.col("part").alias("new"),
        (-F.col("here")).alias("old_edges"), F.col("n").alias("new_edges"),
        (2 * F.col("here") - F.col("deg")).alias("old_cut"), (F.col("deg") - 2 * F.col("n")).alias("new_cut"),
        (F.col("here") - F.col("n")).alias("cut"),
    )
