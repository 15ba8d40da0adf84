"""The whole partitioner: a start, then rounds of balance and refinement on vertices, then on edges and cut."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.operators import metrics
from graphparts.operators.distribution import owners as owners_of
from graphparts.operators.graph import Graph
from graphparts.plans import initial
from graphparts.plans.config import PartitionConfig
from graphparts.plans.scratch import dropped, written
from graphparts.plans.sweeps import Sizes, Stage, admitted, histogram, moved, patch, patched, proposals, released, sizes
from graphparts.plans.worker import Workers, fits


@dataclass
class PartitionResult:
    graph: Graph
    p: int
    parts: DataFrame
    config: PartitionConfig
    history: list[dict] = field(default_factory=list)
    seconds: float = 0.0

    def quality(self) -> DataFrame:
        return metrics.quality(self.graph, self.parts, self.p)

    def history_frame(self) -> DataFrame:
        schema = "stage string, sweep int, mult double, moves bigint, max_v bigint, max_e bigint, max_c bigint, cut bigint, re double, rc double"
        return self.parts.sparkSession.createDataFrame([tuple(h[k] for k in ("stage", "sweep", "mult", "moves", "max_v", "max_e", "max_c", "cut", "re", "rc")) for h in self.history], schema)


def next_bias(re: float, rc: float, reached: bool, objective_cut: bool = True) -> tuple[float, float]:
    """The edge bias grows until edges are balanced; then it stays and the cut bias grows."""
    if not reached:
        return re + 1, rc
    return re, rc + 1 if objective_cut else rc


class _Run:
    def __init__(self, g: Graph, p: int, cfg: PartitionConfig, parts: DataFrame | None):
        self.g, self.p, self.cfg = g.stored(), p, cfg
        weight = F.coalesce(F.sum("w"), F.lit(0))
        n, self.m = self.g.vertices.agg(weight).first()[0], self.g.edges.agg(weight).first()[0]
        total = self.m if cfg.edge_measure == "internal" else 2 * self.m
        self.imb_v, self.imb_e = metrics.max_vertices(n, p, cfg.rat_v), metrics.max_edges(total, p, cfg.rat_e)
        self.limit_v = metrics.vertex_limit(n, p, cfg.rat_v)
        self.owners = written(owners_of(self.g, cfg.n_workers, cfg.distribution), "owners")
        self._parts = written(parts if parts is not None else initial.start(self.g, p, cfg.init, cfg.seed, cfg.init_max_sweeps), "parts")
        self.workers = Workers(self.g, self.owners, self._parts, p, cfg) if cfg.executor == "worker" or fits(self.g, self.owners, p, cfg) else None
        self.known: Sizes | None = None  # with workers: sizes now, as the changes of the last sweep make them
        self.best: tuple[tuple, DataFrame] | None = None
        self.watched = False
        self.hist: DataFrame | None = None
        self.patches = 0
        self.sweep = 0
        self.re = self.rc = 1.0
        self.history: list[dict] = []

    @property
    def parts(self) -> DataFrame:
        return self._parts if self.workers is None else self.workers.parts()

    def histogram(self) -> DataFrame:
        if self.cfg.executor != "delta":
            return histogram(self.g, self.parts)
        if self.workers is not None:
            self.stepped(None, None)  # messages under way are taken in
            return self.workers.histogram()
        if self.hist is None:
            self.hist = written(histogram(self.g, self._parts), "hist")
        return self.hist

    def apply(self, moves: DataFrame) -> None:
        if self.cfg.executor == "delta":
            self.hist = patched(self.hist, patch(self.g, moves))
            self.patches += 1
            if self.patches % self.cfg.rebuild == 0:
                self.hist = written(self.hist, "hist")
        before = self._parts
        self._parts = written(moved(before, moves), "parts")
        dropped(before.sparkSession, before)

    def note(self, kind: str, mult: float, moves: int, s: Sizes) -> None:
        """Sizes at the sweep's start go to the history."""
        self.history.append({"stage": kind, "sweep": self.sweep, "mult": mult, "moves": moves, "max_v": max(s.sv), "max_e": max(s.se), "max_c": max(s.sc), "cut": sum(s.sc) // 2, "re": self.re, "rc": self.rc})
        self.sweep += 1

    def value(self, s: Sizes) -> tuple:
        """How far a state is over the limits, then its objectives as shares of what random parts have."""
        cut, top = sum(s.sc) / 2, max(s.sc)
        over = max(max(s.sv) - self.limit_v, 0) / max(self.limit_v, 1)
        if self.cfg.mode != "vertex":
            over += max(max(s.se) - self.imb_e, 0) / max(self.imb_e, 1)
        return over, cut if self.cfg.mode != "multi" else cut + top * self.p / 2

    def stepped(self, stage: Stage | None, s: Sizes | None) -> tuple[int, Sizes]:
        """With workers: one sweep; the state before it is kept only while it is the best one of the last stage (``worker`` alone)."""
        before = self.workers.state
        out, exact, after, moves = self.workers.run(stage, s)
        kept = self.best[1] if self.best else None
        if self.watched and self.cfg.executor == "worker" and self.cfg.keep == "best" and (self.best is None or self.value(exact) < self.best[0]):
            if kept is not None:
                dropped(kept.sparkSession, kept)
            self.best = (self.value(exact), before)
        elif before is not kept:
            dropped(before.sparkSession, before)
        self.workers.state, self.known = out, after
        return moves, exact

    def one(self, kind: str, t: int) -> int:
        cfg, edge_stage = self.cfg, kind.startswith("edge")
        stage = Stage(kind, t, self.sweep, self.imb_v, self.imb_e, self.re, self.rc if cfg.mode != "vertex_edge" else 0.0)
        if self.workers is not None:
            if self.known is None or edge_stage and cfg.executor != "worker":  # set, delta: of the changes only vertices are counted
                self.stepped(None, None)
            count, s = self.stepped(stage, self.known)
        else:
            hist = self.histogram()
            if edge_stage and cfg.executor != "delta":
                hist = written(hist, "hist")
            s = sizes(self.g.vertices, self._parts, self.p, hist if edge_stage else None, cfg.edge_measure)
            moves = written(admitted(proposals(hist, self.g.vertices, self._parts, self.owners, s, stage, cfg), s, stage, cfg), "moves")
            count = moves.count()
            if count:
                self.apply(moves)
            if edge_stage and cfg.executor != "delta":
                dropped(hist.sparkSession, hist)
        self.note(kind, float(cfg.mult(t)), count, s)
        if edge_stage and kind.endswith("balance"):
            self.re, self.rc = next_bias(self.re, self.rc, max(s.se) <= self.imb_e, cfg.mode != "vertex_edge")
        return count

    def release(self, edges: bool) -> int:
        """Vertices forced out of parts over a limit, over at most ``release_sweeps`` sweeps."""
        cfg, total = self.cfg, 0
        for _ in range(cfg.release_sweeps):
            if self.workers is not None:
                hist, s = None, self.known
                if edges or s is None:  # vertices are counted exactly as they move, edges are not
                    _, s = self.stepped(None, None)
            else:
                hist = written(self.histogram(), "hist")
                s = sizes(self.g.vertices, self._parts, self.p, hist, cfg.edge_measure)
            if max(s.sv) > self.limit_v:
                kind = "vertex_release"
            elif edges and max(s.se) > self.imb_e:
                kind = "edge_release"
            else:
                return total
            if self.workers is not None:
                count, s = self.stepped(Stage(kind, 0, self.sweep, float(self.limit_v), self.imb_e), s)
            else:
                wanted = released(hist, self.g.vertices, self._parts, self.owners, s, self.limit_v, self.imb_e, kind == "edge_release", cfg.n_workers, self.sweep)
                moves = None if wanted is None else written(wanted, "moves")
                count = 0 if moves is None else moves.count()
                if count:
                    self.apply(moves)
            if hist is not None:
                dropped(hist.sparkSession, hist)
            self.note(kind, 0.0, count, s)
            total += count
            if not count:
                break
        return total

    def stage(self, name: str, last: bool) -> None:
        cfg, t = self.cfg, 0
        self.watched = last
        for _ in range(cfg.outer):
            quiet = True
            for step, times in (("balance", cfg.balance), ("refine", cfg.refine)):
                if f"{name}_{step}" not in cfg.stages:
                    continue
                for k in range(times):
                    count = self.one(f"{name}_{step}", t)
                    t += 1
                    quiet = quiet and not count
                    if cfg.early_stop and not count:
                        t += times - k - 1  # the schedule goes on as if they had run
                        break
                if step == "balance" and cfg.release == "gain" and self.release(name == "edge"):
                    quiet = False
            if cfg.early_stop and quiet:
                break
        if cfg.release == "gain" and any(x.startswith(name) for x in cfg.stages):
            self.release(name == "edge")  # early sweeps may admit more than fits, by up to 1 / y times

    def result(self) -> DataFrame:
        """The final parts: with ``keep="best"`` of the worker executor the best state of the last stage."""
        if self.workers is None:
            return self._parts
        if self.cfg.executor == "worker":
            self.stepped(None, None)  # the last state is judged too
        out = self.workers.parts(self.best[1] if self.best else None)
        if self.best:
            dropped(out.sparkSession, self.best[1])
        self.workers.close()
        return out


def partition(g: Graph, p: int, cfg: PartitionConfig | None = None, parts: DataFrame | None = None, **options) -> PartitionResult:
    """Divide ``g`` into ``p`` parts; ``parts`` is a start of one's own, ``options`` override fields of ``cfg``."""
    if p < 1:
        raise ValueError("p must be at least 1")
    base = cfg or PartitionConfig()
    cfg = PartitionConfig(**{**base.__dict__, **options})
    began = time.time()
    run = _Run(g, p, cfg, parts)
    run.stage("vertex", cfg.mode == "vertex")
    if cfg.mode != "vertex":
        run.stage("edge", True)
    return PartitionResult(run.g, p, run.result(), cfg, run.history, time.time() - began)
