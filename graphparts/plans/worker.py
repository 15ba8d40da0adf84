"""Sweeps worker by worker, as the method is described.

A worker owns some vertices with their neighbours, laid out once as arrays: own vertices in the order of
their ids, then its ghosts (neighbours that others own), and for each own vertex the workers that
hold it as a ghost. Arcs are laid out apart, in chunks of about 65 thousand, so no task that builds them
sees more; a neighbour is its place in the worker's arrays, and weights are left out where all are 1. The layout is kept partitioned by worker, so a sweep exchanges only labels: one
job reads a worker's labels and the messages sent to it, moves its vertices, and writes its new
labels, a message with the moved boundary vertices for each worker concerned, and the sizes of parts.

Within a sweep a worker goes through its vertices in blocks. What earlier blocks changed counts at
once, in labels, sizes and weights; within a block the moves into a part are admitted best first, up
to what the worker may still add. Blocks of one vertex (``blocks`` at least the worker's vertices) are the
vertex-by-vertex visit. Sizes are those at the sweep's start plus the multiplier times the worker's
own changes. A worker's arrays must fit one task, and each be below 2 GB: choose ``n_workers`` for that.

The executors ``set`` and ``delta`` run on the same layout where :func:`fits` says so: all of a worker's vertices
choose against the labels and sizes at the sweep's start, and one pass admits them, as the plans of
``plans/sweeps.py`` do and with the same results. ``delta`` keeps a histogram with the labels and
patches it along the arcs of moved vertices.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphparts.operators.graph import Graph
from graphparts.plans.config import PartitionConfig
from graphparts.plans.scratch import dropped, small_batches, written
from graphparts.plans.skew import SMALL, hashed
from graphparts.plans.sweeps import Sizes, Stage, part_state, share

_ARRAYS = {"ids": np.int64, "vw": np.int64, "ptr": np.int64, "deg": np.int64, "ghosts": np.int64, "sub_ptr": np.int64, "sub": np.int32}
_LAYOUT = "owner int, chunk int, " + ", ".join(f"{k} binary" for k in _ARRAYS) + ", idx binary, w binary"
#: Rows of a sweep: a worker's labels (0), a message to a worker (1), and sizes and changes of a part (2).
_STATE = "kind int, owner int, a binary, b binary, x array<bigint>"
_LABELS, _MESSAGE, _SIZES = 0, 1, 2
_CELLS = 1 << 18
#: The most arcs of a worker, and cells of its histogram, with which ``set`` and ``delta`` go through arrays; above it they are plans over tables.
MOST_ARCS, MOST_CELLS = 1 << 25, 1 << 24
_CHUNK = 1 << 16  # 256 kB of places, which the JVM's collector moves like any small object


def _ints(column: pa.ChunkedArray, missing: int = 0) -> np.ndarray:
    """Whole numbers of a column; nulls are filled in Arrow, so ids keep all 64 bits."""
    return column.fill_null(missing).to_numpy().astype(np.int64, copy=False)


def _freed() -> None:
    """What Arrow keeps of earlier groups goes back to the system, as many workers share an executor's memory."""
    pa.default_memory_pool().release_unused()


def _packed(held: np.ndarray) -> tuple[bytes, list[int]]:
    """A histogram in the least bytes a number that hold it, as it is exchanged in every sweep, with those bytes."""
    narrow = [x.astype(next(k for k in (np.int16, np.int32, np.int64) if not x.size or x.max() <= np.iinfo(k).max)) for x in held]
    return b"".join(x.tobytes() for x in narrow), [x.itemsize for x in narrow]


def _unpacked(kept: pa.Buffer, widths: list[int], n: int) -> np.ndarray:
    cells = kept.size // sum(widths)
    return np.stack([np.frombuffer(kept, f"i{k}", cells, at).astype(np.int64).reshape(n, -1) for k, at in zip(widths, (0, cells * widths[0]), strict=True)])


def _owners(rows: DataFrame) -> int:
    """How many workers ``rows(owner)`` names, counted from 0."""
    return (rows.agg(F.max("owner")).first()[0] or 0) + 1


def fits(g: Graph, owners: DataFrame, p: int, cfg: PartitionConfig) -> bool:
    """Whether every worker's arcs, and with ``delta`` its histogram, are few enough for the arrays of one task."""
    held = g.vertices.join(owners, "v").groupBy("owner").agg(F.count("*").alias("n"), F.sum("deg").alias("arcs"))
    top = held.agg(F.max("n").alias("n"), F.max("arcs").alias("arcs")).first()
    return (top.arcs or 0) <= MOST_ARCS and (cfg.executor != "delta" or (top.n or 0) * p <= MOST_CELLS)


def sides(g: Graph, owners: DataFrame, n_workers: int = 0) -> DataFrame:
    """What each worker holds, ``(owner, v, mine, vw, deg, arcs, subs, idx, chunk)``: its own vertices by id, then its ghosts.

    ``idx`` is a vertex's place in the worker's arrays, ``subs`` the workers that hold an own vertex as a ghost, and
    ``chunk`` the run of own vertices, of about 65 thousand arcs together, that its arcs are laid out with.
    """
    n_workers = n_workers or _owners(owners)
    # The vertices are the small side of all joins here, and a partition of them is less than a worker holds: they are hashed, the arcs not sorted.
    far = hashed(owners.select(F.col("v").alias("u"), F.col("owner").alias("owner_u")), g.vertices.count())
    each = g.arcs.select("v", "u").join(far, "u")
    if n_workers < 64:  # the owners around a vertex are bits of one number
        met = each.groupBy("v").agg(F.count("*").alias("arcs"), F.bit_or(F.expr("shiftleft(1L, owner_u)")).alias("bits"))
        near = met.select("v", "arcs", F.expr(f"filter(sequence(0, {n_workers - 1}), k -> shiftright(bits, k) & 1 = 1)").alias("around"))
    else:
        near = each.groupBy("v", "owner_u").agg(F.count("*").alias("n")).groupBy("v").agg(F.sum("n").alias("arcs"), F.array_sort(F.collect_list("owner_u")).alias("around"))
    own = g.vertices.select("v", F.col("w").alias("vw"), "deg").join(owners, "v").join(near, "v", "left")
    subs = F.coalesce(F.array_except("around", F.array("owner")), F.array().cast("array<int>"))
    mine = written(own.select("owner", "v", F.lit(True).alias("mine"), "vw", "deg", F.coalesce("arcs", F.lit(0)).alias("arcs"), subs.alias("subs")), "own")
    # An own vertex is a ghost of every worker around it, as arcs go both ways.
    ghosts = mine.select(F.explode("subs").alias("owner"), "v", F.lit(False).alias("mine"), F.lit(0).cast("bigint").alias("vw"), "deg", F.lit(0).cast("bigint").alias("arcs"), F.array().cast("array<int>").alias("subs"))
    line = Window.partitionBy("owner").orderBy(F.desc("mine"), "v")
    before = F.coalesce(F.sum("arcs").over(line.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    placed = mine.unionByName(ghosts).withColumn("idx", (F.row_number().over(line) - 1).cast("int"))
    out = written(placed.withColumn("chunk", F.floor(before / _CHUNK).cast("int")), "sides")
    dropped(out.sparkSession, mine)
    return out


def layout(g: Graph, side: DataFrame, n_workers: int = 0) -> DataFrame:
    """For each worker a row of arrays of its vertices (chunk -1), and rows of the arcs of runs of its own vertices."""

    def head(t: pa.Table) -> pa.Table:
        _freed()
        t = t.sort_by("idx")
        n = int(pa.compute.sum(t.column("mine")).as_py() or 0)
        v, subs = _ints(t.column("v")), t.column("subs").slice(0, n).combine_chunks()
        out = {
            "ids": v[:n],
            "vw": _ints(t.column("vw"))[:n],
            "ptr": np.concatenate([[0], np.cumsum(_ints(t.column("arcs"))[:n])]),
            "deg": _ints(t.column("deg")),
            "ghosts": v[n:],
            "sub_ptr": np.concatenate([[0], np.cumsum(pa.compute.list_value_length(subs).to_numpy(zero_copy_only=False))]),
            "sub": subs.flatten().to_numpy(zero_copy_only=False),
        }
        arrays = {k: pa.array([out[k].astype(kind).tobytes()], pa.binary()) for k, kind in _ARRAYS.items()}
        nothing = pa.array([None], pa.binary())
        return pa.table({"owner": pa.array([t.column("owner")[0].as_py()], pa.int32()), "chunk": pa.array([-1], pa.int32())} | arrays | {"idx": nothing, "w": nothing})

    def arcs(t: pa.Table) -> pa.Table:
        place, w = t.column("place").to_numpy(), t.column("w").to_numpy()
        weights = None if (w == 1).all() else w[np.argsort(place)].tobytes()
        idx = (np.sort(place) & 0x7FFFFFFF).astype(np.int32)
        held = {k: pa.array([None], pa.binary()) for k in _ARRAYS}
        return pa.table({"owner": t.column("owner").slice(0, 1), "chunk": t.column("chunk").slice(0, 1)} | held | {"idx": pa.array([idx.tobytes()], pa.binary()), "w": pa.array([weights], pa.binary())})

    mine = side.where("mine").select("v", "owner", "chunk", F.col("idx").alias("row"))
    n, n_workers = g.vertices.count(), n_workers or _owners(side)
    if n * n_workers <= 4 * SMALL and n <= SMALL:  # a vertex with its places at all workers: arcs are exchanged once, by chunk
        places = side.groupBy(F.col("v").alias("u")).agg(*(F.max(F.when(F.col("owner") == k, F.col("idx"))).alias(f"at{k}") for k in range(n_workers)))
        rows = g.arcs.join(F.broadcast(mine), "v").join(F.broadcast(places), "u")
        rows = rows.select("owner", "chunk", "row", F.array(*(f"at{k}" for k in range(n_workers)))[F.col("owner")].alias("idx"), "w")
    else:
        there = side.select("owner", F.col("v").alias("u"), "idx")
        rows = g.arcs.join(mine.hint("shuffle_hash"), "v").select("owner", "chunk", "row", "u", "w").join(there.hint("shuffle_hash"), ["owner", "u"]).select("owner", "chunk", "row", "idx", "w")
    heads = side.groupBy("owner").applyInArrow(head, _LAYOUT)
    # Row and place in one number, by which a chunk is sorted.
    packed = rows.select("owner", "chunk", (F.shiftleft(F.col("row").cast("bigint"), 32) + F.col("idx")).alias("place"), "w")
    return heads.unionByName(packed.groupBy("owner", "chunk").applyInArrow(arcs, _LAYOUT))


@dataclass
class Local:
    """A worker's arrays with the labels of its own vertices and ghosts; ``rows`` are where the own vertices of each chunk of arcs begin."""

    owner: int
    ids: np.ndarray
    vw: np.ndarray
    ptr: np.ndarray
    deg: np.ndarray
    ghosts: np.ndarray
    sub_ptr: np.ndarray
    sub: np.ndarray
    labels: np.ndarray
    idx: list[np.ndarray]
    w: list[np.ndarray | None]
    rows: np.ndarray
    came: list[tuple[np.ndarray, np.ndarray]]  # places whose labels messages changed, with the labels before
    held: np.ndarray | None = None  # delta: weight of edges, and sum of degrees, of own vertices towards each part, before what came

    @classmethod
    def of(cls, laid: pa.Table, sent: pa.Table) -> Local:
        """``laid`` with or without the rows of arcs, whose bytes are not copied."""
        chunks = laid.column("chunk").to_pylist()
        at = chunks.index(-1)
        row = {k: np.frombuffer(laid.column(k)[at].as_buffer(), kind) for k, kind in _ARRAYS.items()}
        n, labels, held, came = len(row["ids"]), None, None, []
        kinds = sent.column("kind").to_pylist()
        if _LABELS in kinds:
            labels = np.frombuffer(sent.column("a")[kinds.index(_LABELS)].as_py(), np.int32).copy()
            kept, widths = sent.column("b")[kinds.index(_LABELS)], sent.column("x")[kinds.index(_LABELS)].as_py()
            held = _unpacked(kept.as_buffer(), widths, n) if kept.is_valid and n else None
        else:
            labels = np.zeros(n + len(row["ghosts"]), np.int32)
        for k, kind in enumerate(kinds):
            if kind == _MESSAGE:
                v, part = np.frombuffer(sent.column("a")[k].as_py(), np.int64), np.frombuffer(sent.column("b")[k].as_py(), np.int32)
                for known, base in ((row["ids"], 0), (row["ghosts"], n)):
                    if len(known):
                        place = np.minimum(np.searchsorted(known, v), len(known) - 1)
                        hit = known[place] == v
                        if held is not None:
                            came.append((base + place[hit], labels[base + place[hit]]))
                        labels[base + place[hit]] = part[hit]
        idx, w = [], []
        for _, k in sorted((c, k) for k, c in enumerate(chunks) if c >= 0):
            idx.append(np.frombuffer(laid.column("idx")[k].as_buffer(), np.int32))
            weights = laid.column("w")[k]
            w.append(np.frombuffer(weights.as_buffer(), np.int64) if weights.is_valid else None)
        begins = np.cumsum([0, *map(len, idx)])
        rows = np.searchsorted(row["ptr"], begins)
        return cls(laid.column("owner")[0].as_py(), **row, labels=labels, idx=idx, w=w, rows=rows, came=came, held=held)

    def spans(self, a: int, b: int):
        """The arcs of own vertices a..b-1 chunk by chunk: begin and end of the vertices, neighbours' places, weights (None: all 1)."""
        for k in range(max(int(np.searchsorted(self.rows, a, "right")) - 1, 0), len(self.idx)):
            low, high = max(a, self.rows[k]), min(b, self.rows[k + 1])
            if low >= b:
                return
            if low < high:
                arcs = slice(self.ptr[low] - self.ptr[self.rows[k]], self.ptr[high] - self.ptr[self.rows[k]])
                yield low, high, self.idx[k][arcs], None if self.w[k] is None else self.w[k][arcs]

    def sizes(self, p: int) -> np.ndarray:
        """Vertices, twice the internal edges, edge ends and cut edges of each part, as far as this worker's vertices go."""
        n, between = len(self.ids), np.zeros(p * p)
        if self.held is not None:
            between = np.array([self.held[0][self.labels[:n] == i].sum(axis=0) for i in range(p)], float)
        for low, high, idx, w in self.spans(0, 0 if self.held is not None else n):
            own = np.repeat(self.labels[low:high].astype(np.int64) * p, np.diff(self.ptr[low : high + 1]))
            own += self.labels[idx]
            between += np.bincount(own, w, p * p)
        between = between.reshape(p, p)
        twice, ends = between.diagonal(), between.sum(axis=1)
        return np.rint([np.bincount(self.labels[:n], self.vw, p)[:p], twice, ends, ends - twice]).astype(np.int64)

    def ties(self, a: int, b: int, p: int, weights: np.ndarray | None = None) -> np.ndarray:
        """For own vertices a..b-1 the weight of their edges to each part."""
        out = np.zeros((b - a) * p)
        for low, high, idx, w in self.spans(a, b):
            cell = np.repeat(np.arange(high - low) * p, np.diff(self.ptr[low : high + 1]))
            cell += self.labels[idx]
            if weights is not None:
                w = weights[idx] if w is None else w * weights[idx]
            out[(low - a) * p : (high - a) * p] = np.bincount(cell, w, (high - low) * p)
        return out.reshape(b - a, p)


    def counted(self, p: int) -> None:
        """delta: the histogram of the labels now, patched by what came, or counted where there is none."""
        n = len(self.ids)
        if self.held is None:
            self.held = np.zeros((2, n, p), np.int64)
            step = max(1, _CELLS // p)
            for a in range(0, n, step):
                b = min(n, a + step)
                self.held[0, a:b], self.held[1, a:b] = self.ties(a, b, p), self.ties(a, b, p, self.deg)
        elif self.came:
            self.patch(np.concatenate([x for x, _ in self.came]), np.concatenate([x for _, x in self.came]), p)
        self.came = []

    def patch(self, moved: np.ndarray, old: np.ndarray, p: int) -> None:
        """What labels that changed from ``old`` at the places ``moved`` change in the histogram, by the arcs to them alone."""
        was = np.full(len(self.labels), -1, np.int32)
        was[moved] = old
        for low, high, idx, w in self.spans(0, len(self.ids)):
            at = np.flatnonzero(was[idx] >= 0)
            if not len(at):
                continue
            u, row = idx[at], np.searchsorted(self.ptr[low : high + 1], self.ptr[low] + at, "right") - 1
            weight = np.ones(len(at)) if w is None else w[at].astype(float)
            for k, x in enumerate((weight, weight * self.deg[u])):
                cells = (high - low) * p
                change = np.bincount(row * p + self.labels[u], x, cells) - np.bincount(row * p + was[u], x, cells)
                self.held[k, low:high] += np.rint(change).astype(np.int64).reshape(-1, p)


def _admitted(key: np.ndarray, order: np.ndarray, amounts: list[tuple[np.ndarray, np.ndarray, float, np.ndarray]]) -> np.ndarray:
    """Which movers fit: by target and ``order``, each with size + mult * (earlier amounts) + its own at most the limit."""
    line = np.lexsort((order, key))
    k = key[line]
    first = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
    ok = np.ones(len(k), bool)
    for size, amount, mult, limit in amounts:
        x = amount[line]
        run = np.cumsum(x) - x
        run -= np.repeat(run[first], np.diff(np.append(first, len(k))))
        ok &= size[k] + mult * run + x <= limit[k]
    out = np.zeros(len(k), bool)
    out[line] = ok
    return out


def _sweep(m: Local, start: np.ndarray, stage: Stage, cfg: PartitionConfig, p: int) -> np.ndarray:
    """Move vertices in place; returns the worker's changes of vertices, edges and cut of each part."""
    n, mult = len(m.ids), cfg.mult(stage.t)
    edge_stage, balance = stage.kind.startswith("edge"), stage.kind.endswith("balance")
    max_v, max_e, max_c = max(start[0].max(), stage.imb_v), max(start[1].max(), stage.imb_e), start[2].max()
    by_degree = (cfg.edge_score if edge_stage else cfg.vertex_score) == "degree"
    attract = lambda target, size: np.maximum(target / np.maximum(size, 1) - 1, 0)
    change = np.zeros((3, p))
    budget = None
    if cfg.quota == "apportion":  # whole shares of what a part may still take; only vertex balancing admits more than fits, early on
        f = cfg.factor(stage.t) if cfg.multiplier else 1.0
        f = f if stage.kind == "vertex_balance" else max(f, 1.0)
        rooms = np.maximum(max_v - start[0], 0)
        budget = np.array([share(int(r / f) if f > 0 else 1 << 40, cfg.n_workers, m.owner, i, stage.sweep) for i, r in enumerate(rooms)], float)
    step = max(1, min(-(-n // max(cfg.blocks, 1)), _CELLS // p))
    for a in range(0, n, step):
        b = min(n, a + step)
        ties = m.ties(a, b, p)
        degree, rows = ties.sum(axis=1), np.arange(b - a)
        own, vw = m.labels[a:b].astype(np.int64), m.vw[a:b].astype(float)
        v, e, c = start[0] + mult * change[0], start[1] + mult * change[1], start[2] + mult * change[2]
        add_e = ties if cfg.edge_measure == "internal" else np.broadcast_to(degree[:, None], ties.shape)
        if balance:
            score = m.ties(a, b, p, m.deg) if by_degree else ties.copy()
            score *= stage.re * attract(max_e, e) + stage.rc * attract(max_c, c) if edge_stage else attract(stage.imb_v, v)
        else:
            score = ties.copy()
        full = v[None, :] + vw[:, None] > max_v if budget is None else change[0][None, :] + vw[:, None] > budget
        if edge_stage:
            full |= (e[None, :] + add_e > max_e) | (c[None, :] + degree[:, None] - 2 * ties > max_c)
        if not cfg.own_mask:
            full[rows, own] = False
        score[full] = 0
        to = score.argmax(axis=1)
        best, here = score[rows, to], score[rows, own]
        go = np.flatnonzero((best > 0) & (best > here))
        if not len(go):
            continue
        y, gain = to[go], best[go] - here[go]
        amounts = [(v, vw[go], mult, np.full(p, max_v)) if budget is None else (change[0], vw[go], 1.0, budget)]
        if edge_stage:
            amounts += [(e, add_e[go, y], mult, np.full(p, max_e)), (c, degree[go] - 2 * ties[go, y], mult, np.full(p, max_c))]
        keep = _admitted(y, -gain, amounts) if len(go) > 1 else np.ones(1, bool)
        go, y = go[keep], y[keep]
        _moved(m, change, a, go, y, ties, degree, vw, add_e)
    return change


def _moved(m: Local, change: np.ndarray, a: int, go: np.ndarray, y: np.ndarray, ties: np.ndarray, degree: np.ndarray, vw: np.ndarray, add_e: np.ndarray) -> None:
    x = m.labels[a + go]
    for row, (out, into) in enumerate(((vw[go], vw[go]), (add_e[go, x], add_e[go, y]), (degree[go] - 2 * ties[go, x], degree[go] - 2 * ties[go, y]))):
        np.subtract.at(change[row], x, out)
        np.add.at(change[row], y, into)
    m.labels[a + go] = y


def _release(m: Local, start: np.ndarray, stage: Stage, cfg: PartitionConfig, p: int) -> np.ndarray:
    """Force the vertices of least loss out of parts over their limit, each worker its share, into shares of what other parts have left."""
    n, change, by_edge = len(m.ids), np.zeros((3, p)), stage.kind == "edge_release"
    limit_v, limit_e = int(stage.imb_v), stage.imb_e
    over = np.ceil(np.maximum(start[1] - limit_e, 0)) if by_edge else np.maximum(start[0] - limit_v, 0)
    leave = np.array([share(int(k), cfg.n_workers, m.owner, i, stage.sweep) for i, k in enumerate(over)], float)
    room = np.array([share(int(k), cfg.n_workers, m.owner, i, stage.sweep) for i, k in enumerate(np.maximum(limit_v - start[0], 0))], float)
    room_e = np.maximum(limit_e - start[1], 0) / cfg.n_workers
    room[over > 0] = 0
    if not leave.any() or not room.any():
        return change
    mine = np.flatnonzero(leave[m.labels[:n]] > 0)
    found_v, found_cost = [mine[:0]], [np.zeros(0)]
    by_room = np.lexsort((np.arange(p), room))[::-1]  # of equal ties the part with the most room, then the last
    step = max(1, min(-(-n // max(cfg.blocks, 1)), _CELLS // p))
    for a in range(0, n, step):
        v = mine[np.searchsorted(mine, a) : np.searchsorted(mine, a + step)]
        if not len(v):
            continue
        ties = m.ties(a, min(n, a + step), p)[v - a]
        rows, here = np.arange(len(v)), ties[np.arange(len(v)), m.labels[v]]
        to = by_room[np.where(room > 0, ties, -1)[:, by_room].argmax(axis=1)]
        cost = here - ties[rows, to]
        if by_edge:
            tied = here > 0
            v, cost = v[tied], cost[tied] / here[tied]
        found_v.append(v)
        found_cost.append(cost)
    found_v, found_cost = np.concatenate(found_v), np.concatenate(found_cost)
    for v in found_v[np.lexsort((found_v, found_cost))].tolist():
        x = int(m.labels[v])
        if leave[x] <= 0:
            continue
        ties = m.ties(v, v + 1, p)[0]
        free = np.where((room >= m.vw[v]) & ((room_e >= ties) if by_edge else True), ties, -1)
        to = int(np.lexsort((room, free))[-1])
        if free[to] < 0:
            continue
        leave[x] -= ties[x] if by_edge else m.vw[v]
        room[to] -= m.vw[v]
        room_e[to] -= ties[to]
        add_e = ties if cfg.edge_measure == "internal" else np.full(p, ties.sum())
        _moved(m, change, v, np.zeros(1, int), np.array([to]), ties[None, :], np.array([ties.sum()]), m.vw[v : v + 1].astype(float), add_e[None, :])
        if not (leave > 0).any():
            break
    return change


def _running(line: np.ndarray, key: np.ndarray, amount: np.ndarray) -> np.ndarray:
    """Sums of ``amount`` up to and with each row, along ``line`` and anew for each ``key``."""
    k, run = key[line], np.cumsum(amount[line])
    first = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
    run -= np.repeat(run[first] - amount[line][first], np.diff(np.append(first, len(k))))
    out = np.empty_like(run)
    out[line] = run
    return out


def _set_sweep(m: Local, start: np.ndarray, stage: Stage, cfg: PartitionConfig, p: int, wt: np.ndarray, room: np.ndarray) -> np.ndarray:
    """Move vertices in place, all at once, as ``proposals`` and ``admitted`` of ``plans/sweeps.py``; of the changes only vertices are counted."""
    n, workers, mult, change = len(m.ids), cfg.n_workers, cfg.mult(stage.t), np.zeros((3, p))
    edge_stage, balance = stage.kind.startswith("edge"), stage.kind.endswith("balance")
    max_v, max_e, max_c = max(start[0].max(), stage.imb_v), max(start[1].max(), stage.imb_e), start[2].max()
    by_degree = (cfg.edge_score if edge_stage else cfg.vertex_score) == "degree"
    found = []
    step = max(1, _CELLS // p)
    for a in range(0, n, step):
        b = min(n, a + step)
        ties = m.ties(a, b, p) if m.held is None else m.held[0, a:b].astype(float)
        if not balance:
            score = ties.copy()
        elif not by_degree:
            score = ties * wt
        else:
            score = (m.ties(a, b, p, m.deg) if m.held is None else m.held[1, a:b].astype(float)) * wt
        own, vw, deg, rows = m.labels[a:b].astype(np.int64), m.vw[a:b], m.deg[a:b, None], np.arange(b - a)
        add_e, add_c = ties if cfg.edge_measure == "internal" else np.broadcast_to(deg, ties.shape), deg - 2 * ties
        ok = start[0][None, :] + vw[:, None] <= max_v
        if edge_stage:
            ok &= (start[1] + add_e <= max_e) & (start[2] + add_c <= max_c)
        if not cfg.own_mask:
            ok[rows, own] = True
        score[~ok | (ties == 0)] = -1
        to = score.argmax(axis=1)  # of equal scores the lowest part, and below the own part before all others
        best, here = score[rows, to], score[rows, own]
        go = np.flatnonzero((best > 0) & (best > here))
        y = to[go]
        found.append((a + go, own[go], y, best[go] - np.maximum(here[go], 0), vw[go], add_e[go, y], add_c[go, y]))
    if not found:
        return change
    v, x, y, gain, vw, add_e, add_c = (np.concatenate(k) for k in zip(*found, strict=True))
    if not len(v):
        return change
    line = np.lexsort((v, -gain, y))
    used = _running(line, y, vw)
    if cfg.quota == "strict":
        ok = start[0][y] + mult * (used - vw) + vw <= max_v
    else:
        ok = used <= room[y] // workers + ((m.owner + y + stage.sweep) % workers < room[y] % workers)
    if edge_stage:
        ok &= (start[1][y] + mult * _running(line, y, add_e) <= max_e) & (start[2][y] + mult * _running(line, y, add_c) <= max_c)
    m.labels[v[ok]] = y[ok]
    change[0] = np.bincount(y[ok], vw[ok], p) - np.bincount(x[ok], vw[ok], p)
    return change


def _set_release(m: Local, start: np.ndarray, stage: Stage, cfg: PartitionConfig, p: int) -> np.ndarray:
    """Force vertices out of parts over their limit as ``released`` of ``plans/sweeps.py``; of the changes only vertices are counted."""
    n, workers, change, by_edge = len(m.ids), cfg.n_workers, np.zeros((3, p)), stage.kind == "edge_release"
    limit_v, limit_e = int(stage.imb_v), stage.imb_e
    over = np.ceil(np.maximum(start[1] - limit_e, 0)) if by_edge else np.maximum(start[0] - limit_v, 0)
    room = np.where(over > 0, 0, np.maximum(limit_v - start[0], 0))
    leave = np.array([share(int(k), workers, m.owner, i, stage.sweep) for i, k in enumerate(over)])
    by_room = sorted(range(p), key=lambda i: -room[i])
    free = np.array([share(int(room[i]), workers, m.owner, i, stage.sweep) for i in by_room])
    v = np.flatnonzero(leave[m.labels[:n]] > 0)
    if not len(v) or not free.any():
        return change
    here, step = np.zeros(n, np.int64), max(1, _CELLS // p)
    for a in range(0, n, step):
        b = min(n, a + step)
        ties = m.ties(a, b, p) if m.held is None else m.held[0, a:b]
        here[a:b] = ties[np.arange(b - a), m.labels[a:b]]
    if by_edge:
        v = v[here[v] > 0]
    v = v[np.lexsort((v, here[v], m.labels[v]))]
    old, amount = m.labels[v].astype(np.int64), here[v] if by_edge else m.vw[v]
    if len(v):
        gone = _running(np.arange(len(v)), old, amount) - amount
        v = v[gone < leave[old]]
    at = np.cumsum(m.vw[v])
    slot = np.searchsorted(np.cumsum(free), at)
    fit = (at > 0) & (slot < p)
    v, slot = v[fit], slot[fit]
    old, new = m.labels[v].astype(np.int64), np.array(by_room)[slot]
    m.labels[v] = new
    change[0] = np.bincount(new, m.vw[v], p) - np.bincount(old, m.vw[v], p)
    return change


def _apart(n: int, spark: SparkSession) -> int:
    """The least number of partitions, up to four for each worker, that puts the fewest workers of ``n`` into one by the hash of their number."""
    hashes = [r[0] for r in spark.range(n).select(F.hash(F.col("id").cast("int"))).collect()]
    return min(range(n, 4 * n + 1), key=lambda k: (max(Counter(x % k for x in hashes).values()), k))


class Workers:
    """The labels of all workers between sweeps; every sweep writes a new table and the one before can go."""

    def __init__(self, g: Graph, owners: DataFrame, parts: DataFrame, p: int, cfg: PartitionConfig):
        self.p, self.cfg, self.spark = p, cfg, parts.sparkSession
        side = sides(g, owners, cfg.n_workers)
        laid = written(layout(g, side, cfg.n_workers), "layout")
        self._laid = laid
        #: Kept on disk where it is computed, by worker, as memory is needed for what a sweep sends to Python; a lost executor's share is read again from the written table.
        self.layout = laid.repartition(_apart(cfg.n_workers, self.spark), "owner").persist(StorageLevel.DISK_ONLY)
        self.heads = self.layout.where(F.col("chunk") < 0)
        known = side.select("owner", "v").join(parts, "v").select("owner", "v", "part")

        def first(laid: pa.Table, rows: pa.Table) -> pa.Table:
            if not laid.num_rows:
                return pa.Table.from_pylist([], schema=_state_schema())
            v, part = _ints(rows.column("v")), _ints(rows.column("part")).astype(np.int32)
            sent = pa.table({"kind": [_MESSAGE], "owner": [0], "a": [v.tobytes()], "b": [part.tobytes()], "x": pa.array([None], pa.list_(pa.int64()))})
            m = Local.of(laid, sent)
            return pa.Table.from_pylist([{"kind": _LABELS, "owner": m.owner, "a": m.labels.tobytes(), "b": None, "x": None}], schema=_state_schema())

        with small_batches(self.spark):
            self.state = written(self.heads.groupBy("owner").cogroup(known.groupBy("owner")).applyInArrow(first, _STATE), "labels")
        dropped(self.spark, side)

    def run(self, stage: Stage | None, s: Sizes | None) -> tuple[DataFrame, Sizes, Sizes, int]:
        """One sweep, or with no stage only the sizes: the new table, exact sizes at its start, the sizes that changes make of them, moves."""
        p, cfg = self.p, self.cfg
        start = None if s is None else np.array([s.sv, s.se, s.sc], float)
        together, held = cfg.executor != "worker", cfg.executor == "delta"
        state = part_state(s, stage, cfg) if together and stage is not None and not stage.kind.endswith("release") else None
        wt, room = (None, None) if state is None else (state["wt"].to_numpy(), state["room"].to_numpy())

        def moved(m: Local) -> np.ndarray:
            if stage.kind.endswith("release"):
                return (_set_release if together else _release)(m, start, stage, cfg, p)
            return _set_sweep(m, start, stage, cfg, p, wt, room) if together else _sweep(m, start, stage, cfg, p)

        def step(laid: pa.Table, sent: pa.Table) -> pa.Table:
            if not laid.num_rows:
                return pa.Table.from_pylist([], schema=_state_schema())
            _freed()
            m = Local.of(laid, sent)
            if held:
                m.counted(p)
            n, exact, rows, change, moves = len(m.ids), m.sizes(p), [], np.zeros((3, p)), 0
            if stage is not None:
                old = m.labels[:n].copy()
                change = moved(m)
                went = np.flatnonzero(old != m.labels[:n])
                if held and len(went):
                    m.patch(went, old[went], p)
                moves = len(went)
                many = np.diff(m.sub_ptr)[went]
                who, to = np.repeat(went, many), np.concatenate([m.sub[m.sub_ptr[k] : m.sub_ptr[k + 1]] for k in went]) if moves else np.zeros(0, np.int32)
                for target in np.unique(to).tolist():
                    k = who[to == target]
                    rows.append({"kind": _MESSAGE, "owner": target, "a": m.ids[k].tobytes(), "b": m.labels[k].tobytes(), "x": None})
            kept, widths = _packed(m.held) if held else (None, None)
            rows.append({"kind": _LABELS, "owner": m.owner, "a": m.labels.tobytes(), "b": kept, "x": widths})
            change = np.rint(change).astype(np.int64)
            rows += [{"kind": _SIZES, "owner": i, "a": None, "b": None, "x": [*exact[:, i].tolist(), *change[:, i].tolist(), moves if i == 0 else 0]} for i in range(p)]
            return pa.Table.from_pylist(rows, schema=_state_schema())

        sent = self.state.where(F.col("kind") < _SIZES)
        with small_batches(self.spark):
            out = written(self.layout.groupBy("owner").cogroup(sent.groupBy("owner")).applyInArrow(step, _STATE), "labels")
        x = F.col("x")
        rows = out.where(F.col("kind") == _SIZES).coalesce(1).groupBy("owner").agg(*(F.sum(x[k]).alias(f"x{k}") for k in range(8))).collect()  # p rows
        exact, after, moves = Sizes([0] * p, [0] * p, [0] * p), Sizes([0] * p, [0] * p, [0] * p), 0
        for r in rows:
            i = r.owner
            exact.sv[i], exact.se[i], exact.sc[i] = r.x0, r.x1 // 2 if cfg.edge_measure == "internal" else r.x2, r.x3
            after.sv[i], after.se[i], after.sc[i] = r.x0 + r.x4, max(exact.se[i] + r.x5, 0), max(r.x3 + r.x6, 0)
            moves += r.x7
        return out, exact, after, moves

    def parts(self, state: DataFrame | None = None) -> DataFrame:
        """``(v, part)`` of a table of labels."""

        def rows(laid: pa.Table, sent: pa.Table) -> pa.Table:
            if not laid.num_rows:
                return pa.table({"v": pa.array([], pa.int64()), "part": pa.array([], pa.int32())})
            m = Local.of(laid, sent)
            return pa.table({"v": pa.array(m.ids), "part": pa.array(m.labels[: len(m.ids)])})

        labels = (self.state if state is None else state).where(F.col("kind") == _LABELS)
        with small_batches(self.spark):
            return written(self.heads.groupBy("owner").cogroup(labels.groupBy("owner")).applyInArrow(rows, "v bigint, part int"), "parts")

    def histogram(self) -> DataFrame:
        """delta: ``(v, part, n, dsum)`` as it is kept after a sweep, with no messages under way."""
        p = self.p

        def rows(laid: pa.Table, sent: pa.Table) -> pa.Table:
            if not laid.num_rows:
                return pa.table({"v": pa.array([], pa.int64()), "part": pa.array([], pa.int32()), "n": pa.array([], pa.int64()), "dsum": pa.array([], pa.int64())})
            m = Local.of(laid, sent)
            held = np.zeros((2, 0, p), np.int64) if m.held is None else m.held
            v, part = np.nonzero(held[0])
            return pa.table({"v": m.ids[v], "part": part.astype(np.int32), "n": held[0][v, part], "dsum": held[1][v, part]})

        labels = self.state.where(F.col("kind") == _LABELS)
        with small_batches(self.spark):
            return written(self.heads.groupBy("owner").cogroup(labels.groupBy("owner")).applyInArrow(rows, "v bigint, part int, n bigint, dsum bigint"), "hist")

    def close(self) -> None:
        self.layout.unpersist()
        dropped(self.spark, self._laid, self.state)


def _state_schema() -> pa.Schema:
    return pa.schema([("kind", pa.int32()), ("owner", pa.int32()), ("a", pa.binary()), ("b", pa.binary()), ("x", pa.list_(pa.int64()))])
