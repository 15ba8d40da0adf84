"""Parameters of the partitioner."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class PartitionConfig:
    n_workers: int = 4
    outer: int = 3
    balance: int = 5
    refine: int = 10
    x: float = 1.0
    y: float = 0.25
    rat_v: float = 0.10
    rat_e: float = 0.10
    seed: int = 42
    #: multi: all constraints and objectives; vertex: one of each; vertex_edge: two constraints, one objective.
    mode: str = "multi"
    stages: tuple[str, ...] = ("vertex_balance", "vertex_refine", "edge_balance", "edge_refine")
    init: str = "grow"
    init_max_sweeps: int = 0  # 0: to the end
    leftover: str = "random"
    #: set: all vertices at once; delta: the same result from a maintained histogram; worker: vertex by vertex within each worker.
    executor: str = "set"
    quota: str = "apportion"  # or strict: the one-more test of every single move
    multiplier: bool = True
    schedule_end: str = "exclusive"  # or inclusive: the last sweep uses x itself
    vertex_score: str = "degree"  # or count
    edge_score: str = "degree"
    edge_measure: str = "internal"  # or incident
    own_mask: bool = False  # whether a full part also loses its own vertices
    distribution: str = "random"
    #: gain: a balance phase that ends with a part over its limit forces the vertices of the weakest ties out of it, into parts
    #: below theirs, as label propagation alone cannot fill a part that no neighbourhood touches; none: never.
    release: str = "gain"
    release_sweeps: int = 8
    #: worker: best returns the best state of the last stage (within the limits first, then by its objectives); last the last one.
    keep: str = "best"
    blocks: int = 64  # worker: blocks of a worker's vertices in a sweep; as many as vertices visit them one by one
    early_stop: bool = False
    rebuild: int = 5  # delta: sweeps between rewrites of the histogram
    extra: dict = field(default_factory=dict)

    def __post_init__(self) -> None:
        known = {
            "mode": ("multi", "vertex", "vertex_edge"),
            "init": ("grow", "grow_majority", "random", "vertex_block", "edge_block", "label_prop", "bfs"),
            "executor": ("set", "delta", "worker"),
            "quota": ("apportion", "strict"),
            "schedule_end": ("exclusive", "inclusive"),
            "vertex_score": ("degree", "count"),
            "edge_score": ("degree", "count"),
            "edge_measure": ("internal", "incident"),
            "release": ("gain", "none"),
            "keep": ("best", "last"),
            "distribution": ("random", "vertex_block", "edge_block"),
        }
        for name, values in known.items():
            if getattr(self, name) not in values:
                raise ValueError(f"{name} must be one of {values}, not {getattr(self, name)!r}")
        if self.x < 0 or self.y < 0:
            raise ValueError("x and y must not be negative")
        if self.n_workers < 1 or min(self.outer, self.balance, self.refine) < 0:
            raise ValueError("worker and sweep counts must not be negative")

    @property
    def sweeps(self) -> int:
        """Of one stage's outer loop; the schedule of the multiplier runs over them."""
        return self.outer * (self.balance + self.refine)

    def factor(self, t: int) -> float:
        """The multiplier's share per worker after ``t`` sweeps: from y towards x."""
        last = max(self.sweeps - (self.schedule_end == "inclusive"), 1)
        return (self.x - self.y) * (t / last) + self.y

    def mult(self, t: int) -> float:
        return self.n_workers * self.factor(t) if self.multiplier else 1.0
