"""Options and results of a ranking run."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame

LEVELS = {
    ("sync", False): ("global",),
    ("sync", True): ("node", "global"),
    ("async", False): ("block",),
    ("async", True): ("node", "block"),
}


@dataclass(frozen=True)
class RankConfig:
    """Options shared by all methods.

    damping, tol: of the rank equation and of its largest change a step.
    tol_mode: "absolute", or "uniform_relative" for tol / n.
    max_iter: steps (or rounds) at most; blocks: workers' shares of the vertices.
    block_how: "hash", "range", or "edges" for shares of equal in-edges.
    init: "uniform", or a frame (id, rank) to start from.
    dangling: "leak" as in the rank equation, or "redistribute" evenly.
    freeze, freeze_factor, freeze_guard: stop recomputing vertices whose change fell
        below freeze_factor * tol, at once ("paper") or after two quiet steps, with
        thawing when an input moves ("safe").
    twins: one computation for all vertices with equal in-neighbours.
    fused: shares are computed in the step's own plan; else they are stored first.
    sum_mode: "double", "ordered" (by source) or "decimal" for sums that do not
        depend on the order of rows.
    staleness, schedule_seed: bound and seed of the delays of an adversarial schedule.
    inner_sweeps: sweeps over a block's own edges between two exchanges.
    check_every: steps between two looks at the change, and between two stored states.
    partitions: of a step's frames. max_edges: beyond which a method in one task refuses a graph; None: it takes any.
    hub_degree: out-links above which a vertex's edges do not lie in one partition.
    """

    damping: float = 0.85
    tol: float = 1e-16
    tol_mode: str = "absolute"
    max_iter: int = 250
    blocks: int = 8
    block_how: str = "hash"
    init: str | DataFrame = "uniform"
    dangling: str = "leak"
    freeze: bool = False
    freeze_factor: float = 1e-5
    freeze_guard: str = "paper"
    twins: bool = False
    fused: bool = True
    sum_mode: str = "double"
    staleness: int = 0
    schedule_seed: int | None = None
    inner_sweeps: int = 1
    check_every: int = 1
    partitions: int | None = None
    max_edges: int | None = None
    hub_degree: int = 1_000_000

    def only(self, method: str, **possible) -> None:
        """Refuses options that a method has no meaning for: each name's value must be among those given."""
        for name, values in possible.items():
            value = getattr(self, name)
            if not any(value is v or (isinstance(value, (str, int, float)) and value == v) for v in values):
                raise ValueError(f"{method}: {name}={value!r} is not possible")

    def bound(self, n: int) -> float:
        """The change at which a run over n vertices stops."""
        return self.tol / max(n, 1) if self.tol_mode == "uniform_relative" else self.tol


@dataclass
class RankResult:
    """Ranks and the course of a run.

    history: a dict for each step and block: iteration, block (None: all), max_delta,
    l1_delta, active, edges_touched, seconds.
    """

    ranks: DataFrame
    method: str
    iterations: int
    converged: bool
    stop_reason: str
    history: list[dict] = field(default_factory=list)
    block_iterations: dict[int, int] = field(default_factory=dict)

    def history_frame(self) -> DataFrame:
        schema = "method string, iteration int, block int, max_delta double, l1_delta double, active long, edges_touched long, seconds double"
        names = ["iteration", "block", "max_delta", "l1_delta", "active", "edges_touched", "seconds"]
        return self.ranks.sparkSession.createDataFrame([(self.method, *(h.get(k) for k in names)) for h in self.history], schema)
