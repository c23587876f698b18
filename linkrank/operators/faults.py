"""Planned sleeps and failures of workers."""

from __future__ import annotations

import time
from dataclasses import dataclass, field


class WorkerFailed(RuntimeError):
    """Raised in a worker that the plan lets fail."""


@dataclass
class FaultPlan:
    """sleep: seconds by (iteration, worker). fail: (iteration, worker) pairs that die at the end of that iteration.

    timeout: seconds after which a run in which someone waits for a dead worker counts
    as blocked; in sync_helped only those count in which no worker computes.
    """

    sleep: dict[tuple[int, int], float] = field(default_factory=dict)
    fail: set[tuple[int, int]] = field(default_factory=set)
    timeout: float | None = 60.0

    def before(self, iteration: int, worker: int) -> None:
        if any(w == worker and i < iteration for i, w in self.fail):
            raise WorkerFailed(f"worker {worker}")
        time.sleep(self.sleep.get((iteration, worker), 0.0))

    def sleep_all(self, iteration: int) -> None:
        """What a step with a barrier waits for: the longest sleeper; and a dead worker for ever."""
        if any(i < iteration for i, _ in self.fail):
            raise WorkerFailed("a step waits for a dead worker")
        time.sleep(max((s for (i, _), s in self.sleep.items() if i == iteration), default=0.0))
