"""Cost counters: evaluations of the weight model, forwards, backwards and Hessian products of the main model, rows, bytes and time."""

from __future__ import annotations

import time
from collections import Counter


class CostMeter:
    KINDS = ("weight_fwd", "main_fwd", "main_bwd", "hvp", "rows_in", "rows_kept", "bytes_in")

    def __init__(self) -> None:
        self.total: Counter = Counter()
        self.steps: list[dict] = []
        self.began, self.seconds = time.time(), 0.0

    def step(self, **counts: int) -> None:
        self.total.update(counts)
        self.steps.append(counts)

    def tick(self) -> None:
        """Note the time since the run began."""
        self.seconds = time.time() - self.began

    def summary(self) -> dict[str, float]:
        out = {k: self.total[k] for k in self.KINDS} | {"seconds": self.seconds}
        if self.total["rows_kept"]:
            out["ratio"] = self.total["rows_in"] / self.total["rows_kept"]
            out["unseen_share"] = 1 - self.total["rows_kept"] / self.total["rows_in"] if self.total["rows_in"] else 0.0
        return out
