"""Optimizers on parameter vectors; their state is a plain dict, so it can be checkpointed."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Sgd:
    rate: float

    def start(self, size: int) -> dict:
        return {}

    def step(self, x: np.ndarray, g: np.ndarray, state: dict) -> np.ndarray:
        return x - self.rate * g


@dataclass
class Adam:
    rate: float
    b1: float = 0.9
    b2: float = 0.999
    eps: float = 1e-8

    def start(self, size: int) -> dict:
        return {"m": np.zeros(size), "s": np.zeros(size), "t": 0}

    def step(self, x: np.ndarray, g: np.ndarray, state: dict) -> np.ndarray:
        state["t"] += 1
        state["m"] = self.b1 * state["m"] + (1 - self.b1) * g
        state["s"] = self.b2 * state["s"] + (1 - self.b2) * g * g
        m, s = state["m"] / (1 - self.b1 ** state["t"]), state["s"] / (1 - self.b2 ** state["t"])
        return x - self.rate * m / (np.sqrt(s) + self.eps)
