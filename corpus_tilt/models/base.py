"""Interfaces of main and weight models, in NumPy on small batches of prepared examples.

A main model knows its mean loss, gradient and Hessian-vector product under example weights, and
``dots``: each example's gradient times a vector, without the gradient itself.
"""

from __future__ import annotations

from typing import Protocol

import numpy as np


class MainModel(Protocol):
    size: int

    def init(self, seed: int) -> np.ndarray: ...
    def prepare(self, payloads: list) -> object: ...
    def losses(self, theta: np.ndarray, x: object) -> np.ndarray: ...
    def grad(self, theta: np.ndarray, x: object, w: np.ndarray) -> np.ndarray: ...
    def dots(self, theta: np.ndarray, x: object, v: np.ndarray) -> np.ndarray: ...
    def hvp(self, theta: np.ndarray, x: object, w: np.ndarray, v: np.ndarray) -> np.ndarray: ...


class WeightModel(Protocol):
    size: int

    def init(self, seed: int) -> np.ndarray: ...
    def prepare(self, payloads: list) -> object: ...
    def scores(self, alpha: np.ndarray, x: object) -> np.ndarray: ...
    def back(self, alpha: np.ndarray, x: object, up: np.ndarray) -> np.ndarray: ...


def softmax(z: np.ndarray, axis: int = -1) -> np.ndarray:
    e = np.exp(z - z.max(axis=axis, keepdims=True))
    return e / e.sum(axis=axis, keepdims=True)


def take(x: object, at: np.ndarray) -> object:
    """Rows of a prepared batch: arrays, sequences, or tuples of them."""
    if isinstance(x, tuple):
        return tuple(take(part, at) for part in x)
    if isinstance(x, np.ndarray):
        return x[at]
    return [x[i] for i in at]


def joined(a: object, b: object) -> object:
    """Two prepared batches in one."""
    if isinstance(a, tuple):
        return tuple(joined(p, q) for p, q in zip(a, b, strict=True))
    return np.concatenate([a, b]) if isinstance(a, np.ndarray) else [*a, *b]


def size_of(x: object) -> int:
    return len(x[0]) if isinstance(x, tuple) else len(x)


def numeric_hvp(model: MainModel, theta: np.ndarray, x: object, w: np.ndarray, v: np.ndarray, step: float = 1e-5) -> np.ndarray:
    """Central difference of the gradient: two gradients, whatever the model."""
    norm = np.linalg.norm(v)
    if norm == 0:
        return np.zeros_like(v)
    h = step / norm
    return (model.grad(theta + h * v, x, w) - model.grad(theta - h * v, x, w)) / (2 * h)
