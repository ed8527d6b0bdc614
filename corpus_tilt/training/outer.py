"""Outer steps: how the weight model's parameters move, in one frame.

Each method gives every generic example a utility q; with w the batch softmax of the scores,
the ascent direction is sum_x w_x (q_x - sum w q) grad s_x.  Signs: an example whose gradient
agrees with the specific one gains weight, in all methods.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from ..models.base import size_of, softmax


@dataclass
class OuterStep:
    direction: np.ndarray
    v: np.ndarray | None
    q: np.ndarray
    w: np.ndarray
    flag: str = ""


def _uniform(x) -> np.ndarray:
    return np.full(size_of(x), 1 / size_of(x))


def alpha_direction(weight, alpha: np.ndarray, xw, w: np.ndarray, q: np.ndarray) -> np.ndarray:
    return weight.back(alpha, xw, w * (q - w @ q))


def utilities(method: str, main, theta: np.ndarray, xg, w: np.ndarray, xs, rho: float = 0.5, v: np.ndarray | None = None, eta_v: float = 0.1, damping: float = 0.0, specific=None, new_v: bool = False) -> tuple[np.ndarray, np.ndarray | None, str]:
    """(q, next v, flag).  ``specific`` may be another model object for a different specific loss."""
    own = specific or main
    target = lambda t: own.grad(t, xs, _uniform(xs))
    if method == "unroll_first":
        return rho * main.dots(theta, xg, target(theta)), None, ""
    if method == "unroll":
        ahead = theta - rho * main.grad(theta, xg, w)
        return rho * main.dots(theta, xg, target(ahead)), None, ""
    if method == "cosine":
        gw, gs = main.grad(theta, xg, w), target(theta)
        lw, ls = np.linalg.norm(gw), np.linalg.norm(gs)
        if lw == 0 or ls == 0:
            return np.zeros(size_of(xg)), None, "zero gradient"
        along = gs / ls - (gw @ gs) / (lw * ls) * gw / lw
        return main.dots(theta, xg, along / lw), None, ""
    if method == "implicit":
        v = np.zeros_like(theta) if v is None else v
        moved = v - eta_v * (main.hvp(theta, xg, w, v) + damping * v + target(theta))
        return -main.dots(theta, xg, moved if new_v else v), moved, ""
    raise ValueError(f"unknown method {method}")


def outer_step(method: str, main, theta: np.ndarray, xg, xs, weight, alpha: np.ndarray, xw, **how) -> OuterStep:
    w = softmax(weight.scores(alpha, xw))
    q, v, flag = utilities(method, main, theta, xg, w, xs, **how)
    return OuterStep(alpha_direction(weight, alpha, xw, w, q), v, q, w, flag)


def reweight(main, theta: np.ndarray, xg, xs, eta: float) -> np.ndarray:
    """Batch weights after one outer step from uniform with free parameters; clipped at zero, normalised; uniform if nothing is left."""
    u = _uniform(xg)
    q = main.dots(theta, xg, main.grad(theta, xs, _uniform(xs)))
    w = np.maximum(u + eta * q, 0)
    return w / w.sum() if w.sum() > 0 else u


def steepest_direction(g: np.ndarray) -> np.ndarray:
    """The unit vector along which the loss falls fastest."""
    n = np.linalg.norm(g)
    return -g / n if n else np.zeros_like(g)


def cone_direction(gradients: np.ndarray, target: np.ndarray, iterations: int = 2000, rate: float = 0.05) -> np.ndarray:
    """Non-negative a that best aligns the combination a . gradients with ``target`` (reference solver, projected ascent)."""
    a = np.full(len(gradients), 1 / len(gradients))
    t = target / np.linalg.norm(target)
    for _ in range(iterations):
        g = a @ gradients
        n = np.linalg.norm(g)
        if n == 0:
            break
        a = np.maximum(a + rate * gradients @ (t - (g @ t) / n * g / n) / n, 0)
        a /= a.sum()
    return a


def solve_inner(main, xg, w: np.ndarray, ridge_start: np.ndarray, steps: int = 60) -> np.ndarray:
    """The inner optimum of a small convex model, by Newton steps with an explicit Hessian."""
    theta, eye = ridge_start.copy(), np.eye(main.size)
    for _ in range(steps):
        g = main.grad(theta, xg, w)
        if np.linalg.norm(g) < 1e-12:
            break
        h = np.array([main.hvp(theta, xg, w, e) for e in eye])
        theta = theta - np.linalg.solve(h + 1e-12 * eye, g)
    return theta


def exact_hypergradient(main, xg, xs, weight, alpha: np.ndarray, xw) -> tuple[float, np.ndarray]:
    """The specific loss at the inner optimum and its gradient in alpha (ascent of -loss is minus it)."""
    w = softmax(weight.scores(alpha, xw))
    theta = solve_inner(main, xg, w, main.init(0))
    h = np.array([main.hvp(theta, xg, w, e) for e in np.eye(main.size)])
    v = -np.linalg.solve(h, main.grad(theta, xs, _uniform(xs)))
    q = -main.dots(theta, xg, v)
    return float(main.losses(theta, xs).mean()), -alpha_direction(weight, alpha, xw, w, q)
