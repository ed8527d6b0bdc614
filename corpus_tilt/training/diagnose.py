"""The alignment diagnostic: does the gradient of unseen examples agree with their own side's batches?"""

from __future__ import annotations

import numpy as np

from ..models.base import joined, size_of, softmax
from .outer import outer_step
from .source import Source


def alignment(main, theta: np.ndarray, x, batch, normalise: bool = False) -> np.ndarray:
    g = main.grad(theta, batch, np.full(size_of(batch), 1 / size_of(batch)))
    n = np.linalg.norm(g) if normalise else 1.0
    return main.dots(theta, x, g / n) if n else np.zeros(size_of(x))


def _unit(main, theta: np.ndarray, x) -> np.ndarray:
    g = main.grad(theta, x, np.full(size_of(x), 1 / size_of(x)))
    n = np.linalg.norm(g)
    return g / n if n else g


def acceleration_rates(source: Source, theta: np.ndarray, pairs: int = 20, b: int = 32, seed: int = 0) -> dict[str, float]:
    """Shares of all held-out specific (sar) and generic (gar) examples that align more with their own side's batch; strict."""
    main = source.main
    batches = [source.uniform(side, "train", b, range(pairs), "rates", seed) for side in (0, 1)]
    apart = [_unit(main, theta, s.x) - _unit(main, theta, g.x) for g, s in zip(*batches, strict=False)]
    shares = []
    for side in (1, 0):
        sign = 1 if side else -1

        def measure(x, sign=sign) -> dict[str, float]:
            return {"n": size_of(x)} | {str(i): float((sign * main.dots(theta, x, v) > 0).sum()) for i, v in enumerate(apart)}

        got = source.tally(measure, side, "valid")
        shares.append([got[str(i)] / got["n"] for i in range(len(apart))])
    sar, gar = shares
    return {"sar": float(np.mean(sar)), "gar": float(np.mean(gar)), "mean_rate": float((np.mean(sar) + np.mean(gar)) / 2), "sar_se": float(np.std(sar) / np.sqrt(len(sar))), "gar_se": float(np.std(gar) / np.sqrt(len(gar))), "n_pairs": float(len(apart))}


def mix_diagnostic(source: Source, theta: np.ndarray, alpha: np.ndarray, method: str = "cosine", n: int = 64, seed: int = 0) -> dict[str, float]:
    """One outer step over a batch of equal unseen parts: the mean weight before and after, by origin."""
    g, s = (source.uniform(side, "valid", n, range(1), "both", seed)[0] for side in (0, 1))
    x, xw = joined(g.x, s.x), joined(g.xw, s.xw)
    side = np.repeat([0, 1], [len(g), len(s)])
    spec = source.uniform(1, "train", n, range(1), "spec", seed)[0]
    step = outer_step(method, source.main, theta, x, spec.x, source.weight, alpha, xw)
    after = softmax(source.weight.scores(alpha + 20 * step.direction, xw))
    return {"generic_move": float((after - step.w)[side == 0].mean()), "specific_move": float((after - step.w)[side == 1].mean())}


def rank_correlation(x: list[float], y: list[float]) -> float:
    """Spearman's correlation (mean ranks for ties)."""

    def ranks(v: list[float]) -> np.ndarray:
        a = np.asarray(v)
        return np.array([(a < e).sum() + ((a == e).sum() - 1) / 2 for e in a])

    a, b = ranks(x), ranks(y)
    return float(np.corrcoef(a, b)[0, 1]) if a.std() and b.std() else 0.0
