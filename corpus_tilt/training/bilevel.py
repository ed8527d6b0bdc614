"""The online two-level loop, the other strategies, and fine-tuning, on any ``Source`` of batches.

Order of a step: sample a large generic and a small specific batch; filter the large one with the
old weights; step the main model; then step the weight model with the new main model on a fresh
uniform sub-batch.  Only arrays cross steps, so plans never grow.  On the cluster, ``delay`` steps
share one weight model and one job; with a delay of one the loop is the same as in the driver.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

from ..models.base import softmax
from .costs import CostMeter
from .optim import Sgd
from .outer import outer_step, reweight
from .source import Batch, Draw, Source, choose, hashes, mean_losses


@dataclass
class Run:
    method: str
    theta: np.ndarray
    trajectory: list[np.ndarray]
    cost: CostMeter
    metrics: list[dict] = field(default_factory=list)
    v: np.ndarray | None = None


@dataclass
class Setting:
    """Batch sizes, rates and the variant; ``delay`` large batches share one alpha (1 is the plain loop)."""

    steps: int = 60
    small: int = 32
    large: int = 512
    rate: float = 2.0
    weight_rate: float = 20.0
    rho: float = 2.0
    eta_v: float = 0.5
    filter: str = "gumbel"
    dense: bool = False
    delay: int = 1
    seed: int = 0
    optimizer: type | None = None


    specific: object = None  # another model object, for a specific loss that is not the generic one

    def optimise(self, main) -> tuple:
        opt = (self.optimizer or Sgd)(self.rate)
        return opt, opt.start(main.size)

    def blocks(self) -> list[range]:
        return [range(lo, min(lo + self.delay, self.steps)) for lo in range(0, self.steps, self.delay)]


def _finite(theta: np.ndarray, alpha: np.ndarray) -> bool:
    return bool(np.isfinite(theta).all() and np.isfinite(alpha).all())


def _even(n: int) -> np.ndarray:
    return np.full(n, 1 / n)


def _seen(main, batch: Batch) -> object:
    """The rows as the model sees generic ones: a model that keeps past captions has them as negatives."""
    return main.against_past(batch.x) if hasattr(main, "against_past") else batch.x


def train_bilevel(source: Source, outer: str, s: Setting, theta: np.ndarray | None = None, alpha: np.ndarray | None = None) -> Run:
    """Algorithm of the module's text; ``outer`` is unroll, unroll_first, implicit or cosine."""
    main, weight = source.main, source.weight
    theta = main.init(s.seed) if theta is None else theta
    alpha = weight.init(s.seed) if alpha is None else alpha
    opt, state = s.optimise(main)
    run = Run(outer, theta, [alpha], CostMeter())
    source.expect(draws(("unroll",), s))
    for block in s.blocks():
        held = alpha
        big = source.filtered(held, s.filter, s.large, s.small, block, s.seed)
        spec = source.uniform(1, "train", s.small, block, "spec", s.seed)
        for (kept, sub, scored, size), own in zip(big, spec, strict=True):
            if s.dense:
                kept, w = sub, softmax(weight.scores(held, sub.xw))
            else:
                w = _even(len(kept))
            theta = opt.step(theta, main.grad(theta, _seen(main, kept), w), state)
            more = {"v": run.v, "eta_v": s.eta_v} if outer == "implicit" else {}
            step = outer_step(outer, main, theta, _seen(main, sub), own.x, weight, alpha, sub.xw, rho=s.rho, specific=s.specific, **more)
            alpha = alpha + s.weight_rate * step.direction
            run.v = step.v
            if not _finite(theta, alpha):
                run.metrics.append({"step": len(run.trajectory) - 1, "stopped": 1.0})
                return run
            run.theta = theta
            run.trajectory.append(alpha)
            run.cost.step(weight_fwd=0 if s.dense else scored, main_fwd=len(kept), main_bwd=len(kept) + len(sub) + len(own), hvp=len(sub) if outer == "implicit" else 0, rows_in=scored, rows_kept=len(kept), bytes_in=size)
        run.cost.tick()
    return run


def train_frozen(source: Source, trajectory: list[np.ndarray], s: Setting, theta: np.ndarray | None = None) -> Run:
    """Train the main model under given weight parameters, one entry a step (the last one repeats)."""
    main = source.main
    theta = main.init(s.seed) if theta is None else theta
    opt, state = s.optimise(main)
    run = Run("frozen", theta, list(trajectory), CostMeter())
    source.expect(draws(("unroll",), s))
    at = 0
    while at < s.steps:  # steps that share their weights are one job
        block = range(at, at + 1 if at < len(trajectory) - 1 else s.steps)
        for kept, _, scored, size in source.filtered(trajectory[min(at, len(trajectory) - 1)], s.filter, s.large, s.small, block, s.seed):
            theta = opt.step(theta, main.grad(theta, _seen(main, kept), _even(len(kept))), state)
            run.cost.step(weight_fwd=scored, main_fwd=len(kept), main_bwd=len(kept), rows_in=scored, rows_kept=len(kept), bytes_in=size)
        run.cost.tick()
        at = block.stop
    run.theta = theta
    return run


def train_shuffled(source: Source, trajectory: list[np.ndarray], s: Setting) -> Run:
    """The learned weights of ``trajectory`` in random order."""
    order = np.random.default_rng(s.seed + 1).permutation(len(trajectory))
    return train_frozen(source, [trajectory[i] for i in order], s)


def tune_path(source: Source, theta: np.ndarray, steps: int = 60, small: int = 32, rate: float = 2.0, seed: int = 0, every: int = 5) -> list[np.ndarray]:
    """Go on training on the specific set; the parameters at the start and after each ``every`` steps."""
    main, path = source.main, []
    batches = source.uniform(1, "train", small, range(steps), "tune", seed)
    for t in range(len(batches) + 1):
        if t % every == 0:
            path.append(theta)
        if t < len(batches):
            theta = theta - rate * main.grad(theta, batches[t].x, _even(len(batches[t])))
    return path


def best_of(source: Source, paths: list[list[np.ndarray]]) -> list[np.ndarray]:
    """Of each path the parameters of the least validation loss (the first if there are several); one pass over the split."""
    losses = iter(mean_losses(source, [theta for path in paths for theta in path], "valid"))
    out = []
    for path in paths:
        own = [v if v < math.inf else math.inf for v in (next(losses) for _ in path)]
        out.append(path[own.index(min(own))])
    return out


def fine_tune(source: Source, theta: np.ndarray, steps: int = 60, small: int = 32, rate: float = 2.0, seed: int = 0, every: int = 5) -> np.ndarray:
    """Go on training on the specific set; the step with the least validation loss is returned."""
    return best_of(source, [tune_path(source, theta, steps, small, rate, seed, every)])[0]


def draws(methods: tuple[str, ...], s: Setting, tune: bool = False, shares: tuple[float, ...] | None = None) -> list[Draw]:
    """The batches that ``methods`` will ask for and that no parameters decide on; ``tune``: those of fine-tuning too."""
    steps, out = range(s.steps), []
    for name in methods:
        if name in ("generic_only", "contrastive_select"):
            out.append(Draw(0, s.small, steps, "plain", s.seed))
        if name == "mixing":
            for own in (round(p * s.small) for p in shares or SHARES):
                out += [Draw(0, s.small - own, steps, "plain", s.seed), Draw(1, own, steps, "mix", s.seed)]
        if name == "domain_classifier":
            out += [Draw(side, 32, range(min(300, 4 * s.steps)), "balanced", s.seed) for side in (0, 1)]
        if name == "batch_reweight":
            out += [Draw(side, s.small, steps, "free", s.seed) for side in (0, 1)]
        if name == "loss_input_weights":
            out.append(Draw(0, 4 * s.small, steps, "loss", s.seed))
        if name in ("unroll", "cosine", "implicit"):
            out.append(Draw(0, s.large, steps, "big", s.seed))
        if name in ("loss_input_weights", "unroll", "cosine", "implicit"):
            out.append(Draw(1, s.small, steps, "spec", s.seed))
    if tune or "contrastive_select" in methods:
        out.append(Draw(1, s.small, steps, "tune", s.seed))
    return list(dict.fromkeys(out))


# --- other strategies ------------------------------------------------------------------------------


def _plain_training(source: Source, s: Setting, among=None, share: float = 0.0, theta: np.ndarray | None = None, label: str = "") -> Run:
    """Uniform batches of the generic rows (of ``among``), a fixed share of each from the specific set."""
    main = source.main
    theta = main.init(s.seed) if theta is None else theta
    opt, state = s.optimise(main)
    own = round(share * s.small)
    cost = CostMeter()
    generic = source.uniform(0, "train", s.small - own, range(s.steps), "plain", s.seed, among) if own < s.small else [None] * s.steps
    specific = source.uniform(1, "train", own, range(s.steps), "mix", s.seed) if own else [None] * s.steps
    for a, b in zip(generic, specific, strict=False):
        n = max(sum(len(x) for x in (a, b) if x is not None), 1)
        g = sum(main.grad(theta, x, np.full(len(y), 1 / n)) for x, y in ((_seen(main, a), a) if a is not None else (None, ()), (b.x, b) if b is not None else (None, ())) if len(y))
        theta = opt.step(theta, g, state)
        cost.step(main_fwd=n, main_bwd=n, rows_in=n, rows_kept=n)
    return Run(label, theta, [], cost)


def run_generic_only(source: Source, s: Setting) -> Run:
    return _plain_training(source, s, label="generic_only")


#: Of which mixing chooses.
SHARES = (0.1, 0.25, 0.5)


def run_mixing(source: Source, s: Setting, share: float | None = None, grid: tuple[float, ...] = SHARES) -> Run:
    """``share`` of each batch is specific; without one it is chosen on the validation split."""
    runs = [_plain_training(source, s, share=p, label="mixing") for p in ((share,) if share is not None else grid)]
    if len(runs) == 1:
        return runs[0]
    losses = mean_losses(source, [r.theta for r in runs], "valid")
    return runs[losses.index(min(losses))]


def run_contrastive(source: Source, s: Setting, keep: float = 1 / 8) -> Run:
    """Pre-train, fine-tune, keep the generic rows whose loss falls most between the two, resume on them."""
    main = source.main
    first = run_generic_only(source, s)
    tuned = fine_tune(source, first.theta, s.steps, s.small, s.rate, s.seed)
    before = first.theta
    among = source.best("main", lambda x: main.losses(before, x) - main.losses(tuned, x), keep, s.small)
    run = _plain_training(source, s, among, theta=first.theta, label="contrastive_select")
    total = source.total(0, "train")
    run.cost.step(main_fwd=2 * total, rows_in=total, rows_kept=source.total(0, "train", among))
    return run


def fit_domain_classifier(source: Source, steps: int = 300, batch: int = 64, rate: float = 2.0, seed: int = 0) -> np.ndarray:
    """Cross-entropy of generic against specific on balanced batches, with the weight model's architecture."""
    weight = source.weight
    beta, bias = weight.init(seed), 0.0
    both = zip(*(source.uniform(side, "train", batch // 2, range(steps), "balanced", seed) for side in (0, 1)), strict=False)
    for g, p in both:
        up_g = 1 / (1 + np.exp(-(weight.scores(beta, g.xw) + bias))) / len(g)
        up_p = (1 / (1 + np.exp(-(weight.scores(beta, p.xw) + bias))) - 1) / len(p)
        beta = beta - rate * (weight.back(beta, g.xw, up_g) + weight.back(beta, p.xw, up_p))
        bias -= rate * (up_g.sum() + up_p.sum())
    return beta


def run_classifier(source: Source, s: Setting, keep: float = 1 / 8) -> Run:
    weight = source.weight
    beta = fit_domain_classifier(source, steps=min(300, 4 * s.steps), seed=s.seed)
    among = source.best("weight", lambda xw: weight.scores(beta, xw), keep, s.small)
    run = _plain_training(source, s, among, label="domain_classifier")
    run.trajectory = [beta]
    total = source.total(0, "train")
    run.cost.step(weight_fwd=total, rows_in=total, rows_kept=source.total(0, "train", among))
    return run


def run_batch_reweight(source: Source, s: Setting) -> Run:
    """Each step reweights its batch from uniform by one outer step; nothing is kept between steps."""
    main = source.main
    theta, cost = main.init(s.seed), CostMeter()
    opt, state = s.optimise(main)
    batches = [source.uniform(side, "train", s.small, range(s.steps), "free", s.seed) for side in (0, 1)]
    for own, spec in zip(*batches, strict=True):
        x = _seen(main, own)
        theta = opt.step(theta, main.grad(theta, x, reweight(main, theta, x, spec.x, s.weight_rate)), state)
        cost.step(main_fwd=len(own), main_bwd=2 * len(own) + len(spec), rows_in=len(own), rows_kept=len(own))
    return Run("batch_reweight", theta, [], cost)


def run_loss_input(source: Source, s: Setting) -> Run:
    """The look-ahead step with a weight model whose one input is the example's loss."""
    from ..models.weight_models import MlpWeight

    main, weight = source.main, MlpWeight(1, 8)
    theta, alpha = main.init(s.seed), weight.init(s.seed)
    opt, state = s.optimise(main)
    run = Run("loss_input_weights", theta, [alpha], CostMeter())
    batches = source.uniform(0, "train", 4 * s.small, range(s.steps), "loss", s.seed)
    specific = source.uniform(1, "train", s.small, range(s.steps), "spec", s.seed)
    for t, (big, spec) in enumerate(zip(batches, specific, strict=True)):
        u = hashes(big.ids, f"{s.seed}/{t}/g")
        kept = big.take(choose(s.filter, weight.scores(alpha, main.losses(theta, big.x)[:, None]), s.small, u, u[: s.small]))
        theta = opt.step(theta, main.grad(theta, _seen(main, kept), _even(len(kept))), state)
        sub = big.take(np.argsort(hashes(big.ids, f"{s.seed}/{t}/sub"), kind="stable")[: s.small])
        step = outer_step("unroll", main, theta, _seen(main, sub), spec.x, weight, alpha, main.losses(theta, sub.x)[:, None], rho=s.rho)
        alpha = alpha + s.weight_rate * step.direction
        run.trajectory.append(alpha)
        run.cost.step(weight_fwd=len(big), main_fwd=len(big), main_bwd=len(kept) + len(sub) + len(spec), rows_in=len(big), rows_kept=len(kept))
    run.theta = theta
    return run


METHODS: dict[str, Callable[[Source, Setting], Run]] = {
    "generic_only": run_generic_only,
    "mixing": run_mixing,
    "contrastive_select": run_contrastive,
    "domain_classifier": run_classifier,
    "loss_input_weights": run_loss_input,
    "batch_reweight": run_batch_reweight,
    "unroll": lambda p, s: train_bilevel(p, "unroll", s),
    "cosine": lambda p, s: train_bilevel(p, "cosine", s),
    "implicit": lambda p, s: train_bilevel(p, "implicit", s),
}
