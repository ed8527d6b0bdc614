"""Losses, gradients, Hessian products and outer steps against differences."""

import numpy as np
import pytest

from corpus_tilt.models.base import size_of, softmax
from corpus_tilt.models.main_models import ByteModel, ContextMlp, DualEncoder, LinearSoftmax, PairModel, bleu
from corpus_tilt.models.weight_models import ConvWeight, FreeWeight, ImageWeight, LinearWeight, MlpWeight, PairWeight
from corpus_tilt.training.outer import alpha_direction, cone_direction, exact_hypergradient, outer_step, reweight, solve_inner, steepest_direction, utilities

RNG = np.random.default_rng(3)
TEXTS = [b"the cat sat", b"on the mat and", b"\xc3\xa9t\xc3\xa9 \xc3\xa0", b"zz"]
PAIRS = [("a b c", "x y"), ("b d", "y z w"), ("a", "q")]
VECTORS = [(RNG.normal(size=64), int(k)) for k in (0, 2, 1, 3)]
ROWS = [(RNG.normal(size=4), int(k)) for k in (0, 1, 2, 1, 0)]
MAIN = [(ByteModel(16), TEXTS), (ByteModel(256), TEXTS), (ContextMlp(2, 3, 4), TEXTS), (LinearSoftmax(4, 3, 0.1, 0.1), ROWS), (PairModel(12, 8), PAIRS), (DualEncoder(RNG.normal(size=(4, 6)), 64, 3), VECTORS)]


@pytest.mark.parametrize("model,payloads", MAIN)
def test_main_models_by_differences(model, payloads):
    x = model.prepare(payloads)
    theta, v = RNG.normal(0, 0.2, model.size), RNG.normal(0, 1, model.size)
    w = softmax(RNG.normal(size=len(payloads)))
    h = 1e-5
    slope = (model.losses(theta + h * v, x) - model.losses(theta - h * v, x)) / (2 * h)
    assert np.allclose(model.dots(theta, x, v), slope, atol=1e-4)
    assert np.isclose(model.grad(theta, x, w) @ v, w @ slope, atol=1e-4)
    hv = (model.grad(theta + h * v, x, w) - model.grad(theta - h * v, x, w)) / (2 * h)
    assert np.allclose(model.hvp(theta, x, w, v), hv, atol=1e-3)


@pytest.mark.parametrize("model,payloads", [(LinearWeight(), TEXTS), (ConvWeight(4, 5, 3, 20), TEXTS), (MlpWeight(4, 5), ROWS), (PairWeight(12, 4, 6), PAIRS), (ImageWeight(), VECTORS), (FreeWeight(4), TEXTS)])
def test_weight_models_by_differences(model, payloads):
    x = model.prepare(payloads)
    alpha, up, d = model.init(1) + RNG.normal(0, 0.1, model.size), RNG.normal(size=len(payloads)), RNG.normal(size=model.size)
    h = 1e-6
    slope = up @ (model.scores(alpha + h * d, x) - model.scores(alpha - h * d, x)) / (2 * h)
    assert np.isclose(model.back(alpha, x, up) @ d, slope, atol=1e-5)


@pytest.fixture
def toy():
    rng = np.random.default_rng(0)
    main, weight = LinearSoftmax(4, 3, ridge=0.1), LinearWeight(5)
    g = main.prepare([(rng.normal(size=4), rng.integers(3)) for _ in range(30)])
    s = main.prepare([(rng.normal(size=4), rng.integers(3)) for _ in range(12)])
    return main, weight, g, s, rng.normal(size=(30, 5)), rng.normal(0, 0.3, 5), rng.normal(0, 0.3, main.size), rng.normal(size=5)


def _uniform(x):
    return np.full(size_of(x), 1 / size_of(x))


def test_unroll_is_the_exact_look_ahead_gradient(toy):
    main, weight, g, s, xw, alpha, theta, d = toy
    rho = 0.7

    def ahead(a):
        u = theta - rho * main.grad(theta, g, softmax(weight.scores(a, xw)))
        return main.losses(u, s).mean()

    slope = (ahead(alpha + 1e-6 * d) - ahead(alpha - 1e-6 * d)) / 2e-6
    assert np.isclose(outer_step("unroll", main, theta, g, s, weight, alpha, xw, rho=rho).direction @ d, -slope, atol=1e-6)
    for small, bound in ((0.1, 0.1), (0.001, 0.001)):
        a, b = (outer_step(m, main, theta, g, s, weight, alpha, xw, rho=small).direction for m in ("unroll", "unroll_first"))
        assert np.linalg.norm(a - b) / np.linalg.norm(a) < bound


def test_cosine_raises_the_alignment(toy):
    main, weight, g, s, xw, alpha, theta, d = toy

    def cos(a):
        x, y = main.grad(theta, g, softmax(weight.scores(a, xw))), main.grad(theta, s, _uniform(s))
        return x @ y / np.linalg.norm(x) / np.linalg.norm(y)

    slope = (cos(alpha + 1e-6 * d) - cos(alpha - 1e-6 * d)) / 2e-6
    assert np.isclose(outer_step("cosine", main, theta, g, s, weight, alpha, xw).direction @ d, slope, atol=1e-6)


def test_implicit_at_its_fixed_point_is_the_hypergradient(toy):
    main, weight, g, s, xw, alpha, _, d = toy
    _, exact = exact_hypergradient(main, g, s, weight, alpha, xw)
    slope = (exact_hypergradient(main, g, s, weight, alpha + 1e-5 * d, xw)[0] - exact_hypergradient(main, g, s, weight, alpha - 1e-5 * d, xw)[0]) / 2e-5
    assert np.isclose(exact @ d, slope, atol=1e-5)
    w = softmax(weight.scores(alpha, xw))
    theta, v = solve_inner(main, g, w, main.init()), None
    for _ in range(3000):
        _, v, _ = utilities("implicit", main, theta, g, w, s, v=v, eta_v=0.5)
    q, _, _ = utilities("implicit", main, theta, g, w, s, v=v)
    assert np.allclose(-alpha_direction(weight, alpha, xw, w, q), exact, atol=1e-5)


def test_identities(toy):
    main, weight, g, s, xw, alpha, theta, _ = toy
    free = FreeWeight(30)
    u = _uniform(g)
    q = main.dots(theta, g, main.grad(theta, s, _uniform(s)))
    raw = u + 0.01 * q
    assert np.allclose(reweight(main, theta, g, s, 0.01), raw / raw.sum()) and (raw > 0).all()
    assert np.allclose(outer_step("unroll_first", main, theta, g, s, free, np.zeros(30), np.arange(30), rho=1.0).direction, u * (q - q.mean()))
    zero = main.init()
    same = utilities("cosine", main, zero, g, u, (np.zeros((2, 4)), np.array([0, 1])))
    assert same[2] == "zero gradient" and not same[0].any()


def test_directions():
    g = RNG.normal(size=(6, 3))
    t = RNG.normal(size=3)
    assert np.isclose(np.linalg.norm(steepest_direction(t)), 1) and steepest_direction(t) @ t < 0
    a = cone_direction(g, t)
    cos = lambda x: x @ t / np.linalg.norm(x) / np.linalg.norm(t)
    assert (a >= 0).all() and all(cos(a @ g) >= cos(b @ g) - 1e-3 for b in RNG.dirichlet(np.ones(6) * 0.3, 300))


def test_measures():
    assert np.isclose(ByteModel(16).losses(np.zeros(4096), ByteModel(16).prepare([b"hello"]))[0], np.log(256))
    assert bleu([[1, 2, 3, 4, 5]], [[1, 2, 3, 4, 5]]) == 1
    assert bleu([[1, 2]], [[3, 4]]) == 0
    assert np.isclose(bleu([[1, 2, 3, 4, 9]], [[1, 2, 3, 4, 5]]), np.exp(np.mean(np.log([4 / 5, 3 / 4, 2 / 3, 1 / 2]))))


def test_past_captions_are_the_negatives():
    model = DualEncoder(RNG.normal(size=(4, 6)), 64, 3)
    x = model.prepare(VECTORS[:2])
    assert x[2].all()
    first = model.against_past(x)
    assert first[2].tolist() == [[True, False, True, False]] * 2  # the batch's own captions
    second = model.against_past(model.prepare(VECTORS[3:]))
    assert second[2].tolist() == [[True, False, True, True]]
    theta = model.init(3)
    assert np.isclose(np.exp(-model.losses(theta, first)).sum(), sum(model.probabilities(theta, first)[i, y] for i, y in enumerate(first[1])))
    assert (model.probabilities(theta, first)[:, [1, 3]] == 0).all()
