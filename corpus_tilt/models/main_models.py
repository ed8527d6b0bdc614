"""Main models: byte language models (two convex, one not), a pair model, a dual encoder, a row classifier."""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np

from .base import numeric_hvp, softmax


class ByteModel:
    """Next byte given a class of the byte before: logits in a table, convex.

    ``contexts`` 256 is the large model and 16 (high nibbles) the small one.  An example is its
    pair counts (contexts, nexts, counts), so all quantities are closed forms.
    """

    def __init__(self, contexts: int = 256) -> None:
        self.contexts = contexts
        self.size = contexts * 256

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.size)

    def prepare(self, payloads: list[bytes]) -> tuple[np.ndarray, list]:
        counts, length = [], []
        for p in payloads:
            raw = np.frombuffer(p, np.uint8).astype(np.int64)
            cell = raw[:-1] * self.contexts // 256 * 256 + raw[1:]
            if 16 * len(cell) > self.size:
                every = np.bincount(cell, minlength=self.size)
                at = np.flatnonzero(every)
                n = every[at]
            else:
                at, n = np.unique(cell, return_counts=True)
            counts.append((at, n.astype(float)))
            length.append(max(len(raw) - 1, 1))
        return np.array(length, float), counts

    def packed(self, payloads: list[bytes]) -> list[bytes]:
        """What ``unpacked`` makes the same rows of as ``prepare``: four bytes' cell and four bytes' count a distinct pair."""
        length, counts = self.prepare(payloads)
        return [np.concatenate([[m], at, n]).astype(np.uint32).tobytes() for m, (at, n) in zip(length, counts, strict=True)]

    def unpacked(self, blobs: list[bytes]) -> tuple[np.ndarray, list]:
        rows = [np.frombuffer(b, np.uint32) for b in blobs]
        cut = [1 + len(r) // 2 for r in rows]
        return np.array([r[0] for r in rows], float), [(r[1:c].astype(np.int64), r[c:].astype(float)) for r, c in zip(rows, cut, strict=True)]

    def _table(self, theta: np.ndarray) -> np.ndarray:
        return softmax(theta.reshape(self.contexts, 256))

    def losses_each(self, thetas: list[np.ndarray], x) -> np.ndarray:
        """``losses`` under each of ``thetas``, a row each."""
        logs = np.stack([np.log(self._table(t)).ravel() for t in thetas], axis=1)
        return np.array([-(n @ logs[at]) / m for (at, n), m in zip(x[1], x[0], strict=True)]).reshape(len(x[0]), len(thetas)).T

    def losses(self, theta: np.ndarray, x) -> np.ndarray:
        logs = np.log(self._table(theta)).ravel()
        return np.array([-(n @ logs[at]) / m for (at, n), m in zip(x[1], x[0], strict=True)])

    def _sums(self, x, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        cell = np.zeros(self.size)
        for (at, n), m, a in zip(x[1], x[0], w, strict=True):
            cell[at] += a * n / m
        return cell, cell.reshape(self.contexts, 256).sum(axis=1)

    def grad(self, theta: np.ndarray, x, w: np.ndarray) -> np.ndarray:
        cell, mass = self._sums(x, w)
        return (mass[:, None] * self._table(theta)).ravel() - cell

    def dots(self, theta: np.ndarray, x, v: np.ndarray) -> np.ndarray:
        table = v.reshape(self.contexts, 256)
        inner = (self._table(theta) * table).sum(axis=1)
        spread = (inner[:, None] - table).ravel()
        return np.array([n @ spread[at] / m for (at, n), m in zip(x[1], x[0], strict=True)])

    def hvp(self, theta: np.ndarray, x, w: np.ndarray, v: np.ndarray) -> np.ndarray:
        _, mass = self._sums(x, w)
        p, table = self._table(theta), v.reshape(self.contexts, 256)
        return (mass[:, None] * p * (table - (p * table).sum(axis=1, keepdims=True))).ravel()


class ContextMlp:
    """Next byte from the k bytes before: embeddings, a tanh layer, softmax.  Not convex.

    A position needs its 256 probabilities, so positions are taken ``STRETCH`` at a time.
    """

    STRETCH = 4096

    def __init__(self, k: int = 3, embed: int = 8, hidden: int = 24) -> None:
        self.k, self.embed, self.hidden = k, embed, hidden
        self.shapes = [(256, embed), (k * embed, hidden), (hidden,), (hidden, 256), (256,)]
        self.size = sum(int(np.prod(s)) for s in self.shapes)

    def init(self, seed: int = 0) -> np.ndarray:
        return np.random.default_rng(seed).normal(0, 0.1, self.size)

    def _split(self, theta: np.ndarray) -> list[np.ndarray]:
        out, at = [], 0
        for s in self.shapes:
            n = int(np.prod(s))
            out.append(theta[at : at + n].reshape(s))
            at += n
        return out

    def prepare(self, payloads: list[bytes]) -> list[np.ndarray]:
        return [np.concatenate([np.zeros(self.k, np.uint8), np.frombuffer(p, np.uint8)]) for p in payloads]

    def _rows(self, x) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        context = np.concatenate([np.lib.stride_tricks.sliding_window_view(r, self.k)[:-1] for r in x])
        return context, np.concatenate([r[self.k :] for r in x]), np.repeat(np.arange(len(x)), [len(r) - self.k for r in x])

    def _forward(self, theta: np.ndarray, context: np.ndarray):
        e, w1, b1, w2, b2 = self._split(theta)
        z = e[context].reshape(len(context), -1)
        h = np.tanh(z @ w1 + b1)
        return z, h, softmax(h @ w2 + b2)

    def losses(self, theta: np.ndarray, x) -> np.ndarray:
        context, nxt, of = self._rows(x)
        n = np.bincount(of, minlength=len(x))
        own = np.zeros(len(nxt))
        for lo in range(0, len(nxt), self.STRETCH):
            p = self._forward(theta, context[lo : lo + self.STRETCH])[2]
            own[lo : lo + self.STRETCH] = -np.log(p[np.arange(len(p)), nxt[lo : lo + self.STRETCH]])
        return np.bincount(of, own, len(x)) / np.maximum(n, 1)

    def _pull(self, theta: np.ndarray, context: np.ndarray, nxt: np.ndarray, by: np.ndarray) -> np.ndarray:
        _, w1, _, w2, _ = self._split(theta)
        z, h, p = self._forward(theta, context)
        up = p.copy()
        up[np.arange(len(nxt)), nxt] -= 1
        up *= by[:, None]
        back = (up @ w2.T) * (1 - h * h)
        embed = np.zeros(self.shapes[0])
        np.add.at(embed, context, (back @ w1.T).reshape(len(context), self.k, self.embed))
        return np.concatenate([g.ravel() for g in (embed, z.T @ back, back.sum(0), h.T @ up, up.sum(0))])

    def grad(self, theta: np.ndarray, x, w: np.ndarray) -> np.ndarray:
        context, nxt, of = self._rows(x)
        n = np.maximum(np.bincount(of, minlength=len(x)), 1)
        by, out = (w / n)[of], np.zeros(self.size)
        for lo in range(0, len(nxt), self.STRETCH):
            own = slice(lo, lo + self.STRETCH)
            out += self._pull(theta, context[own], nxt[own], by[own])
        return out

    def dots(self, theta: np.ndarray, x, v: np.ndarray, step: float = 1e-4) -> np.ndarray:
        """The loss's derivative along v, by central differences: two forward passes, no gradients."""
        norm = np.linalg.norm(v)
        if norm == 0:
            return np.zeros(len(x))
        h = step / norm
        return (self.losses(theta + h * v, x) - self.losses(theta - h * v, x)) / (2 * h)

    def hvp(self, theta: np.ndarray, x, w: np.ndarray, v: np.ndarray) -> np.ndarray:
        return numeric_hvp(self, theta, x, w, v)


@dataclass
class LinearSoftmax:
    """Softmax regression on feature vectors, with label smoothing and ridge: the rows of ``prepare`` are (features, classes)."""

    features: int
    classes: int
    ridge: float = 0.0
    smoothing: float = 0.0

    def __post_init__(self) -> None:
        self.size = self.features * self.classes

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.size)

    def prepare(self, payloads: list) -> tuple[np.ndarray, np.ndarray]:
        return np.array([p[0] for p in payloads], float).reshape(len(payloads), self.features), np.array([p[1] for p in payloads], int)

    def _goal(self, y: np.ndarray) -> np.ndarray:
        return np.eye(self.classes)[y] * (1 - self.smoothing) + self.smoothing / self.classes

    def probabilities(self, theta: np.ndarray, x) -> np.ndarray:
        return softmax(x[0] @ theta.reshape(self.features, self.classes))

    def losses(self, theta: np.ndarray, x) -> np.ndarray:
        return -(self._goal(x[1]) * np.log(self.probabilities(theta, x) + 1e-300)).sum(1) + 0.5 * self.ridge * theta @ theta

    def grad(self, theta: np.ndarray, x, w: np.ndarray) -> np.ndarray:
        return (x[0].T @ ((self.probabilities(theta, x) - self._goal(x[1])) * w[:, None])).ravel() + self.ridge * w.sum() * theta

    def dots(self, theta: np.ndarray, x, v: np.ndarray) -> np.ndarray:
        return ((self.probabilities(theta, x) - self._goal(x[1])) * (x[0] @ v.reshape(self.features, self.classes))).sum(1) + self.ridge * theta @ v

    def hvp(self, theta: np.ndarray, x, w: np.ndarray, v: np.ndarray) -> np.ndarray:
        p, d = self.probabilities(theta, x), x[0] @ v.reshape(self.features, self.classes)
        return (x[0].T @ (p * (d - (p * d).sum(1, keepdims=True)) * w[:, None])).ravel() + self.ridge * w.sum() * v

    def accuracy(self, theta: np.ndarray, x) -> float:
        return float((self.probabilities(theta, x).argmax(1) == x[1]).mean())


class PairModel:
    """Target tokens given the target token before and the bag of source tokens: log-linear, smoothed, with beam decoding.

    Tokens are words hashed into ``vocab`` classes; 0 begins and 1 ends a sentence.
    """

    def __init__(self, vocab: int = 96, smoothing: float = 0.1) -> None:
        self.vocab, self.smoothing = vocab, smoothing
        self.size = 2 * vocab * vocab

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.size)

    def tokens(self, text: str) -> list[int]:
        import zlib

        return [2 + zlib.crc32(w.encode()) % (self.vocab - 2) for w in text.lower().split()]

    def prepare(self, payloads: list[tuple[str, str]]) -> list[tuple[np.ndarray, np.ndarray]]:
        out = []
        for src, tgt in payloads:
            bag = np.bincount(self.tokens(src), minlength=self.vocab) / max(len(self.tokens(src)), 1)
            out.append((bag, np.array([0, *self.tokens(tgt), 1])))
        return out

    def _logits(self, theta: np.ndarray, bag: np.ndarray, last: np.ndarray) -> np.ndarray:
        a, b = theta.reshape(2, self.vocab, self.vocab)
        return a[last] + bag @ b

    def _parts(self, theta: np.ndarray, pair) -> tuple[np.ndarray, np.ndarray]:
        bag, t = pair
        p = softmax(self._logits(theta, bag, t[:-1]))
        goal = np.full_like(p, self.smoothing / self.vocab)
        goal[np.arange(len(p)), t[1:]] += 1 - self.smoothing
        return p, goal

    def losses(self, theta: np.ndarray, x) -> np.ndarray:
        """The goal sums to one, so its cross-entropy is the logits' log-sum less their mean under the goal."""
        out = []
        for bag, t in x:
            z = self._logits(theta, bag, t[:-1])
            top = z.max(axis=1)
            log_sum = top + np.log(np.exp(z - top[:, None]).sum(axis=1))
            out.append((log_sum - self.smoothing / self.vocab * z.sum(axis=1) - (1 - self.smoothing) * z[np.arange(len(z)), t[1:]]).mean())
        return np.array(out)

    def grad(self, theta: np.ndarray, x, w: np.ndarray) -> np.ndarray:
        out = np.zeros((2, self.vocab, self.vocab))
        for r, a in zip(x, w, strict=True):
            p, g = self._parts(theta, r)
            up = a * (p - g) / len(p)
            np.add.at(out[0], r[1][:-1], up)
            out[1] += np.outer(r[0], up.sum(0))
        return out.ravel()

    def dots(self, theta: np.ndarray, x, v: np.ndarray) -> np.ndarray:
        out = []
        for r in x:
            p, g = self._parts(theta, r)
            out.append(((p - g) * self._logits(v, r[0], r[1][:-1])).sum(1).mean())
        return np.array(out)

    def hvp(self, theta: np.ndarray, x, w: np.ndarray, v: np.ndarray) -> np.ndarray:
        out = np.zeros((2, self.vocab, self.vocab))
        for r, a in zip(x, w, strict=True):
            p, _ = self._parts(theta, r)
            d = self._logits(v, r[0], r[1][:-1])
            up = a * p * (d - (p * d).sum(1, keepdims=True)) / len(p)
            np.add.at(out[0], r[1][:-1], up)
            out[1] += np.outer(r[0], up.sum(0))
        return out.ravel()

    def beam_decode(self, theta: np.ndarray, bag: np.ndarray, width: int = 4, longest: int = 40) -> list[int]:
        return self.beam_decode_all(theta, [bag], width, longest)[0]

    def beam_decode_all(self, theta: np.ndarray, bags: list[np.ndarray], width: int = 4, longest: int = 40) -> list[list[int]]:
        """Each bag's best target by beam search, all bags a step at a time; equal bags are decoded once."""
        a, b = theta.reshape(2, self.vocab, self.vocab)
        place: dict[bytes, int] = {}
        of = [place.setdefault(bag.tobytes(), len(place)) for bag in bags]
        base = np.stack([np.frombuffer(k) @ b for k in place]) if place else np.zeros((0, self.vocab))
        beams, ended = [[(0.0, (0,))] for _ in place], [[] for _ in place]
        going = list(range(len(place)))
        for _ in range(longest):
            if not going:
                break
            row = np.repeat(going, [len(beams[r]) for r in going])
            logs = np.log(softmax(a[np.array([s[1][-1] for r in going for s in beams[r]])] + base[row]))
            top = np.argsort(-logs, axis=1)[:, :width]
            gain = np.take_along_axis(logs, top, axis=1).tolist()
            top, at, on = top.tolist(), 0, []
            for r in going:
                every = []
                for score, seq in beams[r]:
                    every += [(score + g, seq, t) for g, t in zip(gain[at], top[at], strict=True)]
                    at += 1
                every.sort(key=lambda c: -c[0])
                beams[r] = []
                for score, seq, t in every:
                    (ended[r] if t == 1 else beams[r]).append((score, (*seq, t)))
                    if len(beams[r]) == width:
                        break
                if len(ended[r]) < width and beams[r]:
                    on.append(r)
            going = on
        best = [max(e or b, key=lambda c: c[0] / len(c[1]))[1] for e, b in zip(ended, beams, strict=True)]
        return [[t for t in best[i] if t > 1] for i in of]


class DualEncoder:
    """A linear image branch, and an MLP of two latent layers over caption vectors; a contrastive softmax over candidate captions.

    ``captions`` are the vectors of all class captions; a prediction is the best class's caption.
    Rows are (image, class, candidates).  On specific data all captions are candidates; on generic
    data (``against_past``) those of the last ``memory`` examples and of the batch.
    """

    def __init__(self, captions: np.ndarray, image: int = 64, joint: int = 16, hidden: int = 24, memory: int = 256) -> None:
        self.captions, self.image, self.memory = captions, image, memory
        self.shapes = [(image, joint), (captions.shape[1], hidden), (hidden,), (hidden, hidden), (hidden,), (hidden, joint)]
        self.size = sum(int(np.prod(s)) for s in self.shapes)
        self.past: list[int] = []

    def init(self, seed: int = 0) -> np.ndarray:
        rng = np.random.default_rng(seed)
        return np.concatenate([rng.normal(0, 0.1 if i == 0 else 1 / np.sqrt(s[0]), int(np.prod(s))) if len(s) > 1 else np.zeros(s) for i, s in enumerate(self.shapes)])

    def prepare(self, payloads: list) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        x = np.array([p[0] for p in payloads], float).reshape(len(payloads), self.image)
        return x, np.array([p[1] for p in payloads], int), np.ones((len(payloads), len(self.captions)), bool)

    def against_past(self, x) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The rows with the captions seen lately as candidates; theirs are remembered."""
        there = np.zeros(len(self.captions), bool)
        there[[*self.past, *x[1].tolist()]] = True
        self.past = [*self.past, *x[1].tolist()][-self.memory :]
        return x[0], x[1], np.tile(there, (len(x[1]), 1))

    def _split(self, theta: np.ndarray) -> list[np.ndarray]:
        cuts = np.cumsum([int(np.prod(s)) for s in self.shapes])
        return [p.reshape(s) for p, s in zip(np.split(theta, cuts[:-1]), self.shapes, strict=True)]

    def _texts(self, theta: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        _, w1, b1, w2, b2, w3 = self._split(theta)
        h1 = np.tanh(self.captions @ w1 + b1)
        h2 = np.tanh(h1 @ w2 + b2)
        return h1, h2, h2 @ w3

    def probabilities(self, theta: np.ndarray, x) -> np.ndarray:
        logits = 4 * (x[0] @ self._split(theta)[0]) @ self._texts(theta)[2].T
        return softmax(np.where(x[2], logits, -np.inf))

    def losses(self, theta: np.ndarray, x) -> np.ndarray:
        return -np.log(self.probabilities(theta, x)[np.arange(len(x[1])), x[1]] + 1e-300)

    def _errors(self, theta: np.ndarray, x) -> np.ndarray:
        up = self.probabilities(theta, x)
        up[np.arange(len(x[1])), x[1]] -= 1
        return 4 * up

    def grad(self, theta: np.ndarray, x, w: np.ndarray) -> np.ndarray:
        u, _, _, w2, _, w3 = self._split(theta)
        h1, h2, t = self._texts(theta)
        up = self._errors(theta, x) * w[:, None]
        dt = up.T @ (x[0] @ u)
        d2 = (dt @ w3.T) * (1 - h2 * h2)
        d1 = (d2 @ w2.T) * (1 - h1 * h1)
        return np.concatenate([g.ravel() for g in (x[0].T @ (up @ t), self.captions.T @ d1, d1.sum(0), h1.T @ d2, d2.sum(0), h2.T @ dt)])

    def dots(self, theta: np.ndarray, x, v: np.ndarray) -> np.ndarray:
        u, _, _, w2, _, w3 = self._split(theta)
        du, dw1, db1, dw2, db2, dw3 = self._split(v)
        h1, h2, t = self._texts(theta)
        m1 = (self.captions @ dw1 + db1) * (1 - h1 * h1)
        m2 = (m1 @ w2 + h1 @ dw2 + db2) * (1 - h2 * h2)
        return (self._errors(theta, x) * ((x[0] @ du) @ t.T + (x[0] @ u) @ (m2 @ w3 + h2 @ dw3).T)).sum(1)

    def hvp(self, theta: np.ndarray, x, w: np.ndarray, v: np.ndarray) -> np.ndarray:
        return numeric_hvp(self, theta, x, w, v)

    def accuracy(self, theta: np.ndarray, x) -> float:
        return float((self.probabilities(theta, x).argmax(1) == x[1]).mean())


def bleu_counts(hypotheses: list[list], references: list[list], order: int = 4) -> dict[str, float]:
    """Sums that corpus BLEU is made of: clipped and all n-grams up to ``order``, and lengths."""
    out = {f"{kind}{n}": 0.0 for kind in ("hit", "all") for n in range(1, order + 1)} | {"hyp": 0.0, "ref": 0.0}
    for a, b in zip(hypotheses, references, strict=True):
        out["hyp"] += len(a)
        out["ref"] += len(b)
        for n in range(1, order + 1):
            x, y = (Counter(tuple(s[i : i + n]) for i in range(len(s) - n + 1)) for s in (a, b))
            out[f"hit{n}"] += sum((x & y).values())
            out[f"all{n}"] += max(len(a) - n + 1, 0)
    return out


def bleu_of(sums: dict[str, float], order: int = 4) -> float:
    """Geometric mean of n-gram precisions, with a brevity penalty."""
    hit, total = (np.array([sums[f"{kind}{n}"] for n in range(1, order + 1)]) for kind in ("hit", "all"))
    if not sums["hyp"] or (hit == 0).any() or (total == 0).any():
        return 0.0
    return float(np.exp(np.log(hit / total).mean() + min(0.0, 1 - sums["ref"] / sums["hyp"])))


def bleu(hypotheses: list[list], references: list[list], order: int = 4) -> float:
    """Corpus BLEU: clipped n-gram precision up to ``order``, geometric mean, brevity penalty."""
    return bleu_of(bleu_counts(hypotheses, references, order), order)
