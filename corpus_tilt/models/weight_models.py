"""Weight models: a score for each example; weights are its softmax in a batch.

``back`` gives the gradient of sum(up * score) over a batch.
"""

from __future__ import annotations

import numpy as np


class LinearWeight:
    """alpha . phi on the shares of bytes by high nibble (or any features given)."""

    def __init__(self, features: int = 16, max_bytes: int | None = None) -> None:
        self.size, self.max_bytes = features, max_bytes

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.size)

    def prepare(self, payloads: list) -> np.ndarray:
        if payloads and isinstance(payloads[0], bytes):
            return np.array([np.bincount(np.frombuffer(p, np.uint8) >> 4, minlength=16) / max(len(p), 1) for p in (p[: self.max_bytes] for p in payloads)]).reshape(-1, 16)
        return np.array([np.ravel(p[0] if isinstance(p, tuple) else p) for p in payloads], float)

    def scores(self, alpha: np.ndarray, x: np.ndarray) -> np.ndarray:
        return x @ alpha

    def back(self, alpha: np.ndarray, x: np.ndarray, up: np.ndarray) -> np.ndarray:
        return x.T @ up


class _Net:
    """Parameters in one vector, by shapes."""

    shapes: list[tuple[int, ...]]

    def _sizes(self) -> None:
        self.size = sum(int(np.prod(s)) for s in self.shapes)

    def init(self, seed: int = 0) -> np.ndarray:
        rng = np.random.default_rng(seed)
        return np.concatenate([rng.normal(0, 1 / np.sqrt(max(s[0], 1)), s).ravel() if len(s) > 1 else np.zeros(int(np.prod(s))) for s in self.shapes])

    def _split(self, alpha: np.ndarray) -> list[np.ndarray]:
        out, at = [], 0
        for s in self.shapes:
            n = int(np.prod(s))
            out.append(alpha[at : at + n].reshape(s))
            at += n
        return out


class MlpWeight(_Net):
    """One hidden tanh layer on a feature vector; one feature makes the model of a loss."""

    def __init__(self, features: int, hidden: int = 16) -> None:
        self.features = features
        self.shapes = [(features, hidden), (hidden,), (hidden, 1)]
        self._sizes()

    def prepare(self, payloads: list) -> np.ndarray:
        return np.array([np.ravel(p[0] if isinstance(p, tuple) else p) for p in payloads], float).reshape(len(payloads), self.features)

    def scores(self, alpha: np.ndarray, x: np.ndarray) -> np.ndarray:
        w1, b1, w2 = self._split(alpha)
        return (np.tanh(x @ w1 + b1) @ w2).ravel()

    def back(self, alpha: np.ndarray, x: np.ndarray, up: np.ndarray) -> np.ndarray:
        w1, b1, w2 = self._split(alpha)
        h = np.tanh(x @ w1 + b1)
        d = up[:, None] * w2.T * (1 - h * h)
        return np.concatenate([(x.T @ d).ravel(), d.sum(0), (h.T @ up[:, None]).ravel()])


class ConvWeight(_Net):
    """Byte embeddings, two convolutions, mean pooling, a score; the weight model (alone) reads the first ``max_bytes``."""

    def __init__(self, embed: int = 8, width: int = 32, kernel: int = 3, max_bytes: int = 256) -> None:
        self.kernel, self.max_bytes = kernel, max_bytes
        self.shapes = [(256, embed), (kernel * embed, width), (width,), (kernel * width, width), (width,), (width, 1)]
        self._sizes()

    def prepare(self, payloads: list[bytes]) -> np.ndarray:
        out = np.zeros((len(payloads), self.max_bytes), np.uint8)
        for i, p in enumerate(payloads):
            raw = np.frombuffer(p[: self.max_bytes], np.uint8)
            out[i, : len(raw)] = raw
        return out

    def _patches(self, x: np.ndarray) -> np.ndarray:
        view = np.lib.stride_tricks.sliding_window_view(x, self.kernel, axis=1)
        return np.moveaxis(view, -1, 2).reshape(x.shape[0], view.shape[1], -1)

    def _unpatch(self, d: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
        out = np.zeros(shape)
        parts = d.reshape(d.shape[0], d.shape[1], self.kernel, -1)
        for i in range(self.kernel):
            out[:, i : i + d.shape[1]] += parts[:, :, i]
        return out

    def _forward(self, alpha: np.ndarray, x: np.ndarray):
        e, w1, b1, w2, b2, w3 = self._split(alpha)
        a0 = e[x]
        p1 = self._patches(a0)
        a1 = np.tanh(p1 @ w1 + b1)
        p2 = self._patches(a1)
        a2 = np.tanh(p2 @ w2 + b2)
        return a0, p1, a1, p2, a2, a2.mean(axis=1), w1, w2, w3

    def scores(self, alpha: np.ndarray, x: np.ndarray) -> np.ndarray:
        *_, pooled, _, _, w3 = self._forward(alpha, x)
        return (pooled @ w3).ravel()

    def back(self, alpha: np.ndarray, x: np.ndarray, up: np.ndarray) -> np.ndarray:
        a0, p1, a1, p2, a2, pooled, w1, w2, w3 = self._forward(alpha, x)
        d2 = (up[:, None, None] * w3.ravel() / a2.shape[1]) * (1 - a2 * a2)
        d1 = self._unpatch(d2 @ w2.T, a1.shape) * (1 - a1 * a1)
        d0 = self._unpatch(d1 @ w1.T, a0.shape)
        embed = np.zeros(self.shapes[0])
        np.add.at(embed, x, d0)
        flat = lambda p, d: p.reshape(-1, p.shape[-1]).T @ d.reshape(-1, d.shape[-1])
        return np.concatenate([g.ravel() for g in (embed, flat(p1, d1), d1.sum((0, 1)), flat(p2, d2), d2.sum((0, 1)), pooled.T @ up[:, None])])


class PairWeight(_Net):
    """A shared embedding of dimension 32, mean source beside mean target, an MLP."""

    def __init__(self, vocab: int = 96, embed: int = 32, hidden: int = 128) -> None:
        self.vocab = vocab
        self.shapes = [(vocab, embed), (2 * embed, hidden), (hidden,), (hidden, 1)]
        self._sizes()

    def prepare(self, payloads: list[tuple[str, str]]) -> np.ndarray:
        import zlib

        bag = lambda t: np.bincount([zlib.crc32(w.encode()) % self.vocab for w in t.lower().split()] or [0], minlength=self.vocab) / max(len(t.split()), 1)
        return np.array([np.stack([bag(s), bag(t)]) for s, t in payloads])

    def _forward(self, alpha: np.ndarray, x: np.ndarray):
        e, w1, b1, w2 = self._split(alpha)
        z = (x @ e).reshape(len(x), -1)
        return e, w1, w2, z, np.tanh(z @ w1 + b1)

    def scores(self, alpha: np.ndarray, x: np.ndarray) -> np.ndarray:
        _, _, w2, _, h = self._forward(alpha, x)
        return (h @ w2).ravel()

    def back(self, alpha: np.ndarray, x: np.ndarray, up: np.ndarray) -> np.ndarray:
        e, w1, w2, z, h = self._forward(alpha, x)
        d = up[:, None] * w2.T * (1 - h * h)
        dz = (d @ w1.T).reshape(len(x), 2, -1)
        return np.concatenate([np.einsum("nsv,nse->ve", x, dz).ravel(), (z.T @ d).ravel(), d.sum(0), (h.T @ up[:, None]).ravel()])


class ImageWeight(_Net):
    """Four 3 x 3 convolutions (32, 32, 32 and 64 channels) over a vector laid out as an 8 x 8 image, mean pooling, a score.

    A row's patches are about 450 kB, so scores take rows ``STRETCH`` at a time.
    """

    STRETCH = 128

    def __init__(self, side: int = 8, channels: tuple[int, ...] = (32, 32, 32, 64)) -> None:
        self.side, self.layers = side, len(channels)
        self.shapes = [s for into, out in zip((1, *channels), channels, strict=False) for s in ((9 * into, out), (out,))] + [(channels[-1], 1)]
        self._sizes()

    def prepare(self, payloads: list) -> np.ndarray:
        return np.array([np.ravel(p[0] if isinstance(p, tuple) else p) for p in payloads], float).reshape(len(payloads), self.side, self.side, 1)

    def _patches(self, a: np.ndarray) -> np.ndarray:
        wide = np.pad(a, ((0, 0), (1, 1), (1, 1), (0, 0)))
        view = np.lib.stride_tricks.sliding_window_view(wide, (3, 3), axis=(1, 2))
        return np.moveaxis(view, 3, 5).reshape(*a.shape[:3], -1)

    def _unpatch(self, d: np.ndarray) -> np.ndarray:
        parts = d.reshape(*d.shape[:3], 3, 3, -1)
        out = np.zeros((d.shape[0], self.side + 2, self.side + 2, parts.shape[-1]))
        for i in range(3):
            for j in range(3):
                out[:, i : i + self.side, j : j + self.side] += parts[:, :, :, i, j]
        return out[:, 1:-1, 1:-1]

    def _forward(self, alpha: np.ndarray, x: np.ndarray) -> tuple[list, list, list]:
        *parts, last = self._split(alpha)
        patches, outs = [], []
        for i in range(self.layers):
            patches.append(self._patches(outs[-1] if outs else x))
            outs.append(np.tanh(patches[-1] @ parts[2 * i] + parts[2 * i + 1]))
        return patches, outs, [*parts, last]

    def scores(self, alpha: np.ndarray, x: np.ndarray) -> np.ndarray:
        got = []
        for lo in range(0, max(len(x), 1), self.STRETCH):
            _, outs, parts = self._forward(alpha, x[lo : lo + self.STRETCH])
            got.append((outs[-1].mean(axis=(1, 2)) @ parts[-1]).ravel())
        return np.concatenate(got)

    def back(self, alpha: np.ndarray, x: np.ndarray, up: np.ndarray) -> np.ndarray:
        patches, outs, parts = self._forward(alpha, x)
        grads = [outs[-1].mean(axis=(1, 2)).T @ up[:, None]]
        d = np.broadcast_to(up[:, None, None, None] * parts[-1].ravel() / self.side**2, outs[-1].shape)
        for i in reversed(range(self.layers)):
            d = d * (1 - outs[i] ** 2)
            flat = d.reshape(-1, d.shape[-1])
            grads = [patches[i].reshape(-1, patches[i].shape[-1]).T @ flat, flat.sum(0), *grads]
            if i:
                d = self._unpatch(d @ parts[2 * i].T)
        return np.concatenate([g.ravel() for g in grads])


class FreeWeight:
    """No model: one free score an example of the batch, from uniform."""

    def __init__(self, size: int) -> None:
        self.size = size

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.size)

    def prepare(self, payloads: list) -> np.ndarray:
        return np.arange(len(payloads))

    def scores(self, alpha: np.ndarray, x: np.ndarray) -> np.ndarray:
        return alpha[x]

    def back(self, alpha: np.ndarray, x: np.ndarray, up: np.ndarray) -> np.ndarray:
        return np.bincount(x, up, self.size)
