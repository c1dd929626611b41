"""Feed-forward towers with hand-derived gradients, and the contrastive loss on a batch."""

from __future__ import annotations

import numpy as np

def elu(x: np.ndarray) -> np.ndarray:
    return np.where(x > 0, x, np.expm1(np.minimum(x, 0)))


class Tower:
    """Affine layers, each followed by elu and, in training, dropout.  No layers: the identity."""

    def __init__(self, widths: tuple[int, ...], seed: int = 0, keep: float = 1.0, act: str = "elu"):
        rng = np.random.default_rng(seed)
        self.keep, self.act = keep, act
        self.w, self.b = [], []
        for a, b in zip(widths, widths[1:]):
            limit = np.sqrt(6 / (a + b))
            self.w.append(rng.uniform(-limit, limit, (a, b)))
            self.b.append(np.zeros(b))

    def parameters(self) -> list[np.ndarray]:
        return [p for pair in zip(self.w, self.b) for p in pair]

    def forward(self, x: np.ndarray, rng: np.random.Generator | None = None) -> np.ndarray:
        """Outputs; with ``rng`` the pass is remembered for ``backward`` and units are dropped."""
        trace = []
        for w, b in zip(self.w, self.b):
            pre = x @ w + b
            out = elu(pre) if self.act == "elu" else pre
            mask = (rng.random(out.shape) < self.keep) / self.keep if rng is not None and self.keep < 1 else None
            trace.append((x, pre, mask))
            x = out if mask is None else out * mask
        if rng is not None:
            self.trace = trace
        return x

    def backward(self, grad: np.ndarray) -> list[np.ndarray]:
        """Gradients of the parameters, given that of the outputs of the remembered pass."""
        out: list[np.ndarray] = []
        for i, ((x, pre, mask), w) in reversed(list(enumerate(zip(self.trace, self.w)))):
            if mask is not None:
                grad = grad * mask
            if self.act == "elu":
                grad = grad * np.where(pre > 0, 1.0, np.exp(np.minimum(pre, 0)))
            out = [x.T @ grad, grad.sum(0), *out]
            grad = grad @ w.T if i else grad  # nobody asks for the gradient by the inputs
        return out


def unit_rows(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    size = np.sqrt((x * x).sum(1, keepdims=True))
    return x / np.maximum(size, 1e-12), np.maximum(size, 1e-12)


def side_gradient(dist: np.ndarray, match: np.ndarray, margin: float, positive: str = "mean") -> tuple[float, np.ndarray]:
    """Loss of the rows of a distance matrix and its gradient by distance.

    ``mean`` compares non-matches with the mean distance of a row's matches; ``each`` with every match alone.
    """
    n_pos = match.sum(1)
    if positive == "mean":
        near = np.where(n_pos > 0, (dist * match).sum(1) / np.maximum(n_pos, 1), 0.0)
        gap = np.where(~match & (n_pos > 0)[:, None], margin + near[:, None] - dist, 0.0)
        active = gap > 0
        grad = -active.astype(float) + match * (active.sum(1) / np.maximum(n_pos, 1))[:, None]
        return float(gap[active].sum()), grad
    loss, grad = 0.0, np.zeros_like(dist)
    for i, k in zip(*np.nonzero(match)):
        gap = np.where(~match[i], margin + dist[i, k] - dist[i], 0.0)
        active = gap > 0
        loss += float(gap[active].sum())
        grad[i] -= active
        grad[i, k] += active.sum()
    return loss, grad


def loss_and_gradients(x: np.ndarray, y: np.ndarray, match: np.ndarray, margin: float, positive: str = "mean") -> tuple[float, np.ndarray, np.ndarray]:
    """Two-sided loss of embeddings under cosine distance, and its gradients by both embeddings."""
    (ux, sx), (uy, sy) = unit_rows(x), unit_rows(y)
    cos = ux @ uy.T
    left, g1 = side_gradient(1 - cos, match, margin, positive)
    right, g2 = side_gradient((1 - cos).T, match.T, margin, positive)
    g = g1 + g2.T
    dx = -(g @ uy - (g * cos).sum(1, keepdims=True) * ux) / sx
    dy = -(g.T @ ux - (g * cos).sum(0)[:, None] * uy) / sy
    return left + right, dx, dy


def learning_rate(step: int, rate: float, decay: float = 0.9, every: int = 1000) -> float:
    return rate * decay ** (step // every)


class Adam:
    def __init__(self, parameters: list[np.ndarray], b1: float = 0.9, b2: float = 0.999, eps: float = 1e-8):
        self.p, self.b1, self.b2, self.eps, self.t = parameters, b1, b2, eps, 0
        self.m, self.v = [np.zeros_like(p) for p in parameters], [np.zeros_like(p) for p in parameters]

    def step(self, grads: list[np.ndarray], rate: float) -> None:
        self.t += 1
        scale = rate * np.sqrt(1 - self.b2**self.t) / (1 - self.b1**self.t)
        for p, g, m, v in zip(self.p, grads, self.m, self.v):
            m += (1 - self.b1) * (g - m)
            v += (1 - self.b2) * (g * g - v)
            p -= scale * m / (np.sqrt(v) + self.eps)


class Sgd:
    def __init__(self, parameters: list[np.ndarray]):
        self.p = parameters

    def step(self, grads: list[np.ndarray], rate: float) -> None:
        for p, g in zip(self.p, grads):
            p -= rate * g


class SkewSampler:
    """Draws pairs by weight (1 + seen) ** -power, leaves out pairs seen far more than the mean, and counts."""

    def __init__(self, n: int, power: float = 1.0, omit_above: float = 4.0, seed: int = 0):
        self.seen, self.power, self.omit, self.rng = np.zeros(n), power, omit_above, np.random.default_rng(seed)

    def draw(self, k: int, popularity: np.ndarray | None = None) -> np.ndarray:
        """``k`` pairs; ``popularity`` is the chance with which the stream of examples would offer each."""
        w = (1 + self.seen) ** -self.power
        w[self.seen > self.omit * self.seen.mean() + 1] = 0
        if popularity is not None:
            w = w * popularity
        key = np.where(w > 0, -np.log(self.rng.random(len(w)) + 1e-300) / np.maximum(w, 1e-300), np.inf)
        pick = np.argsort(key)[: min(k, int((w > 0).sum()))]
        self.seen[pick] += 1
        return pick


class UniformSampler(SkewSampler):
    def draw(self, k: int, popularity: np.ndarray | None = None) -> np.ndarray:
        p = popularity / popularity.sum() if popularity is not None else None
        pick = self.rng.choice(len(self.seen), min(k, len(self.seen)), replace=False, p=p)
        self.seen[pick] += 1
        return pick


class ConvTower(Tower):
    """A convolution over windows of the input in front of affine layers: an example of a plug-in tower.

    ``width`` inputs at a time, moved by ``stride``, go through one shared filter bank of ``filters``.
    """

    def __init__(self, size: int, width: int, stride: int, filters: int, out: int, seed: int = 0):
        self.width, self.stride = width, stride
        self.places = (size - width) // stride + 1
        super().__init__((width, filters), seed)
        self.top = Tower((self.places * filters, out), seed + 1)

    def parameters(self) -> list[np.ndarray]:
        return super().parameters() + self.top.parameters()

    def forward(self, x: np.ndarray, rng: np.random.Generator | None = None) -> np.ndarray:
        windows = np.lib.stride_tricks.sliding_window_view(x, self.width, axis=1)[:, :: self.stride]
        flat = super().forward(windows.reshape(-1, self.width), rng)
        return self.top.forward(flat.reshape(len(x), -1), rng)

    def backward(self, grad: np.ndarray) -> list[np.ndarray]:
        own = self.top.backward(grad)
        # The gradient by the top tower's input, which its own pass does not return.
        (x, pre, _), w = self.top.trace[0], self.top.w[0]
        slope = np.where(pre > 0, 1.0, np.exp(np.minimum(pre, 0)))
        below = ((grad * slope) @ w.T).reshape(len(x) * self.places, -1)
        return super().backward(below) + own
