"""Objectives: mean loss and gradient of a batch, with parameters as one flat vector; and proximal maps of regularisers."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


class Objective:
    """value_grad(w, x, y): mean loss over the rows and its gradient; outputs(w, x): predictions or class scores."""

    l2: float = 0.0

    def size(self, n_features: int) -> int:
        return n_features

    def start(self, n_features: int, seed: int = 0) -> np.ndarray:
        return np.zeros(self.size(n_features))

    def value_grad(self, w, x, y):
        raise NotImplementedError

    def outputs(self, w, x):
        raise NotImplementedError

    def value(self, w, x, y) -> float:
        return self.value_grad(w, x, y)[0]

    def accuracy(self, w, x, y) -> float:
        return float((self.outputs(w, x).argmax(1) == y).mean())


@dataclass(frozen=True)
class Ridge(Objective):
    """Half the mean squared error plus half l2 times the squared norm."""

    l2: float = 0.1

    def value_grad(self, w, x, y):
        r = x @ w - y
        return 0.5 * float(r @ r) / len(y) + 0.5 * self.l2 * float(w @ w), x.T @ r / len(y) + self.l2 * w

    def outputs(self, w, x):
        return x @ w


@dataclass(frozen=True)
class Logistic(Objective):
    """Labels 0 and 1; rows of label 1 weigh ``positive``."""

    l2: float = 1e-3
    positive: float = 1.0

    def value_grad(self, w, x, y):
        z = x @ w
        weight = np.where(y > 0, self.positive, 1.0)
        loss = weight * (np.logaddexp(0, z) - y * z)
        return float(loss.mean()) + 0.5 * self.l2 * float(w @ w), x.T @ (weight * (1 / (1 + np.exp(-z)) - y)) / len(y) + self.l2 * w

    def outputs(self, w, x):
        z = x @ w
        return np.stack((-z, z), 1)


def _soft(z: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
    z = z - z.max(1, keepdims=True)
    p = np.exp(z)
    p /= p.sum(1, keepdims=True)
    at = np.arange(len(y)), y.astype(int)
    loss = float(-np.log(np.maximum(p[at], 1e-300)).mean())
    p[at] -= 1
    return loss, p / len(y)


@dataclass(frozen=True)
class Softmax(Objective):
    classes: int = 10
    l2: float = 1e-3

    def size(self, n_features):
        return n_features * self.classes

    def value_grad(self, w, x, y):
        m = w.reshape(-1, self.classes)
        loss, back = _soft(x @ m, y)
        return loss + 0.5 * self.l2 * float(w @ w), (x.T @ back + self.l2 * m).reshape(-1)

    def outputs(self, w, x):
        return x @ w.reshape(-1, self.classes)


class _Layered(Objective):
    """Networks given by a list of parameter shapes."""

    classes = 10

    def shapes(self, n_features: int) -> list[tuple[int, ...]]:
        raise NotImplementedError

    def size(self, n_features):
        return sum(int(np.prod(s)) for s in self.shapes(n_features))

    def start(self, n_features, seed=0):
        rng = np.random.default_rng(seed)
        out = []
        for s in self.shapes(n_features):
            fan = int(np.prod(s[:-1])) if len(s) > 1 else 1
            out.append((rng.normal(0, np.sqrt(2 / fan), s) if len(s) > 1 else np.zeros(s)).reshape(-1))
        return np.concatenate(out)

    def parts(self, w, n_features):
        out, at = [], 0
        for s in self.shapes(n_features):
            n = int(np.prod(s))
            out.append(w[at : at + n].reshape(s))
            at += n
        return out


@dataclass(frozen=True)
class Perceptron(_Layered):
    """One hidden layer of rectified units, softmax output."""

    hidden: int = 32
    classes: int = 10
    l2: float = 0.0

    def shapes(self, n_features):
        return [(n_features, self.hidden), (self.hidden,), (self.hidden, self.classes), (self.classes,)]

    def value_grad(self, w, x, y):
        a, b, c, d = self.parts(w, x.shape[1])
        h = x @ a + b
        r = np.maximum(h, 0)
        loss, back = _soft(r @ c + d, y)
        inner = (back @ c.T) * (h > 0)
        grad = np.concatenate([g.reshape(-1) for g in (x.T @ inner, inner.sum(0), r.T @ back, back.sum(0))])
        return loss + 0.5 * self.l2 * float(w @ w), grad + self.l2 * w

    def outputs(self, w, x):
        a, b, c, d = self.parts(w, x.shape[1])
        return np.maximum(x @ a + b, 0) @ c + d


def _windows(x: np.ndarray) -> np.ndarray:
    """3 by 3 neighbourhoods of images (rows, height, width, channels), zero outside."""
    n, h, w, c = x.shape
    p = np.pad(x, ((0, 0), (1, 1), (1, 1), (0, 0)))
    return np.stack([p[:, i : i + h, j : j + w] for i in range(3) for j in range(3)], 3).reshape(n, h, w, 9 * c)


def _windows_back(g: np.ndarray, channels: int) -> np.ndarray:
    n, h, w, _ = g.shape
    g = g.reshape(n, h, w, 9, channels)
    out = np.zeros((n, h + 2, w + 2, channels))
    for k in range(9):
        out[:, k // 3 : k // 3 + h, k % 3 : k % 3 + w] += g[:, :, :, k]
    return out[:, 1:-1, 1:-1]


def _pool(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    n, h, w, c = x.shape
    t = x.reshape(n, h // 2, 2, w // 2, 2, c).transpose(0, 1, 3, 5, 2, 4).reshape(n, h // 2, w // 2, c, 4)
    best = t.argmax(4)
    return np.take_along_axis(t, best[..., None], 4)[..., 0], best


def _pool_back(g: np.ndarray, best: np.ndarray) -> np.ndarray:
    n, h, w, c = g.shape
    t = np.zeros((n, h, w, c, 4))
    np.put_along_axis(t, best[..., None], g[..., None], 4)
    return t.reshape(n, h, w, c, 2, 2).transpose(0, 1, 4, 2, 5, 3).reshape(n, 2 * h, 2 * w, c)


@dataclass(frozen=True)
class ConvNet(_Layered):
    """Two rounds of 3 by 3 convolution, rectifier and 2 by 2 pooling, then a dense layer; square one-channel images."""

    channels: tuple[int, int] = (4, 8)
    classes: int = 10
    l2: float = 0.0

    def shapes(self, n_features):
        side = int(round(n_features**0.5)) // 4
        a, b = self.channels
        return [(9, a), (a,), (9 * a, b), (b,), (side * side * b, self.classes), (self.classes,)]

    def _forward(self, w, x):
        side = int(round(x.shape[1] ** 0.5))
        k1, b1, k2, b2, d, bd = self.parts(w, x.shape[1])
        w1 = _windows(x.reshape(-1, side, side, 1))
        z1 = w1 @ k1 + b1
        p1, m1 = _pool(np.maximum(z1, 0))
        w2 = _windows(p1)
        z2 = w2 @ k2 + b2
        p2, m2 = _pool(np.maximum(z2, 0))
        flat = p2.reshape(len(x), -1)
        return (k2, d), (w1, z1, m1, w2, z2, m2, p2.shape, flat), flat @ d + bd

    def value_grad(self, w, x, y):
        (k2, d), (w1, z1, m1, w2, z2, m2, shape, flat), out = self._forward(w, x)
        loss, back = _soft(out, y)
        g2 = _pool_back((back @ d.T).reshape(shape), m2) * (z2 > 0)
        g1 = _pool_back(_windows_back(g2 @ k2.T, self.channels[0]), m1) * (z1 > 0)
        parts = (np.einsum("nhwi,nhwo->io", w1, g1), g1.sum((0, 1, 2)), np.einsum("nhwi,nhwo->io", w2, g2), g2.sum((0, 1, 2)), flat.T @ back, back.sum(0))
        return loss + 0.5 * self.l2 * float(w @ w), np.concatenate([p.reshape(-1) for p in parts]) + self.l2 * w

    def outputs(self, w, x):
        return self._forward(w, x)[2]


@dataclass(frozen=True)
class ResidualNet(_Layered):
    """Dense layers with skip connections: input layer, ``blocks`` blocks of two layers each, output layer (18 weight layers by default)."""

    width: int = 24
    blocks: int = 8
    classes: int = 10
    l2: float = 0.0

    def shapes(self, n_features):
        inner = [(self.width, self.width), (self.width,)] * (2 * self.blocks)
        return [(n_features, self.width), (self.width,), *inner, (self.width, self.classes), (self.classes,)]

    def start(self, n_features, seed=0):
        w = super().start(n_features, seed)
        at = n_features * self.width + self.width
        step = self.width * self.width + self.width
        for b in range(self.blocks):  # blocks begin near the identity
            w[at + (2 * b + 1) * step : at + (2 * b + 2) * step] *= 0.1
        return w

    def _forward(self, w, x):
        p = self.parts(w, x.shape[1])
        h, kept = x @ p[0] + p[1], []
        for b in range(self.blocks):
            a1, b1, a2, b2 = p[2 + 4 * b : 6 + 4 * b]
            z = h @ a1 + b1
            kept.append((h, z))
            h = h + np.maximum(z, 0) @ a2 + b2
        return p, kept, h, h @ p[-2] + p[-1]

    def value_grad(self, w, x, y):
        p, kept, h, out = self._forward(w, x)
        loss, back = _soft(out, y)
        grads = [h.T @ back, back.sum(0)]
        g = back @ p[-2].T
        for b in reversed(range(self.blocks)):
            a1, _, a2, _ = p[2 + 4 * b : 6 + 4 * b]
            before, z = kept[b]
            r = np.maximum(z, 0)
            inner = (g @ a2.T) * (z > 0)
            grads = [before.T @ inner, inner.sum(0), r.T @ g, g.sum(0), *grads]
            g = g + inner @ a1.T
        grads = [x.T @ g, g.sum(0), *grads]
        return loss + 0.5 * self.l2 * float(w @ w), np.concatenate([q.reshape(-1) for q in grads]) + self.l2 * w

    def outputs(self, w, x):
        return self._forward(w, x)[3]


# ---- proximal maps -------------------------------------------------------------------------------------------------


class Prox:
    """Argmin over z of penalty(z) + |z - v|^2 / (2 step)."""

    def apply(self, v: np.ndarray, step: float) -> np.ndarray:
        return v

    def penalty(self, v: np.ndarray) -> float:
        return 0.0


NoProx = Prox


@dataclass(frozen=True)
class L1(Prox):
    weight: float = 0.01

    def apply(self, v, step):
        return np.sign(v) * np.maximum(np.abs(v) - step * self.weight, 0)

    def penalty(self, v):
        return self.weight * float(np.abs(v).sum())


@dataclass(frozen=True)
class SquaredL2(Prox):
    weight: float = 0.01

    def apply(self, v, step):
        return v / (1 + step * self.weight)

    def penalty(self, v):
        return 0.5 * self.weight * float(v @ v)


@dataclass(frozen=True)
class ElasticNet(Prox):
    l1: float = 0.01
    l2: float = 0.01

    def apply(self, v, step):
        return SquaredL2(self.l2).apply(L1(self.l1).apply(v, step), step)

    def penalty(self, v):
        return L1(self.l1).penalty(v) + SquaredL2(self.l2).penalty(v)


@dataclass(frozen=True)
class Box(Prox):
    low: float = 0.0
    high: float = float("inf")

    def apply(self, v, step):
        return np.clip(v, self.low, self.high)

    def penalty(self, v):
        return 0.0 if ((v >= self.low) & (v <= self.high)).all() else float("inf")


@dataclass(frozen=True)
class GroupL2(Prox):
    """Sum of the norms of blocks of ``block`` elements."""

    weight: float = 0.01
    block: int = 16

    def apply(self, v, step):
        out = np.array(v, float)
        for i in range(0, len(out), self.block):
            n = np.linalg.norm(out[i : i + self.block])
            out[i : i + self.block] *= max(0.0, 1 - step * self.weight / n) if n else 0.0
        return out

    def penalty(self, v):
        return self.weight * sum(float(np.linalg.norm(v[i : i + self.block])) for i in range(0, len(v), self.block))


@dataclass(frozen=True)
class Ball(Prox):
    radius: float = 1.0

    def apply(self, v, step):
        n = np.linalg.norm(v)
        return v if n <= self.radius else v * (self.radius / n)

    def penalty(self, v):
        return 0.0 if np.linalg.norm(v) <= self.radius * (1 + 1e-12) else float("inf")
