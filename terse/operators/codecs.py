"""Compression of vectors: stochastic and deterministic codecs with their variance constants and nominal prices.

A codec maps an array to one of equal length that costs fewer bits.  Kernels are numpy (they run inside Arrow batches and on small driver
state); ``as_column`` gives the array expression of those that SQL can express, for plans that stay in generated code.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from math import ceil, inf, log2, sqrt

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from terse.functions import vectors

FLOAT_BITS = 32
TRIT_BITS = 1.5


class Codec:
    """unbiased: its expectation is the input; scale_free: scaling the input scales the output, with equal draws."""

    unbiased = True
    scale_free = True

    def apply(self, v: np.ndarray, rng: np.random.Generator) -> np.ndarray:
        raise NotImplementedError

    def constant(self, length: int) -> float:
        """Least C with E|Q(v) - v|^2 <= C |v|^2 for vectors of this length (nan where none is known)."""
        return float("nan")

    def bits(self, length: int, n_nonzero: int | None = None) -> float:
        return FLOAT_BITS * length

    def as_column(self, vals: Column, draw: Callable[[Column], Column]) -> Column:
        """The coded array; ``draw`` gives a number in [0, 1) for a position."""
        raise NotImplementedError(f"{type(self).__name__} has no SQL form")


def check_finite(v: np.ndarray) -> np.ndarray:
    if not np.isfinite(v).all():
        raise ValueError("vectors must be finite")
    return v


@dataclass(frozen=True)
class Identity(Codec):
    def apply(self, v, rng):
        return np.array(v, float)

    def constant(self, length):
        return 0.0

    def as_column(self, vals, draw):
        return vals


@dataclass(frozen=True)
class LevelRounding(Codec):
    """Each element goes to a neighbouring level, up with a probability in proportion to how far it has come; two levels are the plain case."""

    levels: tuple[float, ...] = (0.0, 1.0)
    scale_free = False

    def apply(self, v, rng):
        grid = np.asarray(self.levels, float)
        if (np.asarray(v) < grid[0]).any() or (np.asarray(v) > grid[-1]).any():
            raise ValueError("value outside the levels")
        k = np.clip(np.searchsorted(grid, v, side="right") - 1, 0, len(grid) - 2)
        lo, hi = grid[k], grid[k + 1]
        return np.where(rng.random(len(v)) * (hi - lo) < v - lo, hi, lo)

    def constant(self, length):
        cells = list(zip(self.levels[:-1], self.levels[1:], strict=True))
        return max((b - a) ** 2 / (4 * a * b) if a * b > 0 else inf for a, b in cells)

    def bits(self, length, n_nonzero=None):
        return length * ceil(log2(len(self.levels)))

    def as_column(self, vals, draw):
        def one(v, i):
            out = F.lit(self.levels[-1])
            for a, b in reversed(list(zip(self.levels[:-1], self.levels[1:], strict=True))):
                out = F.when(v < b, F.when(draw(i) * (b - a) < v - a, F.lit(b)).otherwise(F.lit(a))).otherwise(out)
            return out

        return F.transform(vals, one)


@dataclass(frozen=True)
class RandomSparsify(Codec):
    """Keeps an element with probability ``keep`` and divides it by that."""

    keep: float = 0.25

    def apply(self, v, rng):
        return np.where(rng.random(len(v)) < self.keep, np.asarray(v) / self.keep, 0.0)

    def constant(self, length):
        return 1 / self.keep - 1

    def bits(self, length, n_nonzero=None):
        n = self.keep * length if n_nonzero is None else n_nonzero
        return n * (FLOAT_BITS + ceil(log2(max(2, length))))

    def as_column(self, vals, draw):
        return F.transform(vals, lambda v, i: F.when(draw(i) < self.keep, v / self.keep).otherwise(F.lit(0.0)))


@dataclass(frozen=True)
class NormTernary(Codec):
    """Norm times sign times a coin whose odds are the element's share of the norm, by blocks of ``block`` elements (none: one block)."""

    p: float = inf
    block: int | None = 256

    def apply(self, v, rng):
        v = check_finite(np.asarray(v, float))
        n = len(v)
        b = min(self.block or n, n) or 1
        padded = np.zeros(-(-n // b) * b)
        padded[:n] = np.abs(v)
        rows = padded.reshape(-1, b)
        top = rows.max(1, keepdims=True)
        safe = np.where(top > 0, top, 1.0)  # scaled first, so that neither tiny nor huge values break the norm
        rows = rows / safe
        scale = rows.max(1, keepdims=True) if self.p == inf else (rows**self.p).sum(1, keepdims=True) ** (1 / self.p)
        kept = rng.random(padded.shape).reshape(rows.shape) * scale < rows
        return np.sign(v) * np.where(kept, scale * safe, 0.0).reshape(-1)[:n]

    def constant(self, length):
        return norm_constant(self.p, min(length, self.block or length))

    def bits(self, length, n_nonzero=None):
        return FLOAT_BITS * -(-length // min(self.block or length, length)) + TRIT_BITS * length

    def as_column(self, vals, draw):
        def one(part, first):
            coded = lambda scale: F.transform(part, lambda v, i: F.when(draw(i + first) * scale < F.abs(v), F.signum(v) * scale).otherwise(F.lit(0.0)))
            return vectors.let(vectors.norm(part, self.p), coded)

        return vectors.by_blocks(vals, self.block, one)


def norm_constant(p: float, length: int) -> float:
    """Largest |v|_1 |v|_p / |v|_2^2 - 1 over vectors of a length: attained by one large element and equal others."""
    if length <= 1:
        return 0.0
    if p == inf:
        return (sqrt(length) - 1) / 2
    if p == 2:
        return sqrt(length) - 1
    if p == 1:
        return float(length - 1)
    t, m = np.linspace(0, 1, 200_001), length - 1
    return float(((1 + m * t) * (1 + m * t**p) ** (1 / p) / (1 + m * t * t)).max() - 1)


@dataclass(frozen=True)
class Blocked(Codec):
    """Another codec on parts of given lengths, each by itself."""

    codec: Codec
    sizes: tuple[int, ...]

    def apply(self, v, rng):
        if sum(self.sizes) != len(v):
            raise ValueError("block lengths must add up to the vector's")
        return np.concatenate([self.codec.apply(part, rng) for part in np.split(np.asarray(v, float), np.cumsum(self.sizes)[:-1])])

    @property
    def unbiased(self):  # noqa: D102
        return self.codec.unbiased

    def constant(self, length):
        return max(self.codec.constant(n) for n in self.sizes)

    def bits(self, length, n_nonzero=None):
        return sum(self.codec.bits(n) for n in self.sizes)

    def as_column(self, vals, draw):
        starts = [sum(self.sizes[:k]) for k in range(len(self.sizes))]
        return F.concat(*[self.codec.as_column(F.slice(vals, a + 1, n), lambda i, a=a: draw(i + a)) for a, n in zip(starts, self.sizes, strict=True)])


@dataclass(frozen=True)
class MultiLevel(Codec):
    """Magnitudes as multiples of norm / levels, rounded to a neighbour at random."""

    levels: int = 4
    p: float = 2

    def apply(self, v, rng):
        v = check_finite(np.asarray(v, float))
        scale = np.linalg.norm(v, self.p)
        if scale == 0:
            return np.zeros(len(v))
        place = np.abs(v) / scale * self.levels
        low = np.floor(place)
        return np.sign(v) * scale * (low + (rng.random(len(v)) < place - low)) / self.levels

    def constant(self, length):
        return min(length / self.levels**2, sqrt(length) / self.levels)

    def bits(self, length, n_nonzero=None):
        return FLOAT_BITS + length * ceil(log2(2 * self.levels + 1))

    def as_column(self, vals, draw):
        s = float(self.levels)

        def one(scale):
            up = lambda v, i: (F.floor(F.abs(v) / scale * s) + (draw(i) < F.abs(v) / scale * s - F.floor(F.abs(v) / scale * s)).cast("double")) / s
            return F.transform(vals, lambda v, i: F.when(scale > 0, F.signum(v) * scale * up(v, i)).otherwise(F.lit(0.0)))

        return vectors.let(vectors.norm(vals, self.p), one)


@dataclass(frozen=True)
class SignScale(Codec):
    """Signs times the mean magnitude of their block; biased, meant for error memories."""

    block: int | None = None
    unbiased = False

    def apply(self, v, rng):
        v = np.asarray(v, float)
        b = self.block or len(v)
        return np.concatenate([np.sign(part) * np.abs(part).mean() for part in (v[i : i + b] for i in range(0, len(v), b))]) if len(v) else v

    def bits(self, length, n_nonzero=None):
        return length + FLOAT_BITS * -(-length // (self.block or length))

    def as_column(self, vals, draw):
        one = lambda part, _: vectors.let(vectors.total(part, F.abs) / F.size(part), lambda scale: F.transform(part, lambda v: F.signum(v) * scale))
        return vectors.by_blocks(vals, self.block, one)


@dataclass(frozen=True)
class LargestK(Codec):
    """The k largest magnitudes (ties: the earlier element), others 0; biased."""

    k: int | None = None
    fraction: float = 0.1
    unbiased = False

    def count(self, length: int) -> int:
        return min(length, self.k if self.k is not None else max(1, ceil(self.fraction * length)))

    def apply(self, v, rng):
        v = np.asarray(v, float)
        keep = np.argsort(-np.abs(v), kind="stable")[: self.count(len(v))]
        out = np.zeros(len(v))
        out[keep] = v[keep]
        return out

    def bits(self, length, n_nonzero=None):
        return self.count(length) * (FLOAT_BITS + ceil(log2(max(2, length))))

    def as_column(self, vals, draw):
        size = F.size(vals)
        k = F.lit(self.k) if self.k is not None else F.greatest(F.ceil(F.lit(self.fraction) * size), F.lit(1)).cast("int")
        first = F.slice(F.array_sort(F.transform(vals, lambda v, i: F.struct((-F.abs(v)).alias("m"), i.alias("i")))), 1, F.least(k, size))
        return vectors.let(F.transform(first, lambda e: e["i"]), lambda kept: F.transform(vals, lambda v, i: F.when(F.array_contains(kept, i), v).otherwise(F.lit(0.0))))


@dataclass(frozen=True)
class BudgetSparsify(Codec):
    """Keeps elements with probabilities in proportion to their magnitudes, at most 1, that add up to ``budget``: least variance at that price."""

    budget: float = 8.0

    def probabilities(self, v: np.ndarray) -> np.ndarray:
        size = np.abs(np.asarray(v, float))
        p = np.zeros(len(size))
        certain = np.zeros(len(size), bool)
        budget = min(self.budget, float((size > 0).sum()))
        while True:
            rest = size[~certain].sum()
            if rest <= 0:
                break
            p[~certain] = size[~certain] * (budget - certain.sum()) / rest
            over = (p >= 1) & ~certain
            if not over.any():
                break
            certain |= over
        p[certain] = 1.0
        return p

    def apply(self, v, rng):
        p = self.probabilities(v)
        keep = rng.random(len(p)) < p
        return np.where(keep, np.asarray(v, float) / np.where(p > 0, p, 1.0), 0.0)

    def bits(self, length, n_nonzero=None):
        return min(self.budget, length) * (FLOAT_BITS + ceil(log2(max(2, length))))


CODECS: dict[str, type[Codec]] = {c.__name__: c for c in (Identity, LevelRounding, RandomSparsify, NormTernary, Blocked, MultiLevel, SignScale, LargestK, BudgetSparsify)}


def register_codec(name: str, codec: type[Codec]) -> None:
    """Makes a user's codec known by name; it must keep the length of its input."""
    out = codec().apply(np.array([1.0, -2.0, 0.0]), np.random.default_rng(0))
    if len(out) != 3:
        raise ValueError("a codec must keep the length")
    CODECS[name] = codec


def measured_constant(codec: Codec, v: np.ndarray, repeats: int = 2000, seed: int = 0) -> tuple[float, float]:
    """(variance ratio, bias) of repeated coding: mean squared error over squared norm, and distance of the mean from the input."""
    rng = np.random.default_rng(seed)
    out = np.array([codec.apply(v, rng) for _ in range(repeats)])
    return float(((out - v) ** 2).sum(1).mean() / (v @ v)), float(np.linalg.norm(out.mean(0) - v))
