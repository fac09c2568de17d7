"""Training methods as settings of one iteration.

Workers send a coded vector made of their gradient, minus an anchor or plus an error memory; the master averages, steps and sends the model
back raw, as a coded model residual with carry, or as a coded gradient with memory.  Every method and baseline is a choice of these parts, so
that reductions (the difference method is the two-way one with an uncoded way back, and so on) hold by construction.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from math import inf

import numpy as np

from terse.functions.draws import generator
from terse.operators.codecs import Codec, Identity, LargestK, NormTernary, RandomSparsify, SignScale
from terse.operators.objectives import NoProx, Prox

UP, DOWN = 1, 2


@dataclass(frozen=True)
class Method:
    """down: 'raw' sends the model, 'model' a coded model residual, 'gradient' a coded averaged gradient.
    anchor_rate: share of the coded residual that anchors absorb (none: no anchors); memory, decay: weight of a worker's error in its message and in the
    next error (none: no memory); carry_weight: of the master's error; apply_rate: of the coded way back; peers: workers send to each other."""

    name: str
    codec_up: Codec = field(default_factory=Identity)
    codec_down: Codec = field(default_factory=Identity)
    down: str = "raw"
    anchor_rate: float | None = None
    memory: float | None = None
    decay: float | None = None
    carry_weight: float = 0.0
    apply_rate: float = 1.0
    prox: Prox = field(default_factory=NoProx)
    continue_from: str = "shared"
    peers: bool = False
    refresh: float | None = None

    def bits(self, d: int, n: int = 1) -> tuple[float, float]:
        """Nominal bits that one worker sends and receives in an iteration."""
        up = self.codec_up.bits(d)
        if self.peers:
            return up * (n - 1), up * (n - 1)
        return up, 32.0 * d if self.down == "raw" else self.codec_down.bits(d)


def two_way_residual(block=256, anchor_rate=0.1, apply_rate=1.0, carry_weight=1.0, codec_up=None, codec_down=None, prox=None, **more) -> Method:
    coder = NormTernary(inf, block)
    return Method("two_way_residual", codec_up or coder, codec_down or coder, "model", anchor_rate, None, None, carry_weight, apply_rate, prox or NoProx(), **more)


def two_way_residual_smooth(block=256, anchor_rate=0.1, apply_rate=1.0, carry_weight=1.0, codec_up=None, codec_down=None) -> Method:
    """Without regulariser the master codes the gradient estimate itself; for codecs that do not depend on scale the path is that of the general form."""
    coder = NormTernary(inf, block)
    return Method("two_way_residual_smooth", codec_up or coder, codec_down or coder, "gradient", anchor_rate, None, None, carry_weight, apply_rate)


def no_carry(block=256, **more) -> Method:
    return replace(two_way_residual(block, carry_weight=0.0, **more), name="two_way_no_carry")


def exact_next(block=256, **more) -> Method:
    """The master goes on from its own precise model, so workers' gradients belong to another point: an ablation."""
    return replace(two_way_residual(block, **more), name="exact_next", continue_from="precise")


def plain(prox=None) -> Method:
    return Method("plain", prox=prox or NoProx())


def quantized_gradient(block=256, codec=None) -> Method:
    return Method("quantized_gradient", codec or NormTernary(2, block))


def ternary_gradient(block=256) -> Method:
    return Method("ternary_gradient", NormTernary(inf, block))


def sign_gradient(block=None, with_memory=False) -> Method:
    return Method("sign_gradient_memory" if with_memory else "sign_gradient", SignScale(block), memory=1.0 if with_memory else None)


def compensated_gradient(block=256, codec=None) -> Method:
    return Method("compensated_gradient", codec or NormTernary(inf, block), memory=1.0)


def gradient_difference(block=256, anchor_rate=0.1, codec=None, prox=None) -> Method:
    return Method("gradient_difference", codec or NormTernary(inf, block), anchor_rate=anchor_rate, prox=prox or NoProx())


def gradient_difference_vr(block=256, anchor_rate=0.1, refresh=0.1) -> Method:
    return replace(gradient_difference(block, anchor_rate), name="gradient_difference_vr", refresh=refresh)


def two_sided_compensated(block=256, codec=None) -> Method:
    coder = codec or NormTernary(inf, block)
    return Method("two_sided_compensated", coder, coder, "gradient", memory=1.0, carry_weight=1.0)


def two_sided_largest_k(fraction=0.1, k=None) -> Method:
    coder = LargestK(k, fraction)
    return Method("two_sided_largest_k", coder, coder, "gradient", memory=1.0, carry_weight=1.0)


def all_to_all_quantized(block=256, codec=None) -> Method:
    return Method("all_to_all_quantized", codec or NormTernary(inf, block), peers=True)


def all_to_all_compensated(block=256, weight=0.5, decay=0.9, codec=None) -> Method:
    return Method("all_to_all_compensated", codec or NormTernary(inf, block), memory=weight, decay=decay, peers=True)


def sparsified_gradient(codec=None) -> Method:
    return Method("sparsified_gradient", codec or RandomSparsify(0.25))


BASELINES = {
    f.__name__: f
    for f in (
        two_way_residual, two_way_residual_smooth, no_carry, exact_next, plain, quantized_gradient, ternary_gradient, sign_gradient, compensated_gradient, gradient_difference,
        gradient_difference_vr, two_sided_compensated, two_sided_largest_k, all_to_all_quantized, all_to_all_compensated, sparsified_gradient,
    )
}


def seven_curves(block: int) -> list[Method]:
    """The methods compared on the regression problem, all with the same coder."""
    return [
        plain(), quantized_gradient(codec=NormTernary(inf, block)), compensated_gradient(block), gradient_difference(block), two_sided_compensated(block), two_sided_largest_k(), two_way_residual(block),
    ]


def plan_method(method: Method) -> Method:
    """The cheaper equal form where there is one: without regulariser and with a scale-free coder the smooth form needs one vector less."""
    smooth = type(method.prox) is NoProx and method.down == "model" and method.codec_down.scale_free and method.continue_from == "shared"
    return replace(method, name=f"{method.name}_smooth", down="gradient") if smooth else method


@dataclass(frozen=True)
class Schedule:
    """Step of an iteration: constant, times ``factor`` every ``every`` iterations, or divided by 1 + k / slow; ``horizon`` gives the step for a known number of
    iterations."""

    step: float
    factor: float = 1.0
    every: int = 0
    slow: float = 0.0

    @classmethod
    def horizon(cls, iterations: int, n: int, smooth: float, extra: float, anchor_rate: float) -> Schedule:
        from terse.plans.theory import horizon_step

        return cls(horizon_step(iterations, n, smooth, extra, anchor_rate))

    def at(self, k: int) -> float:
        s = self.step * self.factor ** (k // self.every) if self.every else self.step
        return s / (1 + k / self.slow) if self.slow else s


@dataclass
class State:
    """What workers and master hold: shared model, anchors and their mean, worker and master errors; how far the run is and what it has sent; the model and gradients of
    the last snapshot, if the method takes them."""

    shared: np.ndarray
    precise: np.ndarray
    anchors: np.ndarray
    anchor_mean: np.ndarray
    errors: np.ndarray
    carry: np.ndarray
    last_step: float = 0.0
    iteration: int = 0
    bits_up: float = 0.0
    bits_down: float = 0.0
    snapshot: np.ndarray | None = None
    at_snapshot: np.ndarray | None = None

    @classmethod
    def start(cls, x: np.ndarray, n: int, bits_down: float = 0.0) -> State:
        d = len(x)
        return cls(x.copy(), x.copy(), np.zeros((n, d)), np.zeros(d), np.zeros((n, d)), np.zeros(d), bits_down=bits_down)


def iterate(method: Method, state: State, gradients: np.ndarray, step: float, seed: int, k: int) -> dict[str, float]:
    """One iteration, in place; returns the norms of what was coded and the symbols that were not 0."""
    n = len(gradients)
    value = gradients.copy()
    if method.anchor_rate is not None:
        value -= state.anchors
    if method.memory is not None:
        value += method.memory * state.errors
    coded = np.array([method.codec_up.apply(v, generator(seed, k, UP, i)) for i, v in enumerate(value)])
    if method.memory is not None:
        state.errors = value - coded if method.decay is None else method.decay * state.errors + gradients - coded
    mean = coded.mean(0)
    estimate = state.anchor_mean + mean
    if method.anchor_rate is not None:
        state.anchors += method.anchor_rate * coded
        state.anchor_mean = state.anchor_mean + method.anchor_rate * mean
    told = {"up_norm": float(np.sqrt((value**2).sum(1)).mean()), "up_norm_max": float(np.sqrt((value**2).sum(1)).max()), "up_nonzero": int((coded != 0).sum())}
    if method.down == "raw":
        state.shared = method.prox.apply(state.shared - step * estimate, step)
        state.precise = state.shared
        return told | {"down_norm": 0.0, "down_nonzero": len(mean) * 1, "n": n}
    if method.down == "model":
        origin = state.shared if method.continue_from == "shared" else state.precise
        state.precise = method.prox.apply(origin - step * estimate, step)
        residual = state.precise - state.shared + method.carry_weight * state.carry
        sent = method.codec_down.apply(residual, generator(seed, k, DOWN, 0))
        state.carry = residual - sent
        state.shared = state.shared + method.apply_rate * sent
    else:
        if method.anchor_rate is not None and state.last_step:
            state.carry *= state.last_step / step  # the carry is in units of the gradient
        residual = estimate + method.carry_weight * state.carry
        sent = method.codec_down.apply(residual, generator(seed, k, DOWN, 0))
        state.carry = residual - sent
        state.shared = state.shared - step * method.apply_rate * sent
        state.last_step = step
    return told | {"down_norm": float(np.linalg.norm(residual)), "down_nonzero": int((sent != 0).sum()), "n": n}
