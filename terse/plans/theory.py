"""Bounds and rates of the analysis as functions of codec constants, smoothness and workers.

c_up, c_down: variance constants of the two codecs; n: workers; mu, smooth: curvature bounds; extra: the free constant of the analysis.
"""

from __future__ import annotations

from math import inf, sqrt

from pyspark.sql import DataFrame, SparkSession

from terse.operators.codecs import norm_constant


def anchor_rate_interval(c_up: float, n: int, extra: float) -> tuple[float, float] | None:
    """Admissible anchor rates; none if ``extra`` is below its least value."""
    if c_up == 0:
        return 0.0, 1.0
    room = 1 - 4 * c_up * (c_up + 1) / (n * extra) if extra > 0 else -1.0
    if room < -1e-12:
        return None
    centre = 1 / (2 * (c_up + 1))
    half = centre * sqrt(max(room, 0.0))
    return centre - half, centre + half


def apply_rate_max(c_down: float) -> float:
    return 1 / (1 + c_down)


def carry_weight_bounds(c_down: float, apply_rate: float, anchor_rate: float, extra: float, mu: float, smooth: float) -> tuple[float, float]:
    """The two values that the carry weight must stay below."""
    slack = 1 - (c_down + 1) * apply_rate
    by_codec = inf if c_down == 0 else (sqrt(c_down**2 + 4 * max(slack, 0.0)) - c_down) / (2 * c_down)
    product = 4 * mu * smooth
    below = (mu + smooth) ** 2 * (1 + extra * anchor_rate) - product
    return by_codec, inf if below <= 0 else product / below


def carry_weight_max(*settings: float) -> float:
    return min(carry_weight_bounds(*settings))


def step_interval(carry: float, anchor_rate: float, extra: float, mu: float, smooth: float) -> tuple[float, float]:
    low = carry * (mu + smooth) / (2 * (1 + carry) * mu * smooth)
    return low, 2 / ((1 + extra * anchor_rate) * (mu + smooth))


def contraction_parts(carry: float, apply_rate: float, anchor_rate: float, step: float, c_down: float, mu: float, smooth: float) -> tuple[float, float, float]:
    """Factors of carry, descent and anchors; the rate is their largest."""
    slack = 1 - (c_down + 1) * apply_rate
    by_carry = 0.0 if carry == 0 or c_down == 0 else (inf if slack <= 0 else carry * (1 + carry) * c_down / slack)
    descent = 1 + carry * apply_rate - 2 * (1 + carry) * apply_rate * step * mu * smooth / (mu + smooth)
    return by_carry, descent, 1 - anchor_rate


def contraction(*settings: float) -> float:
    return max(contraction_parts(*settings))


def noise_ball(carry: float, apply_rate: float, anchor_rate: float, step: float, extra: float, n: int, rate: float, sigma2: float) -> float:
    """Where the squared distance settles under gradient noise."""
    return (1 + carry) * (1 + n * extra * anchor_rate) * apply_rate * step**2 * sigma2 / (n * (1 - rate))


def recommended(c_up: float, c_down: float, n: int, mu: float, smooth: float) -> dict[str, float]:
    """Settings without carry that give the best proven rate, with their largest step and 1 / (1 - rate)."""
    out = {"anchor_rate": 1 / (2 * (c_up + 1)), "apply_rate": apply_rate_max(c_down), "extra": 4 * c_up * (c_up + 1) / n}
    out["step"] = 2 / ((mu + smooth) * (1 + 2 * c_up / n))
    out["factor"] = convergence_factor(c_up, c_down, n, mu, smooth)
    return out


def convergence_factor(c_up: float, c_down: float, n: int, mu: float, smooth: float) -> float:
    return max(2 * (c_up + 1), (c_down + 1) * (mu + smooth) ** 2 / (2 * mu * smooth) * (0.5 + c_up / n))


def gradient_difference_factor(c_up: float, n: int, mu: float, smooth: float) -> float:
    ratio = 1 / (c_up + 1)
    return max(2 / ratio, (mu + smooth) / mu * (0.5 - 1 / n + 1 / (n * ratio)))


def nonconvex_step_max(apply_rate: float, anchor_rate: float, extra: float, c_down: float, smooth: float) -> float:
    by_sum = 1 / (6 * smooth * apply_rate * (1 + extra * anchor_rate) * (c_down + 1))
    if c_down == 0:
        return by_sum
    scale = smooth * apply_rate * (c_down + 1)
    return min((sqrt(1 + 48 * scale**2 / c_down) - 1) / (12 * scale), by_sum)


def nonconvex_bound(apply_rate, anchor_rate, extra, c_down, smooth, step, sigma2, n, iterations, start_gap) -> tuple[float, float]:
    """(factor of the mean squared gradient norm, what it is bounded by)."""
    left = apply_rate / 2 - 3 * (1 + extra * anchor_rate) * (c_down + 1) * smooth * apply_rate**2 * step
    return left, start_gap / (step * iterations) + 3 * (c_down + 1) * (1 + n * extra * anchor_rate) * smooth * apply_rate**2 * sigma2 * step / n


def horizon_step(iterations: int, n: int, smooth: float, extra: float, anchor_rate: float) -> float:
    return 1 / (12 * smooth * (1 + extra * anchor_rate) * (1 + sqrt(iterations / n)))


def asymptotic_rate(method: str, iterations: int, n: int, bound: float = 0.0) -> float:
    """Order of the mean squared gradient norm in the nonconvex case."""
    k = float(iterations)
    shared = 1 / sqrt(k * n) + 1 / k
    return {"quantized_gradient": 1 / k + bound, "gradient_difference": shared, "two_sided_compensated": shared + k ** (-2 / 3), "two_way_residual": shared}[method]


def constant_from_norm(p: float, block: int) -> float:
    return norm_constant(p, block)


def carry_stability(effective: float, carry: float) -> bool:
    """Whether the carry may feed on itself: a warning, not a bound."""
    return effective * carry**2 > 1


def convex_potential(down_residual, shared, optimum, anchors, worker_gradients, apply_rate, c_down, carry, extra, step) -> float:
    """What shrinks by the rate at every iteration: weighted last residual, distance, and gap of anchors to the gradients at the optimum."""
    gap = ((anchors - worker_gradients) ** 2).sum(1).mean()
    return float(apply_rate * (1 - (c_down + 1) * apply_rate) * (down_residual**2).sum() + ((shared - optimum) ** 2).sum() + (1 + carry) * extra * apply_rate * step**2 * gap)


def nonconvex_potential(down_residual, excess, anchors, apply_rate, c_down, extra, smooth, step) -> float:
    scale = (c_down + 1) * smooth * apply_rate**2
    return float(scale * (down_residual**2).sum() + excess + 3 * extra * scale * step**2 * (anchors**2).sum(1).mean())


#: fixed values: what each method compresses, the codec assumption, whether a linear rate is proven, and the terms of its nonconvex rate
RATES = (
    ("quantized_gradient", "gradient", "2-norm quantisation", False, "1/K + B"),
    ("gradient_difference", "gradient", "p-norm quantisation", True, "1/sqrt(Kn) + 1/K"),
    ("two_sided_compensated", "gradient and model", "bounded variance", False, "1/sqrt(Kn) + 1/K^(2/3) + 1/K"),
    ("two_way_residual", "gradient and model", "variance within C times the squared norm", True, "1/sqrt(Kn) + 1/K"),
)


def rate_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(RATES, "method string, compresses string, codec_assumption string, linear boolean, nonconvex string")
