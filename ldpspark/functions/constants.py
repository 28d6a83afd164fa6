"""Closed-form constants of the mechanisms. All logarithms are natural; they are computed once on the driver and enter plans as literals."""

from __future__ import annotations

import math


def report_scale(eps: float) -> float:
    """c = (e^eps + 1) / (e^eps - 1), by which a randomised sign is multiplied to be unbiased."""
    return 1 / math.tanh(eps / 2)


def keep_probability(eps: float) -> float:
    """Probability that a coin-flip report tells the true sign."""
    return 1 / (1 + math.exp(-eps))


def fair_coin_epsilon(p_truth: float) -> float:
    """Epsilon of answering truthfully with probability ``p_truth`` and at random otherwise."""
    return math.log((1 + p_truth) / (1 - p_truth))


def halfspace_size(d: int) -> int:
    """Number of sign vectors that agree with a given one in more than half of their d places."""
    return sum(math.comb(d, a) for a in range(d // 2 + 1, d + 1))


def halfspace_scale(d: int, eps: float) -> float:
    """Magnitude B of the half-space report, by logarithms so that d may be large."""
    middle = (d - 1) // 2 if d % 2 else d // 2
    ways = lambda n, k: math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)
    if d <= 500:
        top = 2**d + halfspace_size(d) * math.expm1(eps)
        return top / (math.comb(d - 1, middle) * math.expm1(eps))
    half = 0.5 * (0 if d % 2 else math.exp(ways(d, d // 2) - d * math.log(2)))
    share = 0.5 - half  # the half-space's share of all 2^d vectors
    return math.exp(d * math.log(2) - ways(d - 1, middle)) * (1 + share * math.expm1(eps)) / math.expm1(eps)


def halfspace_prob(d: int, eps: float, variant: str = "repaired") -> float:
    """Probability of the agreeing half-space: ``printed`` ignores that the halves differ in size for even d, ``repaired`` weighs by it."""
    if variant == "printed":
        return keep_probability(eps)
    if variant != "repaired":
        raise ValueError(f"unknown variant {variant!r}")
    share = halfspace_size(d) / 2**d
    return math.exp(eps) * share / (math.expm1(eps) * share + 1)


def halfspace_cdf(d: int) -> tuple[list[float], list[float]]:
    """Cumulative probabilities of the number of agreeing places a = 0..d, inside the agreeing half and in the other one."""
    inside = [math.comb(d, a) if 2 * a > d else 0 for a in range(d + 1)]
    other = [0 if 2 * a > d else math.comb(d, a) for a in range(d + 1)]

    def cdf(w: list[int]) -> list[float]:
        total, run, out = sum(w), 0, []
        for x in w:
            run += x
            out.append(run / total)
        return out

    return cdf(inside), cdf(other)


def halfspace_bias(d: int, eps: float, variant: str) -> float:
    """Expected report over true value: 1 if unbiased."""
    p, size, rest = halfspace_prob(d, eps, variant), halfspace_size(d), 2**d - halfspace_size(d)
    gain = lambda keep, total: sum(math.comb(d, a) * (2 * a - d) for a in range(d + 1) if keep(a)) / (d * total)
    agree = p * gain(lambda a: 2 * a > d, size) + (1 - p) * gain(lambda a: 2 * a <= d, rest)
    return halfspace_scale(d, eps) * agree


def effective_epsilon(d: int, eps: float, variant: str) -> float:
    """The epsilon that the half-space report really gives: log ratio of its largest to its smallest output probability."""
    p, size = halfspace_prob(d, eps, variant), halfspace_size(d)
    return math.log(p / size) - math.log((1 - p) / (2**d - size))


def projection_rows(k: int, n: int, eps: float, beta: float) -> int:
    """Rows m of the random sign matrix for k values, n users and failure probability beta; one at least."""
    gamma2 = math.log(2 * k / beta) / (eps * eps * n)
    return max(1, math.ceil(math.log(k + 1) * math.log(2 / beta) / gamma2))


def orthogonal_order(k: int) -> int:
    """Least power of two that holds k columns."""
    return 1 << max(0, (k - 1).bit_length())


def mean_radius(n: int, d: int, eps: float, beta: float) -> float:
    """Bernstein radius: with probability 1-beta every one-coordinate mean of d attributes is within it."""
    c, L = report_scale(eps), math.log(2 * d / beta)
    a, b = 2 * c * c * d, 4 / 3 * c * d
    return (b * L + math.sqrt(b * b * L * L + 4 * n * a * L)) / (2 * n)


def frequency_radius(n: int, d: int, k: int, eps: float, beta: float) -> float:
    """Bernstein radius for the k frequencies of one of d sampled attributes (variance d c^2, range d c + 1)."""
    c, L = report_scale(eps), math.log(2 * k / beta)
    a, b = 2 * d * c * c, 2 / 3 * (d * c + 1)
    return (b * L + math.sqrt(b * b * L * L + 4 * n * a * L)) / (2 * n)


def variances(d: int, eps: float, square: float = 0.0) -> dict[str, float]:
    """Mean variance of one report of one attribute; ``square`` is the mean square of its values."""
    return {"laplace": 8 * d * d / eps**2, "half_space": halfspace_scale(d, eps) ** 2 - square, "one_coordinate": report_scale(eps) ** 2 * d - square}


def batch_size(dim: int, eps: float, n: int, floor_share: int = 1000) -> int:
    """Users per step: 2 d ln d / eps^2, but n / ``floor_share`` at least."""
    return max(1, math.ceil(max(2 * dim * math.log(dim) / eps**2, n / floor_share)))
