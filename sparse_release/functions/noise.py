"""Noise of the releases, as SQL expressions over keys, and its moments."""

from __future__ import annotations

import math

from .prf import uniform


def alpha_of(eps: float, sensitivity: float = 1.0) -> float:
    """The geometric law's ratio for a budget and a sensitivity."""
    if eps <= 0 or sensitivity <= 0:
        raise ValueError("budget and sensitivity must be positive")
    return math.exp(-eps / sensitivity)


def tail(alpha: float, u: str) -> str:
    """SQL: how many whole steps a one-sided geometric draw goes."""
    return f"CAST(floor(ln({u}) / {math.log(alpha)!r}D) AS BIGINT)"


def geometric(alpha: float, seed: str | int, *keys: str, tag: str = "noise", mode: str = "md5") -> str:
    """SQL: two-sided geometric noise, as the difference of two one-sided draws."""
    return f"({tail(alpha, uniform(seed, f'{tag}+', *keys, mode=mode))} - {tail(alpha, uniform(seed, f'{tag}-', *keys, mode=mode))})"


def laplace(scale: float, seed: str | int, *keys: str, tag: str = "noise", mode: str = "md5") -> str:
    """SQL: Laplace noise for real values. As any floating-point noise, its low bits can tell of the value; prefer whole numbers."""
    half = f"({uniform(seed, tag, *keys, mode=mode)} - 0.5D)"
    return f"(-{scale!r}D * signum({half}) * ln(1D - 2D * abs({half})))"


def moments(alpha: float) -> dict[str, float]:
    """Of two-sided geometric noise: chance of 0, mean magnitude, variance."""
    return {"zero": (1 - alpha) / (1 + alpha), "mean_abs": 2 * alpha / (1 - alpha**2), "variance": 2 * alpha / (1 - alpha) ** 2}


def sensitivity(kind: str, **size: int) -> int:
    """How far one individual moves all published numbers together: disjoint counts 1; levels of a hierarchy; levels of each of several dimensions multiplied;
    a sketch twice its rows; several groupings, their number; rows allowed to one person."""
    match kind:
        case "disjoint":
            return 1
        case "levels":
            return size["levels"]
        case "grid":
            return math.prod(size.values())
        case "sketch":
            return 2 * size["rows"]
        case "groupings":
            return size["sets"]
        case "bounded":
            return size["rows"]
    raise ValueError(kind)
