"""One law for what noise makes of empty cells under any of the reductions.

A cut keeps magnitudes of at least lo; a threshold tau keeps magnitude x with chance min(x / tau, 1). reach(x) is, up to a constant, the chance that an empty cell is
kept with a magnitude of at least x; so reach(lo) gives the chance of being kept, and reach(x) / reach(lo) the law of the kept magnitude. Pure filtering, pure
sampling, and both together are the same few lines, real thresholds and thresholds below the cut included.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np

from .prf import BITS


@dataclass(frozen=True)
class KeepLaw:
    """alpha: the noise's ratio; cut: least magnitude kept (0 or 1: any but 0); tau: sampling threshold (1 or less: none); sides: 2, or 1 for positive values only."""

    alpha: float
    cut: float = 0.0
    tau: float = 1.0
    sides: int = 2

    @property
    def lo(self) -> int:
        return max(math.ceil(self.cut), 1)

    @property
    def top(self) -> int:
        """Magnitudes above are kept for sure."""
        return math.floor(self.tau) if self.tau > 1 else 0

    def _mass(self, x: int) -> float:
        return self.alpha**x / (1 - self.alpha)

    def _moment(self, x: int) -> float:
        return self.alpha**x * (x * (1 - self.alpha) + self.alpha) / (1 - self.alpha) ** 2

    def reach(self, x: int) -> float:
        t = self.top
        return (self._moment(x) - self._moment(t + 1)) / self.tau + self._mass(t + 1) if x <= t else self._mass(x)

    def keep(self) -> float:
        """Chance that an empty cell is kept."""
        return self.sides * (1 - self.alpha) / (1 + self.alpha) * self.reach(self.lo)

    def at_least(self, x: int) -> float:
        """Chance that a kept magnitude is x or more."""
        return 1.0 if x <= self.lo else self.reach(x) / self.reach(self.lo)

    def magnitude(self, u, far):
        """Kept magnitudes for arrays of uniform draws, with so many steps beyond the last point: the largest x with reach(x) above u * reach(lo), by halving."""
        a, b, wanted = np.full(len(u), self.lo), np.full(len(u), self.top + 1), self.reach(self.lo) * u
        while (b - a > 1).any():
            middle = (a + b) // 2
            passed = (self._moment(middle) - self._moment(self.top + 1)) / self.tau + self._mass(self.top + 1) > wanted
            a, b = np.where(passed, middle, a), np.where(passed, b, np.maximum(middle, a + 1))
        return np.where(u < self.at_least(self.top + 1), self.top + 1 + far, a)

    def cuts(self) -> list[int]:
        """For magnitudes lo + 1 up to where the tail is a plain geometric one: draws below cuts()[k] reach lo + 1 + k. Whole numbers, so every engine agrees."""
        out: list[int] = []
        for x in range(self.lo + 1, self.top + 2):
            c = round(self.at_least(x) * (1 << BITS))
            if not c:
                break
            out.append(c)
        return out


def pick_cut(m: int, n: int, alpha: float, target: float, sides: int = 2) -> int:
    """The least whole cut under which about `target` empty cells are kept; 1 if no cell is empty, since none can be kept then."""
    if target <= 0 or m < n:
        raise ValueError("a target is needed, and no more cells than the domain has")
    return 1 if m == n else max(1, math.ceil(math.log((1 + alpha) * target / sides / (m - n)) / math.log(alpha)))


def pick_tau(l1: float, m: int, alpha: float, target: float) -> float:
    """A threshold under which about `target` cells are sampled, from totals that are public or noised."""
    return (l1 + 2 * m * alpha / (1 - alpha**2)) / target


def pick_tau_empty(m: int, n: int, alpha: float, target: float, cut: float = 0.0) -> float:
    """The threshold under which `target` empty cells are expected to be sampled."""
    expected = lambda tau: (m - n) * KeepLaw(alpha, cut, tau).keep()
    lo, hi = 1.0, 2.0
    if expected(lo) <= target:
        return lo
    while expected(hi) > target:
        hi *= 2
    for _ in range(80):
        lo, hi = (lo, (lo + hi) / 2) if expected((lo + hi) / 2) <= target else ((lo + hi) / 2, hi)
    return hi


def solve_tau(sizes: list[tuple[int, int]], m: int, n: int, alpha: float, target: float, cut: float = 0.0) -> float:
    """The threshold for `target` rows in all, given how many occupied cells have each noisy magnitude. It reads the data: never publish it; as a first guess for
    a sample of fixed size it does no harm, since that sample's law does not depend on the guess."""
    lo_mag = max(math.ceil(cut), 1)

    def expected(tau: float) -> float:
        return sum(c * min(x / max(tau, 1.0), 1.0) for x, c in sizes if x >= lo_mag) + (m - n) * KeepLaw(alpha, cut, tau).keep()

    lo, hi = 1.0, 2.0
    if expected(lo) <= target:
        return lo
    while expected(hi) > target:
        hi *= 2
    for _ in range(80):
        lo, hi = (lo, (lo + hi) / 2) if expected((lo + hi) / 2) <= target else ((lo + hi) / 2, hi)
    return hi


def laplace_keep(scale: float, cut: float, tau: float) -> float:
    """Chance that an empty cell with Laplace noise is kept; a threshold of at most the cut means pure filtering."""
    if tau <= cut or tau <= 0:
        return math.exp(-cut / scale)
    return ((cut + scale) * math.exp(-cut / scale) - scale * math.exp(-tau / scale)) / tau


def predicted_error(span: int, m: int, alpha: float, scheme: str = "flat") -> float:
    """Standard deviation of noise in a range answer: flat grows with the span, hierarchies with the levels' own noise and the cover's size."""
    levels = math.ceil(math.log2(max(m, 2))) + 1
    var = lambda a: 2 * a / (1 - a) ** 2
    if scheme == "flat":
        return math.sqrt(span * var(alpha))
    return math.sqrt(2 * math.ceil(math.log2(max(span, 2))) * var(alpha ** (1 / levels)))


def advise_cut(mean: float, spread: float, density: float) -> int:
    """About half the mean count; less where counts are spread, more where the table is sparse."""
    return max(1, round(mean / 2 * (0.5 if spread > 0.3 * mean else 1.0) * (1.25 if density < 0.02 else 0.8)))
