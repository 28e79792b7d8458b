"""Parameters of the summary: the proved formulas, and a calibrated profile of the same form with small constants."""

from __future__ import annotations

import math
from typing import NamedTuple


class Params(NamedTuple):
    """All that a summary of one guess needs; by level -1..levels for cells, 0..levels for rates."""

    profile: str
    k: int
    r: float
    d: int
    levels: int
    epsilon: float
    eta: float
    guess: float
    gamma: float
    xi: float
    independence: int
    m: float
    cell_cap: float
    mass_factor: float

    def cell_threshold(self, level: int) -> float:
        """Least size of a heavy cell of a level: a hundredth of the guess over the cell's diameter to the power r."""
        return 0.01 * self.guess / (math.sqrt(self.d) * 2.0 ** (self.levels - level)) ** self.r

    def rate(self, level: int) -> float:
        if self.profile == "theory":
            return min(1.0, 2.0 ** (2 * (self.r + 10)) * self.independence / (self.xi**3 * self.gamma * self.cell_threshold(level)))
        return min(1.0, self.m / self.cell_threshold(level))

    def mass_cap(self, level: int) -> float:
        return self.mass_factor * self.cell_threshold(level)

    def size_rates(self, level: int) -> tuple[float, float]:
        """Rates at which cells' and parts' sizes are estimated from hashed samples."""
        base = 1e6 * 100 * self.d * self.levels if self.profile == "theory" else 1e3
        return min(1.0, base / self.cell_threshold(level)), min(1.0, base / (self.gamma * self.cell_threshold(level)))

    @property
    def size_bound(self) -> float:
        """The proved bound of the summary's size."""
        spread, logs = self.k + self.d ** (1.5 * self.r), max(1.0, math.log2(self.k * self.d * self.levels))
        return 8e12 * 2.0 ** (10 * (self.r + 10)) * self.r * self.k**6 * self.d * spread**5 * self.levels**10 * logs / min(self.epsilon, self.eta) ** 4

    def heavy_bound(self, opt: float) -> float:
        return 2000 * (self.k + self.d ** (1.5 * self.r)) * self.levels * opt / self.guess

    @property
    def centre_cell_bound(self) -> float:
        return 2000 * self.k * self.levels


def derive(k: int, r: float, d: int, levels: int, guess: float, epsilon: float = 0.2, eta: float = 0.2, profile: str = "calibrated", m: float = 64.0, gamma: float = 0.05, kappa_cells: float = 4.0, kappa_mass: float = 8.0, scope: str = "all") -> Params:
    """scope: whether the sample is to serve all sets of centres or one that is fixed beforehand."""
    if not (k >= 1 and d >= 1 and levels >= 0 and r >= 1 and 0 < epsilon <= 1 and 0 < eta <= 1):
        raise ValueError("parameters out of range")
    spread, depth = k + d ** (1.5 * r), max(1, levels)
    if profile == "theory":
        small = 2.0 ** (-2 * (r + 10))
        gamma = small * min(eta / (k * depth), epsilon / (spread * depth))
        xi = small * min(epsilon, eta) / (k * spread * depth**2)
        log = max(1, math.ceil(math.log2(k * d * depth)))
        independence = int(1e6 * r * k**3 * d * depth * log)
        return Params(profile, k, r, d, levels, epsilon, eta, guess, gamma, xi, independence, math.inf, 20_000 * spread * depth, 10_000 * (k * depth + d ** (1.5 * r)))
    if profile != "calibrated":
        raise ValueError(profile)
    independence = 8 if scope == "all" else 4
    return Params(profile, k, r, d, levels, epsilon, eta, guess, gamma, 1 / (200 * k), independence, m, kappa_cells * spread * depth, kappa_mass * (k * depth + d ** (1.5 * r)))


def guess_for(n: int, unit: int) -> float:
    """The largest power of two up to n times a unit cost per point."""
    return float(1 << (max(1, n * unit).bit_length() - 1))


def fixed_instance_rate(xi: float, size: float, k: int, r: float, delta: float, d: int = 0, levels: int = 0) -> tuple[int, float]:
    """(independence, rate) that one fixed set of centres and half-spaces needs, or with d and levels all of them."""
    log = math.ceil(math.log2(k / delta))
    independence = 100 * k * log if not d else 2000 * k**3 * d * levels * log
    return independence, min(1.0, 1000 * 2.0 ** (2 * r) * independence / (xi**3 * size))


def tail_bound(mean: float, most: float, independence: int, off: float) -> float:
    """Bound of the chance that a sum of limited independence with terms up to most is off its mean by so much."""
    return min(1.0, 8 * ((mean * independence * most + independence**2 * most**2) / off**2) ** (independence / 2))


def all_assignments_bound(n: int, k: int) -> float:
    """Samples that a union bound over all assignments would need: more than there are points."""
    return n * math.log(k)


def assignments_bound(side: int, d: int, k: int) -> float:
    """log2 of the number of assignments that can be optimal: a half-space for each pair of centres."""
    return d * math.log2(side) * k * (k - 1) / 2
