"""Solvers for summaries on the driver: seeding, alternation, single swaps, exhaustive search."""

from __future__ import annotations

import itertools

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from balclust.operators import cost as C
from balclust.operators import flow


def seed(x: np.ndarray, w: np.ndarray, k: int, r: float, seed_: int = 1) -> np.ndarray:
    """k points, each drawn with chance in proportion to its weighted distance to those before."""
    rng = np.random.default_rng(seed_)
    out = [int(rng.choice(len(x), p=w / w.sum()))]
    near = flow.costs(x, x[out], r)[:, 0]
    while len(out) < k:
        p = near * w
        out.append(int(rng.choice(len(x), p=p / p.sum())) if p.sum() > 0 else int(rng.integers(len(x))))
        near = np.minimum(near, flow.costs(x, x[out[-1:]], r)[:, 0])
    return x[out]


def centre(x: np.ndarray, w: np.ndarray, r: float) -> np.ndarray:
    """A lattice point of low cost for one cluster: the rounded mean for r = 2, a few steps towards the geometric median otherwise."""
    at = np.average(x, axis=0, weights=w)
    if r != 2:
        for _ in range(20):
            dist = np.maximum(1e-6, np.sqrt(((x - at) ** 2).sum(axis=1)))
            at = np.average(x, axis=0, weights=w * dist ** (r - 2))
    return np.rint(at).astype(np.int64)


def alternate(x: np.ndarray, w: np.ndarray, k: int, t: float, r: float, rounds: int = 10, seed_: int = 1) -> tuple[np.ndarray, float]:
    """(centres, cost): exact assignment under the capacity and new centres in turns, while the cost falls."""
    z, best, kept = seed(x, w, k, r, seed_), np.inf, None
    for _ in range(rounds):
        cost = flow.costs(x, z, r)
        found = flow.transport(cost, w, np.full(k, float(t)))
        if found is None:
            return z, np.inf
        now = flow.value(cost, found[0])
        if now >= best - 1e-9:
            break
        best, kept = now, z
        z = np.stack([centre(x, s, r) if (s := found[0][:, j]).sum() > 0 else z[j] for j in range(k)])
    return kept, best


def local_search(x: np.ndarray, w: np.ndarray, z: np.ndarray, t: float, r: float, tries: int = 20, seed_: int = 1) -> tuple[np.ndarray, float]:
    """Single swaps of a centre for an input point, kept where the cost falls."""
    rng = np.random.default_rng(seed_)
    best = flow.capacitated(x, w, z, t, r)
    for _ in range(tries):
        other = z.copy()
        other[rng.integers(len(z))] = x[rng.integers(len(x))]
        if (now := flow.capacitated(x, w, other, t, r)) < best:
            z, best = other, now
    return z, best


def exhaustive(x: np.ndarray, w: np.ndarray, k: int, t: float, r: float) -> tuple[np.ndarray, float]:
    """The best set of k input points as centres; for small inputs."""
    return min(((x[list(c)], flow.capacitated(x, w, x[list(c)], t, r)) for c in itertools.combinations(range(len(x)), k)), key=lambda f: f[1])


def brute_force(x: np.ndarray, z: np.ndarray, t: int, r: float) -> float:
    """The cost of the best of all assignments of unit points; for tiny inputs."""
    cost = flow.costs(x, z, r)
    return min((sum(cost[p, j] for p, j in enumerate(c)) for c in itertools.product(range(len(z)), repeat=len(x)) if max(np.bincount(c)) <= t), default=np.inf)


def opt_estimate(points: DataFrame, k: int, r: float, d: int, sample: int = 20_000, seed_: int = 1) -> tuple[np.ndarray, int]:
    """(centres, cost on all points): an upper bound of the best uncapacitated cost, from a bounded sample and one pass."""
    chosen = points.orderBy(F.xxhash64("tag", *(f"x{m}" for m in range(d))), "tag").limit(sample)
    x, w = C.arrays(chosen, d)
    z, _ = alternate(x[:, :d], w, min(k, len(x)), float(w.sum()), r, seed_=seed_)
    return z, int(C.plain_cost(points, z.tolist(), r).first()[0])


def solve(summary: DataFrame, k: int, capacity: float, r: float, d: int, eta: float = 0.2, seeds: int = 3) -> tuple[np.ndarray, float]:
    """Centres for the input from its summary under (1 + eta) of the capacity; infinite where the summary's weight does not fit."""
    x, w = C.arrays(summary, d, "w")
    t = (1 + eta) * capacity
    found = [alternate(x[:, :d], w, k, t, r, seed_=s) for s in range(1, seeds + 1)]
    z, best = min(found, key=lambda f: f[1])
    return local_search(x[:, :d], w, z, t, r) if np.isfinite(best) else (z, best)
