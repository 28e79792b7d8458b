"""Assignments of a summary under capacities, on the driver: an exact transport solver, removal of splits, exchange per level.

The network has one node for each centre; moving mass from centre i to j costs the least of d(p, j) - d(p, i) over
points held by i. Mass moves along cheapest chains until no centre is over capacity.
"""

from __future__ import annotations

import heapq
import math

import numpy as np


def costs(x: np.ndarray, centres: np.ndarray, r: float) -> np.ndarray:
    sq = ((x[:, None, :].astype(np.int64) - np.asarray(centres, np.int64)[None]) ** 2).sum(axis=2)
    return sq.astype(float) if r == 2 else sq.astype(float) ** (r / 2)


#: Points up to which a transport begins with the nearest centres; with more it begins with prices that nearly balance the loads.
COLD = 5000


def warm_prices(cost: np.ndarray, w: np.ndarray, capacity: np.ndarray, rounds: int = 40) -> np.ndarray:
    """Prices near those of a cheapest assignment: one centre after the other gets the least price at which it is not over capacity. They only shorten the way of transport."""
    price, k = np.zeros(cost.shape[1]), cost.shape[1]
    for _ in range(rounds):
        before = price.copy()
        for j in range(k):
            other = np.delete(cost + price, j, axis=1).min(axis=1) if k > 1 else np.full(len(cost), np.inf)
            worth = other - cost[:, j]
            order = np.argsort(-worth, kind="stable")
            held = np.searchsorted(np.cumsum(w[order]), capacity[j], side="right")
            price[j] = max(0.0, float(worth[order[held]])) if held < len(order) and np.isfinite(worth[order[held]]) else 0.0
        if np.abs(price - before).max() <= 1e-9 * max(1.0, float(price.max())):
            break
    return price


def transport(cost: np.ndarray, w: np.ndarray, capacity: np.ndarray) -> tuple[np.ndarray, np.ndarray] | None:
    """(shares n x k, prices k) of a cheapest fractional assignment; None if capacities are too small.

    Successive cheapest chains from an overfull centre to one with room, found by label correction over the k centres.
    """
    n, k = cost.shape
    if w.sum() > capacity.sum() * (1 + 1e-12):
        return None
    share = np.zeros((n, k))
    start = np.zeros(k) if n <= COLD else warm_prices(cost, w, capacity)
    first = np.argmin(cost + start, axis=1)
    share[np.arange(n), first] = w
    load = share.sum(axis=0)
    tiny = 1e-9 * max(1.0, float(w.sum()))

    # Who moves cheapest from i to j: the points held at first are in order once, those that come later wait in a heap. A point that left is passed over.
    order, at, late = {}, np.zeros((k, k), np.int64), [[[] for _ in range(k)] for _ in range(k)]
    for i in range(k):
        own = np.flatnonzero(first == i)
        for j in range(k):
            order[i, j] = own[np.argsort(cost[own, j] - cost[own, i], kind="stable")]
    step, who = np.full((k, k), np.inf), np.full((k, k), -1)

    def cheapest(i: int) -> None:
        for j in range(k):
            if j == i:
                continue
            own, waiting = order[i, j], late[i][j]
            while at[i, j] < len(own) and not share[own[at[i, j]], i] > tiny / 1e3:
                at[i, j] += 1
            while waiting and not share[waiting[0][1], i] > tiny / 1e3:
                heapq.heappop(waiting)
            p = own[at[i, j]] if at[i, j] < len(own) else -1
            best = min([*([(cost[p, j] - cost[p, i], p)] if p >= 0 else []), *waiting[:1]], default=(np.inf, -1))
            step[i, j], who[i, j] = best

    for i in range(k):
        cheapest(i)
    while True:
        over = np.flatnonzero(load > capacity + tiny)
        early = not len(over)
        if early:  # prices at the start may have sent away what a centre with room holds cheaper
            if not start.any():
                break
            over = np.flatnonzero(load > tiny)
        dist, back = np.full(k, np.inf), np.full(k, -1)
        dist[over] = 0
        for _ in range(k):
            through = dist[:, None] + step
            best = through.argmin(axis=0)
            better = through[best, np.arange(k)] < dist - 1e-12
            if not better.any():
                break
            dist[better], back[better] = through[best, np.arange(k)][better], best[better]
        room = np.flatnonzero(load < capacity - tiny)
        if not len(room) or not np.isfinite(dist[room]).any():
            break
        end = room[np.argmin(dist[room])]
        if early and dist[end] >= -1e-9 * max(1.0, float(start.max())):
            break
        chain = [end]
        while back[chain[-1]] >= 0 and len(chain) <= k:
            chain.append(back[chain[-1]])
        chain.reverse()
        amount = min(load[chain[0]] - (0 if early else capacity[chain[0]]), capacity[end] - load[end])
        moves = [(a, b, who[a, b]) for a, b in zip(chain, chain[1:])]
        amount = min([amount, *(share[p, a] for a, _, p in moves)])
        for a, b, p in moves:
            share[p, a] -= amount
            share[p, b] += amount
            for j in range(k):
                if j != b:
                    heapq.heappush(late[b][j], (cost[p, j] - cost[p, b], p))
        load[chain[0]] -= amount
        load[end] += amount
        for i in set(chain):
            cheapest(i)
    return share, prices_of(step, load, capacity, tiny)


def prices_of(step: np.ndarray, load: np.ndarray, capacity: np.ndarray, tiny: float) -> np.ndarray:
    """Prices that certify the assignment: the cheapest way from each centre to one with room (0 where there is room)."""
    k = len(load)
    price = np.where(load < capacity - tiny, 0.0, np.inf)
    if np.isinf(price).all():
        price[:] = 0.0
        for _ in range(k):
            price = np.minimum(price, (step + price[None]).min(axis=1))
        return price - price.min()
    for _ in range(k):
        price = np.minimum(price, (step + price[None]).min(axis=1))
    return np.maximum(price, 0)


def dual_value(cost: np.ndarray, w: np.ndarray, capacity: np.ndarray, price: np.ndarray) -> float:
    return float((w * (cost + price).min(axis=1)).sum() - (capacity * price).sum())


def value(cost: np.ndarray, share: np.ndarray) -> float:
    return float((cost * share).sum())


def remove_splits(cost: np.ndarray, share: np.ndarray) -> tuple[np.ndarray, int]:
    """(centre of each point, points that were still split): cycles among split points are cancelled, then each split point goes to its nearest centre.

    Turning a cycle of an optimal assignment costs nothing, so at most k - 1 split points remain.
    """
    share = share.copy()
    tiny = 1e-9 * max(1.0, share.sum())
    while True:
        cycle = _cycle(share > tiny)
        if cycle is None:
            break
        gain = sum(cost[p, b] - cost[p, a] for p, a, b in cycle)
        if gain > 0:
            cycle = [(p, b, a) for p, a, b in cycle]
        amount = min(share[p, a] for p, a, _ in cycle)
        for p, a, b in cycle:
            share[p, a] -= amount
            share[p, b] += amount
        share[share < tiny] = 0
    split = np.flatnonzero((share > tiny).sum(axis=1) > 1)
    out = share.argmax(axis=1)
    out[split] = cost[split].argmin(axis=1)
    return out, len(split)


def _cycle(held: np.ndarray) -> list[tuple[int, int, int]] | None:
    """A cycle of the graph of split points and centres, as (point, from centre, to centre); None if there is none."""
    near: dict[int, list[tuple[int, int]]] = {}
    for p in np.flatnonzero(held.sum(axis=1) > 1):
        cs = np.flatnonzero(held[p])
        for a, b in zip(cs, cs[1:]):  # a path through a point's centres joins them
            near.setdefault(int(a), []).append((int(b), int(p)))
            near.setdefault(int(b), []).append((int(a), int(p)))
    seen: dict[int, tuple[int, int] | None] = {}
    for root in near:
        if root in seen:
            continue
        seen[root] = None
        stack = [(root, -1, -1)]
        while stack:
            at, came, by = stack.pop()
            skipped = False
            for to, p in near[at]:
                if to == came and p == by and not skipped:
                    skipped = True
                    continue
                if to in seen:
                    return _between(seen, at, to, p)
                seen[to] = (at, p)
                stack.append((to, at, p))
    return None


def _between(seen: dict, at: int, to: int, p: int) -> list[tuple[int, int, int]]:
    def up(c: int) -> list[int]:
        out = [c]
        while seen[out[-1]] is not None:
            out.append(seen[out[-1]][0])
        return out

    a, b = up(at), up(to)
    meet = next(c for c in a if c in set(b))
    way = [(p, at, to)]
    c = to
    while c != meet:
        parent, q = seen[c]
        way.append((q, c, parent))
        c = parent
    down, c = [], at
    while c != meet:
        parent, q = seen[c]
        down.append((q, parent, c))
        c = parent
    return way + down[::-1]


def capacitated(x: np.ndarray, w: np.ndarray, centres: np.ndarray, t: float, r: float) -> float:
    """Cost of a cheapest fractional assignment; infinite if the capacities do not suffice."""
    cost = costs(x, centres, r)
    found = transport(cost, w, np.full(len(centres), float(t)))
    return math.inf if found is None else value(cost, found[0])


def bottleneck(x: np.ndarray, w: np.ndarray, centres: np.ndarray, t: float) -> float:
    """Least squared radius within which all mass can be assigned under the capacity (r without bound)."""
    cost = costs(x, centres, 2)
    radii = np.unique(cost)
    low, high = 0, len(radii) - 1
    if w.sum() > t * len(centres):
        return math.inf
    while low < high:
        mid = (low + high) // 2
        far = (cost > radii[mid]).astype(float)
        found = transport(far, w, np.full(len(centres), float(t)))
        low, high = (low, mid) if found and value(far, found[0]) < 1e-6 else (mid + 1, high)
    return float(radii[low])


def reassign(x: np.ndarray, tags: np.ndarray, w: float, centres: np.ndarray, sizes: np.ndarray, r: float) -> np.ndarray:
    """A cheapest assignment of points of one weight with given numbers for the centres, ties exchanged into lexicographic order."""
    cost = costs(x, centres, r)
    share, _ = transport(cost, np.ones(len(x)), sizes.astype(float))
    out = np.rint(share).argmax(axis=1)
    return canonical(x, tags, out, centres, r)


def canonical(x: np.ndarray, tags: np.ndarray, assigned: np.ndarray, centres: np.ndarray, r: float) -> np.ndarray:
    """Points that a pair of centres ties exchange centres until the lexicographically smaller ones are with the earlier centre."""
    out, cost = assigned.copy(), costs(x, centres, r)
    k, again = len(centres), True
    while again:
        again = False
        for i in range(k):
            for j in range(i + 1, k):
                both = np.flatnonzero((out == i) | (out == j))
                diff = np.round((cost[both, i] - cost[both, j]) * 1e6)
                order = both[np.lexsort([tags[both], *x[both].T[::-1], diff])]
                n = int((out[both] == i).sum())
                want = np.where(np.arange(len(order)) < n, i, j)
                before, after = cost[both, out[both]].sum(), cost[order, want].sum()
                if (out[order] != want).any() and after <= before + 1e-6 * max(1.0, before):
                    out[order] = want
                    again = True
    return out
