"""Cutting stock by column generation: few bins of one capacity for a histogram of sizes.

The linear program over patterns (how many items of each class one bin holds) starts with one pattern a class;
a knapsack dynamic program over the dual prices finds the next pattern, until none is worth more than its bin.
Whole parts of the solution are taken as they are; what they leave, a fraction of a bin a pattern at most, is
packed first-fit by decreasing size.
"""

from __future__ import annotations

import numpy as np


def knapsack(prices: np.ndarray, sizes: np.ndarray, capacity: int) -> tuple[float, np.ndarray]:
    """The pattern of most worth within the capacity, items unlimited: (worth, counts)."""
    order = np.argsort(sizes)
    s, p = sizes[order], prices[order]
    worth, took = np.zeros(capacity + 1), np.full(capacity + 1, -1)
    for w in range(1, capacity + 1):
        k = int(np.searchsorted(s, w, "right"))
        worth[w] = worth[w - 1]
        if k:
            value = p[:k] + worth[w - s[:k]]
            best = int(value.argmax())
            if value[best] > worth[w] + 1e-12:
                worth[w], took[w] = value[best], best
    counts, w = np.zeros(len(sizes), np.int64), capacity
    while w > 0:
        if took[w] < 0:
            w -= 1
        else:
            counts[order[took[w]]] += 1
            w -= int(s[took[w]])
    return float(worth[capacity]), counts


def times(matrix: np.ndarray, vector: np.ndarray) -> np.ndarray:
    """Their product without a threaded library: threads that spin cost more than these few numbers."""
    return np.einsum("ij,j->i", matrix, vector)


def inverted(matrix: np.ndarray) -> np.ndarray:
    """The inverse by Gauss-Jordan steps with row exchanges."""
    n = len(matrix)
    work = np.hstack([matrix, np.eye(n)])
    for k in range(n):
        at = k + int(np.abs(work[k:, k]).argmax())
        work[[k, at]] = work[[at, k]]
        work[k] /= work[k, k]
        others = np.arange(n) != k
        work[others] -= work[others, k, None] * work[k]
    return work[:, n:]


def solve(sizes: np.ndarray, demand: np.ndarray, capacity: int, gap: float = 5e-4, rounds: int = 5000) -> tuple[np.ndarray, np.ndarray]:
    """Patterns (rows of counts) and how often each is cut, fractional, near the optimum of the linear program.

    Revised simplex: the basis inverse is updated for each entering column; surplus columns let demands be exceeded.
    The prices divided by the worth of the best pattern are feasible for the dual program, which bounds the
    optimum from below; within `gap` of that, or half a bin, the search ends. Tiny differences in the demands
    keep ties, and so endless exchanges of columns, away.
    """
    n = len(sizes)
    demand = demand + 1e-4 * np.sqrt(np.arange(1, n + 1))
    fit = capacity // sizes
    basis = np.diag(fit.astype(float))
    cost = np.ones(n)
    inverse = np.diag(1.0 / fit)
    x = times(inverse, demand)
    for turn in range(rounds):
        if turn % 200 == 199:
            inverse = inverted(basis)
            x = times(inverse, demand)
        prices = times(inverse.T, cost)
        if prices.min() < -1e-9:
            at = int(prices.argmin())
            column, price = np.zeros(n), 0.0
            column[at] = -1.0
        else:
            worth, counts = knapsack(np.maximum(prices, 0), sizes, capacity)
            now = float(cost @ x)
            if worth <= 1 + 1e-7 or now - float(prices @ demand) / worth < max(0.5, gap * now):
                break
            column, price = counts.astype(float), 1.0
        step = times(inverse, column)
        up = step > 1e-10
        if not up.any():
            break
        ratio = np.full(n, np.inf)
        ratio[up] = np.maximum(x[up], 0) / step[up]
        out = int(ratio.argmin())
        move = ratio[out]
        x = x - move * step
        x[out] = move
        inverse[out] /= step[out]
        others = np.arange(n) != out
        inverse[others] -= np.outer(step[others], inverse[out])
        basis[:, out], cost[out] = column, price
    real = cost > 0
    return basis[:, real].T.round().astype(np.int64), np.maximum(x[real], 0)


def first_fit(sizes: np.ndarray, left: np.ndarray, capacity: int) -> list[np.ndarray]:
    """Bins for a bounded number of items, largest first."""
    rooms: list[int] = []
    bins: list[np.ndarray] = []
    for k in np.argsort(-sizes):
        for _ in range(int(left[k])):
            at = next((i for i, r in enumerate(rooms) if r >= sizes[k]), None)
            if at is None:
                at = len(rooms)
                rooms.append(capacity)
                bins.append(np.zeros(len(sizes), np.int64))
            rooms[at] -= int(sizes[k])
            bins[at][k] += 1
    return bins


def plan(sizes: np.ndarray, demand: np.ndarray, capacity: int) -> list[tuple[int, np.ndarray]]:
    """(how often, pattern) pairs that hold every item of the histogram at least; sizes must be at most the capacity."""
    sizes, demand = np.asarray(sizes, np.int64), np.asarray(demand, np.int64)
    live = demand > 0
    if not live.any():
        return []
    patterns, often = solve(sizes[live], demand[live].astype(float), capacity)
    whole = np.floor(often + 1e-2).astype(np.int64)
    cut = [(int(m), p) for m, p in zip(whole, patterns, strict=True) if m > 0]
    made = sum((m * p for m, p in cut), np.zeros(int(live.sum()), np.int64))
    left = np.maximum(demand[live] - made, 0)
    cut += [(1, p) for p in first_fit(sizes[live], left, capacity)]
    out = []
    for m, p in cut:
        full = np.zeros(len(sizes), np.int64)
        full[live] = p
        out.append((m, full))
    return out
