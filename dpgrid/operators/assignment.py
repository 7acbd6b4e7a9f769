"""Minimum-cost one-to-one assignment of small square matrices."""

from __future__ import annotations

import numpy as np


def assign(cost: np.ndarray) -> np.ndarray:
    """Column of each row in an assignment of least total cost, by shortest augmenting paths over dual prices."""
    n = len(cost)
    if cost.shape != (n, n):
        raise ValueError("a square matrix is needed")
    c = np.asarray(cost, np.float64)
    row_price, col_price = np.zeros(n), np.zeros(n)
    owner = np.full(n, -1)  # row that holds each column
    for start in range(n):
        dist, via = np.full(n, np.inf), np.full(n, -1)
        done = np.zeros(n, bool)
        row, col, base = start, -1, 0.0
        while True:
            slack = base + c[row] - row_price[row] - col_price
            better = ~done & (slack < dist)
            dist[better], via[better] = slack[better], col
            open_ = np.where(done, np.inf, dist)
            col = int(open_.argmin())
            base = float(dist[col])
            done[col] = True
            if owner[col] < 0:
                break
            row = int(owner[col])
        # Prices move by how much nearer a column was than the free one.
        gain = base - dist[done]
        held = owner[done]
        col_price[done] -= gain
        row_price[held[held >= 0]] += gain[held >= 0]
        row_price[start] += base
        while col >= 0:
            before = int(via[col])
            owner[col] = owner[before] if before >= 0 else start
            col = before
    made = np.empty(n, np.int64)
    made[owner] = np.arange(n)
    return made


def matching_cost(cost: np.ndarray) -> float:
    return float(cost[np.arange(len(cost)), assign(cost)].sum()) if len(cost) else 0.0
