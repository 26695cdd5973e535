"""Vantage-point trees over 64-bit fingerprints under Hamming distance, in numpy."""

from __future__ import annotations

import numpy as np

LEAF = 64


def _vantage(points: np.ndarray, rng: np.random.Generator) -> tuple[np.uint64, int]:
    """Of a few candidates, the point whose distances to others spread most, and the radius that halves them."""
    probe = points if len(points) <= 256 else points[rng.integers(0, len(points), 256)]
    best, most = points[0], -1.0
    for c in points[rng.integers(0, len(points), 8)]:
        spread = float(np.var(np.bitwise_count(probe ^ c)))
        if spread > most:
            best, most = c, spread
    return best, int(np.median(np.bitwise_count(points ^ best)))


class Router:
    """The upper levels of the tree, built from a sample: leaves are shards. Node i has children 2i+1 and 2i+2."""

    def __init__(self, sample: np.ndarray, depth: int, seed: int = 7):
        rng, self.depth = np.random.default_rng(seed), depth
        self.vantage, self.radius = np.zeros(2**depth - 1, np.uint64), np.full(2**depth - 1, 32, np.int64)
        held = {0: sample}
        for node in range(2**depth - 1):
            points = held.pop(node)
            if len(points):
                self.vantage[node], self.radius[node] = _vantage(points, rng)
            near = np.bitwise_count(points ^ self.vantage[node]) <= self.radius[node]
            held[2 * node + 1], held[2 * node + 2] = points[near], points[~near]

    def route(self, points: np.ndarray, reach: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row, leaf, home): each point's own leaf, and every leaf that may hold a point within reach of it."""
        row, node, home = np.arange(len(points)), np.zeros(len(points), np.int64), np.ones(len(points), bool)
        for _ in range(self.depth):
            d, mu = np.bitwise_count(points[row] ^ self.vantage[node]).astype(np.int64), self.radius[node]
            inside = d <= mu
            goes_in, goes_out = d - reach <= mu, d + reach > mu
            row = np.concatenate([row[goes_in], row[goes_out]])
            home = np.concatenate([(home & inside)[goes_in], (home & ~inside)[goes_out]])
            node = np.concatenate([2 * node[goes_in] + 1, 2 * node[goes_out] + 2])
        return row, node - (2**self.depth - 1), home


class _Union:
    def __init__(self, n: int):
        self.up = np.arange(n)

    def root(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = int(self.up[i])
        return i

    def join(self, ids: np.ndarray) -> None:
        roots = {self.root(int(i)) for i in np.unique(self.up[ids])}
        if len(roots) > 1:
            low = min(roots)
            for r in roots:
                self.up[r] = low

    def labels(self) -> np.ndarray:
        while True:
            nxt = self.up[self.up]
            if (nxt == self.up).all():
                return nxt
            self.up = nxt


def link(points: np.ndarray, queries: np.ndarray, reach: int, seed: int = 11) -> np.ndarray:
    """Component labels over concat(points, queries) after every query is linked to all points within reach of it.

    points and queries are distinct within themselves; a query equal to a point counts as that point. All queries descend
    together: a branch is left when the triangle inequality rules it out for every query that is still there.
    """
    n = len(points)
    everything = np.concatenate([points, queries])
    union, rng = _Union(len(everything)), np.random.default_rng(seed)
    stack = [(np.arange(n), np.arange(n, n + len(queries)))]
    while stack:
        at, asking = stack.pop()
        if not len(at) or not len(asking):
            continue
        own = everything[at]
        if len(at) > LEAF:
            vantage, mu = _vantage(own, rng)
            near = np.bitwise_count(own ^ vantage) <= mu
            if 0 < near.sum() < len(at):
                d = np.bitwise_count(everything[asking] ^ vantage).astype(np.int64)
                stack.append((at[near], asking[d - reach <= mu]))
                stack.append((at[~near], asking[d + reach > mu]))
                continue
        for i in range(0, len(asking), max(1, (4 << 20) // len(at))):
            some = asking[i : i + max(1, (4 << 20) // len(at))]
            close = np.bitwise_count(everything[some][:, None] ^ own[None, :]) <= reach
            q, p = np.nonzero(close)
            if not len(q):
                continue
            cuts = np.flatnonzero(np.diff(q)) + 1
            for q0, group in zip(q[np.r_[0, cuts]].tolist(), np.split(p, cuts)):
                union.join(np.append(at[group], some[q0]))
    return union.labels()
