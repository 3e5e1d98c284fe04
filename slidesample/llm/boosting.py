"""Histogram gradient-boosted trees for a yes/no label, in numpy; trees live in flat arrays.

`fit` runs on the driver over a bounded sample; `Trees.scores` is what executors call.  Training is deterministic.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Trees:
    """All nodes of all trees side by side: a leaf points at itself, so every row makes the same number of steps."""

    roots: np.ndarray  # per tree: its first node
    feature: np.ndarray  # per node
    threshold: np.ndarray  # per node: go right if value > threshold
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray  # per node: what a leaf adds to the log-odds
    depth: int
    prior: float

    def scores(self, x: np.ndarray) -> np.ndarray:
        """Probability of label 1 for each row of `x`."""
        if len(x) == 0:
            return np.zeros(0)
        at = np.broadcast_to(self.roots, (len(x), len(self.roots))).copy()
        rows = np.arange(len(x))[:, None]
        for _ in range(self.depth):
            at = np.where(x[rows, self.feature[at]] > self.threshold[at], self.right[at], self.left[at])
        return 1 / (1 + np.exp(-(self.prior + self.value[at].sum(axis=1))))


def bin_edges(column: np.ndarray, bins: int) -> np.ndarray:
    """Cut points between bins, at quantiles of the sample."""
    return np.unique(np.quantile(column, np.linspace(0, 1, bins + 1)[1:-1], method="lower"))


def fit(x: np.ndarray, y: np.ndarray, trees: int = 60, depth: int = 4, rate: float = 0.15, bins: int = 48, ridge: float = 1.0, least: int = 5) -> Trees:
    """Logistic loss, second-order gains, level by level.  One class only (or no rows) gives a constant score."""
    share = float(np.clip(y.mean() if len(y) else 0.5, 1e-3, 1 - 1e-3))
    prior = float(np.log(share / (1 - share)))
    nodes: list[list[float]] = []  # feature, threshold, left, right, value
    roots: list[int] = []
    if len(y) and 0 < y.sum() < len(y):
        edges = [bin_edges(x[:, j], bins) for j in range(x.shape[1])]
        coded = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], axis=1)
        margin = np.full(len(y), prior)
        for _ in range(trees):
            p = 1 / (1 + np.exp(-margin))
            margin += grow(nodes, roots, coded, edges, y - p, p * (1 - p), depth, rate, ridge, least)
    if not roots:
        nodes, roots = [[0, np.inf, 0, 0, 0.0]], [0]
    flat = np.array(nodes)
    return Trees(np.array(roots), flat[:, 0].astype(np.int64), flat[:, 1], flat[:, 2].astype(np.int64), flat[:, 3].astype(np.int64), flat[:, 4], depth, prior)


def grow(nodes, roots, coded, edges, g, h, depth, rate, ridge, least) -> np.ndarray:
    """Append one tree to `nodes`; return what it adds to each row's margin."""
    roots.append(len(nodes))
    added, level = np.zeros(len(g)), [(len(nodes), np.arange(len(g)))]
    nodes.append([0, np.inf, 0, 0, 0.0])
    for d in range(depth + 1):
        following = []
        for node, rows in level:
            gs, hs = g[rows].sum(), h[rows].sum()
            best = split_of(coded, edges, g, h, rows, gs, hs, ridge, least) if d < depth else None
            if best is None:
                value = rate * gs / (hs + ridge)
                nodes[node] = [0, np.inf, node, node, value]
                added[rows] = value
                continue
            j, cut = best
            right = coded[rows, j] > cut
            nodes[node] = [j, edges[j][cut], len(nodes), len(nodes) + 1, 0.0]
            for part in (rows[~right], rows[right]):
                following.append((len(nodes), part))
                nodes.append([0, np.inf, len(nodes), len(nodes), 0.0])
        level = following
    return added


def split_of(coded, edges, g, h, rows, gs, hs, ridge, least):
    """Best (feature, bin) of a node, or None."""
    top, found = 1e-6, None
    if len(rows) < 2 * least:
        return None
    gr, hr = g[rows], h[rows]
    for j, e in enumerate(edges):
        if not len(e):
            continue
        code = coded[rows, j]
        n = np.cumsum(np.bincount(code, minlength=len(e) + 1))[:-1]
        gl = np.cumsum(np.bincount(code, gr, len(e) + 1))[:-1]
        hl = np.cumsum(np.bincount(code, hr, len(e) + 1))[:-1]
        gain = gl**2 / (hl + ridge) + (gs - gl) ** 2 / (hs - hl + ridge) - gs**2 / (hs + ridge)
        gain[(n < least) | (len(rows) - n < least)] = -1
        k = int(gain.argmax())
        if gain[k] > top:
            top, found = gain[k], (j, k)
    return found
