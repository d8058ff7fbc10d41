"""Histogram gradient-boosted trees in numpy, flattened to arrays, and isotonic calibration."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Trees:
    """Complete trees: ``feature`` and ``threshold`` are trees x inner nodes, ``leaf`` trees x leaves."""

    base: float
    feature: np.ndarray
    threshold: np.ndarray
    leaf: np.ndarray

    def margin(self, x: np.ndarray) -> np.ndarray:
        """All trees at once: each level moves an index per row and tree."""
        out = np.full(len(x), self.base)
        trees, inner = self.feature.shape
        if not trees:
            return out
        depth, tree = (inner + 1).bit_length() - 1, np.arange(trees)
        for start in range(0, len(x), 4096):
            part = x[start : start + 4096]
            row, node = np.arange(len(part))[:, None], np.zeros((len(part), trees), np.int64)
            for _ in range(depth):
                node = 2 * node + 1 + (part[row, self.feature[tree, node]] > self.threshold[tree, node])
            out[start : start + 4096] += self.leaf[tree, node - inner].sum(1)
        return out

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(x), -30, 30)))


def fit(
    x: np.ndarray, y: np.ndarray, trees: int = 120, depth: int = 4, bins: int = 64, rate: float = 0.1,
    l2: float = 1.0, least_hessian: float = 1.0,
) -> Trees:
    """Newton boosting of the logistic loss over quantile bins. One class alone gives a constant."""
    n, inner = len(y), 2**depth - 1
    share = (y.sum() + 0.5) / (n + 1)
    base = float(np.log(share / (1 - share)))
    if n == 0 or y.min() == y.max():
        return Trees(base, np.zeros((0, inner), np.int64), np.zeros((0, inner)), np.zeros((0, inner + 1)))
    edges = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1], method="lower")) for c in x.T]
    binned = np.stack([np.searchsorted(e, c, side="left") for e, c in zip(edges, x.T, strict=True)]).astype(np.int64)
    margin = np.full(n, base)
    out = Trees(base, np.zeros((trees, inner), np.int64), np.full((trees, inner), np.inf), np.zeros((trees, inner + 1)))
    for t in range(trees):
        p = 1 / (1 + np.exp(-margin))
        g, h, node = p - y, p * (1 - p), np.zeros(n, np.int64)
        for level in range(depth):
            first, width = 2**level - 1, 2**level
            local = (node - first) * bins
            best, split_f, split_b = np.full(width, 1e-6), np.zeros(width, np.int64), np.full(width, -1)
            for f, column in enumerate(binned):
                key = local + column
                gl = np.cumsum(np.bincount(key, g, width * bins).reshape(width, bins), axis=1)
                hl = np.cumsum(np.bincount(key, h, width * bins).reshape(width, bins), axis=1)
                gt, ht = gl[:, -1:], hl[:, -1:]
                gain = gl**2 / (hl + l2) + (gt - gl) ** 2 / (ht - hl + l2) - gt**2 / (ht + l2)
                gain[(hl < least_hessian) | (ht - hl < least_hessian)] = 0
                gain[:, len(edges[f]) :] = 0
                at = gain.argmax(1)
                value = gain[np.arange(width), at]
                better = value > best
                best[better], split_f[better], split_b[better] = value[better], f, at[better]
            for k in np.flatnonzero(split_b >= 0):
                out.feature[t, first + k], out.threshold[t, first + k] = split_f[k], edges[split_f[k]][split_b[k]]
            k = node - first
            node = 2 * node + 1 + ((split_b[k] >= 0) & (binned[split_f[k], np.arange(n)] > split_b[k]))
        k = node - inner
        out.leaf[t] = -rate * np.bincount(k, g, inner + 1) / (np.bincount(k, h, inner + 1) + l2)
        margin += out.leaf[t][k]
    return out


@dataclass
class Isotonic:
    """A rising map from scores to shares: straight lines between the means of pooled groups."""

    at: np.ndarray
    value: np.ndarray

    def __call__(self, s: np.ndarray) -> np.ndarray:
        return np.interp(s, self.at, self.value) if len(self.at) else np.asarray(s)


def fit_isotonic(score: np.ndarray, y: np.ndarray, prior: float = 1.0) -> Isotonic:
    """Pool adjacent violators; each pooled share is drawn to one half by ``prior`` pseudo rows."""
    if len(y) < 2 or y.min() == y.max():
        return Isotonic(np.empty(0), np.empty(0))
    order = np.argsort(score, kind="stable")
    blocks: list[list[float]] = []
    for s, v in zip(score[order].tolist(), y[order].tolist(), strict=True):
        blocks.append([v, 1.0, s, s])
        while len(blocks) > 1 and blocks[-2][0] * blocks[-1][1] >= blocks[-1][0] * blocks[-2][1]:
            last = blocks.pop()
            blocks[-1] = [blocks[-1][0] + last[0], blocks[-1][1] + last[1], blocks[-1][2], last[3]]
    at, value = [], []
    for total, n, low, high in blocks:
        share = (total + prior / 2) / (n + prior)
        at += [low] if low == high else [low, high]
        value += [share] if low == high else [share, share]
    return Isotonic(np.array(at), np.maximum.accumulate(value))


def auc(score: np.ndarray, y: np.ndarray) -> float:
    """Probability that a positive scores above a negative, ties counting half."""
    _, place, counts = np.unique(score, return_inverse=True, return_counts=True)
    rank = (np.cumsum(counts) - (counts - 1) / 2)[place]
    p = y == 1
    return float((rank[p].sum() - p.sum() * (p.sum() + 1) / 2) / max(1, p.sum() * (~p).sum()))
