"""Tree ensembles for a bounded training sample, fitted by histograms in one process.

The method draws t items of the domain to learn from, whatever the domain's size: t rows of a few features fit one
process, and hundreds of trees take seconds where a cluster would run a job for each level of each tree. Prediction is
distributed. Samples beyond MOST_ROWS go to the cluster's own regressors (operators.model).
"""

from __future__ import annotations

import numpy as np

#: Training rows, bins of a feature, least rows of a leaf.
MOST_ROWS, BINS, LEAF = 500_000, 64, 5
#: Rows that are asked at once.
STRETCH = 1 << 13


class Ensemble:
    """start + the sum over trees of step * leaf value; trees are complete arrays of nodes (feature -1: a leaf)."""

    def __init__(self, start: float, step: float, feature: np.ndarray, threshold: np.ndarray, value: np.ndarray):
        self.start, self.step, self.feature, self.threshold, self.value = start, step, feature, threshold, value
        self.breaks = self.levels = None
        if feature.size and feature.max() <= 0:  # one feature: a step function
            self.breaks = np.unique(threshold[feature == 0])
            middle = np.concatenate([self.breaks, [np.inf]])
            self.levels = self.walk(middle[:, None])

    def leaves(self) -> np.ndarray:
        """The value at the end of each path of a complete tree, left to right; a path goes on to the left below a leaf."""
        depth = int(np.log2(self.feature.shape[1] + 1)) - 1
        trees, paths = np.arange(len(self.feature))[:, None], np.arange(2**depth)[None, :]
        at = np.zeros((len(self.feature), 2**depth), np.int64)
        for level in range(depth):
            at = np.where(self.feature[trees, at] < 0, at, 2 * at + 1 + (paths >> (depth - 1 - level) & 1))
        return self.value[trees, at]

    def walk(self, x: np.ndarray) -> np.ndarray:
        """Every split is asked of a stretch of rows at once, and the answers pick the path: no row is followed by itself."""
        out, leaves = np.full(len(x), self.start), self.leaves()
        depth = int(np.log2(self.feature.shape[1] + 1)) - 1
        for first in range(0, len(x), STRETCH):
            columns = np.ascontiguousarray(x[first : first + STRETCH].T)
            part, none = out[first : first + STRETCH], np.zeros(columns.shape[1], bool)
            for feature, threshold, leaf in zip(self.feature.tolist(), self.threshold, leaves, strict=True):
                turns, path = [], np.zeros(columns.shape[1], np.uint8)
                for level in range(depth):
                    asked = [none if feature[i] < 0 else columns[feature[i]] > threshold[i] for i in range(2**level - 1, 2 ** (level + 1) - 1)]
                    for turn in reversed(turns):
                        asked = [left if left is right else left ^ ((left ^ right) & turn) for left, right in zip(asked[::2], asked[1::2], strict=True)]
                    turns.append(asked[0])
                    path = path * np.uint8(2) + asked[0] if depth <= 8 else path.astype(np.int64) * 2 + asked[0]
                part += self.step * leaf[path]
        return out

    def predict(self, x: np.ndarray) -> np.ndarray:
        if self.breaks is not None:
            return self.levels[np.searchsorted(self.breaks, x[:, 0])]
        return self.walk(x)

    @property
    def nodes(self) -> int:
        """Nodes that are reached: splits, and the leaves below them."""
        return int((self.feature >= 0).sum()) * 2 + len(self.feature)


def _listed(codes: np.ndarray) -> list[tuple]:
    """Of each feature the commonest bin, the rows outside it and their bins: what is in it follows from the whole."""
    out = []
    for c in range(codes.shape[1]):
        most = int(np.bincount(codes[:, c], minlength=BINS).argmax())
        rows = np.flatnonzero(codes[:, c] != most)
        out.append((most, rows, codes[rows, c]))
    return out


def _tree(codes: np.ndarray, listed: list[tuple], edges: list[np.ndarray], y: np.ndarray, weight: np.ndarray, depth: int, columns: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """feature, threshold and value of each node, and the node where each row ends."""
    size = 2 ** (depth + 1) - 1
    feature, threshold, value = np.full(size, -1, np.int64), np.zeros(size), np.zeros(size)
    node, wy = np.zeros(len(y), np.int64), weight * y
    for level in range(depth + 1):
        first, width = 2**level - 1, 2**level
        here = node >= first
        local = np.where(here, node - first, width)
        n, s = (np.bincount(local, v, width + 1)[:width] for v in (weight, wy))
        value[first : first + width] = s / np.maximum(n, 1e-12)
        if level == depth:
            break
        best, cut, of = np.full(width, 1e-12), np.zeros(width, np.int64), np.full(width, -1, np.int64)
        for c in columns:
            most, rows, bins = listed[c]
            cell = local[rows] * BINS + bins
            bars = [np.bincount(cell, v[rows], (width + 1) * BINS)[: width * BINS].reshape(width, BINS) for v in (weight, wy)]
            for bar, whole in zip(bars, (n, s), strict=True):
                bar[:, most] = whole - bar.sum(1)
            left_n, left_s = (bar.cumsum(1)[:, :-1] for bar in bars)
            right_n, right_s = n[:, None] - left_n, s[:, None] - left_s
            gain = left_s**2 / np.maximum(left_n, 1e-12) + right_s**2 / np.maximum(right_n, 1e-12) - (s**2 / np.maximum(n, 1e-12))[:, None]
            gain[(left_n < LEAF) | (right_n < LEAF)] = 0
            at = gain.argmax(1)
            top = gain[np.arange(width), at]
            better = top > best
            best[better], cut[better], of[better] = top[better], at[better], c
        split = np.flatnonzero(of >= 0)
        feature[first + split] = of[split]
        threshold[first + split] = [edges[of[i]][min(cut[i], len(edges[of[i]]) - 1)] for i in split]
        moving = here & (of[np.minimum(local, width - 1)] >= 0)
        rows = np.flatnonzero(moving)
        where = local[rows]
        node[rows] = 2 * node[rows] + 1 + (codes[rows, of[where]] > cut[where])
    return feature, threshold, value, node


def _binned(x: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
    edges = [np.unique(np.quantile(x[:, c], np.linspace(0, 1, BINS + 1)[1:-1], method="lower")) for c in range(x.shape[1])]
    return np.column_stack([np.searchsorted(e, x[:, c]) for c, e in enumerate(edges)]), edges


def boosted(x: np.ndarray, y: np.ndarray, trees: int, depth: int, step: float) -> Ensemble:
    """Least-squares boosting: every tree fits what the ones before leave."""
    codes, edges = _binned(x)
    listed = _listed(codes)
    out, rest, ones, columns = [], y - y.mean(), np.ones(len(y)), np.arange(x.shape[1])
    for _ in range(trees):
        feature, threshold, value, node = _tree(codes, listed, edges, rest, ones, depth, columns)
        out.append((feature, threshold, value))
        rest = rest - step * value[node]
    return Ensemble(float(y.mean()), step, *(np.array(v) for v in zip(*out, strict=True)))


def forest(x: np.ndarray, y: np.ndarray, trees: int, depth: int, seed: int = 7) -> Ensemble:
    """The mean of trees on bootstrapped rows, each with a third of the features (one at least)."""
    codes, edges = _binned(x)
    listed = _listed(codes)
    random, out = np.random.default_rng(seed), []
    for _ in range(trees):
        columns = random.permutation(x.shape[1])[: max(1, x.shape[1] // 3)]
        out.append(_tree(codes, listed, edges, y, random.poisson(1.0, len(y)).astype(float), depth, columns)[:3])
    return Ensemble(0.0, 1 / trees, *(np.array(v) for v in zip(*out, strict=True)))
