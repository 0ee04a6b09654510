"""Weighted classification trees and forests in numpy, for training sets that fit a task."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np


@dataclass
class Tree:
    """Node arrays; a leaf has feature -1. ``value`` is the weighted share of class 1 in the node."""

    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray

    def predict(self, x: np.ndarray) -> np.ndarray:
        node = np.zeros(len(x), dtype=np.int64)
        for _ in range(64):
            feature = self.feature[node]
            inner = np.flatnonzero(feature >= 0)
            if not len(inner):
                break
            at = node[inner]
            go_left = x[inner, feature[inner]] <= self.threshold[at]
            node[inner] = np.where(go_left, self.left[at], self.right[at])
        return self.value[node]

    def as_lists(self) -> tuple[list, list, list, list, list]:
        return tuple(a.tolist() for a in (self.feature, self.threshold, self.left, self.right, self.value))


def grow_tree(x: np.ndarray, y: np.ndarray, w: np.ndarray, depth: int, per_split: int, rng: np.random.Generator, min_weight: float = 1.0) -> Tree:
    """A tree by weighted Gini impurity; each split looks at ``per_split`` features, and at more if those give none."""
    nodes: list[list] = []
    ones_of = w * y
    stack = [(np.arange(len(y)), 0, -1, False)]
    while stack:
        rows, level, parent, is_left = stack.pop()
        weight, one = w[rows], ones_of[rows]
        total, ones = weight.sum(), one.sum()
        here = len(nodes)
        nodes.append([-1, 0.0, -1, -1, ones / total if total > 0 else 0.5])
        if parent >= 0:
            nodes[parent][2 if is_left else 3] = here
        if level >= depth or len(rows) < 2 or ones <= 0 or ones >= total:
            continue
        best = (1e-12, -1, 0.0)
        base_1, base_0 = ones**2 / total, (total - ones) ** 2 / total
        for tried, f in enumerate(rng.permutation(x.shape[1])):
            if tried >= per_split and best[1] >= 0:
                break
            v = x[rows, f]
            order = v.argsort(kind="stable")
            v, left_w = v[order], weight[order].cumsum()[:-1]
            at = ((v[1:] > v[:-1]) & (left_w >= min_weight) & (total - left_w >= min_weight)).nonzero()[0]  # places of a split
            if not len(at):
                continue
            left_w, left_1 = left_w[at], one[order].cumsum()[at]
            right_w, right_1 = total - left_w, ones - left_1
            with np.errstate(divide="ignore", invalid="ignore"):
                gain = left_1**2 / left_w + right_1**2 / right_w - base_1
                gain += (left_w - left_1) ** 2 / left_w + (right_w - right_1) ** 2 / right_w - base_0
            k = int(gain.argmax())
            if gain[k] > best[0]:
                best = (float(gain[k]), int(f), float((v[at[k]] + v[at[k] + 1]) / 2))
        if best[1] < 0:
            continue
        nodes[here][0], nodes[here][1] = best[1], best[2]
        goes_left = x[rows, best[1]] <= best[2]
        stack.append((rows[~goes_left], level + 1, here, False))
        stack.append((rows[goes_left], level + 1, here, True))
    feature, threshold, left, right, value = zip(*nodes, strict=True)
    return Tree(np.array(feature), np.array(threshold), np.array(left), np.array(right), np.array(value))


def grow_forest(x: np.ndarray, y: np.ndarray, w: np.ndarray, trees: int, depth: int = 6, bag: float = 0.7, seed: int = 1, per_split: int | None = None) -> list[Tree]:
    """Trees on bags of ``bag`` of the rows, drawn with replacement; log2(features) + 1 features a split by default."""
    rng = np.random.default_rng(seed)
    per_split = per_split or int(math.log2(x.shape[1])) + 1
    size = max(1, round(bag * len(y)))
    out = []
    for _ in range(trees):
        rows = rng.integers(0, len(y), size)
        out.append(grow_tree(x[rows], y[rows], w[rows], depth, per_split, rng))
    return out


def predict_forest(trees: list[Tree], x: np.ndarray) -> np.ndarray:
    """Mean over the trees of the share of class 1."""
    return np.mean([t.predict(x) for t in trees], axis=0) if trees else np.full(len(x), 0.5)
