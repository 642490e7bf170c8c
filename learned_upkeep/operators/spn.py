"""A sum-product network over codes: rows are split by clusters, columns by independence, leaves are histograms.

Fitted on cells (codes with counts), so its cost follows the number of distinct cells.  Insertion
sends each new cell down the tree and adds to sum weights and histograms, without changing the structure.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

LEAST_SHARE, MAX_DEPTH, CORRELATED = 0.02, 8, 0.1


@dataclass
class Node:
    kind: str
    columns: list[int]
    children: list[Node] = field(default_factory=list)
    weights: np.ndarray | None = None
    centres: np.ndarray | None = None
    histogram: np.ndarray | None = None


class SumProduct:
    def __init__(self, sizes: tuple[int, ...], smoothing: float = 0.1, seed: int = 1) -> None:
        self.sizes, self.smoothing, self.rng = sizes, smoothing, np.random.default_rng(seed)
        self.root: Node | None = None
        self.rows = 0.0

    def fit(self, cells: np.ndarray, counts: np.ndarray) -> SumProduct:
        self.rows = float(counts.sum())
        self.root = self._build(cells, counts.astype(float), list(range(len(self.sizes))), 0)
        return self

    def _leaf(self, cells: np.ndarray, counts: np.ndarray, c: int) -> Node:
        return Node("leaf", [c], histogram=np.bincount(cells[:, c], counts, self.sizes[c]).astype(float))

    def _build(self, cells, counts, columns, depth) -> Node:
        if len(columns) == 1:
            return self._leaf(cells, counts, columns[0])
        groups = self._independent(cells, counts, columns)
        if len(groups) > 1 or depth >= MAX_DEPTH or counts.sum() < LEAST_SHARE * self.rows or len(cells) < 4:
            groups = groups if len(groups) > 1 else [[c] for c in columns]
            return Node("product", columns, [self._build(cells, counts, g, depth + 1) for g in groups])
        centres, label = self._clusters(cells[:, columns], counts, columns)
        if (label == label[0]).all():
            return Node("product", columns, [self._leaf(cells, counts, c) for c in columns])
        parts = [label == k for k in range(len(centres))]
        weights = np.array([counts[p].sum() for p in parts])
        return Node("sum", columns, [self._build(cells[p], counts[p], columns, depth + 1) for p in parts], weights, centres)

    def _independent(self, cells, counts, columns) -> list[list[int]]:
        """Connected groups of columns whose weighted correlation of codes reaches CORRELATED."""
        x = cells[:, columns].astype(float)
        mean = np.average(x, 0, counts)
        d = (x - mean) * np.sqrt(counts / counts.sum())[:, None]
        cov = d.T @ d
        std = np.sqrt(np.maximum(np.diag(cov), 1e-12))
        linked = np.abs(cov / np.outer(std, std)) >= CORRELATED
        left, groups = set(range(len(columns))), []
        while left:
            group, queue = set(), [min(left)]
            while queue:
                i = queue.pop()
                if i not in group:
                    group.add(i)
                    queue += [j for j in left if linked[i, j] and j not in group]
            left -= group
            groups.append([columns[i] for i in sorted(group)])
        return groups

    def _clusters(self, x: np.ndarray, counts: np.ndarray, columns: list[int], k: int = 2, rounds: int = 20) -> tuple[np.ndarray, np.ndarray]:
        """Weighted k-means on codes scaled by their domains."""
        scale = np.array([self.sizes[c] for c in columns], float)
        x = x / scale
        spread = x[:, np.argmax(np.average((x - np.average(x, 0, counts)) ** 2, 0, counts))]
        centres = np.stack([x[spread.argmin()], x[spread.argmax()]]).astype(float)
        for _ in range(rounds):
            label = ((x[:, None] - centres[None]) ** 2).sum(2).argmin(1)
            new = np.stack([np.average(x[label == i], 0, counts[label == i]) if (label == i).any() else centres[i] for i in range(k)])
            if np.allclose(new, centres):
                break
            centres = new
        return centres * scale, ((x[:, None] - centres[None]) ** 2).sum(2).argmin(1)

    def insert(self, cells: np.ndarray, counts: np.ndarray) -> SumProduct:
        """Adds new cells along the tree."""
        self.rows += float(counts.sum())
        stack = [(self.root, cells, counts.astype(float))]
        while stack:
            node, x, n = stack.pop()
            if not len(x):
                continue
            if node.kind == "leaf":
                node.histogram += np.bincount(x[:, node.columns[0]], n, self.sizes[node.columns[0]])
            elif node.kind == "product":
                stack += [(c, x, n) for c in node.children]
            else:
                scale = np.array([self.sizes[c] for c in node.columns], float)
                label = (((x[:, node.columns][:, None] - node.centres[None]) / scale) ** 2).sum(2).argmin(1)
                for k, child in enumerate(node.children):
                    node.weights[k] += n[label == k].sum()
                    stack.append((child, x[label == k], n[label == k]))
        return self

    def estimate(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Counts of many boxes at once."""
        return self.rows * self._mass(self.root, lo, hi)

    def _mass(self, node: Node, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        if node.kind == "leaf":
            c = node.columns[0]
            h = node.histogram + self.smoothing
            run = np.concatenate([[0.0], np.cumsum(h / h.sum())])
            return np.maximum(0.0, run[np.clip(hi[:, c] + 1, 0, self.sizes[c])] - run[np.clip(lo[:, c], 0, self.sizes[c])])
        parts = [self._mass(c, lo, hi) for c in node.children]
        return np.prod(parts, 0) if node.kind == "product" else np.average(parts, 0, node.weights)
