"""Shared parts of the block-wise pair operators."""

from __future__ import annotations

import numpy as np


def dense_roots(linked: np.ndarray) -> np.ndarray:
    """Smallest row index reachable from each row of a symmetric boolean matrix."""
    n = len(linked)
    root = np.arange(n)
    left = np.ones(n, bool)
    for start in range(n):
        if not left[start]:
            continue
        left[start] = False
        edge = [start]
        while len(edge):
            reach = linked[edge].any(0) & left
            edge = np.flatnonzero(reach)
            left[edge] = False
            root[edge] = start
    return root


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges ``(node, smallest node of its component)`` that span what the links ``a - b`` join."""
    nodes, where = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = where[: len(a)], where[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[x], label[y])
        new = label.copy()
        np.minimum.at(new, label[x], low)
        np.minimum.at(new, label[y], low)
        new = new[new]
        if (new == label).all():
            break
        label = new
    keep = label != np.arange(len(nodes))
    return nodes[keep], nodes[label[keep]]
