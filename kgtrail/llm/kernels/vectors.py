"""Comparing neighbours in a sorted list of unit vectors."""

from __future__ import annotations

import numpy as np


def unit(rows: np.ndarray) -> np.ndarray:
    rows = np.asarray(rows, np.float64)
    rows = rows / np.abs(rows).max(axis=1, keepdims=True)  # else squares may leave the range of doubles
    return rows / np.linalg.norm(rows, axis=1, keepdims=True)


def forest(ids: np.ndarray, rows: np.ndarray, least: float, groups: np.ndarray) -> list[tuple[int, int]]:
    """Verified links (cosine >= least, same group) that connect what all links among the rows
    connect: at most one for each row, however many pairs are alike."""
    n = len(ids)
    alike = (rows @ rows.T) >= least
    alike &= groups[:, None] == groups[None, :]
    left = np.ones(n, bool)
    links = []
    for start in range(n):
        if not left[start]:
            continue
        left[start] = False
        todo = [start]
        while todo:
            k = todo.pop()
            found = np.flatnonzero(alike[k] & left)
            left[found] = False
            links += [(int(ids[k]), int(ids[j])) for j in found]
            todo += found.tolist()
    return links
