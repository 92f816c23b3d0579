"""Alias tables: one uniform number picks an entry, another decides between it and its alias."""

from __future__ import annotations

import numpy as np


def build(weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(accept, alias) of positive weights."""
    n = len(weights)
    share = np.asarray(weights, float) * (n / np.sum(weights))
    accept, alias = np.ones(n), np.arange(n, dtype=np.int32)
    small = [k for k in range(n) if share[k] < 1]
    large = [k for k in range(n) if share[k] >= 1]
    while small and large:
        s, g = small.pop(), large[-1]
        accept[s], alias[s] = share[s], g
        share[g] -= 1 - share[s]
        if share[g] < 1:
            small.append(large.pop())
    return accept, alias


def pick(accept: np.ndarray, alias: np.ndarray, r1: float, r2: float) -> int:
    k = min(int(r1 * len(accept)), len(accept) - 1)
    return k if r2 < accept[k] else int(alias[k])


def probabilities(accept: np.ndarray, alias: np.ndarray) -> np.ndarray:
    """What the table draws: the normalised weights again."""
    n = len(accept)
    return (accept + np.bincount(alias, 1 - accept, n)) / n
