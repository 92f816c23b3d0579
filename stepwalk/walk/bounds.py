"""Bounds of a transition probability from the sizes and weight ranges of its two vertices alone.

For a move from u over v to a vertex x other than u: the weight of x is at least wmin and at most wmax of v; its factor lies
between the smaller and the larger of 1 and 1/q; the total is one return term, c common terms and the rest, with c between
nothing and as many as both vertices allow.  The total is linear in c, so its extremes stand at the ends.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def _ends(d_u, d_v, p: float, q: float, form: str, least):
    """The two totals, in units of a weight: no common neighbour and as many as can be."""
    most = least(d_u, d_v - 1) if form == "loose" else least(d_u - 1, d_v - 1)
    none = 1 / p + (d_v - 1) / q
    return none, 1 / p + most + (d_v - 1 - most) / q


def bound_low(d_u: Column, d_v: Column, wmin: Column, wmax: Column, p: float, q: float, form: str = "tight") -> Column:
    """``tight`` uses that v is a neighbour of u itself; ``loose`` does not."""
    a, b = _ends(d_u, d_v, p, q, form, F.least)
    return min(1.0, 1 / q) * wmin / (F.greatest(a, b) * wmax)


def bound_high(d_u: Column, d_v: Column, wmin: Column, wmax: Column, p: float, q: float, form: str = "tight") -> Column:
    """Capped at 1."""
    a, b = _ends(d_u, d_v, p, q, form, F.least)
    return F.least(F.lit(1.0), max(1.0, 1 / q) * wmax / (F.least(a, b) * wmin))


def gap(d_u: np.ndarray, d_v: np.ndarray, wmin: np.ndarray, wmax: np.ndarray, p: float, q: float, form: str = "tight") -> np.ndarray:
    """High minus low, in arrays, with the same order of operations as the columns."""
    a, b = _ends(d_u.astype(float), d_v.astype(float), p, q, form, np.minimum)
    low = min(1.0, 1 / q) * wmin / (np.maximum(a, b) * wmax)
    return np.minimum(1.0, max(1.0, 1 / q) * wmax / (np.minimum(a, b) * wmin)) - low
