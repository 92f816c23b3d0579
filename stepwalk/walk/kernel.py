"""Array kernels of one superstep: many walkers, each with the neighbours of its vertex, drawn at once."""

from __future__ import annotations

import numpy as np

from .rng import SPAN


def runs(lengths: np.ndarray) -> np.ndarray:
    ends = np.cumsum(lengths)
    return np.arange(int(ends[-1]) if len(ends) else 0) - np.repeat(ends - lengths, lengths)


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    return np.repeat(starts, lengths) + runs(lengths)


def member(rows: np.ndarray, ids: np.ndarray, in_rows: np.ndarray, in_ids: np.ndarray) -> np.ndarray:
    """Whether (row, id) is among the (in_row, in_id), which run by row and then id."""
    out = np.zeros(len(rows), bool)
    if not len(rows) or not len(in_rows):
        return out
    low = min(int(ids.min()), int(in_ids.min()))
    high = max(int(ids.max()), int(in_ids.max()))
    bits = max(1, (high - low).bit_length())
    top = max(int(rows.max()), int(in_rows.max())) + 1
    if bits + top.bit_length() < 63:
        sought, there = (rows.astype(np.int64) << bits) + (ids - low), (in_rows.astype(np.int64) << bits) + (in_ids - low)
    else:
        names, code = np.unique(np.concatenate([ids, in_ids]), return_inverse=True)
        sought, there = rows.astype(np.int64) * len(names) + code[: len(ids)], in_rows.astype(np.int64) * len(names) + code[len(ids) :]
    at = np.searchsorted(there, sought)
    at[at == len(there)] = 0
    return there[at] == sought


def pick(mass: np.ndarray, lengths: np.ndarray, draw: np.ndarray) -> np.ndarray:
    """Of each row, the first entry whose running sum exceeds the draw; -1 for rows without entries.

    Whole masses: draw modulo the total.  Others: draw / 2^48 of the total.
    """
    begin = np.cumsum(lengths) - lengths
    some = lengths > 0
    sums = np.concatenate([np.zeros(1, mass.dtype), np.cumsum(mass)])
    base, total = sums[begin], sums[begin + lengths] - sums[begin]
    if mass.dtype.kind == "i":
        target = base + draw % np.maximum(total, 1)
    else:
        target = base + draw / SPAN * total
    at = np.searchsorted(sums, target, side="right") - 1
    at = np.clip(at, begin, np.maximum(begin + lengths - 1, begin))
    return np.where(some, at, -1)


def biased_mass(rows: np.ndarray, ids: np.ndarray, ws: np.ndarray, prev: np.ndarray, is_common: np.ndarray, biased: np.ndarray, factors: tuple) -> np.ndarray:
    """Weight times factor of every neighbour; rows that are not ``biased`` keep plain weights."""
    back, common, other = factors
    whole = ws.dtype.kind == "i" and all(isinstance(f, int) for f in factors)
    factor = np.where(is_common, common, other)
    factor = np.where(ids == prev[rows], back, factor)
    factor = np.where(biased[rows], factor, 1)
    return ws * factor if whole else ws.astype(float) * factor


def draw_corrected(prefix: np.ndarray, ws: np.ndarray, begin: np.ndarray, size: np.ndarray, plain: np.ndarray, special: tuple[np.ndarray, np.ndarray, np.ndarray], draw: np.ndarray, whole: bool) -> np.ndarray:
    """Positions drawn from the spans ``begin``..``begin + size`` of static running sums, each in time logarithmic in its span.

    Every weight counts ``plain`` times; ``special`` (row, position, factor beyond ``plain``) corrects single positions.
    """
    row, place, extra = special
    wide = int(len(ws)) + 1
    marked = row * wide + place
    order = np.argsort(marked, kind="stable")  # few sorted runs, one after the other
    row, place, extra, marked = row[order], place[order], extra[order], marked[order]
    base, sums = prefix[begin], prefix[begin + size] - prefix[begin]
    gains = extra * ws[place] if len(place) else extra * 1
    gain = np.concatenate([np.zeros(1, gains.dtype), np.cumsum(gains)])
    n = len(begin)
    first = np.searchsorted(row, np.arange(n + 1))
    total = plain * sums + gain[first[1:]] - gain[first[:-1]]
    target = draw % total if whole else draw / SPAN * total
    low, high = begin.copy(), begin + size - 1
    me = np.arange(n) * wide
    while True:
        live = np.flatnonzero(low < high)
        if not len(live):
            return low
        mid = (low[live] + high[live]) // 2
        upto = np.searchsorted(marked, me[live] + mid, side="right")
        reached = plain[live] * (prefix[mid + 1] - base[live]) + gain[upto] - gain[first[live]]
        over = reached > target[live]
        high[live] = np.where(over, mid, high[live])
        low[live] = np.where(over, low[live], mid + 1)


def pick_corrected(ids: np.ndarray, prefix: np.ndarray, prev: int, common: np.ndarray, factors: tuple, draw: float) -> int:
    """One walker's draw from static prefix sums, corrected at the last vertex and the common neighbours only.

    ``prefix`` has the running sums of weights with a leading zero, ``common`` positions (in order) of common neighbours.
    The total is other*S + (back-other)*w_prev + (common-other)*sum(w_common): work grows with the shorter list.
    """
    back, near, other = factors
    at_prev = int(np.searchsorted(ids, prev))
    has_prev = at_prev < len(ids) and ids[at_prev] == prev
    special = np.union1d(common, [at_prev] if has_prev else []).astype(np.int64)
    weight = prefix[special + 1] - prefix[special]
    extra = np.where(special == at_prev, back - other, near - other) if has_prev else np.full(len(special), near - other)
    gain = np.concatenate([[0], np.cumsum(extra * weight)])
    total = other * prefix[-1] + gain[-1]
    whole = all(isinstance(f, int) for f in factors) and prefix.dtype.kind == "i"
    target = draw % total if whole else draw / SPAN * total
    low, high = 0, len(ids) - 1
    while low < high:
        mid = (low + high) // 2
        reached = other * prefix[mid + 1] + gain[int(np.searchsorted(special, mid, side="right"))]
        if reached > target:
            high = mid
        else:
            low = mid + 1
    return low
