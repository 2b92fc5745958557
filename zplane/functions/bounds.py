"""Distance bounds between Morton cells, point distances, and their periodic forms; as columns and in numpy."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Relative slack of pruning tests, so that rounding of bounds never decides a result.
BOUND_SLACK = 1e-12


def np_wrap(delta: np.ndarray, box) -> np.ndarray:
    if box is None:
        return delta
    for i, b in enumerate(box):
        if b is not None:
            delta[..., i] -= b * np.floor(delta[..., i] / b + 0.5)
    return delta


def np_bounds(c1, l1, c2, l2, box=None) -> tuple[np.ndarray, np.ndarray]:
    """(d_low, d_up) of cells with centres c and extents l, broadcast over leading axes."""
    with np.errstate(invalid="ignore"):
        delta = np.abs(np_wrap(np.subtract(c1, c2), box))
        half = (l1 + l2) / 2
        low, up = np.maximum(delta - half, 0), delta + half
        low = np.where(np.isinf(half), 0.0, low)
    if box is not None:
        for i, b in enumerate(box):
            if b is not None:
                up[..., i] = np.minimum(up[..., i], b / 2)
                low[..., i] = np.where(half[..., i] >= b / 2, 0.0, low[..., i])
    return np.sqrt((low * low).sum(-1)), np.sqrt((up * up).sum(-1))


def wrap(delta: Column, box: float | None) -> Column:
    return delta if box is None else delta - F.lit(float(box)) * F.floor(delta / F.lit(float(box)) + F.lit(0.5))


def dist2(p: list[Column], q: list[Column], box=None) -> Column:
    """Squared distance, summed from the first dimension on (the same order in every engine)."""
    out = None
    for i, (a, b) in enumerate(zip(p, q)):
        d = wrap(a - b, box[i] if box else None)
        out = d * d if out is None else out + d * d
    return out


def d_low(c1: list[Column], l1: list[Column], c2: list[Column], l2: list[Column], box=None) -> Column:
    terms = [F.greatest(F.abs(wrap(a - b, box[i] if box else None)) - (x + y) / 2.0, F.lit(0.0)) for i, (a, x, b, y) in enumerate(zip(c1, l1, c2, l2))]
    return F.sqrt(sum((t * t for t in terms[1:]), terms[0] * terms[0]))


def d_up(c1: list[Column], l1: list[Column], c2: list[Column], l2: list[Column], box=None) -> Column:
    terms = []
    for i, (a, x, b, y) in enumerate(zip(c1, l1, c2, l2)):
        t = F.abs(wrap(a - b, box[i] if box else None)) + (x + y) / 2.0
        terms.append(F.least(t, F.lit(box[i] / 2.0)) if box and box[i] is not None else t)
    return F.sqrt(sum((t * t for t in terms[1:]), terms[0] * terms[0]))
