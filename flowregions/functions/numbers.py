"""The same code lengths for numpy arrays, used inside the kernels."""

from __future__ import annotations

import math

import numpy as np

LN2 = math.log(2.0)
#: Factorials up to here come from a table.
TABLE = 1 << 20
_table: np.ndarray | None = None


def table() -> np.ndarray:
    """log2 n! below TABLE."""
    global _table
    if _table is None:
        _table = np.concatenate([[0.0], np.cumsum(np.log2(np.arange(1, TABLE, dtype=np.float64)))])
    return _table


def lfact(n) -> np.ndarray:
    """log2 n! of whole numbers."""
    known = table()
    n = np.asarray(n)
    if n.size == 0 or n.max() < TABLE:
        return known[n.astype(np.int64, copy=False)]
    out = known[np.minimum(n, TABLE - 1).astype(np.int64)].copy()
    big = n >= TABLE
    m = n[big].astype(np.float64) if n.ndim else float(n)
    value = ((m + 0.5) * np.log(m) - m + 0.5 * math.log(2 * math.pi) + 1 / (12 * m)) / LN2
    if n.ndim:
        out[big] = value
        return out
    return np.float64(value)


def lchoose(n, k):
    return lfact(n) - lfact(k) - lfact(np.asarray(n) - np.asarray(k))


def lmulti(n, k):
    n, k = np.asarray(n), np.asarray(k)
    m = np.maximum(n + k - 1, k)
    if m.size and m.max() < TABLE and m.dtype == k.dtype == np.int64:  # one look at the greatest serves all three
        known = table()
        return known.take(m) - known.take(k) - known.take(m - k)
    return np.where(k == 0, 0.0, lchoose(m, k))


def lcompositions(w, e):
    w, e = np.asarray(w), np.asarray(e)
    some = e > 0
    return np.where(some, lchoose(np.where(some, w - 1, 0), np.where(some, e - 1, 0)), 0.0)
