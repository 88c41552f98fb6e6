"""NumPy forms of the lane operations and of the slice product, for Arrow batches."""

from __future__ import annotations

import numpy as np

from graphslices.schema import MARK
from graphslices.semiring import Semiring


def lane_cmp(a, b, op="="):
    return ((a == b) if op == "=" else (a != b)).astype(np.int64)


def lane_blend(a, b, mask):
    return np.where(mask != 0, b, a)


def complement(a):
    return (np.asarray(a) == 0).astype(np.int64)


def support(a):
    return (np.asarray(a) != 0).astype(np.int64)


def slice_products(cols: np.ndarray, widths: np.ndarray, vector: np.ndarray, s: Semiring, c: int, vals: np.ndarray | None = None) -> np.ndarray:
    """Lanes (rows x c) of the products of slices with a vector. cols: their arrays in a row, column by column; markers are masked before anything is read.

    Slices of one width are computed as one three-dimensional array. vals, if given, scale what the neighbours bring (only the real semiring uses them).
    """
    out = np.full((len(widths), c), s.zero, dtype=s.dtype)
    starts = np.cumsum(widths * c) - widths * c
    for w in np.unique(widths):
        if not w:
            continue
        own = np.flatnonzero(widths == w)
        at = starts[own][:, None] + np.arange(w * c)
        index = cols[at]
        real = index != MARK
        got = s.np_edge(vector[np.where(real, index, 0)])
        if vals is not None:
            got = got * vals[at]
        got = np.where(real, got, s.zero)
        out[own] = s.np_plus.reduce(got.reshape(len(own), w, c), axis=1)
    return out
