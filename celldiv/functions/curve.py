"""Positions on a Hilbert curve of any number of dimensions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Bits of a position that fit a long.
POSITION_BITS = 63


def hilbert_numbers(x: np.ndarray, bits: int) -> np.ndarray:
    """x: n by d integers below 2^bits. Gray-code descent: each plane of bits picks an orthant and turns what lies below."""
    x = np.asfortranarray(x.astype(np.int64))
    d = x.shape[1]
    top = 1 << (bits - 1)
    q = top
    while q > 1:
        low = q - 1
        for i in range(d):
            hit = (x[:, i] & q) != 0
            swap = np.where(hit, 0, (x[:, 0] ^ x[:, i]) & low)
            x[:, 0] ^= np.where(hit, low, swap)
            x[:, i] ^= swap
        q >>= 1
    for i in range(1, d):
        x[:, i] ^= x[:, i - 1]
    turn = np.zeros(len(x), np.int64)
    q = top
    while q > 1:
        turn ^= np.where((x[:, d - 1] & q) != 0, q - 1, 0)
        q >>= 1
    x ^= turn[:, None]
    out = np.zeros(len(x), np.int64)
    for b in range(bits - 1, -1, -1):
        for i in range(d):
            out = out << 1 | (x[:, i] >> b & 1)
    return out


def hilbert_index(codes: list[Column], bits: int) -> Column:
    """The position as a long. Where bits times the number of columns exceed 63, the lowest bits of the codes are left out:
    the curve then runs over a coarser grid, and rows of one grid cell have one position."""
    d = len(codes)
    keep = max(1, min(bits, POSITION_BITS // d))
    if d > POSITION_BITS:
        raise ValueError(f"the curve takes {POSITION_BITS} columns at most")

    @F.pandas_udf("long")
    def run(*columns: pd.Series) -> pd.Series:
        x = np.column_stack([c.to_numpy() for c in columns]) if len(columns[0]) else np.empty((0, d), np.int64)
        return pd.Series(hilbert_numbers(x >> (bits - keep), keep))

    return run(*[c.cast("long") for c in codes])
