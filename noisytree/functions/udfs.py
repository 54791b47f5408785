"""Arrow functions beside the column versions, and aggregates for small groups."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F


def hilbert_encode_arrow(order: int):
    """A pandas UDF of (x, y) cells: the same positions as functions.hilbert.encode, a batch at a time."""

    @F.pandas_udf("long")
    def encode(x: pd.Series, y: pd.Series) -> pd.Series:
        px, py = x.to_numpy(np.int64), y.to_numpy(np.int64)
        at, swap, flip = (np.zeros(len(px), np.int64) for _ in range(3))
        for k in range(order - 1, -1, -1):
            a, b = ((px >> k) & 1) ^ flip, ((py >> k) & 1) ^ flip
            rx, ry = np.where(swap == 1, b, a), np.where(swap == 1, a, b)
            at = 4 * at + ((3 * rx) ^ ry)
            swap, flip = swap ^ (1 - ry), flip ^ (rx & (1 - ry))
        return pd.Series(at)

    return encode


def smooth_sens_agg(lo: float, hi: float, decay: float):
    """A grouped aggregate of v: the smooth sensitivity of its median. The group is held in memory, so for
    small groups only; operators.medians.smooth ships a window of ranks."""

    @F.pandas_udf("double")
    def sigma(v: pd.Series) -> float:
        from noisytree.operators.medians import smooth_sigma

        x = np.sort(np.clip(v.dropna().to_numpy(np.float64), lo, hi))
        return smooth_sigma(x, (len(x) + 1) // 2, lo, hi, decay)

    return sigma
