"""Intersections of sorted adjacency arrays, and grouped measures, as pandas functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.LongType())
def merge_intersection_size(a: pd.Series, b: pd.Series) -> pd.Series:
    """Common members of two sorted arrays without repeats: all rows of a batch are merged at once."""
    n = [np.fromiter(map(len, side), np.int64, len(side)) for side in (a, b)]
    row = [np.repeat(np.arange(len(k)), k) for k in n]
    x = [np.concatenate(side.to_numpy()).astype(np.int64) if k.sum() else np.zeros(0, np.int64) for side, k in zip((a, b), n, strict=True)]
    if not len(x[0]) or not len(x[1]):
        return pd.Series(np.zeros(len(a), np.int64))
    low = min(int(v.min()) for v in x)
    span = max(int(v.max()) for v in x) - low + 1
    if span * len(a) >= 1 << 63:
        # Members too far apart for a row and a member to make one number go by their places among all members.
        names, at = np.unique(np.concatenate(x), return_inverse=True)
        x, low, span = [at[: len(x[0])], at[len(x[0]) :]], 0, len(names)
    # Either side rises by row and member, so a stable sort merges two runs.
    merged = np.sort(np.concatenate([r * span + (v - low) for r, v in zip(row, x, strict=True)]), kind="stable")
    return pd.Series(np.bincount(merged[1:][merged[1:] == merged[:-1]] // span, minlength=len(a)).astype(np.int64))


@F.pandas_udf(T.DoubleType())
def gini(values: pd.Series) -> float:
    """Inequality of a group's values, 0 for equal ones."""
    x = np.sort(values.to_numpy(np.float64))
    n, total = len(x), x.sum()
    return float((2 * np.arange(1, n + 1) - n - 1) @ x / (n * total)) if n and total else 0.0


@F.pandas_udf(T.LongType())
def h_index(values: pd.Series) -> int:
    """Largest h such that h values are h or more."""
    x = np.sort(values.to_numpy())[::-1]
    return int((x >= np.arange(1, len(x) + 1)).sum())
