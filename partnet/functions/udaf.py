"""Aggregates over Arrow batches, for grouped use where generated sums would be too many."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def entropy_agg(n: pd.Series) -> float:
    """Entropy in bits of the counts of a group."""
    x = n.to_numpy(dtype=float)
    p = x[x > 0] / x.sum()
    return float(-(p * np.log2(p)).sum())


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def array_sum_agg(v: pd.Series) -> list[float]:
    """Sum of the vectors of a group, of any length."""
    return np.sum(np.stack(v.to_numpy()), axis=0).tolist()
