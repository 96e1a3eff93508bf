"""Arrow functions for what column expressions cannot do well."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql.functions import pandas_udf


@pandas_udf("int")
def gallop_overlap(a: pd.Series, b: pd.Series) -> pd.Series:
    """Size of the intersection of two ascending arrays: the smaller is looked up in the larger."""

    def size(x: np.ndarray, y: np.ndarray) -> int:
        if len(x) > len(y):
            x, y = y, x
        if not len(x):
            return 0
        at = np.minimum(np.searchsorted(y, x), len(y) - 1)
        return int((y[at] == x).sum())

    return pd.Series([size(x, y) for x, y in zip(a, b)], dtype="int32")


@pandas_udf("double")
def vector_mean_norm(v: pd.Series) -> float:
    """Length of the mean of a group's vectors."""
    return float(np.linalg.norm(np.mean(np.stack(v.to_list()), axis=0))) if len(v) else float("nan")
