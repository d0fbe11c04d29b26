"""Functions that pass through pandas: for measures that users bring along; the searches never call them."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import DoubleType


@pandas_udf(DoubleType())
def cosine(a: pd.Series, b: pd.Series) -> pd.Series:
    """Cosine of two columns of arrays of one length, batch by batch; null for zero vectors."""
    if not len(a):
        return pd.Series([], dtype="float64")
    x, y = np.stack(a.to_numpy()).astype(np.float64), np.stack(b.to_numpy()).astype(np.float64)
    size = np.sqrt((x * x).sum(axis=1) * (y * y).sum(axis=1))
    return pd.Series(np.divide((x * y).sum(axis=1), size, out=np.full(len(x), np.nan), where=size > 0)).replace({np.nan: None})


@pandas_udf(DoubleType())
def deviation(values: pd.Series) -> float:
    """Standard deviation of a group's values, all of them counted."""
    return float(values.to_numpy(dtype=np.float64).std()) if len(values) else float("nan")
