"""User-defined functions and aggregates over Arrow batches."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, LongType


@F.pandas_udf(DoubleType())
def cosine(a: pd.Series, b: pd.Series) -> pd.Series:
    x, y = np.array(a.tolist(), np.float64), np.array(b.tolist(), np.float64)
    return pd.Series((x * y).sum(axis=1) / np.maximum(np.linalg.norm(x, axis=1) * np.linalg.norm(y, axis=1), 1e-300))


@F.pandas_udf(LongType())
def distinct_inbound(e: pd.Series) -> int:
    return int(e.nunique())
