"""Python twins of built-in expressions, for tests and for users who compose their own."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import LongType


@pandas_udf(LongType())
def leg_mm_py(ax: pd.Series, ay: pd.Series, bx: pd.Series, by: pd.Series) -> pd.Series:
    """The rounded-up Euclidean distance; the engine itself uses the column expression."""
    dx, dy = ax - bx, ay - by
    return pd.Series(np.ceil(np.sqrt((dx * dx + dy * dy).astype("float64"))).astype("int64"))


@pandas_udf(LongType())
def least_sum(first: pd.Series, second: pd.Series) -> int:
    """Grouped aggregate: the least of pairwise sums, a min-plus product cell."""
    return int((first + second).min())
