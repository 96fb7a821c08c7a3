"""Search among fences as a vectorised function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F


def search_udf(fences: list):
    """A function of a number column: how many of the ascending fences lie at or below each value; null has none."""
    table = np.asarray(fences)

    @F.pandas_udf("int")
    def find(k: pd.Series) -> pd.Series:
        return pd.Series(np.where(k.isna(), 0, np.searchsorted(table, k.fillna(0).to_numpy(), side="right")).astype("int32"))

    return find
