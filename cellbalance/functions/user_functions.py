"""User-defined functions around the balancers: a grouped aggregate and a table function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import udtf

from .interpolation import barycentric_weights


@F.pandas_udf(T.DoubleType())
def slope_of(y: pd.Series, x: pd.Series) -> float:
    """Least-squares slope of y over x."""
    x = x.astype(float) - float(x.mean())
    squared = float((x * x).sum())
    return float((x * (y - y.mean())).sum() / squared) if squared else 0.0


def weights_of_nodes(n: pd.Series) -> pd.Series:
    """Barycentric weights of n nodes."""
    return n.map(lambda k: barycentric_weights(int(k)).tolist())


@udtf(returnType=T.StructType([T.StructField("k", T.IntegerType()), T.StructField("b", T.LongType())]))
class NearestCuts:
    """Cut vector of one weight array; for lines that fit into a row."""

    def eval(self, weights: list, p: int):
        s = np.concatenate([[0], np.cumsum(np.asarray(weights, dtype=np.int64))])
        n, total = len(s) - 1, int(s[-1])
        yield 0, 0
        for k in range(1, p):
            if not total:
                yield k, k * n // p
                continue
            first = int(np.searchsorted(s * p, k * total, side="right"))
            yield k, first - 1 if 2 * k * total < p * int(s[first - 1] + s[first]) else first
        yield p, n
