"""Functions of this library's own: vectorised scalars, an aggregate and table functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, LongType, StringType, StructType


@pandas_udf(StringType())
def edge_id(src: pd.Series, dst: pd.Series) -> pd.Series:
    """Text name of an edge."""
    return src.astype(str) + "-" + dst.astype(str)


@pandas_udf(LongType())
def edge_code(src: pd.Series, dst: pd.Series) -> pd.Series:
    return src * 1000 + dst


@pandas_udf(DoubleType())
def gini(values: pd.Series) -> float:
    """Gini coefficient of non-negative values; 0 where all are equal or none is positive."""
    x = values.sort_values().to_numpy(dtype=float)
    n, total = len(x), x.sum()
    return float(((2 * pd.RangeIndex(1, n + 1).to_numpy() - n - 1) * x).sum() / (n * total)) if total else 0.0


@udtf(returnType=StructType().add("vid", LongType()).add("a", LongType()).add("b", LongType()))
class NeighbourPairs:
    """Pairs a < b of a vertex's sorted neighbours."""

    def eval(self, vid: int, nbrs: list[int]):
        for i, a in enumerate(nbrs):
            for b in nbrs[i + 1 :]:
                yield vid, a, b


@udtf(returnType=StructType().add("vid", LongType()).add("degree", LongType()))
class GraphDegree:
    """Rows of each vertex in a table of edge ends, partitioned by vertex."""

    def __init__(self):
        self.vid, self.n = None, 0

    def eval(self, row):
        self.vid, self.n = row["vid"], self.n + 1

    def terminate(self):
        if self.n:
            yield self.vid, self.n
