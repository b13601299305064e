"""Vectorised user functions: scalar, aggregate and table-valued."""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import functions as F


@F.pandas_udf("double")
def l2_to_constant(v: pd.Series, c: pd.Series) -> pd.Series:
    """Squared distance of each array to the vector that is ``c`` everywhere, one matrix operation per batch."""
    m = np.stack(v.to_numpy()).astype(np.float64) - c.to_numpy(dtype=np.float64)[:, None]
    return pd.Series(np.einsum("ij,ij->i", m, m))


@F.pandas_udf("string")
def nearest_three(ids: pd.Series, dist: pd.Series) -> str:
    return ",".join(str(i) for _, i in heapq.nsmallest(3, zip(dist.tolist(), ids.tolist(), strict=True)))


@F.udtf(returnType="id long, dist double")
class NearestMatches:
    """Of each shard of TABLE(id, seq, embedding, shard): the three items nearest to a vector among those that have a pattern."""

    def __init__(self) -> None:
        self.best: list[tuple[float, int]] = []

    def eval(self, row, pattern, vector) -> None:  # noqa: ANN001
        if pattern in (row["seq"] or ""):
            d = sum((float(a) - b) ** 2 for a, b in zip(row["embedding"], vector, strict=True))
            heapq.heappush(self.best, (-round(d, 4), -row["id"]))
            if len(self.best) > 3:
                heapq.heappop(self.best)

    def terminate(self):  # noqa: ANN201
        for d, i in self.best:
            yield -i, -d
