"""User-defined functions of every kind, as cross-checks and for what built-ins can't say."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def cosine_pd(a: pd.Series, b: pd.Series) -> pd.Series:
    import numpy as np

    x, y = np.stack(a).astype(float), np.stack(b).astype(float)
    return pd.Series((x * y).sum(1) / np.sqrt((x * x).sum(1) * (y * y).sum(1)))


@F.pandas_udf(T.DoubleType())
def map_terms_agg(cut: pd.Series, vol: pd.Series, total: pd.Series) -> float:
    """The clusters' part of the map equation without the sum of cuts; a grouped aggregate."""
    p = lambda z: z * math.log(z) if z > 0 else 0.0
    return float(sum(p((c + v) / t) - 2 * p(c / t) for c, v, t in zip(cut, vol, total, strict=True)))


@F.udtf(returnType=T.StructType([T.StructField("id", T.LongType()), T.StructField("c", T.LongType())]))
class ExpandMembers:
    """Members of a cluster as rows."""

    def eval(self, ids: list, c: int):
        for i in ids or []:
            yield i, c


def compare_by_component(one: DataFrame, two: DataFrame, comp: DataFrame) -> DataFrame:
    """comp, n, same: per component, nodes and how many pairs of neighbours in id order both labelings treat alike; a cogrouped map."""
    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        m = a.merge(b, on="id").sort_values("id")
        if not len(m):
            return pd.DataFrame({"comp": [], "n": [], "same": []})
        x, y = m.c_x.diff().iloc[1:] == 0, m.c_y.diff().iloc[1:] == 0
        return pd.DataFrame({"comp": [m.comp_x.iloc[0]], "n": [len(m)], "same": [int((x == y).sum())]})

    on = lambda d: d.join(comp, "id").select(F.col("id").alias("id"), F.col("c").alias("c"), F.col("comp").alias("comp")).groupBy("comp")
    return on(one).cogroup(on(two)).applyInPandas(run, "comp long, n long, same long")
