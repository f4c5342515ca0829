"""The SQL surface: scalar, aggregate and table functions for spark.sql."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..settings import Settings
from . import influence as I
from . import similarity as S


@F.pandas_udf(T.DoubleType())
def dempster(theta: pd.Series) -> float:
    """Combined support of normalised confidences."""
    t = np.minimum(theta.to_numpy(dtype=float), 1 - 1e-12)
    z = float(np.log(t / (1 - t)).sum()) if len(t) else 0.0
    return 1 / (1 + np.exp(-np.clip(z, -700, 700)))


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def wls_curve(x: pd.Series, label: pd.Series, weight: pd.Series) -> list:
    """tau, alpha, sigma of a feature's weighted line, with that weight of a match; null where it has no rising curve."""
    ok = x.notna() & label.notna()
    v, y = x[ok].to_numpy(dtype=float), label[ok].to_numpy()
    sums = [f(v[y == k]) for k in (0, 1) for f in (len, np.sum, lambda u: (u * u).sum())]
    curve = I.curves_np(np.array([sums], dtype=float), float(weight.iloc[0]) if len(weight) else 1.0, Settings())
    return [float(curve[c][0]) for c in ("tau", "alpha", "sigma")] if curve["active"][0] else None


@F.pandas_udf(T.DoubleType())
def t_central(q: pd.Series, dof: pd.Series) -> pd.Series:
    return pd.Series(I.central_t_np(q.to_numpy(dtype=float), dof.to_numpy(dtype=float)))


@F.pandas_udf(T.IntegerType())
def lcs_run(a: pd.Series, b: pd.Series) -> pd.Series:
    """Longest common run of two token arrays."""

    def one(x, y) -> int:
        best, row = 0, {}
        at: dict[str, list[int]] = {}
        for j, w in enumerate(y):
            at.setdefault(w, []).append(j)
        for w in x:
            row = {j: row.get(j - 1, 0) + 1 for j in at.get(w, ())}
            best = max(best, *row.values()) if row else best
        return best

    return pd.Series([one(x, y) if x is not None and y is not None else 0 for x, y in zip(a, b, strict=True)])


@F.udtf(returnType=T.StructType([T.StructField("family", T.StringType()), T.StructField("token", T.StringType())]))
class TokenFeatures:
    """Rows of shared and unshared tokens of two arrays."""

    def eval(self, a: Row, b: Row):
        x, y = set(a or ()), set(b or ())
        for t in sorted(x & y):
            yield "same", t
        for t in sorted(x ^ y):
            yield "diff", t


def register_all(spark: SparkSession) -> None:
    """jaro, jaro_winkler, lcs_run, t_central, dempster, wls_curve, token_features."""
    spark.udf.register("jaro", S.jaro)
    spark.udf.register("jaro_winkler", S.jaro_winkler)
    spark.udf.register("lcs_run", lcs_run)
    spark.udf.register("t_central", t_central)
    spark.udf.register("dempster", dempster)
    spark.udf.register("wls_curve", wls_curve)
    spark.udtf.register("token_features", TokenFeatures)
