"""The similarity functions as SQL functions of a session."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from . import kernel


def _matrix(x) -> np.ndarray:
    return np.array([np.asarray(t, float) for t in x]) if x is not None and len(x) else np.zeros((0, 1))


def mv_sim(q: pd.Series, v: pd.Series, gamma: pd.Series) -> pd.Series:
    """Unified similarity of a query to an object; null for a null side."""
    return pd.Series([None if a is None or b is None else kernel.mv_sim(_matrix(a), _matrix(b), int(g)) for a, b, g in zip(q, v, gamma)], dtype="float64")


def edge_weight(u: pd.Series, v: pd.Series) -> pd.Series:
    """Symmetric weight of two objects; null for a null side or one without tokens."""
    full = lambda x: x is not None and len(x)
    return pd.Series([kernel.edge_weight(_matrix(a), _matrix(b)) if full(a) and full(b) else None for a, b in zip(u, v)], dtype="float64")


@F.udtf(returnType="tok_ix int, s double")
class GammaNearest:
    """gamma_nearest(token, object, gamma): the object's nearest tokens, best first, ties by place."""

    def eval(self, token: list, vecs: list, gamma: int):
        if token is None or not vecs:
            return
        s = np.array(vecs, float) @ np.array(token, float)
        for i in np.lexsort((np.arange(len(s)), -s))[:gamma]:
            yield int(i), float(s[i])


#: name -> body over the arguments a and b, run by the engine itself
EXPRESSIONS = {
    "vec_dot": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "vec_l2": "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))",
}


def register(spark: SparkSession) -> None:
    """mv_sim, edge_weight, gamma_nearest, vec_dot and vec_l2 for this session's SQL."""
    spark.udf.register("mv_sim", F.pandas_udf(mv_sim, DoubleType()))
    spark.udf.register("edge_weight", F.pandas_udf(edge_weight, DoubleType()))
    spark.udtf.register("gamma_nearest", GammaNearest)
    for name, body in EXPRESSIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {body}")
