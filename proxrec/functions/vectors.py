"""Vector functions for SQL users: Arrow-batched UDF, UDAF and UDTF."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


def register(spark: SparkSession) -> None:
    """Registers vec_dot, cosine_of, vec_axpy, vec_sum and expand_list in the session."""

    @pandas_udf("double")
    def vec_dot(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([float(np.dot(x, y)) if x is not None and y is not None else None for x, y in zip(a, b, strict=True)])

    @pandas_udf("double")
    def cosine_of(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([float(np.dot(x, y) / max(1e-300, np.linalg.norm(x) * np.linalg.norm(y))) for x, y in zip(a, b, strict=True)])

    @pandas_udf("array<double>")
    def vec_axpy(s: pd.Series, a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([(k * np.asarray(x) + np.asarray(y)).tolist() for k, x, y in zip(s, a, b, strict=True)])

    @pandas_udf("array<double>")
    def vec_sum(a: pd.Series) -> list:
        return np.sum(np.stack(a.to_list()), axis=0).tolist()

    @udtf(returnType="place int, item_id string")
    class ExpandList:
        def eval(self, items: list):
            for i, x in enumerate(items or []):
                yield i + 1, x

    for name, f in (("vec_dot", vec_dot), ("cosine_of", cosine_of), ("vec_axpy", vec_axpy), ("vec_sum", vec_sum)):
        spark.udf.register(name, f)
    spark.udtf.register("expand_list", ExpandList)
