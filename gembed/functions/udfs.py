"""Functions for SQL users: scalar products of vectors, vector aggregates, and table functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


@pandas_udf("double")
def gembed_dot(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([None if x is None or y is None else float((x.astype("float64") * y).sum()) for x, y in zip(a, b, strict=True)])


@pandas_udf("double")
def gembed_cos(a: pd.Series, b: pd.Series) -> pd.Series:
    def one(x, y):
        if x is None or y is None:
            return None
        x, y = x.astype("float64"), y.astype("float64")
        size = ((x * x).sum() * (y * y).sum()) ** 0.5
        return float((x * y).sum() / size) if size > 0 else 0.0

    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)])


@pandas_udf("array<double>")
def vec_mean(v: pd.Series) -> list:
    import numpy as np

    return np.mean(np.stack([np.asarray(x, "float64") for x in v]), 0).tolist()


@pandas_udf("array<double>")
def vec_total(v: pd.Series) -> list:
    import numpy as np

    return np.sum(np.stack([np.asarray(x, "float64") for x in v]), 0).tolist()


@udtf(returnType="step: int, p_src: int, p_dst: int")
class BucketOrder:
    """bucket_order(P, kind): the buckets of an order, step by step."""

    def eval(self, parts: int, kind: str):
        from gembed.operators.schedule import order

        for i, (a, b) in enumerate(order(kind, parts)):
            yield i, a, b


@udtf(returnType="pos: int, cand: int")
class BatchedNegatives:
    """batched_negatives(C, U): which of the C + U candidates are negatives of each edge of a chunk."""

    def eval(self, chunk: int, uniform: int):
        for i in range(chunk):
            for j in range(chunk + uniform):
                if i != j:
                    yield i, j


def register_all(spark: SparkSession) -> None:
    for name, f in (("gembed_dot", gembed_dot), ("gembed_cos", gembed_cos), ("vec_mean", vec_mean), ("vec_total", vec_total)):
        spark.udf.register(name, f)
    spark.udtf.register("bucket_order", BucketOrder)
    spark.udtf.register("batched_negatives", BatchedNegatives)
