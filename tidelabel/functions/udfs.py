"""User-defined functions, and their registration for SQL.

They are made on call: a module that makes them on import can't be imported by workers.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql.functions import pandas_udf, udtf


def _softmax_first():
    def fn(a, b):
        return 1 / (1 + np.exp(b - a))

    fn.__annotations__ = {"a": pd.Series, "b": pd.Series, "return": pd.Series}
    return pandas_udf(fn, "double")


def _mean():
    def fn(v):
        return float(v.mean())

    fn.__annotations__ = {"v": pd.Series, "return": float}
    return pandas_udf(fn, "double")


def softmax_first(a: Column, b: Column) -> Column:
    """Probability of the first of two logits."""
    return _softmax_first()(a, b)


def mean_of(v: Column) -> Column:
    return _mean()(v)


class Classes:
    """(class, hit) for each class of a label."""

    def eval(self, label, classes):
        for c in range(classes):
            yield c, int(label == c)


def register_functions(spark: SparkSession) -> None:
    """tidelabel_softmax_first, tidelabel_mean and the table function tidelabel_classes."""
    spark.udf.register("tidelabel_softmax_first", _softmax_first())
    spark.udf.register("tidelabel_mean", _mean())
    spark.udtf.register("tidelabel_classes", udtf(Classes, returnType="class int, hit int"))
