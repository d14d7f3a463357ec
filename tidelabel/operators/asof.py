"""As-of join by a window over the union of both sides: one shuffle on the key, no pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, key: str, time: str, values: list[str]) -> DataFrame:
    """Each left row with the values of the right side's latest row at or before its time (null if none).

    At equal times the right row counts as before. Right rows are taken to be unique by
    key and time.
    """
    own = [c for c in left.columns if c not in (key, time)]
    a = left.select(key, time, *own, *(F.lit(None).cast(right.schema[v].dataType).alias(v) for v in values), F.lit(1).alias("_side"))
    b = right.select(key, time, *(F.lit(None).cast(left.schema[c].dataType).alias(c) for c in own), *values, F.lit(0).alias("_side"))
    w = Window.partitionBy(key).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(b).select(key, time, *own, *(F.last(v, ignorenulls=True).over(w).alias(v) for v in values), "_side").where("_side = 1").drop("_side")
