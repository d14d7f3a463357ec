"""Column expressions of the softmax model over array columns, and their DuckDB twins.

They stay in the JVM and suit narrow features and fixed models; wide features go
through Arrow batches (``operators.core``).
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def literal(v: Sequence[float]) -> Column:
    return F.array(*(F.lit(float(a)) for a in v))


def total(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, v: s + v)


def dot(x: Column, v: Sequence[float] | Column) -> Column:
    other = v if isinstance(v, Column) else literal(v)
    return total(F.zip_with(x, other, lambda a, b: a * b))


def logits(x: Column, w: np.ndarray) -> Column:
    return F.array(*(dot(x, row) for row in w))


def softmax(z: Column) -> Column:
    e = F.transform(z, lambda v: F.exp(v - F.array_max(z)))
    return F.transform(e, lambda v: v / total(e))


def cross_entropy(p: Column, y: Column) -> Column:
    return -total(F.zip_with(p, y, lambda a, b: b * F.log(F.greatest(a, F.lit(1e-300)))))


def argmax(a: Column) -> Column:
    """Place of the largest entry, from 0; ties: the first."""
    return (F.array_position(a, F.array_max(a)) - 1).cast("int")


def argmin(a: Column) -> Column:
    return (F.array_position(a, F.array_min(a)) - 1).cast("int")


def uplift(s: Column, p: Column, y: Column, gamma: float) -> Column:
    """Class scores y.s - s_c + (1 - gamma) (p - y).s of one row, with s = V x."""
    base = dot(y, s) + F.lit(1 - gamma) * (dot(p, s) - dot(y, s))
    return F.transform(s, lambda v: base - v)


# DuckDB


def list_sql(v: Sequence[float]) -> str:
    return "[" + ", ".join(repr(float(a)) for a in v) + "]"


def logits_sql(x: str, w: np.ndarray) -> str:
    return "[" + ", ".join(f"list_inner_product({x}, {list_sql(r)})" for r in w) + "]"


def softmax_sql(z: str) -> str:
    e = f"list_transform({z}, lambda v: exp(v - list_max({z})))"
    return f"list_transform({e}, lambda q: q / list_sum({e}))"


def fixed_model(classes: int, dims: int, step: int, scale: float) -> np.ndarray:
    """A small fixed matrix by rule, for queries without training noise."""
    c, j = np.mgrid[0:classes, 0:dims]
    return (((7 * c + step * j + c * j) % 13) - 6) / scale
