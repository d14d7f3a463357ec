"""Quality and cost measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidelabel.operators.core import loss_of


def f1(truth: np.ndarray, predicted: np.ndarray, classes: int) -> float:
    """F1 of class 1 for two classes, the classes' mean otherwise; a class that neither side has counts 0."""
    def one(c):
        hit = int(((truth == c) & (predicted == c)).sum())
        return 2 * hit / max(int((truth == c).sum() + (predicted == c).sum()), 1)

    return float(one(1) if classes == 2 else np.mean([one(c) for c in range(classes)]))


def confusions(rows, w: np.ndarray) -> tuple[float, np.ndarray]:
    """(sum of losses, [truth, predicted] counts) of trusted rows, in one pass."""
    c = w.shape[0]

    def fn(x, y, g):
        cells = np.bincount(y.argmax(axis=1) * c + (x @ w.T).argmax(axis=1), minlength=c * c)
        return np.append(loss_of(x, y, g, w).sum(), cells)

    if not rows.size:
        return 0.0, np.zeros((c, c))
    s = np.ravel(rows.total(fn)[0])
    return float(s[0]), s[1:].reshape(c, c)


def f1_of(table: np.ndarray) -> float:
    """``f1`` from [truth, predicted] counts."""
    each = 2 * np.diag(table) / np.maximum(table.sum(axis=0) + table.sum(axis=1), 1)
    return float(each[1] if len(table) == 2 else each.mean())


def quality(rows, w: np.ndarray) -> dict[str, float]:
    """Mean loss and F1 on trusted rows."""
    loss, table = confusions(rows, w)
    return {"loss": loss / max(rows.size, 1), "f1": f1_of(table)}


def confusion(predictions: DataFrame) -> DataFrame:
    return predictions.groupBy("truth", "pred").agg(F.count("*").alias("n"))


def f1_frame(predictions: DataFrame, macro: bool = False) -> DataFrame:
    """f1 of (truth, pred) rows, by conditional sums."""
    classes = predictions.select(F.explode(F.array("truth", "pred")).alias("c")).distinct() if macro else None
    if not macro:
        s = predictions.agg(F.sum(F.expr("if(truth = 1 and pred = 1, 1, 0)")).alias("tp"), F.sum(F.expr("if(truth = 1, 1, 0)")).alias("t"), F.sum(F.expr("if(pred = 1, 1, 0)")).alias("p"))
        return s.select((F.lit(2.0) * F.col("tp") / F.greatest(F.col("t") + F.col("p"), F.lit(1))).alias("f1"))
    each = predictions.select(F.explode(F.array(F.struct(F.col("truth").alias("c"), F.lit(1).alias("t"), F.lit(0).alias("p"), (F.col("truth") == F.col("pred")).cast("int").alias("h")), F.struct(F.col("pred").alias("c"), F.lit(0).alias("t"), F.lit(1).alias("p"), F.lit(0).alias("h")))).alias("z")).select("z.*")
    per_class = each.groupBy("c").agg((F.lit(2.0) * F.sum("h") / F.greatest(F.sum("t") + F.sum("p"), F.lit(1))).alias("f1"))
    return per_class.join(F.broadcast(classes), "c").agg(F.avg("f1").alias("f1"))


def agreement(picks: DataFrame, truth: DataFrame) -> DataFrame:
    """Suggested labels equal to the truth, of those picked."""
    return picks.join(truth.select("row_id", "truth"), "row_id").agg(F.sum((F.col("best_class") == F.col("truth")).cast("int")).alias("n_match"), F.count("*").alias("n"))


def same_picks(a: DataFrame, b: DataFrame) -> DataFrame:
    """(only_a, only_b): rows picked by one side only; both 0 where the picks agree."""
    a, b = a.select("row_id"), b.select("row_id")
    return a.exceptAll(b).agg(F.count("*").alias("only_a")).crossJoin(b.exceptAll(a).agg(F.count("*").alias("only_b")))


def mean_and_spread(values: list[float]) -> tuple[float, float]:
    return float(np.mean(values)), float(np.std(values, ddof=1)) if len(values) > 1 else 0.0


def fidelity(estimated: np.ndarray, exact: np.ndarray) -> dict[str, float]:
    """Correlation and slope of estimates against exact influences."""
    slope = float(np.polyfit(estimated, exact, 1)[0]) if len(exact) > 1 else 0.0
    return {"corr": float(np.corrcoef(estimated, exact)[0, 1]), "slope": slope}
