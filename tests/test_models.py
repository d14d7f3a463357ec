"""The model against Spark's own."""

import numpy as np
import pytest
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.functions import array_to_vector
from pyspark.sql import functions as F

from tidelabel.config import CleanConfig
from tidelabel.operators.core import rows_of, train_newton
from tidelabel.sources.tables import doc_quality


def test_model_equals_the_library_s_on_hard_labels(spark, sf_dir):
    cfg = CleanConfig(lam=0.05, gamma=1.0)
    hard = doc_quality(spark, sf_dir).where("split = 'train' and truth is not null").withColumn("weak", F.expr("array(double(truth = 0), double(truth = 1))"))
    # Spark's leaves constant columns out, so both do without the last one
    hard = hard.withColumn("x", F.expr("slice(x, 1, size(x) - 1)"))
    w = train_newton(rows_of(hard, cfg), cfg)
    fit = LogisticRegression(regParam=cfg.lam, elasticNetParam=0.0, standardization=False, fitIntercept=False, family="multinomial", maxIter=500, tol=1e-12)
    theirs = fit.fit(hard.select(array_to_vector("x").alias("features"), F.col("truth").cast("double").alias("label"))).coefficientMatrix.toArray()
    x = np.array([r.x for r in hard.select("x").collect()])
    assert x @ (w[1] - w[0]) == pytest.approx(x @ (theirs[1] - theirs[0]), abs=1e-4)
