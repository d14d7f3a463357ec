"""The given tables, and the training sets that the workloads draw from them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tidelabel.functions.features import combined_votes, insults, labelling_votes, standardised, text_statistics, vector_features, with_text_features
from tidelabel.functions.linear import argmax, fixed_model, logits
from tidelabel.functions.rand import random_weak, split_of
from tidelabel.schema import TABLES


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    reader = spark.read.schema(TABLES[name]) if name in TABLES else spark.read
    return reader.parquet(f"{sf_dir}/{name}.parquet")


def training_set(rows: DataFrame, classes: int, weak: Column | None = None, seed: str = "weak", split: Column | None = None) -> DataFrame:
    """TRAIN rows from (row_id, x, truth): weak labels are random unless given; nothing is clean yet."""
    return rows.select(
        F.col("row_id").cast("bigint").alias("row_id"), "x", (weak if weak is not None else random_weak(seed, "row_id", classes)).alias("weak"), F.col("truth").cast("int").alias("truth"),
        F.lit(False).alias("is_clean"), (split if split is not None else split_of("row_id")).alias("split"),
    )


def checked(train: DataFrame, classes: int) -> DataFrame:
    """``train``; raises where a weak label isn't a probability vector of the right length."""
    bad = train.where(
        f"weak is null or size(weak) <> {classes} or exists(weak, v -> v is null or isnan(v) or v < 0 or v > 1) or abs(aggregate(weak, 0D, (a, v) -> a + v) - 1) > 1e-6"
    )
    # all rows are looked at anyway, so all parts at once, not a few first
    if bad.count():
        raise ValueError("weak labels must be probability vectors with one entry a class")
    return train


def labelled_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id")


def doc_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = labelled_documents(spark, sf_dir).selectExpr("doc_id as row_id", "text", "quality as truth")
    return training_set(with_text_features(rows.dropna(subset=["truth"])), 2)


def doc_toxic(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = labelled_documents(spark, sf_dir).selectExpr("doc_id as row_id", "text", "toxic as truth")
    return training_set(with_text_features(rows.dropna(subset=["truth"]), extra=[F.least(insults(), F.lit(4.0))]), 2)


def document_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(row_id, the text statistics) of every document."""
    return load(spark, sf_dir, "documents").select(F.col("doc_id").alias("row_id"), *text_statistics())


def doc_crowd(spark: SparkSession, sf_dir: str, stats: DataFrame | None = None) -> DataFrame:
    """Unlabelled documents train on labelling functions' labels; labelled ones validate and test. ``stats``: kept statistics of all documents."""
    stats = document_statistics(spark, sf_dir) if stats is None else stats
    stats = stats.join(load(spark, sf_dir, "labels").selectExpr("doc_id as row_id", "quality as truth"), "row_id", "left")
    rows = stats.select("row_id", "truth", F.array(*standardised(), F.lit(1.0)).alias("x"), *labelling_votes())
    split = F.when(F.col("truth").isNull(), "train").when(F.col("row_id") % 2 == 0, "val").otherwise("test")
    return training_set(rows, 2, combined_votes(), split=split)


def crowd_votes(spark: SparkSession, sf_dir: str, stats: DataFrame | None = None) -> DataFrame:
    """(row_id, annotator, label): every document's votes of the labelling functions."""
    rows = (document_statistics(spark, sf_dir) if stats is None else stats).select("row_id", *labelling_votes())
    names = [c for c in rows.columns if c != "row_id"]
    return rows.select("row_id", F.expr(f"stack({len(names)}, {', '.join(f"'{c}', {c}" for c in names)}) as (annotator, label)"))


def vec_planted(spark: SparkSession, sf_dir: str, classes: int = 4) -> DataFrame:
    """Vectors whose class is the largest of fixed linear forms."""
    rows = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), vector_features().alias("x"))
    return training_set(rows.withColumn("truth", argmax(logits(F.col("x"), fixed_model(classes, 65, 5, 1.0)))), classes)


def vec_control(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A label that no linear model learns from the vectors."""
    rows = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), vector_features().alias("x"), F.col("label").alias("truth"))
    return training_set(rows, 10)


def conv_role(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "conversations").select(
        (F.col("conv_id") * 8 + F.col("turn")).alias("row_id"), "text", F.expr("case role when 'user' then 0 when 'assistant' then 1 when 'system' then 2 end").alias("truth")
    )
    return training_set(with_text_features(rows.dropna(subset=["truth"])), 3)


def line_planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines whose class says if a fixed form of four amounts is above a cut."""
    rows = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    k = F.expr("row_number() over (partition by l_orderkey, l_linenumber order by l_partkey, l_suppkey, l_extendedprice, l_shipdate) - 1")
    rows = rows.withColumn("row_id", (F.col("l_orderkey") * 8 + F.col("l_linenumber")) * 8 + k)
    x = F.expr("array((l_quantity - 25.5) / 14.4, (l_extendedprice - 50000) / 28000, (l_discount - 0.05) / 0.03, (l_tax - 0.04) / 0.026, 1D)")
    rows = rows.withColumn("x", x).withColumn("truth", F.expr("case when x[0] + 0.5 * x[1] - x[2] + 0.3 * x[3] > 0.2 then 1 else 0 end"))
    return training_set(rows, 2)


FIXTURES = {"doc_quality": (doc_quality, 2), "doc_toxic": (doc_toxic, 2), "doc_crowd": (doc_crowd, 2), "vec_planted2": (lambda s, d: vec_planted(s, d, 2), 2), "vec_planted4": (vec_planted, 4), "vec_control": (vec_control, 10), "conv_role": (conv_role, 3), "line_planted": (line_planted, 2)}


def as_arrays(rows: DataFrame, *more: str) -> tuple[np.ndarray, ...]:
    """(row_id, x, weak, truth, more columns) of a table that is known to be small; a null truth is -1."""
    t = rows.select("row_id", "x", "weak", F.coalesce("truth", F.lit(-1)).alias("truth"), *more).toArrow()
    n = t.num_rows
    matrix = lambda c: t[c].combine_chunks().flatten().to_numpy().reshape(n, -1) if n else np.empty((0, 1))
    return t["row_id"].to_numpy(), matrix("x"), matrix("weak"), t["truth"].to_numpy(), *(t[c].to_numpy() for c in more)
