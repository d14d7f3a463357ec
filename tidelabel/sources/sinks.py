"""Sinks: file formats, and the append-only store of rounds."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidelabel.schema import EDITS


def shared_folder(spark: SparkSession) -> str:
    """The folder that all machines see: ``spark.checkpoint.dir``; on one machine without it, a temporary one."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        root = tempfile.mkdtemp(prefix="tidelabel-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def round_trip(rows: DataFrame, fmt: str) -> DataFrame:
    """``rows`` written in a file format and read back with their schema."""
    path = f"{shared_folder(rows.sparkSession)}/{fmt}-{uuid.uuid4().hex}"
    rows.write.format(fmt).option("header", True).save(path)
    return rows.sparkSession.read.format(fmt).schema(rows.schema).option("header", True).load(path)


def written(rows: DataFrame, name: str, *parts: str) -> DataFrame:
    """``rows`` written to the shared folder, in folders by ``parts``, and read back: lost executors don't compute them again."""
    path = f"{shared_folder(rows.sparkSession)}/{name}-{uuid.uuid4().hex}"
    rows.write.parquet(path, partitionBy=list(parts) or None)
    return rows.sparkSession.read.schema(rows.schema).parquet(path)


def bucketed(rows: DataFrame, name: str, keys: list[str], buckets: int) -> DataFrame:
    """``rows`` as a table bucketed and sorted by ``keys``; joins of such tables on the keys don't shuffle them."""
    spark, table = rows.sparkSession, f"{name}_{uuid.uuid4().hex}"
    path = f"{shared_folder(spark)}/{table}"
    rows.write.bucketBy(buckets, *keys).sortBy(*keys).option("path", path).saveAsTable(table)
    return spark.table(table)


class RoundStore:
    """Edits of rounds, appended and never changed: a folder per round, read with partition pruning.

    A round's folder is written once; writing it again replaces that round alone, so a
    driver that fails in the middle of a round repeats it.
    """

    def __init__(self, spark: SparkSession, root: str | None = None):
        self.spark, self.root = spark, root or f"{shared_folder(spark)}/rounds-{uuid.uuid4().hex}"

    def append_edits(self, round_: int, edits: DataFrame) -> None:
        edits.select("row_id", "new_label", "source").write.mode("overwrite").parquet(f"{self.root}/edits/round={round_}")

    def edits(self, up_to: int | None = None) -> DataFrame:
        rows = self.spark.read.schema(EDITS).parquet(f"{self.root}/edits")
        return rows if up_to is None else rows.where(F.col("round") <= up_to)
