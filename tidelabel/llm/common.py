"""Shared helpers of the training-data operators."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Rows handled at once in a Python worker.
SLICE_ROWS = 256
SLICE_BYTES = 24_000_000


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def shared_root(spark: SparkSession) -> str:
    """The folder that the driver and all executors see.

    The session's ``spark.checkpoint.dir`` wins; only where none is set (tests,
    single machine) is a temporary folder made and set as checkpoint folder.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = spark.sparkContext.getCheckpointDir()
    if not root:
        root = tempfile.mkdtemp(prefix="tidelabel-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read back: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def fresh(df: DataFrame, name: str) -> str:
    """``name``, or, where ``df`` has a column of that name, one that it doesn't have."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def slices(batches: Iterator[pa.RecordBatch], rows: int = SLICE_ROWS, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Arrow batches cut into small ones, so that Python objects of few rows live at once.

    A slice has at most ``rows`` rows and, but for larger rows, about ``most`` bytes.
    """
    for batch in batches:
        step = max(1, min(rows, int(most * batch.num_rows / max(batch.nbytes, 1))))
        for at in range(0, batch.num_rows, step):
            yield batch.slice(at, step)
    give_back()


def give_back() -> None:
    """Hand freed memory to the system: Python workers are kept, and a later stage's come on top of what they hold."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def kept_rows(docs: DataFrame, decider: Callable[[], Callable[[list], list[bool]]], rows: int = 1024, most: int = SLICE_BYTES) -> DataFrame:
    """The rows of ``docs`` whose texts pass, all columns as they are, in one pass without a shuffle.

    ``decider`` is called once in each task and gives the function from texts to verdicts.
    """
    at = docs.columns.index("text")

    def run(batches):
        decide = decider()
        for b in slices(batches, rows, most):
            yield b.filter(pa.array(decide(b.column(at).to_pylist()), pa.bool_()))
        del decide
        give_back()

    return docs.mapInArrow(run, docs.schema)
