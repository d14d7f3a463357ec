"""Nearest trusted rows of chosen rows: which verified labels lie around a suggestion.

An exact search: blocks of the asked rows, of a bounded size, go to all tasks, which
read the trusted rows once a block and keep the k best for each asked row.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Asked rows that go to all tasks at once, and those compared with a batch at once.
BLOCK_ROWS, AT_ONCE = 20_000, 256
FOUND = "vec_id long, nn_id long, c double"


def _best(c: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    order = np.lexsort((ids, -c), axis=1)[:, :k]
    return np.take_along_axis(c, order, axis=1), np.take_along_axis(ids, order, axis=1)


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.sqrt((x**2).sum(axis=1, keepdims=True)), 1e-300)


def nearest_trusted(rows: DataFrame, trusted: DataFrame, k: int) -> DataFrame:
    """(vec_id, nn_id, rank): the k trusted rows of largest cosine, ties by id; both sides (vec_id, x); a row isn't its own neighbour."""
    spark = rows.sparkSession
    blocks = max(1, -(-rows.count() // BLOCK_ROWS))
    found = None
    for i in range(blocks):
        t = rows.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == i).select(F.col("vec_id").cast("long"), "x").toArrow()
        if not t.num_rows:
            continue
        asked = spark.sparkContext.broadcast((t["vec_id"].to_numpy(), _unit(t["x"].combine_chunks().flatten().to_numpy().reshape(t.num_rows, -1))))

        def run(batches, asked=asked):
            ids, q = asked.value
            top = (np.full((len(ids), 0), 0.0), np.full((len(ids), 0), 0, dtype=np.int64))
            for b in batches:
                if not b.num_rows:
                    continue
                own, x = b.column(0).to_numpy(), _unit(b.column(1).flatten().to_numpy().reshape(b.num_rows, -1))
                parts = []
                for at in range(0, len(ids), AT_ONCE):
                    s = slice(at, at + AT_ONCE)
                    c = np.round(q[s] @ x.T, 9)
                    c[ids[s, None] == own[None, :]] = -np.inf
                    parts.append(_best(np.hstack([top[0][s], c]), np.hstack([top[1][s], np.broadcast_to(own, c.shape)]), k))
                top = tuple(np.concatenate([p[j] for p in parts]) for j in (0, 1))
            if top[0].shape[1]:
                keep = np.isfinite(top[0]).ravel()
                yield pa.RecordBatch.from_arrays([pa.array(v.ravel()[keep]) for v in (np.repeat(ids, top[0].shape[1]), top[1], top[0])], names=["vec_id", "nn_id", "c"])

        part = trusted.select(F.col("vec_id").cast("long"), "x").mapInArrow(run, FOUND)
        found = part if found is None else found.union(part)
    if found is None:
        found = spark.createDataFrame([], FOUND)
    ranked = found.withColumn("rank", F.expr("cast(row_number() over (partition by vec_id order by c desc, nn_id) as int)"))
    return ranked.where(F.col("rank") <= k).select("vec_id", "nn_id", "rank")
