"""Nearest neighbours by a permutation index with pivot inverted files.

Every vector is represented by its PREFIX nearest pivots, nearest first; a pivot's
inverted file posts the vectors that have it in this list, with the pivot's rank. For
a query, the footrule distance to a vector is the sum, over the query's and the
vector's pivots, of the differences of ranks, where a pivot outside a list has rank
PREFIX: so it is a constant minus what the query's inverted files add up, and only
they are read. The best share of each block by footrule is ranked again by the exact
inner product in double precision.

Vectors are brought to one length first by one more coordinate, sqrt(M^2 - |x|^2) with
M the largest length, so that nearness to pivots orders by inner product. Pivots are a
bounded sample (PIVOTS vectors, those of smallest id hash); all vectors are indexed.

Blocks of stored vectors, each an index of its own, meet blocks of queries: both
are of bounded size, so a task needs one pair of blocks in memory.

Edge cases: null vectors, zero vectors, and those with null or non-finite components
take no part, nor do vectors of another dimension than most (ties: the larger); repeated
vectors are candidates each; equal scores go by id; fewer candidates than k give all;
an empty table gives no rows. A null id takes no part.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidelabel.llm.common import materialise

PIVOTS, PREFIX = 256, 32
#: Vectors ranked again: this share of a block, and at least this many times k.
RERANK_SHARE, RERANK_LEAST = 0.35, 10
BLOCK_VECTORS, BLOCK_QUERIES = 8_192, 1_024
RESULT = "query_id long, rank int, vec_id long, score double"


def usable(table: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(vec_id, x): vectors that can take part, as doubles."""
    x = F.transform(F.col(vec_col), lambda c: c.cast("double"))
    rows = table.select(F.col(id_col).cast("long").alias("vec_id"), x.alias("x")).where("vec_id is not null and x is not null and size(x) > 0")
    fine = rows.where("forall(x, c -> c is not null and not isnan(c) and abs(c) < double('Infinity')) and exists(x, c -> c <> 0)")
    usual = fine.groupBy(F.size("x").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).limit(1)
    return fine.join(F.broadcast(usual.select("d")), F.size("x") == F.col("d")).drop("d")


def matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy()
    return flat.reshape(len(column), -1)


def lifted(x: np.ndarray, longest: float) -> np.ndarray:
    """Vectors with the coordinate that brings them all to the longest one's length."""
    rest = np.sqrt(np.maximum(longest**2 - (x**2).sum(axis=1), 0))
    return np.column_stack([x, rest])


def prefixes(x: np.ndarray, pivots: np.ndarray, prefix: int) -> np.ndarray:
    """[n, prefix] nearest pivots of each row, nearest first (ties: smaller number)."""
    near = -(x @ pivots.T)
    part = np.argpartition(near, prefix - 1, axis=1)[:, :prefix] if prefix < near.shape[1] else np.tile(np.arange(prefix), (len(x), 1))
    part.sort(axis=1)
    return np.take_along_axis(part, np.argsort(np.take_along_axis(near, part, axis=1), axis=1, kind="stable"), axis=1)


class InvertedFiles:
    """Postings (vector, rank) of a block's vectors by pivot."""

    def __init__(self, lists: np.ndarray, n_pivots: int):
        self.n, self.prefix = lists.shape
        pivot = lists.ravel()
        order = np.argsort(pivot, kind="stable")
        self.vector = (order // self.prefix).astype(np.int32)
        self.rank = (order % self.prefix).astype(np.int16)
        self.start = np.searchsorted(pivot[order], np.arange(n_pivots + 1))

    def footrule(self, query: np.ndarray) -> np.ndarray:
        """Footrule distance of the query's pivot list to every vector, less a constant.

        A shared pivot of ranks r and s adds |r - s| instead of (L - r) + (L - s).
        """
        saved = np.zeros(self.n, dtype=np.int32)
        for r, p in enumerate(query.tolist()):
            a, b = self.start[p], self.start[p + 1]
            s = self.rank[a:b].astype(np.int32)
            saved[self.vector[a:b]] += 2 * self.prefix - r - s - np.abs(r - s)
        return -saved


def search_block(queries, q_ids, q_keys, vectors, ids, pivots, longest, k, prefix, share):
    """The block's best (query_id, query_key, vec_id, score) by permutation index and reranking.

    A query's own row is the one of its id with its vector; other rows of that id are candidates.
    """
    files = InvertedFiles(prefixes(lifted(vectors, longest), pivots, prefix), len(pivots))
    lists = prefixes(np.column_stack([queries, np.zeros(len(queries))]), pivots, prefix)
    take = min(len(ids), max(int(np.ceil(share * len(ids))), RERANK_LEAST * k, 1))
    found = []
    for q, q_id, q_key, pivots_of in zip(queries, q_ids.tolist(), q_keys.tolist(), lists):
        far = files.footrule(pivots_of)
        chosen = np.argpartition(far, take - 1)[:take] if take < len(far) else np.arange(len(far))
        chosen = chosen[(ids[chosen] != q_id) | (vectors[chosen] != q).any(axis=1)]
        score = np.einsum("ij,j->i", vectors[chosen], q)
        best = np.lexsort((ids[chosen], -score))[:k]
        found.append((np.full(len(best), q_id), np.full(len(best), q_key), ids[chosen][best], score[best]))
    return [np.concatenate(x) for x in zip(*found)] if found else [*(np.empty(0, np.int64) for _ in range(3)), np.empty(0)]


def nearest(table: DataFrame, queries: DataFrame, k: int, pivots: int = PIVOTS, prefix: int = PREFIX, share: float = RERANK_SHARE) -> DataFrame:
    """The k nearest stored vectors of each query (vec_id, x); a query's own row is no candidate.

    Equal queries of one id are asked once; queries of one id with other vectors each have ranks of their own.
    """
    queries = queries.dropDuplicates(["vec_id", "x"])
    spark = table.sparkSession
    stats = table.agg(F.count("*").alias("n"), F.max(F.aggregate("x", F.lit(0.0), lambda a, c: a + c * c)).alias("m2")).first()
    n_queries = queries.count()
    if not stats.n or not n_queries:
        return spark.createDataFrame([], RESULT)
    longest = float(np.sqrt(stats.m2))
    sample = table.orderBy(F.xxhash64("vec_id"), "vec_id").limit(pivots).select("x").collect()
    shared = spark.sparkContext.broadcast(lifted(np.array([r.x for r in sample]), longest))
    prefix = min(prefix, len(sample))
    blocks, query_blocks = -(-stats.n // BLOCK_VECTORS), -(-n_queries // BLOCK_QUERIES)

    def block_rows(rows: DataFrame, own: str, n_own: int, other: str, n_other: int, role: int) -> DataFrame:
        placed = rows.withColumn(own, F.pmod(F.xxhash64("vec_id"), F.lit(n_own)).cast("int"))
        return placed.select(F.explode(F.sequence(F.lit(0), F.lit(n_other - 1))).alias(other), own, F.lit(role).alias("role"), "vec_id", "x").select("vb", "qb", "role", "vec_id", "x", F.when(F.col("role") == 0, F.xxhash64("x")).otherwise(0).alias("query_key"))

    both = block_rows(queries, "qb", query_blocks, "vb", blocks, 0).union(block_rows(table, "vb", blocks, "qb", query_blocks, 1))

    def run(key, group):
        group = group.combine_chunks()
        role, ids = group["role"].to_numpy(), group["vec_id"].to_numpy()
        x = matrix(group["x"].combine_chunks())
        asks = role == 0
        keys = group["query_key"].to_numpy()
        got = search_block(x[asks], ids[asks], keys[asks], x[~asks], ids[~asks], shared.value, longest, k, prefix, share) if asks.any() and not asks.all() else ([], [], [], [])
        return pa.table({"query_id": pa.array(got[0], pa.int64()), "query_key": pa.array(got[1], pa.int64()), "vec_id": pa.array(got[2], pa.int64()), "score": pa.array(got[3], pa.float64())})

    partial = both.groupBy("vb", "qb").applyInArrow(run, "query_id long, query_key long, vec_id long, score double")
    order = F.expr("row_number() over (partition by query_id, query_key order by score desc, vec_id)")
    return partial.withColumn("rank", order.cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op6_permutation_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    table = materialise(usable(spark.read.parquet(f"{sf_dir}/embeddings.parquet")), "vectors")
    return nearest(table, table.where("vec_id % 20 = 0"), 20)
