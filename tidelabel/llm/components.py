"""Connected components of a link table, by union-find in tasks and star contraction between them."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidelabel.llm.common import materialise


#: Links (two longs each) that one task may finish; above it links are contracted between tasks first.
ONE_TASK_LINKS = 500_000


def _forest(batches):
    """One task's links as (member, root): union-find with path halving, smaller id as root."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for b in batches:
        for u, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            a, c = root(u), root(v)
            if a != c:
                parent[max(a, c)] = min(a, c)
    rows = [(x, root(x)) for x in parent]
    rows = [r for r in rows if r[0] != r[1]]
    for at in range(0, len(rows), 100_000):
        part = rows[at : at + 100_000]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in part], pa.int64()) for i in (0, 1)], names=["u", "v"])


def connected(links: DataFrame, name: str = "links") -> DataFrame:
    """(id, component) for every id in ``links`` (two long columns); component: smallest id reachable.

    Each task first replaces its links by a forest. Then stars are contracted: every
    id's larger neighbours are linked to its smallest one, then its smaller neighbours
    are, until all links point at a component's smallest id, or at most ONE_TASK_LINKS
    are left, which one task can finish. A hub's links are summed up before the shuffle
    and never gathered in one place. Each step is written to the shared folder. Self-links and repeated links change nothing; no link, no row.
    """
    a, b = links.columns[:2]
    pairs = links.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v")).where("u <> v")
    now = materialise(pairs.mapInArrow(_forest, "u long, v long"), name)
    while True:
        if now.count() <= ONE_TASK_LINKS:
            now = materialise(now.coalesce(1).mapInArrow(_forest, "u long, v long"), name)
            break
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).selectExpr("u", "least(u, m) as m")
        large = both.where("v > u").join(least, "u").selectExpr("v as u", "m as v").where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").selectExpr("explode(array(named_struct('u', u, 'v', m), named_struct('u', v, 'v', m))) as x").select("x.*").where("u <> v").distinct()
        new = materialise(small, name)
        # settled: each id has one link, to an id that has none upwards
        multiple = new.groupBy("u").count().where("count > 1").limit(1)
        chained = new.join(new.select(F.col("u").alias("v")), "v", "left_semi").limit(1)
        now = new
        if multiple.isEmpty() and chained.isEmpty():
            break
    return now.select(F.col("u").alias("id"), F.col("v").alias("component")).union(now.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct())
