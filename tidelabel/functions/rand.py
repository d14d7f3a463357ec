"""Pseudo-randomness that any engine can repeat: md5 of a seed and an id."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

RANGE = float(1 << 32)


def uniform(seed: str, row_id: str | Column) -> Column:
    """A number in [0, 1) from the first 8 hex digits of md5(seed|id)."""
    row_id = F.col(row_id) if isinstance(row_id, str) else row_id
    digest = F.md5(F.concat(F.lit(f"{seed}|"), row_id.cast("string")).cast("binary"))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") / F.lit(RANGE)


def uniform_of(seed: str, row_id: int) -> float:
    """The same for one id, without Spark."""
    return int(hashlib.md5(f"{seed}|{row_id}".encode()).hexdigest()[:8], 16) / RANGE


def uniform_sql(seed: str, row_id: str) -> str:
    """The same in DuckDB."""
    return f"(('0x' || md5('{seed}|' || {row_id}::varchar)[1:8])::bigint / {RANGE})"


def split_of(row_id: str) -> Column:
    bucket = F.pmod(F.col(row_id) * 7919 + 13, F.lit(10))
    return F.when(bucket == 0, "val").when(bucket == 1, "test").otherwise("train")


def split_sql(row_id: str) -> str:
    return f"(case ({row_id} * 7919 + 13) % 10 when 0 then 'val' when 1 then 'test' else 'train' end)"


def random_weak(seed: str, row_id: str, classes: int) -> Column:
    """C uniforms, normalised: the weak label of a row about which nothing is known."""
    u = F.array(*(uniform(f"{seed}.{c}", row_id) + F.lit(1e-6) for c in range(classes)))
    # bound once: named twice, the digests would be made again for every class
    return F.transform(F.array(u), lambda w: F.transform(w, lambda v: v / F.aggregate(w, F.lit(0.0), lambda a, b: a + b)))[0]


def random_weak_sql(seed: str, row_id: str, classes: int) -> str:
    u = [f"({uniform_sql(f'{seed}.{c}', row_id)} + 1e-6)" for c in range(classes)]
    return "[" + ", ".join(f"{v} / ({' + '.join(u)})" for v in u) + "]"
