"""A fixed-size bit table of 64-bit hashes that goes to all executors, in DataFrame operations only.

A join of many rows with few keys shuffles all the rows. Where the keys are set as
bits of a table of BITS bits, rows whose bit isn't set are left out before the
shuffle. The table's size doesn't depend on the data: with few keys nearly all other
rows go, with very many keys more rows pass, and the join that follows stays exact.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidelabel.llm.common import fresh

#: 64-bit words of a table, and words in one of its rows: 8 MB in 8,192 rows.
WORDS, ROW_WORDS = 1 << 20, 128
BITS = 64 * WORDS


def word_of(key: str) -> str:
    return f"({key} & {WORDS - 1}L)"


def bit_of(key: str) -> str:
    return f"cast(shiftright({key}, 40) & 63L as int)"


def hash_bits(keys: DataFrame, key: str) -> DataFrame:
    """(bits_row, bits): the table that has the bits of the long column ``key`` set; null keys set none."""
    words = keys.where(f"{key} is not null").groupBy(F.expr(word_of(key)).alias("word")).agg(F.expr(f"bit_or(shiftleft(1L, {bit_of(key)}))").alias("mask"))
    rows = words.groupBy(F.expr(f"cast(word div {ROW_WORDS} as int)").alias("bits_row"))
    found = rows.agg(F.expr(f"map_from_entries(collect_list(struct(cast(word % {ROW_WORDS} as int) as at, mask)))").alias("m"))
    return found.select("bits_row", F.expr(f"transform(sequence(0, {ROW_WORDS - 1}), i -> coalesce(try_element_at(m, i), 0L))").alias("bits"))


def _met(rows: DataFrame, key: str, table: DataFrame, how: str):
    """``rows`` beside their row of the table, and the condition that their bit is set."""
    at, bits = fresh(rows, "bits_row"), fresh(rows, "bits")
    row = F.expr(f"cast({word_of(key)} div {ROW_WORDS} as int)")
    both = rows.join(F.broadcast(table.toDF(at, bits)), row == F.col(at), how)
    return both, F.expr(f"(shiftright({bits}[cast({word_of(key)} % {ROW_WORDS} as int)], {bit_of(key)}) & 1L) = 1L")


def perhaps_in(rows: DataFrame, key: str, table: DataFrame) -> DataFrame:
    """The rows whose ``key`` has its bit set: all that are among the keys, and few others."""
    both, bit = _met(rows, key, table, "inner")
    return both.where(bit).select(*rows.columns)


def surely_not_in(rows: DataFrame, key: str, table: DataFrame) -> DataFrame:
    """The other rows; a null ``key`` is among them."""
    both, bit = _met(rows, key, table, "left")
    return both.where(~F.coalesce(bit, F.lit(False))).select(*rows.columns)
