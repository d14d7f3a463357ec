"""Features of texts and vectors, weak labels by labelling functions, and DuckDB twins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Means and deviations that standardise the eight text statistics.
CENTRE = (6.9, 0.77, 0.003, 0.16, 0.07, 6.0, 0.78, 0.97)
SPREAD = (1.3, 0.08, 0.01, 0.03, 0.08, 8.0, 0.15, 0.1)
STATISTICS = ("log_size", "letters", "digits", "spaces", "others", "line_breaks", "distinct_words", "distinct_lines")
#: Insulting words.
INSULTS = ("trash", "clown", "idiot", "scum", "worthless", "moron", "pathetic", "loser", "disgusting", "stupid")
#: Labelling functions (name, test on the statistics, vote where it holds, reliability).
LABELLING = (
    ("digits", "digits < 0.01", 1, 0.83),
    ("length", "log_size > 5", 1, 0.83),
    ("symbols", "others < 0.1", 1, 0.82),
    ("lines", "distinct_lines > 0.8", 1, 0.88),
)


def text_statistics(text: str = "text") -> list[Column]:
    t, n = F.col(text), F.greatest(F.length(text), F.lit(1))
    kept = lambda pattern: F.length(F.regexp_replace(t, pattern, "")) / n
    letters, digits, spaces = kept("[^A-Za-z]"), kept("[^0-9]"), kept("[^ \\n\\t]")
    words, lines = F.split(t, "[ \\n\\t]+"), F.split(t, "\\n")
    values = [
        F.log(F.lit(1.0) + F.length(text)), letters, digits, spaces, kept("[A-Za-z0-9 \\n\\t]"), (F.size(lines) - 1).cast("double"),
        F.size(F.array_distinct(words)) / F.size(words), F.size(F.array_distinct(lines)) / F.size(lines),
    ]
    return [v.alias(name) for v, name in zip(values, STATISTICS)]


def text_statistics_sql(text: str = "text") -> str:
    n = f"greatest(length({text}), 1)"
    kept = lambda pattern: f"length(regexp_replace({text}, '{pattern}', '', 'g')) / {n}"
    words, lines = f"string_split_regex({text}, '[ \\n\\t]+')", f"string_split({text}, chr(10))"
    values = [
        f"ln(1.0 + length({text}))", kept("[^A-Za-z]"), kept("[^0-9]"), kept("[^ \\n\\t]"), kept("[A-Za-z0-9 \\n\\t]"), f"(len({lines}) - 1)::double",
        f"len(list_distinct({words})) / len({words})", f"len(list_distinct({lines})) / len({lines})",
    ]
    return ", ".join(f"{v} as {name}" for v, name in zip(values, STATISTICS))


def insults(text: str = "text") -> Column:
    return F.expr(f"regexp_count(lower({text}), '{'|'.join(INSULTS)}')").cast("double")


def standardised() -> list[Column]:
    return [(F.col(s) - F.lit(m)) / F.lit(d) for s, m, d in zip(STATISTICS, CENTRE, SPREAD)]


def standardised_sql(only: tuple[str, ...] = STATISTICS) -> str:
    parts = [f"({s} - {m!r}) / {d!r}" for s, m, d in zip(STATISTICS, CENTRE, SPREAD) if s in only]
    return "[" + ", ".join([*parts, "1.0"]) + "]"


def with_text_features(rows: DataFrame, text: str = "text", extra: list[Column] | None = None) -> DataFrame:
    """``rows`` with x: the standardised statistics, ``extra`` features and 1.0; the text goes."""
    stats = rows.select("*", *text_statistics(text), *[c.alias(f"extra_{i}") for i, c in enumerate(extra or [])])
    x = F.array(*standardised(), *(F.col(f"extra_{i}") for i in range(len(extra or []))), F.lit(1.0))
    return stats.withColumn("x", x).drop(text, *STATISTICS, *(f"extra_{i}" for i in range(len(extra or []))))


def vector_features(column: str = "embedding", scale: float = 8.0) -> Column:
    return F.concat(F.transform(column, lambda e: e.cast("double") * F.lit(scale)), F.array(F.lit(1.0)))


def vector_features_sql(column: str = "embedding", scale: float = 8.0) -> str:
    return f"list_append(list_transform({column}, lambda e: e::double * {scale!r}), 1.0)"


def labelling_votes(names=tuple(x[0] for x in LABELLING)) -> list[Column]:
    """One column a labelling function: its vote, or null where it abstains."""
    return [F.expr(f"case when {test} then {vote} else {1 - vote} end").alias(f"lf_{name}") for name, test, vote, _ in LABELLING if name in names]


def combined_votes(names=tuple(x[0] for x in LABELLING)) -> Column:
    """[p0, p1] from the functions' votes, each as reliable as LABELLING says, within [0.05, 0.95]."""
    odds = F.lit(0.0)
    for name, _, _, r in LABELLING:
        if name in names:
            import math

            odds = odds + F.coalesce(F.when(F.col(f"lf_{name}") == 1, math.log(r / (1 - r))).when(F.col(f"lf_{name}") == 0, -math.log(r / (1 - r))), F.lit(0.0))
    p = F.least(F.greatest(F.lit(1.0) / (F.lit(1.0) + F.exp(-odds)), F.lit(0.05)), F.lit(0.95))
    return F.array(F.lit(1.0) - p, p)
