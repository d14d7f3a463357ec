"""Annotation: simulated and given votes, majority, label strategies, edits and their cost."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidelabel.functions.rand import uniform, uniform_of

#: Annotators asked by each strategy.
VOTES = {"HUMAN3": 3, "SUGGEST": 0, "MIX": 2}


def simulate_votes(rows: DataFrame, annotators: int, error: float, classes: int, seed: str = "ann") -> DataFrame:
    """(row_id, annotator, label) of (row_id, truth): each annotator takes the next class on a share ``error`` of rows."""
    asked = rows.select("row_id", "truth", F.explode(F.sequence(F.lit(1), F.lit(annotators))).alias("a"))
    wrong = F.lit(False)
    for a in range(1, annotators + 1):
        wrong = wrong | ((F.col("a") == a) & (uniform(f"{seed}{a}", "row_id") < error))
    label = F.when(wrong, F.pmod(F.col("truth") + 1, F.lit(classes))).otherwise(F.col("truth")).cast("int")
    return asked.select("row_id", F.concat(F.lit("human"), F.col("a").cast("string")).alias("annotator"), label.alias("label"))


def majority_vote(votes: DataFrame, tie: str = "lowest", suggestions: DataFrame | None = None) -> DataFrame:
    """(row_id, label, votes): the label most voted for.

    Ties: the lowest label; or ``suggested``, the suggestion where it is among the tied
    labels; or ``keep``, no label for the row. Votes are counted before the shuffle.
    """
    counts = votes.groupBy("row_id", "label").agg(F.count("*").alias("votes"))
    if tie == "suggested" and suggestions is not None:
        counts = counts.join(suggestions.select("row_id", "best_class"), "row_id", "left").withColumn("own", F.coalesce((F.col("label") == F.col("best_class")).cast("int"), F.lit(0)))
    else:
        counts = counts.withColumn("own", F.lit(0))
    best = counts.groupBy("row_id").agg(F.max(F.struct("votes", "own", (-F.col("label")).alias("low"))).alias("m"), F.max("votes").alias("top"))
    out = best.select("row_id", (-F.col("m.low")).cast("int").alias("label"), F.col("m.votes").alias("votes"))
    if tie == "keep":
        tied = counts.join(best.select("row_id", "top"), "row_id").where("votes = top").groupBy("row_id").count().where("count = 1").select("row_id")
        out = out.join(tied, "row_id", "left_semi")
    return out


def clean_labels(picks: DataFrame, strategy: str, truth: DataFrame, classes: int, error: float = 0.05, votes: DataFrame | None = None) -> DataFrame:
    """(row_id, new_label) of picked rows (row_id, best_class).

    HUMAN3: three annotators; SUGGEST: the suggested class; MIX: two annotators and the
    suggestion. Votes come from ``votes`` where given, else from ``truth`` by simulation.
    """
    suggested = picks.select("row_id", F.lit("suggestion").alias("annotator"), F.col("best_class").alias("label"))
    if strategy == "SUGGEST":
        return suggested.select("row_id", F.col("label").alias("new_label"))
    asked = votes.join(picks.select("row_id"), "row_id", "left_semi") if votes is not None else simulate_votes(picks.select("row_id").join(truth.select("row_id", "truth"), "row_id"), VOTES[strategy], error, classes)
    if strategy == "MIX":
        return majority_vote(asked.unionByName(suggested), "suggested", picks).select("row_id", F.col("label").alias("new_label"))
    return majority_vote(asked).select("row_id", F.col("label").alias("new_label"))


def clean_few(picks: dict[int, int], strategy: str, truth: dict[int, int], classes: int, error: float = 0.05, votes: Iterable[tuple[int, int | None]] | None = None, seed: str = "ann") -> dict[int, int]:
    """``clean_labels`` for picks (row_id: best_class) that the driver holds; ``votes`` are theirs (row_id, label), where given."""
    if strategy == "SUGGEST":
        return dict(picks)
    if votes is None:
        known = [i for i in picks if i in truth]
        votes = [(i, (truth[i] + (uniform_of(f"{seed}{a}", i) < error)) % classes) for i in known for a in range(1, VOTES[strategy] + 1)]
    counts: dict[int, dict] = {}
    for i, label in [*votes, *(picks.items() if strategy == "MIX" else ())]:
        if label is not None:
            of = counts.setdefault(i, {})
            of[label] = of.get(label, 0) + 1
    own = lambda i, c: strategy == "MIX" and c == picks[i]
    return {i: max(of, key=lambda c: (of[c], own(i, c), -c)) for i, of in counts.items()}


def annotation_cost(strategy: str, n: int) -> int:
    return VOTES[strategy] * n


def apply_edits(train: DataFrame, edits: DataFrame, classes: int) -> DataFrame:
    """``train`` with edited rows at their new one-hot label and weight 1; edits are at most the budget, so they are broadcast."""
    joined = train.join(F.broadcast(edits.select("row_id", "new_label")), "row_id", "left")
    one_hot = F.transform(F.sequence(F.lit(0), F.lit(classes - 1)), lambda c: (c == F.col("new_label")).cast("double"))
    changed = F.col("new_label").isNotNull()
    return joined.select("row_id", "x", F.when(changed, one_hot).otherwise(F.col("weak")).alias("weak"), "truth", (F.col("is_clean") | changed).alias("is_clean"), "split")


def annotator_errors(votes: DataFrame, truth: DataFrame) -> DataFrame:
    return votes.join(truth.select("row_id", "truth"), "row_id").groupBy("annotator").agg(F.avg((F.col("label") != F.col("truth")).cast("double")).alias("err"), F.count("*").alias("n"))
