"""Ordinal cumulative-link regression on graded ratings over hashed text features.

P(grade <= j | text) = sigmoid(t_j - w.x) with one weight vector w for all grades and
ordered thresholds t_1 < t_2 < ... A text's features are its hashed words and, hashed
into the same space, levels of its shape (shares of letters, symbols, distinct words
and lines, length); words are weighted by the root of their share. The expected grade
and the tail probabilities P(grade >= j) come out for selection.

Grades come from the ratings: here 0 for low quality, 1 for good quality marked toxic,
2 for good quality. The fit takes at most FIT_ROWS rated rows, those of smallest id hash.

Edge cases: null and empty texts have the features of an empty text and get its
prediction; long texts are read whole; repeated rows are rated and predicted each;
with no rated rows every grade is equally likely; a grade that no rated row has keeps
its place in the order with a probability near 0.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidelabel.llm.common import documents, slices

SLOTS = 1 << 16
FIT_ROWS = 8_000
GRADES = 3
STEPS, RATE, L2 = 300, 0.05, 1e-4
CACHE = 400_000
LETTERS = re.compile(r"[^\W\d_]")
SYMBOLS = re.compile(r"[#*$%&|<>!]")


def slot(name: str) -> int:
    return xxhash.xxh3_64_intdigest(name.encode()) % SLOTS


class Features:
    """Hashed features of texts: (slots, values), slots distinct."""

    def __init__(self):
        self.known: dict[str, int] = {}

    def of(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        text = text or ""
        words = text.lower().split()
        known = self.known
        if len(known) > CACHE:
            known.clear()
        for w in set(words).difference(known):
            known[w] = slot(w)
        at = np.array([known[w] for w in words], dtype=np.int64)
        at, n = np.unique(at, return_counts=True)
        value = np.sqrt(n / max(len(words), 1))
        lines = text.split("\n")
        size = max(len(text), 1)
        shape = {
            "letters": len(LETTERS.findall(text)) / size, "symbols": min(1.0, 5 * len(SYMBOLS.findall(text)) / size), "distinct": len(at) / max(len(words), 1),
            "lines": len(set(lines)) / len(lines), "upper": sum(map(str.isupper, text.split())) / max(len(words), 1), "size": min(1.0, np.log1p(len(words)) / 10),
        }
        own = {f"shape {k} {int(10 * v)}": 1.0 for k, v in shape.items()} | {f"shape {k}": 2 * v for k, v in shape.items()}
        at = np.concatenate([at, [slot(k) for k in own]])
        value = np.concatenate([value, list(own.values())])
        at, back = np.unique(at, return_inverse=True)
        return at, np.bincount(back, weights=value, minlength=len(at))


@dataclass
class Ordinal:
    weights: np.ndarray
    thresholds: np.ndarray  # ascending, one fewer than grades

    def tails(self, at: np.ndarray, value: np.ndarray) -> np.ndarray:
        """P(grade >= j) for j = 1, 2, ..."""
        return 1 / (1 + np.exp(np.clip(self.thresholds - value @ self.weights[at], -30, 30)))


def fit(examples: list[tuple[np.ndarray, np.ndarray]], grades: np.ndarray, n_grades: int = GRADES) -> Ordinal:
    """Adam on the cumulative-link likelihood; thresholds as a first one and positive gaps."""
    if not len(grades):
        return Ordinal(np.zeros(SLOTS), np.array([np.log(j / (n_grades - j)) for j in range(1, n_grades)]))
    row = np.repeat(np.arange(len(examples)), [len(a) for a, _ in examples])
    at, value = (np.concatenate([e[i] for e in examples]) for i in (0, 1))
    seen, col = np.unique(at, return_inverse=True)
    share = np.array([(grades < j).mean() for j in range(1, n_grades)])
    first = np.log(np.clip(share, 1e-3, 1 - 1e-3) / (1 - np.clip(share, 1e-3, 1 - 1e-3)))
    theta = np.concatenate([np.zeros(len(seen)), [first[0]], np.log(np.maximum(np.diff(first), 1e-2))])
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    k, n = len(seen), len(examples)
    for step in range(1, STEPS + 1):
        gaps = np.exp(theta[k + 1 :])
        cuts = np.concatenate([[-np.inf], theta[k] + np.concatenate([[0], np.cumsum(gaps)]), [np.inf]])
        z = np.bincount(row, weights=value * theta[col], minlength=n)
        low, high = (1 / (1 + np.exp(-np.clip(cuts[grades + i] - z, -30, 30))) for i in (0, 1))
        p = np.maximum(high - low, 1e-9)
        d_high, d_low = high * (1 - high) / p, low * (1 - low) / p
        d_high[grades == n_grades - 1] = 0
        d_low[grades == 0] = 0
        g = np.empty_like(theta)
        g[:k] = np.bincount(col, weights=value * (d_high - d_low)[row], minlength=k) / n + L2 * theta[:k]
        of_cut = np.array([(d_low[grades == j].sum() - d_high[grades == j - 1].sum()) / n for j in range(1, n_grades)])
        g[k] = of_cut.sum()
        g[k + 1 :] = gaps * np.cumsum(of_cut[::-1])[::-1][1:]
        m = 0.9 * m + 0.1 * g
        v = 0.999 * v + 0.001 * g * g
        theta = theta - RATE * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    weights = np.zeros(SLOTS)
    weights[seen] = theta[:k]
    return Ordinal(weights, theta[k] + np.concatenate([[0], np.cumsum(np.exp(theta[k + 1 :]))]))


def train(rated: DataFrame, most: int = FIT_ROWS) -> Ordinal:
    """Fit on (doc_id, text, grade) rows; the sample is taken by ids before texts are read."""
    ids = rated.select("doc_id", "grade").where(f"grade between 0 and {GRADES - 1}")
    chosen = F.broadcast(ids.orderBy(F.xxhash64("doc_id"), "doc_id", "grade").limit(most).select("doc_id").distinct())

    def run(batches):
        features = Features()
        for b in slices(batches):
            found = [features.of(t) for t in b.column(1).to_pylist()]
            features_of = [pa.array([f[0] for f in found], pa.list_(pa.int64())), pa.array([f[1] for f in found], pa.list_(pa.float64()))]
            yield pa.RecordBatch.from_arrays([b.column(0), *features_of, b.column(2), b.column(3)], names=["grade", "at", "value", "place", "copy"])

    rows = rated.where(f"grade between 0 and {GRADES - 1}").join(chosen, "doc_id", "left_semi").select(F.col("grade").cast("int"), "text", F.xxhash64("doc_id").alias("place"), F.xxhash64("text").alias("copy"))
    # one order whatever the tasks, so that the fit is the same each time
    t = rows.mapInArrow(run, "grade int, at array<long>, value array<double>, place long, copy long").orderBy("place", "copy", "grade").limit(most).toArrow()
    examples = list(zip(map(np.asarray, t["at"].to_pylist()), map(np.asarray, t["value"].to_pylist())))
    return fit(examples, t["grade"].to_numpy())


def grade(docs: DataFrame, model: Ordinal) -> DataFrame:
    """(doc_id, expected_grade, p_ge_1, p_ge_2, grade, keep): keep where grade 1 or more is likelier than not."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        features = Features()
        for b in slices(batches):
            tails = np.array([shared.value.tails(*features.of(t)) for t in b.column(1).to_pylist()]).reshape(-1, GRADES - 1)
            p = -np.diff(np.column_stack([np.ones(len(tails)), tails, np.zeros(len(tails))]), axis=1)
            out = [b.column(0), pa.array(tails.sum(axis=1)), pa.array(tails[:, 0]), pa.array(tails[:, 1]), pa.array(p.argmax(axis=1).astype("int32")), pa.array(tails[:, 0] >= 0.5)]
            yield pa.RecordBatch.from_arrays(out, names=["doc_id", "expected_grade", "p_ge_1", "p_ge_2", "grade", "kept"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, expected_grade double, p_ge_1 double, p_ge_2 double, grade int, kept boolean")


def rated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Graded training rows: those whose id's crc32 is not 1 modulo 3."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 != 1)
    grades = labels.where("quality is not null").select("doc_id", F.expr("case when quality = 0 then 0 when toxic = 1 then 1 else 2 end").alias("grade"))
    return docs.select("doc_id", "text").join(grades, "doc_id")


def op10_ordinal(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return grade(docs, train(rated(spark, docs, sf_dir)))
