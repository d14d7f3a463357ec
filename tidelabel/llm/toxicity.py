"""Toxicity by class-conditional Kneser-Ney models.

Two models, of toxic and of ordinary texts, are smoothed in levels: pairs of words
back off to words, words to their beginnings, from the longer to the shorter, and
these to what the classes share, the number of classes that a unit occurs in. A
unit's count at a lower level is its number of contexts, here of distinct texts, so
that one repetitive text weighs as much as any other. The discounted mass is shared
by the classes: what the discount takes off wholly counts the same for both. Where
the counts of a level don't differ between the classes by SURE standard errors (by
the likelihood-ratio statistic), the next lower level is asked, so that rare
expressions say no more than their shared parts do. A text's evidence is its log-likelihood ratio per word,
over the text and over its strongest stretch of STRETCH words, so that a few abusive
words in a long text aren't averaged away. A logistic fit on labelled rows that the
counts did not see turns the evidence into a score.

Words and beginnings are counted under their own 64-bit hashes, pairs under those of
both words; counts are summed and turned into ratios by Spark. The model that goes to
the executors holds every unit and pair whose ratio isn't zero, sorted by key: it has
no fixed size and grows with what the labels tell apart.

Edge cases: null, empty and wordless texts have zero evidence and get the score
that the fit gives for it (below 0.5 where toxic rows are a minority); texts of any
length are scored whole; equal training texts of one label count once, repeated rows
score alike; without any labelled row, or with one class only, the score is
the share of toxic labels (0 without labels).
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidelabel.llm.common import documents, kept_rows, materialise, slices

#: A pair's key is the first word's times MIX plus the second's, modulo 2**64.
MIX = np.uint64(0x9E3779B97F4A7C15)
#: Lengths of word beginnings, from the longest.
BEGINNINGS = (7, 6, 5, 4, 3)
STRETCH = 24
#: Counts up to the discount say nothing about a class.
DISCOUNT = 2.0
SURE = 4.0
#: Bounds of one word's evidence.
LEAST, MOST = -2.0, 6.0
#: Of the training texts, one in CALIBRATE_EACH is kept for the logistic fit, and about CALIBRATE_ROWS at most: all others are counted.
CALIBRATE_EACH, CALIBRATE_ROWS = 4, 20_000
THRESHOLD = 0.7
#: Training rows (about 30 bytes each) that may be broadcast.
BROADCAST_LABELS = 2_000_000
WORD = re.compile(r"[^\W_]+")
CACHE = 400_000


def unit_key(unit: str) -> int:
    """64-bit key, never 0."""
    return xxhash.xxh3_64_intdigest(unit) or 1


def units(word: str) -> list[int]:
    """Keys of a word and of its beginnings, longest first; 0 where it is too short for one."""
    long = len(word)
    return [unit_key(word)] + [unit_key(word[:n] + "*") if n < long else 0 for n in BEGINNINGS]


def pair_keys(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    return first * MIX + second


def words_of(text: str | None) -> list[str]:
    return WORD.findall(text.lower()) if text else []


@dataclass
class Model:
    """Log ratios of toxic against ordinary texts."""

    units: np.ndarray  # sorted unit keys
    unit: np.ndarray  # of these
    pairs: np.ndarray  # sorted pair keys
    pair: np.ndarray  # of these
    weights: np.ndarray  # of mean, stretch, and the intercept

    def of_words(self, keys: np.ndarray) -> np.ndarray:
        """What the longest informative unit of each word says; a row of ``keys`` holds the ``units`` of a word."""
        if not len(self.units):
            return np.zeros(len(keys))
        at = np.minimum(np.searchsorted(self.units, keys), len(self.units) - 1)
        hit = (self.units[at] == keys) & (keys != 0)
        longest = at[np.arange(len(keys)), hit.argmax(axis=1)]
        return np.where(hit.any(axis=1), self.unit[longest], 0.0)

    def score(self, evidence: list[tuple[float, float]]) -> np.ndarray:
        x = features(np.array(evidence, dtype=np.float64).reshape(-1, 2))
        z = np.column_stack([x, np.ones(len(x))]) @ self.weights
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


class Vocabulary:
    """Places of words seen, and the keys of their units in one array; forgotten past CACHE words."""

    def __init__(self):
        self.place: dict[str, int] = {}
        self.keys = np.zeros((0, 1 + len(BEGINNINGS)), dtype=np.uint64)

    def places(self, words: list[str]) -> np.ndarray:
        """The place of each word; valid until the next call."""
        if len(self.place) > CACHE:
            self.place.clear()
        new = list(set(words).difference(self.place))
        if new:
            start = len(self.place)
            self.place.update(zip(new, range(start, start + len(new))))
            self.learn(start, np.array([units(w) for w in new], dtype=np.uint64))
        return np.fromiter(map(self.place.__getitem__, words), dtype=np.int64, count=len(words))

    def learn(self, start: int, keys: np.ndarray) -> None:
        self.keys = held(self.keys, start, keys)


def held(array: np.ndarray, start: int, rows: np.ndarray) -> np.ndarray:
    """``array`` with ``rows`` from ``start`` on, in a larger one if it is full."""
    if start + len(rows) > len(array):
        larger = np.zeros((2 * (start + len(rows)), *array.shape[1:]), dtype=array.dtype)
        larger[:start] = array[:start]
        array = larger
    array[start : start + len(rows)] = rows
    return array


class Reader(Vocabulary):
    """Evidence of texts, one after another, by a model; words are kept with what they say."""

    def __init__(self, model: Model):
        super().__init__()
        self.model, self.says = model, np.zeros(0)

    def learn(self, start: int, keys: np.ndarray) -> None:
        super().learn(start, keys)
        self.says = held(self.says, start, self.model.of_words(keys))

    def evidence(self, text: str | None) -> tuple[float, float]:
        """(ratio per word over the text, ratio per word over the strongest stretch)."""
        words, model = words_of(text), self.model
        if not words:
            return 0.0, 0.0
        place = self.places(words)
        ratio = self.says[place]
        if len(model.pairs) and len(words) > 1:
            word = self.keys[place, 0]
            key = pair_keys(word[:-1], word[1:])
            at = np.minimum(np.searchsorted(model.pairs, key), len(model.pairs) - 1)
            hit = np.flatnonzero(model.pairs[at] == key)
            ratio[hit + 1] = model.pair[at[hit]]
        total = np.concatenate([[0.0], np.cumsum(np.clip(ratio, LEAST, MOST))])
        width = min(STRETCH, len(ratio))
        return total[-1] / len(ratio), (total[width:] - total[:-width]).max() / STRETCH


def counts(rows: DataFrame) -> DataFrame:
    """(first, second, toxic, other): numbers of texts of each class that hold a pair of words or, at second = 0, a unit."""

    def run(batches):
        known = Vocabulary()
        for b in slices(batches, 2048):
            of: dict[int, list] = {0: [], 1: []}
            for label, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                words = words_of(text)
                if not words:
                    continue
                place = known.places(words)
                word = known.keys[place, 0]
                at = np.unique(pair_keys(word[:-1], word[1:]), return_index=True)[1]
                unit = np.unique(known.keys[np.unique(place)])
                unit = unit[unit != 0]
                of[label].append((np.concatenate([unit, word[at]]), np.concatenate([np.zeros_like(unit), word[at + 1]])))
            for label, parts in of.items():
                if parts:
                    first, second = (np.concatenate([p[i] for p in parts]) for i in (0, 1))
                    at, n = np.unique(pair_keys(first, second), return_index=True, return_counts=True)[1:]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([label] * len(at), pa.int32()), pa.array(first[at].view(np.int64)), pa.array(second[at].view(np.int64)), pa.array(n.astype(np.int64))], names=["toxic", "first", "second", "n"]
                    )

    found = rows.select("toxic", "text").mapInArrow(run, "toxic int, first long, second long, n long")
    return found.groupBy("first", "second").agg(F.sum(F.when(F.col("toxic") == 1, F.col("n")).otherwise(0)).alias("toxic"), F.sum(F.when(F.col("toxic") == 0, F.col("n")).otherwise(0)).alias("other"))


def logistic(features: np.ndarray, labels: np.ndarray, l2: float = 1e-2, steps: int = 50) -> np.ndarray:
    """Weights of a small logistic regression by Newton's method; the last one is the intercept."""
    x = np.column_stack([features, np.ones(len(features))])
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - labels) + l2 * w
        h = (x * (p * (1 - p))[:, None]).T @ x + l2 * np.eye(len(w))
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w


def features(evidence: np.ndarray) -> np.ndarray:
    return np.clip(evidence * [20.0, 4.0], -10, 10)


def sure(toxic: str, other: str, all_toxic: str, all_other: str) -> str:
    """SQL condition: counts out of totals differ surely between the classes."""
    part = lambda n, total: f"case when {n} > 0 then {n} * ln({n} * ({all_toxic} + {all_other}) / ({total} * ({toxic} + {other}))) else 0D end"
    return f"2 * ({part(toxic, all_toxic)} + {part(other, all_other)}) >= {SURE**2}"


def ratios(rows: DataFrame, columns: int) -> list[np.ndarray]:
    """Key columns and the ratio, of the rows where it isn't zero."""
    t = rows.where("ratio <> 0").toArrow()
    return [t.column(i).to_numpy().view(np.uint64) for i in range(columns)] + [t.column(columns).to_numpy().astype(np.float32)]


def kneser_ney(found: DataFrame) -> dict:
    """The model's arrays from ``counts``. What the executors find to differ surely comes to the driver."""
    unit = found.where("second = 0").selectExpr("first as key", "cast(toxic as double) as toxic", "cast(other as double) as other")
    classes = "(int(toxic > 0) + int(other > 0))"
    t = unit.selectExpr("sum(toxic) as toxic", "sum(other) as other", f"sum(least(toxic, {DISCOUNT}D) + least(other, {DISCOUNT}D)) as off", f"sum({classes}) as classes").first()
    if not t.toxic or not t.other:  # one class only
        return {"units": np.zeros(0, np.uint64), "unit": np.zeros(0, np.float32), "pairs": np.zeros(0, np.uint64), "pair": np.zeros(0, np.float32)}
    back = min(max(t.off / (t.toxic + t.other), 1e-6), 1.0)
    share = lambda c: f"greatest({c} - {DISCOUNT}D, 0D) / {getattr(t, c)!r}D + {back!r}D * {classes} / {t.classes}D"
    unit = unit.selectExpr("key", "toxic", "other", f"{share('toxic')} as p_toxic", f"{share('other')} as p_other")
    keys, ratio = ratios(unit.where(sure("toxic", "other", f"{t.toxic!r}D", f"{t.other!r}D")).selectExpr("key", "ln(p_toxic / p_other) as ratio"), 1)
    order = np.argsort(keys)
    # pairs behind the word that they begin with; a pair can't be in more texts than that word, whose number is what is shared out
    pair = found.where(f"second <> 0 and greatest(toxic, other) > {DISCOUNT}")
    before = unit.selectExpr("key as first", "greatest(toxic, 1D) as before_toxic", "greatest(other, 1D) as before_other")
    pair = pair.join(before, "first").where(sure("toxic", "other", "before_toxic", "before_other"))
    pair = pair.join(unit.selectExpr("key as second", "p_toxic", "p_other"), "second")
    left = f"greatest(least({DISCOUNT}D / (before_toxic + before_other), 1D), 1e-6D)"
    p = lambda c: f"(least(greatest({c} - {DISCOUNT}D, 0D) / before_{c}, 1D) + {left} * p_{c})"
    first, second, pair_ratio = ratios(pair.selectExpr("first", "second", f"ln({p('toxic')} / {p('other')}) as ratio"), 2)
    pairs = pair_keys(first, second)
    pair_order = np.argsort(pairs)
    return {"units": keys[order], "unit": ratio[order], "pairs": pairs[pair_order], "pair": pair_ratio[pair_order]}


def text_evidence(rows: DataFrame, model, keep: str, kept_type: str) -> DataFrame:
    """(keep, mean, stretch) of each row; ``model`` is a broadcast Model."""

    def run(batches):
        reader = Reader(model.value)
        for b in slices(batches, 2048):
            found = [reader.evidence(t) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x[0] for x in found], pa.float64()), pa.array([x[1] for x in found], pa.float64())], names=[keep, "mean", "stretch"])

    return rows.select(keep, "text").mapInArrow(run, f"{keep} {kept_type}, mean double, stretch double")


def examples(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(toxic, text, part, place): labelled texts, one of each group of copies, so that a text counts once.

    Which rows these are is found on ids and hashes alone. Up to BROADCAST_LABELS of them
    are sent to the texts; more are joined by shuffle once and written.
    """
    known = labels.where("toxic in (0, 1)").select("doc_id", F.col("toxic").cast("int").alias("toxic"))
    ids = docs.select("doc_id", F.xxhash64("text").alias("copy"), F.xxhash64("doc_id").alias("place")).join(known, "doc_id")
    chosen = ids.groupBy("copy", "toxic").agg(F.min(F.struct("place", "doc_id")).alias("x"))
    chosen = materialise(chosen.select("x.doc_id", "toxic", "x.place"), "toxicity-labels")
    n = chosen.count()
    chosen = chosen.withColumn("part", F.pmod("place", F.lit(max(CALIBRATE_EACH, -(-n // CALIBRATE_ROWS)))))
    if n <= BROADCAST_LABELS:
        return docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")
    return materialise(docs.select("doc_id", "text").join(chosen, "doc_id"), "toxicity-texts")


def train(docs: DataFrame, labels: DataFrame) -> Model:
    """Fit on the texts of ``docs`` that ``labels`` (doc_id, toxic) rates."""
    spark = docs.sparkSession
    rows = examples(docs, labels)
    # units all stay; a pair up to the discount backs off wholly, so only the others are kept
    found = materialise(counts(rows.where("part > 0")).where(f"second = 0 or greatest(toxic, other) > {DISCOUNT}"), "toxicity-counts")
    model = Model(**kneser_ney(found), weights=np.zeros(3))
    apart = text_evidence(rows.where("part = 0").select(F.struct("toxic", "place").alias("key"), "text"), spark.sparkContext.broadcast(model), "key", "struct<toxic: int, place: bigint>")
    sample = apart.select("key.*", "mean", "stretch").orderBy("place", "toxic", "mean").limit(CALIBRATE_ROWS).toPandas()
    y = sample["toxic"].to_numpy(dtype=np.float64)
    if 0 < y.sum() < len(y):
        model.weights = logistic(features(sample[["mean", "stretch"]].to_numpy()), y)
    else:
        share = np.clip(y.mean() if len(y) else 0.0, 1e-9, 1 - 1e-9)
        model.weights = np.array([0.0, 0.0, np.log(share / (1 - share))])
    return model


def score(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, score, predicted) of every row of ``docs``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        reader = Reader(shared.value)
        for b in slices(batches, 2048):
            s = shared.value.score([reader.evidence(t) for t in b.column(1).to_pylist()])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(s), pa.array((s >= threshold).astype("int32"))], names=["doc_id", "score", "predicted"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, score double, predicted int")


def without_toxic(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """``docs`` without the rows that are predicted toxic."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def decider():
        reader = Reader(shared.value)
        return lambda texts: (shared.value.score([reader.evidence(t) for t in texts]) < threshold).tolist()

    return kept_rows(docs, decider)


def in_training(doc_id="doc_id"):
    """Rows that labels may be learned from: crc32 of the id's text, modulo 3, is not 1."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3 != 1


def training_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet").where(in_training()).select("doc_id", "toxic")


def op9_kneser_ney(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    scored = score(docs, train(docs, training_labels(spark, sf_dir)))
    return scored.select("doc_id", (~in_training()).alias("held_out"), "score", "predicted")
