"""Language identification by bit-sliced Bloom filters of character n-grams.

One array of slots stands for the Bloom filters of all languages: bit l of a slot
belongs to language l's filter. The AND of the slots that an n-gram hashes to is the
mask of all languages that hold it (or seem to). The bits set over all n-grams of a
text are counted for each language, the number that a filter's fill would give by
chance is taken off, and the language with the largest corrected count wins.

An n-gram belongs to a language if it makes up at least RARE of the language's
n-grams and at least NEAR of the share it has in the language where it is most
frequent. So a language has at most 1 / RARE n-grams, and the filters' size is fixed.
Counts are taken over all training rows and summed by Spark; the filters are made by
OR-ing masks by slot.

Edge cases: null texts and texts without a letter are ``und`` with score 0; a text
none of whose n-grams is known, and ties, go to the language with more training
n-grams, then to the smaller name, a text of no known n-gram with score 0; texts are
read whole; without training rows all texts are ``und``.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidelabel.llm.common import documents, kept_rows, materialise, slices

SLOTS, HASHES = 1 << 20, 3
SIZES = (1, 2, 3, 4)
RARE, NEAR = 5e-6, 0.25
#: Languages in one slot value.
BITS = 62
LETTERS = re.compile(r"[^\W\d_]+")
#: Bytes of a slice of texts; their words take about 80 times the bytes while they are told apart.
AT_ONCE = 1 << 20
#: N-grams that a task counts before it hands them on.
CACHE = 1_000_000
UNKNOWN = "und"
GOLDEN = np.uint64(0x9E3779B97F4A7C15)


def mixed(x: np.ndarray) -> np.ndarray:
    """The public splitmix64 finaliser."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@lru_cache(maxsize=1)
def classes() -> tuple[np.ndarray, np.ndarray]:
    """By code point: can it be part of a word; is it a letter."""
    word, letter = np.zeros(0x110000, dtype=bool), np.zeros(0x110000, dtype=bool)
    # in blocks, as lists of all code points take as much memory as all else of a worker
    for start in range(0, 0x110000, 0x800):
        if 0xD800 <= start < 0xE000:
            continue
        block = "".join(map(chr, range(start, start + 0x800)))
        for found in LETTERS.finditer(block):
            word[start + found.start() : start + found.end()] = True
        letter[start : start + 0x800] = [c.isalpha() for c in block]
    return word, letter


class Words:
    """The distinct words of some texts, in lower case, and where they stand."""

    def __init__(self, texts: list[str | None]):
        lower = [(t or "").lower() for t in texts]
        code = np.frombuffer("\n".join(lower).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        word, letter = classes()
        inside = word[code]
        at = np.flatnonzero(inside)
        first = inside[at] & ~np.concatenate([[False], inside])[at] if len(at) else np.zeros(0, dtype=bool)
        starts = np.flatnonzero(first)
        letters, ends = code[at].astype(np.uint64), np.cumsum([len(x) + 1 for x in lower], dtype=np.int64)
        #: the text of each word, and whether each text has a letter
        self.text = np.searchsorted(ends, at[starts], side="right")
        self.has_letter = np.zeros(len(texts), dtype=bool)
        self.has_letter[np.searchsorted(ends, at[letter[code[at]]], side="right")] = True
        if not len(at):
            self.of, self.counts, self.chars, self.begin = np.zeros(0, np.int64), np.zeros(0, np.int64), np.full(1, 32, np.uint64), np.zeros(0, np.int64)
            return
        sizes = np.diff(np.append(starts, len(at)))
        place = (np.arange(len(at)) - np.repeat(starts, sizes)).astype(np.uint64)
        key = np.add.reduceat(mixed(letters + (place << np.uint64(32)) + GOLDEN), starts)
        #: the distinct word of each word, how often each occurs
        _, where, self.of, self.counts = np.unique(key, return_index=True, return_inverse=True, return_counts=True)
        # the distinct words one after another, a blank before, between and behind them
        n = sizes[where]
        self.begin = np.concatenate([[1], 1 + np.cumsum(n + 1)[:-1]])
        self.chars = np.full(int((n + 1).sum()) + 1, 32, dtype=np.uint64)
        offset = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        self.chars[np.repeat(self.begin, n) + offset] = letters[np.repeat(starts[where], n) + offset]

    def grams(self):
        """(hash, place) of the distinct words' n-grams of each size: 63-bit hashes and a place in the word's stretch."""
        c = self.chars
        blank = c == 32
        for n in SIZES:
            if len(c) < n:
                continue
            fine = ~blank.copy() if n == 1 else np.ones(len(c) - n + 1, dtype=bool)
            for i in range(1, n - 1):
                fine &= ~blank[i : len(c) - n + 1 + i]
            at = np.flatnonzero(fine)
            key = np.full(len(at), n, dtype=np.uint64) * GOLDEN
            for i in range(n):
                key = mixed(key + c[at + i]) if i == 2 else key * GOLDEN + c[at + i]
            yield mixed(key) >> np.uint64(1), at + (n > 1)

    def word_at(self) -> np.ndarray:
        """The distinct word of each place; a word's stretch holds the blank behind it."""
        return np.repeat(np.arange(len(self.begin)), np.diff(np.append(self.begin, len(self.chars))))


def gram_counts(rows: DataFrame) -> DataFrame:
    """(lang, gram, n) over (lang, text) rows; gram is an n-gram's hash."""

    def summed(parts: list) -> tuple[np.ndarray, np.ndarray]:
        gram, at = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
        return gram, np.bincount(at, weights=np.concatenate([p[1] for p in parts]), minlength=len(gram)).astype(np.int64)

    def handed(found: dict[str, list]):
        for lang, parts in found.items():
            gram, n = summed(parts)
            for i in range(0, len(gram), 200_000):
                part = [pa.array([lang] * len(gram[i : i + 200_000]), pa.string()), pa.array(gram[i : i + 200_000].astype(np.int64)), pa.array(n[i : i + 200_000])]
                yield pa.RecordBatch.from_arrays(part, names=["lang", "gram", "n"])
        found.clear()

    def run(batches):
        found: dict[str, list] = {}
        for b in slices(batches, 1024, AT_ONCE):
            by_lang: dict[str, list] = {}
            for lang, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                by_lang.setdefault(lang, []).append(text)
            for lang, texts in by_lang.items():
                words = Words(texts)
                if len(words.begin):
                    of = words.word_at()
                    parts = [(gram, words.counts[of[at - 1]].astype(np.float64)) for gram, at in words.grams()]
                    found[lang] = [summed(found.get(lang, []) + parts)]
            if sum(len(p[0][0]) for p in found.values()) > CACHE:
                yield from handed(found)
        yield from handed(found)

    return rows.select("lang", "text").mapInArrow(run, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))


@dataclass
class Filters:
    names: list[str]
    slots: np.ndarray  # [words of BITS bits, SLOTS]
    chance: np.ndarray  # [languages] probability that an n-gram seems to be held by chance


def learn(rows: DataFrame, rare: float = RARE, near: float = NEAR) -> Filters:
    """Filters from (lang, text) rows with a language."""
    counts = materialise(gram_counts(rows.where("lang is not null")), "language-grams")
    totals = {r.lang: r.n for r in counts.groupBy("lang").agg(F.sum("n").alias("n")).where("n > 0").collect()}
    names = sorted(totals, key=lambda x: (-totals[x], x))
    spark = rows.sparkSession
    if not names:
        return Filters([], np.zeros((1, 1), dtype=np.int64), np.zeros(0))
    of_lang = F.broadcast(spark.createDataFrame([(x, i, float(totals[x])) for i, x in enumerate(names)], "lang string, number int, total double"))
    share = counts.join(of_lang, "lang").withColumn("share", F.col("n") / F.col("total")).where(F.col("share") >= rare)
    best = share.groupBy("gram").agg(F.max("share").alias("best"), F.collect_list(F.struct("number", "share")).alias("of"))
    held = best.select("gram", F.expr(f"filter(of, x -> x.share >= {near} * best)").alias("of"))
    masks = held.select("gram", F.explode("of").alias("x")).selectExpr("gram", f"x.number div {BITS} as part", f"shiftleft(1L, cast(x.number % {BITS} as int)) as bit").groupBy("gram", "part").agg(F.expr("bit_or(bit)").alias("mask"))
    # slot i is (gram + i * (gram >> 32)) mod SLOTS
    at = masks.selectExpr("part", "mask", f"explode(transform(sequence(0, {HASHES - 1}), i -> (gram % {SLOTS} + i * (shiftright(gram, 32) % {SLOTS})) % {SLOTS})) as slot")
    table = at.groupBy("part", "slot").agg(F.expr("bit_or(mask)").alias("mask")).toArrow()
    slots = np.zeros((-(-len(names) // BITS), SLOTS), dtype=np.int64)
    slots[table.column(0).to_numpy().astype(np.int64), table.column(1).to_numpy()] = table.column(2).to_numpy()
    fill = [float(((slots[i // BITS] >> (i % BITS)) & 1).mean()) for i in range(len(names))]
    return Filters(names, slots, np.array(fill) ** HASHES)


class Reader:
    """Counts the n-grams of texts by language, once for each distinct word of a slice of texts."""

    def __init__(self, filters: Filters):
        self.filters = filters
        # few languages make a small table, which stays in the processor's cache
        kind = next(k for k in (np.uint8, np.uint16, np.uint32, np.uint64) if len(filters.names) <= 8 * k().itemsize or k is np.uint64)
        self.slots = filters.slots.astype(kind)

    def hits(self, words: Words) -> np.ndarray:
        """[distinct words, languages + 1]: n-grams that each filter holds, and all n-grams."""
        n = len(self.filters.names)
        found = np.zeros((n + 1, len(words.chars)), dtype=np.int32)
        for gram, at in words.grams():
            step = gram >> np.uint64(32)
            masks = [part[(gram & np.uint64(SLOTS - 1)).astype(np.int64)] for part in self.slots]
            for i in range(1, HASHES):
                slot = ((gram + np.uint64(i) * step) & np.uint64(SLOTS - 1)).astype(np.int64)
                masks = [m & part[slot] for m, part in zip(masks, self.slots)]
            for lang in range(n):
                found[lang, at] += ((masks[lang // BITS] >> (lang % BITS)) & 1).astype(np.int32)
            found[n, at] += 1
        return np.add.reduceat(found, words.begin, axis=1).T

    def predict(self, texts: list[str | None]) -> list[tuple[str, float, float]]:
        """(language, share of the corrected hits, corrected hits an n-gram) of each text."""
        words = Words(texts)
        if not self.filters.names or not len(words.begin):
            return [(UNKNOWN, 0.0, 0.0)] * len(texts)
        hits = self.hits(words)[words.of]
        total = np.stack([np.bincount(words.text, weights=column, minlength=len(texts)) for column in hits.T], axis=1)
        all_, hits = total[:, -1:], total[:, :-1]
        right = np.maximum(hits - all_ * self.filters.chance, 0) / np.maximum(1 - self.filters.chance, 1e-9)
        best, sums = right.argmax(axis=1), right.sum(axis=1)
        top = right[np.arange(len(texts)), best]
        score = np.divide(top, sums, out=np.zeros(len(texts)), where=sums > 0)
        known = np.minimum(np.divide(top, all_[:, 0], out=np.zeros(len(texts)), where=all_[:, 0] > 0), 1)
        return [(self.filters.names[i], float(p), float(k)) if fine else (UNKNOWN, 0.0, 0.0) for i, p, k, fine in zip(best, score, known, words.has_letter)]


def identify(docs: DataFrame, filters: Filters) -> DataFrame:
    """(doc_id, lang_pred, score, known): known is the share of n-grams that the language holds."""
    shared = docs.sparkSession.sparkContext.broadcast(filters)

    def run(batches):
        reader = Reader(shared.value)
        for b in slices(batches, 1024, AT_ONCE):
            found = reader.predict(b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array([x[i] for x in found], t) for i, t in enumerate((pa.string(), pa.float64(), pa.float64())))], names=["doc_id", "lang_pred", "score", "known"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, lang_pred string, score double, known double")


def with_language(docs: DataFrame, filters: Filters, least_known: float) -> DataFrame:
    """``docs`` whose predicted language holds at least a share ``least_known`` of the text's n-grams."""
    shared = docs.sparkSession.sparkContext.broadcast(filters)

    def decider():
        reader = Reader(shared.value)
        return lambda texts: [lang != UNKNOWN and known >= least_known for lang, _, known in reader.predict(texts)]

    return kept_rows(docs, decider, most=AT_ONCE)


def held_out(doc_id: str = "doc_id"):
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3 == 1


def op1_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    filters = learn(docs.where(~held_out()).select("lang", "text"))
    return identify(docs, filters).select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "known")
