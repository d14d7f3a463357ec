"""Mixture-controlled packing: deficit round-robin over source queues.

Every source is a queue of tokens (its documents one after another). A source
with target weight w earns credit in proportion to w; whenever a source's credit
covers a quantum of tokens it is served one quantum, and what it lacks or has
over is its deficit, carried on from window to window and from partition to
partition. Services are therefore ordered by (i / w, source) for the i-th quantum
of a source, and the place of a quantum in the stream of windows is the number of
tokens served before it: a sum over sources of a closed form. So a task needs only
the sources' totals and where its own documents start in their queues; no task
walks through another one's windows, and the result doesn't depend on how many
tasks there are. A source whose queue is empty earns nothing more, and the rest
share the windows in their proportions.

All windows but the last are full. A document is cut where a quantum ends or a
window ends; parts that stay side by side are one piece.

Edge cases: null text is an empty text, which still has its end id; null sources
form one queue; documents longer than a window are cut; repeated ids are packed
as separate rows; an empty table gives no rows. State on the driver: one total per
source.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidelabel.llm.bpe import ENCODE_ROWS, array_encoder, default_vocabulary, vocabulary
from tidelabel.llm.common import documents, materialise, slices

WINDOW = 1024
#: Tokens that a source is served at once.
QUANTUM = 64
#: Fixed value: the id put behind each document.
END_ID = 0
#: Rows of (block, source) starts that may be broadcast (about 40 bytes each); more are joined by shuffle.
BROADCAST_STARTS = 200_000
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, source string"


#: Fixed value: the public pre-tokenisation pattern in the form that tiktoken reads.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


class Encoder:
    """Ids as the tokenizers library gives them, the common texts by tiktoken, which is faster.

    Texts with special tokens, or with characters whose classes the two libraries may
    see differently, and texts that tiktoken refuses, take the trie encoder.
    """

    def __init__(self, path: str):
        import tiktoken

        self.vocab, self.exact = vocabulary(path), array_encoder(path)
        self.fast = tiktoken.Encoding("byte-level", pat_str=PATTERN, mergeable_ranks=self.vocab.id_of, special_tokens={})

    def encode(self, texts: list[str | None]) -> list[np.ndarray]:
        out: list[np.ndarray | None] = []
        for t in texts:
            ids = None
            if not t:
                ids = []
            elif not self.vocab.rare.search(t) and not any(s in t for s in self.vocab.special):
                try:
                    ids = self.fast.encode_ordinary(t)
                except BaseException as e:  # a panic of the regex engine isn't an Exception
                    if isinstance(e, (KeyboardInterrupt, SystemExit)):
                        raise
            out.append(None if ids is None else np.array(ids, dtype="<u4"))
        rest = [i for i, x in enumerate(out) if x is None]
        for i, x in zip(rest, self.exact.encode([texts[i] for i in rest])):
            out[i] = x
        return out


def tokenised(docs: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, source, ids, doc_tokens, block, before): one row per document.

    A block is what one task wrote; ``before`` counts the tokens of the same source
    earlier in the block. Written once, so that a lost executor can't renumber it.
    """
    path = path or default_vocabulary()

    def run(batches):
        encoder = Encoder(path)
        end = np.array([END_ID], dtype="<u4")
        block, seen = TaskContext.get().partitionId(), {}
        for b in slices(batches, ENCODE_ROWS):
            ids = [np.concatenate([x, end]) for x in encoder.encode(b.column(2).to_pylist())]
            before = []
            for source, x in zip(b.column(1).to_pylist(), ids):
                before.append(seen.get(source, 0))
                seen[source] = before[-1] + len(x)
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(0), b.column(1), pa.array([x.tobytes() for x in ids], pa.binary()), pa.array([len(x) for x in ids], pa.int64()),
                    pa.array([block] * len(ids), pa.int32()), pa.array(before, pa.int64()),
                ],
                names=["doc_id", "source", "ids", "doc_tokens", "block", "before"],
            )

    rows = docs.select(F.col("doc_id").cast("long"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("source"), "text")
    return materialise(rows.mapInArrow(run, "doc_id long, source string, ids binary, doc_tokens long, block int, before long"), "packing-tokens")


def service_start(of: np.ndarray, quantum_no: np.ndarray, totals: np.ndarray, weights: np.ndarray, quantum: int) -> np.ndarray:
    """Tokens served before the ``quantum_no``-th (from 1) quantum of source ``of``, for many at once."""
    at = np.zeros(len(of), dtype=np.int64)
    own = weights[of]
    for s in range(len(totals)):
        ahead = (quantum_no * weights[s] - (of < s)) // own
        ahead = np.where(of == s, quantum_no - 1, ahead)
        at += np.minimum(totals[s], quantum * ahead)
    return at


def cut(of, first, length, totals, weights, quantum, window):
    """Pieces of documents: (document, start in it, length, position in the stream)."""
    low, high = first // quantum, (first + length - 1) // quantum
    n = high - low + 1
    doc = np.repeat(np.arange(len(of)), n)
    chunk = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + low[doc]
    begin = np.maximum(first[doc], chunk * quantum)
    stop = np.minimum((first + length)[doc], (chunk + 1) * quantum)
    place = service_start(of[doc], chunk + 1, totals, weights, quantum) + begin - chunk * quantum
    left = np.minimum(stop - begin, window - place % window)
    over = np.flatnonzero(stop - begin > left)
    order = np.argsort(np.concatenate([np.arange(len(doc)) * 2, over * 2 + 1]), kind="stable")
    place = np.concatenate([place, (place + left)[over]])[order]
    begin, size = np.concatenate([begin, (begin + left)[over]])[order], np.concatenate([left, (stop - begin - left)[over]])[order]
    doc = np.concatenate([doc, doc[over]])[order]
    fresh = np.ones(len(doc), dtype=bool)
    fresh[1:] = (doc[1:] != doc[:-1]) | (place[1:] != place[:-1] + size[:-1]) | (place[1:] % window == 0)
    heads = np.flatnonzero(fresh)
    return doc[heads], (begin - first[doc])[heads], np.add.reduceat(size, heads) if len(heads) else size, place[heads]


def integer_weights(totals: dict[str, int], targets: dict[str, float] | None) -> dict[str, int]:
    share = {s: (targets or {}).get(s, 0.0) if targets else t for s, t in totals.items()}
    top = max(share.values(), default=1) or 1
    return {s: max(1, round(x / top * (1 << 20))) for s, x in share.items()}


def pack(docs: DataFrame, targets: dict[str, float] | None = None, window: int = WINDOW, quantum: int = QUANTUM, path: str | None = None) -> DataFrame:
    """All documents packed into windows; ``targets`` are token proportions of sources (their own, if None)."""
    if not 0 < quantum <= window:
        raise ValueError("the quantum must be from 1 to the window")
    tokens = tokenised(docs, path)
    spark = docs.sparkSession
    per_block = tokens.groupBy("block", "source").agg(F.sum("doc_tokens").alias("n"))
    per_block = materialise(per_block, "packing-blocks")
    total_rows = per_block.groupBy("source").agg(F.sum("n").alias("n")).orderBy("source").collect()
    if not total_rows:
        return spark.createDataFrame([], PIECES)
    names = [r.source for r in total_rows]
    weight = integer_weights({r.source: r.n for r in total_rows}, targets)
    totals = np.array([r.n for r in total_rows], dtype=np.int64)
    weights = np.array([weight[s] for s in names], dtype=np.int64)
    number = {s: i for i, s in enumerate(names)}
    starts = per_block.selectExpr("block", "source", "coalesce(sum(n) over (partition by source order by block rows between unbounded preceding and 1 preceding), 0L) as base")
    if per_block.count() <= BROADCAST_STARTS:
        starts = F.broadcast(starts)

    def run(batches):
        for b in slices(batches, 2048):
            of = np.array([number[s] for s in b.column(1).to_pylist()], dtype=np.int64)
            ids = b.column(2).to_pylist()
            length = b.column(3).to_numpy()
            first = b.column(4).to_numpy()
            doc, start, size, place = cut(of, first, length, totals, weights, quantum, window)
            crc = [zlib.crc32(memoryview(ids[d])[4 * s : 4 * (s + n)]) for d, s, n in zip(doc.tolist(), start.tolist(), size.tolist())]
            take = pa.array(doc)
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(0).take(take), pa.array(start), pa.array(size), pa.array(crc, pa.int64()), b.column(3).take(take),
                    pa.array(place // window), pa.array(place % window), b.column(1).take(take),
                ],
                names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "source"],
            )

    placed = tokens.join(starts, ["block", "source"]).select("doc_id", "source", "ids", "doc_tokens", (F.col("base") + F.col("before")).alias("first"))
    return placed.mapInArrow(run, PIECES)


def mixture(pieces: DataFrame) -> DataFrame:
    """Tokens of each source in each window."""
    return pieces.groupBy("sequence_id", "source").agg(F.sum("length").alias("tokens"))


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(documents(spark, sf_dir)).drop("source")
