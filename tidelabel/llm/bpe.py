"""BPE encoding and decoding over a trie of distinct words.

The text is cut by the byte-level pre-tokeniser's pattern. The distinct words of
a slice of documents are put in sorted order, which is the depth-first order of
their trie: the path from the root to the current word is a stack of states, and
moving to the next word pops the stack to the shared prefix and pushes the rest.
A state is the id of the *last* token of the path's encoding. It is enough,
because the tokens before it are the encoding of the path without that token, an
ancestor on the stack. So each shared prefix is encoded once.

A token t may follow the ancestor's last token s exactly if merging the bytes of
s and t from scratch gives back s and t; of all tokens that end at a node one
passes. These pair decisions are kept in a table. A word's own token always passes at
its start, as every token of such a vocabulary is what its bytes merge to.

Edge cases: null text is an empty text (0 tokens, digests of the empty string);
texts and single words of any length take time in proportion to their length;
special tokens inside a text are cut out first and keep their id; repeated rows
give repeated results; extra columns of the input are ignored.
"""

from __future__ import annotations

import hashlib
import json
import re
import unicodedata
from array import array
from collections import defaultdict
from collections.abc import Iterable, Iterator
from functools import lru_cache
from itertools import count, islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from tidelabel.llm.common import documents, slices

#: Classes of the public pre-tokenisation pattern of byte-level BPE.
CONTRACTIONS = "'s|'t|'re|'ve|'m|'ll|'d"
WHITE = "\\t-\\r \\x85\\xa0"
#: Below this code point the pattern is run by ``re``. A text with a character from
#: here on is cut by the tokenizers library, whose Unicode tables decide there.
PLAIN_LIMIT = 0x530
#: Words kept with their encoding in a worker; beyond it the table starts anew.
CACHE_WORDS = 250_000
#: Most documents whose words share one trie (slices also end at common.SLICE_BYTES of text).
ENCODE_ROWS = 8192


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def printable_bytes() -> dict[str, int]:
    """The byte that each character of a byte-level vocabulary stands for."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


def plain_pattern() -> re.Pattern:
    """The pre-tokenisation pattern for texts of characters under PLAIN_LIMIT."""

    def members(kind: str) -> str:
        return "".join(re.escape(chr(c)) for c in range(PLAIN_LIMIT) if unicodedata.category(chr(c))[0] == kind)

    letter, number = members("L"), members("N")
    return re.compile(f"{CONTRACTIONS}| ?[{letter}]+| ?[{number}]+| ?[^{WHITE}{letter}{number}]+|[{WHITE}]+(?![^{WHITE}])|[{WHITE}]+")


class Vocabulary:
    """Tokens, merges and special tokens of a byte-level BPE file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        to_byte = printable_bytes()
        model = data["model"]
        raw = lambda s: bytes(to_byte[c] for c in s)
        self.path = path
        self.id_of = {raw(t): i for t, i in model["vocab"].items()}
        self.bytes_of = {i: t for t, i in self.id_of.items()}
        self.special = {t["content"]: t["id"] for t in data.get("added_tokens", [])}
        for text, i in self.special.items():
            self.bytes_of[i] = text.encode()
        self.size = max(self.bytes_of) + 1
        self.rank_of: dict[tuple[int, int], int] = {}
        self.parts: dict[int, tuple[int, int]] = {}
        self.made_at = [-1] * self.size
        for rank, pair in enumerate(model["merges"]):
            left, right = (raw(x) for x in (pair if isinstance(pair, list) else pair.split(" ")))
            token, pair = self.id_of[left + right], (self.id_of[left], self.id_of[right])
            self.rank_of[pair] = rank
            if token not in self.parts:
                self.parts[token], self.made_at[token] = pair, rank
        # tokens by their bytes from the end: edge (node, byte) -> node, and the token that a node is
        self.edge: dict[int, int] = {}
        self.token_at = [-1]
        for token in sorted(self.id_of.values()):
            node = 0
            for byte in reversed(self.bytes_of[token]):
                key = node << 8 | byte
                node = self.edge.get(key, 0)
                if not node:
                    node = self.edge[key] = len(self.token_at)
                    self.token_at.append(-1)
            self.token_at[node] = token
        self.length = [len(self.bytes_of.get(i, b"")) for i in range(self.size)]
        self.words = plain_pattern()
        self.rare = re.compile(f"[{chr(PLAIN_LIMIT)}-{chr(0x10FFFF)}]")
        self.cut = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self._follows: dict[int, bool] = {}
        self._library = None

    def adjacent(self, left: int, right: int) -> bool:
        """Do two tokens stay as they are side by side?

        The tokens' construction is taken back from the latest merge to the first.
        On the way, two parts that touch across the border must have no merge of
        their own that would have come before the merges that took these parts in
        (at equal rank the leftmost place is merged first).
        """
        made, rank_of, parts = self.made_at, self.rank_of, self.parts
        taken_left = taken_right = len(rank_of)
        while True:
            rank = rank_of.get((left, right))
            if rank is not None and rank < taken_left and rank <= taken_right:
                return False
            if made[left] > made[right]:
                taken_left, left = made[left], parts[left][1]
            elif made[right] >= 0:
                taken_right, right = made[right], parts[right][0]
            else:
                return True

    def follows(self, left: int, right: int) -> bool:
        key = left * self.size + right
        known = self._follows.get(key)
        if known is None:
            if len(self._follows) > 500_000:
                self._follows.clear()
            known = self._follows[key] = self.adjacent(left, right)
        return known

    def encode_words(self, words: Iterable[bytes]) -> Iterator[tuple[bytes, list[int]]]:
        """Encodings of distinct words, in the order of a depth-first walk of their trie."""
        last: list[int] = []
        before = b""
        edge, token_at, length, known, size, follows = self.edge.get, self.token_at, self.length, self._follows.get, self.size, self.follows
        for word in sorted(words):
            shared, limit = 0, min(len(before), len(word))
            if before[:limit] == word[:limit]:
                shared = limit
            else:
                while before[shared] == word[shared]:
                    shared += 1
            del last[shared:]
            for end in range(shared, len(word)):
                # every token that ends here, shortest first
                node, start, choices = 0, end, []
                while start >= 0:
                    node = edge(node << 8 | word[start])
                    if node is None:
                        break
                    token = token_at[node]
                    if token >= 0:
                        choices.append(token)
                    start -= 1
                for token in reversed(choices):
                    at = end - length[token]
                    if at < 0:
                        last.append(token)
                        break
                    ok = known(last[at] * size + token)
                    if ok or ok is None and follows(last[at], token):
                        last.append(token)
                        break
                else:
                    raise ValueError("the vocabulary lacks a single byte")
            before = word
            ids, at = [], len(word)
            while at:
                token = last[at - 1]
                ids.append(token)
                at -= length[token]
            ids.reverse()
            yield word, ids

    def _cut_words(self, text: str) -> list[str]:
        if text.isascii() or not self.rare.search(text):
            return self.words.findall(text)
        if self._library is None:
            from tokenizers import Tokenizer

            self._library = Tokenizer.from_file(self.path).pre_tokenizer
        return [text[a:b] for _, (a, b) in self._library.pre_tokenize_str(text)]

    def pieces(self, text: str) -> list[str | int]:
        """The text's words in order; special tokens as their ids."""
        if self.cut is None or not any(s in text for s in self.special):
            return self._cut_words(text)
        out: list[str | int] = []
        for part in self.cut.split(text):
            if part in self.special:
                out.append(self.special[part])
            elif part:
                out.extend(self._cut_words(part))
        return out


@lru_cache(maxsize=2)
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


class SliceEncoder:
    """Encodes the texts of one slice after another; ``entry(ids)`` is kept for each word."""

    def __init__(self, vocab: Vocabulary, entry):
        self.vocab, self.entry = vocab, entry
        self._start()

    def _start(self) -> None:
        self.index: dict = defaultdict(count().__next__)
        self.entries: list = []

    def texts(self, texts: list[str | None]) -> Iterator[list]:
        """For each text the entries of its words in order."""
        if len(self.entries) > CACHE_WORDS:
            self._start()
        index, entries, vocab = self.index, self.entries, self.vocab
        numbers = [array("I", [index[p] for p in vocab.pieces(t)]) if t else () for t in texts]
        fresh = list(islice(reversed(index), len(index) - len(entries)))
        entries.extend([None] * len(fresh))
        spelled = {}
        for p in fresh:
            if isinstance(p, int):
                entries[index[p]] = self.entry([p])
            else:
                spelled[p.encode("utf-8")] = index[p]
        for word, ids in vocab.encode_words(spelled):
            entries[spelled[word]] = self.entry(ids)
        del fresh, spelled
        for of_text in numbers:
            yield [entries[i] for i in of_text]

    def encode(self, texts: list[str | None]) -> list[np.ndarray]:
        return [np.frombuffer(b"".join(e), dtype="<u4") for e in self.texts(texts)]


def array_encoder(path: str) -> SliceEncoder:
    return SliceEncoder(vocabulary(path), lambda ids: np.array(ids, dtype="<u4").tobytes())


def decode(ids, path: str) -> str:
    table = vocabulary(path).bytes_of
    return b"".join(table[int(i)] for i in ids).decode("utf-8", errors="replace")


def encode_documents(docs: DataFrame, path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids): token ids of every whole text."""
    path = path or default_vocabulary()

    def run(batches):
        encoder = array_encoder(path)
        for b in slices(batches, ENCODE_ROWS):
            ids = encoder.encode(b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x.astype("int32") for x in ids], pa.list_(pa.int32()))], names=["doc_id", "ids"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(docs[id_col].alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, f"doc_id {kind}, ids array<int>")


def decode_documents(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, text) from (doc_id, ids)."""
    path = path or default_vocabulary()

    def run(batches):
        for b in slices(batches, ENCODE_ROWS):
            text = [decode(x, path) if x is not None else "" for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(text, pa.string())], names=["doc_id", "text"])

    kind = encoded.schema["doc_id"].dataType.simpleString()
    return encoded.select("doc_id", "ids").mapInArrow(run, f"doc_id {kind}, text string")


def token_digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """Count and digests of each text's encoding and of what decoding gives back, in one pass.

    Null texts count as empty. A row of the input is a row of the result.
    """
    path = path or default_vocabulary()

    def run(batches):
        vocab = vocabulary(path)
        table = vocab.bytes_of
        encoder = SliceEncoder(vocab, lambda ids: (",".join(map(str, ids)), len(ids), b"".join(table[i] for i in ids)))
        for b in slices(batches, ENCODE_ROWS):
            n, of_ids, of_text = [], [], []
            for entries in encoder.texts(b.column(1).to_pylist()):
                n.append(sum([e[1] for e in entries]))
                of_ids.append(hashlib.sha256(",".join([e[0] for e in entries]).encode()).hexdigest())
                back = b"".join([e[2] for e in entries]).decode("utf-8", errors="replace")
                of_text.append(hashlib.sha256(back.encode()).hexdigest())
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(n, pa.int64()), pa.array(of_ids, pa.string()), pa.array(of_text, pa.string())],
                names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op3_bpe_trie(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_digests(documents(spark, sf_dir))
