"""Byte-level BPE by dynamic programming over prefixes.

The valid encoding of a byte string is unique, and so is the last token of the valid
encoding of each of its prefixes. ``PrefixTable`` stores that token for every prefix:
the last token of a prefix is the token t that ends it such that t may follow the
last token of what precedes t. Two tokens may stand side by side if no merge across
their border comes before the merges inside them. Appending extends the table; an
edit keeps the table before it and stops as soon as the table agrees again with the
old one over the length of the longest token.

``encode`` and ``decode`` apply it to DataFrames. Defined results: a null or empty
text has no tokens; rows are handled one by one, so repeated rows and ids don't
matter; only id and text are read, whatever other columns there are; an empty table
gives an empty result. Memory is bounded by a batch of rows, the longest text and
caches of CACHE entries each, which are emptied when full.
"""

from __future__ import annotations

import base64
import functools
from array import array
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Entries of each cache of a Python worker (of words: of each of two generations).
CACHE = 300_000

#: The characters with the Unicode property White_Space, as ranges of a character class.
WHITE_SPACE = r"\t-\r \x85\xa0  -     　"


def read_ranks(path: str) -> list[bytes]:
    """The tokens of a file of base64 tokens and ranks, by rank."""
    with open(path, "rb") as lines:
        found = {int(rank): base64.b64decode(token) for token, rank in (line.split() for line in lines if line.strip())}
    return [found[i] for i in range(len(found))]


class Vocabulary:
    """Tokens by rank, with what says which two may stand side by side."""

    def __init__(self, tokens: list[bytes]) -> None:
        self.tokens, self.ranks = tokens, {t: i for i, t in enumerate(tokens)}
        self.longest = max(map(len, tokens))
        self.halves: dict[int, tuple[int, int] | None] = {}
        #: By left token: which tokens may follow it, as far as known.
        self.beside: dict[int, dict[int, bool]] = defaultdict(dict)
        self.n_beside = 0
        #: A trie: by byte, the next node and the token that ends there (-1: none). Leaves share one node.
        self.root: dict[int, tuple[dict, int]] = {}
        leaf: dict[int, tuple[dict, int]] = {}
        for i, token in enumerate(tokens):
            node, inner = self.root, token[:-1]
            for b in inner:
                child, own = node.get(b, (leaf, -1))
                if child is leaf:
                    child = {}
                    node[b] = child, own
                node = child
            node[token[-1]] = node.get(token[-1], (leaf, -1))[0], i

    def split(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge makes a token; itself twice for a byte; None if no merge makes it."""
        if token not in self.halves:
            parts = [self.ranks[bytes([b])] for b in self.tokens[token]]
            while len(parts) > 2:
                ranks = [self.ranks.get(self.tokens[a] + self.tokens[b], 1 << 40) for a, b in zip(parts, parts[1:], strict=False)]
                best = min(ranks)
                if best >= token:
                    break
                k = ranks.index(best)
                parts[k : k + 2] = [best]
            self.halves[token] = (parts[0], parts[-1]) if len(parts) <= 2 else None
        return self.halves[token]

    def may_follow(self, left: int, right: int) -> bool:
        """Whether a valid encoding can hold left and then right: undoes the later merge of the two again and again, and looks for an earlier one across the border."""
        known = self.beside[left].get(right)
        if known is None:
            if self.n_beside >= CACHE:
                for row in self.beside.values():
                    row.clear()
                self.n_beside = 0
            known = self.beside[left][right] = self.split(right) is not None and self._may_follow(left, right)
            self.n_beside += 1
        return known

    def _may_follow(self, left: int, right: int) -> bool:
        # the merge across the border must come before all that was undone so far
        tokens, ranks, bound = self.tokens, self.ranks, 1 << 40
        while True:
            across = ranks.get(tokens[left] + tokens[right])
            if across is not None and across < bound:
                return False
            one_left, one_right = len(tokens[left]) == 1, len(tokens[right]) == 1
            if one_left and one_right:
                return True
            # of equal merges the one further left comes first, so the right one is undone first
            if one_left or (not one_right and right >= left):
                bound, right = right + 1, self.split(right)[0]
            else:
                bound, left = left, self.split(left)[1]

    def encode_piece(self, piece: bytes) -> list[int]:
        """The tokens of one match of the pattern."""
        whole = self.ranks.get(piece)
        return [whole] if whole is not None else PrefixTable(self, piece).tokens()


class PrefixTable:
    """Bytes with the last token of the valid encoding of each prefix."""

    def __init__(self, vocabulary: Vocabulary, data: bytes = b"") -> None:
        self.vocabulary, self.data = vocabulary, b""
        self.last: list[int | None] = [-1]
        self.append(data)

    def _fill(self, first: int, stop: int) -> None:
        """Fills open (None) entries with the tokens that begin at each place from first to stop; the first that is valid is the longest."""
        vocabulary, data, last, n = self.vocabulary, self.data, self.last, len(self.data)
        root, beside = vocabulary.root, vocabulary.beside
        for begin in range(first, stop):
            node, i, before = root, begin, last[begin]
            known = beside[before]
            while i < n:
                found = node.get(data[i])
                if found is None:
                    break
                node, token = found
                i += 1
                if token >= 0 and last[i] is None:
                    if begin:
                        fits = known.get(token)
                        if fits is None:
                            fits = vocabulary.may_follow(before, token)
                    else:
                        fits = vocabulary.split(token) is not None
                    if fits:
                        last[i] = token

    def append(self, data: bytes) -> None:
        """Adds bytes; the stored entries stay as they are."""
        n, self.data = len(self.data), self.data + data
        self.last += [None] * len(data)
        self._fill(max(0, n - self.vocabulary.longest + 1) if n else 0, len(self.data))

    def replace(self, begin: int, end: int, data: bytes) -> int:
        """Replaces bytes; returns how many entries had to be computed."""
        old, shift, n, longest = self.last, len(data) - (end - begin), len(self.data), self.vocabulary.longest
        self.data = self.data[:begin] + data + self.data[end:]
        self.last = old[: begin + 1] + [None] * (len(self.data) - begin)
        agreed, computed = 0, 0
        for at in range(max(0, begin - longest + 1), len(self.data)):
            self._fill(at, at + 1)
            if at < begin:
                continue
            # entry at + 1 is settled now
            computed += 1
            i = at + 1
            agreed = agreed + 1 if i - shift > end and self.last[i] == old[i - shift] else 0
            if agreed >= longest and i >= begin + len(data):
                self.last[i + 1 :] = old[i + 1 - shift : n + 1]
                break
        return computed

    def tokens(self) -> list[int]:
        out, i = [], len(self.data)
        while i:
            out.append(self.last[i])
            i -= len(self.vocabulary.tokens[out[-1]])
        return out[::-1]


class Encoder:
    """Whole texts: each match of a pattern by itself, with caches."""

    def __init__(self, tokens: list[bytes], pattern: str) -> None:
        self.vocabulary = Vocabulary(tokens)
        pattern = pattern.replace(r"(?!\S)", rf"(?![^{WHITE_SPACE}])")
        self.matches = regex.compile(pattern.replace(r"[^\s", f"[^{WHITE_SPACE}").replace(r"\s", f"[{WHITE_SPACE}]"))
        #: A space that follows a space, or is followed by white space: there the text can't be cut.
        self.uncut = regex.compile(rf" [{WHITE_SPACE}]| $")
        self.pieces: dict[str, list[int]] = {}
        #: Words with the space before them: the younger generation, and the one before it.
        self.units: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}

    def _of(self, text: str) -> list[int]:
        out: list[int] = []
        for piece in self.matches.findall(text):
            ids = self.pieces.get(piece)
            if ids is None:
                if len(self.pieces) >= CACHE:
                    self.pieces.clear()
                ids = self.vocabulary.encode_piece(piece.encode())
                if len(piece) <= 64:
                    self.pieces[piece] = ids
            out += ids
        return out

    def encode(self, text: str) -> np.ndarray:
        """Ids of a text. It is cut before single spaces, where a match always begins, so that words are looked up whole."""
        if self.uncut.search(text):
            return np.array(self._of(text), np.int32)
        first, *rest = text.split(" ")
        found, units = list(map(self.units.get, rest)), self.units
        if None in found:
            for k, ids in enumerate(found):
                if ids is None:
                    word = rest[k]
                    ids = units.get(word)
                    if ids is None:
                        ids = self.older.get(word)
                        if ids is None:
                            ids = array("i", self._of(" " + word)).tobytes()
                        if len(word) <= 64:
                            units[word] = ids
                    found[k] = ids
            if len(units) >= CACHE:
                self.older, self.units = units, {}
        return np.concatenate([np.array(self._of(first), np.int32), np.frombuffer(b"".join(found), np.int32)])


class TokenBytes:
    """The bytes of all tokens in one array."""

    def __init__(self, tokens: list[bytes]) -> None:
        self.data, self.lengths = np.frombuffer(b"".join(tokens), np.uint8), np.array([len(t) for t in tokens], np.int64)
        self.starts = np.cumsum(self.lengths) - self.lengths

    def join(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bytes of tokens one after another, and where each begins, with the end."""
        lengths = self.lengths[ids]
        at = np.zeros(len(ids) + 1, np.int64)
        np.cumsum(lengths, out=at[1:])
        return self.data[np.arange(at[-1]) + np.repeat(self.starts[ids] - at[:-1], lengths)], at


@functools.lru_cache(maxsize=4)
def token_bytes(path: str) -> TokenBytes:
    return TokenBytes(read_ranks(path))


@functools.lru_cache(maxsize=4)
def encoder(path: str, pattern: str) -> Encoder:
    """One for each file and pattern in a Python process."""
    return Encoder(read_ranks(path), pattern)


def encode(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: its id and ``ids array<int>``. The vocabulary file must be at the path on every executor. No shuffle."""
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(path, pattern)
        for batch in batches:
            for part in (batch.slice(i, 500) for i in range(0, len(batch), 500)):
                ids = [own.encode(x) if x else np.zeros(0, np.int32) for x in part.column(1).to_pylist()]
                offsets = np.cumsum([0, *map(len, ids)], dtype=np.int32)
                lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(ids) if ids else np.zeros(0, np.int32)))
                yield pa.RecordBatch.from_arrays([part.column(0), lists], [id_col, "ids"])

    return source.mapInArrow(run, f"`{id_col}` {source.schema['id'].dataType.simpleString()}, ids array<int>")


def decode(encoded: DataFrame, path: str, id_col: str = "doc_id") -> DataFrame:
    """Adds ``decoded binary``, the bytes of ``ids``; null ids give no bytes. No shuffle."""
    source = encoded.select(id_col, "ids")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = token_bytes(path)
        for batch in batches:
            for part in (batch.slice(i, 500) for i in range(0, len(batch), 500)):
                lists = part.column(1)
                ends = np.cumsum([0, *lists.value_lengths().fill_null(0).to_pylist()])
                data, at = table.join(lists.flatten().to_numpy())
                offsets = pa.py_buffer(at[ends].astype(np.int64))
                found = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(part), [None, offsets, pa.py_buffer(data)]).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([*part.columns, found], [id_col, "ids", "decoded"])

    return source.mapInArrow(run, f"`{id_col}` {source.schema[id_col].dataType.simpleString()}, ids array<int>, decoded binary")
