r"""Token counts of fields or sections by offset-mapped attribution.

A document's fields are joined by a separator and encoded once, as a whole. The byte
span of every token follows from the tokens' lengths, and an interval join with the spans
of the sections (sorted positions, by binary search) gives each token its sections. A
token that crosses a border is allocated by rule: "first" gives it to the section of
its first byte (the default), "last" to that of its last byte, "split" to each section by
the share of its bytes.

Sections are the fields themselves, or the lines of the joined text. A line owns the line
break that ends it, a field the separator after it, so the sections cover everything and
the counts add up to the document's tokens. Defined results: null fields are empty; an empty
document has its sections with no tokens; sections without bytes get none; rows are handled
one by one, whatever their ids; an empty table gives an empty result; only the id and the
named fields are read. Memory is bounded by a batch, the longest text and the encoder's caches.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bpe

RULES = ("first", "last", "split")


def attribute(token_ends: np.ndarray, section_ends: np.ndarray, rule: str = "first") -> tuple[np.ndarray, np.ndarray]:
    """Tokens of each section, and how many of them begin there and end in a later one.

    Both arrays hold ascending byte positions; spans lie end to end from 0.
    """
    if rule not in RULES:
        raise ValueError(f"rule is one of {RULES}")
    n, starts = len(section_ends), np.concatenate([[0], token_ends[:-1]]) if len(token_ends) else token_ends
    first, last = np.searchsorted(section_ends, starts, "right"), np.searchsorted(section_ends, token_ends, "left")
    crossing = np.bincount(first[first < last], minlength=n)
    if rule != "split":
        return np.bincount(first if rule == "first" else last, minlength=n).astype(float), crossing
    counts = np.bincount(first[first == last], minlength=n).astype(float)
    for k in np.flatnonzero(first < last):
        edges = np.concatenate([[starts[k]], section_ends[first[k] : last[k]], [token_ends[k]]])
        counts[first[k] : last[k] + 1] += np.diff(edges) / (token_ends[k] - starts[k])
    return counts, crossing


def count(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", fields: list[str] | None = None, by_line: bool = True, separator: str = "\n", rule: str = "first") -> DataFrame:
    """One row per section: the id, ``section`` (its number), ``n_bytes``, ``n_tokens`` (double for "split") and ``n_crossing``. No shuffle."""
    fields = fields or ["text"]
    source = docs.select(F.col(id_col).alias("id"), *(F.coalesce(F.col(f"`{f}`").cast("string"), F.lit("")).alias(f"f{k}") for k, f in enumerate(fields)))
    gap = separator.encode()
    names = [id_col, "section", "n_bytes", "n_tokens", "n_crossing"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, lengths = bpe.encoder(path, pattern), bpe.token_bytes(path).lengths
        for batch in batches:
            for part in (batch.slice(i, 200) for i in range(0, len(batch), 200)):
                found: list[tuple] = []
                for values in zip(*(c.to_pylist() for c in part.columns[1:]), strict=True):
                    text = separator.join(values)
                    data = text.encode()
                    if by_line:
                        ends = np.append(np.flatnonzero(np.frombuffer(data, np.uint8) == 10) + 1, len(data))
                    else:
                        ends = np.cumsum([len(v.encode()) + len(gap) for v in values])
                        ends[-1] -= len(gap)
                    found.append((ends, *attribute(np.cumsum(lengths[own.encode(text)]) if text else np.zeros(0, np.int64), ends, rule)))
                n = [len(f[0]) for f in found]
                flat = lambda k: np.concatenate([f[k] for f in found])
                sizes = np.concatenate([np.diff(f[0], prepend=0) for f in found])
                tokens = flat(1) if rule == "split" else flat(1).astype(np.int64)
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(np.repeat(np.arange(len(n)), n))), pa.array(np.concatenate([np.arange(k) for k in n])), pa.array(sizes), pa.array(tokens), pa.array(flat(2))], names)

    return source.mapInArrow(run, f"`{id_col}` {source.schema['id'].dataType.simpleString()}, section long, n_bytes long, n_tokens {'double' if rule == 'split' else 'long'}, n_crossing long")
