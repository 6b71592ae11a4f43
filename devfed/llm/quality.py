r"""Quality rules by repetition coverage.

Rolling hashes of all windows of several lengths and hashes of all lines show which
windows and lines occur again in their own text. A text is judged by the share of
its characters (code points in words) that lie in repeated windows, all occurrences
counted, and in lines that repeat an earlier one.

A word is ``[^\x20\x09-\x0D]+``. Defined results: a null or empty text has zeros and
fails the base rule (fewer than 50 words); rows with equal ids are judged one by one;
an empty table gives an empty result; columns other than id and text are not read by
``measure`` and pass through ``keep_good`` unchanged, whatever their names. Memory
is bounded by a slice of 4 MB or the longest text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textnp

#: Window lengths in words, with the largest share in percent of a text's characters
#: that windows of that length found twice or more may hold. They are the limits
#: published for large web corpora: longer repeats are tolerated less.
WINDOW_LIMITS = {5: 15, 6: 14, 7: 13, 8: 12, 9: 11, 10: 10}
#: The same for lines equal to an earlier line, as published for characters.
LINE_LIMIT = 20
#: Base rule: least words, and the largest share in percent of words in repeated 3-word windows.
LEAST_WORDS, BASE_WINDOW, BASE_LIMIT = 50, 3, 50

SYMBOLS = "#*$%&|<>"
_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in SYMBOLS]] = True


def _twice(keys: np.ndarray) -> np.ndarray:
    """Flags of values found twice or more."""
    order = np.argsort(keys)
    same = np.concatenate([[False], keys[order][1:] == keys[order][:-1], [False]])
    out = np.zeros(len(keys), bool)
    out[order] = (same[1:] | same[:-1])[: len(keys)]
    return out


def _later(keys: np.ndarray) -> np.ndarray:
    """Flags of values that equal an earlier one."""
    out = np.ones(len(keys), bool)
    out[np.unique(keys, return_index=True)[1]] = False
    return out


def _covered(at: np.ndarray, n: int, n_words: int) -> np.ndarray:
    """Flags of the words in any window of n words that begins at one of the places."""
    begun = np.zeros(n_words + 1, np.int64)
    begun[at + 1] = 1
    begun = np.cumsum(begun)
    return begun[1:] > begun[np.maximum(np.arange(n_words) - n + 1, 0)]


def judge(t: textnp.Texts, window_limits: dict[int, int] | None = None, line_limit: int = LINE_LIMIT) -> dict[str, np.ndarray]:
    """The figures and the verdict of each text."""
    limits, words = window_limits or WINDOW_LIMITS, t.words()
    if min(limits) < BASE_WINDOW:
        raise ValueError(f"window lengths start at {BASE_WINDOW} words")
    points = (t.data & 0xC0) != 0x80
    per_word = textnp._prefix((points & t.in_word).astype(np.int64))
    chars, total = per_word[t.ends] - per_word[t.starts], np.diff(per_word[t.offsets])
    by_text = lambda flags, weights=None: np.bincount(t.doc[flags], weights[flags] if weights is not None else None, t.n).astype(np.int64)

    starts, ends, doc = t.lines()
    with_word = per_word[ends] > per_word[starts]
    starts, ends, doc = starts[with_word], ends[with_word], doc[with_word]
    later = _later(textnp.keyed(t.span_hashes(starts, ends), doc))
    out = {"word_chars": total, "n_symbols": t.per_text(_SYMBOL[t.data]), "n_dup_lines": np.bincount(doc[later], minlength=t.n).astype(np.int64)}
    dup_line_chars = np.bincount(doc[later], (per_word[ends] - per_word[starts])[later], t.n).astype(np.int64)
    good = 100 * dup_line_chars <= line_limit * total
    windows, at = textnp.Windows(words, t.doc), None
    for n in sorted({BASE_WINDOW, *limits}):
        # a window that occurs again begins with a shorter one that does
        at, hashes = windows.of(n, at)
        at = at[_twice(textnp.keyed(hashes, t.doc[at]))]
        covered = _covered(at, n, len(words))
        if n == BASE_WINDOW:
            out["n_repeat_words"] = by_text(covered)
        if n in limits:
            out[f"dup_chars_{n}"] = by_text(covered, chars)
            good &= 100 * out[f"dup_chars_{n}"] <= limits[n] * total
    failed = (t.n_words < LEAST_WORDS) | (100 * out["n_repeat_words"] > BASE_LIMIT * t.n_words)
    return {"n_words": t.n_words.astype(np.int64), **out, "dup_line_chars": dup_line_chars, "base_failed": failed, "kept": good & ~failed}


def measure(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window_limits: dict[int, int] | None = None, line_limit: int = LINE_LIMIT) -> DataFrame:
    """One row per row of ``docs``: its id, all figures, ``base_failed`` and ``kept``. No shuffle."""
    limits = window_limits or WINDOW_LIMITS
    counts = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", *(f"dup_chars_{n}" for n in limits), "dup_line_chars"]
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, texts in textnp.slices(batch.column(1)):
                found = judge(texts, limits, line_limit)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), *(pa.array(found[c]) for c in [*counts, "base_failed", "kept"])], [id_col, *counts, "base_failed", "kept"])
        textnp.release()

    kind = source.schema["id"].dataType.simpleString()
    return source.mapInArrow(run, f"`{id_col}` {kind}, {', '.join(f'{c} long' for c in counts)}, base_failed boolean, kept boolean")


def keep_good(docs: DataFrame, text_col: str = "text", window_limits: dict[int, int] | None = None, line_limit: int = LINE_LIMIT) -> DataFrame:
    """The rows of ``docs`` that ``measure`` keeps, with all their columns."""
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kept = [judge(texts, window_limits, line_limit)["kept"] for _, _, texts in textnp.slices(batch.column(at))]
            if kept:
                yield batch.filter(pa.array(np.concatenate(kept)))
        textnp.release()

    return docs.mapInArrow(run, docs.schema)
