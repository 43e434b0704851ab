"""Repetition coverage: how much of a text lies inside n-grams and lines that it repeats.

For each n-gram length one rolling hash over the word hashes finds the n-grams that occur twice or more, and the
characters of the words under their copies are summed; equal lines are counted beside them. Copies are those after the first, so
a share says what the text could do without; a text whose copies are fewer words than copy_words, such as one short line
said twice, is left alone whatever its length. One pass in numpy per text, map-only: no shuffle, memory bounded by one Arrow batch.

Defined results: a null or empty text has no words, so zero in every count, and fails (fewer than min_words words).
Repeated rows give repeated results. Columns of the input other than the id are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import roll, trimmed, word_bounds, word_hashes

#: Characters that count as symbols.
SYMBOLS = b"#*$%&|<>"
#: The largest share of characters inside copies of n-grams, after the first, that a kept text may have, by n: half of the usual
#: 0.15 to 0.10, which count the first as well.
NGRAM_LIMITS = {5: 0.075, 6: 0.07, 7: 0.065, 8: 0.06, 9: 0.055, 10: 0.05}
#: The same for characters inside repeated lines (copies after the first): half of the usual 0.20.
LINE_LIMIT = 0.10
#: Copies of fewer words in all don't count.
COPY_WORDS = 10

_SYMBOL = np.zeros(256, dtype=bool)
_SYMBOL[list(SYMBOLS)] = True


@dataclass
class RepetitionRules:
    """base_*: the plain rules every text must pass; ngram_limits and line_limit: the coverage rules."""

    min_words: int = 10
    base_ngram: int = 5
    base_repeat_percent: int = 20
    ngram_limits: dict[int, float] = field(default_factory=lambda: dict(NGRAM_LIMITS))
    line_limit: float = LINE_LIMIT
    copy_words: int = COPY_WORDS


def _under(places: np.ndarray, n: int, size: int) -> np.ndarray:
    """Mask of the words under the n-grams at these places."""
    edge = np.zeros(size + 1, dtype=np.int64)
    np.add.at(edge, places, 1)
    np.add.at(edge, places + n, -1)
    return np.cumsum(edge[:-1]) > 0


def _covered(words: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray] | None:
    """Masks of the words inside n-grams found twice or more, and inside their copies after the first; None if there are none."""
    grams = roll(words, n)
    if len(grams) < 2:
        return None
    ranked = np.sort(grams)
    twice = ranked[1:][ranked[1:] == ranked[:-1]]
    if not len(twice):
        return None
    at = np.searchsorted(twice, grams)
    places = np.flatnonzero(twice[np.minimum(at, len(twice) - 1)] == grams)
    order = np.argsort(grams[places], kind="stable")
    same = grams[places[order]]
    return _under(places, n, len(words)), _under(places[order[1:][same[1:] == same[:-1]]], n, len(words))


def measure(text: bytes, rules: RepetitionRules) -> tuple:
    """Counts and verdict of one UTF-8 text: n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, shares, verdicts."""
    raw = np.frombuffer(text, dtype=np.uint8)
    starts, ends = word_bounds(raw)
    n = len(starts)
    if not n:
        return 0, 0, int(_SYMBOL[raw].sum()), 0, 0, 0.0, 0.0, True, False
    points = np.zeros(len(raw) + 1, dtype=np.int64)
    np.cumsum((raw & 0xC0) != 0x80, out=points[1:])
    chars = points[ends] - points[starts]
    total = int(chars.sum())
    words = word_hashes(raw, starts, ends)
    seen: set[bytes] = set()
    dup_lines = dup_chars = dup_words = 0
    if b"\n" in text:
        at = 0
        for line in text.split(b"\n"):
            if line in seen:
                lo, hi = np.searchsorted(starts, (at, at + len(line)))
                if hi > lo:
                    dup_lines += 1
                    dup_chars += int(chars[lo:hi].sum())
                    dup_words += int(hi - lo)
            else:
                seen.add(line)
            at += len(line) + 1
    repeat_words, worst, verdict = 0, 0.0, dup_words < rules.copy_words or dup_chars <= rules.line_limit * total
    lengths = sorted({rules.base_ngram, *rules.ngram_limits})
    for k in lengths:
        found = _covered(words, k)
        if found is None:
            break  # a repeated (k+1)-gram would hold repeated k-grams
        every, copies = found
        if k == rules.base_ngram:
            repeat_words = int(every.sum())
        if k in rules.ngram_limits:
            share = float(chars[copies].sum()) / total
            worst = max(worst, share)
            verdict &= copies.sum() < rules.copy_words or share <= rules.ngram_limits[k]
    failed = n < rules.min_words or 100 * repeat_words > rules.base_repeat_percent * n
    return n, total, int(_SYMBOL[raw].sum()), dup_lines, repeat_words, worst, dup_chars / total, failed, not failed and bool(verdict)


_FIELDS = (
    ("n_words", pa.int64()), ("word_chars", pa.int64()), ("n_symbols", pa.int64()), ("n_dup_lines", pa.int64()),
    ("n_repeat_words", pa.int64()), ("max_ngram_share", pa.float64()), ("dup_line_share", pa.float64()),
    ("base_failed", pa.bool_()), ("kept", pa.bool_()),
)
_DDL = ", ".join(f"{name} {'long' if kind == pa.int64() else 'double' if kind == pa.float64() else 'boolean'}" for name, kind in _FIELDS)


def repetition_profile(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", rules: RepetitionRules | None = None) -> DataFrame:
    """One row per document: the id and the columns of _FIELDS."""
    rules = rules or RepetitionRules()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [measure(x or b"", rules) for x in batch.column(1).cast(pa.binary()).to_pylist()]
            columns = zip(*rows, strict=True) if rows else ((),) * len(_FIELDS)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array(c, kind) for c, (_, kind) in zip(columns, _FIELDS, strict=True))],
                names=[id_col, *(name for name, _ in _FIELDS)],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(trimmed(run), f"`{id_col}` {kind}, {_DDL}")


def filter_repetitive(docs: DataFrame, *, text_col: str = "text", rules: RepetitionRules | None = None) -> DataFrame:
    """The rows of docs whose text is kept, with all their columns, in one map-only pass."""
    rules = rules or RepetitionRules()
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array([measure(x or b"", rules)[-1] for x in batch.column(at).cast(pa.binary()).to_pylist()], pa.bool_()))

    return docs.mapInArrow(trimmed(run), docs.schema)
