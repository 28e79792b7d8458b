"""Quality rules: repetition coverage by rolling hashes of several n-gram lengths.

A slice of texts becomes one byte array; word, n-gram and line hashes come from prefix sums
over it, so that no Python loop runs over words. For each n-gram length the measure is the
share of a text's word characters that lie inside n-grams seen before in that text, and for
lines the share inside lines seen before. A text is kept if no base rule fails and every
share is at most its limit.

Defined cases: a null text has no words and fails; repeated rows each get their row; a text of
separators only has no words; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from . import common

#: n-gram length: largest share of word characters, in hundredths, inside n-grams seen before.
NGRAM_LIMITS = {5: 15, 7: 13, 10: 10}
#: Largest share of characters, in hundredths, inside lines seen before.
LINE_LIMIT = 20
WINDOW, LEAST_WORDS, MOST_REPEATED = 8, 20, 30

_SYMBOLS = np.zeros(256, bool)
_SYMBOLS[list(b"#*$%&|<>")] = True
_STARTS_POINT = (np.arange(256) & 0xC0) != 0x80

COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", *(f"dup_chars_{n}" for n in NGRAM_LIMITS), "dup_line_chars"]
SCHEMA = ", ".join(f"{c} long" for c in COUNTS)


def _spread(first: np.ndarray, length: int, n: int) -> np.ndarray:
    """Whether each of n places lies in a run of so many that begins at one of first."""
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, first, 1)
    np.subtract.at(edge, np.minimum(first + length, n), 1)
    return np.cumsum(edge[:n]) > 0


def measure(data: np.ndarray, where: np.ndarray) -> dict[str, np.ndarray]:
    """COUNTS of each text, for texts laid end to end that begin at where."""
    rows = len(where) - 1
    starts, stops = common.word_runs(data, where)
    points = np.zeros(len(data) + 1, np.int64)
    np.cumsum(_STARTS_POINT[data], out=points[1:])
    chars = points[stops] - points[starts]
    bounds = np.searchsorted(starts, where)
    text_of = np.repeat(np.arange(rows), np.diff(bounds))
    salt = common.mix(np.arange(1, rows + 1, dtype=np.uint64))
    hashed = common.RunHash(common.BYTE_WORDS[data])
    words = common.RunHash(hashed(starts, stops))
    out = {"n_words": np.diff(bounds), "word_chars": common.per_row(chars, bounds), "n_symbols": common.per_row(_SYMBOLS[data], where)}

    def windows(n: int) -> tuple[np.ndarray, np.ndarray]:
        first = np.flatnonzero(np.arange(n, len(starts) + n) <= bounds[text_of + 1])
        return first, words(first, first + n) ^ salt[text_of[first]]

    first, keys = windows(WINDOW)
    out["n_repeat_words"] = common.per_row(_spread(first[common.repeats(keys)[0]], WINDOW, len(starts)), bounds)
    for n in NGRAM_LIMITS:
        first, keys = windows(n)
        inside = _spread(first[common.repeats(keys)[1]], n, len(starts))
        out[f"dup_chars_{n}"] = common.per_row(np.where(inside, chars, 0), bounds)

    begins = np.unique(np.concatenate([where[:-1], np.flatnonzero(data == 10) + 1]))
    begins = begins[begins < len(data)]
    ends = np.append(begins[1:], len(data))
    text_of = np.searchsorted(where, begins, "right") - 1
    ends = ends - (data[ends - 1] == 10) if len(ends) else ends
    worded = np.searchsorted(starts, ends) > np.searchsorted(starts, begins)
    begins, ends, text_of = begins[worded], ends[worded], text_of[worded]
    again = common.repeats(hashed(begins, ends) ^ salt[text_of])[1]
    bounds = np.searchsorted(begins, where)
    out["n_dup_lines"] = common.per_row(again, bounds)
    out["dup_line_chars"] = common.per_row(np.where(again, points[ends] - points[begins], 0), bounds)
    return out


def verdict(m: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(base_failed, kept) of each text."""
    failed = (m["n_words"] < LEAST_WORDS) | (100 * m["n_repeat_words"] > MOST_REPEATED * m["n_words"])
    kept = ~failed & (100 * m["dup_line_chars"] <= LINE_LIMIT * m["word_chars"])
    for n, limit in NGRAM_LIMITS.items():
        kept &= 100 * m[f"dup_chars_{n}"] <= limit * m["word_chars"]
    return failed, kept


def _map(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in common.slices(batches, "text"):
        m = measure(*common.text_bytes(common.column(part, "text")))
        failed, kept = verdict(m)
        yield pa.RecordBatch.from_arrays([common.column(part, "doc_id"), *(pa.array(m[c], pa.int64()) for c in COUNTS), pa.array(failed), pa.array(kept)], ["doc_id", *COUNTS, "base_failed", "kept"])


def assess(docs: DataFrame) -> DataFrame:
    """doc_id, COUNTS, base_failed and kept of each row of docs (doc_id, text)."""
    return docs.select("doc_id", "text").mapInArrow(_map, f"doc_id long, {SCHEMA}, base_failed boolean, kept boolean")


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assess(common.documents(spark, sf_dir))
