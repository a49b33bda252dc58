"""Quality rules by repetition coverage (operator 7).

Rolling hashes of several n-gram lengths mark the characters that lie inside n-grams
found more than once in their text, and inside repeated lines. Everything is computed in
one pass over a text in numpy; no rows move between tasks.

Defined cases: a null or empty text has no words and fails the base rule; equal rows give
equal results; columns other than the id and the text are not read, so their names cannot
clash; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.llm.common import id_text, slices, small, utf8
from corpuskit.llm.shingles import run_hashes, window_hashes, word_bounds


@dataclass(frozen=True)
class RepetitionRules:
    """Bounds of the verdict.

    ``top`` gives, for short n-grams, the largest share of word characters inside the
    single most covering n-gram; ``duplicate`` gives, for longer n-grams, the largest share
    inside any n-gram found twice or more. ``line_chars`` bounds the share of characters
    inside repeated lines, ``symbols`` the symbols for each word.
    """

    min_words: int = 20
    max_repeat_words: float = 0.30
    top: dict[int, float] = field(default_factory=lambda: {2: 0.20, 3: 0.18, 4: 0.16})
    duplicate: dict[int, float] = field(default_factory=lambda: {5: 0.30, 6: 0.29, 7: 0.28, 8: 0.27, 9: 0.26, 10: 0.25})
    line_chars: float = 0.30
    symbols: float = 0.50


SCHEMA = (
    "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, "
    "base_failed boolean, top_share double, dup_share double, dup_line_share double, kept boolean"
)
BASE_N = 8
_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True


def _covered(n_words: int, starts: np.ndarray, n: int) -> np.ndarray:
    """Which words lie inside one of the windows of ``n`` words that begin at ``starts``."""
    edge = np.zeros(n_words + 1, np.int32)
    np.add.at(edge, starts, 1)
    np.add.at(edge, np.minimum(starts + n, n_words), -1)
    return np.cumsum(edge[:-1]) > 0


def _repeats(hashes: np.ndarray) -> tuple[np.ndarray, int]:
    """Sorted hashes that occur twice or more, and how often the most frequent one does."""
    order = np.sort(hashes)
    same = order[1:] == order[:-1]
    if not same.any():
        return order[:0], 1
    ends = np.flatnonzero(np.concatenate((~same, [True])))
    runs = np.diff(ends, prepend=-1)
    return order[ends[runs > 1]], int(runs.max())


def _places(hashes: np.ndarray, among: np.ndarray) -> np.ndarray:
    """Where ``hashes`` holds a value of the sorted array ``among``."""
    at = np.minimum(np.searchsorted(among, hashes), len(among) - 1)
    return np.flatnonzero(among[at] == hashes)


def measure(words: np.ndarray, lengths: np.ndarray, rules: RepetitionRules) -> tuple[int, float, float]:
    """Words inside repeated base windows; the top and the duplicate shares relative to their bounds.

    A text without a repeated n-gram has no longer one either, which ends the loop early. A
    top share is worked out only where count times the longest gram could pass the bound;
    it is 0 otherwise.
    """
    n, total = len(words), int(lengths.sum())
    repeated, top, dup = 0, 0.0, 0.0
    longest = int(lengths.max()) if n else 0
    for k in sorted({*rules.top, *rules.duplicate, BASE_N}):
        if n <= k:
            break
        hashes = window_hashes(words, k)
        again, most = _repeats(hashes)
        if not len(again):
            break
        if k in rules.top and most * k * longest > rules.top[k] * total:
            bound = rules.top[k]
            at = _places(hashes, again)
            group = np.searchsorted(again, hashes[at])
            weight = np.convolve(lengths, np.ones(k, lengths.dtype), "valid")[at]
            most_chars = np.bincount(group, weights=weight)
            for g in np.argsort(-most_chars, kind="stable"):
                # characters times count bounds what a gram covers
                if most_chars[g] <= max(bound, top * bound) * total:
                    break
                share = lengths[_covered(n, at[group == g], k)].sum() / total
                top = max(top, share / bound)
        if k in rules.duplicate or k == BASE_N:
            covered = _covered(n, _places(hashes, again), k)
            if k == BASE_N:
                repeated = int(covered.sum())
            if k in rules.duplicate:
                dup = max(dup, lengths[covered].sum() / total / rules.duplicate[k])
    return repeated, top, dup


def _line_repeats(text: str, wordless: str = "\x20\t\n\x0b\x0c\r") -> tuple[int, float]:
    """Lines with a word that equal an earlier line, and the share of characters in them."""
    seen: set[str] = set()
    n = chars = total = 0
    for line in text.split("\n"):
        if line.strip(wordless):
            total += len(line)
            if line in seen:
                n += 1
                chars += len(line)
            else:
                seen.add(line)
    return n, chars / total if total else 0.0


def score_batches(batches: Iterator[pa.RecordBatch], rules: RepetitionRules) -> Iterator[pa.RecordBatch]:
    for batch in small(batches, 2048):
        ids, texts = batch.column(0), batch.column(1)
        data, offsets = utf8(texts)
        rows = []
        for i, j in slices(offsets):
            part, at = data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
            starts, ends, first = word_bounds(part, at)
            hashes = run_hashes(part, starts, ends)
            points = np.concatenate(([0], np.cumsum((part & 0xC0) != 0x80)))
            lengths = points[ends] - points[starts]
            symbols = np.concatenate(([0], np.cumsum(_SYMBOL[part])))
            for k in range(j - i):
                a, b = first[k], first[k + 1]
                own = lengths[a:b]
                n, n_symbols = int(b - a), int(symbols[at[k + 1]] - symbols[at[k]])
                repeated, top, dup = measure(hashes[a:b], own, rules)
                lines, line_share = _line_repeats(texts[i + k].as_py()) if n else (0, 0.0)
                failed = n < rules.min_words or 100 * repeated > round(100 * rules.max_repeat_words) * n
                kept = not (failed or top > 1 or dup > 1 or line_share > rules.line_chars or n_symbols > rules.symbols * n)
                rows.append((n, int(own.sum()), n_symbols, lines, repeated, failed, top, dup, line_share, kept))
        columns = list(zip(*rows, strict=True)) if rows else [[] for _ in range(10)]
        kinds = [pa.int64()] * 5 + [pa.bool_()] + [pa.float64()] * 3 + [pa.bool_()]
        names = [x.split()[0] for x in SCHEMA.split(", ")]
        yield pa.RecordBatch.from_arrays([ids, *(pa.array(list(c), t) for c, t in zip(columns, kinds, strict=True))], names)


def repetition_quality(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: RepetitionRules | None = None) -> DataFrame:
    """One row for each row of ``df``: base counts, coverage shares relative to their bounds, verdict."""
    rules = rules or RepetitionRules()
    return id_text(df, id_col, text_col).mapInArrow(lambda batches: score_batches(batches, rules), SCHEMA)


def keep_good(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: RepetitionRules | None = None) -> DataFrame:
    """Rows of ``df`` that the rules keep, all columns as they were; decided row by row, without a join."""
    rules = rules or RepetitionRules()
    names = df.columns
    place, body = names.index(id_col), names.index(text_col)

    def kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches, 2048):
            two = pa.RecordBatch.from_arrays([batch.column(place), batch.column(body)], ["doc_id", "text"])
            for verdict in score_batches(iter([two]), rules):
                yield batch.filter(verdict.column(verdict.num_columns - 1))

    return df.mapInArrow(kept, df.schema)


def base_sql(documents: str = "documents") -> str:
    """The base columns in DuckDB SQL, for tests on small tables."""
    return rf"""
    WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM {documents}),
    w AS (SELECT doc_id, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS words FROM t),
    spans AS (SELECT doc_id, i, list_slice(words, i, i + {BASE_N - 1}) AS win
              FROM (SELECT doc_id, words, unnest(range(1, len(words) - {BASE_N - 2})) AS i FROM w)),
    twice AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, win) AS n FROM spans) WHERE n > 1),
    covered AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + {BASE_N})) AS p FROM twice) GROUP BY doc_id),
    lines AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n
              FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM t)
              WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY doc_id)
    SELECT w.doc_id, len(words)::BIGINT AS n_words,
           coalesce(list_sum(list_transform(words, lambda x: length(x))), 0)::BIGINT AS word_chars,
           len(regexp_extract_all(text, '[#*$%&|<>]'))::BIGINT AS n_symbols,
           coalesce(lines.n, 0)::BIGINT AS n_dup_lines, coalesce(covered.n, 0)::BIGINT AS n_repeat_words
    FROM w LEFT JOIN lines USING (doc_id) LEFT JOIN covered USING (doc_id)"""


def digest(df: DataFrame) -> DataFrame:
    """The columns of the registered query."""
    return repetition_quality(df).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept",
        F.round("dup_share", 6).alias("dup_share"),
    )
