"""Token counts of fields or sections, from one encoding of the whole document (operator 1).

A document is encoded once. The bytes of its tokens give the character span of each, and
an interval join of those spans with the spans of the sections (both sorted, inside the
row) tells where each token lies. A token that crosses a boundary is allocated by rule:

``first``     to the section that holds its first byte,
``last``      to the section that holds its last byte,
``majority``  to the section that holds most of its bytes, the first one on a tie,
``split``     to each by its share of the token's bytes.

Without spans of the caller, the sections are the lines of the text, each with the line
feed that ends it. Tokens outside all spans count for no section.

Defined cases: a null or empty text has one empty section and no tokens; empty spans count
no tokens; spans may come in any order, leave gaps and overlap, and a token then counts for
each of the spans that overlap there, by the rule; a span with a null bound, a null span or
one that ends before it begins is an empty span at its start (or at 0); equal rows give
equal results; other columns are not read; an empty table gives an empty result.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.llm.byte_bpe import byte_bpe
from corpuskit.llm.common import id_text, small, utf8
from corpuskit.llm.word_tokens import vocabulary_path

RULES = ("first", "last", "majority", "split")


def line_spans(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Byte spans of the lines of a text, line feeds included; one empty span for an empty text."""
    ends = np.flatnonzero(data == 10) + 1
    if not len(ends) or ends[-1] != len(data):
        ends = np.append(ends, len(data))
    return np.concatenate(([0], ends[:-1])), ends


def allocate(starts: np.ndarray, ends: np.ndarray, first: np.ndarray, last: np.ndarray, rule: str) -> tuple[np.ndarray, np.ndarray]:
    """Tokens ``[starts, ends)`` for each span ``[first, last)``, and how many of them cross one of its bounds."""
    n = len(first)
    filled = np.flatnonzero(last > first)
    counts, crossing = np.zeros(n), np.zeros(n, np.int64)
    if not len(starts) or not len(filled):
        return counts, crossing
    lo, hi = first[filled], last[filled]
    a = np.searchsorted(hi, starts, "right")  # first span that ends behind the token's start
    b = np.searchsorted(lo, ends - 1, "right") - 1  # last span that begins at or before its last byte
    whole = (a == b) & (lo[np.minimum(a, len(lo) - 1)] <= starts) & (hi[np.minimum(a, len(lo) - 1)] >= ends)
    counts += np.bincount(filled[a[whole]], minlength=n)
    for t in np.flatnonzero(~whole & (a <= b)):
        spans = np.arange(a[t], b[t] + 1)
        shared = np.minimum(hi[spans], ends[t]) - np.maximum(lo[spans], starts[t])
        crossing[filled[spans]] += 1
        if rule == "split":
            counts[filled[spans]] += shared / (ends[t] - starts[t])
        elif rule == "majority":
            outside = ends[t] - starts[t] - shared.sum()
            if shared.max() >= outside:
                counts[filled[spans[np.argmax(shared)]]] += 1
        else:
            s, byte = (spans[0], starts[t]) if rule == "first" else (spans[-1], ends[t] - 1)
            if lo[s] <= byte < hi[s]:
                counts[filled[s]] += 1
    return counts, crossing


def layers(lo: np.ndarray, hi: np.ndarray) -> list[np.ndarray]:
    """The spans dealt into as few sorted rows without overlap as can be; a single row if none overlap."""
    order = np.lexsort((hi, lo))
    if (lo[order][1:] >= hi[order][:-1]).all():
        return [order]
    rows: list[list[int]] = []
    free: list[tuple[int, int]] = []  # (where a row ends, its number)
    for k in order.tolist():
        if free and free[0][0] <= lo[k]:
            _, row = heapq.heappop(free)
        else:
            row = len(rows)
            rows.append([])
        rows[row].append(k)
        heapq.heappush(free, (int(max(hi[k], lo[k])), row))
    return [np.array(r) for r in rows]


def attribute_tokens(
    df: DataFrame, id_col: str = "doc_id", text_col: str = "text", spans_col: str | None = None, rule: str = "majority", vocabulary: str = "byte_bpe_50k.json"
) -> DataFrame:
    """One row for each section of each row: ``doc_id, section, start, end, n_tokens, n_crossing``.

    ``spans_col`` names an ``array<struct<start, end>>`` of character places; ``start`` and
    ``end`` of the result are character places too.
    """
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}")
    docs = id_text(df, id_col, text_col)
    if spans_col:
        start = lambda s: F.coalesce(s["start"].cast("long"), F.lit(0))
        end = lambda s: F.when(s["start"].isNull(), 0).otherwise(F.coalesce(s["end"].cast("long"), start(s)))
        spans = F.transform(F.col(spans_col), lambda s: F.array(start(s), F.greatest(start(s), end(s))))
        docs = df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), spans.alias("spans"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = byte_bpe(vocabulary_path(vocabulary))
        for batch in small(batches):
            data, offsets = utf8(batch.column(1))
            raws = [data[a:b].tobytes() for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
            given = batch.column(2).to_pylist() if spans_col else None
            columns: list[list[np.ndarray]] = [[], [], [], [], []]
            repeat = []
            for i, (raw, ids) in enumerate(zip(raws, bpe.encode_all(raws), strict=True)):
                own = np.frombuffer(raw, np.uint8)
                ends = np.cumsum(bpe.length_of[ids])
                leads = np.concatenate(([0], np.cumsum((own & 0xC0) != 0x80)))  # characters begun before each byte
                if given is None:
                    lo, hi = line_spans(own)
                    c_lo, c_hi = leads[lo], leads[hi]
                else:
                    pairs = np.array(given[i] or [], np.int64).reshape(-1, 2)
                    c_lo, c_hi = (np.clip(p, 0, leads[-1]) for p in pairs.T)
                    begins = np.append(np.flatnonzero((own & 0xC0) != 0x80), len(own))
                    lo, hi = begins[c_lo], begins[c_hi]
                n, crossing = np.zeros(len(lo)), np.zeros(len(lo), np.int64)
                for own_spans in layers(lo, hi):
                    n[own_spans], crossing[own_spans] = allocate(ends - bpe.length_of[ids], ends, lo[own_spans], hi[own_spans], rule)
                repeat.append(len(lo))
                for column, values in zip(columns, (np.arange(len(lo)), c_lo, c_hi, n, crossing), strict=True):
                    column.append(values)
            joined = [np.concatenate(c) if c else np.zeros(0) for c in columns]
            ids = batch.column(0).take(pa.array(np.repeat(np.arange(batch.num_rows), repeat)))
            kinds = [pa.int32(), pa.int64(), pa.int64(), pa.float64(), pa.int64()]
            yield pa.RecordBatch.from_arrays(
                [ids, *(pa.array(v).cast(k) for v, k in zip(joined, kinds, strict=True))], ["doc_id", "section", "start", "end", "n_tokens", "n_crossing"]
            )

    return docs.mapInArrow(run, "doc_id long, section int, start long, end long, n_tokens double, n_crossing long")
