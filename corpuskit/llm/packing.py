"""Best-fit packing of token pieces into sequences, in bulk-synchronous rounds (operator 10).

Lengths are whole numbers up to the sequence size, so equal pieces, and sequences that are
filled alike, are held as runs: a piece is (length, rank), a gap is a run of sequences with
the same room. One pass over the corpus gives each piece its rank inside its partition;
counts by partition and length turn that into a global rank without moving the pieces of a
length to one task.

A round takes a band of lengths, from the largest down. The gaps are sorted by size and
dealt by rank: each of ``slices`` tasks gets an even share of the sequences of every gap and
of the pieces of every length in the band. A task sweeps its share: the successor of a
length is the least gap that holds it, pieces that want the same gap are served in the
order of their ranks, gaps are updated, and the sweep goes on until the band is placed; a
piece without a successor opens a sequence. After the round the gaps of all tasks are
sorted and dealt anew. Shares are alike, so what a task cannot use well is at most a
sequence or so in each round, and later rounds fill it. The plan is a list of rank ranges;
its size depends on the sequence size and the slices and not on the corpus, and every piece
looks its place up in it.

Defined cases: null and empty texts are a piece of the end token alone; repeated rows and
repeated ids are packed once for each row; only the id and text columns are read; an empty
table gives an empty result.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corpuskit.llm.common import id_text, small, stored
from corpuskit.llm.word_tokens import vocabulary_path, word_encoder


@dataclass(frozen=True)
class Packing:
    size: int = 2048
    end_id: int = 0
    vocabulary: str = "word_bpe_49k.json"
    slices: int = 16
    slice_sequences: int = 20_000


PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, part int, nth long, ids binary"


def _cut(batches: Iterator[pa.RecordBatch], cfg: Packing, with_ids: bool) -> Iterator[pa.RecordBatch]:
    """Pieces of one partition, each with its rank among the partition's pieces of that length."""
    encoder = word_encoder(vocabulary_path(cfg.vocabulary))
    part = TaskContext.get().partitionId()
    used = np.zeros(cfg.size + 1, np.int64)
    for batch in small(batches):
        ids_of = batch.column(0).to_pylist()
        out: list[tuple] = []
        for doc, ids in zip(ids_of, encoder.encode_all(batch.column(1).to_pylist()), strict=True):
            whole = np.append(ids, np.uint16(cfg.end_id)).astype("<u4")
            for k, start in enumerate(range(0, len(whole), cfg.size)):
                own = whole[start : start + cfg.size]
                body = own.tobytes()
                out.append((doc, k, start, len(own), zlib.crc32(body), int(used[len(own)]), body if with_ids else None))
                used[len(own)] += 1
        doc, piece, start, length, crc, nth, body = zip(*out, strict=True) if out else ([],) * 7
        yield pa.RecordBatch.from_arrays(
            [
                pa.array(doc, pa.int64()), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()),
                pa.array(crc, pa.int64()), pa.array([part] * len(out), pa.int32()), pa.array(nth, pa.int64()), pa.array(body, pa.binary()),
            ],
            ["doc_id", "piece", "start", "length", "ids_crc32", "part", "nth", "ids"],
        )


def cut_pieces(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", cfg: Packing | None = None, with_ids: bool = False) -> DataFrame:
    cfg = cfg or Packing()
    return id_text(df, id_col, text_col).mapInArrow(lambda b: _cut(b, cfg, with_ids), PIECES)


class Gaps:
    """Runs of equally filled sequences, held by the gap they still have, in sorted order."""

    def __init__(self, size: int, opened: int = 0):
        self.size = size
        self.sizes: list[int] = []
        self.runs: dict[int, list[tuple[int, int]]] = {}
        self.opened = opened

    def add(self, gap: int, first: int, count: int) -> None:
        if gap and count:
            if gap not in self.runs:
                insort(self.sizes, gap)
                self.runs[gap] = []
            self.runs[gap].append((first, count))

    def successor(self, length: int) -> int | None:
        i = bisect_left(self.sizes, length)
        return self.sizes[i] if i < len(self.sizes) else None

    def take(self, gap: int, most: int) -> tuple[int, int]:
        """Up to ``most`` sequences of one run with this gap."""
        first, count = self.runs[gap].pop()
        if count > most:
            self.runs[gap].append((first + most, count - most))
            count = most
        if not self.runs[gap]:
            del self.runs[gap]
            self.sizes.remove(gap)
        return first, count

    def open(self, count: int) -> None:
        self.add(self.size, self.opened, count)
        self.opened += count


def sweep(pieces: list[tuple[int, int, int]], gaps: Gaps) -> list[tuple[int, int, int, int]]:
    """Places for runs of pieces (length, first rank, count), longest first: (length, first rank, first sequence, offset)."""
    plan = []
    for length, rank, left in sorted(pieces, reverse=True):
        while left:
            gap = gaps.successor(length)
            if gap is None:
                gaps.open(-(-left // (gaps.size // length)))
                continue
            deep = gap // length
            first, count = gaps.take(gap, -(-left // deep))
            for layer in range(deep):
                now = min(count, left)
                if now:
                    plan.append((length, rank, first, gaps.size - gap + layer * length))
                    rank, left = rank + now, left - now
                # sequences of the run that this layer did not reach keep the gap they have
                gaps.add(gap - layer * length, first + now, count - now)
                count = now
            gaps.add(gap - deep * length, first, count)
    return plan


def bands(size: int) -> list[tuple[int, int]]:
    """Ranges of lengths (above, up to), from the largest down, each about three quarters of the one before."""
    bounds = [size]
    while bounds[-1] > 16:
        bounds += [bounds[-1] // 2 + bounds[-1] // 6, bounds[-1] // 2]
    bounds = sorted({b for b in bounds if b >= 8} | {0}, reverse=True)
    return list(zip(bounds[1:], bounds[:-1], strict=True))


def share(n: int, k: int, of: int) -> tuple[int, int]:
    """First rank and number of the ``k``-th of ``of`` even shares of ``n``."""
    return n * k // of, n * (k + 1) // of - n * k // of


_STATE = "slice int, kind int, a long, b long, c long, d long"
_PLAN, _GAP, _OPENED = 0, 1, 2


def _sweeper(counts: dict[int, int], slices: int, size: int) -> Callable[[pd.DataFrame], pd.DataFrame]:
    return lambda rows: _sweep_slice(rows, counts, slices, size)


def _sweep_slice(rows: pd.DataFrame, counts: dict[int, int], slices: int, size: int) -> pd.DataFrame:
    """One task of a round: its share of the gaps (kind 1) and how many sequences it has opened (kind 2) go in and come out."""
    k = int(rows["slice"].iloc[0])
    opened = int(rows.loc[rows["kind"] == _OPENED, "a"].max())
    gaps = Gaps(size, opened)
    for gap, first, count in rows.loc[rows["kind"] == _GAP, ["a", "b", "c"]].sort_values(["a", "b"]).itertuples(index=False):
        gaps.add(int(gap), int(first), int(count))
    plan = sweep([(length, *share(n, k, slices)) for length, n in counts.items()], gaps)
    out = [(k, _PLAN, *p) for p in plan] + [(k, _GAP, g, f, n, 0) for g, runs in gaps.runs.items() for f, n in runs] + [(k, _OPENED, gaps.opened, 0, 0, 0)]
    return pd.DataFrame(out, columns=["slice", "kind", "a", "b", "c", "d"])


def _dealt(state: DataFrame, slices: int) -> DataFrame:
    """The gaps of a state, sorted by size and dealt by rank, and what each task has opened."""
    of_gap = Window.partitionBy("a")
    before = F.coalesce(F.sum("c").over(of_gap.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    runs = state.filter(F.col("kind") == _GAP).withColumns({"before": before, "total": F.sum("c").over(of_gap)})
    each = runs.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(slices - 1))))
    lo = F.greatest("before", F.floor(F.col("total") * F.col("k") / slices))
    hi = F.least(F.col("before") + F.col("c"), F.floor(F.col("total") * (F.col("k") + 1) / slices))
    cut = each.withColumns({"lo": lo, "hi": hi}).filter("lo < hi")
    mine = cut.select(F.col("k").alias("slice"), "kind", "a", (F.col("b") + F.col("lo") - F.col("before")).alias("b"), (F.col("hi") - F.col("lo")).alias("c"), "d")
    return mine.unionByName(state.filter(F.col("kind") == _OPENED))


def match(spark: SparkSession, counts: dict[int, int], cfg: Packing) -> np.ndarray:
    """Places for ``counts[length]`` pieces: rows (length, first rank, first sequence, offset), sorted."""
    tokens = sum(length * n for length, n in counts.items())
    slices = max(1, min(cfg.slices, tokens // (cfg.size * cfg.slice_sequences)))
    # the sequences of each task are numbered in a range of its own
    state = spark.range(slices).select(F.col("id").cast("int").alias("slice"), F.lit(_OPENED).alias("kind"), F.shiftleft("id", 40).alias("a"), *[F.lit(0).cast("long").alias(c) for c in "bcd"])
    plans = []
    for above, upto in bands(cfg.size) if slices > 1 else [(0, cfg.size)]:  # one task alone need not deal its gaps anew
        band = {length: n for length, n in counts.items() if above < length <= upto}
        if band:
            state = stored(_dealt(state, slices).groupBy("slice").applyInPandas(_sweeper(band, slices, cfg.size), _STATE), "round")
            plans.append(state.filter(F.col("kind") == _PLAN).select("a", "b", "c", "d").toPandas().to_numpy())
    plan = np.concatenate(plans) if plans else np.zeros((0, 4))
    plan = plan.astype(np.int64).reshape(-1, 4)
    return plan[np.lexsort((plan[:, 1], plan[:, 0]))]


def _place(batches: Iterator[pa.RecordBatch], plan: np.ndarray) -> Iterator[pa.RecordBatch]:
    key = plan[:, 0] << 42 | plan[:, 1]
    for batch in small(batches):
        length, rank = (batch.column(batch.schema.get_field_index(n)).to_numpy() for n in ("length", "rank"))
        at = np.searchsorted(key, length << 42 | rank, "right") - 1
        row = plan[at]
        kept = [batch.column(i) for i, n in enumerate(batch.schema.names) if n != "rank"]
        names = [n for n in batch.schema.names if n != "rank"]
        yield pa.RecordBatch.from_arrays(
            [*kept, pa.array(row[:, 2] + rank - row[:, 1]), pa.array(row[:, 3])], [*names, "sequence_id", "offset"]
        )


def pack(pieces: DataFrame, cfg: Packing | None = None) -> DataFrame:
    """``pieces`` of :func:`cut_pieces`, written once, with ``sequence_id`` and ``offset``."""
    cfg = cfg or Packing()
    counts = stored(pieces.groupBy("part", "length").agg(F.count("*").alias("n")), "counts")
    by_length = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    plan = match(pieces.sparkSession, by_length, cfg)
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("part", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    columns = ["doc_id", "piece", "start", "length", "ids_crc32", *(["ids"] if "ids" in pieces.columns else [])]
    # partitions times lengths grow with the corpus, so this side is never broadcast
    ranked = pieces.join(base.hint("merge"), ["part", "length"]).select(*columns, (F.col("base") + F.col("nth")).alias("rank"))
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids binary" * ("ids" in columns)
    return ranked.mapInArrow(lambda b: _place(b, plan), schema + ", sequence_id long, offset long")


def pack_documents(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", cfg: Packing | None = None, with_ids: bool = False) -> DataFrame:
    """One row for each piece of each row of ``df``, placed; ``with_ids`` adds the ids themselves."""
    cfg = cfg or Packing()
    pieces = cut_pieces(df, id_col, text_col, cfg, with_ids)
    return pack(stored(pieces if with_ids else pieces.drop("ids"), "pieces"), cfg)


def fill(packed: DataFrame, cfg: Packing | None = None) -> DataFrame:
    """Sequences used, the least number possible by volume, and the share of places filled."""
    cfg = cfg or Packing()
    used = packed.agg(F.count_distinct("sequence_id").alias("sequences"), F.coalesce(F.sum("length"), F.lit(0)).alias("tokens"))
    return used.withColumn("least", F.ceil(F.col("tokens") / cfg.size)).withColumn("filled", F.try_divide("tokens", F.col("sequences") * cfg.size))
