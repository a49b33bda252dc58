"""Token-bounded chunks with overlap, and the simpler chunkers they are compared with.

A text is read once, as an array of pieces (a token and the white space behind it). All
else works on whole numbers: where paragraphs and sentences end, how long the units are,
and where chunks are cut. A chunk with its overlap is one run of pieces, so its text is a
verbatim part of the document. Nothing but the finished chunks leaves the row; there is no
exchange.

Defined cases: a null text, or one without tokens, has no chunks; a sentence longer than
the budget is cut into runs of tokens; equal rows give equal chunks.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpuskit.functions import tokens as T

MERGE_MODES = ("fill", "strict", "cap", "rebalance")


@dataclass(frozen=True)
class ChunkConfig:
    """Limits of a chunk, overlap included.

    ``merge_mode`` says what becomes of a chunk below the minimum that the next unit does
    not fit behind: ``fill`` takes the beginning of that unit, up to the limit, so only the
    last chunk of a document can be short and none is too long; ``strict`` leaves it short;
    ``cap`` joins it to a neighbour up to ``merge_cap``; ``rebalance`` cuts the last two
    chunks anew in the middle.
    """

    max_tokens: int = 200
    min_tokens: int = 100
    overlap: int = 20
    merge_mode: str = "fill"
    merge_cap: int = 300
    scheme: str = "wordpunct"

    def __post_init__(self):
        if self.merge_mode not in MERGE_MODES:
            raise ValueError(f"merge_mode must be one of {MERGE_MODES}")
        if not 0 <= self.overlap < self.max_tokens or self.min_tokens > self.budget:
            raise ValueError("the overlap must be below, and the minimum not above, what a chunk may hold")

    @property
    def budget(self) -> int:
        return self.max_tokens - self.overlap


def screen(df: DataFrame, text: str = "text") -> DataFrame:
    """``reason`` why a document cannot be chunked, NULL if it can."""
    t = F.col(text)
    reason = F.when(t.isNull() | ~t.rlike(rf"[^{T.SPACE}]"), "empty_content").when(~F.is_valid_utf8(t), "bad_encoding").when(~t.rlike(T.WORDPUNCT), "no_tokens")
    return df.withColumn("reason", reason)


# ------------------------------------------------------------------------- units of a text


def _steps(ends: Column) -> Column:
    """Lengths of the stretches that end at ``ends``."""
    return F.transform(ends, lambda e, i: e - F.when(i > 0, F.get(ends, i - 1)).otherwise(0))


def _ends(pieces: Column, test) -> Column:
    """Places (from 1) of the pieces that end a stretch, the last piece among them."""
    n = F.size(pieces)
    at = F.transform(pieces, lambda p, i: F.when(test(p, i) | (i + 1 == n), i + 1))
    return F.filter(at, lambda e: e.isNotNull())


def _ends_paragraph(pieces: Column):
    return lambda p, i: F.contains(p, F.lit("\n"))


def _ends_sentence(pieces: Column):
    """The last of a row of sentence marks, or the end of a line."""
    mark = lambda c: c.isin(".", "!", "?")
    after = lambda i: F.coalesce(mark(F.substring(F.get(pieces, i + 1), 1, 1)), F.lit(False))
    return lambda p, i: (mark(F.substring(F.rtrim(p), -1, 1)) & ~after(i)) | F.contains(p, F.lit("\n"))


def _lengths(pieces: Column, kind) -> Column:
    return T.let(_ends(pieces, kind(pieces)), _steps)


def unit_lengths(pieces: Column, budget: int) -> Column:
    """Tokens of each unit: paragraphs; sentences of a paragraph over the budget; runs of a sentence that still is."""

    def runs(n: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.floor((n - 1) / budget).cast("int")), lambda k: F.least(F.lit(budget), n - k * budget))

    def sentences(own: Column) -> Column:
        return F.flatten(F.transform(_lengths(own, _ends_sentence), lambda n: F.when(n > budget, runs(n)).otherwise(F.array(n))))

    def of(ends: Column) -> Column:
        def unit(e: Column, i: Column) -> Column:
            start = F.when(i > 0, F.get(ends, i - 1)).otherwise(0)
            long_ = T.let(F.slice(pieces, start + 1, e - start), sentences)
            return F.when(e - start > budget, long_).otherwise(F.array(e - start))

        return F.flatten(F.transform(ends, unit))

    return T.let(_ends(pieces, _ends_paragraph(pieces)), of)


# ------------------------------------------------------------------------- places of cuts


def pack(lengths: Column, budget: int, least_first: int = 0, least: int = 0) -> Column:
    """Greedy packing: the places where chunks end, in tokens.

    A unit that does not fit closes the chunk if that holds at least ``least`` tokens
    (``least_first`` for the first one). Otherwise the unit's beginning fills the chunk up
    to the budget, and its rest begins the next one.
    """
    state = F.struct(F.array().cast("array<int>").alias("cuts"), F.lit(0).alias("base"), F.lit(0).alias("s"))

    def step(acc: Column, n: Column) -> Column:
        total = acc["s"] + n
        enough = acc["s"] >= F.when(F.size(acc["cuts"]) == 0, least_first).otherwise(least)
        kept = F.when(enough, acc["s"]).otherwise(budget)
        closed = F.struct(F.array_append(acc["cuts"], acc["base"] + kept).alias("cuts"), (acc["base"] + kept).alias("base"), (total - kept).alias("s"))
        grown = F.struct(acc["cuts"].alias("cuts"), acc["base"].alias("base"), total.alias("s"))
        return F.when((acc["s"] > 0) & (total > budget), closed).otherwise(grown).cast("struct<cuts: array<int>, base: int, s: int>")

    return F.aggregate(lengths, state, step, lambda acc: F.when(acc["s"] > 0, F.array_append(acc["cuts"], acc["base"] + acc["s"])).otherwise(acc["cuts"]))


def _joined(cuts: Column, cfg: ChunkConfig) -> Column:
    """Short chunks join a neighbour, left to right, with decisions on merged sizes."""
    least, cap = cfg.min_tokens - cfg.overlap, cfg.merge_cap - cfg.overlap
    state = F.struct(F.array().cast("array<int>").alias("cuts"), F.lit(0).alias("base"), F.lit(0).alias("s"))

    def step(acc: Column, n: Column) -> Column:
        total = acc["s"] + n
        joins = (acc["s"] == 0) | (((n < least) | (acc["s"] < least)) & (total <= cap))
        grown = F.struct(acc["cuts"].alias("cuts"), acc["base"].alias("base"), total.alias("s"))
        closed = F.struct(F.array_append(acc["cuts"], acc["base"] + acc["s"]).alias("cuts"), (acc["base"] + acc["s"]).alias("base"), n.alias("s"))
        return F.when(joins, grown).otherwise(closed).cast("struct<cuts: array<int>, base: int, s: int>")

    return F.aggregate(_steps(cuts), state, step, lambda acc: F.when(acc["s"] > 0, F.array_append(acc["cuts"], acc["base"] + acc["s"])).otherwise(acc["cuts"]))


def _halved(cuts: Column, cfg: ChunkConfig) -> Column:
    """A short last chunk and the one before it, cut anew in the middle."""
    n = F.size(cuts)
    last, before = F.element_at(cuts, -1), F.element_at(cuts, -2)
    begin = F.when(n > 2, F.get(cuts, n - 3)).otherwise(0)
    middle = (begin + F.ceil((last - begin) / 2)).cast("int")
    short = F.when(n > 1, last - before < cfg.min_tokens - cfg.overlap).otherwise(False)
    return F.when(short, F.concat(F.slice(cuts, F.lit(1), F.greatest(n - 2, F.lit(0))), F.array(middle, last))).otherwise(cuts)


def cut_places(pieces: Column, cfg: ChunkConfig) -> Column:
    lengths = unit_lengths(pieces, cfg.budget)
    if cfg.merge_mode == "fill":
        return pack(lengths, cfg.budget, cfg.min_tokens, cfg.min_tokens - cfg.overlap)
    cuts = pack(lengths, cfg.budget)
    if cfg.merge_mode == "cap":
        return T.let(cuts, lambda c: _joined(c, cfg))
    return T.let(cuts, lambda c: _halved(c, cfg)) if cfg.merge_mode == "rebalance" else cuts


# ---------------------------------------------------------------------------- the chunkers


def _run(pieces: Column, first: Column, n: Column) -> Column:
    """Text of ``n`` pieces from place ``first`` (0 is the first), without the white space at its end."""
    return F.regexp_replace(F.array_join(F.slice(pieces, first + 1, n), ""), rf"[{T.SPACE}]+$", "")


def _rows(df: DataFrame, cuts, overlap: int, key: str, text: str, scheme: str) -> DataFrame:
    """Chunk rows from the places where ``cuts(pieces)`` ends them."""

    def chunks(pieces: Column) -> Column:
        def of(ends: Column) -> Column:
            def one(e: Column, i: Column) -> Column:
                start = F.when(i > 0, F.get(ends, i - 1)).otherwise(0)
                lap = F.when(i > 0, F.least(F.lit(overlap), start - F.when(i > 1, F.get(ends, i - 2)).otherwise(0))).otherwise(0)
                return F.struct(
                    (i + 1).alias("chunk_no"), _run(pieces, start - lap, e - start + lap).alias("text"), (e - start).alias("body_tokens"),
                    lap.alias("overlap_tokens"), (e - start + lap).alias("n_tokens"),
                )

            return F.transform(ends, one)

        return T.let(cuts(pieces), of)

    rows = df.select(F.col(key).alias("corpus_id"), F.explode(T.let(T.pieces(F.col(text), scheme), chunks)).alias("c"))
    no = F.col("c.chunk_no").cast("int")
    number = lambda c: F.col(f"c.{c}").cast("int").alias(c)
    return rows.select("corpus_id", no.alias("chunk_no"), chunk_id("corpus_id", no).alias("chunk_id"), "c.text", number("body_tokens"), number("overlap_tokens"), number("n_tokens"))


def chunk_id(key: str, no: Column) -> Column:
    return F.concat(F.col(key).cast("string"), F.lit("P"), no.cast("string"))


def split_units(df: DataFrame, cfg: ChunkConfig | None = None, text: str = "text", key: str = "doc_id") -> DataFrame:
    """The units that are packed: ``corpus_id, unit_no, n_tokens, text``."""
    cfg = cfg or ChunkConfig()
    ends = lambda p: T.let(unit_lengths(p, cfg.budget), lambda n: pack(n, 0))  # noqa: E731  nothing fits, so each unit is cut off
    rows = _rows(df, ends, 0, key, text, cfg.scheme)
    return rows.select("corpus_id", F.col("chunk_no").alias("unit_no"), "n_tokens", "text")


def chunk(df: DataFrame, cfg: ChunkConfig | None = None, text: str = "text", key: str = "doc_id") -> DataFrame:
    """The whole chunker: ``corpus_id, chunk_no, chunk_id, text, body_tokens, overlap_tokens, n_tokens``."""
    cfg = cfg or ChunkConfig()
    ok = screen(df, text).filter("reason is null")
    return _rows(ok, lambda p: cut_places(p, cfg), cfg.overlap, key, text, cfg.scheme)


# ------------------------------------------------------------------------ simpler chunkers


def fixed_window(df: DataFrame, max_tokens: int = 200, overlap: int = 20, text: str = "text", key: str = "doc_id", scheme: str = "wordpunct") -> DataFrame:
    """Windows of tokens with a stride of ``max_tokens - overlap``."""
    stride = max_tokens - overlap

    def windows(pieces: Column) -> Column:
        n = F.size(pieces)
        last = F.greatest(F.ceil((n - overlap) / stride), F.lit(1)).cast("int")
        every = F.transform(F.sequence(F.lit(0), last - 1), lambda i: F.struct((i + 1).alias("chunk_no"), _run(pieces, i * stride, F.lit(max_tokens)).alias("text"), F.least(F.lit(max_tokens), n - i * stride).alias("n_tokens")))
        return F.when(n > 0, every)

    rows = df.select(F.col(key).alias("corpus_id"), F.explode(T.let(T.pieces(F.col(text), scheme), windows)).alias("c"))
    return rows.select("corpus_id", "c.chunk_no", chunk_id("corpus_id", F.col("c.chunk_no")).alias("chunk_id"), "c.text", F.col("c.n_tokens").cast("int").alias("n_tokens"))


def by_sentence(df: DataFrame, max_tokens: int = 200, text: str = "text", key: str = "doc_id", scheme: str = "wordpunct") -> DataFrame:
    """Whole sentences packed greedily; a longer sentence is a chunk of its own."""
    return _rows(df, lambda p: T.let(_lengths(p, _ends_sentence), lambda n: pack(n, max_tokens)), 0, key, text, scheme)


def by_paragraph(df: DataFrame, text: str = "text", key: str = "doc_id", scheme: str = "wordpunct") -> DataFrame:
    return _rows(df, lambda p: _ends(p, _ends_paragraph(p)), 0, key, text, scheme)


def whole(df: DataFrame, text: str = "text", key: str = "doc_id", scheme: str = "wordpunct") -> DataFrame:
    n = T.count(F.col(text), scheme)
    rows = df.filter(n > 0)
    return rows.select(F.col(key).alias("corpus_id"), F.lit(1).alias("chunk_no"), chunk_id(key, F.lit(1)).alias("chunk_id"), F.col(text).alias("text"), n.cast("int").alias("n_tokens"))
