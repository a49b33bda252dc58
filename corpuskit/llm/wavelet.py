"""Token files as wavelet matrices (operator 8).

The corpus is range-partitioned by document id, tokenized, and cut into shards of a
bounded number of tokens. Each shard is one compressed file image: a header, the ids and
lengths of its documents, and for each bit of the vocabulary a bit-plane with a rank
directory. From that image alone a reader gets the token at a place, the count of a token
before a place, the place of its k-th occurrence, or the whole sequence. The images are
the rows of a Parquet table, which every storage that Spark writes to can hold, and which
a lost executor does not take with it.

Defined cases: null and empty texts are the end token alone; null ids come first; repeated
ids lie side by side, ordered by a hash of their text; only the id and text columns are
read; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpuskit.llm.common import id_text, new_path, small
from corpuskit.llm.word_tokens import vocabulary_path, word_encoder

#: First bytes of an image; bits for each entry of a rank directory.
MAGIC = b"WVMX0001"
BLOCK = 512


@dataclass(frozen=True)
class TokenFiles:
    vocabulary: str = "word_bpe_49k.json"
    end_id: int = 2
    bits: int = 16
    shard_tokens: int = 2_000_000
    level: int = 3


class WaveletMatrix:
    """``planes[l]`` holds bit ``bits - 1 - l`` of every token, in the order of that level."""

    def __init__(self, n: int, bits: int, zeros: np.ndarray, planes: list[np.ndarray], ranks: list[np.ndarray]):
        self.n, self.bits, self.zeros, self.planes, self.ranks = n, bits, zeros, planes, ranks

    @classmethod
    def build(cls, tokens: np.ndarray, bits: int = 16) -> WaveletMatrix:
        n = len(tokens)
        planes, ranks, zeros = [], [], np.zeros(bits, np.int64)
        level = tokens.astype(np.uint16)
        for l in range(bits):
            if bits - l == 8:  # what is left of a token fits a byte
                level = level.astype(np.uint8)
            ones = (level & level.dtype.type(1 << (bits - 1 - l))) != 0
            packed = np.zeros(-(-max(n, 1) // BLOCK) * BLOCK // 8, np.uint8)
            packed[: (n + 7) // 8] = np.packbits(ones, bitorder="little")
            planes.append(packed)
            ranks.append(cls._directory(packed))
            if l < bits - 1:
                level = np.concatenate((level[~ones], level[ones]))
            zeros[l] = n - int(ranks[-1][-1])
        return cls(n, bits, zeros, planes, ranks)

    @staticmethod
    def _directory(packed: np.ndarray) -> np.ndarray:
        counts = np.bitwise_count(packed.view(np.uint64)).reshape(-1, BLOCK // 64).sum(1)
        return np.concatenate(([0], np.cumsum(counts))).astype(np.uint32)

    def _rank1(self, l: int, at: np.ndarray) -> np.ndarray:
        """Ones of plane ``l`` before each place."""
        at = np.asarray(at, np.int64)
        words = self.planes[l].view(np.uint64)
        block, word, bit = at // BLOCK, at // 64, at % 64
        total = self.ranks[l][block].astype(np.int64)
        for k in range(BLOCK // 64):
            w = block * (BLOCK // 64) + k
            full, part = w < word, w == word
            value = words[np.minimum(w, len(words) - 1)]
            mask = np.where(full, np.uint64(0xFFFFFFFFFFFFFFFF), np.where(part, (np.uint64(1) << bit.astype(np.uint64)) - np.uint64(1), np.uint64(0)))
            total += np.bitwise_count(value & mask)
        return total

    def _bit(self, l: int, at: np.ndarray) -> np.ndarray:
        return (self.planes[l][at >> 3] >> (at & 7).astype(np.uint8)) & 1

    def access(self, at: np.ndarray) -> np.ndarray:
        """Tokens at the given places."""
        at = np.array(at, np.int64)
        out = np.zeros(len(at), np.int64)
        for l in range(self.bits):
            one, before = self._bit(l, at).astype(bool), self._rank1(l, at)
            out = out << 1 | one
            at = np.where(one, self.zeros[l] + before, at - before)
        return out

    def rank(self, token: int, at: int) -> int:
        """Occurrences of ``token`` before place ``at``."""
        lo, hi = np.array([0]), np.array([at])
        for l in range(self.bits):
            a, b = self._rank1(l, lo), self._rank1(l, hi)
            if token >> (self.bits - 1 - l) & 1:
                lo, hi = self.zeros[l] + a, self.zeros[l] + b
            else:
                lo, hi = lo - a, hi - b
        return int(hi[0] - lo[0])

    def count(self, token: int) -> int:
        return self.rank(token, self.n)

    def occurrences(self, token: int) -> np.ndarray:
        """All places of ``token``, ascending."""
        lo, hi = np.array([0]), np.array([self.n])
        path = []
        for l in range(self.bits):
            bit = token >> (self.bits - 1 - l) & 1
            a, b = self._rank1(l, lo), self._rank1(l, hi)
            lo, hi = (self.zeros[l] + a, self.zeros[l] + b) if bit else (lo - a, hi - b)
            path.append(bit)
        at = np.arange(lo[0], hi[0])
        for l in range(self.bits - 1, -1, -1):
            at = self._select(l, path[l], at - (self.zeros[l] if path[l] else 0))
        return at

    def select(self, token: int, k: int) -> int:
        """Place of the ``k``-th occurrence (from 0)."""
        return int(self.occurrences(token)[k])

    def _select(self, l: int, bit: int, k: np.ndarray) -> np.ndarray:
        """Places of the ``k``-th ones (or zeros) of plane ``l``."""
        ranks = self.ranks[l].astype(np.int64)
        if not bit:
            ranks = np.arange(len(ranks), dtype=np.int64) * BLOCK - ranks
        block = np.searchsorted(ranks, k, "right") - 1
        out = np.zeros(len(k), np.int64)
        for b in np.unique(block):
            bits = np.unpackbits(self.planes[l][b * BLOCK // 8 : (b + 1) * BLOCK // 8], bitorder="little") == bit
            own = block == b
            out[own] = b * BLOCK + np.flatnonzero(bits)[k[own] - ranks[b]]
        return out

    def tokens(self) -> np.ndarray:
        """The whole sequence: the levels are undone from the last to the first."""
        level = np.zeros(self.n, np.uint8 if self.bits > 7 else np.uint16)
        for l in range(self.bits - 1, -1, -1):
            if self.bits - l == 9:
                level = level.astype(np.uint16)
            ones = np.unpackbits(self.planes[l], count=self.n, bitorder="little").view(bool)
            z = int(self.zeros[l])
            up = np.empty(self.n, level.dtype)
            up[~ones] = level[:z]
            up[ones] = level[z:] | level.dtype.type(1 << (self.bits - 1 - l))
            level = up
        return level.astype(np.uint16)

    def to_bytes(self, docs: list[int | None], lengths: np.ndarray, level: int = 3) -> bytes:
        """The file image, with the documents whose tokens it holds; behind their ids a byte for each tells the null ones."""
        press = zstandard.ZstdCompressor(level=level)
        ids, none = np.array([d or 0 for d in docs], "<i8"), np.array([d is None for d in docs], np.uint8)
        parts = [ids.tobytes() + none.tobytes(), lengths.astype("<u4").tobytes(), self.zeros.astype("<i8").tobytes()]
        for plane, ranks in zip(self.planes, self.ranks, strict=True):
            parts += [plane.tobytes(), np.diff(ranks).astype("<u2").tobytes()]
        packed = [press.compress(p) for p in parts]
        head = np.array([self.n, self.bits, len(docs), *map(len, packed)], "<i8").tobytes()
        return b"".join([MAGIC, len(head).to_bytes(8, "little"), head, *packed])

    @classmethod
    def from_bytes(cls, image: bytes) -> tuple[WaveletMatrix, pa.Array, np.ndarray]:
        if image[:8] != MAGIC:
            raise ValueError("not a token file")
        size = int.from_bytes(image[8:16], "little")
        head = np.frombuffer(image[16 : 16 + size], "<i8")
        n, bits = int(head[0]), int(head[1])
        ends = 16 + size + np.cumsum(head[3:])
        open_ = zstandard.ZstdDecompressor()
        parts = [open_.decompress(image[a:b]) for a, b in zip([16 + size, *ends[:-1].tolist()], ends.tolist(), strict=True)]
        many = int(head[2])
        docs = pa.array(np.frombuffer(parts[0][: 8 * many], "<i8"), mask=np.frombuffer(parts[0][8 * many :], np.uint8).astype(bool))
        lengths, zeros = np.frombuffer(parts[1], "<u4"), np.frombuffer(parts[2], "<i8")
        planes = [np.frombuffer(p, np.uint8) for p in parts[3::2]]
        ranks = [np.concatenate(([0], np.cumsum(np.frombuffer(p, "<u2")))).astype(np.uint32) for p in parts[4::2]]
        return cls(n, bits, zeros, planes, ranks), docs, lengths


def _shards(batches: Iterator[pa.RecordBatch], cfg: TokenFiles) -> Iterator[pa.RecordBatch]:
    """File images of one partition, in document order."""
    encoder = word_encoder(vocabulary_path(cfg.vocabulary))
    part = TaskContext.get().partitionId()
    docs: list[int | None] = []
    lengths: list[int] = []
    body: list[np.ndarray] = []
    shard = before = held = 0

    def flush() -> pa.RecordBatch:
        image = WaveletMatrix.build(np.concatenate(body), cfg.bits).to_bytes(docs, np.array(lengths), cfg.level)
        return pa.RecordBatch.from_arrays(
            [pa.array([part], pa.int32()), pa.array([shard], pa.int32()), pa.array([before], pa.int64()), pa.array([held], pa.int64()), pa.array([image], pa.binary())],
            ["part", "shard", "before", "n_tokens", "image"],
        )

    end = np.array([cfg.end_id], np.uint16)
    for batch in small(batches):
        for doc, ids in zip(batch.column(0).to_pylist(), encoder.encode_all(batch.column(1).to_pylist()), strict=True):
            docs.append(doc)
            lengths.append(len(ids) + 1)
            body += [ids, end]
            held += len(ids) + 1
            if held >= cfg.shard_tokens:
                yield flush()
                shard, before, held = shard + 1, before + held, 0
                docs, lengths, body = [], [], []
    if docs:
        yield flush()


def write_token_files(df: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", cfg: TokenFiles | None = None) -> None:
    """Token files of ``df`` in ascending id order below ``path``."""
    cfg = cfg or TokenFiles()
    docs = id_text(df, id_col, text_col)
    parts = max(2 * docs.rdd.getNumPartitions(), 8)
    # a hash of the text deals the rows of a very frequent id, or of none, over several partitions
    by = [F.col("doc_id").asc_nulls_first(), F.col("h").asc_nulls_first()]
    ordered = docs.withColumn("h", F.xxhash64("text")).repartitionByRange(parts, *by).sortWithinPartitions(*by, "text").drop("h")
    images = ordered.mapInArrow(lambda b: _shards(b, cfg), "part int, shard int, before long, n_tokens long, image binary")
    images.write.option("compression", "uncompressed").parquet(path)


def read_token_files(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """One row for each document in the files: ``doc_id, start, n_tokens, ids_crc32`` (and ``ids``).

    Only one number for each partition of the writing job reaches the driver.
    """
    files = spark.read.schema("part int, shard int, before long, n_tokens long, image binary").parquet(path)
    totals = {r["part"]: r["n"] for r in files.groupBy("part").agg(F.sum("n_tokens").alias("n")).collect()}
    base, total = {}, 0
    for part in sorted(totals):
        base[part], total = total, total + totals[part]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches):
            for part, before, image in zip(*(batch.column(i) for i in range(3)), strict=True):
                matrix, docs, lengths = WaveletMatrix.from_bytes(image.as_py())
                tokens = matrix.tokens().astype("<u4")
                ends = np.cumsum(lengths.astype(np.int64))
                starts = ends - lengths
                raw = memoryview(tokens).cast("B")
                crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]
                out = [docs, pa.array(starts + base[part.as_py()] + before.as_py()), pa.array(lengths.astype(np.int64)), pa.array(crc, pa.int64())]
                names = ["doc_id", "start", "n_tokens", "ids_crc32"]
                if with_ids:
                    out.append(pa.array([raw[4 * a : 4 * b].tobytes() for a, b in zip(starts.tolist(), ends.tolist(), strict=True)], pa.binary()))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(out, names)

    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids binary" * with_ids
    return files.select("part", "before", "image").mapInArrow(run, schema)


def token_counts(spark: SparkSession, path: str, tokens: list[int]) -> DataFrame:
    """How often each of ``tokens`` occurs, by shard, from rank queries on the files alone."""
    files = spark.read.schema("part int, shard int, before long, n_tokens long, image binary").parquet(path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches):
            for part, shard, image in zip(*(batch.column(i) for i in range(3)), strict=True):
                matrix, _, _ = WaveletMatrix.from_bytes(image.as_py())
                yield pa.RecordBatch.from_arrays(
                    [pa.array([part.as_py()] * len(tokens), pa.int32()), pa.array([shard.as_py()] * len(tokens), pa.int32()),
                     pa.array(tokens, pa.int64()), pa.array([matrix.count(t) for t in tokens], pa.int64())],
                    ["part", "shard", "token", "n"],
                )

    return files.select("part", "shard", "image").mapInArrow(run, "part int, shard int, token long, n long")


def round_trip(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", cfg: TokenFiles | None = None) -> DataFrame:
    """Write the token files of ``df`` to the shared scratch folder and read them back."""
    path = new_path(df.sparkSession, "token-files")
    write_token_files(df, path, id_col, text_col, cfg)
    return read_token_files(df.sparkSession, path)
