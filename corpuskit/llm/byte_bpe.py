"""Byte-level BPE with forced boundaries: encoding and decoding (operator 5).

A merge can only make a token of the vocabulary, so two neighbouring bytes that lie next
to each other inside no token are never joined: between them there is a certain cut. The
table of such byte pairs comes from the vocabulary alone. A text is cut, over all its
bytes in numpy, at its certain cuts, and each distinct fragment is encoded on its own, once
while it stays in the cache. The ids of a text are the concatenation of those of its
fragments. Decoding joins the bytes of the tokens.

The library splits a text into pre-tokens before it merges. The split goes from left to
right without looking back, so what stands behind a cut is split as if the text began
there, and what stands before it as if the text ended there, unless the cut is behind
white space (whose split depends on what follows) or beside an apostrophe that may begin a
contraction. Those cuts are not taken, nor those inside a character or a special token.

Defined cases: a null text counts as empty and has no ids; the literal of a special token
gets the special id, as the library does; equal texts get equal ids; columns other than
the id and the text are not read; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from corpuskit.llm.common import id_text, small, utf8
from corpuskit.llm.word_tokens import load_tokenizer, vocabulary_path

#: Which bytes are ASCII white space, as the pre-tokenizer sees it.
_ASCII_SPACE = np.zeros(256, bool)
_ASCII_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D, 0x1C, 0x1D, 0x1E, 0x1F]] = True
_ALNUM = np.zeros(256, bool)
_ALNUM[[*range(48, 58), *range(65, 91), *range(97, 123)]] = True
_CONTRACTED = (b"re", b"ve", b"ll")


def printable_bytes() -> dict[str, int]:
    """The alphabet in which vocabulary files write bytes: printable ones as themselves, others from 256 on."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in shown]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


def _wide_space_ends(data: np.ndarray) -> np.ndarray | None:
    """Ends of the white-space characters beyond ASCII, None if there are none."""
    two = np.flatnonzero(data[:-1] == 0xC2)
    ends = [two[np.isin(data[two + 1], (0x85, 0xA0))] + 2] if len(two) else []
    lead = np.flatnonzero((data[:-2] == 0xE1) | (data[:-2] == 0xE2) | (data[:-2] == 0xE3)) if len(data) > 2 else two[:0]
    if len(lead):
        a, b, c = data[lead], data[lead + 1], data[lead + 2]
        space = (a == 0xE1) & (b == 0x9A) & (c == 0x80) | (a == 0xE3) & (b == 0x80) & (c == 0x80)
        space |= (a == 0xE2) & ((b == 0x80) & ((c <= 0x8A) | np.isin(c, (0xA8, 0xA9, 0xAF))) | (b == 0x81) & (c == 0x9F))
        ends.append(lead[space] + 3)
    found = np.concatenate(ends) if ends else two[:0]
    return found if len(found) else None


class ByteBPE:
    def __init__(self, path: str, cache_fragments: int = 400_000):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        alphabet = printable_bytes()
        vocab = {t: bytes(alphabet[c] for c in t) for t in spec["model"]["vocab"]}
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = list(vocab.values())
        self.bytes_of = [b""] * (max([*spec["model"]["vocab"].values(), *special.values()]) + 1)
        for token, i in spec["model"]["vocab"].items():
            self.bytes_of[i] = vocab[token]
        for token, i in special.items():
            self.bytes_of[i] = token.encode()
        self.length_of = np.array([len(b) for b in self.bytes_of])
        self.special = re.compile(b"|".join(re.escape(t.encode()) for t in special)) if special else None
        self.tokenizer = load_tokenizer(path)
        self.certain = self._certain_cuts()
        if any(self.certain[a, b] for a, b in _CONTRACTED):
            raise ValueError("a cut could fall inside a contraction")
        # cuts that hold whatever stands around the pair, but for white space beyond ASCII and special tokens
        left, right = np.arange(256)[:, None], np.arange(256)[None, :]
        inside = (right >= 0x80) & (right < 0xC0)
        quote = (left == 0x27) | ((right == 0x27) & ~_ALNUM[left])
        self.taken = self.certain & ~inside & ~_ASCII_SPACE[left] & ~quote
        self.cache: dict[bytes, bytes] = {}
        self.cache_fragments = cache_fragments

    def _certain_cuts(self) -> np.ndarray:
        """``[left, right]``: whether no token holds these two bytes side by side."""
        cut = np.ones((256, 256), bool)
        for token in self.tokens:
            own = np.frombuffer(token, np.uint8)
            cut[own[:-1], own[1:]] = False
        return cut

    def text_cuts(self, data: np.ndarray) -> np.ndarray:
        """Places where a text may be cut."""
        if len(data) < 2:
            return np.zeros(0, np.int64)
        at = np.flatnonzero(self.taken[data[:-1], data[1:]]) + 1
        wide = _wide_space_ends(data)
        return at if wide is None else at[~np.isin(at, wide)]

    def fragments(self, raw: bytes) -> list[bytes]:
        if not raw:
            return []
        cuts = self.text_cuts(np.frombuffer(raw, np.uint8))
        if self.special and b"<|" in raw:
            for m in self.special.finditer(raw):
                cuts = cuts[(cuts <= m.start()) | (cuts >= m.end())]
        cuts = cuts.tolist()
        return [raw[a:b] for a, b in zip([0, *cuts], [*cuts, len(raw)], strict=True)]

    def _learn(self, fragments: set[bytes]) -> None:
        if len(self.cache) + len(fragments) > self.cache_fragments:
            self.cache.clear()
        own = list(fragments)
        self.cache.update((f, ids.tobytes()) for f, ids in zip(own, self._ids(own), strict=True))

    def _ids(self, texts: list[bytes]) -> list[np.ndarray]:
        found = self.tokenizer.encode_batch_fast([t.decode() for t in texts], add_special_tokens=False)
        return [np.array(e.ids, "<u4") for e in found]

    def encode_all(self, raws: list[bytes], at_once: int = 256) -> Iterator[np.ndarray]:
        """Ids of each text, given as UTF-8."""
        for i in range(0, len(raws), at_once):
            cut = [self.fragments(raw) for raw in raws[i : i + at_once]]
            here = set().union(*cut)
            missing = here.difference(self.cache)
            if missing:
                self._learn(missing)
                if not here <= self.cache.keys():
                    self._learn(here)
            cache = self.cache
            for own in cut:
                yield np.frombuffer(b"".join([cache[f] for f in own]), "<u4")

    def decode(self, ids: np.ndarray) -> str:
        """Text of the ids, special tokens shown; bytes that are no UTF-8 become replacement characters."""
        return b"".join(map(self.bytes_of.__getitem__, ids.tolist())).decode("utf-8", "replace")


@lru_cache(maxsize=2)
def byte_bpe(path: str) -> ByteBPE:
    """One encoder for the life of a worker process, so that later tasks find a warm cache."""
    return ByteBPE(path)


def encode_documents(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = "byte_bpe_50k.json") -> DataFrame:
    """``doc_id, ids`` with the ids as little-endian unsigned 32-bit integers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = byte_bpe(vocabulary_path(vocabulary))
        for batch in small(batches):
            data, offsets = utf8(batch.column(1))
            raw = [data[a:b].tobytes() for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
            ids = [x.tobytes() for x in bpe.encode_all(raw)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.binary())], ["doc_id", "ids"])

    return id_text(df, id_col, text_col).mapInArrow(run, "doc_id long, ids binary")


def decode_ids(df: DataFrame, vocabulary: str = "byte_bpe_50k.json") -> DataFrame:
    """``doc_id, text`` of a table of :func:`encode_documents`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = byte_bpe(vocabulary_path(vocabulary))
        for batch in small(batches):
            text = [bpe.decode(np.frombuffer(x, "<u4")) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(text, pa.string())], ["doc_id", "text"])

    return df.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def round_trip(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = "byte_bpe_50k.json") -> DataFrame:
    """Encode and decode in one pass: counts and SHA-256 digests of ids and of the decoded text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = byte_bpe(vocabulary_path(vocabulary))
        digest = lambda b: hashlib.sha256(b).hexdigest()
        for batch in small(batches):
            data, offsets = utf8(batch.column(1))
            raw = [data[a:b].tobytes() for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
            n, of_ids, of_text = [], [], []
            for ids in bpe.encode_all(raw):
                n.append(len(ids))
                of_ids.append(digest(ids.tobytes()))
                of_text.append(digest(bpe.decode(ids).encode()))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n, pa.int64()), pa.array(of_ids, pa.string()), pa.array(of_text, pa.string())],
                ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    return id_text(df, id_col, text_col).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
