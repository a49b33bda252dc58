"""Token ids of a word-level vocabulary, with a cache of whole words.

The normaliser of such a vocabulary drops white space and no token spans it, so the ids
of a text are the ids of its white-space-separated words, one after the other. Each
distinct word goes through the tokenizers library once while it stays in the cache.
"""

from __future__ import annotations

import gc
import os
import re
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np

#: Unicode white space, as the normaliser's pattern sees it.
_SPACE = re.compile("[\t-\r \x85\xa0  -     　]+")
#: What ``str.split`` takes for white space beyond that.
_SEPARATORS = re.compile("[\x1c-\x1f]")
CACHE_WORDS = 300_000


def vocabulary_path(name: str) -> str:
    """Place of a vocabulary file of the installed public tokenizers."""
    import public_tokenizers

    return public_tokenizers.path(name)


def load_tokenizer(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    tokenizer.no_truncation()
    tokenizer.no_padding()
    return tokenizer


#: Texts of these characters are their own canonical composition and are lower-cased one
#: character at a time, so their pre-tokens can be told without the library.
_SIMPLE = re.compile("[\t-\r -~\u00c0-\u012f\u0131-\u017f]*")
#: Fixed value: the pre-tokenizer's pattern, written for those characters.
_LETTERS = "a-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u017f"
_PRETOKEN = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{_LETTERS}]+|[0-9]|[^\t-\r 0-9{_LETTERS}]+")


def _byte_letters() -> dict[int, str]:
    """How a character beyond ASCII is written in the alphabet of the vocabulary's bytes."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    letter = {b: chr(b) for b in shown} | {b: chr(256 + i) for i, b in enumerate(b for b in range(256) if b not in shown)}
    return {c: "".join(letter[b] for b in chr(c).encode()) for c in range(0xC0, 0x180)}


class WordEncoder:
    """Ids of texts as little-endian 16-bit arrays, equal to the library's.

    Texts of simple characters are split into pre-tokens, texts of other scripts (or that
    may hold a special token) into words; either kind of piece has its own cache.
    """

    def __init__(self, path: str, cache_words: int = CACHE_WORDS):
        self.tokenizer = load_tokenizer(path)
        if self.tokenizer.get_vocab_size() > 1 << 16:
            raise ValueError("the vocabulary needs more than 16 bits")
        # the same model behind white space only, for pre-tokens that are already normal
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import WhitespaceSplit

        self.bare = Tokenizer(self.tokenizer.model)
        self.bare.pre_tokenizer = WhitespaceSplit()
        self.ends_word = np.zeros(1 << 16, bool)
        for token, i in self.tokenizer.get_vocab().items():
            self.ends_word[i] = token.endswith("</w>")
        self.letters = _byte_letters()
        self.cache_words = cache_words
        self.words_known: dict[str, bytes] = {}
        self.pretokens: dict[str, bytes] = {}

    def _learn_pretokens(self, parts: list[str]) -> None:
        """Ids of new pre-tokens, many at a time: each ends at its one token that ends a word."""
        for i in range(0, len(parts), 2048):
            own = parts[i : i + 2048]
            line = " ".join([p if p.isascii() else p.translate(self.letters) for p in own])
            ids = np.array(self.bare.encode_batch_fast([line], add_special_tokens=False)[0].ids, "<u2")
            body, ends = ids.tobytes(), ((np.flatnonzero(self.ends_word[ids]) + 1) * 2).tolist()
            self.pretokens.update(zip(own, [body[a:b] for a, b in zip([0, *ends[:-1]], ends, strict=True)], strict=True))

    def _learn_words(self, words: list[str]) -> None:
        for word, found in zip(words, self.tokenizer.encode_batch_fast(words, add_special_tokens=False), strict=True):
            self.words_known[word] = array("H", found.ids).tobytes()

    @staticmethod
    def words(text: str) -> list[str]:
        if _SEPARATORS.search(text):
            return [w for w in _SPACE.split(text) if w]
        return text.split()

    def _join(self, pieces: list[list[str]], known: dict[str, bytes], learn) -> list[bytes]:
        new = set().union(*pieces).difference(known)
        if len(known) + len(new) > self.cache_words:
            known.clear()
            new = set().union(*pieces)
        if new:
            learn(list(new))
        return [b"".join(map(known.__getitem__, own)) for own in pieces]

    def encode_all(self, texts: list[str | None], at_once: int = 64) -> Iterator[np.ndarray]:
        """Ids of each text, null counting as empty."""
        for i in range(0, len(texts), at_once):
            own = [t or "" for t in texts[i : i + at_once]]
            simple = ["<|" not in t and _SIMPLE.fullmatch(t) is not None for t in own]
            plain = iter(self._join([_PRETOKEN.findall(t.lower()) for t, s in zip(own, simple, strict=True) if s], self.pretokens, self._learn_pretokens))
            other = iter(self._join([self.words(t) for t, s in zip(own, simple, strict=True) if not s], self.words_known, self._learn_words))
            for s in simple:
                yield np.frombuffer(next(plain if s else other), "<u2")


@lru_cache(maxsize=2)
def word_encoder(path: str) -> WordEncoder:
    """One encoder for the life of a worker process, so that later tasks find a warm cache."""
    gc.set_threshold(50_000, 50, 50)  # the caches hold no cycles, and walking them again and again takes time
    return WordEncoder(path)
