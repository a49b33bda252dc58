"""Dense encodings of texts behind one protocol, and vector helpers."""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Iterator
from typing import Protocol

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpuskit.functions.tokens import let

_WORD = re.compile(r"[^\W_]+")
#: Capitals whose lower case is another one in its context, or more than one letter, and the plain lower case that SQL has for them.
_CAPITALS, _SMALL = "\u0130\u03a3", "i\u03c3"
_PLAIN = str.maketrans(_CAPITALS, _SMALL)


class Encoder(Protocol):
    """Anything that turns texts into rows of floats; it is loaded once in each Python worker."""

    dim: int

    def __call__(self, texts: list[str]) -> np.ndarray: ...


class HashingEncoder:
    """Signed feature hashing of lower-cased words with weight 1 + ln(count); a deterministic stand-in for a learned encoder.

    A text whose signed features cancel out, such as a word that meets the prefix with the
    other sign, takes them without signs, so each text with a word has a unit vector.
    """

    def __init__(self, dim: int = 1024, signed: bool = True, ngrams: bool = False):
        self.dim, self.signed, self.ngrams = dim, signed, ngrams
        self._places: dict[str, tuple[int, int]] = {}

    def _place(self, word: str) -> tuple[int, int]:
        if word not in self._places:
            if len(self._places) > 500_000:
                self._places.clear()
            h = int(hashlib.md5(word.encode()).hexdigest()[:8], 16)
            self._places[word] = (h % self.dim, -1 if self.signed and (h // self.dim) % 2 else 1)
        return self._places[word]

    def features(self, text: str) -> Counter:
        words = _WORD.findall(text.translate(_PLAIN).lower() if not text.isascii() else text.lower())
        out = Counter(words)
        if self.ngrams:
            out.update(w[i : i + 3] for w in words for i in range(len(w) - 2))
        return out

    def signed_features(self, text: str) -> tuple[list[int], list[float]]:
        """The places that a text's features meet, and their unit weights as 32-bit floats: all 0 where they cancel out."""
        sums: dict[int, float] = {}
        for word, n in self.features(text).items():
            at, sign = self._place(word)
            sums[at] = sums.get(at, 0.0) + sign * (1 + math.log(n))
        v = np.array(list(sums.values()))
        norm = math.sqrt((v * v).sum())
        return list(sums), (v / (norm or 1)).astype(np.float32).tolist()

    def __call__(self, texts: list[str]) -> np.ndarray:
        out = np.zeros((len(texts), self.dim), np.float64)
        for row, text in zip(out, texts, strict=True):
            for word, n in self.features(text).items():
                at, sign = self._place(word)
                row[at] += sign * (1 + math.log(n))
            if not row.any():
                for word, n in self.features(text).items():
                    row[self._place(word)[0]] += 1 + math.log(n)
        norm = np.sqrt((out * out).sum(1, keepdims=True))
        return (out / np.where(norm == 0, 1, norm)).astype(np.float32)


def embed(df: DataFrame, text: str, encoder: Encoder, prefix: str = "passage: ", max_tokens: int = 512, out: str = "embedding") -> DataFrame:
    """``df`` with a unit vector for each text, computed in Arrow batches; null texts have none."""
    schema = df.withColumn(out, F.lit(None).cast("array<float>")).schema

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            texts = [prefix + " ".join(t.split()[:max_tokens]) if t is not None else "" for t in b[text]]
            vectors = encoder(texts)
            yield b.assign(**{out: [None if t is None else v for t, v in zip(b[text], vectors, strict=True)]})

    return df.mapInPandas(run, schema)


def embed_queries(df: DataFrame, text: str, encoder: Encoder, prefix: str = "query: ", max_tokens: int = 512) -> DataFrame:
    return embed(df, text, encoder, prefix, max_tokens)


def embed_places(df: DataFrame, text: str, encoder: HashingEncoder, prefix: str = "passage: ", max_tokens: int = 512) -> DataFrame:
    """``df`` with each text's hashed features as parallel arrays ``places`` and ``weights``; null texts have none."""
    schema = df.withColumns({"places": F.lit(None).cast("array<int>"), "weights": F.lit(None).cast("array<float>")}).schema

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            coded = [(None, None) if t is None else encoder.signed_features(prefix + " ".join(t.split()[:max_tokens])) for t in b[text]]
            yield b.assign(places=[p for p, _ in coded], weights=[w for _, w in coded])

    return df.mapInPandas(run, schema)


def embed_abstracts(df: DataFrame, encoder: Encoder, min_chars: int = 1000, text: str = "abstract") -> DataFrame:
    """A vector for abstracts of at least ``min_chars``; an empty array for empty ones, NULL for short ones."""
    long_ = F.when(F.length(text) >= min_chars, F.col(text))
    coded = embed(df.withColumn("_long", long_), "_long", encoder, out="abstract_embedding").drop("_long")
    return coded.withColumn("abstract_embedding", F.when(F.length(text) == 0, F.array().cast("array<float>")).otherwise(F.col("abstract_embedding")))


def norm(v: str | Column) -> Column:
    return F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))


def l2_normalise(v: str) -> Column:
    """The unit vector as floats; NULL for a zero vector."""
    return let(norm(v), lambda n: F.when(n > 0, F.transform(v, lambda x: (x.cast("double") / n).cast("float"))))


def hash_features(df: DataFrame, dim: int = 64, text: str = "text", key: str = "doc_id", signed: bool = True) -> DataFrame:
    """The hashing encoder without its normalisation as an aggregation: ``key, bucket, value``."""
    words = df.select(key, F.explode(F.regexp_extract_all(F.lower(F.translate(text, _CAPITALS, _SMALL)), F.lit(r"[\p{L}\p{N}]+"), F.lit(0))).alias("w"))
    h = F.conv(F.substring(F.md5(F.col("w")), 1, 8), 16, 10).cast("long")
    sign = F.when((F.floor(h / dim) % 2 == 1) & F.lit(signed), -1.0).otherwise(1.0)
    counted = words.groupBy(key, "w").agg(F.count("*").alias("n"))
    weight = sign * (1 + F.ln("n"))
    return counted.groupBy(key, (h % dim).cast("int").alias("bucket")).agg(F.sum(weight).alias("value"))


def tfidf(df: DataFrame, dim: int = 4096, text: str = "text"):
    """Hashed TF-IDF vectors of Spark ML: the fitted model and the transformed rows."""
    from pyspark.ml import Pipeline
    from pyspark.ml.feature import IDF, HashingTF, RegexTokenizer

    steps = [RegexTokenizer(inputCol=text, outputCol="_w", pattern=r"[^\p{L}\p{N}]+", minTokenLength=1), HashingTF(inputCol="_w", outputCol="_tf", numFeatures=dim), IDF(inputCol="_tf", outputCol="embedding")]
    model = Pipeline(stages=steps).fit(df)
    return model, model.transform(df).drop("_w", "_tf")


def word2vec(df: DataFrame, dim: int = 32, seed: int = 42, text: str = "text", part_rows: int = 8192):
    """Averaged word vectors of Spark ML, fitted on all rows.

    About ``part_rows`` rows train in one task, and the tasks' vectors are averaged: a
    single task, as Spark ML has it by default, would take the whole corpus.
    """
    from pyspark.ml.feature import Word2Vec

    words = df.withColumn("_w", F.split(F.lower(F.col(text)), r"[^\p{L}\p{N}]+"))
    parts = max(1, -(-df.count() // part_rows))
    model = Word2Vec(vectorSize=dim, seed=seed, inputCol="_w", outputCol="embedding", minCount=3, maxIter=1, numPartitions=parts).fit(words)
    return model, model.transform(words).drop("_w")
