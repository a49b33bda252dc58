"""SQL surface: temporary SQL functions that stay in the JVM, vectorised functions, and table functions."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf
from pyspark.sql.types import ArrayType, DoubleType, FloatType

from corpuskit.functions.tokens import WORDPUNCT

_SQL_FUNCTIONS = {
    "cosine": """(a ARRAY<FLOAT>, b ARRAY<FLOAT>) RETURNS DOUBLE RETURN
        aggregate(zip_with(a, b, (x, y) -> CAST(x AS DOUBLE) * y), CAST(0 AS DOUBLE), (s, x) -> s + x)
        / sqrt(aggregate(a, CAST(0 AS DOUBLE), (s, x) -> s + CAST(x AS DOUBLE) * x) * aggregate(b, CAST(0 AS DOUBLE), (s, x) -> s + CAST(x AS DOUBLE) * x))""",
    "n_tokens": r"(t STRING) RETURNS INT RETURN size(regexp_extract_all(t, '[\\p{L}\\p{N}]+|[^\\p{L}\\p{N}\\s]', 0))",
    "license_family": "(code STRING) RETURNS STRING RETURN CASE WHEN code LIKE 'ATTR%' THEN 'attribution' WHEN code IN ('ZERO', 'PUBLIC_DOMAIN') THEN 'free' ELSE 'other' END",
}


@udtf(returnType="chunk_no: int, text: string, n_tokens: int")
class ChunkText:
    """Token windows of a text with overlap, as a table function for lateral joins."""

    def eval(self, text: str, max_tokens: int, overlap: int):
        words = re.findall(r"[^\W_]+|[^\w \t-\r]|_", text or "")
        stride = max(1, max_tokens - overlap)
        for n, i in enumerate(range(0, max(1, len(words) - overlap), stride), 1):
            own = words[i : i + max_tokens]
            if own:
                yield n, " ".join(own), len(own)


@udtf(returnType="gram: string")
class Ngrams:
    def eval(self, text: str, n: int):
        words = re.findall(r"[^\W_]+", (text or "").lower())
        for i in range(len(words) - n + 1):
            yield (" ".join(words[i : i + n]),)


@F.pandas_udf(ArrayType(FloatType()))
def encode_text(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
    """Hashed unit vectors; the encoder is made once for each worker."""
    from corpuskit.plans.encode import HashingEncoder

    encoder = HashingEncoder(64)
    for texts in batches:
        yield pd.Series(list(encoder([t or "" for t in texts])))


def soft_f1(candidate: list[str], reference: list[str], encoder) -> float:
    """Soft matching of two word lists: each word takes its most similar counterpart."""
    import numpy as np

    if not candidate or not reference:
        return 0.0
    a, b = np.asarray(encoder(candidate), float), np.asarray(encoder(reference), float)
    s = a @ b.T
    p, r = s.max(1).mean(), s.max(0).mean()
    return float(2 * p * r / (p + r)) if p + r else 0.0


@F.pandas_udf(DoubleType())
def soft_match(candidate: pd.Series, reference: pd.Series) -> float:
    """Grouped aggregate: the mean soft-match F1 of the group's pairs of texts."""
    from corpuskit.plans.encode import HashingEncoder

    encoder = HashingEncoder(32, ngrams=True)
    words = lambda t: re.findall(r"[^\W_]+", (t or "").lower())
    scores = [soft_f1(words(c), words(r), encoder) for c, r in zip(candidate, reference, strict=True)]
    return float(sum(scores) / len(scores)) if scores else 0.0


def register(spark: SparkSession) -> None:
    """Make all functions known to the session's SQL."""
    for name, body in _SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("chunk_text", ChunkText)
    spark.udtf.register("ngrams", Ngrams)
    spark.udf.register("encode_text", encode_text)
    spark.udf.register("soft_match", soft_match)


def engine_sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    """SQL over the given tables and the adapter views, with the functions above."""
    from corpuskit.sources import adapters as A
    from corpuskit.sources.tables import TABLES, read_table

    register(spark)
    frames = {n: read_table(spark, sf_dir, n) for n in TABLES if "{" + n + "}" in text}
    views = {"papers": A.papers, "abstracts": A.abstracts, "fulltexts": A.fulltexts, "license_reports": A.license_reports, "vector_labels": A.vector_labels}
    frames |= {n: f(spark, sf_dir) for n, f in views.items() if "{" + n + "}" in text}
    return spark.sql(text, **frames)


__all__ = ["WORDPUNCT", "ChunkText", "Ngrams", "encode_text", "engine_sql", "register", "soft_f1", "soft_match"]
