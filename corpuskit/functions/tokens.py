"""Token counters and n-grams as column expressions that stay in the JVM, with their DuckDB twins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: White space as SQL has it: unlike Java's ``\s``, without the vertical tab, which is a token of its own.
SPACE = r" \t\n\f\r"
WORDPUNCT = rf"[\p{{L}}\p{{N}}]+|[^\p{{L}}\p{{N}}{SPACE}]"
WORDS = r"[\p{L}\p{N}]+"
SENTENCE = r"[^.!?\n]+[.!?]*"


#: A token with the white space behind it: the pieces of a text, put together, are the text again.
PIECES = {
    "wordpunct": rf"(?:[\p{{L}}\p{{N}}]+|[^\p{{L}}\p{{N}}{SPACE}])[{SPACE}]*",
    "whitespace": rf"[^{SPACE}]+[{SPACE}]*",
    "subword": rf"(?:[\p{{L}}\p{{N}}]{{1,4}}|[^\p{{L}}\p{{N}}{SPACE}])[{SPACE}]*",
}


def _all(text: Column, pattern: str) -> Column:
    return F.regexp_extract_all(text, F.lit(pattern), F.lit(0))


def tokenize(text: Column, scheme: str = "wordpunct") -> Column:
    """Tokens of a text: words and marks, white-space words, or words cut into pieces of up to four letters."""
    if scheme == "wordpunct":
        return _all(text, WORDPUNCT)
    if scheme == "whitespace":
        return _all(text, rf"[^{SPACE}]+")
    if scheme == "subword":
        return _all(text, rf"[\p{{L}}\p{{N}}]{{1,4}}|[^\p{{L}}\p{{N}}{SPACE}]")
    raise ValueError(f"no token scheme {scheme}")


def count(text: Column, scheme: str = "wordpunct") -> Column:
    return F.coalesce(F.size(tokenize(text, scheme)), F.lit(0))


def pieces(text: Column, scheme: str = "wordpunct") -> Column:
    """The tokens of a text, each with the white space that follows it; empty for NULL."""
    if scheme not in PIECES:
        raise ValueError(f"no token scheme {scheme}")
    return F.coalesce(_all(text, PIECES[scheme]), F.array().cast("array<string>"))


def let(value: Column, body) -> Column:
    """``body(value)`` with the value worked out once, not for each use inside a lambda."""
    return F.element_at(F.transform(F.array(value), lambda v: body(v)), 1)


def once(df: DataFrame, **columns: Column) -> DataFrame:
    """``df`` with further columns that are worked out once for each row.

    The optimizer puts a column's expression wherever the column is used, also into the body
    of a lambda, where it would run for each element. A generator of one element stands in
    the way of that, and moves no row.
    """
    made = F.explode(F.array(F.struct(*[c.alias(n) for n, c in columns.items()])))
    return df.select("*", made.alias("_once")).select("*", "_once.*").drop("_once")


def ngrams(words: Column, n: int) -> Column:
    """Joined n-grams; empty for shorter lists."""

    def of(w: Column) -> Column:
        at = F.when(F.size(w) >= n, F.sequence(F.lit(1), F.size(w) - (n - 1))).otherwise(F.array().cast("array<int>"))
        return F.transform(at, lambda i: F.array_join(F.slice(w, i, F.lit(n)), " "))

    return let(words, of)


def round6(c: Column) -> Column:
    """Rounding that both engines do alike, without negative zero."""
    return F.floor(c * 1000000 + 0.5) / 1000000 + F.lit(0.0)
