"""Selecting the domain and aligning abstracts and full texts by the shared id."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def domain_filter(papers: DataFrame, field: str, match: str = "any") -> DataFrame:
    """Papers of a field: in ``any`` place, as the ``only`` one, or as the ``first`` of their fields."""
    tests = {
        "any": F.exists("fields", lambda f: f == field),
        "only": (F.size("fields") == 1) & (F.try_element_at("fields", F.lit(1)) == field),
        "first": F.try_element_at("fields", F.lit(1)) == field,
    }
    return papers.filter(tests[match])


def align(left: DataFrame, right: DataFrame, on: str = "corpus_id", how: str = "inner") -> DataFrame:
    """Join on the shared id; Catalyst picks the strategy, and bucketed tables need no exchange."""
    return left.join(right, on, how)


def overlap(domain: DataFrame, abstracts: DataFrame, fulltexts: DataFrame) -> DataFrame:
    """One row: papers with only an abstract, only a full text, both, either, neither, and the inclusion-exclusion gap."""
    ids = domain.select("corpus_id").distinct()
    a = abstracts.select("corpus_id").distinct().withColumn("a", F.lit(True))
    f = fulltexts.select("corpus_id").distinct().withColumn("f", F.lit(True))
    flags = ids.join(a, "corpus_id", "left").join(f, "corpus_id", "left").select(F.coalesce("a", F.lit(False)).alias("a"), F.coalesce("f", F.lit(False)).alias("f"))
    n = lambda c: F.count_if(c).cast("long")
    a_, f_ = F.col("a"), F.col("f")
    out = flags.agg(
        F.count("*").alias("domain"), n(a_ & ~f_).alias("abstract_only"), n(f_ & ~a_).alias("fulltext_only"), n(a_ & f_).alias("both"),
        n(a_ | f_).alias("either"), n(~(a_ | f_)).alias("neither"), (n(a_) + n(f_) - n(a_ & f_) - n(a_ | f_)).alias("identity_gap"),
    )
    return out


def backfill(primary: DataFrame, *fallbacks: DataFrame, key: str = "corpus_id", value: str = "abstract") -> DataFrame:
    """The first non-empty value among the sources, and which source gave it (0 is the primary)."""
    out = primary.select(key, F.nullif(F.col(value), F.lit("")).alias("v0"))
    for n, more in enumerate(fallbacks, 1):
        out = out.join(more.select(key, F.nullif(F.col(value), F.lit("")).alias(f"v{n}")), key, "left")
    values = [f"v{n}" for n in range(len(fallbacks) + 1)]
    which = F.coalesce(*[F.when(F.col(v).isNotNull(), n) for n, v in enumerate(values)])
    return out.select(key, F.coalesce(*values).alias(value), which.cast("int").alias("source_no"))


@dataclass(frozen=True)
class Step:
    """A step of the funnel: the condition that a record meets to get through it, and the step its retention is relative to (a position, or None)."""

    name: str
    passed: Column
    reference: int | None = None


def funnel(records: DataFrame, steps: list[Step]) -> DataFrame:
    """Retained records by step, with the percentage of the step named as reference: all steps in one pass over ``records``.

    A record is retained by a step if it meets the step's condition and was retained by
    the step that is its reference.
    """
    met: list[Column] = []
    for s in steps:
        own = F.coalesce(s.passed, F.lit(False))
        met.append(own if s.reference is None else met[s.reference] & own)
    counts = records.agg(*[F.count_if(c).alias(f"n{i}") for i, c in enumerate(met)])
    one = lambda i, s: F.struct(
        F.lit(i + 1).alias("step"), F.lit(s.name).alias("name"), F.col(f"n{i}").alias("retained"), F.lit(None if s.reference is None else s.reference + 1).cast("int").alias("reference"),
        (F.lit(None) if s.reference is None else F.floor(F.try_divide(F.col(f"n{i}") * 10000, F.col(f"n{s.reference}"))) / 100).cast("double").alias("pct"),
    )
    return counts.select(F.explode(F.array(*[one(i, s) for i, s in enumerate(steps)])).alias("s")).select("s.*")


def profile(docs: DataFrame, chunks: DataFrame, dim: int, text: str = "text") -> DataFrame:
    """One row about a corpus: documents, mean and greatest length, chunks and their mean tokens, the vectors' size."""
    n = F.length(text)
    of_docs = docs.agg(F.count("*").alias("docs"), (F.floor(F.avg(n) * 1000 + 0.5) / 1000).alias("mean_chars"), F.max(n).cast("long").alias("max_chars"))
    of_chunks = chunks.agg(F.count("*").alias("chunks"), (F.floor(F.avg("n_tokens") * 1000 + 0.5) / 1000).alias("mean_tokens"))
    return of_docs.crossJoin(of_chunks).withColumn("dim", F.lit(dim))
