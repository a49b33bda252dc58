"""Licence screening by agreement of independent sources.

A label is accepted only if at least two sources support it and no other source that knows
the paper contradicts it. A source without a report neither supports nor contradicts.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpuskit.sources.adapters import SERVICES

#: The codes that the screening accepts.
STUDY_ALLOW = ("ATTR", "ATTR_SA", "ZERO", "PUBLIC_DOMAIN", "GOV_WORK", "ATTR_NC", "ATTR_NC_SA")
_RULES = (
    ("ZERO", r"cc0|publicdomain/zero|\bzero\b"),
    ("PUBLIC_DOMAIN", r"public[ _-]?domain|\bpdm\b"),
    ("GOV_WORK", r"us[ -]?gov|government work"),
    ("ATTR_NC_ND", r"by[ -]nc[ -]nd"),
    ("ATTR_NC_SA", r"by[ -]nc[ -]sa"),
    ("ATTR_NC", r"by[ -]nc"),
    ("ATTR_ND", r"by[ -]nd"),
    ("ATTR_SA", r"by[ -]sa"),
    ("ATTR", r"(cc|licenses)[ /-]*by\b|creative commons attribution"),
)


def normalise(raw: str | Column, keep_version: bool = False) -> Column:
    """Controlled code of a raw spelling; UNKNOWN for what no rule knows, NULL for NULL."""
    text = F.lower(F.trim(raw if isinstance(raw, Column) else F.col(raw)))
    out = F.when(text.isNull(), F.lit(None))
    for code, pattern in _RULES:
        out = out.when(text.rlike(pattern), code)
    out = out.when(text.rlike(r"^(all rights reserved|publisher[ -]specific.*|.*user-licen[sc]e.*)$"), "OTHER").otherwise("UNKNOWN")
    if keep_version:
        version = F.regexp_extract(text, r"(\d\.\d)", 1)
        out = F.when(out.isNotNull() & (version != ""), F.concat(out, F.lit("-"), version)).otherwise(out)
    return out


def normalise_sql(raw: str) -> str:
    """The same rules for DuckDB."""
    cases = " ".join(f"WHEN regexp_matches(lower(trim({raw})), '{p}') THEN '{c}'" for c, p in _RULES)
    return f"CASE WHEN {raw} IS NULL THEN NULL {cases} WHEN regexp_matches(lower(trim({raw})), '^(all rights reserved|publisher[ -]specific.*|.*user-licen[sc]e.*)$') THEN 'OTHER' ELSE 'UNKNOWN' END"


def canonical_doi(doi: Column) -> Column:
    return F.regexp_replace(F.lower(F.trim(doi)), r"^(https?://(dx\.)?doi\.org/|doi:)\s*", "")


def collect_reports(papers: DataFrame, sources: dict[str, DataFrame]) -> DataFrame:
    """Wide reports: each source is looked up by canonical DOI. Only (corpus_id, doi) is shuffled, never a text."""
    out = papers.select("corpus_id", canonical_doi(F.col("doi")).alias("doi"))
    for name, frame in sources.items():
        reports = frame.select(canonical_doi(F.col("doi")).alias("doi"), F.col("raw").alias(name)).groupBy("doi").agg(F.min(name).alias(name))
        out = out.join(reports, "doi", "left")
    return out.select("corpus_id", "doi", *sources)


def widen(tall: DataFrame) -> DataFrame:
    """``corpus_id`` and one column of normalised codes for each service."""
    coded = tall.withColumn("code", normalise("raw"))
    return coded.groupBy("corpus_id").agg(*[F.max(F.when(F.col("service") == s, F.col("code"))).alias(s) for s in SERVICES])


def decide(wide: DataFrame, min_agree: int = 2, veto: bool = True, unknown: str = "neutral", priority: tuple[str, ...] | None = None) -> DataFrame:
    """``license, supporters, outcome`` for each row of codes, computed inside the row.

    ``veto=False`` lets a majority win in spite of a contradiction. ``priority`` takes the
    first source that knows the paper. ``unknown='veto'`` makes an unknown token block.
    """
    services = [s for s in SERVICES if s in wide.columns]
    codes = F.array(*services)
    known = F.filter(codes, lambda c: c.isNotNull() & (c != "UNKNOWN"))
    present = F.filter(codes, lambda c: c.isNotNull())
    kinds = F.array_distinct(known)
    votes = lambda c: F.size(F.filter(known, lambda k: k == c))
    if priority:
        first = F.coalesce(*[F.when(F.col(s) != "UNKNOWN", F.col(s)) for s in priority])
        label = first
    elif veto:
        label = F.when((F.size(kinds) == 1) & (F.size(known) >= min_agree), kinds[0])
    else:
        label = F.try_element_at(F.filter(kinds, lambda k: votes(k) >= min_agree), F.lit(1))
    if unknown == "veto":
        label = F.when(F.size(present) == F.size(known), label)
    outcome = (
        F.when(F.col("license").isNotNull(), "label")
        .when(F.size("present") == 0, "no_evidence")
        .when((F.size("known") == 0) | ((F.lit(unknown) == "veto") & (F.size("present") > F.size("known"))), "indeterminate")
        .when(F.size(F.array_distinct("known")) > 1, "conflict")
        .otherwise("insufficient")
    )
    supporters = F.array_join(F.filter(F.array(*[F.when(F.col(s) == F.col("license"), F.lit(s)) for s in services]), lambda x: x.isNotNull()), "+")
    base = wide.withColumns({"known": known, "present": present}).withColumn("license", label)
    return base.withColumns({"outcome": outcome, "supporters": F.when(F.col("license").isNotNull(), supporters)}).drop("known", "present")


def screen(decisions: DataFrame, allow: tuple[str, ...] = STUDY_ALLOW) -> DataFrame:
    """``kept`` and, for the others, a reason: restrictive, conflict, indeterminate, insufficient or no_evidence."""
    kept = F.coalesce(F.col("license").isin(*allow), F.lit(False))
    return decisions.withColumns({"kept": kept, "reason": F.when(kept, F.lit(None)).when(F.col("license").isNotNull(), "restrictive").otherwise(F.col("outcome"))})


def coverage(wide: DataFrame, everyone: DataFrame) -> DataFrame:
    """Counts for each pattern of services that report anything; bit *i* stands for service *i*."""
    bits = [F.when(F.col(s).isNotNull(), 1 << i).otherwise(0) for i, s in enumerate(SERVICES)]
    mask = sum(bits[1:], bits[0])
    rows = everyone.select("corpus_id").join(wide, "corpus_id", "left").select(mask.alias("mask"))
    return rows.groupBy(F.col("mask").cast("int").alias("mask")).agg(F.count("*").alias("n"))


def resolution_mix(decisions: DataFrame) -> DataFrame:
    return _shares(decisions.filter("license is not null").groupBy("supporters").agg(F.count("*").alias("n")), "supporters")


def type_mix(decisions: DataFrame) -> DataFrame:
    return _shares(decisions.filter("license is not null").groupBy("license").agg(F.count("*").alias("n")), "license")


def _shares(counts: DataFrame, key: str) -> DataFrame:
    total = counts.agg(F.sum("n").alias("total"))
    share = F.floor(F.col("n") * 1000000.0 / F.col("total") + 0.5) / 1000000
    return counts.crossJoin(F.broadcast(total)).select(key, "n", share.cast("double").alias("share"))


def consensus(votes: DataFrame, key: str = "key", value: str = "value", min_agree: int = 2) -> DataFrame:
    """The rule for any number of voters. Three mergeable numbers for each key suffice: votes, least and greatest value."""
    g = votes.groupBy(key).agg(F.count(value).alias("votes"), F.min(value).alias("low"), F.max(value).alias("high"))
    label = F.when((F.col("votes") >= min_agree) & (F.col("low") == F.col("high")), F.col("low"))
    outcome = F.when(label.isNotNull(), "label").when(F.col("votes") == 0, "no_evidence").when(F.col("low") != F.col("high"), "conflict").otherwise("insufficient")
    return g.select(key, F.col("votes").cast("long").alias("votes"), label.alias("label"), outcome.alias("outcome"))


def drift(old: DataFrame, new: DataFrame, key: str = "corpus_id", value: str = "license") -> DataFrame:
    """What a newer snapshot changes: upgraded (now a label), revoked, changed, unchanged; counts by kind."""
    o, n = old.select(key, F.col(value).alias("o")), new.select(key, F.col(value).alias("n"))
    kind = (
        F.when(F.col("o").eqNullSafe(F.col("n")), "unchanged").when(F.col("o").isNull(), "upgraded").when(F.col("n").isNull(), "revoked").otherwise("changed")
    )
    return o.join(n, key, "full").groupBy(kind.alias("kind")).agg(F.count("*").alias("n"))
