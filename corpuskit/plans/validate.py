"""Validation in nine areas. Each check is a column of codes over one pass; reports are unions of (area, id, status, codes)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpuskit.functions.tokens import SENTENCE, SPACE, WORDS, let
from corpuskit.sources.adapters import dot


def codes(**tests: Column) -> Column:
    """Names of the tests that hold, in the order given."""
    return F.filter(F.array(*[F.when(t, F.lit(n)) for n, t in tests.items()]), lambda c: c.isNotNull())


def status(found: Column, hard: tuple[str, ...] = (), soft_name: str = "warn", hard_name: str = "fail") -> Column:
    hit = F.exists(found, lambda c: c.isin(*hard)) if hard else F.lit(False)
    return F.when(hit, hard_name).when(F.size(found) > 0, soft_name).otherwise("pass")


# ---------------------------------------------------------------------------------- areas


def schema(records: DataFrame, dim: int, min_chars: int = 1000) -> DataFrame:
    """Mandatory fields, lengths and omissions: A empty abstract, B short vector, C short abstract, D missing vector key, E missing subfields."""
    n = F.length("abstract")
    c = codes(
        A=n == 0, B=F.coalesce(F.size("abstract_embedding") < dim, F.lit(False)) & F.col("abstract_embedding").isNotNull(),
        C=(n > 0) & (n < min_chars), D=F.col("abstract_embedding").isNull(), E=F.col("subfields").isNull(),
        F=F.col("title").isNull() | F.col("full_text").isNull() | (F.size("paragraphs") != F.size("paragraph_embeddings")),
    )
    return records.select(F.col("corpus_id").alias("id"), c.alias("codes")).withColumn("status", status(F.col("codes"), ("F",), "incomplete"))


def metadata(papers: DataFrame, license_: str = "license") -> DataFrame:
    t = F.trim("title")
    c = codes(
        no_title=F.coalesce(F.length(t) == 0, F.lit(True)), short_title=(F.length(t) > 0) & (F.length(t) < 5), no_authors=F.size("authors") == 0,
        bad_authors=F.exists("authors", lambda a: F.trim(a) == ""), no_venue=F.col("venue").isNull(), no_date=F.col("publication_date").isNull(),
        no_doi=F.col("doi").isNull(), bad_doi=F.col("doi").isNotNull() & ~F.col("doi").rlike(r"^10\.\d{4,9}/\S+$"), no_license=F.col(license_).isNull(),
    )
    return papers.select(F.col("corpus_id").alias("id"), c.alias("codes")).withColumn("status", status(F.col("codes")))


def subfields(records: DataFrame, vocabulary: tuple[str, ...], min_chars: int = 1000) -> DataFrame:
    """Labels in the vocabulary, scores in [0, 1], present exactly for eligible abstracts."""
    eligible = F.length("abstract") >= min_chars
    c = codes(
        foreign_label=F.size(F.array_except(F.map_keys("subfields"), F.array(*map(F.lit, vocabulary)))) > 0,
        bad_score=F.exists(F.map_values("subfields"), lambda s: (s < 0) | (s > 1) | F.isnan(s)),
        missing=eligible & F.col("subfields").isNull(), unexpected=~eligible & F.col("subfields").isNotNull(), omitted=~eligible & F.col("subfields").isNull(),
    )
    return records.select(F.col("corpus_id").alias("id"), c.alias("codes")).withColumn("status", status(F.col("codes"), ("foreign_label", "bad_score", "missing", "unexpected"), "incomplete"))


@dataclass(frozen=True)
class TextLimits:
    min_chars: int = 100
    max_chars: int = 1_000_000
    max_replacement: float = 0.001
    max_non_ascii: float = 0.30
    max_space: float = 0.40
    language: str = "en"


#: The words by which the four languages of the corpus are told apart.
LANGUAGE_WORDS = {
    "en": ("the", "of", "and", "to", "in", "that", "is", "was", "for", "with"),
    "fr": ("le", "la", "les", "des", "du", "et", "une", "que", "qui", "dans"),
    "de": ("der", "die", "das", "und", "den", "von", "mit", "sich", "nicht", "zu"),
    "es": ("el", "los", "las", "y", "del", "por", "con", "una", "que", "se"),
}


def language(text: Column) -> Column:
    """The language whose frequent words occur most; ties go to the first in alphabetical order, no hit gives NULL.

    One pass keeps the few words that belong to any list; the languages are counted in those.
    """
    every = sorted({w for own in LANGUAGE_WORDS.values() for w in own})

    def best(found: Column) -> Column:
        hits = [F.struct((-F.size(F.filter(found, lambda w: w.isin(*own)))).alias("n"), F.lit(code).alias("code")) for code, own in sorted(LANGUAGE_WORDS.items())]
        return let(F.array_min(F.array(*hits)), lambda b: F.when(b["n"] < 0, b["code"]))

    return let(F.regexp_extract_all(F.lower(text), F.lit(rf"(?<![\p{{L}}\p{{N}}])({'|'.join(every)})(?![\p{{L}}\p{{N}}])"), F.lit(1)), best)


def text_quality(df: DataFrame, limits: TextLimits | None = None, text: str = "text", key: str = "corpus_id") -> DataFrame:
    """Length, encoding, character mix and language of each text, with codes for what is out of bounds."""
    lim, t = limits or TextLimits(), F.col(text)
    n = F.length(t)
    m = df.select(
        F.col(key).alias("id"), n.cast("long").alias("n_chars"), F.regexp_count(t, F.lit(SENTENCE)).cast("long").alias("n_sentences"),
        (n - F.length(F.regexp_replace(t, "�", ""))).cast("long").alias("n_replacement"), F.length(F.regexp_replace(t, r"[\x00-\x7F]", "")).cast("long").alias("n_non_ascii"),
        (n - F.length(F.regexp_replace(t, f"[{SPACE}]", ""))).cast("long").alias("n_space"), language(t).alias("language"),
    )
    over = lambda c, share: F.coalesce(F.try_divide(c, F.col("n_chars")) > share, F.lit(False))
    c = codes(
        empty=F.col("n_chars") == 0, short=(F.col("n_chars") > 0) & (F.col("n_chars") < lim.min_chars), long=F.col("n_chars") > lim.max_chars,
        replacement=over(F.col("n_replacement"), lim.max_replacement), non_ascii=over(F.col("n_non_ascii"), lim.max_non_ascii),
        spaces=over(F.col("n_space"), lim.max_space), language=F.coalesce(F.col("language") != lim.language, F.lit(True)),
    )
    return m.withColumn("codes", c).withColumn("status", status(F.col("codes")))


def alignment(df: DataFrame, abstract: str = "abstract", text: str = "text", intro_tokens: int = 1000, min_chars: int = 100, key: str = "corpus_id") -> DataFrame:
    """Share of the abstract's words, as a multiset, found in the opening of the full text; NULL without a usable abstract.

    The words of each side are numbered among their equals (the second "the" is another
    token than the first), so the shared multiset is the intersection of two sets, which
    the engine finds by hashing.
    """

    def numbered(words: Column) -> Column:
        # sorted words: a word's number is its distance to the first of its equals
        def of(s: Column) -> Column:
            starts = F.filter(F.transform(s, lambda w, i: F.when((i == 0) | (w != F.get(s, i - 1)), F.struct(w.alias("w"), i.alias("i")))), lambda x: x.isNotNull())
            return let(F.map_from_entries(starts), lambda first: F.transform(s, lambda w, i: F.concat(w, F.lit(" "), (i - F.try_element_at(first, w)).cast("string"))))

        return let(F.array_sort(words), of)

    words = lambda c: F.regexp_extract_all(F.lower(F.col(c)), F.lit(WORDS), F.lit(0))
    rows = df.select(F.col(key).alias("id"), words(abstract).alias("a"), F.slice(words(text), 1, intro_tokens).alias("f"), ((F.length(abstract) >= min_chars) & (F.length(text) > 0)).alias("usable"))
    shared = F.size(F.array_intersect(numbered(F.col("a")), numbered(F.col("f"))))
    recall = F.when(F.col("usable"), F.try_divide(shared, F.size("a")))
    out = rows.select("id", "usable", recall.alias("recall"))
    return out.withColumn("band", F.when(F.col("recall") >= 0.95, "strong").when(F.col("recall") < 0.5, "low").when(F.col("recall").isNotNull(), "middle"))


def alignment_histogram(aligned: DataFrame, flags: DataFrame | None = None, width: float = 0.05) -> DataFrame:
    """Documents by bin of recall, and by flag where flags are given."""
    rows = aligned.filter("recall is not null").withColumn("bin", F.least(F.floor(F.col("recall") / width + 1e-9), F.lit(int(1 / width) - 1)).cast("int"))
    if flags is not None:
        rows = rows.join(flags.select("id", F.explode_outer("codes").alias("code")), "id")
        return rows.groupBy("bin", F.coalesce("code", F.lit("none")).alias("code")).agg(F.count("*").alias("n"))
    return rows.groupBy("bin").agg(F.count("*").alias("n"))


def chunks(table: DataFrame, least: int = 100, most: int = 200) -> DataFrame:
    """By document: chunks, short and long ones, whether the only short one is the last, mean tokens."""
    g = table.groupBy(F.col("corpus_id").alias("id")).agg(
        F.count("*").alias("n"), F.count_if(F.col("n_tokens") < least).alias("short"), F.count_if(F.col("n_tokens") > most).alias("long"),
        F.max_by(F.col("n_tokens") < least, "chunk_no").alias("last_short"), F.avg("n_tokens").alias("mean_tokens"),
    )
    c = codes(one_short_final=(F.col("short") == 1) & F.col("last_short"), short_inside=F.col("short") > F.col("last_short").cast("int"), too_long=F.col("long") > 0)
    return g.withColumn("codes", c).withColumn("status", status(F.col("codes"), ("too_long",)))


def fine_vector(v: str, dim: int) -> Column:
    """Whether a vector is there, has the length, finite components and a norm of 1."""
    fine = (F.size(v) == dim) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.col(v).isNotNull() & F.coalesce(fine, F.lit(False)) & F.coalesce(F.abs(F.sqrt(dot(v, v)) - 1) < 1e-3, F.lit(False))


def passages(checked: DataFrame, key: str = "corpus_id") -> DataFrame:
    """By document: whether each of its passage vectors (a row with ``fine``) is valid."""
    g = checked.groupBy(F.col(key).alias("id")).agg(F.count_if(~F.col("fine")).alias("bad"))
    return g.select("id", codes(invalid=F.col("bad") > 0).alias("codes")).withColumn("status", status(F.col("codes"), ("invalid",)))


def embeddings(expected: DataFrame, stored: DataFrame, dim: int) -> DataFrame:
    """One row: expected ids, missing, extra and invalid vectors (length, finiteness, norm 1)."""
    fine = fine_vector("v", dim)
    met = expected.select("id", F.lit(1).alias("e")).join(stored.select("id", "v", F.lit(1).alias("s")), "id", "full")
    return met.agg(
        F.count("e").alias("expected"), F.count_if(F.col("s").isNull()).alias("missing"), F.count_if(F.col("e").isNull()).alias("extra"),
        F.count_if(F.col("s").isNotNull() & ~F.coalesce(fine, F.lit(False))).alias("invalid"),
    )


def reproduce(stored: DataFrame, again: DataFrame) -> DataFrame:
    """Cosine of stored and regenerated vectors: mean, least, largest drift from 1, correlation of components."""
    both = stored.select("id", F.col("v").alias("a")).join(again.select("id", F.col("v").alias("b")), "id")
    cos = F.try_divide(dot("a", "b"), F.sqrt(dot("a", "a") * dot("b", "b")))
    pairs = both.select(cos.alias("c"), F.arrays_zip("a", "b").alias("z"))
    drift = pairs.agg(F.count("*").alias("n"), F.avg("c").alias("mean"), F.min("c").alias("least"), F.max(F.abs(F.col("c") - 1)).alias("max_drift"))
    r = pairs.select(F.explode("z").alias("z")).agg(F.corr(F.col("z.a").cast("double"), F.col("z.b").cast("double")).alias("pearson"))
    return drift.crossJoin(r)


def ids(records: DataFrame, reports: dict[str, DataFrame]) -> DataFrame:
    """File id equals corpus id, and the DOIs that the services report equal the record's."""
    out = records.select("corpus_id", "filename_id", F.lower("doi").alias("doi"))
    for name, r in reports.items():
        out = out.join(r.select("corpus_id", F.lower("doi").alias(f"_{name}")), "corpus_id", "left")
    differ = [F.col(f"_{n}").isNotNull() & ~F.col(f"_{n}").eqNullSafe(F.col("doi")) for n in reports]
    c = codes(file_id=~F.col("filename_id").eqNullSafe(F.col("corpus_id").cast("string")), **{f"doi_{n}": d for n, d in zip(reports, differ, strict=True)})
    return out.select(F.col("corpus_id").alias("id"), c.alias("codes")).withColumn("status", status(F.col("codes"), ("file_id", *[f"doi_{n}" for n in reports])))


def licensing(records: DataFrame, wide: DataFrame) -> DataFrame:
    """The decision rule, run again, gives the stored label."""
    from corpuskit.plans.licensing import decide

    again = decide(wide).select("corpus_id", F.col("license").alias("again"))
    met = records.select("corpus_id", "license").join(again, "corpus_id", "left")
    c = codes(differs=~F.col("license").eqNullSafe(F.col("again")))
    return met.select(F.col("corpus_id").alias("id"), c.alias("codes")).withColumn("status", status(F.col("codes"), ("differs",)))


# -------------------------------------------------------------------------------- reports


def report(areas: dict[str, DataFrame]) -> DataFrame:
    """Tall report of all areas, with the time of the check."""
    out = None
    for name, df in areas.items():
        rows = df.select(F.lit(name).alias("area"), F.col("id").cast("long").alias("id"), "status", "codes", F.current_timestamp().alias("checked_at"))
        out = rows if out is None else out.unionByName(rows)
    return out


def summary(tall: DataFrame) -> DataFrame:
    """Records by area and status with the rates of passes and warnings, in one small shuffle."""
    kinds = ["pass", "warn", "fail", "incomplete"]
    g = tall.groupBy("area").agg(F.count("*").alias("records"), *[F.count_if(F.col("status") == k).alias(k if k != "pass" else "passed") for k in kinds])
    rate = lambda c: F.floor(F.col(c) * 1000000.0 / F.col("records") + 0.5) / 1000000
    return g.withColumns({"pass_rate": rate("passed"), "warn_rate": rate("warn")})


def cooccurrence(checked: DataFrame) -> DataFrame:
    """For codes i and j: records with both, and that number over the records with i. The pairs are built inside the row."""
    pairs = F.flatten(F.transform("codes", lambda a: F.transform("codes", lambda b: F.struct(a.alias("i"), b.alias("j")))))
    n = checked.select(F.explode(pairs).alias("p")).groupBy("p.i", "p.j").agg(F.count("*").alias("n"))
    own = n.filter("i = j").select("i", F.col("n").alias("of"))
    return n.join(F.broadcast(own), "i").select("i", "j", "n", (F.floor(F.col("n") / F.col("of") * 1000000 + 0.5) / 1000000).alias("share"))


def warnings_histogram(checked: DataFrame) -> DataFrame:
    return checked.groupBy(F.size("codes").alias("warnings")).agg(F.count("*").alias("records"))


def lengths(df: DataFrame, value: str, by: str | None = None, exact: bool = True) -> DataFrame:
    """Quartiles, their range, mean, extremes, zero and small counts of a length.

    ``exact=False`` takes the quartiles from mergeable sketches, for groups too large to sort.
    """
    q = (lambda p: F.percentile(value, p)) if exact else (lambda p: F.percentile_approx(value, F.lit(p), F.lit(10_000)).cast("double"))
    v = F.col(value)
    aggs = [
        F.count("*").alias("n"), q(0.25).alias("q1"), q(0.5).alias("median"), q(0.75).alias("q3"), (q(0.75) - q(0.25)).alias("iqr"), (F.floor(F.avg(v) * 1000 + 0.5) / 1000).alias("mean"),
        F.min(v).cast("long").alias("least"), F.max(v).cast("long").alias("most"), F.count_if(v == 0).alias("zeros"), F.count_if(v < 100).alias("below_100"),
    ]
    return df.groupBy(by).agg(*aggs) if by else df.agg(*aggs)


def log_histogram(df: DataFrame, value: str, per_decade: int = 4) -> DataFrame:
    """Counts by logarithm of a length, for its outliers."""
    bin_ = F.floor(F.log10(F.greatest(F.col(value), F.lit(1))) * per_decade).cast("int")
    return df.groupBy(bin_.alias("bin")).agg(F.count("*").alias("n"))


def clean_view(records: DataFrame, tall: DataFrame, drop: tuple[str, ...] = ("warn", "fail"), key: str = "corpus_id") -> DataFrame:
    """Records that no area marks with one of the statuses."""
    return records.join(tall.filter(F.col("status").isin(*drop)).select(F.col("id").alias(key)).distinct(), key, "left_anti")
