"""Lexical and semantic trend analysis over years."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def resolve_year(year: Column, published: Column, publication_date: Column) -> Column:
    """The first of three metadata fields that gives a plausible year."""
    def of(c: Column) -> Column:
        y = F.substring(F.trim(c), 1, 4).try_cast("int")
        return F.when(y.between(1500, 2100), y)

    return F.coalesce(of(year), of(published), of(publication_date))


def flag(chunks: DataFrame, patterns: dict[str, str], anchor: str | None = None, sections: tuple[str, ...] | None = None, text: str = "text", header: str = "header") -> DataFrame:
    """A boolean column for each pattern: it and the anchor occur in the same passage of a relevant section.

    ``sections`` are canonical names; a passage is relevant if its normalised header is one of them.
    """
    from corpuskit.plans.structure import canonical_header

    where = F.lit(True) if anchor is None else F.col(text).rlike(anchor)
    if sections:
        where = where & F.coalesce(canonical_header(F.col(header)).isin(*sections), F.lit(False))
    return chunks.withColumns({n: where & F.col(text).rlike(p) for n, p in patterns.items()})


def sentences(df: DataFrame, text: str = "text") -> DataFrame:
    return df.withColumn("sentence", F.explode(F.regexp_extract_all(F.col(text), F.lit(r"[^.!?\n]+[.!?]*"), F.lit(0))))


def flag_sentences(df: DataFrame, value: dict[str, str], context: str, cue: str | None = None, text: str = "text") -> DataFrame:
    """Sentences with a value, its context and, if given, an instrument cue, one boolean for each value."""
    s = sentences(df, text)
    near = F.col("sentence").rlike(context)
    if cue:
        near = near & F.col("sentence").rlike(cue)
    return s.withColumns({n: near & F.col("sentence").rlike(p) for n, p in value.items()})


def flag_semantic(df: DataFrame, concept: list[float], threshold: float, vector: str = "embedding", name: str = "hit") -> DataFrame:
    """Similarity to a concept vector in place of a pattern; unit vectors are assumed."""
    from corpuskit.plans.search import dot_with

    return df.withColumn(name, dot_with(vector, concept) >= threshold)


def per_document(flags: DataFrame, names: list[str], key: str = "corpus_id") -> DataFrame:
    return flags.groupBy(key).agg(*[F.bool_or(n).alias(n) for n in names])


def yearly(docs: DataFrame, names: list[str], year: str = "year") -> DataFrame:
    """Counts of documents by year, and each flag's share among the flagged."""
    g = docs.filter(F.col(year).isNotNull()).groupBy(year).agg(*[F.count_if(n).cast("long").alias(n) for n in names])
    total = sum((F.col(n) for n in names[1:]), F.col(names[0]))
    return g.withColumns({f"{n}_share": F.try_divide(F.col(n), total) for n in names})


def densify(series: DataFrame, names: list[str], year: str = "year") -> DataFrame:
    """Every year between the first and the last; the counts of missing ones are 0."""
    span = series.agg(F.min(year).alias("lo"), F.max(year).alias("hi")).filter("lo is not null")
    years = span.select(F.explode(F.sequence("lo", "hi")).alias(year))
    return years.join(series.select(year, *names), year, "left").na.fill(0, names)


def smooth(series: DataFrame, column: str, width: int = 3, frame: str = "range", edges: str = "shrink", year: str = "year") -> DataFrame:
    """Centred moving average over a yearly series, which is small by nature."""
    half = width // 2
    w = Window.partitionBy(F.lit(0)).orderBy(year)
    w = w.rangeBetween(-half, half) if frame == "range" else w.rowsBetween(-half, half)
    mean = F.avg(column).over(w)
    if edges == "null":
        mean = F.when(F.count(column).over(w) == width, mean)
    return series.withColumn(f"{column}_smooth", mean)


def expand_terms(df: DataFrame, seed: str, k: int = 10, min_docs: int = 3, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Words that occur with a seed word more than by chance, by pointwise mutual information over documents."""
    words = df.select(key, F.explode(F.array_distinct(F.regexp_extract_all(F.lower(F.col(text)), F.lit(r"\p{L}+"), F.lit(0)))).alias("word"))
    n = df.agg(F.count_distinct(key).alias("n"))
    with_seed = words.filter(F.col("word") == seed).select(key)
    total = with_seed.agg(F.count("*").alias("s"))
    near = words.join(with_seed.withColumn("hit", F.lit(1)), key, "left").groupBy("word").agg(F.count("*").alias("docs"), F.count("hit").alias("both"))
    scored = near.filter((F.col("word") != seed) & (F.col("both") >= min_docs)).crossJoin(F.broadcast(n)).crossJoin(F.broadcast(total))
    pmi = F.floor(F.log2(F.col("both") * F.col("n") / (F.col("docs") * F.col("s"))) * 1000000 + 0.5) / 1000000
    return scored.select("word", "docs", "both", pmi.alias("pmi")).orderBy(F.col("pmi").desc(), F.col("both").desc(), "word").limit(k)


def link_entities(chunks: DataFrame, registry: DataFrame, n: int = 2, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Dictionary links: word n-grams of the texts equi-joined with the names of a registry(entity_id, name)."""
    words = F.regexp_extract_all(F.lower(F.col(text)), F.lit(r"[\p{L}\p{N}]+"), F.lit(0))
    grams = F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - n + 1, F.lit(1))), lambda i: F.array_join(F.slice("w", i, n), " "))
    have = chunks.select(key, words.alias("w")).select(key, F.explode(F.array_distinct(grams)).alias("name"))
    return have.join(registry.select("entity_id", F.lower("name").alias("name")), "name").select(key, "entity_id").distinct()
