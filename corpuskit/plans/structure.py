"""From annotated texts to structured Markdown.

Everything is per document, so it stays inside the row: spans are arrays, sorted once and
cut at the headers, and higher-order functions work on them. Nothing here has an exchange.
The relational forms (one row for each span, paragraph or section) are exploded last.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpuskit.functions.tokens import let, once

KINDS = ("title", "abstract", "section_header", "paragraph")
_SPANS = "array<struct<start: int, end: int>>"
_SPAN_K = "array<struct<start: int, end: int, k: int>>"
BLOCK = 2048
#: Common section names; those that may stay short.
CURATED = (
    "introduction", "background", "related work", "methods", "materials and methods", "experimental", "results", "results and discussion",
    "discussion", "conclusion", "conclusions", "abstract", "references", "acknowledgements", "supplementary",
)
SHORT_OK = ("abstract", "conclusion", "conclusions")


def parse_spans(df: DataFrame) -> DataFrame:
    """``spans``: the annotation strings as arrays; ``bad_json`` where one does not parse."""
    parsed = {k: F.from_json(F.col("annotations")[k], _SPANS, {"mode": "PERMISSIVE"}) for k in KINDS}
    # a list cut short parses to its complete members, so the brackets tell whether it was whole
    whole = [F.col("annotations")[k].isNull() | F.trim(F.col("annotations")[k]).rlike(r"^\[.*\]$") for k in KINDS]
    spans = F.struct(*[F.coalesce(c, F.array().cast(_SPANS)).alias(k) for k, c in parsed.items()])
    ok = whole[0] & whole[1] & whole[2] & whole[3]
    return once(df, spans=spans, bad_json=~ok)


def _cutter(text: Column):
    """``cut(span)``: the text of a span, from blocks of fixed size, so a cut late in a long text does not walk all of it."""

    def of(blocks: Column):
        def cut(s: Column) -> Column:
            first = F.greatest(s["start"], F.lit(0))
            at = F.floor(first / BLOCK).cast("int")
            n = F.floor((F.greatest(s["end"], first + 1) - 1) / BLOCK).cast("int") - at + 1
            near = F.array_join(F.slice(blocks, at + 1, n), "")
            return F.substring(near, first - at * BLOCK + 1, F.greatest(s["end"] - first, F.lit(0)))

        return cut

    return F.coalesce(F.regexp_extract_all(text, F.lit(f"(?s).{{1,{BLOCK}}}"), F.lit(0)), F.array().cast("array<string>")), of


def extract_spans(parsed: DataFrame, text: str = "text") -> DataFrame:
    """One row for each span: ``corpus_id, kind, start, end, text``, in any order; bad documents are left out.

    The texts of the spans are cut inside the row, so the rows carry their own text alone.
    """
    blocks, of = _cutter(F.col(text))

    def spans(b: Column) -> Column:
        cut = of(b)
        one = lambda k: F.transform(F.col("spans")[k], lambda s: F.struct(F.lit(k).alias("kind"), s["start"].alias("start"), s["end"].alias("end"), cut(s).alias("text")))
        return F.flatten(F.array(*map(one, KINDS)))

    rows = parsed.filter("not bad_json").select("corpus_id", F.explode(let(blocks, spans)).alias("s"))
    return rows.select("corpus_id", "s.kind", "s.start", "s.end", "s.text")


def screen_structure(parsed: DataFrame, require: tuple[str, ...] = ("paragraph", "section_header")) -> DataFrame:
    """``reason`` of the first failed test, NULL for accepted documents."""
    every = F.flatten(F.array(*[F.col("spans")[k] for k in KINDS]))
    n = F.length("text")
    bad = F.exists(every, lambda s: s["start"].isNull() | s["end"].isNull() | (s["start"] < 0) | (s["end"] < s["start"]) | (s["end"] > n))
    odd = F.length(F.regexp_replace("text", "[^\\x{FFFD}\\x00-\\x08\\x0E-\\x1F]", ""))
    reason = F.when(F.col("text").isNull() | (F.trim("text") == ""), "empty_text").when(F.col("bad_json"), "bad_json").when(bad, "offset_range").when(odd * 20 > n, "unreadable")
    for kind, name in (("paragraph", "no_paragraph"), ("section_header", "no_header")):
        if kind in require:
            reason = reason.when(F.size(F.col("spans")[kind]) == 0, name)
    return parsed.withColumn("reason", reason)


def canonical_header(header: Column) -> Column:
    h = F.lower(F.trim(header))
    h = F.regexp_replace(h, r"^([0-9]+(\.[0-9]+)*\.?|[ivx]+\.)\s+", "")
    h = F.regexp_replace(F.regexp_replace(h, "&", " and "), r"\s+", " ")
    return F.trim(F.regexp_replace(h, r"[\s\p{P}]+$", ""))


def canonical_header_sql(header: str) -> str:
    h = f"regexp_replace(lower(trim({header})), '^([0-9]+(\\.[0-9]+)*\\.?|[ivx]+\\.)\\s+', '')"
    h = f"regexp_replace(replace({h}, '&', ' and '), '\\s+', ' ', 'g')"
    return f"trim(regexp_replace({h}, '[\\s\\p{{P}}]+$', ''))"


def normalise_headers(sections: DataFrame, curated: tuple[str, ...] = CURATED, header: str = "header") -> DataFrame:
    """``level`` 2 for a curated name, 3 for any other, from a broadcast list of fixed size."""
    return sections.withColumn("level", F.when(canonical_header(F.col(header)).isin(*curated), 2).otherwise(3))


# ------------------------------------------------------------------------------- sections


def _gaps(policy: str) -> Column:
    """Headers in order, each with its paragraphs: ``array<struct<header, paragraphs>>``, NULL header if there is none.

    Headers and paragraphs are sorted together once; the places of the headers cut the row
    into stretches, so the work is linear in the spans.
    """
    if policy not in ("preceding", "closest"):
        raise ValueError(f"no policy {policy}")
    kind = lambda k, n: F.transform(F.col("spans")[k], lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), F.lit(n).alias("k")))
    merged = F.array_sort(F.concat(kind("section_header", 3), kind("paragraph", 4)))
    none = F.array().cast(_SPAN_K)

    def of(m: Column) -> Column:
        n = F.size(m)

        def sections(at: Column) -> Column:
            def stretch(i: Column) -> Column:  # paragraphs behind header i; -1 is what comes before the first
                begin = F.when(i < 0, 0).otherwise(F.get(at, i) + 1)
                stop = F.coalesce(F.get(at, i + 1), n)
                return F.slice(m, begin + 1, F.greatest(stop - begin, F.lit(0)))

            head = lambda i: F.get(m, F.get(at, i))

            def own(i: Column) -> Column:
                lead = F.when(i == 0, stretch(i - 1)).otherwise(none)
                if policy == "preceding":
                    return F.concat(lead, stretch(i))
                here, after = head(i), head(i + 1)
                kept = F.filter(stretch(i), lambda p: after.isNull() | (p["start"] - here["start"] <= after["start"] - p["start"]))
                before = head(i - 1)
                caught = F.when(i > 0, F.filter(stretch(i - 1), lambda p: p["start"] - before["start"] > here["start"] - p["start"])).otherwise(none)
                return F.concat(lead, caught, kept)

            one = lambda i: F.struct(head(i).alias("header"), own(i).alias("paragraphs"))
            every = F.transform(F.sequence(F.lit(0), F.size(at) - 1), one)
            bare = F.array(F.struct(F.lit(None).cast(_SPAN_K[6:-1]).alias("header"), m.alias("paragraphs")))
            return F.when(F.size(at) > 0, every).otherwise(bare)

        places = F.filter(F.transform(m, lambda s, i: F.when(s["k"] == 3, i)), lambda i: i.isNotNull())
        return let(places, sections)

    return let(merged, of)


def assign_sections(parsed: DataFrame, policy: str = "preceding", text: str = "text") -> DataFrame:
    """A row for each paragraph: ``corpus_id, header_start, header, start, end, text``.

    ``preceding``: the last header at or before the paragraph, the first one for those ahead
    of all headers. ``closest``: the header whose start is nearest, the earlier on a tie.
    All of it happens inside the row; the explode is the last step.
    """
    blocks, of = _cutter(F.col(text))

    def paragraphs(b: Column) -> Column:
        cut = of(b)

        def section(g: Column) -> Column:
            h = g["header"]
            head = F.when(h.isNotNull(), cut(h))
            return F.transform(g["paragraphs"], lambda p: F.struct(h["start"].alias("header_start"), head.alias("header"), p["start"].alias("start"), p["end"].alias("end"), cut(p).alias("text")))

        return F.flatten(F.transform(_gaps(policy), section))

    rows = parsed.filter("not bad_json").select("corpus_id", F.explode(let(blocks, paragraphs)).alias("p"))
    return rows.select("corpus_id", "p.header_start", "p.header", "p.start", "p.end", "p.text")


def _sections(cut, policy: str) -> Column:
    """Sections that have paragraphs: ``array<struct<header_start, header, body, n_words>>``; one line feed between paragraphs."""

    def section(g: Column) -> Column:
        body = F.array_join(F.transform(g["paragraphs"], cut), "\n")
        words = lambda b: F.when(F.trim(b) == "", 0).otherwise(F.size(F.split(F.trim(b), r"\s+")))
        h = g["header"]
        return let(body, lambda b: F.struct(h["start"].alias("header_start"), F.when(h.isNotNull(), cut(h)).alias("header"), b.alias("body"), words(b).alias("n_words")))

    return F.transform(F.filter(_gaps(policy), lambda g: F.size(g["paragraphs"]) > 0), section)


def to_sections(parsed: DataFrame, policy: str = "preceding", text: str = "text") -> DataFrame:
    """One row for each section with paragraphs: ``corpus_id, header_start, header, body, n_words``."""
    blocks, of = _cutter(F.col(text))
    rows = parsed.filter("not bad_json").select("corpus_id", F.explode(let(blocks, lambda b: _sections(of(b), policy))).alias("s"))
    return rows.select("corpus_id", "s.*")


def _stays(header: Column, n_words: Column, min_words: int, whitelist: tuple[str, ...]) -> Column:
    return (n_words >= min_words) | F.coalesce(canonical_header(header).isin(*whitelist), F.lit(False))


def drop_thin_sections(sections: DataFrame, min_words: int = 10, whitelist: tuple[str, ...] = SHORT_OK) -> DataFrame:
    return sections.filter(_stays(F.col("header"), F.col("n_words"), min_words, whitelist))


_BARRIER = r"^\s*$|^#|^\s*([-*+]|\[[ xX]\])\s|^\(?\d+\)?$|^Eq\.?\s*\d+"
_ENDED = r"[.!?:]\s*$"


def unwrap_lines(text: Column) -> Column:
    """Broken lines joined by a blank; headers, empty lines, list markers, equation labels and sentence ends stay.

    Whether a line joins the one before it depends on these two lines alone, so the lines
    are looked at once, side by side.
    """

    def joined(lines: Column) -> Column:
        def with_separator(line: Column, i: Column) -> Column:
            before = F.get(lines, i - 1)
            keeps = before.rlike(_BARRIER) | line.rlike(_BARRIER) | before.rlike(_ENDED)
            return F.when(i == 0, line).otherwise(F.concat(F.when(keeps, F.lit("\n")).otherwise(F.lit(" ")), line))

        return F.array_join(F.transform(lines, with_separator), "")

    return let(F.split(text, "\n"), joined)


def render(parsed: DataFrame, curated: tuple[str, ...] = CURATED, min_words: int = 10, whitelist: tuple[str, ...] = SHORT_OK, policy: str = "preceding", unwrap: bool = False, text: str = "text") -> DataFrame:
    """``corpus_id, markdown``: title, abstract, then the sections in the order of their headers.

    One pass inside the row: no exchange, and no row but the document's own.
    """
    blocks, of = _cutter(F.col(text))

    def markdown(b: Column) -> Column:
        cut = of(b)
        titles, abstracts = F.array_sort("spans.title"), F.array_sort("spans.abstract")
        title = F.when(F.size(titles) > 0, F.concat(F.lit("# "), cut(F.get(titles, F.lit(0)))))
        abstract = F.when(F.size(abstracts) > 0, F.concat(F.lit("## Abstract\n"), F.array_join(F.transform(abstracts, cut), "\n")))
        kept = F.filter(_sections(cut, policy), lambda s: _stays(s["header"], s["n_words"], min_words, whitelist))
        marks = lambda s: F.when(canonical_header(s["header"]).isin(*curated), F.lit("## ")).otherwise(F.lit("### "))
        parts = F.transform(kept, lambda s: F.concat(marks(s), F.coalesce(s["header"], F.lit("")), F.lit("\n"), s["body"]))
        return F.array_join(F.concat(F.array(title, abstract), parts), "\n")

    md = let(blocks, markdown)
    return parsed.filter("not bad_json").select("corpus_id", (unwrap_lines(md) if unwrap else md).alias("markdown"))
