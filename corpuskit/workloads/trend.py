"""Workloads of trend analysis."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpuskit.functions.tokens import round6
from corpuskit.plans import structure, trends
from corpuskit.registry import register
from corpuskit.sources import adapters as A
from corpuskit.sources.tables import read_table, sql
from corpuskit.workloads.text import SECTIONED
from corpuskit.workloads.vectors import dot_sql

PATTERNS = {"gold": r"\berin\b", "silver": r"\beron\b"}
_LINES = "l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS t FROM documents WHERE lang = 'en')"
_FLAGS = rf"{_LINES}, f AS (SELECT doc_id, regexp_matches(t, '\bthing\b') AND regexp_matches(t, '\berin\b') AS gold, regexp_matches(t, '\bthing\b') AND regexp_matches(t, '\beron\b') AS silver FROM l)"
_PER_DOC = f"{_FLAGS}, d AS (SELECT doc_id, bool_or(gold) AS gold, bool_or(silver) AS silver FROM f GROUP BY doc_id)"
_YEARLY = "y AS (SELECT year(o_orderdate)::INT AS year, count(*) FILTER (gold) AS gold, count(*) FILTER (silver) AS silver FROM d JOIN orders ON o_orderkey = d.doc_id GROUP BY 1)"


def _text_flags(spark, sf_dir):
    lines = read_table(spark, sf_dir, "documents").filter("lang = 'en'").select("doc_id", F.explode(F.split("text", "\n")).alias("text"))
    return trends.flag(lines, PATTERNS, r"\bthing\b")


def _text_docs(spark, sf_dir):
    d = trends.per_document(_text_flags(spark, sf_dir), list(PATTERNS), "doc_id")
    o = read_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("doc_id"), F.year("o_orderdate").alias("year"))
    return d.join(o, "doc_id")


@register("trend_flags_text", f"WITH {_PER_DOC} SELECT doc_id, gold, silver FROM d")
def trend_flags_text(spark, sf_dir):
    return trends.per_document(_text_flags(spark, sf_dir), list(PATTERNS), "doc_id")


_SHARES = "CASE WHEN gold + silver = 0 THEN NULL ELSE gold / (gold + silver) END"


@register("trend_yearly_text", f"WITH {_PER_DOC}, {_YEARLY} SELECT year, gold, silver, floor({_SHARES} * 1000000 + 0.5) / 1000000 AS gold_share FROM y")
def trend_yearly_text(spark, sf_dir):
    y = trends.yearly(_text_docs(spark, sf_dir), list(PATTERNS))
    return y.select("year", "gold", "silver", round6(F.col("gold_share")).alias("gold_share"))


def _smooth_sql(docs):
    return f"""WITH {docs}, {_YEARLY}, s AS (SELECT *, {_SHARES} AS share FROM y)
SELECT year, floor(avg(share) OVER (ORDER BY year RANGE BETWEEN 1 PRECEDING AND 1 FOLLOWING) * 1000000 + 0.5) / 1000000 AS smooth FROM s"""


@register("trend_smooth_text", _smooth_sql(_PER_DOC))
def trend_smooth_text(spark, sf_dir):
    y = trends.yearly(_text_docs(spark, sf_dir), list(PATTERNS))
    return trends.smooth(y, "gold_share").select("year", round6(F.col("gold_share_smooth")).alias("smooth"))


_ORDERS = "f AS (SELECT l_orderkey AS doc_id, contains(p_name, 'red') AND regexp_matches(p_name, 'widget|gizmo') AS gold, contains(p_name, 'blue') AND regexp_matches(p_name, 'widget|gizmo') AS silver FROM lineitem JOIN part ON p_partkey = l_partkey), d AS (SELECT doc_id, bool_or(gold) AS gold, bool_or(silver) AS silver FROM f GROUP BY doc_id)"


def _order_docs(spark, sf_dir):
    rows = sql(spark, sf_dir, "SELECT l_orderkey AS doc_id, p_name AS text FROM {lineitem} JOIN {part} ON p_partkey = l_partkey")
    d = trends.per_document(trends.flag(rows, {"gold": "red", "silver": "blue"}, "widget|gizmo"), ["gold", "silver"], "doc_id")
    o = read_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("doc_id"), F.year("o_orderdate").alias("year"))
    return d.join(o, "doc_id")


@register("trend_flags_orders", f"WITH {_ORDERS} SELECT count(*) AS docs, count(*) FILTER (gold) AS gold, count(*) FILTER (silver) AS silver, count(*) FILTER (gold AND silver) AS both FROM d JOIN orders ON o_orderkey = doc_id")
def trend_flags_orders(spark, sf_dir):
    return _order_docs(spark, sf_dir).agg(F.count("*").alias("docs"), F.count_if("gold").alias("gold"), F.count_if("silver").alias("silver"), F.count_if(F.col("gold") & F.col("silver")).alias("both"))


@register("trend_yearly_orders", f"WITH {_ORDERS}, {_YEARLY} SELECT year, gold, silver FROM y")
def trend_yearly_orders(spark, sf_dir):
    return trends.yearly(_order_docs(spark, sf_dir), ["gold", "silver"]).select("year", "gold", "silver")


@register("trend_smooth_orders", _smooth_sql(_ORDERS))
def trend_smooth_orders(spark, sf_dir):
    y = trends.yearly(_order_docs(spark, sf_dir), ["gold", "silver"])
    return trends.smooth(y, "gold_share").select("year", round6(F.col("gold_share_smooth")).alias("smooth"))


@register("trend_densify", f"WITH {_PER_DOC}, {_YEARLY}, g AS (SELECT * FROM y WHERE year <> 1998), b AS (SELECT unnest(range(min(year), max(year) + 1))::INT AS year FROM g) SELECT b.year, coalesce(gold, 0) AS gold, coalesce(silver, 0) AS silver FROM b LEFT JOIN g USING (year)")
def trend_densify(spark, sf_dir):
    y = trends.yearly(_text_docs(spark, sf_dir), list(PATTERNS)).filter("year <> 1998")
    return trends.densify(y, ["gold", "silver"])


@register("trend_sentence_values", r"""WITH s AS (SELECT doc_id, unnest(regexp_extract_all(text, '[^.!?\n]+[.!?]*')) AS s FROM documents)
SELECT doc_id, bool_or(regexp_matches(s, '\bthe\b') AND regexp_matches(s, '\bering\b')) AS a, bool_or(regexp_matches(s, '\bthe\b') AND regexp_matches(s, '\boning\b')) AS b FROM s GROUP BY doc_id""")
def trend_sentence_values(spark, sf_dir):
    f = trends.flag_sentences(read_table(spark, sf_dir, "documents").select("doc_id", "text"), {"a": r"\bering\b", "b": r"\boning\b"}, r"\bthe\b")
    return trends.per_document(f, ["a", "b"], "doc_id")


@register("trend_semantic", f"""WITH c AS (SELECT embedding AS c FROM embeddings WHERE vec_id = 5), h AS (SELECT vec_id, {dot_sql('embedding', 'c')} >= 0.1 AS hit FROM embeddings, c)
SELECT year(o_orderdate)::INT AS year, count(*) FILTER (hit) AS hit, count(*) AS n FROM h JOIN orders ON o_orderkey = vec_id GROUP BY 1""")
def trend_semantic(spark, sf_dir):
    e = read_table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    concept = e.filter("vec_id = 5").first()["embedding"]
    o = read_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("vec_id"), F.year("o_orderdate").alias("year"))
    return trends.flag_semantic(e, concept, 0.1).join(o, "vec_id").groupBy("year").agg(F.count_if("hit").alias("hit"), F.count("*").alias("n"))


@register("trend_expand_terms", r"""WITH w AS (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '\p{L}+'))) AS word FROM documents), s AS (SELECT doc_id FROM w WHERE word = 'thing'),
g AS (SELECT word, count(*) AS docs, count(s.doc_id) AS hits FROM w LEFT JOIN s USING (doc_id) GROUP BY word), k AS (SELECT *, floor(log2(hits * (SELECT count(*) FROM documents) / (docs * (SELECT count(*) FROM s))::DOUBLE) * 1000000 + 0.5) / 1000000 AS pmi FROM g WHERE word <> 'thing' AND hits >= 3)
SELECT word, docs, hits AS "both", pmi FROM k ORDER BY pmi DESC, hits DESC, word LIMIT 10""")
def trend_expand_terms(spark, sf_dir):
    return trends.expand_terms(read_table(spark, sf_dir, "documents"), "thing")


@register("entity_links", r"""WITH w AS (SELECT p_partkey AS doc_id, regexp_extract_all(lower(p_name), '[\p{L}\p{N}]+') AS w FROM part), g AS (SELECT doc_id, unnest(list_transform(range(1, greatest(len(w), 2)), lambda i: array_to_string(list_slice(w, i, i + 1), ' '))) AS name FROM w),
r AS (SELECT min(p_partkey) AS entity_id, lower(p_name) AS name FROM part GROUP BY lower(p_name)) SELECT DISTINCT doc_id, entity_id FROM g JOIN r USING (name)""")
def entity_links(spark, sf_dir):
    part = read_table(spark, sf_dir, "part")
    registry = part.groupBy(F.lower("p_name").alias("name")).agg(F.min("p_partkey").alias("entity_id"))
    return trends.link_entities(part.select(F.col("p_partkey").alias("doc_id"), F.col("p_name").alias("text")), registry)


@register("gold_pairs", A.DOC_GOLD_SQL)
def gold_pairs(spark, sf_dir):
    return A.doc_gold(spark, sf_dir)


_RELEVANT = ("of", "and ornd", "in in oredble ea", "hetible th", "tion was thanonontioniner. es")
_TERMS = {"gold": r"\bthe\b", "silver": r"\bof\b"}


@register("trend_flags_sections", rf"""WITH {SECTIONED}, near AS (SELECT corpus_id, {structure.canonical_header_sql('header')} IN ({", ".join(map(repr, _RELEVANT))}) AND regexp_matches(body, '\bin\b') AS near, body FROM sections)
SELECT corpus_id, bool_or(coalesce(near, false) AND regexp_matches(body, '\bthe\b')) AS gold, bool_or(coalesce(near, false) AND regexp_matches(body, '\bof\b')) AS silver FROM near GROUP BY corpus_id""")
def trend_flags_sections(spark, sf_dir):
    """Terms beside the anchor, in the passages of the relevant sections alone."""
    sections = structure.to_sections(structure.parse_spans(A.fulltexts(spark, sf_dir)))
    flags = trends.flag(sections.withColumnRenamed("body", "text"), _TERMS, r"\bin\b", sections=_RELEVANT)
    return trends.per_document(flags, list(_TERMS))


@register("trend_sentence_numbers", r"""WITH s AS (SELECT doc_id, unnest(regexp_extract_all(text, '[^.!?\n]+[.!?]*')) AS s FROM documents), f AS (SELECT doc_id, regexp_matches(s, '[Ll]icensed') AND regexp_matches(s, '[Vv]ersion') AS near, s FROM s)
SELECT doc_id, bool_or(near AND regexp_matches(s, '\b2\b')) AS two, bool_or(near AND regexp_matches(s, '\b3\b')) AS three FROM f GROUP BY doc_id""")
def trend_sentence_numbers(spark, sf_dir):
    """Two numeric values, each in a sentence with a context word and a cue."""
    f = trends.flag_sentences(read_table(spark, sf_dir, "documents").select("doc_id", "text"), {"two": r"\b2\b", "three": r"\b3\b"}, "[Ll]icensed", cue="[Vv]ersion")
    return trends.per_document(f, ["two", "three"], "doc_id")
