"""Paper-shaped inputs derived from the given tables, by rules that SQL on both engines can follow.

Each adapter has a Spark form and, as text, the same rule for DuckDB, which the oracles of
the workloads build on. ``k`` below is ``doc_id``.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpuskit.functions.tokens import once
from corpuskit.sources.tables import read_table, sql

SERVICES = ("oa_aggregator", "venue_index", "publisher_registry")

_PAPERS = """
SELECT d.doc_id AS corpus_id, substr({first_line}, 1, 120) AS title, d.lang AS field,
       CASE WHEN d.doc_id % 13 = 0 THEN NULL ELSE d.source END AS venue,
       CASE WHEN d.doc_id % 29 = 0 THEN NULL
            WHEN d.doc_id % 31 = 0 THEN concat('10.', CAST(1000 + d.doc_id % 9000 AS {str}), 'd', CAST(d.doc_id AS {str}))
            ELSE concat('10.', CAST(1000 + d.doc_id % 9000 AS {str}), '/d', CAST(d.doc_id AS {str})) END AS doi,
       CASE WHEN d.doc_id % 101 = 0 THEN NULL ELSE CAST(o.o_orderdate AS DATE) END AS publication_date,
       CASE WHEN d.doc_id % 202 = 0 THEN NULL ELSE CAST(year(o.o_orderdate) AS INT) END AS year,
       CASE WHEN d.doc_id % 211 = 0 THEN NULL ELSE c.c_name END AS author, l.quality = 1 AS is_oa
FROM {documents} d LEFT JOIN {orders} o ON o.o_orderkey = d.doc_id LEFT JOIN {customer} c ON c.c_custkey = o.o_custkey
     LEFT JOIN {labels} l ON l.doc_id = d.doc_id
"""


def _duck(text: str, **more: str) -> str:
    names = {n: n for n in ("documents", "orders", "customer", "labels", "lineitem", "embeddings", "benchmark")}
    return text.format(str="VARCHAR", first_line="string_split(d.text, chr(10))[1]", **names, **more)


PAPERS_SQL = _duck(_PAPERS)


def papers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One bibliographic row for each document, with ``authors`` and ``fields`` as arrays."""
    text = _PAPERS.replace("{str}", "STRING").replace("{first_line}", "split(d.text, '\n')[0]")
    rows = sql(spark, sf_dir, text)
    return rows.withColumns({"fields": F.array("field"), "authors": F.when(F.col("author").isNull(), F.array().cast("array<string>")).otherwise(F.array("author"))})


ABSTRACTS_SQL = """
SELECT doc_id AS corpus_id, CASE WHEN doc_id % 11 = 0 THEN '' ELSE array_to_string(list_slice(string_split(text, chr(10)), 1, 3), ' ') END AS abstract
FROM documents WHERE doc_id % 7 <> 0"""


def abstracts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").filter("doc_id % 7 <> 0")
    lead = F.array_join(F.slice(F.split("text", "\n"), 1, 3), " ")
    return docs.select(F.col("doc_id").alias("corpus_id"), F.when(F.col("doc_id") % 11 == 0, "").otherwise(lead).alias("abstract"))


LINES_SQL = """
SELECT doc_id AS corpus_id, text, i, line, n_lines, CAST(upto - length(line) AS BIGINT) AS s, CAST(upto AS BIGINT) AS e FROM (
  SELECT *, sum(length(line) + 1) OVER (PARTITION BY doc_id ORDER BY i) - 1 AS upto FROM (
    SELECT doc_id, text, unnest(range(1, len(l) + 1)) AS i, unnest(l) AS line, len(l) AS n_lines FROM (
      SELECT doc_id, text, string_split(text, chr(10)) AS l FROM documents WHERE doc_id % 5 <> 4)))"""
SPANS_SQL = f"""
SELECT corpus_id, text, i, n_lines, s, CASE WHEN corpus_id % 37 = 5 AND i = n_lines THEN e + 7 ELSE e END AS e, line,
       CASE WHEN i = 1 THEN 'title' WHEN i <= 3 AND n_lines >= 3 THEN 'abstract'
            WHEN len(list_filter(string_split(line, ' '), lambda w: w <> '')) <= 6 THEN 'section_header' ELSE 'paragraph' END AS kind
FROM ({LINES_SQL})"""
KINDS = ("title", "abstract", "section_header", "paragraph")


def fulltexts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Texts with stand-off annotations: for each kind, a JSON list of ``{start, end}`` as a string.

    Two known faults are planted: an end behind the text (k % 37 = 5), and JSON cut short
    (k % 41 = 7).
    """
    docs = read_table(spark, sf_dir, "documents").filter("doc_id % 5 <> 4").select(F.col("doc_id").alias("corpus_id"), "text")
    kind = """case when x.i = 1 then 'title' when x.i <= 3 and size(l) >= 3 then 'abstract'
               when size(filter(split(l[x.i - 1], ' '), w -> w <> '')) <= 6 then 'section_header' else 'paragraph' end"""
    rows = _annotated(once(docs, l=F.split("text", "\n")), kind, "corpus_id % 37 = 5 and x.i = size(l)")
    cut = F.when(F.col("corpus_id") % 41 == 7, F.expr("substr(paragraph, 1, length(paragraph) - 1)")).otherwise(F.col("paragraph"))
    return rows.withColumn("paragraph", cut).select("corpus_id", "text", F.struct(*KINDS).alias("annotations"))


def _annotated(rows: DataFrame, kind: str, shifted: str = "false") -> DataFrame:
    """Span lists as JSON strings, one column for each kind, for texts whose lines are the array ``l``."""
    # running character offsets of the lines, folded inside the row
    spans = F.expr("""
        aggregate(sequence(0, size(l) - 1), cast(array() as array<struct<i: int, s: int, e: int>>),
          (acc, k) -> array_append(acc, named_struct('i', k + 1, 's', if(k = 0, 0, acc[k - 1].e + 1), 'e', if(k = 0, 0, acc[k - 1].e + 1) + length(l[k]))))""")
    named = F.expr(f"transform(spans, x -> named_struct('start', x.s, 'end', if({shifted}, x.e + 7, x.e), 'kind', {kind}))")
    one = lambda k: F.to_json(F.transform(F.filter("kinds", lambda x: x["kind"] == k), lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"))))
    full = once(rows, spans=F.when(F.size("l") > 0, spans).otherwise(F.array().cast("array<struct<i: int, s: int, e: int>>")))
    return once(full, kinds=named).withColumns({k: one(k) for k in KINDS})


#: The character references of the pages' texts.
_REFERENCES = {"&lt;": "<", "&gt;": ">", "&quot;": '"', "&#39;": "'", "&nbsp;": " ", "&amp;": "&"}
_BLOCK_TAG = r"<(h[1-6]|p)(?:\s[^>]*)?>"


def _plain(body: str, flags: str, slash: str) -> str:
    """SQL for the text of a piece of HTML: no tags, references resolved, one blank for white space."""
    out = f"regexp_replace({body}, '<[^>]*>', ' '{flags})"
    for name, value in _REFERENCES.items():
        out = f"replace({out}, {name!r}, {value!r})"
    return f"trim(regexp_replace({out}, '[ {slash}t{slash}r{slash}n]+', ' '{flags}))".replace('"&#39;"', "'&#39;'").replace('"\'"', "chr(39)")


PAGE_SPANS_SQL = rf"""
SELECT corpus_id, text, CASE tag WHEN 'h1' THEN 'title' WHEN 'p' THEN 'paragraph' ELSE 'section_header' END AS kind, CAST(upto - length(line) AS BIGINT) AS s, CAST(upto AS BIGINT) AS e, line FROM (
  SELECT *, sum(length(line) + 1) OVER (PARTITION BY corpus_id ORDER BY i) - 1 AS upto, string_agg(line, chr(10)) OVER (PARTITION BY corpus_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS text FROM (
    SELECT corpus_id, i, split_part(x, chr(2), 1) AS tag, {_plain("split_part(x, chr(2), 2)", ", 'g'", chr(92))} AS line FROM (
      SELECT corpus_id, unnest(range(1, len(l))) AS i, unnest(list_slice(l, 2, len(l))) AS x FROM (
        SELECT page_id AS corpus_id, string_split(regexp_replace(regexp_replace(regexp_extract(html, '(?s)<article>(.*)</article>', 1), '(?s)<!--.*?-->', '', 'g'), '{_BLOCK_TAG}', chr(1) || '\1' || chr(2), 'g'), chr(1)) AS l FROM pages)))
  WHERE line <> '')""".replace("'" + chr(92) * 2 + "1'", "'" + chr(92) + "1'")


def page_fulltexts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The span model from web pages: ``corpus_id`` (the page), its text and the annotations of its blocks.

    The first-level heading is the title, lower headings are section headers, and paragraphs
    end where the next block begins, closed or not.
    """
    article = F.regexp_replace(F.regexp_extract("html", r"(?s)<article>(.*)</article>", 1), r"(?s)<!--.*?-->", "")
    marked = F.regexp_replace(article, _BLOCK_TAG, "\u0001$1\u0002")
    pages = read_table(spark, sf_dir, "pages").select(F.col("page_id").alias("corpus_id"), F.split(marked, "\u0001").alias("x"))
    line = _plain("split_part(y, chr(2), 2)", "", chr(92) * 2)
    plain = F.expr(f"filter(transform(slice(x, 2, greatest(size(x) - 1, 0)), y -> named_struct('tag', split_part(y, chr(2), 1), 'line', {line})), z -> z.line <> '')")
    blocks = once(once(pages, b=plain).drop("x"), l=F.col("b.line"))
    rows = once(blocks, text=F.array_join("l", "\n"))
    kind = "case b[x.i - 1].tag when 'h1' then 'title' when 'p' then 'paragraph' else 'section_header' end"
    return _annotated(rows, kind).select("corpus_id", "text", F.struct(*KINDS).alias("annotations"))


_REPORTS = """
WITH c AS (SELECT doc_id AS corpus_id, (doc_id * 7919) % 1000 AS b, (doc_id * 104729) % 1000 AS c FROM {documents}),
t AS (SELECT *, CASE WHEN b < 875 THEN 'ATTR' WHEN b < 982 THEN 'ATTR_NC' WHEN b < 991 THEN 'ATTR_NC_SA' WHEN b < 996 THEN 'ATTR_SA' ELSE 'PUBLIC_DOMAIN' END AS code FROM c),
s AS (
  SELECT corpus_id, 'oa_aggregator' AS service, CASE WHEN corpus_id % 19 = 4 THEN 'UNKNOWN' ELSE code END AS code FROM t WHERE c < 790 OR (c >= 795 AND c < 835)
  UNION ALL SELECT corpus_id, 'venue_index', CASE WHEN corpus_id % 17 = 3 THEN 'ATTR_ND' ELSE code END FROM t WHERE c < 495 OR (c >= 690 AND c < 795) OR (c >= 870 AND c < 899)
  UNION ALL SELECT corpus_id, 'publisher_registry', code FROM t WHERE c < 690 OR (c >= 790 AND c < 795) OR (c >= 835 AND c < 870))
SELECT corpus_id, service,
  CASE WHEN code = 'UNKNOWN' THEN 'other-oa'
       WHEN code = 'PUBLIC_DOMAIN' THEN CASE corpus_id % 4 WHEN 0 THEN 'https://creativecommons.org/publicdomain/mark/1.0/' WHEN 1 THEN 'public-domain' WHEN 2 THEN 'Public Domain' ELSE 'PDM-1.0' END
       WHEN corpus_id % 4 = 0 THEN concat('https://creativecommons.org/licenses/', {slug}, '/4.0/')
       WHEN corpus_id % 4 = 1 THEN concat('cc-', {slug})
       WHEN corpus_id % 4 = 2 THEN concat('CC ', upper({slug}), ' 4.0')
       ELSE concat('CC-', upper({slug}), '-4.0') END AS raw
FROM s
"""
_SLUG = "CASE code WHEN 'ATTR' THEN 'by' WHEN 'ATTR_NC' THEN 'by-nc' WHEN 'ATTR_NC_SA' THEN 'by-nc-sa' WHEN 'ATTR_SA' THEN 'by-sa' WHEN 'ATTR_ND' THEN 'by-nd' END"
REPORTS_SQL = _REPORTS.format(documents="documents", slug=_SLUG)


def license_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tall reports (corpus_id, service, raw spelling); a service that does not know a paper has no row."""
    return sql(spark, sf_dir, _REPORTS.replace("{slug}", _SLUG))


def frozen_reports(k: int) -> list[tuple[str, str]]:
    """The same reports for one paper in plain Python: what a live lookup of the three services would answer."""
    b, c = k * 7919 % 1000, k * 104729 % 1000
    code = next(name for bound, name in ((875, "ATTR"), (982, "ATTR_NC"), (991, "ATTR_NC_SA"), (996, "ATTR_SA"), (1000, "PUBLIC_DOMAIN")) if b < bound)
    known = {
        "oa_aggregator": (c < 790 or 795 <= c < 835) and ("UNKNOWN" if k % 19 == 4 else code),
        "venue_index": (c < 495 or 690 <= c < 795 or 870 <= c < 899) and ("ATTR_ND" if k % 17 == 3 else code),
        "publisher_registry": (c < 690 or 790 <= c < 795 or 835 <= c < 870) and code,
    }

    def spelled(code: str) -> str:
        if code == "UNKNOWN":
            return "other-oa"
        if code == "PUBLIC_DOMAIN":
            return ("https://creativecommons.org/publicdomain/mark/1.0/", "public-domain", "Public Domain", "PDM-1.0")[k % 4]
        slug = code.lower().replace("attr", "by").replace("_", "-")
        return (f"https://creativecommons.org/licenses/{slug}/4.0/", f"cc-{slug}", f"CC {slug.upper()} 4.0", f"CC-{slug.upper()}-4.0")[k % 4]

    return [(name, spelled(code)) for name, code in known.items() if code]


VOTERS_SQL = """
SELECT l_orderkey AS key, CAST(voter AS INT) AS voter, l_returnflag AS value FROM (
  SELECT l_orderkey, l_returnflag, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_returnflag, l_quantity) AS voter FROM {lineitem})
WHERE voter <= 3"""


def voter_reports(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first three line items of an order as three voters on a value: a stand-in at scale."""
    return sql(spark, sf_dir, VOTERS_SQL)


DOC_GOLD_SQL = "SELECT b.item_id, d.doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)"


def doc_gold(spark: SparkSession, sf_dir: str, most: int = 10_000) -> DataFrame:
    """Which documents hold which benchmark passage.

    Up to ``most`` passages go to every task and are looked for by Python's substring search,
    which skips ahead; the engine's compares place by place. More of them meet the texts in a join.
    """
    asked = read_table(spark, sf_dir, "benchmark").select("item_id", "text").filter("text is not null")
    passages = [(r["item_id"], r["text"]) for r in asked.limit(most + 1).collect()]
    if len(passages) > most:
        return sql(spark, sf_dir, "SELECT b.item_id, d.doc_id FROM {benchmark} b JOIN {documents} d ON contains(d.text, b.text)")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            found = [(i, k) for k, text in zip(batch["doc_id"], batch["text"], strict=True) for i, p in passages if p in text]
            yield pd.DataFrame(found, columns=["item_id", "doc_id"])

    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text").filter("text is not null")
    return docs.mapInPandas(run, "item_id long, doc_id long")


VECTOR_LABELS_SQL = """
SELECT e.vec_id, CAST(r.vec_id AS INT) AS label FROM embeddings e JOIN embeddings r ON r.vec_id < 17
WHERE list_sum(list_transform(range(1, len(e.embedding) + 1), lambda i: CAST(e.embedding[i] AS DOUBLE) * CAST(r.embedding[i] AS DOUBLE))) > 0.16"""


def dot(a: str, b: str) -> F.Column:
    """Inner product of two array columns, in doubles, inside the JVM."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def vector_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Learnable multi-label truth: label j holds where the vector points along direction j; 17 where none does."""
    e = read_table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    r = e.filter("vec_id < 17").select(F.col("vec_id").cast("int").alias("label"), F.col("embedding").alias("d"))
    some = e.join(F.broadcast(r)).filter(dot("embedding", "d") > 0.16).select("vec_id", "label")
    none = e.join(some, "vec_id", "left_anti").select("vec_id", F.lit(17).alias("label"))
    return some.unionByName(none)
