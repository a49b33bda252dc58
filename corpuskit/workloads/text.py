"""Workloads of structuring and chunking."""

from __future__ import annotations

from pyspark.sql import functions as F

from corpuskit.functions import tokens as T
from corpuskit.plans import chunking, structure
from corpuskit.registry import register
from corpuskit.sources import adapters as A
from corpuskit.sources.tables import read_table

SPANS = f"sp AS ({A.SPANS_SQL}), good AS (SELECT * FROM sp WHERE corpus_id % 41 <> 7)"


def _parsed(spark, sf_dir):
    return structure.parse_spans(A.fulltexts(spark, sf_dir))


def _docs(spark, sf_dir):
    return read_table(spark, sf_dir, "documents")


@register("span_extract", f"WITH {SPANS} SELECT corpus_id, kind, s::INT AS start, e::INT AS \"end\", substr(text, s + 1, e - s) AS text FROM good")
def span_extract(spark, sf_dir):
    return structure.extract_spans(_parsed(spark, sf_dir))


@register("span_rejects", f"""WITH {SPANS}, d AS (SELECT corpus_id, any_value(text) AS text, max(e) AS e, count(*) FILTER (kind = 'paragraph') AS p, count(*) FILTER (kind = 'section_header') AS h FROM sp GROUP BY corpus_id),
r AS (SELECT corpus_id, CASE WHEN trim(text) = '' THEN 'empty_text' WHEN corpus_id % 41 = 7 THEN 'bad_json' WHEN e > length(text) THEN 'offset_range' WHEN p = 0 THEN 'no_paragraph' WHEN h = 0 THEN 'no_header' END AS reason FROM d)
SELECT reason, count(*) AS n FROM r GROUP BY reason""")
def span_rejects(spark, sf_dir):
    return structure.screen_structure(_parsed(spark, sf_dir)).groupBy("reason").agg(F.count("*").alias("n"))


_ASSIGNED = f"""{SPANS}, hp AS (SELECT *, CASE kind WHEN 'section_header' THEN 3 ELSE 4 END AS k FROM good WHERE kind IN ('section_header', 'paragraph')),
f AS (SELECT *, last_value(CASE WHEN kind = 'section_header' THEN s END IGNORE NULLS) OVER w AS ps, first_value(CASE WHEN kind = 'section_header' THEN s END IGNORE NULLS) OVER v AS ns FROM hp
  WINDOW w AS (PARTITION BY corpus_id ORDER BY s, e, k ROWS UNBOUNDED PRECEDING), v AS (PARTITION BY corpus_id ORDER BY s, e, k ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)),
a AS (SELECT corpus_id, {{choose}} AS hs, s, e, substr(text, s + 1, e - s) AS text FROM f WHERE kind = 'paragraph'),
h AS (SELECT corpus_id, s, any_value(substr(text, s + 1, e - s)) AS header FROM good WHERE kind = 'section_header' GROUP BY corpus_id, s),
assigned AS (SELECT a.corpus_id, a.hs::INT AS header_start, h.header, a.s::INT AS start, a.e::INT AS "end", a.text FROM a LEFT JOIN h ON h.corpus_id = a.corpus_id AND h.s = a.hs)"""
_PRECEDING = _ASSIGNED.format(choose="coalesce(ps, ns)")
_CLOSEST = _ASSIGNED.format(choose="CASE WHEN ns IS NULL OR s - ps <= ns - s THEN ps ELSE ns END")
_SECTIONS = f"""{_PRECEDING}, sections AS (SELECT corpus_id, header_start, header, string_agg(text, chr(10) ORDER BY start, text) AS body FROM assigned GROUP BY ALL),
counted AS (SELECT *, CASE WHEN trim(body) = '' THEN 0 ELSE len(regexp_split_to_array(trim(body), '\\s+')) END AS n_words FROM sections)"""
SECTIONED = _SECTIONS
SECTIONS_SQL = _SECTIONS.replace(SPANS + ", ", "", 1)
_CURATED = ", ".join(repr(c) for c in structure.CURATED)


@register("sections_assign", f"WITH {_PRECEDING} SELECT * FROM assigned")
def sections_assign(spark, sf_dir):
    return structure.assign_sections(_parsed(spark, sf_dir))


@register("sections_assign_closest", f"WITH {_CLOSEST} SELECT * FROM assigned")
def sections_closest(spark, sf_dir):
    return structure.assign_sections(_parsed(spark, sf_dir), "closest")


def _sections(spark, sf_dir):
    return structure.to_sections(_parsed(spark, sf_dir))


@register("headers_normalise", f"""WITH {SPANS}, h AS (SELECT DISTINCT substr(text, s + 1, e - s) AS header FROM good WHERE kind = 'section_header')
SELECT header, {structure.canonical_header_sql('header')} AS canonical, CASE WHEN {structure.canonical_header_sql('header')} IN ({_CURATED}, 'the', 'of') THEN 2 ELSE 3 END AS level FROM h""")
def headers_normalise(spark, sf_dir):
    h = structure.extract_spans(_parsed(spark, sf_dir)).filter("kind = 'section_header'").select(F.col("text").alias("header")).distinct()
    return structure.normalise_headers(h, (*structure.CURATED, "the", "of")).select("header", structure.canonical_header(F.col("header")).alias("canonical"), "level")


@register("thin_sections", f"WITH {_SECTIONS} SELECT corpus_id, header_start, n_words::INT AS n_words FROM counted WHERE n_words >= 10 OR {structure.canonical_header_sql('header')} IN ('abstract', 'conclusion', 'conclusions')")
def thin_sections(spark, sf_dir):
    return structure.drop_thin_sections(_sections(spark, sf_dir)).select("corpus_id", "header_start", F.col("n_words").cast("int").alias("n_words"))


_MARKDOWN = MARKDOWN_SQL = f"""kept AS (SELECT *, CASE WHEN {structure.canonical_header_sql('header')} IN ({_CURATED}) THEN 2 ELSE 3 END AS level FROM counted WHERE n_words >= 10 OR {structure.canonical_header_sql('header')} IN ('abstract', 'conclusion', 'conclusions')),
tops AS (SELECT corpus_id, min_by(substr(text, s + 1, e - s), s) FILTER (kind = 'title') AS t, string_agg(substr(text, s + 1, e - s), chr(10) ORDER BY s) FILTER (kind = 'abstract') AS a FROM good GROUP BY corpus_id),
bodies AS (SELECT corpus_id, string_agg(repeat('#', level) || ' ' || coalesce(header, '') || chr(10) || body, chr(10) ORDER BY header_start) AS b FROM kept GROUP BY corpus_id),
md AS (SELECT corpus_id, concat_ws(chr(10), '# ' || t, '## Abstract' || chr(10) || a, b) AS markdown FROM tops LEFT JOIN bodies USING (corpus_id))"""


@register("markdown_render", f"WITH {_SECTIONS}, {_MARKDOWN} SELECT * FROM md")
def markdown_render(spark, sf_dir):
    return structure.render(_parsed(spark, sf_dir))


_BAR = r"'^\s*$|^#|^\s*([-*+]|\[[ xX]\])\s|^\(?\d+\)?$|^Eq\.?\s*\d+'"


def unwrap_sql(table, key, text):
    """Lines joined by a blank unless one of the two is a barrier or the first ends a sentence."""
    return rf"""w AS (SELECT {key}, unnest(range(1, len(l) + 1)) AS i, unnest(l) AS line FROM (SELECT {key}, string_split({text}, chr(10)) AS l FROM {table})),
g AS (SELECT *, lag(line) OVER (PARTITION BY {key} ORDER BY i) AS prev FROM w),
b AS (SELECT *, CASE WHEN prev IS NULL THEN '' WHEN regexp_matches(prev, '[.!?:]\s*$') OR regexp_matches(line, {_BAR}) OR regexp_matches(prev, {_BAR}) THEN chr(10) ELSE ' ' END AS sep FROM g),
unwrapped AS (SELECT {key}, string_agg(sep || line, '' ORDER BY i) AS text FROM b GROUP BY {key})"""


@register("unwrap_lines", f"WITH {unwrap_sql('documents', 'doc_id', 'text')} SELECT * FROM unwrapped")
def unwrap(spark, sf_dir):
    return _docs(spark, sf_dir).select("doc_id", structure.unwrap_lines(F.col("text")).alias("text"))


@register("markdown_unwrapped", f"WITH {_SECTIONS}, {_MARKDOWN}, {unwrap_sql('md', 'corpus_id', 'markdown')} SELECT corpus_id, text AS markdown FROM unwrapped")
def markdown_unwrapped(spark, sf_dir):
    return structure.render(_parsed(spark, sf_dir), unwrap=True)


def _page_parsed(spark, sf_dir):
    return structure.parse_spans(A.page_fulltexts(spark, sf_dir))


@register("page_spans", f"""SELECT corpus_id AS page_id, kind, s::INT AS start, e::INT AS "end", line AS text FROM ({A.PAGE_SPANS_SQL})""")
def page_spans(spark, sf_dir):
    return structure.extract_spans(_page_parsed(spark, sf_dir)).withColumnRenamed("corpus_id", "page_id")


@register("page_rejects", f"""WITH sp AS ({A.PAGE_SPANS_SQL}), g AS (SELECT corpus_id, count(*) FILTER (kind = 'paragraph') AS p, any_value(text) AS text FROM sp GROUP BY corpus_id)
SELECT CASE WHEN g.corpus_id IS NULL OR trim(g.text) = '' THEN 'empty_text' WHEN p = 0 THEN 'no_paragraph' END AS reason, count(*) AS n FROM pages LEFT JOIN g ON g.corpus_id = page_id GROUP BY ALL""")
def page_rejects(spark, sf_dir):
    return structure.screen_structure(_page_parsed(spark, sf_dir), require=("paragraph",)).groupBy("reason").agg(F.count("*").alias("n"))


@register("page_markdown", rf"""WITH sp AS ({A.PAGE_SPANS_SQL}), g AS (SELECT corpus_id, min_by(line, s) FILTER (kind = 'title') AS t, string_agg(line, chr(10) ORDER BY s) FILTER (kind = 'paragraph') AS b FROM sp GROUP BY corpus_id),
n AS (SELECT *, CASE WHEN trim(b) = '' THEN 0 ELSE len(regexp_split_to_array(trim(b), '\s+')) END AS n_words FROM g)
SELECT page_id AS corpus_id, concat_ws(chr(10), '# ' || t, CASE WHEN n_words >= 10 THEN '### ' || chr(10) || b END) AS markdown FROM pages LEFT JOIN n ON n.corpus_id = page_id""")
def page_markdown(spark, sf_dir):
    return structure.render(_page_parsed(spark, sf_dir))


# ------------------------------------------------------------------------------ chunking


def _n(text, pattern):
    return f"len(regexp_extract_all({text}, '{pattern}'))"


WP = r"[\p{L}\p{N}]+|[^\p{L}\p{N}\s]"


@register("token_counts", rf"SELECT doc_id, {_n('text', WP)}::INT AS wordpunct, {_n('text', '[^ ' + chr(92) + 't' + chr(92) + 'n' + chr(92) + 'r' + chr(92) + 'f]+')}::INT AS whitespace, {_n('text', r'[\p{L}\p{N}]{1,4}|[^\p{L}\p{N}\s]')}::INT AS subword FROM documents")
def token_counts(spark, sf_dir):
    t = F.col("text")
    return _docs(spark, sf_dir).select("doc_id", *[T.count(t, s).alias(s) for s in ("wordpunct", "whitespace", "subword")])


_PIECE = r"(?:[\p{L}\p{N}]+|[^\p{L}\p{N}\s])\s*"
_UNITS_SQL = rf"""tk AS (SELECT doc_id, unnest(range(1, len(l) + 1)) AS i, unnest(l) AS t FROM (SELECT doc_id, regexp_extract_all(text, '{_PIECE}') AS l FROM {{docs}})),
fl AS (SELECT doc_id, i, contains(t, chr(10)) AS pe, contains(t, chr(10)) OR (regexp_matches(t, '[.!?]\s*$') AND NOT coalesce(regexp_matches(lead(t) OVER w, '^[.!?]'), false)) AS se FROM tk WINDOW w AS (PARTITION BY doc_id ORDER BY i)),
gr AS (SELECT doc_id, i, coalesce(sum(pe::INT) OVER w, 0) AS par, coalesce(sum(se::INT) OVER w, 0) AS sen FROM fl WINDOW w AS (PARTITION BY doc_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
pn AS (SELECT doc_id, par, count(*) AS n FROM gr GROUP BY ALL),
sn AS (SELECT doc_id, par, sen, count(*) AS n FROM gr SEMI JOIN (SELECT doc_id, par FROM pn WHERE n > 180) b USING (doc_id, par) GROUP BY ALL),
u0 AS (SELECT doc_id, par, 0 AS sen, 0 AS k, n FROM pn WHERE n <= 180 UNION ALL SELECT doc_id, par, sen, k, least(180, n - 180 * k) FROM (SELECT *, unnest(range(0, ((n - 1) // 180) + 1)) AS k FROM sn)),
u AS (SELECT doc_id, row_number() OVER (PARTITION BY doc_id ORDER BY par, sen, k) AS r, n FROM u0)"""


def _packed_sql(name, least_first, least):
    """Recursive packing: a unit that does not fit closes a chunk of at least ``least`` tokens, or else fills it up to 180."""
    enough = f"{name}0.s >= CASE {name}0.c WHEN 1 THEN {least_first} ELSE {least} END"
    fits = f"{name}0.s + u.n <= 180"
    return f"""{name}0 AS (SELECT doc_id, r, 1::BIGINT AS c, n::BIGINT AS s, 0::BIGINT AS base FROM u WHERE r = 1 UNION ALL
  SELECT u.doc_id, u.r, CASE WHEN {fits} THEN c ELSE c + 1 END, CASE WHEN {fits} THEN s + u.n WHEN {enough} THEN u.n ELSE s + u.n - 180 END, base + CASE WHEN {fits} THEN 0 WHEN {enough} THEN s ELSE 180 END FROM {name}0 JOIN u ON u.doc_id = {name}0.doc_id AND u.r = {name}0.r + 1),
{name}1 AS (SELECT doc_id, c, any_value(base) AS base, max(base + s) AS reach FROM {name}0 GROUP BY ALL),
{name} AS (SELECT doc_id, c, base, coalesce(lead(base) OVER w, reach) - base AS body, CASE WHEN c = 1 THEN 0 ELSE least(20, base - lag(base) OVER w) END AS lap FROM {name}1 WINDOW w AS (PARTITION BY doc_id ORDER BY c))"""


CHUNKS_SQL = f"{_UNITS_SQL}, {_packed_sql('lapped', 100, 80)}"
_PACK_SQL = f"{_UNITS_SQL}, {_packed_sql('packed', 0, 0)}"


def _chunk_sql(docs, key="doc_id"):
    return f"""WITH RECURSIVE {CHUNKS_SQL.replace('{docs}', docs)}, own AS (SELECT doc_id, regexp_extract_all(text, '{_PIECE}') AS l FROM {docs} d)
SELECT doc_id AS corpus_id, c::INT AS chunk_no, doc_id::VARCHAR || 'P' || c::VARCHAR AS chunk_id, regexp_replace(array_to_string(list_slice(l, (base - lap + 1)::BIGINT, (base + body)::BIGINT), ''), '\\s+$', '') AS text,
  body::INT AS body_tokens, lap::INT AS overlap_tokens, (body + lap)::INT AS n_tokens FROM lapped JOIN own USING (doc_id)"""


@register("split_units", rf"""WITH {_UNITS_SQL.replace('{docs}', 'documents')}, e AS (SELECT doc_id, r, n, sum(n) OVER (PARTITION BY doc_id ORDER BY r) AS upto FROM u), own AS (SELECT doc_id, regexp_extract_all(text, '{_PIECE}') AS l FROM documents)
SELECT doc_id AS corpus_id, r::INT AS unit_no, n::INT AS n_tokens, regexp_replace(array_to_string(list_slice(l, (upto - n + 1)::BIGINT, upto::BIGINT), ''), '\s+$', '') AS text FROM e JOIN own USING (doc_id)""")
def split_units(spark, sf_dir):
    return chunking.split_units(_docs(spark, sf_dir))


@register("chunk_pack", f"WITH RECURSIVE {_PACK_SQL.replace('{docs}', 'documents')} SELECT doc_id AS corpus_id, c::INT AS chunk_no, body::INT AS body_tokens FROM packed")
def chunk_pack(spark, sf_dir):
    return chunking.chunk(_docs(spark, sf_dir), chunking.ChunkConfig(merge_mode="strict")).select("corpus_id", "chunk_no", "body_tokens")


@register("chunk_merge", _chunk_sql("documents"))
def chunk_merge(spark, sf_dir):
    return chunking.chunk(_docs(spark, sf_dir))


_MODES = f"""{_PACK_SQL.replace('{docs}', 'documents')},
mg AS (SELECT doc_id, c, 1 AS m, body::BIGINT AS s FROM packed WHERE c = 1 UNION ALL SELECT p.doc_id, p.c, CASE WHEN (p.body < 80 OR mg.s < 80) AND mg.s + p.body <= 280 THEN mg.m ELSE mg.m + 1 END, CASE WHEN (p.body < 80 OR mg.s < 80) AND mg.s + p.body <= 280 THEN mg.s + p.body ELSE p.body END
  FROM mg JOIN packed p ON p.doc_id = mg.doc_id AND p.c = mg.c + 1),
cap0 AS (SELECT doc_id, m, max_by(s, c) AS body FROM mg GROUP BY ALL),
las AS (SELECT doc_id, max(c) AS z FROM packed GROUP BY doc_id), ends AS (SELECT doc_id, z, sum(body) FILTER (c >= z - 1) AS pair, sum(body) FILTER (c = z) AS tail FROM packed JOIN las USING (doc_id) GROUP BY ALL),
reb AS (SELECT p.doc_id, c, CASE WHEN z > 1 AND tail < 80 AND c = z - 1 THEN ceil(pair / 2) WHEN z > 1 AND tail < 80 AND c = z THEN pair - ceil(pair / 2) ELSE body END AS body FROM packed p JOIN ends USING (doc_id)),
every AS (SELECT 'strict' AS mode, doc_id, c, body FROM packed UNION ALL SELECT 'cap', doc_id, m, body FROM cap0 UNION ALL SELECT 'rebalance', doc_id, c, body FROM reb),
n AS (SELECT *, body + CASE WHEN c = 1 THEN 0 ELSE least(20, lag(body) OVER (PARTITION BY mode, doc_id ORDER BY c)) END AS n FROM every)"""


@register("chunk_merge_modes", f"WITH RECURSIVE {_MODES} SELECT mode, count(*) AS n_chunks, sum(n)::BIGINT AS tokens, max(n)::INT AS longest, count(*) FILTER (n < 100) AS short FROM n GROUP BY mode")
def chunk_merge_modes(spark, sf_dir):
    out = None
    for mode in ("strict", "cap", "rebalance"):
        c = chunking.chunk(_docs(spark, sf_dir), chunking.ChunkConfig(merge_mode=mode))
        row = c.agg(F.count("*").alias("n_chunks"), F.sum("n_tokens").alias("tokens"), F.max("n_tokens").alias("longest"), F.count_if(F.col("n_tokens") < 100).alias("short")).select(F.lit(mode).alias("mode"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@register("chunk_overlap", _chunk_sql("documents").replace("SELECT doc_id AS corpus_id, c::INT", "SELECT corpus_id, chunk_no, overlap_tokens, array_to_string(list_slice(regexp_extract_all(text, '" + WP + "'), 1, overlap_tokens), ' ') AS carried FROM (SELECT doc_id AS corpus_id, c::INT") + ")")
def chunk_overlap(spark, sf_dir):
    c = chunking.chunk(_docs(spark, sf_dir))
    return c.select("corpus_id", "chunk_no", "overlap_tokens", F.array_join(F.slice(T.tokenize(F.col("text")), F.lit(1), F.col("overlap_tokens")), " ").alias("carried"))


@register("chunk_ids", f"WITH RECURSIVE {CHUNKS_SQL.replace('{docs}', 'documents')} SELECT doc_id AS corpus_id, doc_id::VARCHAR || 'P' || c::INT::VARCHAR AS chunk_id FROM lapped")
def chunk_ids(spark, sf_dir):
    return chunking.chunk(_docs(spark, sf_dir)).select("corpus_id", "chunk_id")


@register("chunk_pages", _chunk_sql(f"(SELECT DISTINCT corpus_id AS doc_id, text FROM ({A.PAGE_SPANS_SQL}))"))
def chunk_pages(spark, sf_dir):
    return chunking.chunk(A.page_fulltexts(spark, sf_dir), key="corpus_id")


@register("chunk_conversations", _chunk_sql("(SELECT conv_id AS doc_id, string_agg(text, chr(10) ORDER BY turn, text) AS text FROM conversations GROUP BY conv_id)"))
def chunk_conversations(spark, sf_dir):
    turns = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("turn", "text"))), lambda s: s["text"]), "\n")
    return chunking.chunk(read_table(spark, sf_dir, "conversations").groupBy(F.col("conv_id").alias("doc_id")).agg(turns.alias("text")))


@register("chunk_rejects", f"SELECT doc_id, CASE WHEN text IS NULL OR NOT regexp_matches(text, '\\S') THEN 'empty_content' ELSE 'no_tokens' END AS reason FROM documents WHERE text IS NULL OR {_n('text', WP)} = 0")
def chunk_rejects(spark, sf_dir):
    return chunking.screen(_docs(spark, sf_dir)).filter("reason is not null").select("doc_id", "reason")


_FIXED = f"w AS (SELECT doc_id, {_n('text', WP)} AS n FROM documents), f AS (SELECT doc_id, unnest(range(1, greatest(ceil((n - 20) / 180)::INT, 1) + 1)) AS c, n FROM w WHERE n > 0)"
# sentences and paragraphs as the units of the recursive chunker count them
_SENT = """sm AS (SELECT doc_id, row_number() OVER (PARTITION BY doc_id ORDER BY sen) AS r, count(*) AS n FROM gr GROUP BY doc_id, sen),
sp AS (SELECT doc_id, r, 1::BIGINT AS c, n::BIGINT AS s, n::BIGINT AS n FROM sm WHERE r = 1 UNION ALL SELECT m.doc_id, m.r, CASE WHEN sp.s + m.n > 200 THEN sp.c + 1 ELSE sp.c END, CASE WHEN sp.s + m.n > 200 THEN m.n ELSE sp.s + m.n END, m.n FROM sp JOIN sm m ON m.doc_id = sp.doc_id AND m.r = sp.r + 1),
sc AS (SELECT doc_id, c, sum(n) AS n FROM sp GROUP BY doc_id, c)"""
_PARA = "pc AS (SELECT doc_id, row_number() OVER (PARTITION BY doc_id ORDER BY par) AS c, n FROM pn)"
_U = _UNITS_SQL.replace("{docs}", "documents")


@register("chunk_fixed_window", rf"""WITH {_FIXED}, own AS (SELECT doc_id, regexp_extract_all(text, '{_PIECE}') AS l FROM documents)
SELECT doc_id AS corpus_id, c::INT AS chunk_no, least(200, n - (c - 1) * 180)::INT AS n_tokens, regexp_replace(array_to_string(list_slice(l, (c - 1) * 180 + 1, (c - 1) * 180 + 200), ''), '\s+$', '') AS text FROM f JOIN own USING (doc_id)""")
def chunk_fixed(spark, sf_dir):
    return chunking.fixed_window(_docs(spark, sf_dir)).select("corpus_id", "chunk_no", "n_tokens", "text")


@register("chunk_by_sentence", f"WITH RECURSIVE {_U}, {_SENT} SELECT doc_id AS corpus_id, c::INT AS chunk_no, n::INT AS n_tokens FROM sc")
def chunk_by_sentence(spark, sf_dir):
    return chunking.by_sentence(_docs(spark, sf_dir)).select("corpus_id", "chunk_no", "n_tokens")


@register("chunk_by_paragraph", f"WITH {_U}, {_PARA} SELECT doc_id AS corpus_id, c::INT AS chunk_no, n::INT AS n_tokens FROM pc")
def chunk_by_paragraph(spark, sf_dir):
    return chunking.by_paragraph(_docs(spark, sf_dir)).select("corpus_id", "chunk_no", "n_tokens")


@register("chunk_whole", f"SELECT doc_id AS corpus_id, {_n('text', WP)}::INT AS n_tokens FROM documents WHERE {_n('text', WP)} > 0")
def chunk_whole(spark, sf_dir):
    return chunking.whole(_docs(spark, sf_dir)).select("corpus_id", "n_tokens")


_STAT = "count(*) AS n_chunks, floor(avg(n) * 1000 + 0.5) / 1000 AS mean_tokens, max(n)::INT AS max_tokens, count(*) FILTER (n < 100) AS short"


@register("chunk_strategy_compare", f"""WITH RECURSIVE {CHUNKS_SQL.replace('{docs}', 'documents')}, {_FIXED}, {_SENT}, {_PARA}, wh AS (SELECT n FROM w WHERE n > 0)
SELECT 'recursive' AS strategy, {_STAT} FROM (SELECT body + lap AS n FROM lapped) UNION ALL SELECT 'fixed', {_STAT} FROM (SELECT least(200, n - (c - 1) * 180) AS n FROM f)
UNION ALL SELECT 'sentence', {_STAT} FROM sc UNION ALL SELECT 'paragraph', {_STAT} FROM pc UNION ALL SELECT 'whole', {_STAT} FROM wh""")
def chunk_compare(spark, sf_dir):
    d = _docs(spark, sf_dir)
    every = {"recursive": chunking.chunk(d), "fixed": chunking.fixed_window(d), "sentence": chunking.by_sentence(d), "paragraph": chunking.by_paragraph(d), "whole": chunking.whole(d)}
    out = None
    for name, c in every.items():
        row = c.agg(F.count("*").alias("n_chunks"), (F.floor(F.avg("n_tokens") * 1000 + 0.5) / 1000).alias("mean_tokens"), F.max("n_tokens").cast("int").alias("max_tokens"), F.count_if(F.col("n_tokens") < 100).alias("short")).select(F.lit(name).alias("strategy"), "*")
        out = row if out is None else out.unionByName(row)
    return out


_DOC_MEANS = f"WITH RECURSIVE {CHUNKS_SQL.replace('{docs}', 'documents')}, m AS (SELECT doc_id, avg(body + lap) AS mean FROM lapped GROUP BY doc_id)"


@register("chunk_mean_quartiles", f"{_DOC_MEANS} SELECT count(*) AS docs, floor(quantile_cont(mean, 0.25) * 1000 + 0.5) / 1000 AS q1, floor(quantile_cont(mean, 0.5) * 1000 + 0.5) / 1000 AS median, floor(quantile_cont(mean, 0.75) * 1000 + 0.5) / 1000 AS q3 FROM m")
def chunk_mean_quartiles(spark, sf_dir):
    """Quartiles over documents of the mean chunk length; exact, as the group is one number for each document."""
    means = chunking.chunk(_docs(spark, sf_dir)).groupBy("corpus_id").agg(F.avg("n_tokens").alias("mean"))
    q = lambda p: F.floor(F.percentile("mean", p) * 1000 + 0.5) / 1000
    return means.agg(F.count("*").alias("docs"), q(0.25).alias("q1"), q(0.5).alias("median"), q(0.75).alias("q3"))
