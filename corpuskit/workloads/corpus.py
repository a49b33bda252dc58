"""Workloads of the corpus build: funnel, alignment, overlap, release files."""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.functions.tokens import round6
from corpuskit.plans import acquire, chunking, encode, licensing, structure, validate
from corpuskit.registry import register
from corpuskit.sources import adapters as A
from corpuskit.sources.tables import read_table, stored
from corpuskit.workloads import text

PAPERS, ABSTRACTS, REPORTS = f"papers AS ({A.PAPERS_SQL})", f"abstracts AS ({A.ABSTRACTS_SQL})", f"reports AS ({A.REPORTS_SQL})"
FULL = "fulltexts AS (SELECT doc_id AS corpus_id, text FROM documents WHERE doc_id % 5 <> 4)"
WIDE = f"""{REPORTS}, coded AS (SELECT corpus_id, service, {licensing.normalise_sql("raw")} AS code FROM reports),
wide AS (SELECT corpus_id, max(code) FILTER (service = 'oa_aggregator') AS a, max(code) FILTER (service = 'venue_index') AS v, max(code) FILTER (service = 'publisher_registry') AS p FROM coded GROUP BY corpus_id)"""
DECIDED = f"""{WIDE}, every AS (SELECT doc_id AS corpus_id, a, v, p FROM documents LEFT JOIN wide ON wide.corpus_id = doc_id),
votes AS (SELECT *, list_filter([a, v, p], lambda x: x IS NOT NULL AND x <> 'UNKNOWN') AS known, list_filter([a, v, p], lambda x: x IS NOT NULL) AS present FROM every),
decided AS (SELECT *, CASE WHEN len(known) >= 2 AND len(list_distinct(known)) = 1 THEN known[1] END AS license FROM votes),
outcomes AS (SELECT *, CASE WHEN license IS NOT NULL THEN 'label' WHEN len(present) = 0 THEN 'no_evidence' WHEN len(known) = 0 THEN 'indeterminate'
  WHEN len(list_distinct(known)) > 1 THEN 'conflict' ELSE 'insufficient' END AS outcome,
  CASE WHEN license IS NOT NULL THEN concat_ws('+', CASE WHEN a = license THEN 'oa_aggregator' END, CASE WHEN v = license THEN 'venue_index' END, CASE WHEN p = license THEN 'publisher_registry' END) END AS supporters FROM decided)"""


def wide(spark, sf_dir):
    """A row for every document: codes by service, NULL where a service has no report."""
    ids = read_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("corpus_id"))
    return ids.join(licensing.widen(A.license_reports(spark, sf_dir)), "corpus_id", "left")


@register("domain_filter", f"WITH {PAPERS} SELECT corpus_id, title, year FROM papers WHERE field = 'en'")
def domain(spark, sf_dir):
    return acquire.domain_filter(A.papers(spark, sf_dir), "en").select("corpus_id", "title", "year")


@register("align_abstracts", f"WITH {PAPERS}, {ABSTRACTS} SELECT corpus_id, title, abstract FROM papers JOIN abstracts USING (corpus_id) WHERE field = 'en'")
def align_abstracts(spark, sf_dir):
    return acquire.align(domain(spark, sf_dir), A.abstracts(spark, sf_dir)).select("corpus_id", "title", "abstract")


@register("align_fulltexts", f"WITH {PAPERS}, {FULL} SELECT corpus_id, length(text)::BIGINT AS n_chars FROM papers JOIN fulltexts USING (corpus_id) WHERE field = 'en'")
def align_fulltexts(spark, sf_dir):
    texts = A.fulltexts(spark, sf_dir).select("corpus_id", F.length("text").cast("long").alias("n_chars"))
    return acquire.align(domain(spark, sf_dir).select("corpus_id"), texts)


@register("overlap_breakdown", f"""WITH {PAPERS}, {ABSTRACTS}, {FULL},
t AS (SELECT (a.corpus_id IS NOT NULL) AS a, (f.corpus_id IS NOT NULL) AS f FROM papers p LEFT JOIN abstracts a USING (corpus_id) LEFT JOIN fulltexts f USING (corpus_id) WHERE field = 'en')
SELECT count(*) AS domain, count(*) FILTER (a AND NOT f) AS abstract_only, count(*) FILTER (f AND NOT a) AS fulltext_only, count(*) FILTER (a AND f) AS both,
  count(*) FILTER (a OR f) AS either, count(*) FILTER (NOT (a OR f)) AS neither, count(*) FILTER (a) + count(*) FILTER (f) - count(*) FILTER (a AND f) - count(*) FILTER (a OR f) AS identity_gap FROM t""")
def overlap_breakdown(spark, sf_dir):
    return acquire.overlap(domain(spark, sf_dir), A.abstracts(spark, sf_dir), A.fulltexts(spark, sf_dir))


@register("abstract_backfill", f"""WITH {ABSTRACTS}, d AS (SELECT doc_id AS corpus_id, nullif(string_split(text, chr(10))[1], '') AS b FROM documents)
SELECT corpus_id, coalesce(nullif(abstract, ''), b) AS abstract, CASE WHEN nullif(abstract, '') IS NOT NULL THEN 0 WHEN b IS NOT NULL THEN 1 END AS source_no FROM abstracts LEFT JOIN d USING (corpus_id)""")
def abstract_backfill(spark, sf_dir):
    first = read_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("corpus_id"), F.split("text", "\n")[0].alias("abstract"))
    return acquire.backfill(A.abstracts(spark, sf_dir), first)


_ALLOWED = ", ".join(repr(x) for x in licensing.STUDY_ALLOW)
_FUNNEL = f"""sp AS ({A.SPANS_SQL}), good AS (SELECT * FROM sp WHERE corpus_id % 41 <> 7), {text.SECTIONS_SQL}, {text.MARKDOWN_SQL},
d AS (SELECT corpus_id, any_value(text) AS text, max(e) AS e, count(*) FILTER (kind = 'paragraph') AS p, count(*) FILTER (kind = 'section_header') AS h FROM sp GROUP BY corpus_id),
st AS (SELECT corpus_id, trim(text) <> '' AND corpus_id % 41 <> 7 AND e <= length(text) AND p > 0 AND h > 0 AS structured FROM d),
s AS (SELECT papers.corpus_id, field = 'en' AS dom, a.corpus_id IS NOT NULL AS abs, f.corpus_id IS NOT NULL AS ful, coalesce(structured, false) AS str, coalesce(regexp_matches(markdown, '[\\p{{L}}\\p{{N}}]|[^\\p{{L}}\\p{{N}}\\s]'), false) AS chu,
  coalesce(license IN ({_ALLOWED}), false) AS lic, coalesce(length(abstract) >= 1000, false) AS enr
  FROM papers LEFT JOIN abstracts a USING (corpus_id) LEFT JOIN fulltexts f USING (corpus_id) LEFT JOIN st USING (corpus_id) LEFT JOIN md USING (corpus_id) LEFT JOIN outcomes USING (corpus_id)),
n AS (SELECT 1 AS step, 'release' AS name, count(*) AS retained, NULL AS reference FROM s UNION ALL SELECT 2, 'domain', count(*), 1 FROM s WHERE dom UNION ALL SELECT 3, 'abstracts', count(*), 2 FROM s WHERE dom AND abs
  UNION ALL SELECT 4, 'fulltexts', count(*), 2 FROM s WHERE dom AND ful UNION ALL SELECT 5, 'markdown', count(*), 4 FROM s WHERE dom AND ful AND str UNION ALL SELECT 6, 'chunks', count(*), 5 FROM s WHERE dom AND ful AND str AND chu
  UNION ALL SELECT 7, 'embeddings', count(*), 6 FROM s WHERE dom AND ful AND str AND chu UNION ALL SELECT 8, 'licence', count(*), 7 FROM s WHERE dom AND ful AND str AND chu AND lic
  UNION ALL SELECT 9, 'enrichment', count(*), 8 FROM s WHERE dom AND ful AND str AND chu AND lic AND enr)"""


@register("funnel_retention", f"""WITH {PAPERS}, {ABSTRACTS}, {FULL}, {DECIDED}, {_FUNNEL}
SELECT n.step, n.name, n.retained, n.reference, CASE WHEN r.retained = 0 THEN NULL ELSE floor(n.retained * 10000 / r.retained) / 100 END AS pct FROM n LEFT JOIN n r ON r.step = n.reference""")
def funnel_retention(spark, sf_dir):
    """Every step run for real: structuring screens, rendered Markdown, its chunks, their vectors, licences, eligibility."""
    return funnel_of(A.papers(spark, sf_dir), A.abstracts(spark, sf_dir), A.fulltexts(spark, sf_dir), licensing.decide(wide(spark, sf_dir)))


def funnel_of(papers, abstracts, fulltexts, decisions, domain_="en", dim=64):
    in_domain = acquire.domain_filter(papers, domain_).select("corpus_id")
    parsed = structure.parse_spans(acquire.align(fulltexts, in_domain))
    # the rendered texts are the product of the middle steps: written once, read by the steps behind them
    sound = stored(structure.render(structure.screen_structure(parsed).filter("reason is null")), "markdown")
    chunks = chunking.chunk(sound, text="markdown", key="corpus_id").select("corpus_id", "chunk_id", "text")
    coded = encode.embed(chunks, "text", encode.HashingEncoder(dim)).select("corpus_id", validate.fine_vector("embedding", dim).alias("fine"))
    whole_ = coded.groupBy("corpus_id").agg(F.bool_and("fine").alias("coded"))
    # narrow rows of ids and flags, put together by one grouping instead of a join for each step
    flags = ("released", "in_domain", "abstract", "eligible", "fulltext", "structured", "chunked", "coded", "kept")
    mark = lambda df, **f: df.select("corpus_id", *[(f[n] if n in f else F.lit(False)).alias(n) for n in flags])
    yes = F.lit(True)
    sides = [
        mark(papers, released=yes), mark(in_domain, in_domain=yes), mark(abstracts, abstract=yes, eligible=F.coalesce(F.length("abstract") >= 1000, F.lit(False))),
        mark(fulltexts, fulltext=yes), mark(sound, structured=yes), mark(whole_, chunked=yes, coded=F.col("coded")), mark(licensing.screen(decisions), kept=F.col("kept")),
    ]
    rows = reduce(DataFrame.unionByName, sides).groupBy("corpus_id").agg(*[F.bool_or(n).alias(n) for n in flags]).filter("released")
    S, c = acquire.Step, F.col
    return acquire.funnel(rows, [
        S("release", F.lit(True)), S("domain", c("in_domain"), 0), S("abstracts", c("abstract"), 1), S("fulltexts", c("fulltext"), 1), S("markdown", c("structured"), 3),
        S("chunks", c("chunked"), 4), S("embeddings", c("coded"), 5), S("licence", c("kept"), 6), S("enrichment", c("eligible"), 7),
    ])


@register("license_normalise", f"WITH {REPORTS} SELECT raw, {licensing.normalise_sql('raw')} AS code, count(*) AS n FROM reports GROUP BY ALL")
def license_normalise(spark, sf_dir):
    return A.license_reports(spark, sf_dir).groupBy("raw", licensing.normalise("raw").alias("code")).agg(F.count("*").alias("n"))


@register("license_coverage", f"""WITH {WIDE} SELECT (CASE WHEN a IS NULL THEN 0 ELSE 1 END + CASE WHEN v IS NULL THEN 0 ELSE 2 END + CASE WHEN p IS NULL THEN 0 ELSE 4 END)::INT AS mask, count(*) AS n
FROM documents LEFT JOIN wide ON corpus_id = doc_id GROUP BY ALL""")
def license_coverage(spark, sf_dir):
    ids = read_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("corpus_id"))
    return licensing.coverage(licensing.widen(A.license_reports(spark, sf_dir)), ids)


@register("license_decide", f"WITH {DECIDED} SELECT corpus_id, license, outcome, supporters FROM outcomes")
def license_decide(spark, sf_dir):
    return licensing.decide(wide(spark, sf_dir)).select("corpus_id", "license", "outcome", "supporters")


@register("license_reasons", f"""WITH {DECIDED} SELECT CASE WHEN license IN ({", ".join(repr(x) for x in licensing.STUDY_ALLOW)}) THEN NULL WHEN license IS NOT NULL THEN 'restrictive' ELSE outcome END AS reason, count(*) AS n FROM outcomes GROUP BY ALL""")
def license_reasons(spark, sf_dir):
    return licensing.screen(licensing.decide(wide(spark, sf_dir))).groupBy("reason").agg(F.count("*").alias("n"))


def _mix(key):
    return f"WITH {DECIDED} SELECT {key}, count(*) AS n, floor(count(*) * 1000000.0 / sum(count(*)) OVER () + 0.5) / 1000000 AS share FROM outcomes WHERE license IS NOT NULL GROUP BY {key}"


@register("license_resolution_mix", _mix("supporters"))
def license_resolution_mix(spark, sf_dir):
    return licensing.resolution_mix(licensing.decide(wide(spark, sf_dir)))


@register("license_type_mix", _mix("license"))
def license_type_mix(spark, sf_dir):
    return licensing.type_mix(licensing.decide(wide(spark, sf_dir)))


def _labels(rule):
    return f"WITH {DECIDED} SELECT license, count(*) AS n FROM (SELECT {rule} AS license FROM votes) GROUP BY ALL"


@register("license_majority_baseline", _labels("CASE WHEN a <> 'UNKNOWN' AND (a = v OR a = p) THEN a WHEN v <> 'UNKNOWN' AND v = p THEN v END"))
def license_majority(spark, sf_dir):
    return licensing.decide(wide(spark, sf_dir), veto=False).groupBy("license").agg(F.count("*").alias("n"))


@register("license_single_source_baseline", _labels("coalesce(CASE WHEN p <> 'UNKNOWN' THEN p END, CASE WHEN a <> 'UNKNOWN' THEN a END, CASE WHEN v <> 'UNKNOWN' THEN v END)"))
def license_single(spark, sf_dir):
    order = ("publisher_registry", "oa_aggregator", "venue_index")
    return licensing.decide(wide(spark, sf_dir), min_agree=1, priority=order).groupBy("license").agg(F.count("*").alias("n"))


@register("license_any_evidence_baseline", _labels("CASE WHEN len(known) >= 1 AND len(list_distinct(known)) = 1 THEN known[1] END"))
def license_any(spark, sf_dir):
    return licensing.decide(wide(spark, sf_dir), min_agree=1).groupBy("license").agg(F.count("*").alias("n"))


@register("license_unknown_veto", _labels("CASE WHEN len(known) = len(present) AND len(known) >= 2 AND len(list_distinct(known)) = 1 THEN known[1] END"))
def license_unknown_veto(spark, sf_dir):
    return licensing.decide(wide(spark, sf_dir), unknown="veto").groupBy("license").agg(F.count("*").alias("n"))


_CONSENSUS = """WITH v AS ({votes}), g AS (SELECT key, count(value) AS votes, min(value) AS low, max(value) AS high FROM v GROUP BY key)
SELECT key, votes, CASE WHEN votes >= 2 AND low = high THEN low END AS label, CASE WHEN votes >= 2 AND low = high THEN 'label' WHEN votes = 0 THEN 'no_evidence' WHEN low <> high THEN 'conflict' ELSE 'insufficient' END AS outcome FROM g"""


@register("consensus_lineitem", _CONSENSUS.format(votes=A.VOTERS_SQL.format(lineitem="lineitem")))
def consensus_lineitem(spark, sf_dir):
    return licensing.consensus(A.voter_reports(spark, sf_dir))


_LICENSE_LINE = "(?i)(licensed under|license|all rights reserved|copyright)"


@register("license_lines_in_text", f"""WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)
SELECT doc_id, line, {licensing.normalise_sql("line")} AS code, count(*) AS n FROM l WHERE regexp_matches(line, '{_LICENSE_LINE}') GROUP BY ALL""")
def license_lines(spark, sf_dir):
    lines = read_table(spark, sf_dir, "documents").filter(F.col("text").rlike(_LICENSE_LINE)).select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    return lines.filter(F.col("line").rlike(_LICENSE_LINE)).groupBy("doc_id", "line", licensing.normalise("line").alias("code")).agg(F.count("*").alias("n"))


@register("license_drift", f"""WITH {DECIDED}, n AS (SELECT corpus_id, CASE WHEN corpus_id % 23 = 0 THEN NULL WHEN corpus_id % 29 = 1 THEN 'ZERO' ELSE license END AS nl, license AS ol FROM outcomes)
SELECT CASE WHEN ol IS NOT DISTINCT FROM nl THEN 'unchanged' WHEN ol IS NULL THEN 'upgraded' WHEN nl IS NULL THEN 'revoked' ELSE 'changed' END AS kind, count(*) AS n FROM n GROUP BY ALL""")
def license_drift(spark, sf_dir):
    old = licensing.decide(wide(spark, sf_dir)).select("corpus_id", "license")
    k = F.col("corpus_id")
    new = old.withColumn("license", F.when(k % 23 == 0, F.lit(None)).when(k % 29 == 1, "ZERO").otherwise(F.col("license")))
    return licensing.drift(old, new)


@register("doi_reports_join", f"""WITH {PAPERS}, {REPORTS}, r AS (SELECT lower(doi) AS doi, min(raw) FILTER (service = 'oa_aggregator') AS oa_aggregator, min(raw) FILTER (service = 'venue_index') AS venue_index,
  min(raw) FILTER (service = 'publisher_registry') AS publisher_registry FROM papers JOIN reports USING (corpus_id) WHERE doi IS NOT NULL GROUP BY 1)
SELECT p.corpus_id, lower(p.doi) AS doi, oa_aggregator, venue_index, publisher_registry FROM papers p LEFT JOIN r ON r.doi = lower(p.doi)""")
def doi_reports_join(spark, sf_dir):
    papers = A.papers(spark, sf_dir)
    raw = A.license_reports(spark, sf_dir).join(papers.select("corpus_id", "doi"), "corpus_id").filter("doi is not null")
    with_resolver = raw.withColumn("doi", F.concat(F.lit("https://doi.org/"), F.upper("doi")))
    return licensing.collect_reports(papers, {s: with_resolver.filter(F.col("service") == s) for s in A.SERVICES})


@register("redistributable", f"""WITH {DECIDED} SELECT doc_id AS corpus_id, license, length(text)::BIGINT AS n_chars FROM documents JOIN outcomes ON corpus_id = doc_id WHERE license IN ('ATTR', 'ATTR_SA', 'ZERO', 'PUBLIC_DOMAIN', 'GOV_WORK')""")
def redistributable(spark, sf_dir):
    open_ = licensing.screen(licensing.decide(wide(spark, sf_dir)), ("ATTR", "ATTR_SA", "ZERO", "PUBLIC_DOMAIN", "GOV_WORK")).filter("kept")
    texts = read_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("corpus_id"), F.length("text").cast("long").alias("n_chars"))
    return texts.join(open_.select("corpus_id", "license"), "corpus_id")


_YEAR = "CASE WHEN corpus_id % 5 = 0 THEN NULL WHEN corpus_id % 5 = 1 THEN 'n.d.' ELSE CAST(year AS {str}) END"
_PUBLISHED = "CASE WHEN corpus_id % 3 = 0 THEN CAST(year AS {str}) || '-06' END"


@register("year_resolve", f"""WITH {PAPERS}, f AS (SELECT *, {_YEAR.format(str="VARCHAR")} AS y, {_PUBLISHED.format(str="VARCHAR")} AS published FROM papers)
SELECT corpus_id, coalesce(TRY_CAST(y AS INT), TRY_CAST(substr(published, 1, 4) AS INT), CAST(year(publication_date) AS INT)) AS year FROM f""")
def year_resolve(spark, sf_dir):
    """Three fields: the first is missing or no number for some papers, the second is there for a third of them."""
    from corpuskit.plans.trends import resolve_year

    p = A.papers(spark, sf_dir).select("corpus_id", "publication_date", F.expr(_YEAR.format(str="STRING")).alias("y"), F.expr(_PUBLISHED.format(str="STRING")).alias("published"))
    return p.select("corpus_id", resolve_year(F.col("y"), F.col("published"), F.col("publication_date").cast("string")).alias("year"))


def _profile_sql(name, docs, share):
    return f"""SELECT '{name}' AS corpus, (SELECT count(*) FROM {docs}) AS docs, (SELECT floor(avg(length(text)) * 1000 + 0.5) / 1000 FROM {docs}) AS mean_chars, (SELECT max(length(text))::BIGINT FROM {docs}) AS max_chars,
  count(*) AS chunks, floor(avg(body + lap) * 1000 + 0.5) / 1000 AS mean_tokens, {share} AS license_share, 64 AS dim FROM lapped_{name}"""


def _chunks_of(name, docs):
    body = text.CHUNKS_SQL.replace("{docs}", docs)
    for cte in ("tk", "fl", "gr", "pn", "sn", "u0", "u", "lapped0", "lapped1", "lapped"):
        body = re.sub(rf"\b{cte}\b", f"{cte}_{name}", body)
    return body


_LICENSED = f"(SELECT floor(count(*) FILTER (license IN ({_ALLOWED})) * 1000000.0 / count(*) + 0.5) / 1000000 FROM outcomes)"


@register("corpus_profile", f"""WITH RECURSIVE {DECIDED}, dd AS (SELECT doc_id, text FROM documents), pp AS (SELECT page_id AS doc_id, coalesce(any_value(text), '') AS text FROM pages LEFT JOIN ({A.PAGE_SPANS_SQL}) x ON corpus_id = page_id GROUP BY page_id),
cc AS (SELECT conv_id AS doc_id, string_agg(text, chr(10) ORDER BY turn, text) AS text FROM conversations GROUP BY conv_id), {_chunks_of('documents', 'dd')}, {_chunks_of('pages', 'pp')}, {_chunks_of('conversations', 'cc')}
{_profile_sql('documents', 'dd', _LICENSED)} UNION ALL {_profile_sql('pages', 'pp', 'NULL')} UNION ALL {_profile_sql('conversations', 'cc', 'NULL')}""")
def corpus_profile(spark, sf_dir):
    """Corpora side by side: documents, lengths, chunks, the share under an accepted licence, the vectors' size."""
    turns = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("turn", "text"))), lambda s: s["text"]), "\n")
    corpora = {
        "documents": read_table(spark, sf_dir, "documents").select("doc_id", "text"),
        "pages": A.page_fulltexts(spark, sf_dir).select(F.col("corpus_id").alias("doc_id"), "text"),
        "conversations": read_table(spark, sf_dir, "conversations").groupBy(F.col("conv_id").alias("doc_id")).agg(turns.alias("text")),
    }
    kept = licensing.screen(licensing.decide(wide(spark, sf_dir))).agg(round6(F.avg(F.col("kept").cast("double"))).alias("license_share"))
    out = None
    for name, docs in corpora.items():
        row = acquire.profile(docs, chunking.chunk(docs), 64).select(F.lit(name).alias("corpus"), "*")
        row = row.crossJoin(kept) if name == "documents" else row.withColumn("license_share", F.lit(None).cast("double"))
        out = row if out is None else out.unionByName(row)
    return out


@register("structure_parse_json", f"""WITH sp AS ({A.SPANS_SQL}) SELECT corpus_id, count(*) FILTER (kind = 'paragraph')::BIGINT AS n_paragraphs, count(*) FILTER (kind = 'section_header')::BIGINT AS n_headers
FROM sp WHERE corpus_id % 41 <> 7 GROUP BY corpus_id""")
def structure_parse_json(spark, sf_dir):
    from corpuskit.plans.structure import parse_spans

    p = parse_spans(A.fulltexts(spark, sf_dir)).filter("not bad_json")
    return p.select("corpus_id", F.size("spans.paragraph").cast("long").alias("n_paragraphs"), F.size("spans.section_header").cast("long").alias("n_headers"))
