"""Workloads of encodings, search, recommendation, answering and their measures."""

from __future__ import annotations

import math

from pyspark.sql import Window
from pyspark.sql import functions as F

from corpuskit.functions.tokens import round6
from corpuskit.plans import chunking, encode, enrich, metrics, search, validate
from corpuskit.registry import register
from corpuskit.sources import adapters as A
from corpuskit.sources.tables import read_table, stored
from corpuskit.workloads import text
from corpuskit.workloads.corpus import ABSTRACTS, PAPERS

DOT = "list_sum(list_transform(range(1, len({a}) + 1), lambda i: CAST({a}[i] AS DOUBLE) * CAST({b}[i] AS DOUBLE)))"
PROBED = 0.82  # share of the cells that a search probes: the vectors have no clusters, and fewer cells lose more than a tenth
R6 = "floor(({x}) * 1000000 + 0.5) / 1000000 + 0.0"
QUERIES = "vec_id % 100 = 0"  # the stated query set: ids divisible by 100, against all rows


def dot_sql(a, b):
    return DOT.format(a=a, b=b)


def r6(x):
    return R6.format(x=x)


def _vectors(spark, sf_dir):
    return read_table(spark, sf_dir, "embeddings").select("vec_id", "embedding")


_IP = f"SELECT q.vec_id AS query_id, e.vec_id AS id, {r6(dot_sql('e.embedding', 'q.embedding'))} AS score FROM embeddings e JOIN embeddings q ON q.{QUERIES}"
_L2 = f"SELECT q.vec_id AS query_id, e.vec_id AS id, {r6('sqrt(list_sum(list_transform(range(1, len(e.embedding) + 1), lambda i: (CAST(e.embedding[i] AS DOUBLE) - CAST(q.embedding[i] AS DOUBLE)) ** 2)))')} AS score FROM embeddings e JOIN embeddings q ON q.{QUERIES}"
_COS = f"SELECT q.vec_id AS query_id, e.vec_id AS id, {r6(dot_sql('e.embedding', 'q.embedding') + ' / (sqrt(' + dot_sql('e.embedding', 'e.embedding') + ') * sqrt(' + dot_sql('q.embedding', 'q.embedding') + '))')} AS score FROM embeddings e JOIN embeddings q ON q.{QUERIES}"


def _ranked(scores, k, order="DESC"):
    return f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score {order}, id)::INT AS rank FROM ({scores})) WHERE rank <= {k}"


@register("topk_l2", _ranked(_L2, 10, "ASC"))
def topk_l2(spark, sf_dir):
    v = _vectors(spark, sf_dir)
    return search.topk(v, v.filter(QUERIES), 10, "l2")


@register("topk_cosine", _ranked(_COS, 10))
def topk_cosine(spark, sf_dir):
    v = _vectors(spark, sf_dir)
    return search.topk(v, v.filter(QUERIES), 10, "cosine")


@register("topk_blocked", _ranked(_IP, 10))
def topk_blocked(spark, sf_dir):
    v = _vectors(spark, sf_dir)
    return search.topk_blocked(v, v.filter(QUERIES), 10)


@register("l2_cosine_same_rank", f"WITH a AS ({_ranked(_L2, 10, 'ASC')}), b AS ({_ranked(_COS, 10)}) SELECT count(*) AS n, count(*) FILTER (abs(a.score * a.score - (2 - 2 * b.score)) < 0.0001) AS same FROM a JOIN b USING (query_id, rank)")
def same_rank(spark, sf_dir):
    a = topk_l2(spark, sf_dir).select("query_id", "rank", F.col("score").alias("d"))
    both = a.join(topk_cosine(spark, sf_dir), ["query_id", "rank"])
    return both.agg(F.count("*").alias("n"), F.count_if(F.abs(F.col("d") * F.col("d") - (2 - 2 * F.col("score"))) < 0.0001).alias("same"))


@register("recommend_by_id", _ranked(f"SELECT * FROM ({_IP}) WHERE id <> query_id", 5))
def recommend_by_id(spark, sf_dir):
    return search.by_paper(_vectors(spark, sf_dir), QUERIES, 5)


_FILTER = "p.year BETWEEN 1996 AND 1999"


@register("recommend_filtered", f"WITH {PAPERS}, c AS ({_ranked(f'SELECT * FROM ({_IP}) WHERE id <> query_id', 25)}) {_ranked(f'SELECT query_id, id, score FROM c JOIN papers p ON p.corpus_id = c.id WHERE {_FILTER}', 5)}")
def recommend_filtered(spark, sf_dir):
    return search.recommend(_vectors(spark, sf_dir), A.papers(spark, sf_dir), QUERIES, 5, year=(1996, 1999))


@register("recommend_prefiltered", f"WITH {PAPERS}, c AS (SELECT * FROM ({_IP}) WHERE id <> query_id) {_ranked(f'SELECT query_id, id, score FROM c JOIN papers p ON p.corpus_id = c.id WHERE {_FILTER} AND is_oa', 5)}")
def recommend_prefiltered(spark, sf_dir):
    return search.recommend(_vectors(spark, sf_dir), A.papers(spark, sf_dir), QUERIES, 5, mode="pre", year=(1996, 1999), open_access=True)


KEYWORDS = enrich.VOCABULARY[:-1]
# confidence of a keyword label: 1 - 1 / (1 + occurrences), so one occurrence gives 0.5 and two 0.67


def scores_sql(source, key="corpus_id", text_="abstract"):
    """label, score rows of the keyword scorer; ``others`` at 0.5 where no keyword occurs."""
    parts = [f"SELECT {key}, '{w}' AS label, 1 - 1 / (1.0 + (length(lower({text_})) - length(replace(lower({text_}), '{w}', ''))) / {len(w)}) AS score FROM {source} WHERE contains(lower({text_}), '{w}')" for w in KEYWORDS]
    none = " AND ".join(f"NOT contains(lower({text_}), '{w}')" for w in KEYWORDS)
    return " UNION ALL ".join([*parts, f"SELECT {key}, 'others', 0.5 FROM {source} WHERE {text_} IS NOT NULL AND {none}"])


def subfield_map(text_="abstract"):
    """The same scores as a map column."""
    low = F.lower(F.col(text_))
    times = lambda w: (F.length(low) - F.length(F.replace(low, F.lit(w), F.lit("")))) / len(w)
    entries = F.filter(F.array(*[F.struct(F.lit(w).alias("k"), (1 - 1 / (1 + times(w))).alias("v")) for w in KEYWORDS]), lambda x: x["v"] > 0)
    others = F.array(F.struct(F.lit("others").alias("k"), F.lit(0.5).alias("v")))
    return F.when(low.isNotNull(), F.map_from_entries(F.when(F.size(entries) > 0, entries).otherwise(others)))


def _subfields(spark, sf_dir):
    return A.abstracts(spark, sf_dir).filter("abstract <> ''").select("corpus_id", subfield_map().alias("subfields"))


_SCORES = f"{ABSTRACTS}, sc AS ({scores_sql('(SELECT * FROM abstracts WHERE length(abstract) > 0)')})"


@register("recommend_by_subfield", f"WITH {PAPERS}, {_SCORES}, c AS ({_ranked(f'SELECT * FROM ({_IP}) WHERE id <> query_id', 50)}) {_ranked('SELECT query_id, c.id, c.score FROM c JOIN sc ON sc.corpus_id = c.id WHERE sc.label = ' + repr('thing') + ' AND sc.score >= 0.6', 5)}")
def recommend_by_subfield(spark, sf_dir):
    """Only papers whose confidence for one subfield is at least 0.6."""
    meta = A.papers(spark, sf_dir).join(_subfields(spark, sf_dir), "corpus_id", "left")
    return search.recommend(_vectors(spark, sf_dir), meta, QUERIES, 5, overfetch=10, subfield=("thing", 0.6))


_LEAD2 = r"(SELECT doc_id AS corpus_id, array_to_string(list_slice(list_filter(list_transform(regexp_extract_all(text, '[^.!?\n]+[.!?]*'), lambda s: trim(s)), lambda s: s <> ''), 1, 2), ' ') AS summary FROM documents)"


def _summaries(spark, sf_dir):
    return enrich.lead_k(read_table(spark, sf_dir, "documents"), 2).select(F.col("doc_id").alias("corpus_id"), "summary")


@register("recommend_cards", f"WITH {PAPERS}, c AS ({_ranked(f'SELECT * FROM ({_IP}) WHERE id <> query_id', 5)}) SELECT query_id, rank, id, score, title, year, author, venue, doi, summary FROM c LEFT JOIN papers p ON p.corpus_id = c.id LEFT JOIN {_LEAD2} l ON l.corpus_id = c.id")
def recommend_cards(spark, sf_dir):
    return search.cards(recommend_by_id(spark, sf_dir), A.papers(spark, sf_dir), _summaries(spark, sf_dir))


def _mmr(spark, sf_dir, lam=0.7):
    v = _vectors(spark, sf_dir)
    cands = search.by_paper(v, QUERIES, 30).join(v.withColumnRenamed("vec_id", "id"), "id")
    return search.rerank_diverse(cands, 6, lam)


def _mmr_sql(k, lam, pool=30):
    """Greedy picks, one step for each: the best of what is left by relevance less the closest pick so far."""
    out = f"""cand AS ({_ranked(f'SELECT * FROM ({_IP}) WHERE id <> query_id', pool)}),
sims AS (SELECT a.query_id, a.id, b.id AS other, {r6(dot_sql('x.embedding', 'y.embedding'))} AS sim FROM cand a JOIN cand b ON a.query_id = b.query_id JOIN embeddings x ON x.vec_id = a.id JOIN embeddings y ON y.vec_id = b.id),
p1 AS (SELECT query_id, 1 AS pick, id FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, id) AS n FROM cand) WHERE n = 1)"""
    for i in range(2, k + 1):
        out += f""",
p{i} AS (SELECT * FROM p{i - 1} UNION ALL SELECT query_id, {i}, id FROM (SELECT c.query_id, c.id, row_number() OVER (PARTITION BY c.query_id ORDER BY floor(({lam}::DOUBLE * any_value(c.score) - (1 - {lam}::DOUBLE) * max(s.sim)) * 1000000 + 0.5) / 1000000 DESC, c.id) AS n
  FROM cand c JOIN sims s ON s.query_id = c.query_id AND s.id = c.id JOIN p{i - 1} p ON p.query_id = c.query_id AND p.id = s.other WHERE NOT EXISTS (SELECT 1 FROM p{i - 1} z WHERE z.query_id = c.query_id AND z.id = c.id) GROUP BY c.query_id, c.id) WHERE n = 1)"""
    return f"{out} SELECT query_id, pick::INT AS pick, id FROM p{k}"


@register("mmr_rerank", f"WITH {_mmr_sql(6, 0.7)}")
def mmr_rerank(spark, sf_dir):
    return _mmr(spark, sf_dir)


@register("mmr_relevance_only", f"SELECT query_id, rank AS pick, id FROM ({_ranked(f'SELECT * FROM ({_IP}) WHERE id <> query_id', 6)})")
def mmr_relevance(spark, sf_dir):
    return _mmr(spark, sf_dir, 1.0)


@register("intra_list_diversity", f"""WITH c AS ({_ranked(f'SELECT * FROM ({_IP}) WHERE id <> query_id', 6)})
SELECT a.query_id, {r6('avg(1 - ' + dot_sql('x.embedding', 'y.embedding') + ')')} AS diversity FROM c a JOIN c b ON a.query_id = b.query_id AND a.rank < b.rank JOIN embeddings x ON x.vec_id = a.id JOIN embeddings y ON y.vec_id = b.id GROUP BY a.query_id""")
def diversity(spark, sf_dir):
    v = _vectors(spark, sf_dir).withColumnRenamed("vec_id", "id")
    return metrics.diversity(_mmr(spark, sf_dir, 1.0).join(v, "id"))


@register("mmr_diversity_gain")
def mmr_gain(spark, sf_dir):
    v = _vectors(spark, sf_dir).withColumnRenamed("vec_id", "id")
    both = [metrics.diversity(_mmr(spark, sf_dir, lam).join(v, "id")).withColumn("lam", F.lit(lam)) for lam in (1.0, 0.7, 0.3)]
    return both[0].unionByName(both[1]).unionByName(both[2])


def _ivf(v):
    index = search.InvertedFile.build(v)
    return index, math.ceil(len(index.centers) * PROBED)


@register("ivf_search")
def ivf_search(spark, sf_dir):
    """Recall of at least 0.9 against exact search is asserted in the tests and reported by ``ivf_recall``."""
    v = _vectors(spark, sf_dir)
    index, nprobe = _ivf(v)
    return index.search(v.filter(QUERIES), 10, nprobe)


@register("ivf_recall")
def ivf_recall(spark, sf_dir):
    v = _vectors(spark, sf_dir)
    q = v.filter(QUERIES)
    (index, nprobe), exact = _ivf(v), search.topk(v, q, 10)
    out = None
    for n in sorted({1, len(index.centers) // 4, nprobe, len(index.centers)}):
        row = metrics.ann_recall(index.search(q, 10, n), exact).select(F.lit(n).alias("nprobe"), F.lit(len(index.centers)).alias("cells"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@register("sharded_topk", _ranked(f"SELECT query_id, id, score FROM ({_IP}) s JOIN embeddings a ON a.vec_id = s.id JOIN embeddings b ON b.vec_id = s.query_id AND a.label = b.label", 5))
def sharded(spark, sf_dir):
    v = read_table(spark, sf_dir, "embeddings")
    return search.sharded_topk(v, v.filter(QUERIES), 5, "label")


@register("query_valid_vectors", "SELECT count(*) AS n FROM embeddings WHERE len(embedding) = 64 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0")
def valid(spark, sf_dir):
    return search.valid_vectors(read_table(spark, sf_dir, "embeddings"), 64).agg(F.count("*").alias("n"))


# ------------------------------------------------------------------------------- encodings

_HASHED = r"""w AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) AS w FROM documents), c AS (SELECT doc_id, w, count(*) AS n FROM w GROUP BY ALL),
h AS (SELECT doc_id, ('0x' || substr(md5(w), 1, 8))::BIGINT AS h, 1 + ln(n) AS wt FROM c)"""


@register("hash_features", f"WITH {_HASHED} SELECT doc_id, (h % 64)::INT AS bucket, floor(sum(CASE WHEN (h // 64) % 2 = 1 THEN -wt ELSE wt END) * 10000 + 0.5) / 10000 + 0.0 AS value FROM h GROUP BY ALL")
def hash_features(spark, sf_dir):
    f = encode.hash_features(read_table(spark, sf_dir, "documents"), 64)
    return f.select("doc_id", "bucket", (F.floor(F.col("value") * 10000 + 0.5) / 10000 + F.lit(0.0)).alias("value"))


@register("hash_features_unsigned", f"WITH {_HASHED} SELECT doc_id, (h % 64)::INT AS bucket, floor(sum(wt) * 10000 + 0.5) / 10000 AS value FROM h GROUP BY ALL")
def hash_unsigned(spark, sf_dir):
    f = encode.hash_features(read_table(spark, sf_dir, "documents"), 64, signed=False)
    return f.select("doc_id", "bucket", (F.floor(F.col("value") * 10000 + 0.5) / 10000).alias("value"))


@register("l2_normalise", f"SELECT vec_id, {r6('sqrt(' + dot_sql('embedding', 'embedding') + ')')} AS norm, 1.0 AS unit FROM embeddings")
def l2_normalise(spark, sf_dir):
    v = _vectors(spark, sf_dir).withColumn("u", encode.l2_normalise("embedding"))
    return v.select("vec_id", round6(encode.norm("embedding")).alias("norm"), (F.floor(encode.norm("u") * 10000 + 0.5) / 10000).alias("unit"))


def _chunks(spark, sf_dir):
    return chunking.chunk(read_table(spark, sf_dir, "documents"))


_N_CHUNKS = f"WITH RECURSIVE {text.CHUNKS_SQL.replace('{docs}', 'documents')} SELECT count(*) AS n"


@register("embedding_reproducibility", f"{_N_CHUNKS}, 1.0 AS mean, 1.0 AS least, true AS tight, 1.0 AS pearson FROM lapped")
def reproducibility(spark, sf_dir):
    """Every chunk encoded twice, in other batches and tasks the second time."""
    chunks = _chunks(spark, sf_dir).select(F.col("chunk_id").alias("id"), "text")
    enc = encode.HashingEncoder(64)
    a, b = (encode.embed(c, "text", enc).select("id", F.col("embedding").alias("v")) for c in (chunks, chunks.repartition(3, "id")))
    r = validate.reproduce(a, b)
    near = lambda c: F.floor(F.col(c) * 100000 + 0.5) / 100000
    return r.select("n", near("mean").alias("mean"), near("least").alias("least"), (F.col("max_drift") < 1e-6).alias("tight"), near("pearson").alias("pearson"))


_DRIFTED = "CAST(x + CASE WHEN vec_id % 10 = 3 THEN 0.01 * (i % 5) ELSE 0.0 END AS DOUBLE)"


@register("embedding_drift", f"""WITH c AS (SELECT vec_id, i, x::DOUBLE AS x, {_DRIFTED} AS y FROM (SELECT vec_id, unnest(range(0, len(embedding))) AS i, unnest(embedding)::DOUBLE AS x FROM embeddings)),
k AS (SELECT vec_id, sum(x * y) / sqrt(sum(x * x) * sum(y * y)) AS c FROM c GROUP BY vec_id)
SELECT count(*) AS n, {r6('avg(c)')} AS mean, {r6('min(c)')} AS least, {r6('max(abs(c - 1))')} AS max_drift, {r6('(SELECT corr(x, y) FROM c)')} AS pearson FROM k""")
def embedding_drift(spark, sf_dir):
    """Stored vectors against a regeneration in which every tenth is off."""
    v = _vectors(spark, sf_dir)
    off = F.transform("embedding", lambda x, i: x.cast("double") + F.when(F.col("vec_id") % 10 == 3, 0.01 * (i % 5)).otherwise(0.0))
    r = validate.reproduce(v.select(F.col("vec_id").alias("id"), F.col("embedding").alias("v")), v.select(F.col("vec_id").alias("id"), off.alias("v")))
    return r.select("n", *[round6(F.col(c)).alias(c) for c in ("mean", "least", "max_drift", "pearson")])


@register("embedding_two_plans", "SELECT count(*) AS n, 1.0 AS least_cosine FROM documents WHERE regexp_matches(text, '[\\p{L}\\p{N}]')")
def two_plans(spark, sf_dir):
    """The aggregation form and the Arrow form of the hashing encoder, compared by cosine; texts without a word have no vector in either."""
    docs = read_table(spark, sf_dir, "documents")
    agg = encode.hash_features(docs, 64)
    n = agg.groupBy("doc_id").agg(F.sqrt(F.sum(F.col("value") * F.col("value"))).alias("norm"))
    arrow = encode.embed(docs.select("doc_id", "text"), "text", encode.HashingEncoder(64), prefix="", max_tokens=10**9).select("doc_id", F.posexplode("embedding").alias("bucket", "x"))
    met = agg.join(arrow, ["doc_id", "bucket"]).groupBy("doc_id").agg(F.sum(F.col("value") * F.col("x")).alias("s")).join(n, "doc_id")
    cosine = F.try_divide(F.col("s"), F.col("norm"))
    return met.agg(F.count("*").alias("n"), (F.floor(F.min(cosine) * 100000 + 0.5) / 100000).alias("least_cosine"))


@register("paragraph_vector_alignment", f"{_N_CHUNKS} AS chunks, count(*) FILTER (doc_id % 19 <> 4) AS vectors, count(*) FILTER (doc_id % 19 = 4) AS missing, count(*) FILTER (doc_id % 23 = 5 AND doc_id % 19 <> 4) AS invalid FROM lapped".replace("count(*) AS n AS", "count(*) AS"))
def vector_alignment(spark, sf_dir):
    """One valid vector for each chunk; the vectors of some documents are lost, those of others are scaled, and both must show."""
    c = _chunks(spark, sf_dir).select("corpus_id", "chunk_id", "text")
    coded = encode.embed(c, "text", encode.HashingEncoder(64)).filter("corpus_id % 19 <> 4")
    scaled = F.when(F.col("corpus_id") % 23 == 5, F.transform("embedding", lambda x: x * F.lit(1.5).cast("float"))).otherwise(F.col("embedding"))
    r = validate.embeddings(c.select(F.col("chunk_id").alias("id")), coded.select(F.col("chunk_id").alias("id"), scaled.alias("v")), 64)
    return r.select(F.col("expected").alias("chunks"), (F.col("expected") - F.col("missing")).alias("vectors"), "missing", "invalid")


@register("abstract_vectors_eligible", f"WITH abstracts AS ({A.ABSTRACTS_SQL}) SELECT CASE WHEN length(abstract) = 0 THEN 'empty' WHEN length(abstract) < 1000 THEN 'none' ELSE 'vector' END AS kind, count(*) AS n FROM abstracts GROUP BY ALL")
def abstract_vectors(spark, sf_dir):
    a = encode.embed_abstracts(A.abstracts(spark, sf_dir), encode.HashingEncoder(64))
    kind = F.when(F.col("abstract_embedding").isNull(), "none").when(F.size("abstract_embedding") == 0, "empty").otherwise("vector")
    return a.groupBy(kind.alias("kind")).agg(F.count("*").alias("n"))


@register("encoder_tfidf")
def tfidf(spark, sf_dir):
    from pyspark.ml.functions import vector_to_array

    rows = encode.tfidf(read_table(spark, sf_dir, "documents").select("doc_id", "text"))[1]
    return rows.select("doc_id", round6(encode.norm(vector_to_array("embedding"))).alias("norm"))


@register("encoder_word2vec")
def word2vec(spark, sf_dir):
    from pyspark.ml.functions import vector_to_array

    rows = encode.word2vec(read_table(spark, sf_dir, "documents").select("doc_id", "text"))[1]
    return rows.select("doc_id", vector_to_array("embedding").cast("array<float>").alias("embedding"))


@register("encoder_recall")
def encoder_recall(spark, sf_dir):
    """The encoders by recall of the documents that hold a benchmark passage: hashing, unsigned hashing, TF-IDF, word vectors."""
    from pyspark.ml.functions import vector_to_array

    docs, asked = read_table(spark, sf_dir, "documents").select("doc_id", "text"), read_table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("doc_id"), "text")
    gold = stored(A.doc_gold(spark, sf_dir).select(F.col("item_id").alias("query_id"), F.col("doc_id").alias("id")), "gold")
    unit = lambda df: df.select(F.col("doc_id").alias("vec_id"), encode.l2_normalise("embedding").alias("embedding")).filter("embedding is not null")
    sides = {}
    for name, signed in (("hashing", True), ("unsigned", False)):
        enc = encode.HashingEncoder(256, signed=signed)
        sides[name] = [encode.embed(df, "text", enc, prefix="", max_tokens=10**9) for df in (docs, asked)]
    for name, fitted in (("tfidf", encode.tfidf(docs, 512)[0]), ("word2vec", encode.word2vec(docs)[0])):
        split = lambda df: df.withColumn("_w", F.split(F.lower(F.col("text")), r"[^\p{L}\p{N}]+"))
        sides[name] = [fitted.transform(df if name == "tfidf" else split(df)).withColumn("embedding", vector_to_array("embedding")) for df in (docs, asked)]
    out = None
    for name, (a, q) in sides.items():
        run = search.topk_streamed(unit(a), unit(q), 10)
        row = metrics.retrieval(run, gold, 10).select(F.lit(name).alias("encoder"), "*")
        out = row if out is None else out.unionByName(row)
    return out


# ------------------------------------------------------------------- answering and retrieval


def _questions(spark, sf_dir):
    return read_table(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("text"))


_JACCARD = r"""a AS (SELECT item_id AS query_id, list_distinct(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) AS a FROM benchmark),
b AS (SELECT doc_id AS id, list_distinct(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) AS b FROM documents),
m AS (SELECT query_id, id, len(list_intersect(a, b)) AS k, len(a) AS na, len(b) AS nb FROM a, b),
j AS (SELECT query_id, id, floor(coalesce(k::DOUBLE / nullif(na + nb - k, 0), 0) * 1000000 + 0.5) / 1000000 AS score FROM m)"""


def _lexical(spark, sf_dir):
    return search.jaccard(read_table(spark, sf_dir, "documents"), _questions(spark, sf_dir), 10)


@register("lexical_jaccard", f"WITH {_JACCARD} {_ranked('SELECT * FROM j', 10)}")
def lexical(spark, sf_dir):
    return _lexical(spark, sf_dir)


@register("lexical_minhash")
def minhash(spark, sf_dir):
    return search.minhash_topk(read_table(spark, sf_dir, "documents"), _questions(spark, sf_dir))


@register("lexical_minhash_recall")
def minhash_recall(spark, sf_dir):
    """Share of the exact ten best that the hashed search finds; at least 0.9 is asserted in the tests."""
    return metrics.ann_recall(minhash(spark, sf_dir), _lexical(spark, sf_dir).filter("score > 0"))


@register("retrieval_recall", f"""WITH {_JACCARD}, run AS ({_ranked('SELECT * FROM j', 10)}), gold AS (SELECT item_id AS query_id, doc_id AS id FROM ({A.DOC_GOLD_SQL})),
rel AS (SELECT query_id, count(*) AS n FROM gold GROUP BY query_id), g AS (SELECT query_id, count(*) AS hits, min(rank) AS first, sum(1 / log2(rank + 1.0)) AS dcg FROM run SEMI JOIN gold USING (query_id, id) GROUP BY query_id),
e AS (SELECT coalesce(hits / n, 0) AS recall, coalesce(1 / first, 0) AS rr, coalesce(dcg / (SELECT sum(1 / log2(i + 1.0)) FROM unnest(range(1, least(n, 10) + 1)) t(i)), 0) AS ndcg FROM rel LEFT JOIN g USING (query_id))
SELECT count(*) AS queries, {r6('avg(recall)')} AS recall, {r6('avg(rr)')} AS mrr, {r6('avg(ndcg)')} AS ndcg FROM e""")
def retrieval_recall(spark, sf_dir):
    gold = A.doc_gold(spark, sf_dir).select(F.col("item_id").alias("query_id"), F.col("doc_id").alias("id"))
    return metrics.retrieval(_lexical(spark, sf_dir), gold, 10)


# dense retrieval over hashed encodings: the same vectors in SQL


def encoded_sql(name, source, key, text_, prefix, dim=256):
    """``{name}v (id, b, v)``: the hashing encoder's unit vectors by component."""
    cut = rf"array_to_string(list_slice(regexp_extract_all({text_}, '\S+'), 1, 512), ' ')"
    return rf"""{name}w AS (SELECT id, w, count(*) AS n FROM (SELECT {key} AS id, unnest(regexp_extract_all(lower('{prefix}' || {cut}), '[\p{{L}}\p{{N}}]+')) AS w FROM {source}) GROUP BY ALL),
{name}f AS (SELECT id, h % {dim} AS b, sum(CASE WHEN (h // {dim}) % 2 = 1 THEN -1 ELSE 1 END * (1 + ln(n))) AS v FROM (SELECT id, n, ('0x' || substr(md5(w), 1, 8))::BIGINT AS h FROM {name}w) GROUP BY ALL),
{name}v AS (SELECT id, b, (v / sqrt(sum(v * v) OVER (PARTITION BY id)))::FLOAT AS v FROM {name}f)"""


def _found_sql(corpus, k=5):
    return _ranked(f"SELECT q.id AS query_id, c.id, floor(sum(c.v::DOUBLE * q.v::DOUBLE) * 1000000 + 0.5) / 1000000 + 0.0 AS score FROM qv q JOIN {corpus}v c USING (b) GROUP BY ALL", k)


_ASKED = encoded_sql("q", "benchmark", "item_id", "text", "query: ")

def _chunk_cte():
    whole = text._chunk_sql("documents").removeprefix("WITH RECURSIVE ")
    cut = whole.index("SELECT doc_id AS corpus_id")
    return f"{whole[:cut].rstrip()}, ch AS ({whole[cut:]})"


_EVIDENCE = f"{_chunk_cte()}, {_ASKED}, {encoded_sql('c', 'ch', 'chunk_id', 'text', 'passage: ')}, ev AS (SELECT f.query_id, f.rank, f.id AS chunk_id, ch.corpus_id, ch.text, ch.n_tokens, f.score FROM ({_found_sql('c')}) f JOIN ch ON ch.chunk_id = f.id)"


def retrieve(spark, sf_dir, rows, key, k=5):
    """The ``k`` best rows of ``rows`` (key, text, ...) for each question, with all their columns."""
    enc = encode.HashingEncoder(256)
    coded = encode.embed(rows.select(F.col(key).alias("vec_id"), "text"), "text", enc)
    asked = encode.embed_queries(_questions(spark, sf_dir).select(F.col("item_id").alias("vec_id"), "text"), "text", enc)
    found = search.topk_blocked(coded, asked, k).withColumnRenamed("id", key)
    return found.join(rows, key)


def _evidence(spark, sf_dir, k=5):
    """Chunk evidence from hashed encodings, exact search over all chunks."""
    return retrieve(spark, sf_dir, _chunks(spark, sf_dir).select("chunk_id", "corpus_id", "text", "n_tokens"), "chunk_id", k)


@register("rag_retrieve", f"WITH RECURSIVE {PAPERS}, {_EVIDENCE} SELECT query_id, rank, chunk_id, ev.corpus_id, text, n_tokens, score, title, year, doi FROM ev LEFT JOIN papers p ON p.corpus_id = ev.corpus_id")
def rag_retrieve(spark, sf_dir):
    """Evidence with the metadata of its papers."""
    meta = A.papers(spark, sf_dir).select("corpus_id", "title", "year", "doi")
    return _evidence(spark, sf_dir).join(meta, "corpus_id", "left").select("query_id", "rank", "chunk_id", "corpus_id", "text", "n_tokens", "score", "title", "year", "doi")


def _level(spark, sf_dir, level):
    if level == "abstract":
        rows = A.abstracts(spark, sf_dir).filter("abstract <> ''").select("corpus_id", F.col("abstract").alias("text"))
    else:
        rows = _summaries(spark, sf_dir).filter("summary <> ''").select("corpus_id", F.col("summary").alias("text"))
    return retrieve(spark, sf_dir, rows, "corpus_id").select("query_id", "rank", "corpus_id", "score", "text")


def _level_sql(source, text_):
    return f"WITH {ABSTRACTS}, rows_ AS (SELECT corpus_id, {text_} AS text FROM {source} WHERE {text_} <> ''), {_ASKED}, {encoded_sql('c', 'rows_', 'corpus_id', 'text', 'passage: ')} SELECT f.query_id, f.rank, f.id AS corpus_id, f.score, text FROM ({_found_sql('c')}) f JOIN rows_ ON corpus_id = f.id"


@register("rag_retrieve_abstracts", _level_sql("abstracts", "abstract"))
def rag_retrieve_abstracts(spark, sf_dir):
    return _level(spark, sf_dir, "abstract")


@register("rag_retrieve_summaries", _level_sql(_LEAD2, "summary"))
def rag_retrieve_summaries(spark, sf_dir):
    """Retrieval over summary vectors; the summary is a compact context."""
    return _level(spark, sf_dir, "summary")


_CONTEXT = f"""fits AS (SELECT * FROM (SELECT *, sum(n_tokens) OVER (PARTITION BY query_id ORDER BY rank) AS upto FROM ev) WHERE upto <= 1000),
cx AS (SELECT query_id, string_agg('[' || chunk_id || '] ' || text, chr(10) ORDER BY rank) AS context, count(*) AS n_evidence FROM fits GROUP BY query_id)"""


@register("rag_context", f"WITH RECURSIVE {_EVIDENCE}, {_CONTEXT} SELECT * FROM cx")
def rag_context(spark, sf_dir):
    return search.context(_evidence(spark, sf_dir))


@register("context_by_subfield", f"""WITH RECURSIVE {_EVIDENCE}, {_CONTEXT}, {_SCORES}, lc AS (SELECT query_id, label, count(*) AS n FROM (SELECT DISTINCT query_id, corpus_id FROM fits) JOIN sc USING (corpus_id) GROUP BY ALL),
lr AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY n DESC, label) AS r FROM lc), ln AS (SELECT query_id, string_agg(label, ', ' ORDER BY r) AS names FROM lr WHERE r <= 3 GROUP BY query_id)
SELECT query_id, 'Subfields: ' || coalesce(names, 'none') || chr(10) || context AS context, n_evidence FROM cx LEFT JOIN ln USING (query_id)""")
def context_by_subfield(spark, sf_dir):
    """Prompts conditioned on the subfields of the evidence."""
    labels = _subfields(spark, sf_dir).select("corpus_id", F.explode(F.map_keys("subfields")).alias("label"))
    return search.context(_evidence(spark, sf_dir), subfields=labels)


def _answers(spark, sf_dir):
    q = _questions(spark, sf_dir).select(F.col("item_id").alias("query_id"), F.col("text").alias("question"))
    return search.answer(_evidence(spark, sf_dir), q)


_ANSWER = rf"""{_EVIDENCE}, words_asked AS (SELECT item_id AS query_id, list_distinct(regexp_extract_all(lower(text), '[\p{{L}}\p{{N}}_]+')) AS asked FROM benchmark),
sn0 AS (SELECT query_id, rank, chunk_id, unnest(range(1, len(l) + 1)) AS i, unnest(l) AS s FROM (SELECT *, list_filter(list_transform(regexp_extract_all(text, '[^.!?\n]+[.!?]*'), lambda x: regexp_replace(x, '^\s+|\s+$', '', 'g')), lambda x: x <> '') AS l FROM ev)),
sb AS (SELECT *, row_number() OVER (PARTITION BY query_id, rank ORDER BY len(list_intersect(asked, list_distinct(regexp_extract_all(lower(s), '[\p{{L}}\p{{N}}_]+')))) DESC, i) AS best FROM sn0 JOIN words_asked USING (query_id)),
an AS (SELECT query_id, string_agg(rtrim(s, '.!? ') || ' (' || chunk_id || ').', ' ' ORDER BY rank) AS answer FROM sb WHERE best = 1 GROUP BY query_id)"""


@register("rag_answer", f"WITH RECURSIVE {_ANSWER} SELECT * FROM an")
def rag_answer(spark, sf_dir):
    return _answers(spark, sf_dir)


@register("rag_references", f"WITH RECURSIVE {PAPERS}, {_ANSWER}, rf AS (SELECT DISTINCT query_id, split_part(unnest(regexp_extract_all(answer, '\\((\\d+P\\d+)\\)', 1)), 'P', 1)::BIGINT AS corpus_id FROM an) SELECT query_id, rf.corpus_id, title, author, year, venue, doi FROM rf LEFT JOIN papers p ON p.corpus_id = rf.corpus_id")
def rag_references(spark, sf_dir):
    """Only the papers whose chunks are cited, with what a reference list shows."""
    meta = A.papers(spark, sf_dir).select("corpus_id", "title", "author", "year", "venue", "doi")
    return search.references(_answers(spark, sf_dir)).join(meta, "corpus_id", "left").select("query_id", "corpus_id", "title", "author", "year", "venue", "doi")


@register("rag_citation_fidelity", f"""WITH RECURSIVE {_ANSWER}, n AS (SELECT query_id, len(regexp_extract_all(answer, '\\(\\d+P\\d+\\)')) AS cited FROM an)
SELECT 'as generated' AS answers, count(*) AS n, sum(cited)::BIGINT AS cited, 0::BIGINT AS foreign_ids, 0::BIGINT AS uncited FROM n
UNION ALL SELECT 'with faults', count(*), sum(cited + CASE WHEN query_id % 4 = 0 THEN 1 ELSE 0 END)::BIGINT, count(*) FILTER (query_id % 4 = 0), count(*) FILTER (query_id % 3 = 0) FROM n""")
def rag_fidelity(spark, sf_dir):
    """The answers, and the same with a foreign citation in every fourth and an uncited sentence in every third."""
    evidence, answers = _evidence(spark, sf_dir), _answers(spark, sf_dir)
    q = F.col("query_id")
    broken = answers.withColumn("answer", F.concat("answer", F.when(q % 4 == 0, " Another claim (999999999P1).").otherwise(""), F.when(q % 3 == 0, " A claim without a source.").otherwise("")))
    out = None
    for name, df in (("as generated", answers), ("with faults", broken)):
        f = search.fidelity(df, evidence).agg(F.count("*").alias("n"), F.sum("n_cited").alias("cited"), F.sum("n_foreign").alias("foreign_ids"), F.sum("n_uncited").alias("uncited"))
        row = f.select(F.lit(name).alias("answers"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@register("retrieval_recall_dense", f"""WITH RECURSIVE {_EVIDENCE.replace('rank <= 5', 'rank <= 20')}, gold AS (SELECT item_id AS query_id, doc_id AS id FROM ({A.DOC_GOLD_SQL})),
run AS (SELECT query_id, id, row_number() OVER (PARTITION BY query_id ORDER BY first, id) AS rank FROM (SELECT query_id, corpus_id AS id, min(rank) AS first FROM ev GROUP BY ALL) QUALIFY rank <= 10),
rel AS (SELECT query_id, count(*) AS n FROM gold GROUP BY query_id), g AS (SELECT query_id, count(*) AS hits, min(rank) AS first, sum(1 / log2(rank + 1.0)) AS dcg FROM run SEMI JOIN gold USING (query_id, id) GROUP BY query_id),
e AS (SELECT coalesce(hits / n, 0) AS recall, coalesce(1 / first, 0) AS rr, coalesce(dcg / (SELECT sum(1 / log2(i + 1.0)) FROM unnest(range(1, least(n, 10) + 1)) t(i)), 0) AS ndcg FROM rel LEFT JOIN g USING (query_id))
SELECT count(*) AS queries, {r6('avg(recall)')} AS recall, {r6('avg(rr)')} AS mrr, {r6('avg(ndcg)')} AS ndcg FROM e""")
def retrieval_recall_dense(spark, sf_dir):
    """The papers of the twenty best chunks, in the order of their best chunk, against the documents that hold the passage."""
    gold = A.doc_gold(spark, sf_dir).select(F.col("item_id").alias("query_id"), F.col("doc_id").alias("id"))
    best = _evidence(spark, sf_dir, 20).groupBy("query_id", F.col("corpus_id").alias("id")).agg(F.min("rank").alias("first"))
    run = best.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("first", "id"))).filter("rank <= 10")
    return metrics.retrieval(run, gold, 10)


@register("recommend_by_text", f"WITH {PAPERS}, {_ASKED}, {encoded_sql('c', '(SELECT corpus_id, title FROM papers WHERE length(trim(title)) > 0)', 'corpus_id', 'title', 'passage: ')} {_found_sql('c')}")
def recommend_by_text(spark, sf_dir):
    """Free text as the query, over the hashed features of the titles."""
    enc = encode.HashingEncoder(256)
    titles = A.papers(spark, sf_dir).filter("length(trim(title)) > 0").select(F.col("corpus_id").alias("vec_id"), F.col("title").alias("text"))
    asked = _questions(spark, sf_dir).select(F.col("item_id").alias("vec_id"), "text")
    return search.by_text(encode.embed_places(titles, "text", enc), asked, enc, 5)
