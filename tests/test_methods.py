"""Worked examples, edge cases and invariants of the methods."""

import json
import math
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpuskit.functions import tokens
from corpuskit.operators import relational
from corpuskit.plans import acquire, chunking, encode, enrich, licensing, metrics, records, search, structure, trends, validate
from corpuskit.workloads import checks, vectors

SERVICES = ("oa_aggregator", "venue_index", "publisher_registry")


# ---------------------------------------------------------------------------- licensing


def expected(codes, veto=True):
    known = [c for c in codes if c not in (None, "UNKNOWN")]
    present = [c for c in codes if c is not None]
    if veto and len(known) >= 2 and len(set(known)) == 1:
        return known[0], "label"
    if not veto:
        for k in known:
            if known.count(k) >= 2:
                return k, "label"
    if not present:
        return None, "no_evidence"
    if not known:
        return None, "indeterminate"
    return None, "conflict" if len(set(known)) > 1 else "insufficient"


def test_all_64_vote_combinations(spark):
    values = (None, "UNKNOWN", "ATTR", "ATTR_NC")
    rows = [(i, a, b, c) for i, (a, b, c) in enumerate((a, b, c) for a in values for b in values for c in values)]
    df = spark.createDataFrame(rows, "corpus_id long, oa_aggregator string, venue_index string, publisher_registry string")
    for veto in (True, False):
        got = {r.corpus_id: (r.license, r.outcome) for r in licensing.decide(df, veto=veto).collect()}
        assert all(got[i] == expected(v, veto) for i, *v in rows)
    strict = {r.corpus_id: r.license for r in licensing.decide(df, unknown="veto").collect()}
    assert all(strict[i] == (None if "UNKNOWN" in v else expected(v)[0]) for i, *v in rows)


@pytest.mark.parametrize(
    ("raw", "code"),
    [
        ("https://creativecommons.org/licenses/by/4.0/", "ATTR"), ("https://creativecommons.org/licenses/by-nc-sa/4.0", "ATTR_NC_SA"), ("cc-by", "ATTR"), ("CC BY-NC 4.0", "ATTR_NC"),
        ("CC-BY-ND-4.0", "ATTR_ND"), ("cc by-nc-nd", "ATTR_NC_ND"), ("CC-BY-SA-4.0", "ATTR_SA"), ("CC0", "ZERO"), ("public-domain", "PUBLIC_DOMAIN"), ("PDM-1.0", "PUBLIC_DOMAIN"),
        ("other-oa", "UNKNOWN"), ("publisher-specific, author manuscript", "OTHER"), (None, None), ("US-Gov", "GOV_WORK"),
    ],
)
def test_license_spellings(spark, raw, code):
    assert spark.createDataFrame([(raw,)], "raw string").select(licensing.normalise("raw").alias("c")).first().c == code


def test_streamed_consensus_equals_wide_rule(spark):
    rows = [(1, "a"), (1, "a"), (2, "a"), (3, "a"), (3, "b"), (4, None)]
    got = {r.key: r.outcome for r in licensing.consensus(spark.createDataFrame(rows, "key long, value string")).collect()}
    assert got == {1: "label", 2: "insufficient", 3: "conflict", 4: "no_evidence"}


# ---------------------------------------------------------------------------- structure


def parsed(spark, text, **kinds):
    ann = {k: kinds.get(k, "[]") for k in structure.KINDS}
    row = spark.createDataFrame([(1, text, *ann.values())], "corpus_id long, text string, title string, abstract string, section_header string, paragraph string")
    return structure.parse_spans(row.select("corpus_id", "text", F.struct(*structure.KINDS).alias("annotations")))


@pytest.mark.parametrize(
    ("text", "kinds", "reason"),
    [
        ("", {}, "empty_text"), ("abc", {"paragraph": '[{"start":0,"end":'}, "bad_json"), ("abc", {"paragraph": '[{"start":-1,"end":2}]'}, "offset_range"),
        ("abc", {"paragraph": '[{"start":2,"end":1}]'}, "offset_range"), ("abc", {"paragraph": '[{"start":0,"end":9}]'}, "offset_range"), ("��a", {"paragraph": '[{"start":0,"end":1}]'}, "unreadable"),
        ("abc", {"section_header": '[{"start":0,"end":1}]'}, "no_paragraph"), ("abc", {"paragraph": '[{"start":0,"end":1}]'}, "no_header"),
        ("abc", {"paragraph": '[{"start":1,"end":3}]', "section_header": '[{"start":0,"end":1}]'}, None),
    ],
)
def test_structure_rejects(spark, text, kinds, reason):
    assert structure.screen_structure(parsed(spark, text, **kinds)).first().reason == reason


def test_headers_and_sections(spark):
    h = [("Introduction", "introduction", 2), ("1. INTRODUCTION", "introduction", 2), ("2.1 Materials & Methods:", "materials and methods", 2), ("Results and Discussion", "results and discussion", 2), ("Zebra", "zebra", 3), ("", "", 3)]
    got = structure.normalise_headers(spark.createDataFrame([(a,) for a, _, _ in h], "header string")).select(structure.canonical_header(F.col("header")).alias("c"), "level").collect()
    assert [(r.c, r.level) for r in got] == [(c, n) for _, c, n in h]
    text = "early|H1|one|H2|two"
    p = parsed(spark, text, paragraph='[{"start":0,"end":5},{"start":9,"end":12},{"start":16,"end":19}]', section_header='[{"start":6,"end":8},{"start":13,"end":15}]')
    rows = structure.assign_sections(p).orderBy("start").collect()
    assert [(r.header, r.text) for r in rows] == [("H1", "early"), ("H1", "one"), ("H2", "two")]
    near = structure.assign_sections(p, "closest").orderBy("start").collect()
    assert [(r.header, r.text) for r in near] == [("H1", "early"), ("H1", "one"), ("H2", "two")]
    assert [(r.header, r.body, r.n_words) for r in structure.to_sections(p).orderBy("header_start").collect()] == [("H1", "early\none", 2), ("H2", "two", 1)]
    assert structure.render(p, min_words=2).first().markdown == "### H1\nearly\none"
    bare = parsed(spark, "one|two", paragraph='[{"start":0,"end":3},{"start":4,"end":7}]')
    assert [(r.header, r.text) for r in structure.assign_sections(bare).orderBy("start").collect()] == [(None, "one"), (None, "two")]


def test_spans_of_a_long_text_are_cut_at_their_places(spark):
    """Blocks of the cutter: spans inside, across and at the bounds of blocks, with characters of two code units."""
    text = "".join(chr(0x1F600 + i % 40) if i % 7 == 0 else chr(97 + i % 26) for i in range(3 * structure.BLOCK + 10))
    at = [(0, 5), (structure.BLOCK - 3, structure.BLOCK + 3), (structure.BLOCK, 2 * structure.BLOCK), (10, 3 * structure.BLOCK), (3 * structure.BLOCK, len(text)), (7, 7)]
    p = parsed(spark, text, paragraph=json.dumps([{"start": a, "end": b} for a, b in at]))
    assert sorted((r.start, r.end, r.text) for r in structure.extract_spans(p).collect()) == sorted((a, b, text[a:b]) for a, b in at)


def test_structuring_and_chunking_have_no_exchange(spark):
    p = parsed(spark, "abc", paragraph='[{"start":0,"end":1}]')
    chunks = chunking.chunk(spark.createDataFrame([(1, "a b")], "doc_id long, text string"))
    for df in (structure.render(p), structure.assign_sections(p), chunks):
        assert "Exchange" not in df._jdf.queryExecution().executedPlan().toString()


def test_unwrap_is_idempotent(spark):
    text = "# Head\nbroken\nline here.\nNext\n\n- item\n[x] done\nEq. 4\n(3)\ntail"
    once = spark.createDataFrame([(text,)], "t string").select(structure.unwrap_lines(F.col("t")).alias("t"))
    assert once.first().t == "# Head\nbroken line here.\nNext\n\n- item\n[x] done\nEq. 4\n(3)\ntail"
    assert once.select(structure.unwrap_lines(F.col("t")).alias("t")).first().t == once.first().t


# ----------------------------------------------------------------------------- chunking


def test_chunks_keep_their_bounds_and_words(spark):
    sent = " ".join(f"w{i}" for i in range(30)) + "."
    texts = ["", "   ", "one", " ".join(["x"] * 200), " ".join(["x"] * 201), "long " * 1000, "a. " * 300, (sent + " ") * 40 + "\n" + sent, "é中😀 " * 50, None, "a\r\nb"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for mode in chunking.MERGE_MODES:
        cfg = chunking.ChunkConfig(merge_mode=mode)
        rows = chunking.chunk(df, cfg).collect()
        by = {}
        for r in rows:
            by.setdefault(r.corpus_id, []).append(r)
        assert not {0, 1, 9} & set(by)
        most = cfg.merge_cap if mode == "cap" else cfg.max_tokens
        for i, own in by.items():
            own.sort(key=lambda r: r.chunk_no)
            assert [r.chunk_id for r in own] == [f"{i}P{n + 1}" for n in range(len(own))]
            assert all(r.n_tokens <= most and r.n_tokens == r.body_tokens + r.overlap_tokens for r in own)
            words = re.findall(r"[^\W_]+|[^\w\s]|_", texts[i])
            assert sum(r.body_tokens for r in own) == len(words)
            assert own[0].overlap_tokens == 0 and all(r.overlap_tokens == min(20, p.body_tokens) for p, r in zip(own, own[1:], strict=False))
            at = 0
            for r in own:  # a chunk is a verbatim part of the text: its overlap, then its body
                assert re.findall(r"[^\W_]+|[^\w\s]|_", r.text) == words[at - r.overlap_tokens : at + r.body_tokens] and r.text in texts[i]
                at += r.body_tokens
            if mode == "fill":
                assert all(r.n_tokens >= cfg.min_tokens for r in own[:-1])


def plain_chunks(units, budget=180, least=100, overlap=20):
    """The rule for short chunks in plain Python: body lengths."""
    done, s = [], 0
    for u in units:
        if s and s + u > budget:
            full = s if s >= (least - overlap if done else least) else budget
            done.append(full)
            s = s + u - full
        else:
            s += u
    return [*done, s] if s else done


def test_filled_chunks_against_plain_python(spark):
    rng = np.random.default_rng(3)
    units = [rng.integers(1, 181, rng.integers(1, 30)).tolist() for _ in range(60)]
    df = spark.createDataFrame([(i, u) for i, u in enumerate(units)], "id long, u array<int>")
    got = {r.id: r.c for r in df.select("id", chunking.pack(F.col("u"), 180, 100, 80).alias("c")).collect()}
    assert all(got[i] == np.cumsum(plain_chunks(u)).tolist() for i, u in enumerate(units))


def test_chunk_of_a_million_characters(spark):
    df = spark.createDataFrame([(1, "word and more. " * 70_000)], "doc_id long, text string")
    got = chunking.chunk(df).agg(F.sum("body_tokens").alias("n"), F.max("n_tokens").alias("most")).first()
    assert (got.n, got.most) == (4 * 70_000, 200)


def test_chunks_pass_their_own_validation(spark):
    """None over the limit; a warning only for one short chunk at the end."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    kinds = {(r.status, tuple(r.codes)) for r in validate.chunks(chunking.chunk(docs)).select("status", "codes").distinct().collect()}
    assert kinds == {("pass", ()), ("warn", ("one_short_final",))}


def test_fixed_windows(spark):
    df = spark.createDataFrame([(1, " ".join(f"t{i}" for i in range(401)))], "doc_id long, text string")
    assert [r.n_tokens for r in chunking.fixed_window(df).orderBy("chunk_no").collect()] == [200, 200, 41]


# --------------------------------------------------------------------- vectors and search


def test_search_edges(spark):
    rows = [(0, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [float("nan"), 0.0]), (3, None), (4, [1.0]), (5, [float("inf"), 0.0]), (6, [None, 1.0]), (7, [1.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    ok = search.valid_vectors(df, 2)
    assert sorted(r.vec_id for r in ok.collect()) == [0, 1, 7]
    q = ok.filter("vec_id = 0")
    for metric in ("ip", "l2", "cosine"):
        a = [(r.id, r.rank) for r in search.topk(ok, q, 2, metric).orderBy("rank").collect()]
        b = [(r.id, r.rank) for r in search.topk_blocked(ok, q, 2, metric).orderBy("rank").collect()]
        assert a == b == [(0, 1), (7, 2)]


def test_diverse_rerank_against_plain_python(spark):
    rng = np.random.default_rng(1)
    v = rng.normal(size=(20, 5))
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    rel = np.floor(v @ v[0] * 1e6 + 0.5) / 1e6
    df = spark.createDataFrame([(1, i, float(rel[i]), v[i].tolist()) for i in range(20)], "query_id long, id long, score double, embedding array<double>")
    got = [r.id for r in search.rerank_diverse(df, 6, 0.7).orderBy("pick").collect()]
    chosen = [int(np.argmax(rel))]
    while len(chosen) < 6:
        value = {i: round(0.7 * rel[i] - 0.3 * max(v[i] @ v[c] for c in chosen), 6) for i in range(20) if i not in chosen}
        chosen.append(min(value, key=lambda i: (-value[i], i)))
    assert got == chosen
    assert [r.id for r in search.rerank_diverse(df, 3, 1.0).orderBy("pick").collect()] == np.argsort(-rel, kind="stable")[:3].tolist()


def test_inverted_file_with_all_cells_is_exact(spark, sf_dir):
    v = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    q = v.filter("vec_id < 5")
    index, exact = search.InvertedFile.build(v, 8, part_rows=20), search.topk(v, q, 10)  # cells are dealt into parts
    assert metrics.ann_recall(index.search(q, 10, 8), exact).first().recall == 1.0
    low, high = (metrics.ann_recall(index.search(q, 10, n), exact).first().recall for n in (1, 4))
    assert low <= high <= 1.0
    assert [search.cells_for(n) for n in (10, 10_000, 10**9)] == [16, 100, 31623]


def test_inverted_file_at_the_registered_probes(spark):
    """Fewer probes than cells, the whole table: recall against exact search is at least 0.9."""
    d = "/root/testdata/sf0.01"
    got = {r.nprobe: (r.cells, r.recall) for r in vectors.ivf_recall(spark, d).collect()}
    nprobe = sorted(got)[-2]
    assert nprobe == math.ceil(got[nprobe][0] * vectors.PROBED) < got[nprobe][0] and got[nprobe][1] >= 0.9
    v = spark.read.parquet(f"{d}/embeddings.parquet").select("vec_id", "embedding")
    assert metrics.ann_recall(search.InvertedFile.build(v).search(v, 10, nprobe), search.topk(v, v, 10)).first().recall >= 0.9


def test_minhash_search_deals_out_no_features(spark, monkeypatch):
    """Both forms against brute force over shared minima; rows and questions without a word, or null, meet nothing, and only ids and scores are exchanged."""
    rng = np.random.default_rng(7)
    words = [f"w{i}" for i in range(40)]
    texts = [" ".join(rng.choice(words, rng.integers(1, 12))) for _ in range(80)] + [None, "!?", "w1 w2 w3", "w1 w2 w3"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    asked = spark.createDataFrame([(0, "w1 w2 w3"), (1, "w5"), (2, None), (3, "..."), (4, "unheard of"), (5, " ".join(words))], "item_id long, text string")
    found = lambda: sorted((r.query_id, r.rank, r.id, r.score) for r in search.minhash_topk(docs, asked, 5).collect())
    got = found()
    sets = {i: set(re.findall(r"w\d+", t or "")) for i, t in enumerate(texts)}
    for q, own in ((0, {"w1", "w2", "w3"}), (1, {"w5"}), (5, set(words))):
        exact = {i: math.floor(len(own & b) / len(own | b) * 1e6 + 0.5) / 1e6 for i, b in sets.items() if own & b}
        mine = [g for g in got if g[0] == q]
        assert len(mine) == 5 and all(exact[i] == score for _, _, i, score in mine)
        assert [(-s, i) for _, _, i, s in mine] == sorted((-s, i) for _, _, i, s in mine)
    assert [g[2:] for g in got if g[:2] in ((0, 1), (0, 2))] == [(82, 1.0), (83, 1.0)] and {g[0] for g in got} == {0, 1, 5}
    plan = search.minhash_topk(docs, asked, 5)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Generate" not in plan
    monkeypatch.setattr(search, "is_small", lambda df: False)
    assert found() == got


@pytest.mark.parametrize("method", ["jaccard", "minhash_topk"])
def test_larger_question_sets_join_no_features_to_pairs(spark, monkeypatch, method):
    """Blocks and shards give the rows of the plain form, rows that share no word and null questions included, and make no row of a pair."""
    rng = np.random.default_rng(9)
    texts = [" ".join(rng.choice([f"w{i}" for i in range(30)], rng.integers(1, 9))) for _ in range(60)] + [None, "!?", "w1 w2"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    asked = spark.createDataFrame([*enumerate(texts[:9]), (90, None), (91, "..."), (92, "unheard of"), (93, "w1 w2")], "item_id long, text string")
    found = lambda: getattr(search, method)(docs, asked, 30)
    got = lambda: sorted((r.query_id, r.rank, r.id, r.score) for r in found().collect())
    want = got()
    assert {w[0] for w in want} == {*range(9), 93} | ({90, 91, 92} if method == "jaccard" else set())
    monkeypatch.setattr(search, "is_small", lambda df: False)
    assert "Join" not in found()._jdf.queryExecution().executedPlan().toString()
    assert got() == want
    monkeypatch.setattr(search._searched, "__defaults__", (4, 16))
    assert got() == want


@pytest.mark.parametrize("metric", ["ip", "l2", "cosine"])
def test_blocked_search_decides_ties_by_id(spark, metric):
    """Forty equal vectors and more: the same rows as the plain form, over any shards and blocks."""
    rng = np.random.default_rng(4)
    rows = [(i, [0.6, 0.8]) for i in range(40)] + [(100 + i, rng.normal(size=2).tolist()) for i in range(60)] + [(200 + i, [0.6 + 1e-9 * i, 0.8]) for i in range(5)]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    q = v.filter("vec_id in (3, 39, 104, 202)")
    for own in (False, True):
        want = sorted((r.query_id, r.rank, r.id, r.score) for r in search.topk(v, q, 10, metric, exclude_self=own).collect())
        for block, shard in ((2048, 8192), (2, 17)):
            assert sorted((r.query_id, r.rank, r.id, r.score) for r in search.topk_blocked(v, q, 10, metric, block, shard, own).collect()) == want
    assert [w[2] for w in want if w[0] == 3][:3] == ([0, 1, 2] if metric == "l2" else [w[2] for w in want if w[0] == 3][:3])


def test_a_large_query_set_is_not_broadcast(spark, monkeypatch):
    v = spark.createDataFrame([(i, [float(i % 7), 1.0]) for i in range(30)], "vec_id long, embedding array<double>")
    want = sorted(map(tuple, search.topk(v, v, 3).collect()))
    docs = spark.createDataFrame([(i, f"w{i % 5} w{i % 3} x") for i in range(30)], "doc_id long, text string")
    asked = docs.withColumnRenamed("doc_id", "item_id")
    exact = sorted((r.query_id, r.rank, r.id, r.score) for r in search.jaccard(docs, asked, 5).collect())
    monkeypatch.setattr(search, "is_small", lambda *_: False)
    assert "Broadcast" not in search.topk(v, v, 3)._jdf.queryExecution().executedPlan().toString()
    assert sorted((r[0], r[1], r[2], r[3]) for r in search.topk(v, v, 3).select("query_id", "id", "score", "rank").collect()) == sorted((w[0], w[1], w[2], w[3]) for w in want)
    assert sorted((r.query_id, r.rank, r.id, r.score) for r in search.jaccard(docs, asked, 5).collect()) == exact


def test_jaccard_against_plain_python(spark):
    texts = ["a b c", "b c d e", "", None, "A  b, c!", "z"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    asked = spark.createDataFrame([(7, "a b x"), (8, "z z"), (9, "")], "item_id long, text string")
    sets = {i: set(re.findall(r"\w+", (t or "").lower())) for i, t in enumerate(texts)}
    want = []
    for q, t in ((7, {"a", "b", "x"}), (8, {"z"}), (9, set())):
        scored = sorted((-(round(len(t & s) / len(t | s), 6) if t | s else 0.0), i) for i, s in sets.items())[:4]
        want += [(q, n + 1, i, -x) for n, (x, i) in enumerate(scored)]
    assert sorted((r.query_id, r.rank, r.id, r.score) for r in search.jaccard(docs, asked, 4).collect()) == [(a, b, c, pytest.approx(d)) for a, b, c, d in want]


def test_minhash_finds_nine_of_ten(spark):
    assert vectors.minhash_recall(spark, "/root/testdata/sf0.01").first().recall >= 0.9


def test_dense_retrieval_finds_the_passages(spark, sf_dir):
    r = vectors.retrieval_recall_dense(spark, "/root/testdata/sf0.01").first()
    assert r.queries == 20 and r.recall > 0.5 and r.ndcg <= 1


def test_encoders(spark):
    e = encode.HashingEncoder(64)
    x = e(["the cat", "THE cat", ""])
    assert np.allclose(x[0], x[1]) and abs(np.linalg.norm(x[0]) - 1) < 1e-6 and not x[2].any()
    df = spark.createDataFrame([(1, "a b a"), (2, None)], "doc_id long, text string")
    got = {r.doc_id: r.embedding for r in encode.embed(df, "text", e).collect()}
    assert got[2] is None and len(got[1]) == 64
    assert spark.createDataFrame([([0.0, 0.0],)], "v array<float>").select(encode.l2_normalise("v").alias("u")).first().u is None


def test_answers_cite_only_their_evidence(spark):
    ev = spark.createDataFrame([(1, 1, "7P1", "The sky is blue. Grass is green.", 8), (1, 2, "9P2", "Blue paint dries.", 4), (1, 3, "9P3", "x " * 2000, 2000)], "query_id long, rank int, chunk_id string, text string, n_tokens int")
    q = spark.createDataFrame([(1, "Why is the sky blue?")], "query_id long, question string")
    a = search.answer(ev.filter("rank < 3"), q)
    assert a.first().answer == "The sky is blue (7P1). Blue paint dries (9P2)."
    f = search.fidelity(a, ev).first()
    assert (f.n_cited, f.n_foreign) == (2, 0) and sorted(r.corpus_id for r in search.references(a).collect()) == [7, 9]
    c = search.context(ev, 100).first()
    assert c.n_evidence == 2 and c.context.startswith("[7P1] The sky")


def test_uncited_sentences_are_reported(spark, monkeypatch):
    texts = ["A b (1P1). C d. E f!", "G h (1P1). I j (2P1).", "K l? M n (9P9).", ""]
    answers = spark.createDataFrame(list(enumerate(texts)), "query_id long, answer string")
    evidence = spark.createDataFrame([(i, c) for i in range(4) for c in ("1P1", "2P1")], "query_id long, chunk_id string")
    monkeypatch.setattr(vectors, "_answers", lambda *_: answers)
    monkeypatch.setattr(vectors, "_evidence", lambda *_: evidence)
    sentences = [s for t in texts for s in re.findall(r"[^.!?]+[.!?]", t)]
    rows = {r.answers: r for r in vectors.rag_fidelity(spark, "").collect()}
    r = rows["as generated"]
    assert (r.n, r.foreign_ids, r.uncited) == (4, 1, sum("(" not in s for s in sentences)) == (4, 1, 3)
    r = rows["with faults"]  # one more foreign citation (query 0), two more bare sentences (0 and 3)
    assert (r.n, r.foreign_ids, r.uncited) == (4, 2, 5)


def test_prompts_name_the_subfields_of_their_evidence(spark):
    ev = spark.createDataFrame([(1, 1, "7P1", 7, "One.", 5), (1, 2, "7P2", 7, "Two.", 5), (1, 3, "8P1", 8, "Three.", 5), (2, 1, "9P1", 9, "Four.", 5)], "query_id long, rank int, chunk_id string, corpus_id long, text string, n_tokens int")
    labels = spark.createDataFrame([(7, "wood"), (8, "wood"), (8, "heat"), (7, "sand")], "corpus_id long, label string")
    got = {r.query_id: r.context for r in search.context(ev, 100, labels).collect()}
    assert got[1] == "Subfields: wood, heat, sand\n[7P1] One.\n[7P2] Two.\n[8P1] Three." and got[2] == "Subfields: none\n[9P1] Four."


# ------------------------------------------------------------------------------ measures


def test_overlap_by_hand(spark):
    rows = [(1, "the cat sat", "the cat sat"), (2, "a a a b", "a b b"), (3, "x y", "p q"), (4, "", "p"), (5, "b a", "a b")]
    df = spark.createDataFrame(rows, "id int, c string, r string")
    got = {r.id: (r.p, r.r, r.f1) for r in metrics.ngram_overlap(df, "c", "r", 1).collect()}
    assert got[1] == (1, 1, 1) and got[2] == (0.5, 0.666667, 0.571429) and got[3] == (0, 0, 0) and got[4] == (0, 0, 0)
    lcs = {r.id: r.r for r in metrics.lcs_overlap(df, "c", "r").collect()}
    assert lcs[1] == 1 and lcs[2] == 0.666667 and lcs[5] == 0.5 and lcs[4] == 0
    assert metrics.summary_lcs([["a", "b"], ["c"]], [["a", "x", "c"]]) == (2 / 3, 2 / 3, pytest.approx(2 / 3))


def table_lcs(a, b):
    t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            t[i + 1][j + 1] = t[i][j] + 1 if x == y else max(t[i][j + 1], t[i + 1][j])
    return t[-1][-1]


def test_subsequences_against_the_table():
    """Lengths, and the places of one longest subsequence, of random word lists; summaries clip by counts."""
    rng = np.random.default_rng(1)
    for _ in range(200):
        a, b = (rng.choice(list("abcde"), rng.integers(0, 90)).tolist() for _ in range(2))
        hits = sorted(metrics._sequence_hits(a, b))
        assert metrics.lcs_length(a, b) == table_lcs(a, b) == len(hits)
        rest = iter(b)
        assert all(a[i] in rest for i in hits)  # in this order they occur in b
    assert metrics.summary_lcs([["a", "b"], ["c"]], [["a", "x", "c"], ["b"]]) == (1.0, 0.75, pytest.approx(6 / 7))
    assert metrics.summary_lcs([], [["a"]]) == (0, 0, 0) and metrics.summary_lcs([["a"]], [["a"], ["a"]]) == (1.0, 0.5, pytest.approx(2 / 3))


def test_soft_match_against_plain_python(spark):
    rng = np.random.default_rng(2)
    vocabulary = [f"word{i}" for i in range(12)]
    unit = rng.normal(size=(12, 6))
    unit /= np.linalg.norm(unit, axis=1, keepdims=True)
    pairs = [(k, rng.choice(vocabulary, rng.integers(1, 9)).tolist(), rng.choice(vocabulary, rng.integers(1, 9)).tolist()) for k in range(15)]
    vectors_ = spark.createDataFrame([(w, v.tolist()) for w, v in zip(vocabulary, unit)], "word string, v array<double>")
    got = {r.id: (r.p, r.r, r.f1) for r in metrics.soft_match(spark.createDataFrame(pairs, "id long, candidate array<string>, reference array<string>"), vectors_).collect()}
    of = dict(zip(vocabulary, unit))
    for k, c, r in pairs:
        s = np.array([[of[x] @ of[y] for y in r] for x in c])
        p, q = s.max(1).mean(), s.max(0).mean()
        assert got[k] == pytest.approx((p, q, 2 * p * q / (p + q)), abs=2e-6)


def test_soft_match_as_a_grouped_function(spark):
    from corpuskit.functions import udfs

    udfs.register(spark)
    spark.createDataFrame([(1, "the cat", "the cat"), (1, "a dog", "a dog"), (2, "x", None)], "g int, c string, r string").createOrReplaceTempView("soft_pairs")
    got = {r.g: r.f for r in spark.sql("SELECT g, soft_match(c, r) AS f FROM soft_pairs GROUP BY g").collect()}
    assert got[1] == pytest.approx(1.0) and got[2] == 0
    assert spark.sql("SELECT encode_text('the cat') AS v").first().v == pytest.approx(encode.HashingEncoder(64)(["the cat"])[0].tolist())


def test_centrality_against_a_dense_solution():
    text = "Cats like milk. Dogs like bones. Cats like warm milk. Cats and dogs like milk. Trains are late. Late trains like rain."
    parts = [s.strip() for s in re.findall(r"[^.!?]+[.!?]", text)]
    a = (enrich._similarity(parts) > 0.1).astype(float)
    np.fill_diagonal(a, 0)
    m = np.array([row / row.sum() if row.sum() else np.full(len(row), 1 / len(row)) for row in a])
    p = np.linalg.solve(np.eye(len(m)) - 0.85 * m.T, np.full(len(m), 0.15 / len(m)))
    best = sorted(np.argsort(-p, kind="stable")[:3])
    assert enrich.central_sentences(text, 3) == " ".join(parts[i] for i in best)


def test_f1_by_hand(spark):
    truth = {(1, 0), (2, 0), (3, 1), (4, 1)}
    hits = {(1, 0), (2, 1), (3, 1), (4, 0)}
    rows = [(d, l, int((d, l) in truth), 1.0 if (d, l) in hits else 0.0) for d in range(1, 5) for l in range(3)]
    got = {r.name: r.f1 for r in metrics.f1(spark.createDataFrame(rows, "vec_id int, label int, truth int, score double")).collect()}
    assert got["micro"] == 0.5 and got["label 2"] == 0 and got["macro"] == 0.333333 and got["weighted"] == 0.5


def test_network_learns_and_its_gradient_is_right():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(600, 8))
    y = (x[:, :3] > 0.3).astype(float)
    m = enrich.MLPModel(8, 3, enrich.MLPConfig(hidden=32, epochs=20)).fit(x[100:], y[100:], x[:100], y[:100])
    assert ((m.predict(x[:100]) >= 0.5) == y[:100]).mean() > 0.85
    m = enrich.MLPModel(4, 2, enrich.MLPConfig(hidden=5, dropout=0.0))
    xs, ys, w = rng.normal(size=(7, 4)), (rng.random((7, 2)) > 0.5).astype(float), np.array([1.0, 3.0])

    def loss():
        h = xs
        for i in range(2):
            z = h @ m.w[i] + m.b[i]
            h = np.maximum(m.gamma[i] * (z - z.mean(0)) / np.sqrt(z.var(0) + 1e-5) + m.beta[i], 0)
        p = 1 / (1 + np.exp(-(h @ m.w[2] + m.b[2])))
        return -(w * ys * np.log(p) + (1 - ys) * np.log(1 - p)).mean()

    for p, g in zip(m.params(), m.gradients(xs, ys, w), strict=True):
        at = tuple(0 for _ in p.shape)
        p[at] += 1e-5
        up = loss()
        p[at] -= 2e-5
        down = loss()
        p[at] += 1e-5
        assert abs((up - down) / 2e-5 - g[at]) < 1e-5


def test_teacher_constraints(spark):
    rows = [(1, "A b. C 3 d.", '{"summary": "A b. C 3 d.", "labels": ["heat"]}'), (2, "n 5.", '{"summary": "no number", "labels": ["heat", "heat"]}'), (3, "x", "not json"), (4, "x", '{"summary": "' + "w " * 51 + '", "labels": ["nope"]}'), (5, "x", '{"summary": "A. B. C.", "labels": []}')]
    got = {r.id: set(r.codes) for r in enrich.check_teacher(spark.createDataFrame(rows, "id int, abstract string, teacher string")).collect()}
    assert got == {1: set(), 2: {"no_number", "repeated_label"}, 3: {"not_json"}, 4: {"too_long", "foreign_label"}, 5: {"many_sentences"}}


def test_every_broken_answer_is_counted(spark, sf_dir, monkeypatch):
    long = "word " * 60
    abstracts = [f"{long}first. Then 7 more. " + "x " * 600, f"{long}and 12 in one sentence. " + "x " * 600, "No figures here. " + "x " * 600, "short 1."]
    for a in abstracts[:3]:
        s = json.loads(enrich.rule_teacher(a))["summary"]
        assert len(s.split()) <= 50 and len(re.findall(r"[^.!?]+[.!?]*", s)) <= 2 and bool(re.search("[0-9]", s)) == bool(re.search("[0-9]", a))
    df = spark.createDataFrame(list(enumerate(abstracts)), "corpus_id long, abstract string")
    monkeypatch.setattr(checks.A, "abstracts", lambda *_: df)
    assert tuple(checks.teacher_constraints(spark, sf_dir).first()) == (3, 3)
    plain, three = '{"summary": "none", "labels": []}', '{"summary": "A 1. B. C.", "labels": []}'
    teacher = F.when(F.col("corpus_id") == 2, three).otherwise(plain)
    monkeypatch.setattr(enrich, "annotate", lambda a: a.withColumn("teacher", teacher))
    assert tuple(checks.teacher_constraints(spark, sf_dir).first()) == (3, 0)


def test_network_beats_the_simple_baselines(spark):
    """On held-out rows, all fitted on the same rows, the network at its full size."""
    train, test, labels = checks._split_vectors(spark, "/root/testdata/sf0.01")
    micro = lambda scores: {r.name: r.f1 for r in metrics.f1(enrich.with_truth(scores, labels)).collect()}["micro"]
    network = micro(checks._mlp_scores(train, test, labels))
    assert network >= micro(enrich.direction_scores(test, train, labels))
    assert network > micro(enrich.majority_scores(test, labels.join(train, "vec_id", "left_semi")))


def test_every_row_is_scored_by_a_model_that_has_not_seen_it(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    labels = checks.A.vector_labels(spark, sf_dir)
    cfg = enrich.MLPConfig(hidden=8, epochs=2, max_rows=60)  # the bound on training rows leaves all rows in the folds
    got = enrich.cross_validate(rows, labels, k=3, cfg=cfg).collect()
    assert sum(r.rows for r in got) == rows.count() and len(got) == 3


def test_labels_fall_back_to_the_best(spark):
    s = spark.createDataFrame([(1, 0, 0.9), (1, 1, 0.5), (1, 2, 0.4), (2, 0, 0.2), (2, 3, 0.3)], "vec_id long, label int, score double")
    assert {r.vec_id: dict(r.subfields) for r in enrich.rank_labels(s, 0.5).collect()} == {1: {"0": 0.9, "1": 0.5}, 2: {"3": 0.3}}


def test_summariser_settings_are_used(spark):
    texts = ["Cats like milk. Dogs bark 3 times. Trains are late."] * 8
    a, b = (enrich.ExtractiveSummariser().fit(texts, ["Cats like milk."] * 8, enrich.TrainConfig(epochs=n)).weights for n in (1, 5))
    assert not np.allclose(a, b)
    df = spark.createDataFrame([(i, t, "Cats like milk.") for i, t in enumerate(texts)], "corpus_id long, abstract string, reference string")
    model = enrich.fit_summariser(df, cfg=enrich.TrainConfig(max_rows=4))
    short = enrich.summarise(df, model, cfg=enrich.TrainConfig(max_in=3, max_out=2)).first().summary
    assert short == "Cats like"


def test_centrality_and_extractive_summaries():
    text = "Cats like milk. Dogs like bones. Cats like warm milk. Cats and dogs like milk. Trains are late."
    assert "Trains" not in enrich.central_sentences(text, 3)
    assert enrich.central_sentences("One. Two.", 3) == "One. Two."
    model = enrich.ExtractiveSummariser().fit([text] * 5, ["Cats like milk."] * 5)
    assert model([text])[0].startswith("Cats like milk.") and model([""]) == [""]


# ---------------------------------------------------------------------------- validation


def test_metadata_and_alignment_codes(spark):
    p = spark.createDataFrame(
        [(1, "Good title", ["A"], "V", "2020-01-01", "10.1234/x", "ATTR"), (2, "abc", [], None, None, "10.12", None), (3, None, [""], "V", "2020-01-01", None, "ATTR")],
        "corpus_id long, title string, authors array<string>, venue string, publication_date string, doi string, license string",
    )
    got = {r.id: set(r.codes) for r in validate.metadata(p).collect()}
    assert got[1] == set() and got[2] == {"short_title", "no_authors", "no_venue", "no_date", "bad_doi", "no_license"} and got[3] == {"no_title", "bad_authors", "no_doi"}
    a = spark.createDataFrame([(1, "alpha beta alpha", "alpha beta gamma"), (2, "x", "y")], "corpus_id long, abstract string, text string")
    rec = {r.id: (r.usable, r.recall) for r in validate.alignment(a, min_chars=5).collect()}
    assert rec[1] == (True, pytest.approx(2 / 3)) and rec[2] == (False, None)


def test_vectors_are_reproduced(spark):
    v = spark.createDataFrame([(1, [0.6, 0.8]), (2, [1.0, 0.0])], "id long, v array<double>")
    r = validate.reproduce(v, v).first()
    assert r.n == 2 and r.max_drift < 1e-12 and r.pearson == pytest.approx(1.0)
    e = validate.embeddings(v.select("id"), v.filter("id = 1").unionByName(spark.createDataFrame([(9, [1.0])], "id long, v array<double>")), 2).first()
    assert (e.expected, e.missing, e.extra, e.invalid) == (2, 1, 1, 1)


# ------------------------------------------------------------------------------- trends


def test_years_and_smoothing(spark):
    rows = [("2001", None, None), (None, "1999-05-01", None), (None, None, "2003-01-01"), ("n/a", "x", None), ("9999", None, "2002-02-02")]
    df = spark.createDataFrame(rows, "a string, b string, c string")
    assert [r.y for r in df.select(trends.resolve_year(F.col("a"), F.col("b"), F.col("c")).alias("y")).collect()] == [2001, 1999, 2003, None, 2002]
    s = trends.densify(spark.createDataFrame([(2000, 3), (2002, 6)], "year int, n long"), ["n"])
    sm = [(r.year, r.n_smooth) for r in trends.smooth(s, "n").orderBy("year").collect()]
    assert sm == [(2000, 1.5), (2001, 3.0), (2002, 3.0)]
    assert [r.n_smooth for r in trends.smooth(s, "n", edges="null").orderBy("year").collect()] == [None, 3.0, None]


# ------------------------------------------------------------------------------ acquire


def test_overlap_identity_and_backfill(spark):
    ids = lambda *x: spark.createDataFrame([(i,) for i in x], "corpus_id long")
    r = acquire.overlap(ids(1, 2, 3, 4), ids(1, 2, 9), ids(2, 3)).first()
    assert (r.abstract_only, r.fulltext_only, r.both, r.either, r.neither, r.identity_gap) == (1, 1, 1, 3, 1, 0)
    a = spark.createDataFrame([(1, "x"), (2, ""), (3, None)], "corpus_id long, abstract string")
    b = spark.createDataFrame([(2, "y"), (1, "z")], "corpus_id long, abstract string")
    assert sorted(map(tuple, acquire.backfill(a, b).collect()), key=str) == [(1, "x", 0), (2, "y", 1), (3, None, None)]


def test_funnel_percentages(spark):
    S, k = acquire.Step, F.col("id")
    steps = [S("a", F.lit(True)), S("b", k < 50, 0), S("c", k < 0, 1), S("d", F.lit(True), 2), S("e", F.when(k > 100, k % 2 == 0), 0)]
    r = acquire.funnel(spark.range(200), steps).orderBy("step").collect()
    assert [(x.retained, x.pct) for x in r] == [(200, None), (50, 25.0), (0, 0.0), (0, None), (49, 24.5)]


def test_the_funnel_runs_its_screens(spark):
    """Each kind of broken record leaves at its own step."""
    from corpuskit.workloads import corpus

    body = "a paragraph with enough words to stay in the rendered text of the record"
    text = f"Head\n{body}"
    whole = ("[]", "[]", json.dumps([{"start": 0, "end": 4}]), json.dumps([{"start": 5, "end": len(text)}]))
    rows = [(1, text, *whole), (2, text, *whole[:3], '[{"start": 5'), (3, text, *whole[:3], json.dumps([{"start": 5, "end": 999}])), (4, text, "[]", "[]", "[]", whole[3]), (5, text, *whole)]
    full = spark.createDataFrame(rows, "corpus_id long, text string, title string, abstract string, section_header string, paragraph string").select("corpus_id", "text", F.struct(*structure.KINDS).alias("annotations"))
    papers = spark.createDataFrame([(i, ["en" if i < 6 else "fr"]) for i in range(1, 8)], "corpus_id long, fields array<string>")
    abstracts = spark.createDataFrame([(1, "x" * 1000), (5, "x")], "corpus_id long, abstract string")
    lic = spark.createDataFrame([(i, "ATTR", "label") for i in (1, 5, 6)], "corpus_id long, license string, outcome string")
    got = {r.name: r.retained for r in corpus.funnel_of(papers, abstracts, full, lic).collect()}
    assert got == {"release": 7, "domain": 5, "abstracts": 2, "fulltexts": 5, "markdown": 2, "chunks": 2, "embeddings": 2, "licence": 2, "enrichment": 1}


def test_a_changed_release_is_refused(spark, tmp_path):
    from corpuskit.sources import tables

    path = str(tmp_path / "release")
    spark.range(20).repartition(2).write.json(path)
    manifest = tables.release_manifest(spark, path).filter("file like 'part-%'")
    assert tables.read_release(spark, manifest, path, "id long").count() == 20
    broken = manifest.withColumn("sha256", F.lit("0"))
    with pytest.raises(ValueError, match="not the pinned one"):
        tables.read_release(spark, broken, path, "id long")
    assert tables.read_release(spark, broken, path, "id long", verify=False).count() == 20


def test_bucketed_tables_join_without_an_exchange(spark, sf_dir):
    from corpuskit.workloads import relational as workload

    plan = workload.ingest_bucketed(spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Exchange" not in plan


def test_manifests_ignore_row_order(spark):
    a = spark.range(100)
    assert records.table_hash(spark.range(3)).first().checksum != records.table_hash(spark.range(1, 4)).first().checksum
    assert records.diff(records.manifest({"t": a}), records.manifest({"t": a.repartition(7)})).isEmpty()
    assert not records.diff(records.manifest({"t": a}), records.manifest({"t": spark.range(101)})).isEmpty()


# ---------------------------------------------------------------------------- operators


def test_operator_guards(spark):
    with pytest.raises(ValueError):
        relational.join_theta(spark.range(5).withColumnRenamed("id", "a"), spark.range(50).withColumnRenamed("id", "b"), F.expr("a < b"), max_rows=10)
    big, small = spark.range(1000).select((F.col("id") % 3).alias("k"), "id"), spark.range(3).select(F.col("id").alias("k"), (F.col("id") * 10).alias("v"))
    assert relational.join_salted(big, small, "k").count() == big.join(small, "k").count() == 1000
    assert math.isclose(relational.sketches(big, ["k"], "id").agg(F.avg(F.abs(F.col("distinct_sketch") - F.col("exact")) / F.col("exact"))).first()[0], 0, abs_tol=0.05)


def test_sketches_stay_within_their_error(spark):
    df = spark.range(200_000).select((F.col("id") % 2).alias("g"), (F.col("id") % 30_011).alias("v"))
    exact = {r.g: r.m for r in df.groupBy("g").agg(F.percentile("v", 0.5).alias("m")).collect()}
    for r in relational.sketches(df, ["g"], "v").collect():
        assert abs(r.distinct_hll - r.exact) < 0.1 * r.exact and abs(r.distinct_sketch - r.exact) < 0.05 * r.exact and abs(r["median"] - exact[r.g]) < 30


def test_contains_join_misses_no_passage(spark):
    docs = ["alpha beta gamma delta", "one two three four five six seven eight nine ten eleven twelve", "beta gammas", "", None, "x alpha"]
    passages = ["one two three four five six seven eight nine ten eleven", "beta gamma", "eta gamma del", "alpha", "two three four", "", "ine ten eleven tw", None]
    d = spark.createDataFrame(list(enumerate(docs)), "doc_id long, text string")
    p = spark.createDataFrame(list(enumerate(passages)), "item_id long, passage string")
    got = {(r.doc_id, r.item_id) for r in relational.join_contains(d, p).collect()}
    assert got == {(i, j) for i, t in enumerate(docs) for j, q in enumerate(passages) if t is not None and q is not None and q in t}


def test_interval_join_of_a_hot_key(spark):
    rng = np.random.default_rng(9)
    a, b = ([(1, float(t)) for t in rng.integers(0, 500_000, 150)] for _ in range(2))
    ts = lambda rows, name: spark.createDataFrame(rows, "k long, s double").select("k", F.timestamp_seconds("s").alias(name))
    got = relational.join_interval(ts(a, "l"), ts(b, "r"), "k", "l", "r", "2 HOURS").count()
    assert got == sum(0 <= y - x <= 7200 for _, x in a for _, y in b)


def test_records_are_laid_out_by_version_and_bucket(spark, tmp_path):
    df = spark.createDataFrame([(i, "1", f"t{i}") for i in range(40)], "corpus_id long, schema_version string, title string")
    records.write_records(df, str(tmp_path / "r"), "json", buckets=4)
    back = spark.read.schema("corpus_id long, title string, schema_version string, bucket int").json(str(tmp_path / "r"))
    assert back.count() == 40 and back.select("bucket").distinct().count() == 4 and back.filter("schema_version = '1'").count() == 40


def test_features_that_cancel_out_still_give_a_unit_vector(spark, tmp_path):
    """Chunks of one word that meets the prefix with the other sign, at 16 and at 64 places, have valid vectors as in SQL."""
    words = {}
    for dim in (16, 64):
        enc = encode.HashingEncoder(dim)
        at, sign = enc._place("passage")
        words[dim] = next(w for w in (f"w{i}" for i in range(10**6)) if enc._place(w) == (at, -sign))
        assert np.linalg.norm(enc([f"passage: {words[dim]}", "!?"]), axis=1).round(6).tolist() == [1, 0]
    texts = [words[16], words[64], "two words", words[16], words[64], words[64]]
    docs = spark.createDataFrame([(i + 23 * (i % 2), t) for i, t in enumerate(texts)], "doc_id long, text string")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    r = vectors.vector_alignment(spark, str(tmp_path)).first()
    kept = [i + 23 * (i % 2) for i in range(6) if (i + 23 * (i % 2)) % 19 != 4]
    assert (r.chunks, r.vectors, r.invalid) == (6, len(kept), sum(i % 23 == 5 for i in kept))
    coded = encode.embed(docs, "text", encode.HashingEncoder(16)).select(validate.fine_vector("embedding", 16).alias("fine"))
    assert coded.filter("not fine").count() == 0


@pytest.mark.parametrize("metric", ["ip", "l2", "cosine"])
def test_streamed_search_equals_the_plain_form(spark, monkeypatch, metric):
    rng = np.random.default_rng(5)
    rows = [(i, [0.6, 0.8]) for i in range(40)] + [(100 + i, rng.normal(size=2).tolist()) for i in range(60)]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3)
    q = v.filter("vec_id in (3, 39, 104)")
    found = lambda df: sorted((r.query_id, r.rank, r.id, r.score) for r in df.collect())
    for own in (False, True):
        want = found(search.topk(v, q, 10, metric, exclude_self=own))
        assert found(search.topk_streamed(v, q, 10, metric, own)) == want
    monkeypatch.setattr(search, "is_small", lambda df: False)
    assert found(search.topk_streamed(v, q, 10, metric, True)) == want


def test_unit_vectors_take_the_norm_once(spark):
    """The norm stands outside the lambda over the components, where it would be worked out for each of them."""
    v = spark.createDataFrame([(1, [3.0, 4.0]), (2, [0.0, 0.0]), (3, None)], "id int, v array<double>").select("id", encode.l2_normalise("v").alias("u"))
    assert [None if r.u is None else [round(x, 6) for x in r.u] for r in v.orderBy("id").collect()] == [[0.6, 0.8], None, None]
    assert v._jdf.queryExecution().optimizedPlan().toString().count("aggregate(") == 1


def test_word_vectors_train_in_as_many_tasks_as_the_rows_need(spark):
    docs = spark.createDataFrame([(i, "alpha beta gamma delta " * 3) for i in range(40)], "doc_id long, text string")
    for part_rows, parts in ((8192, 1), (16, 3)):
        model, rows = encode.word2vec(docs, dim=4, part_rows=part_rows)
        assert model.getNumPartitions() == parts and rows.filter("embedding is not null").count() == 40


def test_gold_passages_are_found_without_a_nested_loop(spark, tmp_path):
    from corpuskit.sources import adapters

    spark.createDataFrame([(1, "a passage"), (2, ""), (3, None), (4, "absent")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame([(7, "holds a passage here"), (8, "holds none"), (9, None)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    for most in (10_000, 2):
        gold = adapters.doc_gold(spark, str(tmp_path), most)
        assert sorted((r.item_id, r.doc_id) for r in gold.collect()) == [(1, 7), (2, 7), (2, 8)]
        assert ("NestedLoop" in gold._jdf.queryExecution().executedPlan().toString()) == (most == 2)
