"""Each training-data operator against brute force, and on nulls, empties, ties and clashing columns."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import zstandard
from pyspark.sql import functions as F

from corpuskit.llm import byte_bpe, chat, html_text, maxscore, near_dedup, packing, quality, repetition, token_counts, wavelet
from corpuskit.llm.common import new_path, table
from corpuskit.llm.word_tokens import WordEncoder, load_tokenizer, vocabulary_path

ODD = [None, "", "   \n ", "a", "word " * 3000, "tie tie tie", "tie tie tie", "é中😀 ß́\n\n\tx\x1cy z", "<|endoftext|> x<|startoftext|>", "x" * 20000]
SPACE = "[\\x20\\x09-\\x0D]+"


@pytest.fixture(scope="module")
def odd(spark):
    """Odd texts with columns whose names the operators use themselves."""
    rows = [(i, t, "k", [1], 2.0, 3) for i, t in enumerate(ODD)] + [(4, ODD[4], "k", [1], 2.0, 3), (None, "no id", "k", None, None, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, bands array<long>, score double, length long")


@pytest.fixture(scope="module")
def empty(odd):
    return odd.limit(0)


@pytest.fixture(scope="module")
def docs(spark, sf_dir):
    return table(spark, sf_dir, "documents")


def words(text):
    return [w for w in re.split(SPACE, text or "") if w]


# ------------------------------------------------------------------ 7 repetition rules


def brute_base(text):
    w = words(text)
    seen = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    covered = {j for i in range(len(w) - 7) if seen[tuple(w[i : i + 8])] > 1 for j in range(i, i + 8)}
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    n = len(w)
    return (n, sum(map(len, w)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(covered),
            n < 20 or 100 * len(covered) > 30 * n)


def test_repetition_equals_brute_force(docs, odd):
    for df in (docs, odd):
        texts = sorted((r.doc_id is None, r.doc_id or 0, r.text or "") for r in df.select("doc_id", "text").collect())
        got = sorted(((r.doc_id is None, r.doc_id or 0), r[1:7], r.kept) for r in repetition.repetition_quality(df).collect())
        want = sorted(((none, i), brute_base(t)) for none, i, t in texts)
        assert [g[:2] for g in got] == want
        assert not any(kept and base[5] for _, base, kept in got)


def brute_verdict(text, rules):
    """The shares of the repetition rules, word by word, and the verdict."""
    w, base = words(text), brute_base(text)
    n, total = len(w), sum(map(len, w))
    top = dup = 0.0
    for k in sorted({*rules.top, *rules.duplicate}):
        places = defaultdict(list)
        for i in range(n - k + 1):
            places[tuple(w[i : i + k])].append(i)
        again = [p for p in places.values() if len(p) > 1]
        chars = lambda starts: sum(len(w[j]) for j in {j for i in starts for j in range(i, i + k)})  # noqa: B023, E731
        if k in rules.top and again:
            top = max(top, max(map(chars, again)) / total / rules.top[k])
        if k in rules.duplicate and again:
            dup = max(dup, chars([i for p in again for i in p]) / total / rules.duplicate[k])
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    twice = [x for i, x in enumerate(lines) if x in set(lines[:i])]
    share = sum(map(len, twice)) / max(1, sum(map(len, lines)))
    return dup, not (base[5] or top > 1 or dup > 1 or share > rules.line_chars or base[2] > rules.symbols * n)


def test_repetition_shares_and_verdict_equal_brute_force(docs):
    rules = repetition.RepetitionRules()
    got = {r.doc_id: r for r in repetition.repetition_quality(docs).collect()}
    verdicts = set()
    for r in docs.select("doc_id", "text").collect():
        dup, kept = brute_verdict(r.text, rules)
        assert abs(got[r.doc_id].dup_share - dup) < 1e-9 and got[r.doc_id].kept == kept
        verdicts.add(kept)
    assert verdicts == {True, False}


def test_repetition_keeps_columns_and_empty_tables(odd, empty):
    kept = repetition.keep_good(odd)
    assert kept.columns == odd.columns and kept.filter("text is null").isEmpty()
    assert repetition.repetition_quality(empty).count() == 0 and repetition.keep_good(empty).count() == 0


def test_repetition_covers_top_and_duplicate_grams(spark):
    clean = " ".join(f"w{i}" for i in range(200))
    phrase = " ".join(f"w{i}" for i in range(60)) + " same five words come back" * 20 + " " + " ".join(f"v{i}" for i in range(40))
    rows = repetition.repetition_quality(spark.createDataFrame([(1, clean), (2, phrase)], "doc_id long, text string")).orderBy("doc_id").collect()
    assert rows[0].kept and not rows[1].kept and rows[0].dup_share == 0 and rows[1].dup_share > 1


# --------------------------------------------------------------------- 4 quality model


def test_quality_separates_held_out_labels(spark):
    d = "/root/testdata/sf0.01"
    got = quality.classify(table(spark, d, "documents")).join(table(spark, d, "labels"), "doc_id").toPandas()
    good, bad = got[got.quality == 1], got[got.quality == 0]
    assert good.kept.mean() > 0.98 and (~bad.kept).mean() > 0.75


def brute_votes(text):
    """The labellers of the quality model in plain Python."""
    w = words(text)
    n = len(w)
    raw = text or ""
    data = raw.encode()
    lower = sum(97 <= c <= 122 or c >= 128 for c in data)
    upper = sum(65 <= c <= 90 for c in data)
    lines = [x for x in raw.split("\n") if x]
    low = [re.sub("[A-Z]", lambda m: m[0].lower(), x) for x in w]
    bare = [x[:-1] if x[-1] in ".,!?;:" else x for x in low]
    stop, long_ = sum(x in set(quality.STOP_WORDS) for x in bare) / n, n >= 20
    symbols, bars, shouts = sum(c in "#*$%&|<>" for c in raw) / n, raw.count("|"), raw.count("!") / n
    caps, variety, size = upper / max(1, upper + lower), len(set(low)) / n, sum(len(x.encode()) for x in w) / n
    repeats = (len(lines) - len(set(lines))) / max(1, len(lines))
    ends, same = sum(c in ".!?" for c in raw), sum(a == b for a, b in zip(low, low[1:]))
    vote = lambda good, bad: -1 if bad else 1 if good else 0
    return [
        vote(symbols < 0.02, symbols > 0.6), vote(bars * 50 < n, bars * 5 > n), vote(caps < 0.08 and long_, caps > 0.3 and long_), vote(shouts < 0.05, shouts > 0.5),
        vote(variety > 0.5 and long_, variety < 0.3 and long_), vote(stop > 0.12 and long_, stop < 0.02 and long_), vote(3 < size < 9 and long_, (size < 2.5 or size > 12) and long_),
        vote(repeats == 0 and len(lines) > 2, repeats > 0.5 and len(lines) > 3), vote(ends * 30 > n and ends * 2 < n and long_, ends * 100 < n and long_), vote(same * 50 < n and long_, same * 5 > n and long_),
    ]


def brute_posteriors(texts, rounds=100):
    """Posterior of good for each text by EM over its votes, one text at a time."""
    votes = [brute_votes(t) for t in texts]
    post = [1 / (1 + np.exp(-(2 + 0.2 * v.count(1) - 6 * v.count(-1)))) for v in votes]
    for _ in range(rounds):
        p = []
        for c in (0, 1):
            w = [x if c else 1 - x for x in post]
            each = []
            for j in range(len(quality.LABELLERS)):
                up = sum(a for a, v in zip(w, votes) if v[j] == 1) + 1
                down = sum(a for a, v in zip(w, votes) if v[j] == -1) + 1
                each.append({1: up / (up + down), -1: down / (up + down), 0: 1.0})
            p.append(each)
        prior = min(max(sum(post) / len(post), 1e-3), 1 - 1e-3)
        new = []
        for v in votes:
            bad, good = (np.prod([p[c][j][x] for j, x in enumerate(v)]) * q for c, q in ((0, 1 - prior), (1, prior)))
            new.append(good / (good + bad))
        done, post = max(abs(a - b) for a, b in zip(new, post)) < 1e-7, new
        if done:
            break
    return post


def test_quality_equals_brute_force(docs):
    """Weak labels of every document equal an EM in plain Python; the scorer, fitted to them, follows them."""
    rows = sorted(docs.select("doc_id", "text").collect())
    full = [r for r in rows if words(r.text)]
    want = dict(zip([r.doc_id for r in full], brute_posteriors([r.text for r in full]), strict=True))
    got = {r.doc_id: r for r in quality.classify(docs).collect()}
    assert all(abs(got[i].weak_label - p) < 1e-6 for i, p in want.items())
    assert np.mean([(got[i].score >= 0.5) == (p >= 0.5) for i, p in want.items()]) > 0.97
    assert all(r.kept == (r.score >= 0.5) for r in got.values()) and not any(r.kept for i, r in got.items() if i not in want)


def test_quality_edges(odd, empty, docs):
    got = {r.doc_id: r for r in quality.score_documents(odd, quality.fit(docs)).collect()}
    assert not got[0].kept and not got[1].kept and not got[2].kept and got[5].score == got[6].score
    assert quality.classify(empty).count() == 0 and quality.keep_good(odd).columns == odd.columns


def test_label_model_recovers_accuracies():
    rng = np.random.default_rng(3)
    truth = rng.random(20000) < 0.7
    right = np.array([0.9, 0.8, 0.75, 0.95])
    votes = np.where(rng.random((20000, 4)) < right, 1, -1) * np.where(truth, 1, -1)[:, None]
    patterns, counts = np.unique(votes, axis=0, return_counts=True)
    post, tables, prior = quality.label_model(patterns, counts)
    assert abs(prior - 0.7) < 0.05 and np.allclose(tables[1, :, 2], right, atol=0.04) and np.allclose(tables[0, :, 0], right, atol=0.04)


# ----------------------------------------------------------------- 3 near duplicates


def shingles(text):
    w = words((text or "").lower())
    k = min(5, len(w))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if w else set()


def brute_weights(texts, gain=0.1, floor=0.005, bits=18):
    """TF-IDF weights of the shingles of each text: those in a share of the documents below the floor count as rare."""
    counts = [Counter(shingle_list(t)) for t in texts]
    df = Counter(s for c in counts for s in c)
    n = sum(t is not None for t in texts)
    least = max(2, floor * n, 2 * sum(df.values()) / 2**bits)
    idf = {s: 1 + gain * np.log((1 + n) / (1 + k)) / np.log(2 + n) if k >= least else 1 + gain for s, k in df.items()}
    return [{s: idf[s] * (1 + np.log(k)) for s, k in c.items()} for c in counts]


def shingle_list(text):
    w = words(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    k = min(5, len(w))
    return [tuple(w[i : i + k]) for i in range(len(w) - k + 1)] if w else []


def alike(a, b):
    shared = sum(min(w, b[s]) for s, w in a.items() if s in b)
    return shared / (sum(a.values()) + sum(b.values()) - shared) if shared else 0.0


def weighted_links(texts, threshold=0.8):
    sets = brute_weights(texts)
    total = [sum(s.values()) for s in sets]
    return [(a, b) for a in range(len(sets)) for b in range(a) if min(total[a], total[b]) >= threshold * max(total[a], total[b], 1e-9) and alike(sets[a], sets[b]) >= threshold]


def brute_classes(n, links):
    label = list(range(n))

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    for a, b in links:
        x, y = sorted((find(a), find(b)))
        label[y] = x
    return [find(i) for i in range(n)]


def test_near_duplicates_equal_brute_force(docs):
    """Same classes as all pairs of the smoke table compared by weighted Jaccard similarity."""
    rows = sorted(docs.select("doc_id", "text").collect())
    got = {r.doc_id: r.class_id for r in near_dedup.near_duplicate_classes(docs).collect()}
    links = weighted_links([r.text for r in rows])
    want = brute_classes(len(rows), links)
    same = [got[rows[a].doc_id] == got[rows[b].doc_id] for a, b in links]
    assert len(links) > 10 and np.mean(same) >= 0.99
    by_class = defaultdict(set)
    for i, r in enumerate(rows):
        by_class[got[r.doc_id]].add(want[i])
    assert all(len(v) == 1 for v in by_class.values())  # no class joins what brute force keeps apart


def test_near_duplicate_recall_on_more_documents(spark):
    """At sf0.01 at least 99 of 100 linked pairs, plain similarity included, end in one class."""
    df = table(spark, "/root/testdata/sf0.01", "documents")
    rows = df.select("doc_id", "text").collect()
    got = {r.doc_id: r.class_id for r in near_dedup.near_duplicate_classes(df).collect()}
    sets = [(r.doc_id, shingles(r.text)) for r in rows]
    links = [(a, b) for i, (a, x) in enumerate(sets) for b, y in sets[:i] if x and y and 0.8 * max(len(x), len(y)) <= min(len(x), len(y)) and len(x & y) >= 0.8 * len(x | y)]
    assert len(links) > 100 and sum(got[a] == got[b] for a, b in links) >= 0.99 * len(links)
    assert all(c <= i for i, c in got.items())


def test_near_duplicates_in_a_large_group(spark):
    """A third of all rows are near copies: idf and bucket leaders must not break the group."""
    base = [f"tok{i}" for i in range(120)]
    near = [" ".join(base[:j] + [f"new{j}"] + base[j + 1 :]) for j in range(0, 120, 2)]
    others = [" ".join(f"o{k}x{i}" for i in range(80)) for k in range(90)]
    df = spark.createDataFrame(list(enumerate(near + others + near[:10])), "doc_id long, text string")
    got = {r.doc_id: r.class_id for r in near_dedup.near_duplicate_classes(df).collect()}
    assert {got[i] for i in range(60)} == {0} and {got[i] for i in range(150, 160)} == {0}
    assert all(got[i] == i for i in range(60, 150))


def template_pages(n, own=42, changed=24):
    """Pages on one template, below 0.8 of each other, each with a partner at 0.8 or more."""
    base = " ".join(f"t{i}" for i in range(200))
    pages = []
    for p in range(n):
        mine = [f"p{p}x{i}" for i in range(own)]
        pages += [f"{base} {' '.join(mine)}", f"{base} {' '.join(mine[: own - changed] + [f'q{p}x{i}' for i in range(changed)])}"]
    return pages


def missed_candidates(spark, texts, cfg=None):
    """Links between texts that share a band, and those of them that end in different classes."""
    cfg = cfg or near_dedup.NearDedup()
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r.class_id for r in near_dedup.near_duplicate_classes(df, cfg=cfg).collect()}
    bands = {r.doc_id: set(r.bands) for r in near_dedup.signatures(df, near_dedup.shingle_weights(df, cfg), cfg).collect()}
    links = [(a, b) for a, b in weighted_links(texts) if bands[a] & bands[b]]
    return links, [p for p in links if got[p[0]] != got[p[1]]]


def test_near_duplicates_of_small_groups_beside_a_large_one(spark):
    """The links of one large group do not end the search for the links of the others."""
    base = [f"tok{i}" for i in range(120)]
    near = [" ".join(base[:j] + [f"new{j}n{k}"] + base[j + 1 :]) for j in range(120) for k in range(5)]
    links, missed = missed_candidates(spark, near[::3] + template_pages(60))
    assert len(links) > 60 and not missed


def test_near_duplicates_in_a_hot_bucket(spark):
    """Each page of a bucket far above the cap still finds its partner, and only few pairs are compared for it."""
    links, missed = missed_candidates(spark, template_pages(200))
    assert len(links) > 180 and not missed


def test_rare_shingles_keep_every_link(spark):
    """All pairs at the threshold or above meet by their rare shingles; most others do not."""
    cfg = near_dedup.NearDedup(block=16)
    texts = template_pages(30) + template_pages(10, own=60, changed=15) + [f"short{i} text" for i in range(5)]
    df = spark.createDataFrame([(i, t, zstandard.compress(t.encode())) for i, t in enumerate(texts)], "id long, text string, body binary")
    weights = near_dedup.shingle_weights(df, cfg)
    for label in (F.col("id"), F.col("id") % 3):
        own = df.select("id", label.alias("label"))
        got = {(r.a, r.b) for r in near_dedup._prefix_pairs(own, df.select("id", "body"), weights, cfg).collect()}
        sets = [near_dedup.weighted_set(t.encode(), weights, cfg) for t in texts]
        of = {r.id: r.label for r in own.collect()}
        every = [(a, b) for b in range(len(texts)) for a in range(b) if of[a] != of[b]]
        want = {p for p in every if near_dedup.similarity(sets[p[0]], sets[p[1]]) >= cfg.threshold}
        assert len(want) >= 20 and want <= got and len(got) < 0.2 * len(every)


def test_weights_of_frequent_shingles_are_exact(spark):
    texts = ["every text has these five words and own" + str(i) + " words that no other one has" + str(i) for i in range(300)]
    cfg = near_dedup.NearDedup()
    weights = near_dedup.shingle_weights(spark.createDataFrame([(t,) for t in texts], "text string"), cfg)
    brute = brute_weights(texts)
    s, w = near_dedup.weighted_set(texts[7].encode(), weights, cfg)
    assert np.allclose(sorted(w), sorted(brute[7].values())) and w.min() < 1.01 and abs(w.max() - 1.1) < 1e-9
    assert set(weights.document_counts(s).tolist()) == {0, 300}


def test_components_of_any_shape(spark):
    rng = np.random.default_rng(8)
    path = rng.permutation(600).tolist()
    links = list(zip(path, path[1:])) + [(1000 + i, 2000) for i in range(50)] + [(3000, 3001), (3001, 3000)] + [(int(a), int(b)) for a, b in 4000 + rng.integers(0, 80, (60, 2)) if a != b]
    got = {r.id: r.label for r in near_dedup.components(spark.createDataFrame(links, "a long, b long")).collect()}
    ids = sorted({x for p in links for x in p})
    at = {x: i for i, x in enumerate(ids)}
    want = brute_classes(len(ids), [(at[a], at[b]) for a, b in links])
    assert got == {x: ids[want[at[x]]] for x in ids}


def test_near_duplicates_edges(odd, empty):
    got = [(r.doc_id, r.class_id, r.is_kept) for r in near_dedup.near_duplicate_classes(odd).collect()]
    ids = dict((g[0], g[1]) for g in got)
    assert len(got) == len(ODD) + 2 and ids[6] == 5 and ids[0] == 0 and ids[1] == 1 and ids[2] == 2
    assert near_dedup.near_duplicate_classes(empty).count() == 0
    kept = near_dedup.keep_one_of_each(odd.filter("doc_id is not null").dropDuplicates(["doc_id"]))
    assert kept.columns == odd.columns and kept.count() == len(ODD) - 1


def test_near_duplicates_with_null_and_repeated_ids(spark):
    """One row of each class stays, whatever its id; texts under one id are compared each for itself."""
    words = [f"w{i}" for i in range(100)]
    near = " ".join(["new", *words[1:]])
    far = " ".join(f"v{i}" for i in range(100))
    rows = [(None, "only here", 0), (None, " ".join(words), 1), (7, near, 2), (7, far, 3), (9, far + " end", 4), (5, "same row", 5), (5, "same row", 6),
            (None, "no id twice", 7), (None, "no id twice", 8), (None, None, 9), (5, None, 10)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n int")
    kept = near_dedup.keep_one_of_each(df)
    assert kept.columns == df.columns
    n = sorted(r.n for r in kept.collect())
    assert [x for x in n if x not in (5, 6, 7, 8)] == [0, 2, 3, 9, 10] and len({5, 6} & set(n)) == 1 and len({7, 8} & set(n)) == 1
    got = near_dedup.near_duplicate_classes(df).collect()
    assert len(got) == len(rows) and sum(r.is_kept for r in got) == 7 and all(r.is_kept is not None for r in got)


def test_weighted_samples_agree_as_often_as_sets_are_alike():
    rng = np.random.default_rng(0)
    u = rng.integers(0, 1 << 63, 300).astype(np.uint64)
    wa, wb = rng.random(300) * 4 + 0.1, rng.random(300) * 4 + 0.1
    wb[:200] = wa[:200]
    s = [near_dedup.weighted_samples(u, np.log(w).astype(np.float32), np.array([0, 300]), 3000)[0] for w in (wa, wb)]
    want = np.minimum(wa, wb).sum() / np.maximum(wa, wb).sum()
    assert abs((s[0] == s[1]).mean() - want) < 0.03


# ------------------------------------------------------------------------- 10 packing


def check_packed(df, spark):
    packed = packing.pack_documents(df, with_ids=True).toPandas()
    tok = load_tokenizer(vocabulary_path("word_bpe_49k.json"))
    want = Counter()
    for r in df.select("doc_id", "text").collect():
        ids = np.array([*tok.encode(r.text or "", add_special_tokens=False).ids, 0], "<u4")
        for k, a in enumerate(range(0, len(ids), 2048)):
            own = ids[a : a + 2048]
            want[(r.doc_id, k, a, len(own), zlib.crc32(own.tobytes()))] += 1
    ids_or_none = [None if x != x or x is None else int(x) for x in packed.doc_id]
    assert Counter(zip(ids_or_none, packed.piece, packed.start, packed.length, packed.ids_crc32, strict=True)) == want
    g = packed.sort_values(["sequence_id", "offset"])
    assert ((g.groupby("sequence_id").length.cumsum() - g.length) == g.offset).all() and g.groupby("sequence_id").length.sum().max() <= 2048
    return packed


def test_packing_is_exact_and_tight(docs, odd, empty, spark):
    packed = check_packed(docs, spark)
    assert packed.sequence_id.nunique() <= -(-packed.length.sum() // 2048) * 1.02 + 1
    check_packed(odd, spark)
    assert packing.pack_documents(empty).count() == 0


def test_sweep_against_sequential_best_fit():
    rng = np.random.default_rng(5)
    for top in (2048, 900, 60):
        sizes = rng.integers(1, top + 1, 500)
        held = packing.Gaps(2048)
        packing.sweep([(length, 0, n) for length, n in Counter(sizes.tolist()).items()], held)
        gaps = []
        for s in sorted(sizes, reverse=True):  # plain best-fit decreasing
            fit = [g for g in range(len(gaps)) if gaps[g] >= s]
            if fit:
                gaps[min(fit, key=lambda g: gaps[g])] -= s
            else:
                gaps.append(2048 - s)
        assert held.opened <= len(gaps) + 1


def test_distributed_sweeps_place_every_piece_once_and_tightly(spark):
    """Many tasks and rounds: no overlap, no place beyond the size, and hardly more sequences than one task needs."""
    rng = np.random.default_rng(6)
    counts = Counter(np.minimum(2048, rng.lognormal(5.5, 1.1, 6000).astype(int) + 1).tolist())
    used = {}
    for slices in (1, 7):
        cfg = packing.Packing(slices=slices, slice_sequences=1)
        plan = packing.match(spark, counts, cfg)
        filled, n = defaultdict(list), Counter()
        for i, (length, rank, first, offset) in enumerate(plan.tolist()):
            last = plan[i + 1][1] if i + 1 < len(plan) and plan[i + 1][0] == length else counts[length]
            assert rank == n[length]
            n[length] += last - rank
            for r in range(last - rank):
                filled[first + r].append((offset, length))
        assert n == counts
        for places in filled.values():
            places.sort()
            assert [o for o, _ in places] == [sum(x for _, x in places[:i]) for i in range(len(places))] and sum(x for _, x in places) <= 2048
        used[slices] = len(filled)
    least = -(-sum(length * k for length, k in counts.items()) // 2048)
    assert used[1] <= least * 1.01 + 1 and used[7] <= used[1] + 4 * 7
    assert packing.bands(2048)[0][1] == 2048 and packing.bands(2048)[-1][0] == 0 and all(a[0] == b[1] for a, b in zip(packing.bands(2048), packing.bands(2048)[1:]))


# -------------------------------------------------------------------- 5 and 1: tokens


def test_forced_boundary_bpe_equals_the_library(odd, docs, empty, spark):
    tok = load_tokenizer(vocabulary_path("byte_bpe_50k.json"))
    for df in (odd, docs):
        got = Counter((r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in byte_bpe.round_trip(df).collect())
        want = Counter()
        for r in df.select("doc_id", "text").collect():
            ids = tok.encode(r.text or "", add_special_tokens=False).ids
            back = tok.decode(ids, skip_special_tokens=False)
            want[(r.doc_id, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(back.encode()).hexdigest())] += 1
        assert got == want
    assert byte_bpe.round_trip(empty).count() == 0
    back = byte_bpe.decode_ids(byte_bpe.encode_documents(docs)).join(docs.select("doc_id", F.col("text").alias("was")), "doc_id")
    assert back.filter("text <> was").isEmpty()


def test_certain_cuts_hold_in_no_token():
    bpe = byte_bpe.byte_bpe(vocabulary_path("byte_bpe_50k.json"))
    assert bpe.certain[ord("e"), ord(" ")] and not bpe.certain[ord(" "), ord("e")]
    assert not any(bpe.certain[t[i], t[i + 1]] for t in bpe.tokens for i in range(len(t) - 1))


def test_fragments_are_encoded_each_on_its_own():
    """Cuts fall at certain pairs, inside words too; a long text without a space is many fragments."""
    path = vocabulary_path("byte_bpe_50k.json")
    bpe, tok = byte_bpe.ByteBPE(path), load_tokenizer(path)
    rng = np.random.default_rng(6)
    text = "".join(rng.choice(list("abcdefghijklmnopqrstuvwxyzQZXJ0123456789.,;:!?()[]{}#$%&*+-/=_~éüß中日本語"), 1_000_000))
    parts = bpe.fragments(text.encode())
    assert b"".join(parts) == text.encode() and len(parts) > 50_000 and max(map(len, parts)) < 1000
    assert all(bpe.certain[a[-1], b[0]] for a, b in zip(parts, parts[1:]))
    alone = [i for p in parts[:3000] for i in tok.encode(p.decode(), add_special_tokens=False).ids]
    assert alone == tok.encode(b"".join(parts[:3000]).decode(), add_special_tokens=False).ids
    assert next(bpe.encode_all([text.encode()])).tolist() == tok.encode(text, add_special_tokens=False).ids


def test_both_encoders_on_random_unicode():
    rng = np.random.default_rng(9)
    alphabet = list("relv|< \t\n\r\x0b\x0c\x1c\x1f\x85\xa0   　ab'sdZ17٣é́ß中😀.,!#​﻿Σİ") + ["'ll", "<|endoftext|>", "<|startoftext|>"]
    texts = ["".join(rng.choice(alphabet, rng.integers(0, 40))) for _ in range(6000)]
    for enc, name, wrap in ((WordEncoder(vocabulary_path("word_bpe_49k.json"), 500), "word_bpe_49k.json", list),
                            (byte_bpe.ByteBPE(vocabulary_path("byte_bpe_50k.json"), 500), "byte_bpe_50k.json", lambda x: [t.encode() for t in x])):
        want = load_tokenizer(vocabulary_path(name)).encode_batch(texts, add_special_tokens=False)
        assert all(a.tolist() == b.ids for a, b in zip(enc.encode_all(wrap(texts)), want, strict=True))


def brute_attribution(text, spans, rule):
    tok = load_tokenizer(vocabulary_path("byte_bpe_50k.json"))
    raw = text.encode()
    pos, out = 0, [0.0] * len(spans)
    at = [len(text[:i].encode()) for i in range(len(text) + 1)]
    bytes_of = byte_bpe.byte_bpe(vocabulary_path("byte_bpe_50k.json")).bytes_of
    for i in tok.encode(text, add_special_tokens=False).ids:
        own = range(pos, pos + len(bytes_of[i]))
        pos += len(bytes_of[i])
        shared = [sum(at[a] <= b < at[z] for b in own) for a, z in spans]
        if rule == "split":
            for k, n in enumerate(shared):
                out[k] += n / len(own)
        elif rule == "majority":
            if spans and max(shared) and max(shared) >= len(own) - sum(shared):
                out[shared.index(max(shared))] += 1
        else:
            b = own[0] if rule == "first" else own[-1]
            for k, (a, z) in enumerate(spans):
                out[k] += at[a] <= b < at[z]
    assert pos == len(raw)
    return out


@pytest.mark.parametrize("rule", token_counts.RULES)
def test_token_attribution_equals_brute_force(spark, rule):
    texts = [("one two\n\n\nthree  éé中中 four", [(0, 3), (3, 5), (6, 11), (11, 12), (13, 22)]), ("abcdefgh indivisible", [(0, 2), (2, 2), (2, 14), (14, 20)]), ("", []), (None, None), ("no spans", [])]
    df = spark.createDataFrame([(i, t, s) for i, (t, s) in enumerate(texts)], "doc_id long, text string, spans array<struct<start: int, end: int>>")
    got = defaultdict(dict)
    for r in token_counts.attribute_tokens(df, spans_col="spans", rule=rule).collect():
        got[r.doc_id][r.section] = r.n_tokens
    for i, (t, s) in enumerate(texts):
        want = brute_attribution(t or "", s or [], rule)
        assert np.allclose([got[i][k] for k in range(len(want))], want)


@pytest.mark.parametrize("rule", token_counts.RULES)
def test_token_attribution_of_any_spans(spark, rule):
    """Unsorted, overlapping, nested, repeated, reversed and null-bounded spans, each counted as if it were alone with its row."""
    text = "one two three éé four five six seven eight nine ten indivisible"
    spans = [(30, 40), (0, 13), (4, 13), (4, 13), (12, 30), (60, 20), (None, 9), (7, None), (None, None), (50, 400)]
    kind = "doc_id long, text string, spans array<struct<start: int, end: int>>"
    got = {r.section: (r.n_tokens, r.start, r.end) for r in token_counts.attribute_tokens(spark.createDataFrame([(1, text, spans)], kind), spans_col="spans", rule=rule).collect()}
    assert len(got) == len(spans)
    for k, (a, b) in enumerate(spans):
        empty = a is None or b is None or b < a
        alone = [(a or 0, a or 0)] if empty else [(a, min(b, len(text)))]
        if not empty and rule in ("first", "last", "split"):  # the majority rule weighs what other spans of the row hold
            assert abs(got[k][0] - brute_attribution(text, alone, rule)[0]) < 1e-9
        assert not empty or got[k][0] == 0
        assert got[k][1:] == alone[0]


def test_token_counts_by_line_sum_to_all(odd, docs, empty):
    for df in (odd, docs):
        total = token_counts.attribute_tokens(df).agg(F.sum("n_tokens")).first()[0]
        assert total == byte_bpe.round_trip(df).agg(F.sum("n_tokens")).first()[0]
    assert token_counts.attribute_tokens(empty).count() == 0


# --------------------------------------------------------------------- 8 token files


def test_token_files_round_trip(docs, odd, empty, spark):
    tok = load_tokenizer(vocabulary_path("word_bpe_49k.json"))
    for df in (docs, odd):
        got = sorted(map(tuple, wavelet.round_trip(df, cfg=wavelet.TokenFiles(shard_tokens=3000)).collect()), key=lambda r: r[1])
        listed = df.select("doc_id", "text", F.xxhash64("text").alias("h")).collect()
        start, rows = 0, sorted(((r.doc_id is not None, r.doc_id or 0, r.h, r.text or "", r.doc_id) for r in listed))
        for (_, _, _, text, doc), r in zip(rows, got, strict=True):
            ids = np.array([*tok.encode(text, add_special_tokens=False).ids, 2], "<u4")
            assert r == (doc, start, len(ids), zlib.crc32(ids.tobytes()))
            start += len(ids)
    assert wavelet.round_trip(empty).count() == 0


def test_wavelet_matrix_queries():
    rng = np.random.default_rng(1)
    for n in (1, 511, 512, 5000):
        a = rng.integers(0, 700, n).astype(np.uint16)
        m, docs, lengths = wavelet.WaveletMatrix.from_bytes(wavelet.WaveletMatrix.build(a).to_bytes([None], np.array([n])))
        assert (m.tokens() == a).all() and (m.access(np.arange(n)) == a).all() and docs.to_pylist() == [None] and lengths[0] == n
        for t in {int(a[0]), 3, 65535}:
            at = np.flatnonzero(a == t)
            assert m.count(t) == len(at) and (m.occurrences(t) == at).all() and m.rank(t, n // 2) == (at < n // 2).sum()
            if len(at):
                assert m.select(t, len(at) - 1) == at[-1]


def test_token_counts_from_files(docs, spark):
    path = new_path(spark, "test-files")
    wavelet.write_token_files(docs, path)
    ids = [i for r in wavelet.read_token_files(spark, path, with_ids=True).collect() for i in np.frombuffer(r.ids, "<u4").tolist()]
    got = {r.token: r.n for r in wavelet.token_counts(spark, path, [2, 320, 49000]).groupBy("token").agg(F.sum("n").alias("n")).collect()}
    want = Counter(ids)
    assert got == {t: want[t] for t in (2, 320, 49000)}


# ------------------------------------------------------------------------ 2 MaxScore


def brute_topk(rows, every, k):
    ok = [(i, [int(np.floor(256 * float(x))) for x in v]) for i, v in rows if v and all(x is not None and np.isfinite(x) for x in v)]
    out = []
    for q, a in ok:
        if q % every == 0:
            hits = sorted((-sum(x * y for x, y in zip(a, b, strict=False)), i) for i, b in ok if i != q)[:k]
            out += [(q, n + 1, i, -s) for n, (s, i) in enumerate(hits)]
    return sorted(out)


@pytest.mark.parametrize("cfg", [maxscore.MaxScore(), maxscore.MaxScore(shard_rows=40, query_rows=3, block_rows=7)])
def test_maxscore_equals_brute_force(spark, cfg):
    rng = np.random.default_rng(2)
    rows = [(int(i), rng.normal(size=6).tolist()) for i in range(150)]
    rows += [(200, None), (250, []), (251, [1.0, None]), (252, [float("nan")]), (253, [float("inf")]), (300, rows[3][1]), (301, rows[3][1]), (302, [0.0] * 6), (350, [0.5])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("score", F.lit(1))
    got = sorted(map(tuple, maxscore.neighbours(df, cfg=cfg).collect()))
    assert got == brute_topk(rows, 50, 5)


def test_maxscore_on_sparse_positive_vectors(spark):
    rng = np.random.default_rng(4)
    rows = [(i, (rng.random(30) * (rng.random(30) < 0.15)).tolist()) for i in range(400)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = sorted(map(tuple, maxscore.neighbours(df, cfg=maxscore.MaxScore(block_rows=50)).collect()))
    assert got == brute_topk(rows, 50, 5)


def test_maxscore_walks_the_postings_of_essential_terms_only():
    """Sparse vectors: a high threshold leaves most postings unvisited, and no result is lost."""
    rng = np.random.default_rng(7)
    w = (rng.integers(1, 50, (500, 40)) * (rng.random((500, 40)) < 0.1)).astype(float)
    w[:, 0] = rng.integers(100, 200, 500) * (rng.random(500) < 0.03)  # one rare term with large weights
    queries = np.zeros((3, 40))
    queries[:, [0, 1, 2]] = [[10, 1, 1], [10, 2, 0], [10, 0, 3]]
    scores = queries @ w.T
    block = maxscore.Block(np.arange(500), w)
    q, d, s = block.search(queries, np.full(3, 1000.0))
    assert set(zip(q.tolist(), d.tolist(), s.tolist())) == {(i, j, scores[i, j]) for i in range(3) for j in range(500) if scores[i, j] >= 1000}
    assert block.visited == 3 * (w[:, 0] > 0).sum()  # the two other terms are non-essential: none of their postings is walked
    everything = maxscore.Block(np.arange(500), w)
    everything.search(queries, np.full(3, -1.0))
    assert everything.visited == sum((queries[:, i] > 0).sum() * (w[:, i] > 0).sum() for i in range(3))


def test_maxscore_with_few_rows(spark):
    df = spark.createDataFrame([(0, [1.0]), (1, [2.0])], "vec_id long, embedding array<float>")
    assert [tuple(r) for r in maxscore.neighbours(df).collect()] == [(0, 1, 1, 131072)]
    assert maxscore.neighbours(df.limit(0)).count() == 0


# ---------------------------------------------------------------------------- 9 HTML

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style></head><body class="has-sidebar">
<header><h1>Site name</h1></header><nav><ul><li><a href=/>Home</a><li><a href=/x>News</a></ul></nav>
<div class="cookie-notice">We use cookies to make this site work for you and for us, and this is a long sentence of the notice.</div>
<article><header><h1>The &amp; title</h1></header><p>First paragraph of the&nbsp;story,
  with <b>bold</b> words<br>and a break.<p>Short one.
<div class="share"><a href=#>Share</a></div>
<p>A paragraph with <a href="/a">one link</a> among many other words that are plain text of the article itself.</p>
<form><label>Mail</label><input></form>
<section id="comments"><p>I think that this is the best article of the year and of all the years before it.</p></section></article>
<aside><p>Related: that other story of the week that you have to read now.</p></aside>
<script>var t="<p>not text</p>";</script><footer><p>Copyright of the site and of all the people in it</p></footer></body></html>"""


def test_html_keeps_the_article_alone():
    want = ["The & title", "First paragraph of the story, with bold words and a break.", "Short one.",
            "A paragraph with one link among many other words that are plain text of the article itself."]
    assert html_text.main_text(PAGE) == "\n".join(want)


def test_html_without_article_uses_stop_words_and_neighbours():
    long_ = "This is the first of the long paragraphs of the story that we want to keep, and it is written with the words of the language in it."
    page = f"<body><div><a href=1>One</a> <a href=2>Two</a></div><h2>Heading</h2><p>{long_}</p><p>Short.</p><p>{long_}</p><ul><li><a href=3>More</a></li></ul><p>Tail</p></body>"
    assert html_text.main_text(page) == "\n".join(["Heading", long_, "Short.", long_])


STORY = "This is one of the long paragraphs of the story that we want to keep, and it is written with the words of the language in it."


@pytest.mark.parametrize("name", ["share-price", "article legal", "legal", "has-sidebar", "comment-piece", "story share", "legalAnalysis", "no-comments", "search-for-truth"])
def test_html_names_alone_do_not_drop_article_text(name):
    for page in (f'<article><div class="{name}"><p>{STORY}</p></div></article>', f'<body><div id="{name}"><p>{STORY}</p></div><div><p>{STORY}</p></div></body>'):
        assert html_text.main_text(page) == "\n".join([STORY] * page.count(STORY))


@pytest.mark.parametrize("name", ["comments", "comment-list", "ad", "ad-slot-2", "cookieNotice", "newsletter-signup", "related-posts", "sidebar", "main-nav", "post-comments"])
def test_html_names_that_say_so_are_left_out(name):
    page = f'<article><p>{STORY}</p><div class="{name}"><p>{STORY} {STORY}</p></div></article>'
    assert html_text.main_text(page) == STORY


def test_html_short_text_under_a_doubtful_name_is_left_out():
    assert html_text.main_text(f'<article><p>{STORY}</p><div class="share">Share this with all your friends</div><p>Tail.</p></article>') == f"{STORY}\nTail."


@pytest.mark.parametrize("piece", ['<a x="', "<a x='>", '<p class="a', "<a ", "<div><b", "</section><div>", "<script>", "<!--", '<a x="> <b y=\'>', "<title>"])
def test_html_scanner_is_linear(piece):
    """Broken markup, repeated: four times the page takes far less than sixteen times as long."""
    import time

    def seconds(n):
        began = time.perf_counter()
        html_text.main_text(piece * n + "<p>" + STORY)
        return time.perf_counter() - began

    seconds(200)
    assert seconds(60_000) < max(0.5, 9 * seconds(15_000))


def test_html_edges(spark, sf_dir):
    rows = [(1, "u", None), (2, None, ""), (3, "u", "plain < text"), (4, "u", "<article><p>a &lt;b&gt; &#233;"), (4, "u", "<article><p>a &lt;b&gt; &#233;"), (5, "u", "<p class='x>" + "a" * 50), (6, "u", "<article>" + "word " * 50000)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", F.lit("clash"))
    got = [(r.page_id, r.text, r.n_chars) for r in html_text.extract_pages(df).collect()]
    assert len(got) == 7 and (1, "", 0) in got and (2, "", 0) in got and got.count((4, "a <b> é", 7)) == 2 and got[-1][2] == 249999
    assert html_text.extract_pages(df.limit(0)).count() == 0


def test_html_on_the_pages_equals_their_articles(spark, sf_dir):
    from html import unescape

    pages = table(spark, sf_dir, "pages")
    got = {r.page_id: r.text for r in html_text.extract_pages(pages).collect()}
    for r in pages.collect():
        body = re.search(r"<article>(.*?)</article>", r.html, re.S)[1]
        parts = [" ".join(unescape(re.sub(r"<[^>]*>", " ", b)).split()) for b in re.split(r"</?(?:p|h1)>", body)]
        assert got[r.page_id] == "\n".join(p for p in parts if p)


# ---------------------------------------------------------------------------- 6 chat


def test_quotation_linking(spark):
    rows = [
        (1, 0, "user", "hello there\nhow are you"), (1, 1, "assistant", "fine, thanks\n\nand you?"),
        (1, 2, "user", "> fine,  Thanks\nGood to hear"), (1, 3, "assistant", "On Monday x wrote:\n> Good to hear\n>> fine, thanks\nindeed"),
        (1, 4, "user", "> nobody said this\nwhat"), (1, 5, "user", "> hello there\nlate reply"), (1, 6, None, ">> fine, thanks"),
        (2, 0, None, None), (2, 1, "user", ""), (None, 1, "user", "x"), (2, 0, "user", "> x\ny"), (3, None, "user", "> x"),
    ]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("hash", F.lit(0))
    got = {(r.conv_id, r.turn, r.role): (r.content, r.parent_turn, r.thread_turn, r.depth) for r in chat.format_conversations(df).collect()}
    assert got[1, 0, "user"] == ("hello there\nhow are you", None, 0, 0)
    assert got[1, 2, "user"] == ("Good to hear", 1, 1, 1) and got[1, 3, "assistant"] == ("indeed", 2, 1, 2)
    assert got[1, 4, "user"] == ("what", None, 4, 0) and got[1, 5, "user"] == ("late reply", 0, 0, 1)
    assert got[1, 6, None] == ("", 1, 1, 1) and got[2, 0, "user"] == ("y", None, 0, 0) and len(got) == len(rows)
    assert chat.format_conversations(df.limit(0)).count() == 0


def brute_links(rows):
    """The turn that each message answers: its outermost linked passage's earliest source, the latest one of several."""
    out = {}
    for conv in {r[0] for r in rows}:
        own = sorted(r for r in rows if r[0] == conv)
        said = {}
        for _, turn, _, text in own:
            body, _ = chat.parse(text)
            for unit in {body, *re.split(r"\n\s*\n", body), *body.split("\n")}:
                if key := " ".join(unit.casefold().split()):
                    said[key] = min(said.get(key, turn), turn)
        for _, turn, _, text in own:
            found = []
            for level, passage in chat.parse(text)[1]:
                for units in ([passage], passage.split("\n")):
                    sources = [said[k] for u in units if (k := " ".join(u.casefold().split())) in said and said[k] < turn]
                    if sources:
                        found.append((level, -max(sources)))
                        break
            out[conv, turn] = -min(found)[1] if found else None
    return out


def test_quotations_of_random_conversations_equal_brute_force(spark):
    rng = np.random.default_rng(12)
    rows = []
    for conv in range(25):
        texts: list[str] = []
        for turn in range(12):
            lines = []
            for _ in range(rng.integers(0, 3)):
                if texts and rng.random() < 0.8:  # quote some lines of an earlier message, quotations in it included
                    earlier = texts[rng.integers(len(texts))].split("\n")
                    a = rng.integers(len(earlier))
                    lines += ["> " + x.upper() if rng.random() < 0.2 else ">" + x for x in earlier[a : a + rng.integers(1, 4)]]
                lines += [" ".join(rng.choice(["yes", "no", "well", "the", "plan", f"t{turn}"], rng.integers(1, 5))) for _ in range(rng.integers(0, 3))]
            texts.append("\n".join(lines))
            rows.append((conv, turn, "user", texts[-1]))
    got = {(r.conv_id, r.turn): (r.parent_turn, r.thread_turn, r.depth) for r in chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    parents = brute_links(rows)
    assert sum(p is not None for p in parents.values()) > 50
    for (conv, turn), parent in parents.items():
        head, depth = turn, 0
        while parents[conv, head] is not None:
            head, depth = parents[conv, head], depth + 1
        assert got[conv, turn] == (parent, head, depth)


def test_long_reply_chain(spark):
    rows = [(1, i, "user", (f"> message {i - 1} text\n" if i else "") + f"message {i} text") for i in range(40)]
    got = {r.turn: (r.parent_turn, r.thread_turn, r.depth) for r in chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    assert all(got[i] == (i - 1 if i else None, 0, i) for i in range(40))


def test_conversations_without_quotes_keep_their_order(spark, sf_dir):
    df = table(spark, sf_dir, "conversations")
    got = chat.format_conversations(df)
    assert got.count() == df.count() and got.filter("thread_turn <> turn or depth > 0").isEmpty()
