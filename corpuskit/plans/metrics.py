"""Accuracy measures: n-gram overlap, longest common subsequences, soft matching, F1, retrieval, intervals."""

from __future__ import annotations

import re
from collections import Counter

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpuskit.functions.tokens import WORDS, ngrams, round6


def words(c: Column) -> Column:
    return F.regexp_extract_all(F.lower(c), F.lit(WORDS), F.lit(0))


def prf(matches: Column, n_candidate: Column, n_reference: Column) -> dict[str, Column]:
    p = F.coalesce(F.try_divide(matches, n_candidate), F.lit(0.0))
    r = F.coalesce(F.try_divide(matches, n_reference), F.lit(0.0))
    return {"p": round6(p), "r": round6(r), "f1": round6(F.coalesce(F.try_divide(2 * p * r, p + r), F.lit(0.0)))}


def clipped(a: list, b: list) -> int:
    """Size of the multiset intersection of two lists."""
    return sum((Counter(a) & Counter(b)).values())


def ngram_overlap(df: DataFrame, candidate: str, reference: str, n: int = 1) -> DataFrame:
    """Clipped n-gram matches over the n-grams of the candidate (p) and of the reference (r).

    Counting is linear in the texts, in Arrow batches; nested array functions would compare
    every gram with every other.
    """

    @F.pandas_udf("int")
    def matches(c: pd.Series, r: pd.Series) -> pd.Series:
        return pd.Series([clipped(list(x), list(y)) if x is not None and y is not None else 0 for x, y in zip(c, r, strict=True)])

    grams = df.withColumns({"_c": ngrams(words(F.col(candidate)), n), "_r": ngrams(words(F.col(reference)), n)}).withColumn("_n", matches("_c", "_r"))
    return grams.withColumns(prf(F.col("_n"), F.size("_c"), F.size("_r"))).drop("_c", "_r", "_n")


def lcs_length(a: list[str], b: list[str]) -> int:
    """Longest common subsequence by bit vectors: one whole-number step for each word of ``b``."""
    masks: dict[str, int] = {}
    for i, w in enumerate(a):
        masks[w] = masks.get(w, 0) | 1 << i
    full = (1 << len(a)) - 1
    v = full
    for w in b:
        u = v & masks.get(w, 0)
        v = (v + u | v - u) & full
    return len(a) - v.bit_count()


def lcs_overlap(df: DataFrame, candidate: str, reference: str) -> DataFrame:
    """Longest common subsequence over the words of each side, in Arrow batches."""

    @F.pandas_udf("int")
    def length(c: pd.Series, r: pd.Series) -> pd.Series:
        return pd.Series([lcs_length(list(x), list(y)) if x is not None and y is not None else 0 for x, y in zip(c, r, strict=True)])

    both = df.withColumns({"_c": words(F.col(candidate)), "_r": words(F.col(reference))}).withColumn("_n", length("_c", "_r"))
    return both.withColumns(prf(F.col("_n"), F.size("_c"), F.size("_r"))).drop("_c", "_r", "_n")


def _sequence_hits(ref: list[str], cand: list[str]) -> set[int]:
    """Places of ``ref`` on one longest common subsequence with ``cand``.

    The table is kept as one bit vector for each word of ``cand``: the length for the first
    ``i`` words of ``ref`` is the number of zeros among the low ``i`` bits.
    """
    masks: dict[str, int] = {}
    for i, w in enumerate(ref):
        masks[w] = masks.get(w, 0) | 1 << i
    full = (1 << len(ref)) - 1
    rows = [full]
    for w in cand:
        v = rows[-1]
        u = v & masks.get(w, 0)
        rows.append((v + u | v - u) & full)
    length = lambda i, j: i - (rows[j] & ((1 << i) - 1)).bit_count()
    hits, i, j = set(), len(ref), len(cand)
    while i and j:
        if ref[i - 1] == cand[j - 1]:
            hits.add(i - 1)
            i, j = i - 1, j - 1
        elif length(i - 1, j) >= length(i, j - 1):
            i -= 1
        else:
            j -= 1
    return hits


def summary_lcs(candidate: list[list[str]], reference: list[list[str]]) -> tuple[float, float, float]:
    """Union over candidate sentences of the matched places of each reference sentence; counts are clipped."""
    left_c, left_r, hit = Counter(w for s in candidate for w in s), Counter(w for s in reference for w in s), 0
    for r in reference:
        union = set().union(*(_sequence_hits(r, c) for c in candidate)) if candidate else set()
        for i in sorted(union):
            if left_c[r[i]] > 0 and left_r[r[i]] > 0:
                left_c[r[i]] -= 1
                left_r[r[i]] -= 1
                hit += 1
    n_c, n_r = sum(map(len, candidate)), sum(map(len, reference))
    p, q = hit / n_c if n_c else 0.0, hit / n_r if n_r else 0.0
    return p, q, 2 * p * q / (p + q) if p + q else 0.0


def lcs_summary(df: DataFrame, candidate: str, reference: str) -> DataFrame:
    """Summary-level variant over sentences, in Arrow batches."""
    def split(t: str | None) -> list[list[str]]:
        return [w for s in re.findall(r"[^.!?\n]+[.!?]*", t or "") if (w := re.findall(r"[^\W_]+", s.lower()))]

    @F.pandas_udf("p double, r double, f1 double")
    def score(c: pd.Series, r: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([summary_lcs(split(a), split(b)) for a, b in zip(c, r, strict=True)], columns=["p", "r", "f1"])

    return df.withColumn("_s", score(candidate, reference)).select("*", "_s.*").drop("_s")


def soft_match(pairs: DataFrame, vectors: DataFrame, key: str = "id") -> DataFrame:
    """Greedy soft matching of ``candidate`` and ``reference`` word arrays, with a vector for each word.

    ``vectors``: ``word, v`` (unit). Each word takes its most similar counterpart; the means
    give precision, recall and their harmonic mean. Words are exploded by pair, so the work
    of a pair is spread and its key is the grouping key.
    """
    from corpuskit.sources.adapters import dot

    def side(column: str, name: str) -> DataFrame:
        # equal words have equal vectors, so a side is its distinct words with their counts
        counted = pairs.select(key, F.explode(column).alias("word")).groupBy(key, "word").agg(F.count("*").alias(f"n{name}"))
        return counted.join(vectors, "word").select(key, F.col("word").alias(name), f"n{name}", F.col("v").alias(f"v{name}"))

    met = side("candidate", "a").join(side("reference", "b"), key).select(key, "a", "b", "na", "nb", dot("va", "vb").alias("s"))
    mean = lambda w: met.groupBy(key, w, f"n{w}").agg(F.max("s").alias("s")).groupBy(key).agg((F.sum(F.col("s") * F.col(f"n{w}")) / F.sum(f"n{w}")).alias(w))
    out = mean("a").withColumnRenamed("a", "p").join(mean("b").withColumnRenamed("b", "r"), key)
    return out.select(key, round6(F.col("p")).alias("p"), round6(F.col("r")).alias("r"), round6(F.try_divide(2 * F.col("p") * F.col("r"), F.col("p") + F.col("r"))).alias("f1"))


def f1(scores: DataFrame, tau: float = 0.5) -> DataFrame:
    """Per-label, micro, macro and weighted F1 from ``label, truth (0/1), score`` rows."""
    hit, true = F.col("score") >= tau, F.col("truth") == 1
    g = scores.groupBy("label").agg(F.count_if(hit & true).alias("tp"), F.count_if(hit & ~true).alias("fp"), F.count_if(~hit & true).alias("fn"))
    one = F.coalesce(F.try_divide(2.0 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")), F.lit(0.0))
    by = g.withColumn("f1", one)
    total = by.agg(
        F.coalesce(F.try_divide(2.0 * F.sum("tp"), 2 * F.sum("tp") + F.sum("fp") + F.sum("fn")), F.lit(0.0)).alias("micro"), F.avg("f1").alias("macro"),
        F.coalesce(F.try_divide(F.sum(F.col("f1") * (F.col("tp") + F.col("fn"))), F.sum(F.col("tp") + F.col("fn"))), F.lit(0.0)).alias("weighted"),
    )
    named = total.select(F.explode(F.map_from_arrays(F.array(*map(F.lit, ("micro", "macro", "weighted"))), F.array("micro", "macro", "weighted"))).alias("name", "f1"))
    return by.select(F.concat(F.lit("label "), F.col("label").cast("string")).alias("name"), "f1").unionByName(named).select("name", round6(F.col("f1")).alias("f1"))


def f1_sweep(scores: DataFrame, grid: tuple[float, ...] = (0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9)) -> DataFrame:
    """Micro F1 over a grid of thresholds, in one pass."""
    aggs = []
    for t in grid:
        hit, true = F.col("score") >= t, F.col("truth") == 1
        tp, fp, fn = F.count_if(hit & true), F.count_if(hit & ~true), F.count_if(~hit & true)
        aggs.append(F.struct(F.lit(t).cast("double").alias("tau"), round6(F.coalesce(F.try_divide(2.0 * tp, 2 * tp + fp + fn), F.lit(0.0))).alias("micro")))
    return scores.agg(F.array(*aggs).alias("a")).select(F.explode("a").alias("x")).select("x.*")


def binned_ci(df: DataFrame, x: str, ys: list[str], width: int) -> DataFrame:
    """Means with 95 % intervals by bins of ``x``."""
    g = df.groupBy((F.floor(F.col(x) / width) * width).cast("long").alias("bin"))
    aggs = [F.count("*").alias("n")]
    for y in ys:
        aggs += [round6(F.avg(y)).alias(f"{y}_mean"), round6(F.coalesce(1.96 * F.stddev_samp(y) / F.sqrt(F.count(y)), F.lit(0.0))).alias(f"{y}_ci")]
    return g.agg(*aggs)


def share_over(df: DataFrame, n: str, limit: int = 1024) -> DataFrame:
    """One row: rows, those over a limit of tokens, and their share."""
    over = F.count_if(F.col(n) > limit)
    return df.agg(F.count("*").alias("n"), over.alias("over"), round6(F.coalesce(F.try_divide(over, F.count("*")), F.lit(0.0))).alias("share"))


def retrieval(run: DataFrame, gold: DataFrame, k: int) -> DataFrame:
    """Recall@k, mean reciprocal rank and nDCG@k; ``run``: query_id, id, rank; ``gold``: query_id, id."""
    rel = gold.groupBy("query_id").agg(F.count("*").alias("n_rel"))
    hits = run.filter(F.col("rank") <= k).join(gold, ["query_id", "id"], "left_semi")
    g = hits.groupBy("query_id").agg(F.count("*").alias("hits"), F.min("rank").alias("first"), F.sum(1 / F.log2(F.col("rank") + 1.0)).alias("dcg"))
    ideal = F.aggregate(F.sequence(F.lit(1), F.least(F.col("n_rel"), F.lit(k)).cast("int")), F.lit(0.0), lambda s, i: s + 1 / F.log2(i + 1.0))
    z = lambda c: F.coalesce(c, F.lit(0.0))
    each = rel.join(g, "query_id", "left").select(z(F.col("hits") / F.col("n_rel")).alias("recall"), z(1 / F.col("first")).alias("rr"), z(F.col("dcg") / ideal).alias("ndcg"))
    return each.agg(F.count("*").alias("queries"), round6(F.avg("recall")).alias("recall"), round6(F.avg("rr")).alias("mrr"), round6(F.avg("ndcg")).alias("ndcg"))


def ann_recall(approximate: DataFrame, exact: DataFrame) -> DataFrame:
    """Share of the exact neighbours that the approximate search finds."""
    found = exact.join(approximate.select("query_id", "id").withColumn("hit", F.lit(1)), ["query_id", "id"], "left")
    return found.agg(F.count("*").alias("n"), round6(F.avg(F.coalesce("hit", F.lit(0)).cast("double"))).alias("recall"))


def diversity(lists: DataFrame) -> DataFrame:
    """Mean of 1 - cosine over the pairs inside each (short) result list with ``query_id, pick, embedding``."""
    from corpuskit.sources.adapters import dot

    a = lists.select("query_id", F.col("pick").alias("i"), F.col("embedding").alias("a"))
    b = lists.select("query_id", F.col("pick").alias("j"), F.col("embedding").alias("b"))
    pairs = a.join(b, "query_id").filter("i < j")
    return pairs.groupBy("query_id").agg(round6(F.avg(1 - dot("a", "b"))).alias("diversity"))
