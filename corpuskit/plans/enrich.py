"""Summaries and subfields: eligibility, a rule teacher, a learned extractive summariser, a multi-label network, baselines."""

from __future__ import annotations

import json
import pickle
import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from typing import Protocol

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpuskit.functions.tokens import SENTENCE, WORDS, round6

_SENT = re.compile(SENTENCE)
#: Keyword stems of the rule teacher's labels on the invented prose of the test tables.
VOCABULARY = ("thing", "heat", "ration", "wood", "sand", "others")


def eligibility(df: DataFrame, text: str = "abstract", flag_below: int = 100, exclude_below: int = 1000) -> DataFrame:
    n = F.length(text)
    band = F.when(n.isNull() | (n == 0), "empty").when(n < flag_below, "too_short").when(n < exclude_below, "excluded").otherwise("eligible")
    return df.withColumn("band", band)


# -------------------------------------------------------------------------------- teacher


class Teacher(Protocol):
    def __call__(self, abstract: str) -> str: ...


def rule_teacher(abstract: str) -> str:
    """First sentence, then the first later one with a number; up to 50 words; labels by keyword; JSON."""
    parts = [s.strip() for s in _SENT.findall(abstract) if s.strip()]
    chosen = parts[:1] + [s for s in parts[1:] if re.search(r"\d", s)][:1]
    words = " ".join(chosen).split()[:50]
    if not any(re.search("[0-9]", w) for w in words) and (far := next((s.split() for s in parts if re.search("[0-9]", s)), None)):
        at = next(i for i, w in enumerate(far) if re.search("[0-9]", w))
        words = parts[0].split()[:25] + far[max(0, at - 24) : at + 1]  # the cut must not lose the number
    low = abstract.lower()
    labels = [v for v in VOCABULARY[:-1] if v in low] or [VOCABULARY[-1]]
    return json.dumps({"summary": " ".join(words), "labels": labels}, ensure_ascii=False)


def annotate(df: DataFrame, teacher: Teacher = rule_teacher, text: str = "abstract", out: str = "teacher") -> DataFrame:
    schema = df.withColumn(out, F.lit(None).cast("string")).schema

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield b.assign(**{out: [None if t is None else teacher(t) for t in b[text]]})

    return df.mapInPandas(run, schema)


def check_teacher(df: DataFrame, text: str = "abstract", out: str = "teacher", vocabulary: tuple[str, ...] = VOCABULARY) -> DataFrame:
    """Codes of the constraints that an answer breaks."""
    from corpuskit.plans.validate import codes

    j = F.from_json(out, "summary string, labels array<string>")
    rows = df.withColumn("_j", j)
    words = F.size(F.filter(F.split("_j.summary", r"\s+"), lambda w: w != ""))
    n_sent = F.regexp_count(F.col("_j.summary"), F.lit(SENTENCE))
    digit = r"\d"
    broken = codes(
        not_json=F.col("_j.summary").isNull() | F.col("_j.labels").isNull(), too_long=words > 50, many_sentences=n_sent > 2,
        no_number=F.col(text).rlike(digit) & ~F.col("_j.summary").rlike(digit),
        foreign_label=F.size(F.array_except("_j.labels", F.array(*map(F.lit, vocabulary)))) > 0,
        repeated_label=F.size("_j.labels") > F.size(F.array_distinct("_j.labels")),
    )
    return rows.withColumn("codes", broken).drop("_j")


def review_sample(df: DataFrame, n: int = 45, seed: int = 42, key: str = "corpus_id") -> DataFrame:
    """The same ``n`` rows on every run and cluster."""
    return df.orderBy(F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string"))), key).limit(n)


def split(df: DataFrame, weights: tuple[int, int, int] = (80, 10, 10), seed: int = 42, key: str = "corpus_id") -> DataFrame:
    b = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string"))), 1, 8), 16, 10).cast("long") % sum(weights)
    return df.withColumn("split", F.when(b < weights[0], "train").when(b < weights[0] + weights[1], "validation").otherwise("test"))


# ------------------------------------------------------------------------------ summaries


class Summariser(Protocol):
    def __call__(self, texts: list[str]) -> list[str]: ...


@dataclass(frozen=True)
class TrainConfig:
    """Settings of the fit and of the decoding.

    A fine-tuned encoder-decoder behind :class:`Summariser` takes them all; the extractive
    stand-in takes the seed, the batches, the epochs and the limits, and ``step`` as its
    learning rate. ``max_rows`` bounds the rows that any fit on the driver reads.
    """

    seed: int = 42
    learning_rate: float = 2e-5
    batch: int = 4
    accumulate: int = 4
    epochs: int = 5
    max_in: int = 1024
    max_out: int = 128
    eval_steps: int = 1000
    save_steps: int = 1000
    log_steps: int = 500
    step: float = 0.5
    max_rows: int = 20_000


def _sentence_features(text: str) -> tuple[list[str], np.ndarray]:
    parts = [s.strip() for s in _SENT.findall(text) if s.strip()]
    bags = [set(re.findall(r"\w+", s.lower())) for s in parts]
    every = set().union(*bags) if bags else set()
    x = [
        [1.0, 1 / (1 + i), float(i == 0), min(len(b), 60) / 60, float(bool(re.search(r"\d", s))), len(b & bags[0]) / max(1, len(b)), len(b) / max(1, len(every))]
        for i, (s, b) in enumerate(zip(parts, bags, strict=True))
    ]
    return parts, np.array(x).reshape(len(parts), 7)


@dataclass
class ExtractiveSummariser:
    """Logistic regression over sentence features, fitted to the teacher's choices; gives up to two sentences and 50 words."""

    weights: np.ndarray = field(default_factory=lambda: np.zeros(7))

    def fit(self, texts: list[str], summaries: list[str], cfg: TrainConfig | None = None) -> ExtractiveSummariser:
        """Steps of ``batch * accumulate`` texts, ``epochs`` times over all, in an order given by the seed."""
        cfg = cfg or TrainConfig()
        rows = []
        for t, s in zip(texts, summaries, strict=True):
            parts, x = _sentence_features(t)
            rows.append((x, np.array([float(" ".join(p.split()[:8]) in s) for p in parts])))
        rng = np.random.default_rng(cfg.seed)
        size = cfg.batch * cfg.accumulate
        for epoch in range(cfg.epochs):
            order = rng.permutation(len(rows))
            for i in range(0, len(order), size):
                own = [rows[k] for k in order[i : i + size] if len(rows[k][1])]
                if own:
                    x, y = np.concatenate([r[0] for r in own]), np.concatenate([r[1] for r in own])
                    p = 1 / (1 + np.exp(-np.clip(x @ self.weights, -30, 30)))
                    self.weights = self.weights - cfg.step / (1 + epoch) * (x.T @ (p - y) / len(y) + 1e-4 * self.weights)
        return self

    def __call__(self, texts: list[str]) -> list[str]:
        out = []
        for t in texts:
            parts, x = _sentence_features(t)
            best = sorted(np.argsort(-(x @ self.weights), kind="stable")[:2]) if parts else []
            out.append(" ".join(" ".join(parts[i] for i in best).split()[:50]))
        return out


def fit_summariser(df: DataFrame, text: str = "abstract", summary: str = "reference", cfg: TrainConfig | None = None, key: str = "corpus_id") -> ExtractiveSummariser:
    """The stand-in fitted to at most ``max_rows`` (text, summary) rows, taken by hash order."""
    cfg = cfg or TrainConfig()
    rows = df.filter(F.col(text).isNotNull() & F.col(summary).isNotNull()).orderBy(F.xxhash64(key, F.lit(cfg.seed)), key).limit(cfg.max_rows).select(text, summary).toPandas()
    return ExtractiveSummariser().fit(list(rows[text]), list(rows[summary]), cfg)


def summarise(df: DataFrame, model: Summariser, text: str = "abstract", out: str = "summary", cfg: TrainConfig | None = None) -> DataFrame:
    """Inputs cut to ``max_in`` words, outputs to ``max_out``, in Arrow batches."""
    cfg = cfg or TrainConfig()
    schema = df.withColumn(out, F.lit(None).cast("string")).schema

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            texts = [_first_words(t, cfg.max_in) for t in b[text]]
            yield b.assign(**{out: [_first_words(s, cfg.max_out) for s in model(texts)]})

    return df.mapInPandas(run, schema)


def _first_words(text: str | None, n: int) -> str:
    m = re.match(rf"\s*(?:\S+\s+){{0,{n - 1}}}\S+", text or "")
    return m[0].strip() if m else ""


def lead_k(df: DataFrame, k: int = 3, text: str = "text", out: str = "summary") -> DataFrame:
    parts = F.filter(F.transform(F.regexp_extract_all(F.col(text), F.lit(SENTENCE), F.lit(0)), lambda s: F.trim(s)), lambda s: s != "")
    return df.withColumn(out, F.array_join(F.slice(parts, 1, k), " "))


def _similarity(parts: list[str]) -> np.ndarray:
    bags = [re.findall(r"\w+", s.lower()) for s in parts]
    vocab = {w: i for i, w in enumerate(sorted({w for b in bags for w in b}))}
    tf = np.zeros((len(parts), max(1, len(vocab))))
    for i, b in enumerate(bags):
        for w in b:
            tf[i, vocab[w]] += 1
    x = tf * np.log((1 + len(parts)) / (1 + (tf > 0).sum(0)))
    n = np.sqrt((x * x).sum(1, keepdims=True))
    x = x / np.where(n == 0, 1, n)
    return x @ x.T


def central_sentences(text: str, k: int = 3, threshold: float = 0.1, damping: float = 0.85, max_sentences: int = 2000) -> str:
    """The ``k`` sentences of highest stationary weight in the similarity graph, in text order.

    A text of more sentences than ``max_sentences`` is ranked in windows of that size, whose
    winners are ranked together, so memory stays bounded and no sentence is left out.
    """
    parts = [s.strip() for s in _SENT.findall(text) if s.strip()]
    if len(parts) > max_sentences:
        firsts = [central_sentences(" ".join(parts[i : i + max_sentences]), k, threshold, damping, max_sentences) for i in range(0, len(parts), max_sentences)]
        return central_sentences(" ".join(firsts), k, threshold, damping, max_sentences)
    if len(parts) <= k:
        return " ".join(parts)
    a = (_similarity(parts) > threshold).astype(float)
    np.fill_diagonal(a, 0)  # a sentence does not vote for itself
    degree = a.sum(1, keepdims=True)
    m = np.where(degree > 0, a / np.where(degree == 0, 1, degree), 1 / len(parts))
    p = np.full(len(parts), 1 / len(parts))
    for _ in range(100):
        new = (1 - damping) / len(parts) + damping * (m.T @ p)
        done, p = np.abs(new - p).max() < 1e-9, new
        if done:
            break
    return " ".join(parts[i] for i in sorted(np.argsort(-p, kind="stable")[:k]))


def lexical_centrality(df: DataFrame, k: int = 3, threshold: float = 0.1, damping: float = 0.85, text: str = "text", out: str = "summary") -> DataFrame:
    schema = df.withColumn(out, F.lit(None).cast("string")).schema

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield b.assign(**{out: [central_sentences(t or "", k, threshold, damping) for t in b[text]]})

    return df.mapInPandas(run, schema)


def degree_centrality(df: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """For each sentence, the words it shares with the rest of its text, over its own words: centrality from counts alone.

    A shared word of *c* sentences links a sentence to c - 1 others; summing that by counts
    needs no pairs of sentences.
    """
    s = df.select(key, F.posexplode(F.regexp_extract_all(F.col(text), F.lit(SENTENCE), F.lit(0))).alias("pos", "sentence"))
    w = s.select(key, "pos", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("sentence"), F.lit(WORDS), F.lit(0)))).alias("w"))
    c = w.groupBy(key, "w").agg((F.count("*") - 1).alias("links"))
    return w.join(c, [key, "w"]).groupBy(key, "pos").agg(F.sum("links").alias("links"), F.count("*").alias("words"))


# ------------------------------------------------------------------------------ subfields


def class_weights(labels: DataFrame, n: int, lo: float = 1.0, hi: float = 20.0) -> DataFrame:
    """Negatives over positives for each label, clipped."""
    g = labels.groupBy("label").agg(F.count("*").alias("positives"))
    return g.withColumn("weight", round6(F.greatest(F.lit(lo), F.least(F.lit(hi), (F.lit(float(n)) - F.col("positives")) / F.col("positives")))))


def cardinality(labels: DataFrame, key: str = "vec_id") -> DataFrame:
    return labels.groupBy(key).agg(F.count("*").alias("labels")).groupBy("labels").agg(F.count("*").alias("n"))


@dataclass(frozen=True)
class MLPConfig:
    hidden: int = 256
    dropout: float = 0.3
    lr: float = 1e-3
    batch: int = 32
    epochs: int = 50
    patience: int = 5
    plateau: int = 2
    seed: int = 42
    max_rows: int = 20_000


class MLPModel:
    """d -> hidden -> hidden -> labels with batch norm, ReLU and dropout, sigmoid outputs; numpy, weighted cross-entropy, Adam."""

    def __init__(self, d: int, out: int, cfg: MLPConfig):
        rng = np.random.default_rng(cfg.seed)
        sizes = [d, cfg.hidden, cfg.hidden, out]
        self.w = [rng.normal(size=(a, b)) * np.sqrt(2 / a) for a, b in zip(sizes, sizes[1:], strict=False)]
        self.b = [np.zeros(b) for b in sizes[1:]]
        self.gamma, self.beta = [np.ones(cfg.hidden) for _ in range(2)], [np.zeros(cfg.hidden) for _ in range(2)]
        self.mean, self.var = [np.zeros(cfg.hidden) for _ in range(2)], [np.ones(cfg.hidden) for _ in range(2)]
        self.cfg, self.rng = cfg, rng

    def params(self) -> list[np.ndarray]:
        return [*self.w, *self.b, *self.gamma, *self.beta]

    def predict(self, x: np.ndarray) -> np.ndarray:
        h = x
        for i in range(2):
            z = h @ self.w[i] + self.b[i]
            h = np.maximum(self.gamma[i] * (z - self.mean[i]) / np.sqrt(self.var[i] + 1e-5) + self.beta[i], 0)
        return 1 / (1 + np.exp(-np.clip(h @ self.w[2] + self.b[2], -30, 30)))

    def gradients(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> list[np.ndarray]:
        cache, h = [], x
        for i in range(2):
            z = h @ self.w[i] + self.b[i]
            mu, var = z.mean(0), z.var(0)
            self.mean[i], self.var[i] = 0.9 * self.mean[i] + 0.1 * mu, 0.9 * self.var[i] + 0.1 * var
            inv = 1 / np.sqrt(var + 1e-5)
            n = (z - mu) * inv
            a = self.gamma[i] * n + self.beta[i]
            keep = (self.rng.random(a.shape) >= self.cfg.dropout) / (1 - self.cfg.dropout)
            cache.append((h, n, inv, a > 0, keep))
            h = np.maximum(a, 0) * keep
        p = 1 / (1 + np.exp(-np.clip(h @ self.w[2] + self.b[2], -30, 30)))
        d = (p * (1 + (weight - 1) * y) - weight * y) / y.size
        gw, gb, gg, gt = [None] * 3, [None] * 3, [None] * 2, [None] * 2
        gw[2], gb[2] = h.T @ d, d.sum(0)
        d = d @ self.w[2].T
        for i in (1, 0):
            h, n, inv, on, keep = cache[i]
            d = d * keep * on
            gg[i], gt[i] = (d * n).sum(0), d.sum(0)
            dn = d * self.gamma[i]
            dz = inv * (dn - dn.mean(0) - n * (dn * n).mean(0))
            gw[i], gb[i] = h.T @ dz, dz.sum(0)
            d = dz @ self.w[i].T
        return [*gw, *gb, *gg, *gt]

    def loss(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> float:
        p = np.clip(self.predict(x), 1e-7, 1 - 1e-7)
        return float(-(weight * y * np.log(p) + (1 - y) * np.log(1 - p)).mean())

    def fit(self, x: np.ndarray, y: np.ndarray, xv: np.ndarray, yv: np.ndarray) -> MLPModel:
        cfg = self.cfg
        pos = y.sum(0)
        weight = np.clip((len(y) - pos) / np.maximum(pos, 1), 1, 20)
        m, v = [np.zeros_like(p) for p in self.params()], [np.zeros_like(p) for p in self.params()]
        lr, best, bad, step, kept = cfg.lr, np.inf, 0, 0, None
        for _ in range(cfg.epochs):
            order = self.rng.permutation(len(x))
            for i in range(0, len(x), cfg.batch):
                at = order[i : i + cfg.batch]
                if len(at) < 2:
                    continue
                step += 1
                for k, (p, g) in enumerate(zip(self.params(), self.gradients(x[at], y[at], weight), strict=True)):
                    m[k] = 0.9 * m[k] + 0.1 * g
                    v[k] = 0.999 * v[k] + 0.001 * g * g
                    p -= lr * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
            now = self.loss(xv, yv, weight)
            if now < best - 1e-5:
                best, bad, kept = now, 0, ([p.copy() for p in self.params()], [a.copy() for a in self.mean], [a.copy() for a in self.var])
            else:
                bad += 1
                if bad % cfg.plateau == 0:
                    lr *= 0.5
                if bad >= cfg.patience:
                    break
        if kept:
            for p, q in zip(self.params(), kept[0], strict=True):
                p[...] = q
            self.mean, self.var = kept[1], kept[2]
        return self


def label_matrix(rows: DataFrame, labels: DataFrame, n_labels: int, cfg: MLPConfig | None = None, key: str = "vec_id") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids, vectors and label sets of a bounded training set, on the driver: at most ``max_rows``, taken by hash order."""
    cfg = cfg or MLPConfig()
    sets = labels.groupBy(key).agg(F.collect_set("label").alias("labels"))
    got = rows.join(sets, key, "left").orderBy(F.xxhash64(key), key).limit(cfg.max_rows).select(key, "embedding", "labels").toPandas()
    y = np.zeros((len(got), n_labels))
    for i, own in enumerate(got["labels"]):
        if own is not None:
            y[i, list(own)] = 1
    return got[key].to_numpy(), np.array(got["embedding"].tolist(), float), y


def fit_subfields(rows: DataFrame, labels: DataFrame, n_labels: int = 18, cfg: MLPConfig | None = None) -> MLPModel:
    cfg = cfg or MLPConfig()
    _, x, y = label_matrix(rows, labels, n_labels, cfg)
    cut = max(1, len(x) // 9)
    return MLPModel(x.shape[1], n_labels, cfg).fit(x[cut:], y[cut:], x[:cut], y[:cut])


def fold_of(key: str, k: int, seed: int = 42) -> Column:
    return F.pmod(F.xxhash64(key, F.lit(seed)), F.lit(k)).cast("int")


def cross_validate(rows: DataFrame, labels: DataFrame, n_labels: int = 18, k: int = 5, cfg: MLPConfig | None = None, key: str = "vec_id") -> DataFrame:
    """Micro F1 of each fold, over all its rows.

    Every row is in a fold, by hash. A fold's model is fitted on the bounded training rows
    of the others, the folds in parallel; then each row is scored by the model that has not
    seen its fold.
    """
    cfg = cfg or MLPConfig()
    spark = rows.sparkSession
    folded = rows.withColumn("fold", fold_of(key, k, cfg.seed))
    ids, x, y = label_matrix(rows, labels, n_labels, cfg, key)
    listed = spark.createDataFrame([(int(i),) for i in ids], f"{key} long").withColumn("fold", fold_of(key, k, cfg.seed)).toPandas()
    of = listed.set_index(key)["fold"].loc[ids].to_numpy()

    def fit(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for fold in b["fold"]:
                xs, ys = x[of != fold], y[of != fold]
                cut = max(1, len(xs) // 9)
                model = MLPModel(x.shape[1], n_labels, cfg).fit(xs[cut:], ys[cut:], xs[:cut], ys[:cut])
                yield pd.DataFrame({"fold": [fold], "model": [pickle.dumps(model)]})

    fitted = spark.range(k).select(F.col("id").cast("int").alias("fold")).repartition(k, "fold").mapInPandas(fit, "fold int, model binary").collect()
    models = {r["fold"]: pickle.loads(bytes(r["model"])) for r in fitted}

    def score(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for fold, own in b.groupby("fold"):
                p = models[fold].predict(np.array(own["embedding"].tolist(), float))
                n = p.shape[1]
                yield pd.DataFrame({key: np.repeat(own[key].to_numpy(), n), "fold": np.int32(fold), "label": np.tile(np.arange(n, dtype=np.int32), len(own)), "score": p.ravel()})

    scores = with_truth(folded.select(key, "embedding", "fold").mapInPandas(score, f"{key} long, fold int, label int, score double"), labels, key)
    hit, true = F.col("score") >= 0.5, F.col("truth") == 1
    g = scores.groupBy("fold").agg(F.count_distinct(key).alias("rows"), F.count_if(hit & true).alias("tp"), F.count_if(hit & ~true).alias("fp"), F.count_if(~hit & true).alias("fn"))
    return g.select("fold", "rows", round6(F.coalesce(F.try_divide(2.0 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")), F.lit(0.0))).alias("micro_f1"))


def predict_subfields(rows: DataFrame, model: MLPModel, key: str = "vec_id") -> DataFrame:
    """``key, label, score`` for every label of every row."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                p = model.predict(np.array(b["embedding"].tolist(), float))
                n = p.shape[1]
                yield pd.DataFrame({key: np.repeat(b[key].to_numpy(), n), "label": np.tile(np.arange(n, dtype=np.int32), len(b)), "score": p.ravel()})

    return rows.select(key, "embedding").mapInPandas(run, f"{key} long, label int, score double")


def with_truth(scores: DataFrame, labels: DataFrame, key: str = "vec_id") -> DataFrame:
    return scores.join(labels.withColumn("truth", F.lit(1)), [key, "label"], "left").na.fill(0, ["truth"])


def majority_scores(rows: DataFrame, train: DataFrame, top: int = 1, n_labels: int = 18, key: str = "vec_id") -> DataFrame:
    """The labels most frequent in ``train`` (key, label) for every one of ``rows``: score 1 for those, 0 for the others."""
    first = train.groupBy("label").agg(F.count("*").alias("n")).orderBy(F.col("n").desc(), "label").limit(top).select("label", F.lit(1.0).alias("hit"))
    every = rows.select(key).crossJoin(F.broadcast(rows.sparkSession.range(n_labels).select(F.col("id").cast("int").alias("label"))))
    return every.join(F.broadcast(first), "label", "left").select(key, "label", F.coalesce("hit", F.lit(0.0)).alias("score"))


def direction_scores(rows: DataFrame, train: DataFrame, labels: DataFrame, threshold: float = 0.08, key: str = "vec_id") -> DataFrame:
    """Mean direction of each label's training rows; score 1 where a row's inner product passes the threshold. One mean for each label is broadcast."""
    from corpuskit.sources.adapters import dot

    sums = train.join(labels, key).select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.avg(F.col("x").cast("double")).alias("m"))
    mean = sums.groupBy("label").agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "m"))), lambda s: s["m"]).alias("c"))
    met = rows.crossJoin(F.broadcast(mean))
    return met.select(key, "label", F.when(round6(dot("embedding", "c")) >= threshold, 1.0).otherwise(0.0).alias("score"))


def _ml_vectors(rows: DataFrame, *keep: str) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    return rows.select(*[F.col(f"`{k}`") for k in keep], array_to_vector(F.transform("embedding", lambda v: v.cast("double"))).alias("features"))


def one_vs_rest(rows: DataFrame, train: DataFrame, labels: DataFrame, names: tuple[int, ...], key: str = "vec_id", max_iter: int = 20) -> DataFrame:
    """A logistic regression of Spark ML for each label, fitted on ``train``, as scores of ``rows``."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import vector_to_array

    wide = labels.groupBy(key).pivot("label", list(names)).agg(F.lit(1.0))
    x, own = _ml_vectors(rows, key), _ml_vectors(train.join(wide, key, "left").na.fill(0.0, [str(n) for n in names]), key, *[str(n) for n in names]).cache()
    out = None
    for n in names:
        model = LogisticRegression(labelCol=str(n), maxIter=max_iter, regParam=0.001).fit(own)
        part = model.transform(x).select(key, F.lit(n).alias("label"), vector_to_array("probability")[1].alias("score"))
        out = part if out is None else out.unionByName(part)
    own.unpersist()
    return out


def spark_mlp(rows: DataFrame, train: DataFrame, labels: DataFrame, n_labels: int = 18, hidden: int = 32, key: str = "vec_id") -> DataFrame:
    """Single-label network of Spark ML on the least label of each training row, as scores of ``rows``."""
    from pyspark.ml.classification import MultilayerPerceptronClassifier
    from pyspark.ml.functions import vector_to_array

    y = labels.groupBy(key).agg(F.min("label").cast("double").alias("y"))
    fitted = _ml_vectors(train.join(y, key), key, "y")
    d = len(train.select("embedding").first()[0])
    model = MultilayerPerceptronClassifier(layers=[d, hidden, n_labels], labelCol="y", maxIter=40, seed=42).fit(fitted)
    return model.transform(_ml_vectors(rows, key)).select(key, F.posexplode(vector_to_array("probability")).alias("label", "score"))


def rank_labels(scores: DataFrame, tau: float, key: str = "vec_id") -> DataFrame:
    """``subfields`` as a map of the scores at or above the threshold, and the best label."""
    w = Window.partitionBy(key).orderBy(F.col("score").desc(), "label")
    kept = scores.withColumn("n", F.row_number().over(w)).filter((F.col("score") >= tau) | (F.col("n") == 1))
    entry: Column = F.struct(F.col("label").cast("string").alias("k"), F.col("score").alias("v"))
    return kept.groupBy(key).agg(F.map_from_entries(F.collect_list(entry)).alias("subfields"))
