"""Quality classifier from weak labels (operator 4).

Heuristic labellers vote good, bad or abstain on every document. Expectation-maximisation
over the counts of vote patterns (a table of at most ``3 ** labellers`` rows, whatever the
corpus) estimates how each labeller votes on good and on bad documents. The posteriors of
the patterns are the targets of a linear scorer over hashed features, fitted on a bounded
sample (``train_rows``), and the scorer then reads every document.

Defined cases: a text without words (null, empty, white space) gets no votes, score 0 and
is rejected; equal texts get equal scores; only the id and text columns are read; with no
documents, or none with words, the result has a score of 0 for each row.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpuskit.llm.common import id_text, slices, small, utf8
from corpuskit.llm.shingles import LOWER, run_hashes, word_bounds

_U = np.uint64


@dataclass(frozen=True)
class QualityModel:
    """``train_rows`` bounds the documents that the scorer is fitted on; all else reads all rows."""

    train_rows: int = 8192
    feature_bits: int = 16
    iterations: int = 120
    threshold: float = 0.5
    em_rounds: int = 100


#: Frequent function words of English, French, German and Spanish.
STOP_WORDS = (
    "the of and to a in that is was for on with as by it be at are this from or an not "
    "de la le et les des en un une du dans que qui pour sur au par avec est "
    "der die und das den von zu mit sich ist im ein eine nicht auf für "
    "el los las y del se por con su al lo como más"
).split()
LABELLERS = ("symbols", "bars", "capitals", "exclamations", "variety", "stop_words", "word_length", "lines", "endings", "runs")

_KIND = np.full(256, 0, np.uint8)  # 0 other, 1 lower or part of a character beyond ASCII, 2 upper, 3 digit
_KIND[97:123] = 1
_KIND[128:] = 1
_KIND[65:91] = 2
_KIND[48:58] = 3
_SHAPE = np.where(_KIND == 1, ord("a"), np.where(_KIND == 2, ord("A"), np.where(_KIND == 3, ord("0"), np.arange(256)))).astype(np.uint8)
_IS_SYMBOL = np.zeros(256, bool)
_IS_SYMBOL[list(b"#*$%&|<>")] = True


def _stop_hashes() -> np.ndarray:
    body = [w.encode() for w in STOP_WORDS]
    ends = np.cumsum([len(w) for w in body])
    return np.sort(run_hashes(np.frombuffer(b"".join(body), np.uint8), np.concatenate(([0], ends[:-1])), ends))


class Measures:
    """What the labellers and the scorer look at, for the texts of one slice."""

    stops: np.ndarray | None = None

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        if Measures.stops is None:
            Measures.stops = _stop_hashes()
        self.starts, self.ends, self.first = word_bounds(data, offsets)
        self.n = np.diff(self.first)
        low = LOWER[data]
        self.words = run_hashes(low, self.starts, self.ends)
        letters_end = self.ends - np.isin(data[self.ends - 1] if len(self.ends) else self.ends, list(b".,!?;:"))
        bare = run_hashes(low, self.starts, np.maximum(letters_end, self.starts))
        at = np.minimum(np.searchsorted(self.stops, bare), len(self.stops) - 1)
        self.stop = self.stops[at] == bare
        shape = _SHAPE[data]
        self.tails = run_hashes(shape, np.maximum(self.starts, self.ends - 4), self.ends)
        self.same = np.zeros(len(self.words), bool)
        self.same[1:] = self.words[1:] == self.words[:-1]
        self.same[self.first[:-1][self.first[:-1] < len(self.words)]] = False
        kind = _KIND[data]
        total = lambda flags: np.diff(np.concatenate(([0], np.cumsum(flags)))[offsets])
        self.upper, self.lower = total(kind == 2), total(kind == 1)
        self.symbols, self.shouts, self.bars = total(_IS_SYMBOL[data]), total(data == ord("!")), total(data == ord("|"))
        by_word = lambda x: np.diff(np.concatenate(([0], np.cumsum(x)))[self.first])
        self.stop_n, self.same_n = by_word(self.stop), by_word(self.same)
        self.chars = by_word(self.ends - self.starts)
        ends_sentence = np.isin(data, list(b".!?"))
        self.stops_n = total(ends_sentence)
        self.variety = np.array([len(np.unique(self.words[a:b])) for a, b in zip(self.first[:-1], self.first[1:], strict=True)])
        line_ends = np.flatnonzero(data == 10)
        self.lines, self.line_repeats = [], []
        for a, b in zip(offsets[:-1], offsets[1:], strict=True):
            cut = line_ends[np.searchsorted(line_ends, a) : np.searchsorted(line_ends, b)]
            begin, end = np.concatenate(([a], cut + 1)), np.concatenate((cut, [b]))
            full = end - begin > 0
            found = run_hashes(data[a:b], begin[full] - a, end[full] - a) if full.any() else full[:0]
            self.lines.append(len(found))
            self.line_repeats.append(len(found) - len(np.unique(found)))
        self.lines, self.line_repeats = np.array(self.lines), np.array(self.line_repeats)

    def votes(self) -> np.ndarray:
        """A row for each text, a column for each labeller: 1 good, -1 bad, 0 no opinion."""
        n = np.maximum(self.n, 1)
        long_, letters = self.n >= 20, np.maximum(self.upper + self.lower, 1)
        share = lambda good, bad: np.where(bad, -1, np.where(good, 1, 0))
        symbols, upper, shout = self.symbols / n, self.upper / letters, self.shouts / n
        variety, stop, length = self.variety / n, self.stop_n / n, self.chars / n
        repeated = self.line_repeats / np.maximum(self.lines, 1)
        out = [
            share(symbols < 0.02, symbols > 0.6),
            share(self.bars * 50 < n, self.bars * 5 > n),
            share((upper < 0.08) & long_, (upper > 0.3) & long_),
            share(shout < 0.05, shout > 0.5),
            share((variety > 0.5) & long_, (variety < 0.3) & long_),
            share((stop > 0.12) & long_, (stop < 0.02) & long_),
            share((length > 3) & (length < 9) & long_, ((length < 2.5) | (length > 12)) & long_),
            share((repeated == 0) & (self.lines > 2), (repeated > 0.5) & (self.lines > 3)),
            share((self.stops_n * 30 > n) & (self.stops_n * 2 < n) & long_, (self.stops_n * 100 < n) & long_),
            share((self.same_n * 50 < n) & long_, (self.same_n * 5 > n) & long_),
        ]
        return np.where(self.n[:, None] > 0, np.stack(out, axis=1), 0)

    def features(self, bits: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Hashed features of each text and their weights, of length 1 for each block."""
        shift, salt = _U(64 - bits), _U(0x5851F42D4C957F2D)
        n = np.maximum(self.n, 1)
        ratios = np.stack(
            [self.variety / n, self.same_n / n, self.line_repeats / np.maximum(self.lines, 1), self.symbols / n, self.shouts / n,
             self.bars / n, self.upper / np.maximum(self.upper + self.lower, 1), self.stop_n / n], axis=1)
        level = np.minimum(8, np.floor(np.minimum(ratios, 1) * 8)).astype(np.int64) + 9 * np.arange(ratios.shape[1]) + 100 * (self.n >= 20)[:, None]
        with np.errstate(over="ignore"):
            dense = ((level.astype(_U) + _U(7)) * _U(0x9E3779B97F4A7C15) * salt) >> shift
            words, tails = self.words >> shift, (self.tails * salt) >> shift
        for i, (a, b) in enumerate(zip(self.first[:-1], self.first[1:], strict=True)):
            blocks, weights = [dense[i]], [np.full(dense.shape[1], dense.shape[1] ** -0.5)]
            for part in (words[a:b], tails[a:b]):
                at, k = np.unique(part, return_counts=True)
                w = np.log1p(k)
                blocks.append(at)
                weights.append(w / max(1e-9, np.sqrt((w * w).sum())))
            yield np.concatenate(blocks).astype(np.int32), np.concatenate(weights).astype(np.float32)


def _measured(batch: pa.RecordBatch) -> Iterator[tuple[int, int, Measures]]:
    data, offsets = utf8(batch.column(batch.num_columns - 1))
    for i, j in slices(offsets):
        yield i, j, Measures(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])


def _code(votes: np.ndarray) -> np.ndarray:
    return (votes + 1) @ (3 ** np.arange(votes.shape[1]))


def _count_patterns(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    seen: Counter = Counter()
    for batch in small(batches, 2048):
        for _, _, m in _measured(batch):
            seen.update(_code(m.votes()[m.n > 0]).tolist())
    yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.int64()), pa.array(list(seen.values()), pa.int64())], ["pattern", "n"])


def label_model(patterns: np.ndarray, counts: np.ndarray, rounds: int = 100) -> tuple[np.ndarray, np.ndarray, float]:
    """EM with labellers that are independent given the class.

    Returns the posterior of good for each pattern (rows of ``patterns``), the vote
    probabilities [class, labeller, vote + 1] given that the labeller votes, and the share
    of good documents.
    """
    n = counts.astype(float)
    vote = patterns + 1
    # a kind of junk has a labeller or two of its own and looks good to all others, so one bad vote starts as bad
    post = 1 / (1 + np.exp(-(2.0 + 0.2 * (patterns == 1).sum(1) - 6.0 * (patterns == -1).sum(1))))
    table, prior = np.zeros((2, vote.shape[1], 3)), 0.5
    for _ in range(rounds):
        for c, w in ((0, n * (1 - post)), (1, n * post)):
            for j in range(vote.shape[1]):
                table[c, j] = np.bincount(vote[:, j], weights=w, minlength=3) + 1
        table[:, :, 1] = 0  # to abstain says nothing of the class: what counts is how a labeller votes when it does
        table /= table.sum(2, keepdims=True)
        table[:, :, 1] = 1
        prior = float(np.clip((n * post).sum() / max(n.sum(), 1), 1e-3, 1 - 1e-3))
        log = [np.log(table[c, np.arange(vote.shape[1]), vote]).sum(1) for c in (0, 1)]
        new = 1 / (1 + np.exp(np.clip(log[0] - log[1] + np.log((1 - prior) / prior), -700, 700)))
        done, post = np.abs(new - post).max(initial=0) < 1e-7, new
        if done:
            break
    return post, table, prior


def fit_scorer(index: np.ndarray, value: np.ndarray, first: np.ndarray, target: np.ndarray, cfg: QualityModel) -> tuple[np.ndarray, float]:
    """Logistic regression with soft targets, by full-batch Adam; rows are ``first[i]:first[i + 1]``."""
    size = 1 << cfg.feature_bits
    w, bias = np.zeros(size), float(np.log(max(target.mean(), 1e-3) / max(1 - target.mean(), 1e-3)))
    m, v, mb, vb = np.zeros(size), np.zeros(size), 0.0, 0.0
    row = np.repeat(np.arange(len(target)), np.diff(first))
    for step in range(1, cfg.iterations + 1):
        z = np.bincount(row, weights=w[index] * value, minlength=len(target)) + bias
        err = 1 / (1 + np.exp(-np.clip(z, -50, 50))) - target
        g = np.bincount(index, weights=err[row] * value, minlength=size) / len(target) + 1e-5 * w
        gb = float(err.mean())
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        mb, vb = 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb * gb
        a, b = 1 - 0.9**step, 1 - 0.99**step
        w -= 0.1 * (m / a) / (np.sqrt(v / b) + 1e-8)
        bias -= 0.1 * (mb / a) / (np.sqrt(vb / b) + 1e-8)
    return w.astype(np.float32), bias


@dataclass(frozen=True)
class Fitted:
    weights: np.ndarray
    bias: float
    posterior: dict[int, float]
    table: np.ndarray
    prior: float


def fit(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", cfg: QualityModel | None = None) -> Fitted:
    """The label model over all rows of ``df`` and the scorer over its sample."""
    cfg = cfg or QualityModel()
    docs = id_text(df, id_col, text_col)
    rows = docs.select("text").mapInArrow(_count_patterns, "pattern long, n long").groupBy("pattern").agg(F.sum("n").alias("n")).toArrow()
    codes, counts = rows["pattern"].to_numpy(), rows["n"].to_numpy()
    order = np.argsort(codes)
    codes, counts = codes[order], counts[order]
    votes = (codes[:, None] // 3 ** np.arange(len(LABELLERS))) % 3 - 1
    post, table, prior = label_model(votes, counts, cfg.em_rounds)
    posterior = dict(zip(codes.tolist(), post.tolist(), strict=True))
    many = int(counts.sum())
    if not many:
        return Fitted(np.zeros(1 << cfg.feature_bits, np.float32), 0.0, posterior, table, prior)

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches, 2048):
            index, value, target = [], [], []
            for _, _, m in _measured(batch):
                codes = _code(m.votes())
                for k, (at, w) in enumerate(m.features(cfg.feature_bits)):
                    if m.n[k]:
                        index.append(at.tobytes())
                        value.append(w.tobytes())
                        target.append(posterior[int(codes[k])])
            yield pa.RecordBatch.from_arrays([pa.array(index, pa.binary()), pa.array(value, pa.binary()), pa.array(target, pa.float64())], ["i", "v", "t"])

    share = min(1.0, cfg.train_rows / many)
    bound = int(share * 1_000_000)
    sample = docs.filter(F.pmod(F.xxhash64("doc_id", F.lit(17)), F.lit(1_000_000)) < max(bound, 1)) if share < 1 else docs
    got = sample.select("text").mapInArrow(gather, "i binary, v binary, t double").toArrow()
    if not got.num_rows:
        return Fitted(np.zeros(1 << cfg.feature_bits, np.float32), float(np.log(prior / (1 - prior))), posterior, table, prior)
    index = [np.frombuffer(x, np.int32) for x in got["i"].to_pylist()]
    value = np.concatenate([np.frombuffer(x, np.float32) for x in got["v"].to_pylist()])
    first = np.concatenate(([0], np.cumsum([len(x) for x in index])))
    w, bias = fit_scorer(np.concatenate(index), value, first, got["t"].to_numpy(), cfg)
    return Fitted(w, bias, posterior, table, prior)


def _score(batch: pa.RecordBatch, model: Fitted, cfg: QualityModel) -> tuple[np.ndarray, np.ndarray]:
    score, weak = np.zeros(batch.num_rows), np.full(batch.num_rows, model.prior)
    for i, _, m in _measured(batch):
        codes = _code(m.votes())
        for k, (at, w) in enumerate(m.features(cfg.feature_bits)):
            if m.n[k]:
                score[i + k] = 1 / (1 + np.exp(-np.clip(float(model.weights[at] @ w) + model.bias, -50, 50)))
                weak[i + k] = model.posterior.get(int(codes[k]), model.prior)
    return score, weak


def score_documents(df: DataFrame, model: Fitted, id_col: str = "doc_id", text_col: str = "text", cfg: QualityModel | None = None) -> DataFrame:
    """``doc_id, weak_label, score, kept`` for each row."""
    cfg = cfg or QualityModel()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches, 2048):
            score, weak = _score(batch, model, cfg)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(weak), pa.array(score), pa.array(score >= cfg.threshold)], ["doc_id", "weak_label", "score", "kept"]
            )

    return id_text(df, id_col, text_col).mapInArrow(run, "doc_id long, weak_label double, score double, kept boolean")


def classify(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", cfg: QualityModel | None = None) -> DataFrame:
    """Fit on ``df`` and score it."""
    return score_documents(df, fit(df, id_col, text_col, cfg), id_col, text_col, cfg)


def keep_good(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", cfg: QualityModel | None = None) -> DataFrame:
    """Rows of ``df`` that the scorer keeps, all columns as they were."""
    cfg = cfg or QualityModel()
    model = fit(df, id_col, text_col, cfg)
    body = df.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches, 2048):
            text = pa.RecordBatch.from_arrays([batch.column(body)], ["text"])
            yield batch.filter(pa.array(_score(text, model, cfg)[0] >= cfg.threshold))

    return df.mapInArrow(run, df.schema)
