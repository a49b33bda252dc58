"""Exact top-k by inner product with MaxScore (operator 2).

Each vector is a sparse document whose terms are (component, sign): a positive and a
negative component are postings of different terms. For a query, terms of its own sign
add to the score and terms of the other sign take away. A shard keeps, block by block, the
postings of each term and the largest weight in each, so the most that a term can add to
any vector of a block is known.

For a query and a block, terms are ordered by that bound. With the score of the k-th best
so far as threshold, the terms whose bounds together cannot reach it are non-essential: a
vector with postings in none of the others cannot compete. The postings of the essential
terms are walked, term by term, for all queries of a group to which the term is essential;
no other posting is touched. The terms that take away have a bound of 0; they are probed
next, in the vectors and for the queries that still have competitors in the block. The
non-essential terms are probed last, from the largest bound down and pair by pair; a pair
is dropped once what is left cannot lift it. Shards give their k best, and the merge takes
the k best of those, ties going to the smaller id.

Work is dealt by (shard, block of queries), so neither side is collected or broadcast.

Defined cases: vectors that are null, empty, or hold a null or a number that is not finite
take no part; a component that a shorter vector lacks counts as 0; a repeated id is a
candidate for each of its rows, but never for its own id; integer weights must stay below
2**31; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

_LOW = np.iinfo(np.int64).min


@dataclass(frozen=True)
class MaxScore:
    k: int = 5
    scale: int = 256
    shard_rows: int = 4096
    query_rows: int = 2048
    block_rows: int = 512


def quantised(df: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 256) -> DataFrame:
    """``vec_id, w``: floor(scale * x) of each component of the vectors that take part."""
    x = F.transform(F.col(vector_col), lambda v: v.cast("double"))
    fine = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    return (
        df.select(F.col(id_col).cast("long").alias("vec_id"), x.alias("x"), fine.alias("fine"))
        .filter("vec_id is not null and x is not null and size(x) > 0 and fine")
        .select("vec_id", F.transform("x", lambda v: F.floor(v * scale).cast("long")).alias("w"))
    )


class Block:
    """Some vectors: their weights, the postings of each term, and the largest weight in each."""

    def __init__(self, ids: np.ndarray, weights: np.ndarray):
        self.ids, self.weights = ids, weights
        self.high, self.low = np.maximum(weights.max(0), 0), np.minimum(weights.min(0), 0)
        self.postings = []
        for column in weights.T:
            own = [np.flatnonzero(column > 0), np.flatnonzero(column < 0)]
            self.postings.append([(docs, column[docs]) for docs in own])
        self.visited = 0

    def _walk(self, queries: np.ndarray, essential: np.ndarray) -> np.ndarray:
        """What the postings of the essential terms add, a row for each vector and a column for each query."""
        score = np.zeros((len(self.ids), len(queries)), queries.dtype)
        for i, both in enumerate(self.postings):
            for sign, (docs, weights) in enumerate(both):
                asked = np.flatnonzero(essential[:, i] & ((queries[:, i] < 0) if sign else (queries[:, i] > 0)))
                if len(docs) and len(asked):
                    self.visited += len(docs) * len(asked)
                    if len(asked) == len(queries):
                        score[docs] += weights[:, None] * queries[None, :, i]
                    else:
                        score[np.ix_(docs, asked)] += weights[:, None] * queries[None, asked, i]
        return score

    def search(self, queries: np.ndarray, threshold: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Places of queries, places of vectors and scores, of all pairs that score at least the query's threshold."""
        gain = np.maximum(queries * self.high, queries * self.low)
        order = np.argsort(-gain, axis=1, kind="stable")
        by_bound = np.take_along_axis(gain, order, 1)
        # most that the terms from a place on can add
        rest = np.concatenate((np.cumsum(by_bound[:, ::-1], axis=1)[:, ::-1], np.zeros((len(queries), 1), gain.dtype)), axis=1)
        able = np.flatnonzero(rest[:, 0] >= threshold)
        if not len(able):
            return able, able, rest[:0, 0]
        queries, order, rest, threshold = (x[able] for x in (queries, order, rest, threshold))
        done = np.minimum((rest >= threshold[:, None]).sum(1), order.shape[1])  # number of essential terms
        place = np.argsort(order, axis=1)  # of each term in its query's order
        score = self._walk(queries, place < done[:, None])
        left = rest[np.arange(len(done)), done]
        # without a posting in an essential term a vector cannot reach a threshold above 0
        alive = ((score > 0) | (threshold <= 0)) & (score + left >= threshold)
        d, q = np.flatnonzero(alive.any(1)), np.flatnonzero(alive.any(0))
        if not len(d):
            return able[:0], able[:0], rest[:0, 0]
        own, asked = self.weights[d], queries[q]
        taken = np.maximum(own, 0) @ np.minimum(asked, 0).T + np.minimum(own, 0) @ np.maximum(asked, 0).T
        score, alive = score[np.ix_(d, q)] + taken, alive[np.ix_(d, q)]
        at, of = np.nonzero(alive & (score + left[q] >= threshold[q]))
        total, d, q = score[at, of], d[at], q[of]
        for p in range(int(done.min()), order.shape[1]):
            if not len(q):
                break
            t = order[q, p]
            more = np.maximum(queries[q, t] * self.weights[d, t], 0)
            total = total + np.where(p >= done[q], more, 0)
            keep = total + rest[q, np.maximum(p + 1, done[q])] >= threshold[q]
            q, d, total = q[keep], d[keep], total[keep]
        return able[q], d, total


def best(group: np.ndarray, ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of the ``k`` best of each group, the groups ascending, ties to the smaller id."""
    order = np.lexsort((ids, -scores, group))
    first = np.searchsorted(group[order], group[order], "left")
    return order[np.arange(len(order)) - first < k]


def _matrix(rows: pd.Series, width: int) -> np.ndarray:
    lengths = rows.map(len).to_numpy()
    if len(rows) and (lengths == width).all():
        return np.concatenate(rows.to_list()).reshape(-1, width).astype(np.int64)
    out = np.zeros((len(rows), width), np.int64)
    for i, r in enumerate(rows):
        out[i, : len(r)] = r
    return out


def _search_shard(corpus: pd.DataFrame, queries: pd.DataFrame, cfg: MaxScore) -> pd.DataFrame:
    if not len(corpus) or not len(queries):
        return pd.DataFrame({n: pd.Series(dtype="int64") for n in ("query_id", "vec_id", "score")})
    width = max(max(map(len, corpus["w"])), max(map(len, queries["w"])))
    ids, weights = corpus["vec_id"].to_numpy(), _matrix(corpus["w"], width)
    asked, query_ids = _matrix(queries["w"], width), queries["vec_id"].to_numpy()
    if float(np.abs(weights).max(initial=0)) * float(np.abs(asked).max(initial=0)) * width < 2.0**52:
        weights, asked = weights.astype(np.float64), asked.astype(np.float64)  # whole numbers, still exact, and fast
    n = len(asked)
    q, v, s = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, asked.dtype)
    # small blocks first: they give a threshold before much is compared
    cuts = [0, *(c for c in (cfg.block_rows // 8, cfg.block_rows // 2) if 0 < c < len(ids))]
    cuts += range(cuts[-1] + cfg.block_rows, len(ids), cfg.block_rows)
    for i, j in zip(cuts, [*cuts[1:], len(ids)], strict=True):
        block = Block(ids[i:j], weights[i:j])
        threshold = np.full(n, _LOW // 4, asked.dtype)
        filled = np.bincount(q, minlength=n) == cfg.k
        if len(q):
            least = np.full(n, np.inf) if asked.dtype == np.float64 else np.full(n, np.iinfo(np.int64).max)
            np.minimum.at(least, q, s)
            threshold[filled] = least[filled]
        more_q, d, more_s = block.search(asked, threshold)
        own = block.ids[d] != query_ids[more_q]
        q, v, s = np.concatenate((q, more_q[own])), np.concatenate((v, block.ids[d][own])), np.concatenate((s, more_s[own]))
        kept = best(q, v, s, cfg.k)
        q, v, s = q[kept], v[kept], s[kept]
    return pd.DataFrame({"query_id": query_ids[q], "vec_id": v, "score": s.astype(np.int64)})


def top_k(corpus: DataFrame, queries: DataFrame, cfg: MaxScore | None = None) -> DataFrame:
    """``query_id, rank, vec_id, score``: the ``k`` best of ``corpus`` for each row of ``queries`` (both from :func:`quantised`)."""
    cfg = cfg or MaxScore()
    sizes = corpus.agg(F.count("*").alias("n")).crossJoin(queries.agg(F.count("*").alias("q"))).first()
    shards, groups = max(1, -(-sizes["n"] // cfg.shard_rows)), max(1, -(-sizes["q"] // cfg.query_rows))
    # the row's hash deals rows out evenly whatever the ids are; each side goes to every block of the other
    dealt = corpus.withColumn("shard", F.pmod(F.xxhash64("vec_id", "w"), F.lit(shards))).withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
    asked = queries.withColumn("block", F.pmod(F.xxhash64("vec_id", F.lit(3)), F.lit(groups))).withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1)).cast("array<long>")))
    keys = [F.col("shard").cast("long"), F.col("block").cast("long")]
    found = (
        dealt.select(keys[0].alias("shard"), keys[1].alias("block"), "vec_id", "w").groupBy("shard", "block")
        .cogroup(asked.select(keys[0].alias("shard"), keys[1].alias("block"), "vec_id", "w").groupBy("shard", "block"))
        .applyInPandas(lambda a, b: _search_shard(a, b, cfg), "query_id long, vec_id long, score long")
    )
    w = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= cfg.k).select("query_id", "rank", "vec_id", "score")


def neighbours(df: DataFrame, every: int = 50, cfg: MaxScore | None = None) -> DataFrame:
    """Nearest neighbours of the rows whose id is divisible by ``every``, among all rows."""
    cfg = cfg or MaxScore()
    rows = quantised(df, scale=cfg.scale)
    return top_k(rows, rows.filter(F.col("vec_id") % every == 0), cfg)


def oracle(every: int = 50, k: int = 5, scale: int = 256) -> str:
    return f"""
    WITH q AS (SELECT vec_id, list_transform(embedding, lambda x: floor({scale} * x::DOUBLE)::BIGINT) AS w FROM embeddings
               WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x::DOUBLE))) = 0),
    e AS (SELECT vec_id, unnest(range(1, len(w) + 1)) AS i, unnest(w) AS v FROM q),
    s AS (SELECT a.vec_id AS query_id, b.vec_id, sum(a.v * b.v)::BIGINT AS score
          FROM e a JOIN e b ON a.i = b.i AND a.vec_id % {every} = 0 AND a.vec_id <> b.vec_id GROUP BY ALL),
    r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score FROM s)
    SELECT query_id, rank, vec_id, score FROM r WHERE rank <= {k}"""
