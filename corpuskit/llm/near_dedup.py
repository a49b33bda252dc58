"""Near duplicates by consistent weighted sampling over TF-IDF shingles (operator 3).

1. ``shingle_weights`` counts, over all documents, in how many of them each five-word
   shingle occurs. A first pass counts hashed buckets; every shingle in at least ``floor``
   documents lies in a bucket with that count, so a second pass counts the shingles of
   those buckets alone, exactly. By the choice of the floor there are at most
   ``2 ** (idf_bits - 1)`` such shingles, whatever the corpus; all others are rare and weigh
   the same. A weight is (1 + ln tf) (1 + gain idf), idf between 0 and 1.
2. ``signatures`` draws improved consistent weighted samples from the weighted shingle
   set of each text. Two texts agree in a sample with a probability equal to their
   weighted Jaccard similarity; four samples make a band.
3. Equal texts become one representative. Texts that agree in a band meet in a bucket.
   The members of a bucket are put in an order by hash and each is compared with the next
   one, so a bucket of n members gives n - 1 pairs. Buckets whose members are still in
   different classes are put in other orders for a few rounds. This is the fast way; what
   it leaves is done exactly: in buckets of up to ``crowd`` members every pair across
   classes is compared, and the members of larger ones meet by their rarest shingles,
   which no pair at the threshold can escape (see ``_prefixes``).
4. A pair is a link if its weighted Jaccard similarity over the exact shingle sets is at
   least the threshold.
5. Connected components: every class takes the least label among its neighbours, and
   labels are followed to their own labels; all in tables.

Defined cases: a null text is in a class of its own; empty texts (and texts without
words) are equal only to the same text; equal rows share a class; a repeated id gives a
row each, classed by its own text; a null id is no one's least id unless the class has no
other; only the id and text columns are read; an empty table gives an empty result. Rows
and texts are told apart by a row number and the text's hash, never by the id.
"""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpuskit.llm.common import id_text, slices, small, stored, utf8
from corpuskit.llm.shingles import LOWER, mix, run_hashes, shingle_counts, window_hashes, word_bounds, word_hash_lists

_U = np.uint64


@dataclass(frozen=True)
class NearDedup:
    """``idf_gain`` is what the rarest shingle weighs more than one in all documents. ``floor``
    is the least share of documents of a shingle whose frequency is told from a rare one's.
    ``rounds``, ``crowd`` and ``block`` change the work, not the result."""

    words: int = 5
    threshold: float = 0.8
    bands: int = 12
    rows: int = 4
    idf_gain: float = 0.1
    idf_bits: int = 18
    floor: float = 0.005
    bloom_bits: int = 23
    rounds: int = 3
    crowd: int = 32
    block: int = 256


# --------------------------------------------------------------------------- frequencies


def _bucket_counts(batches: Iterator[pa.RecordBatch], cfg: NearDedup) -> Iterator[pa.RecordBatch]:
    """Document frequencies of one partition, by bucket; one row more, bucket -1, counts the documents."""
    total = np.zeros(1 << cfg.idf_bits, np.int64)
    n, shift = 0, _U(64 - cfg.idf_bits)
    for batch in small(batches, 2048):
        n += batch.num_rows - batch.column(0).null_count
        data, offsets = utf8(batch.column(0))
        for i, j in slices(offsets):
            lists = word_hash_lists(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
            found = [np.unique(window_hashes(w, min(cfg.words, len(w))) >> shift) for w in lists if len(w)]
            if found:
                total += np.bincount(np.concatenate(found).astype(np.int64), minlength=len(total))
    at = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays(
        [pa.array(np.append(at, -1).astype(np.int32)), pa.array(np.append(total[at], n))], ["bucket", "n"]
    )


@dataclass(frozen=True)
class Weights:
    """Inverse document frequency of shingles: ``frequent`` (sorted) have their own, all others are rare."""

    shift: int
    crowded: np.ndarray  # of each bucket, whether a frequent shingle may be in it
    frequent: np.ndarray
    counts: np.ndarray
    idf: np.ndarray
    rare: float

    def places(self, shingles: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which of ``shingles`` are frequent, and where in ``frequent`` they are."""
        maybe = np.flatnonzero(self.crowded[(shingles >> _U(self.shift)).astype(np.int64)])
        if not len(maybe) or not len(self.frequent):
            return maybe[:0], maybe[:0]
        at = np.minimum(np.searchsorted(self.frequent, shingles[maybe]), len(self.frequent) - 1)
        same = self.frequent[at] == shingles[maybe]
        return maybe[same], at[same]

    def of(self, shingles: np.ndarray, counts: np.ndarray) -> np.ndarray:
        out = np.full(len(shingles), self.rare)
        which, at = self.places(shingles)
        out[which] = self.idf[at]
        return out * (1 + np.log(counts))

    def document_counts(self, shingles: np.ndarray) -> np.ndarray:
        """Documents with each shingle, 0 for the rare ones."""
        out = np.zeros(len(shingles), np.int64)
        which, at = self.places(shingles)
        out[which] = self.counts[at]
        return out


def _count_crowded(batches: Iterator[pa.RecordBatch], crowded: np.ndarray, cfg: NearDedup) -> Iterator[pa.RecordBatch]:
    """Documents of one partition with each shingle of the crowded buckets."""
    shift = _U(64 - cfg.idf_bits)
    held, size, total = [], 0, np.zeros((2, 0), _U)

    def folded(parts: list[np.ndarray], total: np.ndarray) -> np.ndarray:
        new, n = np.unique(np.concatenate(parts), return_counts=True) if parts else (total[0][:0], total[1][:0])
        both, at = np.unique(np.concatenate((total[0], new)), return_inverse=True)
        sums = np.bincount(at, weights=np.concatenate((total[1], n)).astype(float), minlength=len(both))
        return np.stack((both, sums.astype(_U)))

    for batch in small(batches, 2048):
        data, offsets = utf8(batch.column(0))
        for i, j in slices(offsets):
            for w in word_hash_lists(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]):
                if len(w):
                    found = window_hashes(w, min(cfg.words, len(w)))
                    found = np.unique(found[crowded[(found >> shift).astype(np.int64)]])
                    if len(found):
                        held.append(found)
                        size += len(found)
            if size > 1_000_000:
                total, held, size = folded(held, total), [], 0
    total = folded(held, total)
    yield pa.RecordBatch.from_arrays([pa.array(total[0].view(np.int64)), pa.array(total[1].astype(np.int64))], ["shingle", "n"])


def shingle_weights(docs: DataFrame, cfg: NearDedup) -> Weights:
    """Weights from the document frequencies of the whole table; what reaches the driver has a bounded size."""
    found = docs.select("text").mapInArrow(lambda b: _bucket_counts(b, cfg), "bucket int, n long")
    rows = found.groupBy("bucket").agg(F.sum("n").alias("n")).toArrow()
    bucket, n = rows["bucket"].to_numpy(), rows["n"].to_numpy()
    many = float(n[bucket == -1].sum()) if len(n) else 0.0
    # at most half as many shingles as there are buckets can reach twice the mean load of a bucket
    floor = max(2.0, cfg.floor * many, 2.0 * float(n[bucket >= 0].sum()) / (1 << cfg.idf_bits))
    crowded = np.zeros(1 << cfg.idf_bits, bool)
    crowded[bucket[(bucket >= 0) & (n >= floor)]] = True
    frequent, counts = np.zeros(0, _U), np.zeros(0, np.int64)
    if crowded.any():
        exact = docs.select("text").mapInArrow(lambda b: _count_crowded(b, crowded, cfg), "shingle long, n long")
        kept = exact.groupBy("shingle").agg(F.sum("n").alias("n")).filter(F.col("n") >= floor).toArrow()
        frequent, counts = kept["shingle"].to_numpy().view(_U), kept["n"].to_numpy()
        order = np.argsort(frequent)
        frequent, counts = frequent[order], counts[order]
    idf = 1 + cfg.idf_gain * np.log((1 + many) / (1 + np.minimum(counts, many))) / np.log(2 + many)
    return Weights(64 - cfg.idf_bits, crowded, frequent, counts, idf, 1 + cfg.idf_gain)


# ---------------------------------------------------------------------------- signatures


def _odd(seed: int, n: int) -> np.ndarray:
    return mix(np.arange(1, n + 1, dtype=_U) * _U(0xA24BAED4963EE407) + _U(seed)) | _U(1)


def weighted_samples(shingles: np.ndarray, log_weights: np.ndarray, first: np.ndarray, k: int) -> np.ndarray:
    """``k`` consistent samples for each set; set *i* is ``shingles[first[i]:first[i + 1]]``, none empty.

    For shingle *s* and sample *j*, r and c are Gamma(2, 1) and b is uniform, all functions
    of (s, j) alone. With t = floor(log w / r + b), the sample is the (s, t) of least
    log c - r (t - b + 1).
    """
    out = np.empty((len(first) - 1, k), _U)
    a, b, c = _odd(1, k), _odd(2, k), _odd(3, k)
    place = np.arange(len(shingles), dtype=_U)
    unit, low = np.float32(2.0**-24), _U(0xFFFFFF)
    turned = shingles ^ (shingles >> _U(29))
    with np.errstate(over="ignore"):
        for j in range(k):
            x, y, z = shingles * a[j], turned * b[j], shingles * c[j]
            y ^= x >> _U(32)
            r = -np.log(((x >> _U(40)).astype(np.float32) + 1) * unit * (((x >> _U(16)) & low).astype(np.float32) + 1) * unit)
            g = -np.log(((y >> _U(40)).astype(np.float32) + 1) * unit * (((y >> _U(16)) & low).astype(np.float32) + 1) * unit)
            r = np.maximum(r, np.float32(1e-6))
            beta = (z >> _U(40)).astype(np.float32) * unit
            t = np.floor(log_weights / r + beta)
            value = np.log(np.maximum(g, np.float32(1e-12))) - r * (t - beta + 1)
            bits = value.view(np.uint32)
            order = np.where(bits >> np.uint32(31), ~bits, bits | np.uint32(1 << 31)).astype(_U)
            best = (np.minimum.reduceat((order << _U(32)) | place, first[:-1]) & _U(0xFFFFFFFF)).astype(np.int64)
            out[:, j] = mix(shingles[best] + t[best].astype(np.int64).view(_U) * _U(0xD1342543DE82EF95))
    return out


def _band_keys(samples: np.ndarray, cfg: NearDedup) -> np.ndarray:
    with np.errstate(over="ignore"):
        key = np.zeros((len(samples), cfg.bands), _U)
        for i in range(cfg.rows):
            key = mix(key * _U(0x2545F4914F6CDD1D) + samples[:, i :: cfg.rows])
        return mix(key + np.arange(cfg.bands, dtype=_U))


def _with_key(docs: DataFrame) -> DataFrame:
    return docs.withColumn("text_key", F.unhex(F.sha2("text", 256)))


def _sign(batches: Iterator[pa.RecordBatch], weights: Weights, cfg: NearDedup) -> Iterator[pa.RecordBatch]:
    for batch in small(batches, 2048):
        data, offsets = utf8(batch.column(1))
        bands = np.zeros((batch.num_rows, cfg.bands), np.int64)
        signed = np.zeros(batch.num_rows, bool)
        for i, j in slices(offsets):
            sets, counts, whose = [], [], []
            for k, w in enumerate(word_hash_lists(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]), i):
                if len(w):
                    s, n = shingle_counts(w, cfg.words)
                    sets.append(s)
                    counts.append(n)
                    whose.append(k)
            if not sets:
                continue
            shingles = np.concatenate(sets)
            first = np.concatenate(([0], np.cumsum([len(s) for s in sets])))
            log_w = np.log(weights.of(shingles, np.concatenate(counts))).astype(np.float32)
            samples = weighted_samples(shingles, log_w, first, cfg.bands * cfg.rows)
            bands[whose] = _band_keys(samples, cfg).view(np.int64)
            signed[whose] = True
        lists = pa.ListArray.from_arrays(
            pa.array(np.arange(batch.num_rows + 1, dtype=np.int32) * cfg.bands), pa.array(bands.ravel()), mask=pa.array(~signed)
        )
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), lists], ["doc_id", "text_key", "bands"])


def signatures(docs: DataFrame, weights: Weights, cfg: NearDedup) -> DataFrame:
    return _with_key(docs).mapInArrow(lambda b: _sign(b, weights, cfg), "doc_id long, text_key binary, bands array<long>")


# --------------------------------------------------------------------------- verification


def _filter_words(ids: np.ndarray, bits: int) -> Iterator[np.ndarray]:
    """Two bit places for each id in a filter of ``2 ** bits`` bits."""
    with np.errstate(over="ignore"):
        h = mix(ids.astype(np.int64).view(_U) + _U(0x9E3779B97F4A7C15))
    yield (h >> _U(64 - bits)).astype(np.int64)
    yield ((h >> _U(8)) & _U((1 << bits) - 1)).astype(np.int64)


def id_filter(ids: DataFrame, bits: int) -> np.ndarray:
    """A Bloom filter of the ``id`` column; its size is fixed, whatever the number of ids."""

    def places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = np.zeros(1 << (bits - 6), np.int64)
        for batch in small(batches, 2048):
            for at in _filter_words(batch.column(0).to_numpy(), bits):
                np.bitwise_or.at(own, at >> 6, np.int64(1) << (at & 63))
        word = np.flatnonzero(own)
        yield pa.RecordBatch.from_arrays([pa.array(word.astype(np.int32)), pa.array(own[word])], ["word", "mask"])

    rows = ids.select("id").mapInArrow(places, "word int, mask long").groupBy("word").agg(F.bit_or("mask").alias("mask")).toArrow()
    out = np.zeros(1 << (bits - 6), np.int64)
    out[rows["word"].to_numpy()] = rows["mask"].to_numpy()
    return out


def _payload(batches: Iterator[pa.RecordBatch], allowed: np.ndarray, bits: int) -> Iterator[pa.RecordBatch]:
    """Compressed texts of the rows whose probe, a hash of id and text, may be among the candidates."""
    squeeze = zstandard.ZstdCompressor(level=3)
    for batch in small(batches, 2048):
        may = np.ones(batch.num_rows, bool)
        for at in _filter_words(batch.column(0).to_numpy(), bits):
            may &= (allowed[at >> 6] >> (at & 63)) & 1 == 1
        picked = batch.filter(pa.array(may))
        data, offsets = utf8(picked.column(1))
        raw = memoryview(data)
        body = [squeeze.compress(raw[offsets[i] : offsets[i + 1]]) for i in range(picked.num_rows)]
        yield pa.RecordBatch.from_arrays([*picked.columns[2:], pa.array(body, pa.binary())], ["doc_id", "text_key", "body"])


def similarity(a: tuple, b: tuple) -> float:
    """Weighted Jaccard similarity of two (shingles, weights) sets, sorted by shingle."""
    (ua, wa), (ub, wb) = (a, b) if len(a[0]) <= len(b[0]) else (b, a)
    if not len(ua):
        return 0.0
    at = np.minimum(np.searchsorted(ub, ua), len(ub) - 1)
    both = ub[at] == ua
    shared = float(np.minimum(wa[both], wb[at[both]]).sum())
    return shared / (float(wa.sum()) + float(wb.sum()) - shared)


def weighted_set(text: bytes, weights: Weights, cfg: NearDedup) -> tuple[np.ndarray, np.ndarray]:
    data = LOWER[np.frombuffer(text, np.uint8)]
    starts, ends, _ = word_bounds(data, np.array([0, len(data)]))
    s, n = shingle_counts(run_hashes(data, starts, ends), cfg.words)
    return s, weights.of(s, n)


def _verify(batches: Iterator[pa.RecordBatch], weights: Weights, cfg: NearDedup) -> Iterator[pa.RecordBatch]:
    open_ = zstandard.ZstdDecompressor()
    kept: OrderedDict[int, tuple] = OrderedDict()
    held = 0

    def of(key: int, body) -> tuple:
        nonlocal held
        if key not in kept:
            kept[key] = weighted_set(open_.decompress(body.as_py()), weights, cfg)
            held += len(kept[key][0])
            while held > 1_000_000 and len(kept) > 2:
                held -= len(kept.popitem(last=False)[1][0])
        kept.move_to_end(key)
        return kept[key]

    for batch in small(batches, 512):
        a, b, left, right = (batch.column(i) for i in range(4))
        alike = np.array([similarity(of(x, left[i]), of(y, right[i])) for i, (x, y) in enumerate(zip(a.to_pylist(), b.to_pylist(), strict=True))], float)
        good = pa.array(alike >= cfg.threshold - 1e-9)
        yield pa.RecordBatch.from_arrays([a.filter(good), b.filter(good), pa.array(alike).filter(good)], ["a", "b", "weighted"])


def verified(pairs: DataFrame, texts: DataFrame, weights: Weights, cfg: NearDedup) -> DataFrame:
    left = texts.select(F.col("id").alias("a"), F.col("body").alias("left"))
    right = texts.select(F.col("id").alias("b"), F.col("body").alias("right"))
    both = pairs.join(left, "a").join(right, "b").select("a", "b", "left", "right")
    return both.mapInArrow(lambda x: _verify(x, weights, cfg), "a long, b long, weighted double")


# ------------------------------------------------------------------------------- classes


def components(links: DataFrame) -> DataFrame:
    """``(id, label)`` for each id in ``links(a, b)``: the least id it is connected with.

    In each round a class, that is all ids of one label, takes the least label next to any
    of its ids, and then the label of that label. So whole classes merge, and the rounds
    grow with the logarithm of a class's size, whatever its shape.
    """
    edges = stored(
        links.select(F.col("a").alias("node"), F.col("b").alias("peer")).union(links.select("b", "a")).distinct(), "edges"
    )
    labels = edges.groupBy(F.col("node").alias("id")).agg(F.least(F.col("id"), F.min("peer")).alias("label"))
    while True:
        labels = stored(labels, "labels")
        near = edges.join(labels.select(F.col("id").alias("peer"), "label"), "peer").groupBy("node").agg(F.min("label").alias("seen"))
        seen = labels.join(near, labels.id == near.node).select("id", "label", "seen")
        least = stored(seen.groupBy("label").agg(F.min("seen").alias("least")).filter("least < label"), "least")
        step = stored(labels.join(least, "label", "left").select("id", F.coalesce("least", "label").alias("label")), "step")
        if least.isEmpty() and labels.join(labels.select(F.col("id").alias("label"), F.col("label").alias("above")), "label").filter("above <> label").isEmpty():
            return labels.select("id", "label")
        jump = step.select(F.col("id").alias("label"), F.col("label").alias("above"))
        labels = step.join(jump, "label", "left").select("id", F.coalesce("above", "label").alias("label"))


def _merge_classes(labels: DataFrame, fresh: DataFrame) -> DataFrame:
    """Labels after further links: only the classes that these join are worked on."""
    of_a = labels.select(F.col("id").alias("a"), F.col("label").alias("la"))
    of_b = labels.select(F.col("id").alias("b"), F.col("label").alias("lb"))
    met = fresh.join(of_a, "a", "left").join(of_b, "b", "left").select(F.coalesce("la", "a").alias("a"), F.coalesce("lb", "b").alias("b"))
    joined = components(met.filter("a <> b").distinct())
    moved = joined.select(F.col("id").alias("was"), F.col("label").alias("now"))
    kept = labels.join(moved, labels.label == moved.was, "left").select("id", F.coalesce("now", "label").alias("label"))
    alone = joined.join(labels.select("id"), "id", "left_anti").select("id", "label")
    return stored(kept.unionByName(alone), "labels")


def _next_pairs(named: DataFrame, cfg: NearDedup, salt: int) -> DataFrame:
    """Each member of a bucket with the next one of another class, in an order by hash.

    A large bucket is dealt into parts of about ``block`` members, so no task sorts all of
    it; the first members of its parts make a second, shorter order.
    """
    rows = named.withColumn("o", F.xxhash64("id", "bucket", F.lit(salt))).withColumn("part", F.pmod(F.xxhash64("o"), _blocks("n", cfg)).cast("int"))
    of_part = Window.partitionBy("bucket", "part").orderBy("o", "id")
    ahead = lambda w: F.lead(F.struct(F.col("id").alias("id"), F.col("label").alias("label"))).over(w)
    placed = stored(rows.select("bucket", "part", "n", "id", "label", F.row_number().over(of_part).alias("k"), ahead(of_part).alias("next")), "placed")
    heads = placed.filter(F.col("n") > cfg.block).filter("k = 1").withColumn("next", ahead(Window.partitionBy("bucket").orderBy("part")))
    met = placed.select("id", "label", "next").unionByName(heads.select("id", "label", "next")).filter("label <> next.label and id <> next.id")
    return met.select(F.least("id", "next.id").alias("a"), F.greatest("id", "next.id").alias("b")).distinct()


def _blocks(of: str, cfg: NearDedup) -> Column:
    """Number of parts of a group of ``of`` rows."""
    return F.ceil(F.col(of) / F.lit(cfg.block)).cast("int")


def _split(buckets: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of the buckets whose members are in different classes, with their labels."""
    named = buckets.select("id", "bucket", "n").join(labels, "id", "left").select("id", "bucket", "n", F.coalesce("label", "id").alias("label"))
    split = named.groupBy("bucket").agg(F.min("label").alias("low"), F.max("label").alias("high")).filter("low <> high").select("bucket")
    return stored(named.join(stored(split, "split"), "bucket"), "buckets")


def _rest_pairs(own: DataFrame, texts: DataFrame, weights: Weights, cfg: NearDedup) -> DataFrame:
    """Every pair across the classes that meet in a bucket, but those of large buckets that cannot be links."""
    left, right = own.filter(F.col("n") <= cfg.crowd), own.select("bucket", F.col("id").alias("b"), F.col("label").alias("lb"))
    pairs = left.join(right, "bucket").filter("id < b and label <> lb").select(F.col("id").alias("a"), "b")
    return pairs.unionByName(_prefix_pairs(own.filter(F.col("n") > cfg.crowd), texts, weights, cfg)).distinct()


def _shingle_rows(batches: Iterator[pa.RecordBatch], weights: Weights, cfg: NearDedup) -> Iterator[pa.RecordBatch]:
    """A row for each shingle of each member: its weight, and its document frequency or 0 if it is rare."""
    open_ = zstandard.ZstdDecompressor()
    for batch in small(batches, 256):
        ids, labels = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        sets = [weighted_set(open_.decompress(body.as_py()), weights, cfg) for body in batch.column(2)]
        at = np.repeat(np.arange(len(sets)), [len(s) for s, _ in sets])
        key, w = (np.concatenate(x) if x else np.zeros(0, t) for x, t in zip(zip(*sets, strict=True), (_U, float), strict=True)) if sets else (np.zeros(0, _U), np.zeros(0))
        arrays = (ids[at], labels[at], key.view(np.int64), w, weights.document_counts(key))
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in arrays], ["id", "label", "key", "w", "docs"])


def _prefixes(own: DataFrame, texts: DataFrame, weights: Weights, cfg: NearDedup) -> DataFrame:
    """The first shingles of each member in order of rarity among the members.

    ``rest`` is the weight of the set from the shingle on, ``whole`` that of all. Sets A and
    B are alike by t only if they share at least t / (1 + t) (A + B). In one order for all,
    what is left of either set at their first shared shingle is at least that, and so at
    least t times the set. A shingle that is frequent in the corpus keeps its count there,
    so no task counts a very common one.
    """
    bodies = own.select("id", "label").distinct().join(texts, "id").select("id", "label", "body")
    rows = bodies.mapInArrow(lambda b: _shingle_rows(b, weights, cfg), "id long, label long, key long, w double, docs long")
    dealt = F.when(F.col("docs") > 0, F.xxhash64("id")).otherwise(0)
    every = rows.withColumn("docs", F.when(F.col("docs") > 0, F.col("docs")).otherwise(F.count("*").over(Window.partitionBy("key", dealt))))
    onward = Window.partitionBy("id").orderBy(F.col("docs").desc(), "key")
    kept = every.withColumns({"rest": F.sum("w").over(onward.rowsBetween(Window.unboundedPreceding, 0)), "whole": F.sum("w").over(Window.partitionBy("id"))})
    least = cfg.threshold - 1e-6
    return kept.filter(F.col("rest") >= least * F.col("whole")).select("id", "label", "key", "rest", "whole")


def _prefix_pairs(own: DataFrame, texts: DataFrame, weights: Weights, cfg: NearDedup) -> DataFrame:
    """Pairs across classes that share a shingle early enough to be links."""
    keyed = stored(_prefixes(own, texts, weights, cfg), "keys")
    by_label = keyed.groupBy("key", "label").agg(F.count("*").alias("n"))
    # the members of a key's largest class need not meet each other: one side is all other members
    of_key = by_label.groupBy("key").agg(F.sum("n").alias("n"), F.count("*").alias("labels"), F.max(F.struct("n", "label")).alias("most")).filter("labels > 1")
    met = stored(keyed.join(of_key.select("key", F.col("most.label").alias("main"), _blocks("n", cfg).alias("blocks")), "key"), "met")
    columns = ("id", "label", "rest", "whole")
    side = lambda df, s: df.select("key", "block", *[F.col(c).alias(f"{c}_{s}") for c in columns])
    other = side(met.filter("label <> main").withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))), "a")
    every = side(met.withColumn("block", F.pmod(F.xxhash64("id"), "blocks").cast("int")), "b")
    least = cfg.threshold - 1e-6
    pairs = other.join(every, ["key", "block"]).filter("label_a <> label_b")
    near = pairs.filter(F.least("rest_a", "rest_b") >= F.lit(least / (1 + least)) * (F.col("whole_a") + F.col("whole_b")))
    return near.select(F.least("id_a", "id_b").alias("a"), F.greatest("id_a", "id_b").alias("b")).distinct()


def _first() -> Column:
    """Order of the rows of a class: least id, null ids last, then the row number."""
    return F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row")


def near_duplicate_links(docs: DataFrame, cfg: NearDedup) -> tuple[DataFrame, DataFrame]:
    """``(signed rows, reps, labels of reps)``; a rep is a row number, and those without a link have no label."""
    weights = shingle_weights(docs, cfg)
    signed = stored(signatures(docs, weights, cfg).withColumn("row", F.monotonically_increasing_id()), "signed")
    reps = stored(
        signed.filter("text_key is not null").groupBy("text_key").agg(F.min(_first()).alias("lead"), F.first("bands").alias("bands"))
        .select("text_key", "lead", F.col("lead.row").alias("rep"), "bands"), "reps"
    )
    buckets = _met(reps.filter("bands is not null").select(F.col("rep").alias("id"), F.explode("bands").alias("bucket")))
    own = buckets.select(F.col("id").alias("rep")).distinct()
    members = stored(reps.join(own, "rep").select(F.col("rep").alias("id"), F.col("lead.doc_id").alias("lead_id"), F.col("text_key").alias("lead_key")), "members")
    allowed = id_filter(members.select(F.xxhash64("lead_id", "lead_key").alias("id")), cfg.bloom_bits)
    probed = _with_key(docs).select(F.xxhash64("doc_id", "text_key").alias("probe"), "text", "doc_id", "text_key")
    bodies = probed.mapInArrow(lambda b: _payload(b, allowed, cfg.bloom_bits), "doc_id long, text_key binary, body binary")
    same = (F.col("text_key") == F.col("lead_key")) & F.col("doc_id").eqNullSafe(F.col("lead_id"))
    texts = stored(bodies.join(members, same).select("id", "body").dropDuplicates(["id"]), "texts")
    # two neighbouring bands together make tight buckets, where a next member is nearly always alike
    both = F.expr(f"transform(sequence(0, {cfg.bands - 1}), i -> xxhash64(i, bands[i], bands[(i + 1) % {cfg.bands}]))")
    tight = _met(reps.filter("bands is not null").select(F.col("rep").alias("id"), F.explode(both).alias("bucket")))
    alone = F.col("id").alias("label")
    seen = stored(_next_pairs(buckets.unionByName(tight).select("id", "bucket", "n", alone), cfg, 0), "pairs")
    links = stored(verified(seen, texts, weights, cfg), "links")
    labels = components(links)
    for turn in range(1, cfg.rounds + 1):
        buckets = _split(buckets, labels)
        last = turn == cfg.rounds
        met = _rest_pairs(buckets, texts, weights, cfg) if last else _next_pairs(buckets, cfg, turn)
        pairs = stored(met.join(seen, ["a", "b"], "left_anti"), "pairs")
        fresh = stored(verified(pairs, texts, weights, cfg), "links")
        seen = seen.unionByName(pairs)
        if not fresh.isEmpty():
            labels = _merge_classes(labels, fresh)
    return signed, reps, labels


def _met(entries: DataFrame) -> DataFrame:
    """Entries of the buckets with more than one member, with that number."""
    crowded = stored(entries.groupBy("bucket").agg(F.count("*").alias("n")).filter("n > 1"), "crowded")
    return stored(entries.join(crowded, "bucket").select("id", "bucket", "n"), "buckets")


def _classes(docs: DataFrame, cfg: NearDedup) -> DataFrame:
    """``doc_id, text_key, row, lead``: the rows, and the first row of the class of each; null texts have no lead."""
    signed, reps, labels = near_duplicate_links(docs, cfg)
    of_text = stored(reps.join(labels, reps.rep == labels.id, "left").select("text_key", "lead", F.coalesce("label", "rep").alias("class")), "named")
    of_class = of_text.groupBy("class").agg(F.min("lead").alias("lead"))
    named = stored(of_text.select("text_key", "class").join(of_class, "class").select("text_key", "lead"), "named")
    return signed.select("doc_id", "text_key", "row").join(named, "text_key", "left")


def near_duplicate_classes(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", cfg: NearDedup | None = None) -> DataFrame:
    """One row for each row of ``df``: ``doc_id, class_id, is_kept``.

    ``class_id`` is the least id of the class, null if all its ids are; ``is_kept`` marks
    one row of each class, one with that id.
    """
    rows = _classes(id_text(df, id_col, text_col), cfg or NearDedup())
    alone = F.col("lead").isNull()
    return rows.select("doc_id", F.when(alone, F.col("doc_id")).otherwise(F.col("lead.doc_id")).alias("class_id"), (alone | (F.col("lead.row") == F.col("row"))).alias("is_kept"))


def keep_one_of_each(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", cfg: NearDedup | None = None) -> DataFrame:
    """One row of ``df`` for each class, all columns as they were; each row without a text is kept.

    Ids may be null or repeated: a row is found again by its id and text, and of rows
    equal in both one stays.
    """
    rows = stored(_classes(id_text(df, id_col, text_col), cfg or NearDedup()), "rows")
    kept = rows.filter(F.col("lead.row") == F.col("row")).select(F.col("text_key").alias("__text"), F.col("doc_id").alias("__id"))
    twice = rows.groupBy("text_key", "doc_id").agg(F.count("*").alias("n")).filter("n > 1 and text_key is not null")
    same = (F.col("text_key") == F.col("__text")) & F.col("doc_id").eqNullSafe(F.col("__id"))
    again = stored(kept.join(twice, same, "left_semi"), "again")
    keyed = df.withColumn("__key", F.unhex(F.sha2(F.col(text_col).cast("string"), 256)))
    at = (F.col("__key") == F.col("__text")) & F.col(id_col).cast("long").eqNullSafe(F.col("__id"))
    if again.isEmpty():
        out = keyed.join(kept, at, "left_semi")
    else:
        out = keyed.join(kept.join(again, ["__text"], "left_anti"), at, "left_semi").unionByName(keyed.join(again, at, "left_semi").dropDuplicates(["__key"]))
    return out.unionByName(keyed.filter("__key is null")).drop("__key")
