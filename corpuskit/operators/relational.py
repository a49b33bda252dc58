"""Relational operators around the methods, each the plan one would want at scale."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def join_equi(left: DataFrame, right: DataFrame, on: list[str] | str | Column, how: str = "inner", hint: str | None = None) -> DataFrame:
    """Equi-join; ``hint`` is merge, broadcast, shuffle_hash or shuffle_replicate_nl. Broadcast only sides of known size."""
    return left.join(right.hint(hint) if hint else right, on, how)


def join_theta(left: DataFrame, right: DataFrame, condition: Column, max_rows: int = 100_000) -> DataFrame:
    """Join on any condition. The right side is broadcast after its size is checked; a larger one is an error, not a cross join."""
    if right.limit(max_rows + 1).count() > max_rows:
        raise ValueError(f"the right side has over {max_rows} rows; give the join a key")
    return left.join(F.broadcast(right), condition)


def join_contains(docs: DataFrame, passages: DataFrame, n: int = 8, small: int = 10_000) -> DataFrame:
    """``contains`` at scale: an equi-join on one n-word shingle of the passage, then the exact test.

    A passage of under ``n + 2`` words has no whole shingle inside; it meets the texts by
    its longest inner word, and one of under three words, which has none, is tested against
    every text. Those few are broadcast behind a check of their number.
    """
    from corpuskit.functions.tokens import ngrams

    words = lambda c: F.regexp_extract_all(F.col(c), F.lit(r"\S+"), F.lit(0))
    p = passages.filter("passage is not null").withColumn("w", words("passage"))
    long_ = p.filter(F.size("w") >= n + 2).withColumn("g", F.array_join(F.slice("w", 2, n), " "))
    inner = F.slice("w", F.lit(2), F.greatest(F.size("w") - 2, F.lit(0)))
    short = p.filter((F.size("w") < n + 2) & (F.size("w") >= 3)).withColumn("g", F.array_max(F.transform(inner, lambda x: F.struct(F.length(x).alias("n"), x.alias("w"))))["w"])
    tiny = p.filter(F.size("w") < 3).select("item_id", "passage")
    texts = docs.filter("text is not null").select("doc_id", "text")
    by = lambda grams, side: texts.select("doc_id", "text", F.explode(F.array_distinct(grams)).alias("g")).join(side, "g")
    met = by(ngrams(words("text"), n), long_).select("doc_id", "text", "item_id", "passage").unionByName(by(words("text"), short).select("doc_id", "text", "item_id", "passage"))
    found = met.filter(F.contains("text", "passage")).select("doc_id", "item_id")
    return found.unionByName(join_theta(texts, tiny, F.contains("text", "passage"), small).select("doc_id", "item_id")).distinct()


def join_range(points: DataFrame, intervals: DataFrame, bin_width: int, point: str = "p", lo: str = "lo", hi: str = "hi", on: list[str] | None = None) -> DataFrame:
    """Points in [lo, hi): an equi-join on bins, then the exact predicate. Each interval goes to the bins that it meets."""
    keys = on or []
    a = points.withColumn("_bin", F.floor(F.col(point) / bin_width))
    spans = F.sequence(F.floor(F.col(lo) / bin_width), F.floor((F.greatest(F.col(hi) - 1, F.col(lo))) / bin_width))
    b = intervals.withColumn("_bin", F.explode(spans))
    return a.join(b, [*keys, "_bin"]).filter((F.col(point) >= F.col(lo)) & (F.col(point) < F.col(hi))).drop("_bin")


def join_interval(left: DataFrame, right: DataFrame, key: str, lt: str, rt: str, within: str) -> DataFrame:
    """Right rows of the same key up to an interval after the left one.

    Time is cut into bins of the interval's length, so rows of a key meet only those of the
    same or the next bin: a hot key is spread over its bins, and no task pairs all of it.
    """
    seconds = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    width = F.expr(f"unix_micros(timestamp'1970-01-02 00:00:00' + INTERVAL {within}) - unix_micros(timestamp'1970-01-02 00:00:00')")
    a = left.withColumn("_bin", F.floor(seconds(lt) / width))
    b = right.withColumn("_bin", F.explode(F.array(F.floor(seconds(rt) / width), F.floor(seconds(rt) / width) - 1)))
    return a.join(b, [key, "_bin"]).filter((F.col(rt) >= F.col(lt)) & (F.col(rt) <= F.col(lt) + F.expr(f"INTERVAL {within}"))).drop("_bin")


def join_asof(left: DataFrame, right: DataFrame, by: list[str], left_ts: str, right_ts: str, value: str) -> DataFrame:
    """The latest right row at or before each left row: one exchange and one sort, no pairs."""
    a = left.withColumns({"_t": F.col(left_ts), "_side": F.lit(1), "_v": F.lit(None)})
    b = right.select(*by, F.col(right_ts).alias("_t"), F.lit(0).alias("_side"), F.struct(F.col(right_ts).alias("ts"), F.col(value).alias("v")).alias("_v"))
    both = a.drop("_v").unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(*by).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("_m", F.last("_v", ignorenulls=True).over(w)).filter("_side = 1").select(*left.columns, F.col("_m.ts").alias(f"asof_{right_ts}"), F.col("_m.v").alias(f"asof_{value}"))


def join_salted(left: DataFrame, right: DataFrame, on: str, salts: int = 8) -> DataFrame:
    """A hot key of the left side is dealt over ``salts`` tasks; the right side is repeated as often."""
    a = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [on, "_salt"]).drop("_salt")


def agg(df: DataFrame, keys: list[str], **aggs: Column) -> DataFrame:
    return df.groupBy(*keys).agg(*[c.alias(n) for n, c in aggs.items()])


def grouping(df: DataFrame, kind: str, keys: list[str], **aggs: Column) -> DataFrame:
    """``rollup`` or ``cube`` with the grouping id."""
    g = getattr(df, kind)(*keys)
    return g.agg(F.grouping_id().cast("int").alias("gid"), *[c.alias(n) for n, c in aggs.items()])


def pivot(df: DataFrame, key: str, column: str, values: list[str], value: Column) -> DataFrame:
    """With explicit values, so no pass over the data is needed to find them."""
    return df.groupBy(key).pivot(column, values).agg(value)


def rank_within(df: DataFrame, by: list[str], order: list[Column], kind: str = "row_number", name: str = "rank") -> DataFrame:
    return df.withColumn(name, getattr(F, kind)().over(Window.partitionBy(*by).orderBy(*order)))


def rolling(df: DataFrame, by: list[str], order: Column | str, lo: int, hi: int, kind: str = "rows", **aggs: Column) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(order)
    w = w.rowsBetween(lo, hi) if kind == "rows" else w.rangeBetween(lo, hi)
    return df.withColumns({n: c.over(w) for n, c in aggs.items()})


def top_k(df: DataFrame, k: int, *order: Column) -> DataFrame:
    return df.orderBy(*order).limit(k)


def top_k_per(df: DataFrame, by: list[str], k: int, *order: Column) -> DataFrame:
    """The window's limit is pushed below the exchange, so each task sends ``k`` rows of a group."""
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).filter(F.col("rank") <= k)


def sketches(df: DataFrame, keys: list[str], column: str) -> DataFrame:
    """Mergeable sketches: distinct count and quantiles of a long column."""
    c = F.col(column).cast("long")
    return df.groupBy(*keys).agg(
        F.approx_count_distinct(c).alias("distinct_hll"), F.hll_sketch_estimate(F.hll_sketch_agg(c)).alias("distinct_sketch"),
        F.percentile_approx(c, 0.5, 10000).alias("median"), F.count_distinct(c).alias("exact"),
    )
