"""Assembly of one nested record for each paper, its sinks, manifests and exports."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SCHEMA_VERSION = "1"


def assemble(papers: DataFrame, abstracts: DataFrame, texts: DataFrame, chunks: DataFrame, vectors: DataFrame, licenses: DataFrame) -> DataFrame:
    """Records with parallel arrays of passages and vectors in chunk order.

    ``chunks``: corpus_id, chunk_no, chunk_id, text, n_tokens; ``vectors``: chunk_id, vector;
    ``licenses``: corpus_id, license and the three service columns. Only the chunks are
    grouped; one document's chunks are bounded by its own length.
    """
    rows = chunks.join(vectors, "chunk_id", "left")
    one = F.sort_array(F.collect_list(F.struct("chunk_no", "chunk_id", "text", "n_tokens", "vector")))
    passages = rows.groupBy("corpus_id").agg(one.alias("c")).select(
        "corpus_id",
        F.transform("c", lambda x: F.struct(x["chunk_id"].alias("id"), x["text"].alias("text"), x["n_tokens"].alias("n_tokens"))).alias("paragraphs"),
        F.transform("c", lambda x: F.struct(x["chunk_id"].alias("id"), x["vector"].alias("vector"))).alias("paragraph_embeddings"),
    )
    out = papers.join(abstracts, "corpus_id", "left").join(texts.withColumnRenamed("text", "full_text"), "corpus_id").join(passages, "corpus_id").join(licenses, "corpus_id", "left")
    return out.withColumns({"schema_version": F.lit(SCHEMA_VERSION), "filename_id": F.col("corpus_id").cast("string"), "abstract": F.coalesce("abstract", F.lit(""))})


def write_records(df: DataFrame, path: str, fmt: str = "parquet", buckets: int = 8) -> None:
    """Parquet or JSON Lines, laid out by schema version and a hash bucket of the id."""
    rows = df.withColumn("bucket", F.pmod(F.xxhash64("corpus_id"), F.lit(buckets)).cast("int"))
    rows.write.mode("overwrite").partitionBy("schema_version", "bucket").format(fmt).save(path)


def redistributable(df: DataFrame, licenses: DataFrame, allow: tuple[str, ...]) -> DataFrame:
    """Texts that may be passed on under their licence."""
    return df.join(licenses.filter(F.col("license").isin(*allow)).select("corpus_id"), "corpus_id", "left_semi")


def table_hash(df: DataFrame) -> DataFrame:
    """Row count and a checksum that does not depend on row order: the sum of 60 bits of each row's digest."""
    row = F.concat_ws("|", *[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in df.columns])
    bits = F.conv(F.substring(F.md5(row), 1, 15), 16, 10).cast("decimal(38,0)")
    return df.agg(F.count("*").alias("rows"), F.coalesce(F.sum(bits), F.lit(0)).cast("decimal(38,0)").alias("checksum"))


def manifest(named: dict[str, DataFrame], config: str = "") -> DataFrame:
    """Counts and checksums of the tables of a run; two runs over pinned inputs must give the same rows."""
    out = None
    for name, df in named.items():
        row = table_hash(df).select(F.lit(name).alias("name"), "rows", F.col("checksum").cast("string").alias("checksum"), F.sha2(F.lit(config), 256).alias("config"))
        out = row if out is None else out.unionByName(row)
    return out


def diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Entries of two manifests that are not the same."""
    return a.exceptAll(b).withColumn("side", F.lit("left")).unionByName(b.exceptAll(a).withColumn("side", F.lit("right")))


def export_training(chunks: DataFrame, abstracts: DataFrame, seed: int = 42) -> DataFrame:
    """Chunk and abstract pairs with a split that depends on the paper's id alone."""
    from corpuskit.plans.enrich import split

    pairs = chunks.join(abstracts.filter("abstract <> ''"), "corpus_id").select("corpus_id", "chunk_id", F.col("text").alias("passage"), "abstract")
    return split(pairs, seed=seed, key="corpus_id")


def timed(action: Callable[[], object]) -> tuple[object, float]:
    """Result and wall seconds of an action."""
    began = time.perf_counter()
    out = action()
    return out, time.perf_counter() - began
