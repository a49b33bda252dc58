"""Reading the given tables, and the file formats around the methods."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

TABLES = (
    "region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events",
    "documents", "embeddings", "pages", "benchmark", "labels", "conversations",
)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; Parquet carries its schema, so nothing is inferred and only used columns are read."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tables(spark: SparkSession, sf_dir: str, *names: str) -> dict[str, DataFrame]:
    return {n: read_table(spark, sf_dir, n) for n in names or TABLES}


def sql(spark: SparkSession, sf_dir: str, text: str, **frames: DataFrame) -> DataFrame:
    """``text`` over the tables it names in braces, e.g. ``SELECT count(*) FROM {documents}``."""
    used = {n: read_table(spark, sf_dir, n) for n in TABLES if "{" + n + "}" in text and n not in frames}
    return spark.sql(text, **used, **frames)


def read(spark: SparkSession, path: str, fmt: str, schema: StructType | str | None = None, **options: str) -> DataFrame:
    """Any of parquet, orc, json (plain or compressed), csv, text and binaryFile, with a declared schema."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), **options: str) -> None:
    writer = df.write.format(fmt).options(**options).mode("overwrite")
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def ingest(df: DataFrame, table: str, key: str = "corpus_id", buckets: int = 16, path: str | None = None) -> DataFrame:
    """A bucketed, sorted table: later joins on ``key`` need no exchange. ``path`` puts its files outside the warehouse."""
    writer = df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key)
    (writer.option("path", path) if path else writer).saveAsTable(table)
    return df.sparkSession.table(table)


def release_manifest(spark: SparkSession, path: str) -> DataFrame:
    """Files below ``path`` with sizes and checksums, hashed where they are read."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path)
    return files.select(F.element_at(F.split("path", "/"), -1).alias("file"), F.col("length").alias("bytes"), F.sha2("content", 256).alias("sha256"))


def check_release(spark: SparkSession, manifest: DataFrame, path: str) -> DataFrame:
    """``file, status`` for each file of the pinned manifest or below ``path``: intact, changed, missing or extra."""
    now = release_manifest(spark, path).select("file", F.col("sha256").alias("found"))
    met = manifest.select("file", "sha256").join(now, "file", "full")
    status = F.when(F.col("sha256").isNull(), "extra").when(F.col("found").isNull(), "missing").when(F.col("sha256") == F.col("found"), "intact").otherwise("changed")
    return met.select("file", status.alias("status"))


def read_release(spark: SparkSession, manifest: DataFrame, root: str, schema: str, fmt: str = "json", verify: bool = True) -> DataFrame:
    """The files that a pinned manifest lists; with ``verify``, an error if one of them is missing or not the pinned one.

    The list of files is metadata and small by nature.
    """
    if verify:
        bad = check_release(spark, manifest, root).filter("status in ('changed', 'missing')").limit(5).collect()
        if bad:
            raise ValueError("the release is not the pinned one: " + ", ".join(f"{r['file']} {r['status']}" for r in bad))
    names = [r["file"] for r in manifest.select("file").orderBy("file").collect()]
    return spark.read.schema(schema).format(fmt).load([f"{root}/{n}" for n in names])


def scratch_path(spark: SparkSession, label: str) -> str:
    """A new folder below the one that the cluster names in ``spark.checkpoint.dir``.

    Without that setting a machine-local folder serves, but only if the whole engine runs
    on this machine; other executors could not read it.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = f"{tempfile.gettempdir()}/corpuskit-{os.getuid()}"
    return f"{base.rstrip('/')}/corpuskit/{label}-{uuid.uuid4().hex}"


def stored(df: DataFrame, label: str) -> DataFrame:
    """``df`` written to the scratch folder and read back, which cuts its lineage."""
    path = scratch_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


class _Pages(DataSourceReader):
    """Each page of identifiers is a task; a worker asks the service for the reports on its page alone."""

    def __init__(self, options: dict, service):
        self.rows, self.page, self.service = int(options.get("rows", "100")), int(options.get("page_size", "250")), service

    def partitions(self):
        return [InputPartition(i) for i in range(0, max(self.rows, 1), self.page)]

    def read(self, partition):
        for k in range(partition.value, min(partition.value + self.page, self.rows)):
            yield from ((k, name, raw) for name, raw in self.service(k))


class PagedLicenses(DataSource):
    """A paginated licence lookup behind Spark's Python data source interface.

    ``service(id)`` gives (service, raw string) pairs; the default is a frozen stand-in for
    the live services. Subclasses put another one in its place.
    """

    @classmethod
    def name(cls):
        return "paged_licenses"

    @staticmethod
    def service(k: int) -> list[tuple[str, str]]:
        from corpuskit.sources.adapters import frozen_reports

        return frozen_reports(k)

    def schema(self):
        return "corpus_id long, service string, raw string"

    def reader(self, schema):
        return _Pages(self.options, self.service)
