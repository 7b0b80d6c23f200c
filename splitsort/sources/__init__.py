"""Tables, readers, sinks and locators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..records import RecordSpec
from .fixedrec import FixedRecords
from .klvrec import KlvRecords

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_tables(spark: SparkSession, sf_dir: str) -> None:
    """All given tables as temporary views."""
    for name in TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def register_formats(spark: SparkSession) -> None:
    spark.dataSource.register(FixedRecords)
    spark.dataSource.register(KlvRecords)


def read(spark: SparkSession, path: str, fmt: str, schema=None, **options) -> DataFrame:
    """CSV, JSON, ORC, text, binaryFile, Parquet, fixedrec or klvrec."""
    register_formats(spark)
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def stream(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def with_locator(df: DataFrame) -> DataFrame:
    """Where each row of a file-based scan lies: costs no extra reading and survives replanning."""
    return df.select("*", F.col("_metadata.file_path").alias("file_path"), F.col("_metadata.row_index").alias("row_index"))


def write_sorted(df: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None, buckets: int = 0, table_name: str = "", **options) -> None:
    """Write partitions in their order; ``by`` makes folders, ``buckets`` a bucketed and sorted table."""
    register_formats(df.sparkSession)
    writer = df.write.format(fmt).options(**options)
    if buckets:
        writer.bucketBy(buckets, *by).sortBy(*by).option("path", path).saveAsTable(table_name)
        return
    (writer.partitionBy(*by) if by else writer).mode("append").save(path)


def write_fixed(df: DataFrame, path: str, spec: RecordSpec) -> None:
    register_formats(df.sparkSession)
    out = df.select("key", "value").write.format("fixedrec").mode("append")
    out.options(keyBytes=spec.key_bytes, valueBytes=spec.value_bytes).save(path)


def write_klv(df: DataFrame, path: str, spec: RecordSpec, anchors: int = 1000) -> None:
    register_formats(df.sparkSession)
    df.select("key", "value").write.format("klvrec").mode("append").options(keyBytes=spec.key_bytes, anchors=anchors).save(path)
