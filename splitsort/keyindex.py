"""Building a slim index: the key of each record and where the record lies."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .records import RecordSpec
from .sources import register_formats, with_locator
from .sources.fixedrec import STRIDE_GAP, split_ranges

__all__ = ["build_fixed", "build_klv", "build_parquet", "counters", "split_ranges"]


def _fixed(spark: SparkSession, path: str, spec: RecordSpec, **options):
    register_formats(spark)
    return spark.read.format("fixedrec").options(path=path, keyBytes=spec.key_bytes, valueBytes=spec.value_bytes, **options)


def build_fixed(spark: SparkSession, path: str, spec: RecordSpec, access: str = "strided", readers: int = 0, stride_gap: int = STRIDE_GAP) -> DataFrame:
    """``(key, file_id, pos)`` of fixed records; locators are computed, not read.

    ``strided`` needs keys only, and reads nothing else where values are as long as ``stride_gap``; shorter
    ones are read over.  ``sequential`` loads whole records and drops the values.
    """
    return _fixed(spark, path, spec, access=access, readers=readers, strideGap=stride_gap).load()


def counters(spark: SparkSession, path: str, spec: RecordSpec, access: str = "strided", stride_gap: int = STRIDE_GAP) -> DataFrame:
    """Bytes needed, bytes read and requests of the index load, one row for each reader."""
    return _fixed(spark, path, spec, access=access, counters="true", strideGap=stride_gap).load()


def records(spark: SparkSession, path: str, spec: RecordSpec) -> DataFrame:
    """Whole fixed records with their locators."""
    return _fixed(spark, path, spec, access="full").load()


def build_klv(spark: SparkSession, path: str, spec: RecordSpec, anchors: bool = True, value: bool = False, task_bytes: int = 64 << 20) -> DataFrame:
    """``(key, vlength, file_id, pos)`` of length-prefixed records, ``pos`` the value's byte offset.

    Without anchors each file is walked by one task from its start.
    """
    register_formats(spark)
    options = {"path": path, "keyBytes": spec.key_bytes, "anchors": str(anchors).lower(), "value": str(value).lower(), "taskBytes": task_bytes}
    return spark.read.format("klvrec").options(**options).load()


def build_parquet(df: DataFrame, key: Column) -> DataFrame:
    """``(key, file_path, row_index)`` of a Parquet scan: only the key's columns are read."""
    return with_locator(df).select(key.alias("key"), "file_path", "row_index")
