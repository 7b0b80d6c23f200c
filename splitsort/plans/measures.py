"""What is measured: efficiency, stage shares, timelines, amplification, lines touched."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def io_efficiency(ops: DataFrame, peak: float) -> DataFrame:
    """Ideal seconds (bytes at peak bandwidth, in bytes a nanosecond) over seconds taken, by operation."""
    ideal = F.col("bytes") / peak / 1e9
    return ops.withColumn("ideal_s", ideal).withColumn("efficiency", ideal / F.col("seconds"))


def shares(ops: DataFrame) -> DataFrame:
    """Seconds of each operation and its share of its system's total."""
    total = Window.partitionBy("system")
    return ops.withColumn("share", F.col("seconds") / F.sum("seconds").over(total))


def timeline(ops: DataFrame) -> DataFrame:
    """Operations of a system one after the other: running start and end."""
    order = Window.partitionBy("system").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    start = F.coalesce(F.sum("seconds").over(order), F.lit(0.0))
    return ops.withColumn("start_s", start).withColumn("end_s", start + F.col("seconds"))


def buckets(line: DataFrame, count: int) -> DataFrame:
    """Bytes of each operation in ``count`` equal slices of its system's time."""
    whole = F.max("end_s").over(Window.partitionBy("system"))
    t = line.withColumn("slice", whole / count).withColumn("bucket", F.explode(F.sequence(F.lit(0), F.lit(count - 1))))
    lo, hi = F.col("bucket") * F.col("slice"), (F.col("bucket") + 1) * F.col("slice")
    overlap = F.greatest(F.least("end_s", hi) - F.greatest("start_s", lo), F.lit(0.0))
    t = t.withColumn("part", F.col("bytes") * overlap / F.col("seconds")).where("part > 0")
    return t.groupBy("system", "bucket", "op").agg(F.sum("part").alias("bytes"), F.first("slice").alias("slice_s"))


def amplification(needed: Column, block: int) -> Column:
    """Bytes read in whole blocks over bytes needed."""
    return F.ceil(needed / block) * block / needed


def lines_touched(start: Column, size: Column, line: int) -> Column:
    """Lines of a device that one access spans."""
    return F.floor((start + size - 1) / line) - F.floor(start / line) + 1
