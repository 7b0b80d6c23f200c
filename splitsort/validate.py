"""Is an output sorted, and a permutation of its input?"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def checksum(df: DataFrame, cols: list[str]) -> DataFrame:
    """One row that doesn't depend on order: rows, the exclusive-or and the exact sum of row hashes."""
    h = F.xxhash64(*cols)
    return df.agg(F.count("*").alias("n"), F.coalesce(F.bit_xor(h), F.lit(0)).alias("xor"), F.sum(h.cast("decimal(38,0)")).alias("total"))


def order_violations(ranked: DataFrame, stretch: int = 1_000_000) -> DataFrame:
    """One row: neighbours by rank whose keys descend, and ranks that are missing or doubled.

    Stretches of ranks, of a bounded size, are compared side by side; each also holds the last row of the one before.
    """
    size = max(1, min(stretch, -(-ranked.count() // 200)))
    own = ranked.select("rank", "key", F.floor((F.col("rank") - 1) / size).alias("g"))
    edge = own.where(F.col("rank") % size == 0).withColumn("g", F.col("g") + 1)
    w = Window.partitionBy("g").orderBy("rank")
    pairs = own.unionAll(edge).select("rank", "key", F.lag("key").over(w).alias("k"), F.lag("rank").over(w).alias("r"))
    return pairs.agg(
        F.count(F.when(F.col("key") < F.col("k"), 1)).alias("descents"),
        F.count(F.when(F.col("rank") - F.col("r") != 1, 1)).alias("gaps"),
    )


def is_sorted_permutation(source: DataFrame, ranked: DataFrame, cols: list[str]) -> bool:
    a, b = checksum(source, cols).first(), checksum(ranked, cols).first()
    v = order_violations(ranked).first()
    return a == b and v["descents"] == 0 and v["gaps"] == 0
