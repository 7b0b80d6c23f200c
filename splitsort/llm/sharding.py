"""Sharding by a two-pass external shuffle.

Pass one scatters the records uniformly into buckets of bounded memory by a seeded hash.  Pass two
shuffles each bucket by the Fisher-Yates exchange that Spark's ``shuffle`` runs on an array, and
writes it.  Buckets in order, each in its shuffled order, are one random permutation of all records;
dealing it round robin gives shards whose counts are at most one apart.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, repeat_salt, small, staged

#: Bytes of text a bucket holds on average, while a million buckets suffice, and the least number of buckets.
BUCKET_BYTES, LEAST_BUCKETS = 16 << 20, 64
#: Partitions that the buckets are dealt over at most.
MOST_PARTITIONS = 20_000


def shard(
    docs: DataFrame, shards: int = 8, seed: int = 20, text: str = "text", bucket_bytes: int = BUCKET_BYTES
) -> DataFrame:
    """All rows and columns of ``docs`` with ``shard`` (0 to shards-1) and ``slot`` (gapless from 0 in it).

    Law ``rows``: the counts of shards are at most one apart.  The placement depends on the rows'
    content, the seed and the size of the table, not on their order or files (but see
    ``repeat_salt`` for masses of wholly equal rows).  Nulls and empty texts are records like any
    other; an empty table gives an empty result; columns called shard or slot are replaced.

    Shuffles: hashes only for the size of the table, then each record once, into its bucket.  A bucket
    is the unit of memory: ``bucket_bytes`` on average, plus at most one record of any length.
    """
    docs = docs.drop("shard", "slot")
    names = docs.columns
    keys = [F.col(f"`{c}`").cast("string") if t.startswith("map") else F.col(f"`{c}`") for c, t in docs.dtypes]
    n, size = docs.agg(
        F.count("*"), F.coalesce(F.sum(F.coalesce(F.octet_length(F.col(f"`{text}`")), F.lit(0)) + 64), F.lit(0))
    ).first()
    buckets = min(BROADCAST_ROWS, max(LEAST_BUCKETS, -(-int(size) // bucket_bytes)))
    salt = repeat_salt(docs.select(F.xxhash64(*keys).alias("h")), max(1000, n // buckets))
    # The input's columns lie inside one struct, where no name of ours meets theirs.
    record = F.struct(F.xxhash64(F.lit(seed), *keys).alias("o"), F.struct(*[F.col(f"`{c}`") for c in names]).alias("v"))
    scattered = docs.select(F.pmod(F.xxhash64(F.lit(~seed), salt, *keys), F.lit(buckets)).cast("int").alias("b"), record.alias("rec"))
    # A bucket is brought into one order before it is shuffled, whatever order its rows arrived in.
    byorder = F.array_sort(F.collect_list("rec"), lambda x, y: F.when(x["o"] < y["o"], -1).when(x["o"] > y["o"], 1).otherwise(0))
    # The exchange draws from its partition's stream, so partitions and the order of buckets in them are fixed too.
    # One bucket is one partition while that many partitions are sensible, so that no task draws several by chance.
    dealt = scattered.repartitionById(buckets, "b") if buckets <= MOST_PARTITIONS else scattered.repartition(MOST_PARTITIONS, "b")
    gathered = dealt.groupBy("b").agg(byorder.alias("recs"))
    gathered = gathered.sortWithinPartitions("b").select("b", F.size("recs").alias("n"), F.shuffle("recs", seed).alias("recs"))
    written = staged(gathered, "buckets")
    rank = F.col("s") + F.col("i")
    return (
        written.join(small(_starts(written.select("b", "n"), buckets), buckets), "b")
        .select("s", F.posexplode("recs").alias("i", "rec"))
        .select(
            *[F.col(f"rec.v.`{c}`").alias(c) for c in names],
            F.pmod(rank, F.lit(shards)).cast("int").alias("shard"),
            F.floor(rank / shards).cast("long").alias("slot"),
        )
    )


def _starts(counts: DataFrame, buckets: int) -> DataFrame:
    """``(b, s)``: records in all buckets before each one; summed in stretches of buckets, then over stretches."""
    before = (Window.unboundedPreceding, -1)
    counts = counts.withColumn("g", F.floor(F.col("b") / F.lit(max(1, round(buckets**0.5)))))
    inside = F.coalesce(F.sum("n").over(Window.partitionBy("g").orderBy("b").rowsBetween(*before)), F.lit(0))
    groups = counts.groupBy("g").agg(F.sum("n").alias("gn"))
    whole = F.coalesce(F.sum("gn").over(Window.orderBy("g").rowsBetween(*before)), F.lit(0))  # about a thousand rows
    groups = groups.select("g", whole.alias("w"))
    return counts.withColumn("i", inside).join(F.broadcast(groups), "g").select("b", (F.col("w") + F.col("i")).cast("long").alias("s"))


def write_shards(sharded: DataFrame, path: str) -> None:
    """One folder for each shard, files in slot order."""
    sharded.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
