"""Exact deduplication by distributed most-significant-digit radix partitioning.

Documents are split by successive stretches of their UTF-8 bytes.  A group that is down to one
document is settled at once; a group whose texts have ended is settled as equal.  The stretches grow
eightfold, so that a text of n bytes is done in about log8(n) levels, and only groups that still
hold several documents are carried on: unique documents leave at the first level.  Texts are equal
only because every one of their bytes was compared; no digest takes part.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import apart, placed, small, staged, unstage

#: Bytes compared at the first level, the growth of the next ones, and the longest stretch.
FIRST, GROWTH, WIDEST = 64, 8, 1 << 20


def equal_groups(docs: DataFrame, file: str, row: str, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``(file, row, keep_id, group_size, kept)`` of the rows of ``docs``, named by ``placed``, that have an equal.

    Counts of stretches are aggregated before they are shuffled, and written; so the joins with them are plain
    equi-joins of two reads, whose hot keys Spark splits.
    """
    body = F.coalesce(F.encode(F.col(f"`{text}`"), "UTF-8"), F.lit(b""))
    rows = docs.select(F.col(file).alias("f"), F.col(row).alias("r"), F.col(f"`{doc_id}`").alias("id"), body.alias("body"))
    # The first digit is the length, so that all texts of a group end at the same byte.
    rows = rows.select("*", F.octet_length("body").alias("size"), F.substring("body", 1, FIRST).alias("digit"))
    last = F.max(F.struct("id", "f", "r")).alias("last")
    heads = rows.groupBy("size", "digit").agg(F.count("*").alias("n"), last).where("n > 1")
    heads = staged(heads.withColumn("gid", F.monotonically_increasing_id()), "heads")
    live = rows.join(small(heads, heads.count() * 4), ["size", "digit"]).drop("digit")  # wide rows: a quarter as many
    settled: DataFrame | None = None
    at, width, before = FIRST, FIRST * GROWTH, [heads]
    while True:
        live = staged(live.withColumn("body", F.when(F.col("size") > at, F.col("body"))), "radix")
        unstage(*before)
        before = [live]
        ended = live.where(F.col("size") <= at)
        ended = ended.select("f", "r", F.col("last.id").alias("keep_id"), F.col("n").alias("group_size"), ((F.col("f") == F.col("last.f")) & (F.col("r") == F.col("last.r"))).alias("kept"))
        known, settled = settled, staged(ended if settled is None else settled.unionAll(ended), "settled")
        if known is not None:
            unstage(known)
        rest = live.where(F.col("size") > at)
        if rest.isEmpty():
            unstage(live)
            return settled.select(F.col("f").alias(file), F.col("r").alias(row), "keep_id", "group_size", "kept")
        rest = rest.drop("n", "last").withColumn("digit", F.substring("body", at + 1, width))
        groups = rest.groupBy("gid", "digit").agg(F.count("*").alias("n"), last).where("n > 1")
        groups = staged(groups.withColumn("next", F.monotonically_increasing_id()), "groups")
        before.append(groups)
        live = rest.join(small(groups, groups.count() * (1 + width // FIRST)), ["gid", "digit"]).drop("gid", "digit").withColumnRenamed("next", "gid")
        at, width = at + width, min(width * GROWTH, WIDEST)


def exact_dedup(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """All rows and columns of ``docs``, dropped ones too, with ``keep_id``, ``group_size``, ``kept``.

    Of equal texts the row with the largest id stays.  Null text counts as empty, empty texts are
    equal to each other.  A null id is less than any other.  Where several rows share text and
    largest id, exactly one of them (by its place in the files) is ``kept``.  Columns of the input that
    are called like the three new ones are replaced.  An empty table gives an empty result.

    Shuffles: the first level moves the length and the first bytes of each text, aggregated before
    the exchange; rows of groups (and, where their list is too long to broadcast, the table once) move on.
    """
    docs = docs.drop("keep_id", "group_size", "kept")
    file, row = apart(docs, "f", "r")
    rows = placed(docs, file, row)
    groups = equal_groups(rows, file, row, text, doc_id)
    out = rows.join(small(groups, groups.count()), [file, row], "left")
    return out.select(
        *[F.col(f"`{c}`") for c in docs.columns],
        F.when(F.col("group_size").isNull(), F.col(f"`{doc_id}`")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"),
        F.coalesce("kept", F.lit(True)).alias("kept"),
    )


def without_copies(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``docs`` less the rows that ``exact_dedup`` doesn't keep; texts move only where that list is long."""
    file, row = apart(docs, "f", "r", "keep_id", "group_size", "kept")[:2]
    rows = placed(docs, file, row)
    groups = equal_groups(rows, file, row, text, doc_id)
    gone = staged(groups.where("NOT kept").select(file, row), "gone")
    unstage(groups)
    return rows.join(small(gone, gone.count()), [file, row], "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])
