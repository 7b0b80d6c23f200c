"""Split sort: one pass where the slim index fits its memory budget, two passes beyond it."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import gather, keyindex, merge
from .plans.concurrency import ConcurrencyPlan
from .records import RecordSpec
from .session import new_path, staged
from .sources import files, write_fixed

#: Slim bytes that one sorted partition should hold, entries under which another task isn't worth it, bytes for one task alone.
PARTITION_BYTES, LEAST_ENTRIES, SINGLE_BYTES = 64 << 20, 10_000, 1 << 30


@dataclass(frozen=True)
class SortPlan:
    mode: str
    runs: int
    index_bytes: int
    records_per_run: int


def choose_mode(n: int, spec: RecordSpec, budget: int) -> SortPlan:
    """One pass iff the index fits ``budget``, the bytes granted to the index alone; else runs of equal counts.

    A run holds whole entries: where equal counts would be over the budget by a part of one, there is a run more.
    """
    index = n * spec.entry_bytes
    if index <= budget:
        return SortPlan("one_pass", 1, index, n)
    runs = -(-n // max(1, budget // spec.entry_bytes))
    return SortPlan("two_pass", runs, index, -(-n // runs))


def sort_index(idx: DataFrame, parts: int | None = None) -> DataFrame:
    """The slim index in ranges of the key, sorted inside; the locator breaks ties and so splits heavy keys."""
    by = ["key", *[c for c in ("file_id", "pos", "file_path", "row_index") if c in idx.columns]]
    ranged = idx.repartitionByRange(parts, *by) if parts else idx.repartitionByRange(*by)
    return ranged.sortWithinPartitions(*by)


def with_global_rank(ordered: DataFrame, name: str = "ranked") -> DataFrame:
    """Rows of range-partitioned, sorted ``ordered`` with ``rank`` from 1, without a one-partition window.

    The order is written once, each row with its partition and place; counts by partition, as many rows as
    partitions, become starting ranks on the driver.
    """
    placed = staged(ordered.withColumn("__m", F.monotonically_increasing_id()), name)
    part, place = F.shiftright("__m", 33), F.col("__m").bitwiseAND(F.lit((1 << 33) - 1))
    sizes = sorted((r[0], r[1]) for r in placed.groupBy(part.alias("p")).agg(F.max(place) + 1).collect())
    starts, total = [], 0
    for p, n in sizes:
        starts.append((p, total))
        total += n
    at = ordered.sparkSession.createDataFrame(starts or [(0, 0)], "__p long, __s long")
    return placed.join(F.broadcast(at), part == F.col("__p")).withColumn("rank", F.col("__s") + place + 1).drop("__m", "__p", "__s")


def partitions_for(spark: SparkSession, n: int, spec: RecordSpec) -> int:
    """Ranges of a slim index of ``n`` entries: PARTITION_BYTES each, and as many as there are slots if it is small."""
    slots = spark.sparkContext.defaultParallelism
    return max(-(-n * spec.entry_bytes // PARTITION_BYTES), min(slots, -(-n // LEAST_ENTRIES)), 1)


def records_in(path: str, spec: RecordSpec) -> int:
    return sum(size for _, size in files.listed(path, ".rec")) // spec.record_bytes


def _fetch_options(plan: ConcurrencyPlan | None, policy: str, read_pool: int) -> dict:
    if plan is None:
        return {"policy": policy, "read_pool": read_pool}
    return {"policy": plan.policy, "read_pool": plan.threads("read_random", read_pool)}


def one_pass(
    spark: SparkSession,
    path: str,
    spec: RecordSpec,
    access: str = "strided",
    pools: int | None = None,
    buffered: bool = True,
    policy: str = "no_sync",
    read_pool: int = gather.READ_POOL,
    plan: ConcurrencyPlan | None = None,
    stride_gap: int = keyindex.STRIDE_GAP,
    gap_bytes: int = gather.GAP_BYTES,
    refetch_key: bool = False,
) -> DataFrame:
    """``(rank, key, value)`` of fixed records: index, sort, rank, fetch each value once.

    ``plan``, if given, sets the policy, the threads that read values, and as many tasks as it has threads for writing.
    ``pools`` 1 sorts in one task, for an index of at most SINGLE_BYTES.
    """
    n = records_in(path, spec)
    if pools == 1 and n * spec.entry_bytes > SINGLE_BYTES:
        raise ValueError(f"an index of {n * spec.entry_bytes} bytes isn't sorted by one task")
    ranked = with_global_rank(sort_index(keyindex.build_fixed(spark, path, spec, access, stride_gap=stride_gap), pools or partitions_for(spark, n, spec)))
    if plan is not None:
        ranked = ranked.coalesce(plan.threads("write_seq", ranked.rdd.getNumPartitions()))
    options = _fetch_options(plan, policy, read_pool)
    got = gather.point_fetch(ranked, path, spec, batch_bytes=gather.BATCH_BYTES if buffered else 0, gap_bytes=gap_bytes, refetch_key=refetch_key, **options)
    return got.select("rank", "key", "value")


def write_sorted_records(spark: SparkSession, path: str, spec: RecordSpec, out: str) -> None:
    """One-pass sort into record files whose order is that of the ranks: the slim index is dealt by rank, values go from file to file."""
    n = records_in(path, spec)
    parts = partitions_for(spark, n, spec)
    ranked = with_global_rank(sort_index(keyindex.build_fixed(spark, path, spec), parts))
    dealt = ranked.repartitionById(parts, F.floor((F.col("rank") - 1) * parts / max(1, n)).cast("int")).sortWithinPartitions("rank")
    write_fixed(gather.point_fetch(dealt, path, spec), out, spec)


def write_runs(idx: DataFrame, plan: SortPlan, order: Column, parts: int | None = None, compression: str = "zstd", path: str = "") -> str:
    """Sorted slim runs in folders ``run=r/range_id=g``; ``order`` numbers the records from 0.

    All runs are made by one job: one range partitioning gives all runs the same cuts.
    """
    out = path or new_path(idx.sparkSession, "runs")
    by = ["key", "file_id", "pos"]
    marked = idx.withColumn("run", F.floor(order / plan.records_per_run).cast("int"))
    ranged = marked.repartitionByRange(parts, *by) if parts else marked.repartitionByRange(*by)
    ranged = ranged.withColumn("range_id", F.spark_partition_id()).sortWithinPartitions("run", "range_id", *by)
    ranged.write.mode("overwrite").option("compression", compression).partitionBy("run", "range_id").parquet(out)
    return out


def next_phase(spark: SparkSession, runs: str, fan_in: int) -> str:
    """Neighbouring runs merged ``fan_in`` at a time into new ones, range by range."""
    out, by = new_path(spark, "phase"), ["key", "file_id", "pos"]
    grouped = spark.read.parquet(runs).withColumn("run", F.floor(F.col("run") / fan_in).cast("int"))
    grouped = grouped.repartition("run", "range_id").sortWithinPartitions("run", "range_id", *by)
    grouped.write.partitionBy("run", "range_id").parquet(out)
    return out


def record_number(path: str, spec: RecordSpec) -> Column:
    """The number of a fixed record over all files, from its locator."""
    base, total = F.lit(None).cast("long"), 0
    for i, (_, size) in enumerate(files.listed(path, ".rec")):
        base, total = F.when(F.col("file_id") == i, F.lit(total)).otherwise(base), total + size // spec.record_bytes
    return base + F.col("pos")


def locators(numbered: DataFrame, path: str, spec: RecordSpec) -> DataFrame:
    """``numbered`` with the ``file_id`` and ``pos`` that its record ``number`` stands for."""
    file_id, base, total = F.lit(0), F.lit(0).cast("long"), 0
    for i, (_, size) in enumerate(files.listed(path, ".rec")):
        here = F.col("number") >= total
        file_id, base, total = F.when(here, F.lit(i)).otherwise(file_id), F.when(here, F.lit(total)).otherwise(base), total + size // spec.record_bytes
    return numbered.withColumn("file_id", file_id).withColumn("pos", F.col("number") - base).drop("number")


def merged(spark: SparkSession, runs: str, fan_in: int, count: int, extra: str = "", buffer_entries: int = merge.BUFFER_ENTRIES) -> DataFrame:
    """Ranked entries of ``count`` runs under ``runs``, brought down to ``fan_in`` of them first."""
    while count > fan_in:
        runs, count = next_phase(spark, runs, fan_in), -(-count // fan_in)
    sizes = sorted((r[0], r[1]) for r in spark.read.parquet(runs).groupBy("range_id").count().collect())
    starts, total = [], 0
    for g, n in sizes:
        starts.append((g, total))
        total += n
    at = F.broadcast(spark.createDataFrame(starts or [(0, 0)], "range_id int, __s long"))
    ranges = max((g for g, _ in sizes), default=-1) + 1
    entries = merge.merge_runs(spark, runs, count, ranges, extra, buffer_entries)
    return entries.join(at, "range_id").withColumn("rank", F.col("__s") + F.col("i") + 1).drop("__s", "i", "range_id")


def two_pass(
    spark: SparkSession,
    path: str,
    spec: RecordSpec,
    budget: int,
    access: str = "strided",
    parts: int | None = None,
    fan_in: int = 1000,
    compression: str = "zstd",
    batch_bytes: int = gather.BATCH_BYTES,
    policy: str = "no_sync",
    read_pool: int = gather.READ_POOL,
    plan: ConcurrencyPlan | None = None,
    stride_gap: int = keyindex.STRIDE_GAP,
    gap_bytes: int = gather.GAP_BYTES,
) -> DataFrame:
    """``(rank, key, value)``: slim runs written, merged range by range, values fetched last."""
    n = records_in(path, spec)
    if parts == 1 and n * spec.entry_bytes > SINGLE_BYTES:
        raise ValueError(f"an index of {n * spec.entry_bytes} bytes isn't sorted by one task")
    if not n:
        return one_pass(spark, path, spec)
    runs_of = choose_mode(n, spec, budget)
    idx = keyindex.build_fixed(spark, path, spec, access, stride_gap=stride_gap)
    runs = write_runs(idx, runs_of, record_number(path, spec), parts or partitions_for(spark, n, spec), compression)
    ranked = merged(spark, runs, fan_in, runs_of.runs, buffer_entries=max(1, budget // spec.entry_bytes))
    options = _fetch_options(plan, policy, read_pool)
    return gather.point_fetch(ranked, path, spec, batch_bytes, gap_bytes, **options).select("rank", "key", "value")


def sort_records(spark: SparkSession, path: str, spec: RecordSpec, budget: int) -> DataFrame:
    """Whichever mode the budget allows."""
    return one_pass(spark, path, spec) if choose_mode(records_in(path, spec), spec, budget).mode == "one_pass" else two_pass(spark, path, spec, budget)


def klv_runs(spark: SparkSession, path: str, spec: RecordSpec, budget: int, anchors: bool = True) -> tuple[str, SortPlan]:
    """Slim runs of length-prefixed records, none of more entries than the budget holds.

    Only a scan can number such records: the index is written once, in the order of the input, and numbered from the counts of
    its partitions.
    """
    idx = staged(keyindex.build_klv(spark, path, spec, anchors).withColumn("m", F.monotonically_increasing_id()), "klv-index")
    part = F.shiftright("m", 33)
    sizes = sorted((r[0], r[1]) for r in idx.groupBy(part.alias("p")).count().collect())
    starts, total = [], 0
    for p, n in sizes:
        starts.append((p, total))
        total += n
    at = F.broadcast(spark.createDataFrame(starts or [(0, 0)], "p long, s long"))
    plan = choose_mode(total, spec, budget)
    number = F.col("s") + F.col("m").bitwiseAND(F.lit((1 << 33) - 1))
    numbered = idx.join(at, part == F.col("p")).select("key", "vlength", "file_id", "pos", number.alias("number"))
    marked = numbered.withColumn("number", F.floor(F.col("number") / F.lit(max(1, plan.records_per_run))))
    runs = write_runs(marked, SortPlan(plan.mode, plan.runs, plan.index_bytes, 1), F.col("number"), partitions_for(spark, total, spec))
    return runs, plan


def sort_klv(spark: SparkSession, path: str, spec: RecordSpec, budget: int | None = None, anchors: bool = True) -> DataFrame:
    """``(rank, key, vlength, value)`` of length-prefixed records, in one pass or two."""
    if budget is None:
        ranked = with_global_rank(sort_index(keyindex.build_klv(spark, path, spec, anchors)))
    else:
        runs, plan = klv_runs(spark, path, spec, budget, anchors)
        ranked = merged(spark, runs, 1000, plan.runs, "vlength int", max(1, budget // spec.entry_bytes))
    return gather.point_fetch(ranked, path, spec).select("rank", "key", "vlength", "value")


def order_by(df: DataFrame, cols: list[Column], carry: DataFrame | None = None, ids: list[str] | None = None) -> DataFrame:
    """ORDER BY on any columns with ``rank``; with ``ids`` only they and the sort keys go through the sort.

    ``carry`` then gives the other columns of each row, joined back by ``ids``.
    """
    slim = df if ids is None else df.select(*ids, *[c.alias(f"__k{i}") for i, c in enumerate(cols)])
    by = cols if ids is None else [F.col(f"__k{i}") for i in range(len(cols))]
    ranked = with_global_rank(slim.orderBy(*by))
    if carry is None:
        return ranked.drop(*[f"__k{i}" for i in range(len(cols))])
    return carry.join(ranked.select(*ids, "rank"), ids)


def top_k(df: DataFrame, cols: list[Column], k: int, ids: list[str]) -> DataFrame:
    """The first k rows: k slim rows are found first, then only their other columns are fetched."""
    best = df.orderBy(*cols).limit(k).select(*ids)  # pruned to the ids and the sort columns
    return df.join(F.broadcast(best) if k <= gather.BROADCAST_ENTRIES else best, ids, "left_semi")


def top_k_ties(df: DataFrame, col: str, k: int, descending: bool = True) -> DataFrame:
    """Rows at least as high as the k-th: a threshold from k values, then a filter that reaches the scan."""
    c = F.col(col)
    edge = df.select(c).orderBy(c.desc() if descending else c.asc()).limit(k).agg(F.min(c) if descending else F.max(c)).first()[0]
    if edge is None:
        return df.limit(0) if df.isEmpty() else df
    return df.where(c >= F.lit(edge) if descending else c <= F.lit(edge))
