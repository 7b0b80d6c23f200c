"""The sorts that split sort is compared with.  All return ``(rank, key, value)``."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import gather, keyindex, sorter
from .plans.concurrency import exclusive_map
from .records import RecordSpec
from .session import new_path
from .sources import files
from .sources.fixedrec import CHUNK, split_ranges


def wide_merge(spark: SparkSession, path: str, spec: RecordSpec, policy: str = "no_sync", parts: int | None = None, pool: int = 0) -> DataFrame:
    """External merge sort of whole records: the shuffle writes and reads every value, the ranked rows are its output.

    ``exclusive`` loads the runs by a barrier: all tasks of a ``pool`` (as many as there are slots, if 0) read a chunk, and only then
    do all hand theirs to the shuffle, so that no run is written while another is read.
    """
    rows = _exclusive_records(spark, path, spec, pool) if policy == "exclusive" else keyindex.records(spark, path, spec)
    return sorter.with_global_rank(sorter.sort_index(rows, parts), "wide-ranked").select("rank", "key", "value")


def _exclusive_records(spark: SparkSession, path: str, spec: RecordSpec, pool: int) -> DataFrame:
    width, step = spec.record_bytes, max(1, CHUNK // spec.record_bytes)
    found = files.listed(path, ".rec")
    slots = min(pool or spark.sparkContext.defaultParallelism, spark.sparkContext.defaultParallelism)
    chunks = [(i, a, b) for i, (_, size) in enumerate(found) for a, b in split_ranges(size // width, -(-size // width // step))]
    paths = [name for name, _ in found]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                yield batch.slice(k, 1)

    def fetch(chunk: pa.RecordBatch) -> pa.RecordBatch:
        i, a, b = (c[0].as_py() for c in chunk.columns)
        block = np.frombuffer(files.handle(paths[i]).read_at((b - a) * width, a * width), np.uint8).reshape(b - a, width)
        cols = [files.fixed_binary(block[:, : spec.key_bytes]), files.fixed_binary(block[:, spec.key_bytes :])]
        return pa.RecordBatch.from_arrays([*cols, pa.array(np.full(b - a, i, np.int32)), pa.array(np.arange(a, b, dtype=np.int64))], ["key", "value", "file_id", "pos"])

    tasks = spark.createDataFrame(chunks, "file_id int, a long, b long").coalesce(slots)
    return exclusive_map(tasks, cut, fetch, "key binary, value binary, file_id int, pos long")


def wide_in_memory(spark: SparkSession, path: str, spec: RecordSpec) -> DataFrame:
    """Whole records sorted in one pass, for data that fits memory."""
    rows = keyindex.records(spark, path, spec)
    return sorter.with_global_rank(rows.orderBy("key", "file_id", "pos"), "memory-ranked").select("rank", "key", "value")


def splitters(keys: DataFrame, n: int, fanout: int, oversample: int, seed: int = 1) -> tuple[list[bytes], set[bytes]]:
    """Keys that cut a bounded sample of ``keys`` evenly, and those that the sample holds too often to be cut at all."""
    want = fanout * oversample
    got = keys.select("key").sample(min(1.0, 1.2 * want / max(1, n)), seed).limit(2 * want).collect()
    found = sorted(bytes(r[0]) for r in got)
    if not found:
        return [], set()
    cuts = [found[len(found) * k // fanout] for k in range(1, fanout)]
    heavy = {c for c in cuts if cuts.count(c) > 1} or ({found[0]} if found[0] == found[-1] else set())
    return sorted(set(cuts) | heavy), heavy


def classified(df: DataFrame, cuts: list[bytes], equal: set[bytes], width: int) -> DataFrame:
    """``df`` with ``bucket``: 2k for keys between cuts k-1 and k, 2k + 1 for keys equal to a heavy cut k."""
    at = np.array([c + b"\x01" for c in cuts], dtype=f"S{width + 1}")  # a trailing byte keeps zero bytes at a key's end
    heavy = np.array([c in equal for c in cuts] + [False])
    schema = ", ".join(f"`{n}` {t}" for n, t in df.dtypes) + ", bucket int"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys = np.array([k + b"\x01" for k in b.column("key").to_pylist()], dtype=at.dtype)
            right = np.searchsorted(at, keys, "right") if len(at) else np.zeros(len(keys), np.int64)
            same = np.zeros(len(keys), bool)
            if len(at):
                last = np.maximum(right - 1, 0)
                same = (right > 0) & heavy[last] & (at[last] == keys)
            bucket = np.where(same, 2 * (right - 1) + 1, 2 * right)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(bucket.astype(np.int32))], [*b.schema.names, "bucket"])

    return df.mapInArrow(run, schema)


@dataclass
class Classes:
    """Splitters that sampling has settled on, level by level, and what each bucket holds."""

    cuts: list[bytes]
    equal: set[bytes]
    counts: dict[int, int]
    levels: int


def classes(spark: SparkSession, path: str, spec: RecordSpec, oversample: int, fanout: int, bucket_bytes: int, max_levels: int = 12) -> Classes:
    """Sample, classify, and sample again inside each bucket that is over ``bucket_bytes``, until none is.

    A key too frequent to be split gets an equality bucket, which needs no sorting.  Only keys are read; a level
    costs one scan of them, and the driver holds the splitters and one count for each bucket.
    """
    n = sorter.records_in(path, spec)
    keys = keyindex.build_fixed(spark, path, spec)
    cuts, equal = splitters(keys, n, fanout, oversample)
    levels = 1
    while True:
        marked = classified(keys, cuts, equal, spec.key_bytes)
        counts = {r[0]: r[1] for r in marked.groupBy("bucket").count().collect()}
        wide = sorted(b for b, c in counts.items() if b % 2 == 0 and c * spec.record_bytes > bucket_bytes)
        if not wide or levels == max_levels:
            return Classes(cuts, equal, counts, levels)
        new_cuts, new_equal = set(cuts), set(equal)
        share = {b: min(1.0, 1.2 * fanout * oversample / counts[b]) for b in wide}
        got = marked.sampleBy("bucket", share, levels).select("bucket", "key").collect()  # a bounded sample of each wide bucket
        for b in wide:
            found = sorted(bytes(k) for x, k in got if x == b)
            parts = min(fanout, 2 * -(-counts[b] * spec.record_bytes // bucket_bytes))
            mine = [found[len(found) * k // parts] for k in range(1, parts)] if found else []
            new_cuts |= set(mine)
            new_equal |= {c for c in mine if mine.count(c) > 1 or found[0] == found[-1]}
        if new_cuts == set(cuts) and new_equal == equal:
            return Classes(cuts, equal, counts, levels)
        cuts, equal, levels = sorted(new_cuts), new_equal, levels + 1


def sample_sort(
    spark: SparkSession, path: str, spec: RecordSpec, oversample: int = 32, fanout: int = 16, bucket_bytes: int = 64 << 20, device: str = "storage"
) -> DataFrame:
    """Sample sort of whole records: splitters by ``classes``, one partition for each bucket, sorted there.

    Equality buckets over ``bucket_bytes`` are cut by the place of their records.  Spark can't permute a file in place, so records
    move once, whatever the levels; what permuting would cost is a matter of ``plans.cost``.  ``device`` ``memory``
    holds the records in the executors' memory from the start, the point of reference for a sort without a slow device.
    """
    tree = classes(spark, path, spec, oversample, fanout, bucket_bytes)
    n, start, rows = sorter.records_in(path, spec), {}, keyindex.records(spark, path, spec)
    if device == "memory":
        rows = rows.persist(StorageLevel.MEMORY_ONLY)
        rows.count()
    total = 0
    pieces = {b: max(1, -(-c * spec.record_bytes // bucket_bytes)) if b % 2 else 1 for b, c in tree.counts.items()}
    for b in sorted(tree.counts):
        start[b] = total
        total += pieces[b]
    at = F.broadcast(spark.createDataFrame([(b, start[b], pieces[b]) for b in start] or [(0, 0, 1)], "bucket int, s int, pieces int"))
    piece = F.floor(sorter.record_number(path, spec) * F.col("pieces") / max(1, n)).cast("int")
    marked = classified(rows, tree.cuts, tree.equal, spec.key_bytes).join(at, "bucket").withColumn("part", F.col("s") + piece)
    placed = marked.repartitionById(max(1, total), "part").sortWithinPartitions("key", "file_id", "pos")
    return sorter.with_global_rank(placed.select("key", "value", "file_id", "pos"), "buckets").select("rank", "key", "value")


def resorting_key_sort(spark: SparkSession, path: str, spec: RecordSpec) -> DataFrame:
    """Key sort, then a sort by place so that the input is read once in order, then a sort back by rank."""
    ranked = sorter.with_global_rank(sorter.sort_index(keyindex.build_fixed(spark, path, spec)))
    inplace = ranked.select("file_id", "pos", "rank")
    wide = keyindex.records(spark, path, spec)
    joined = wide.join(inplace.hint("merge"), ["file_id", "pos"])
    return joined.repartitionByRange("rank").sortWithinPartitions("rank").select("rank", "key", "value")


def quick_runs(spark: SparkSession, path: str, spec: RecordSpec, plan: sorter.SortPlan) -> str:
    """Slim runs as the earlier splitter makes them: a run's records are loaded whole, its keys sorted by quick sort, one range."""
    out = new_path(spark, "quick-runs")
    idx = keyindex.build_fixed(spark, path, spec, "sequential").withColumn("run", F.floor(sorter.record_number(path, spec) / plan.records_per_run).cast("int"))

    def run(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches)).combine_chunks()  # a run is what the budget holds
        keys = np.array([k + b"\x01" for k in t.column("key").to_pylist()])
        place = t.column("file_id").to_numpy().astype(np.int64) << 40 | t.column("pos").to_numpy()
        order = np.argsort(keys, kind="quicksort")
        same = np.flatnonzero(keys[order][1:] == keys[order][:-1])
        if len(same):  # quick sort isn't stable: equal keys go by place
            order = np.lexsort((place, keys))
        number = key[0].as_py()
        name, draft = f"{out}/run={number}/range_id=0/part.parquet", f"{out}/.draft-{number}-{uuid.uuid4().hex}"
        system, local = files.opened(draft)
        system.create_dir(files.opened(f"{out}/run={number}/range_id=0")[1], recursive=True)
        pq.write_table(t.select(["key", "file_id", "pos"]).take(pa.array(order)), local, filesystem=system)
        files.move(draft, name)
        yield pa.RecordBatch.from_arrays([pa.array([number], pa.int32()), pa.array([len(order)], pa.int64())], ["run", "entries"])

    idx.groupBy("run").applyInArrow(run, "run int, entries long").write.format("noop").mode("overwrite").save()
    return out


def serial_split(spark: SparkSession, path: str, spec: RecordSpec, budget: int, policy: str = "serial", run_sort: str = "sample") -> DataFrame:
    """The earlier splitter: runs load whole records and keep slim entries; values follow one at a time.

    ``serial`` does so in one task, and ``no_sync`` in many, each moving its values straight to the output one by one; ``overlap`` fetches
    by the bufferful into two buffers, one of which is read while the other is handed on.  ``run_sort`` ``quick`` sorts each run by quick
    sort, in memory and in one range, in place of the sampled ranges.
    """
    batch = gather.BATCH_BYTES if policy == "overlap" else 0
    fetch = "overlap" if policy == "overlap" else "no_sync"
    if run_sort == "quick":
        plan = sorter.choose_mode(sorter.records_in(path, spec), spec, budget)
        ranked = sorter.merged(spark, quick_runs(spark, path, spec, plan), 1000, plan.runs, buffer_entries=max(1, budget // spec.entry_bytes))
        return gather.point_fetch(ranked, path, spec, batch, policy=fetch).select("rank", "key", "value")
    return sorter.two_pass(spark, path, spec, budget, access="sequential", parts=1 if policy == "serial" else None, batch_bytes=batch, policy=fetch)


def dataset_bytes(path: str, suffix: str = ".rec") -> int:
    return sum(size for _, size in files.listed(path, suffix))
