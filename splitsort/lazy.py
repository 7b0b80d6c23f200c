"""Using a slim index without sorting everything: ranges on demand, joins, late values."""

from __future__ import annotations

import bisect
import os
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import gather, sorter
from .sources import files


def range_rows(idx: DataFrame, lo: Column, hi: Column) -> DataFrame:
    """Index entries with lo <= key < hi, sorted and ranked among themselves; nothing else is sorted or fetched."""
    return sorter.with_global_rank(sorter.sort_index(idx.where((F.col("key") >= lo) & (F.col("key") < hi))))


def rank_rows(idx: DataFrame, first: int, last: int, cells: int = 4096) -> DataFrame:
    """Entries of ranks first to last, ranked; what lies before is counted and what lies after is not sorted.

    Keys are counted in ranges cut by a bounded sample; only the entries of the ranges that hold the wanted ranks are sorted.
    """
    if last < first:
        return sorter.with_global_rank(idx.limit(0))
    sample = idx.select("key").sample(min(1.0, 8.0 * cells / max(1, idx.count())), 3).limit(16 * cells).collect()
    found = sorted({bytes(r[0]) for r in sample})
    cuts = found[:: max(1, len(found) // cells)]
    cell = _cells(idx, cuts)
    counts = sorted((r[0], r[1]) for r in cell.groupBy("cell").count().collect())
    total, wanted, before = 0, [], None
    for c, n in counts:
        if total < last and total + n >= first:
            wanted.append(c)
            before = total if before is None else before
        total += n
    if not wanted:
        return sorter.with_global_rank(idx.limit(0))
    near = cell.where(F.col("cell").between(wanted[0], wanted[-1])).drop("cell")
    ranked = sorter.with_global_rank(sorter.sort_index(near)).withColumn("rank", F.col("rank") + F.lit(before))
    return ranked.where(F.col("rank").between(first, last))


def _cells(idx: DataFrame, cuts: list[bytes]) -> DataFrame:
    """``idx`` with ``cell``, the number of cuts at or below the key."""
    schema = ", ".join(f"`{n}` {t}" for n, t in idx.dtypes) + ", cell int"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cell = [bisect.bisect_right(cuts, k) for k in b.column("key").to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(cell, pa.int32())], [*b.schema.names, "cell"])

    return idx.mapInArrow(run, schema)


def index_join(a: DataFrame, b: DataFrame, on: list[str], how: str = "inner", fetch: list[tuple[DataFrame, str, str]] = ()) -> DataFrame:
    """Join two slim frames; then fetch the wide columns of the survivors by locator.

    ``fetch`` lists (wide Parquet scan, path column, row column): the locator columns that one side brought along.  Values are
    read from the files where they lie, row group by row group; they take part in no shuffle.
    """
    out = a.join(b, on, how)
    for wide, path, row in fetch:
        named = out.withColumnsRenamed({path: "file_path", row: "row_index"})
        out = gather.parquet_fetch(named, wide).drop("file_path", "row_index")
    return out


def compress_runs(idx: DataFrame, path: str, codec: str, delta: bool = False, ordered: bool = False) -> None:
    """Sorted slim entries written with a codec of Parquet's; ``ordered`` says that ``idx`` is sorted in ranges already.

    ``delta`` stores keys as what they add to the key before and places as differences, within each written stretch; ``read_runs``
    undoes it.  Sorted keys share their first bytes, so the form pays where there are many entries for each of these.
    """
    entries = idx if ordered else sorter.sort_index(idx)
    if delta:
        entries = entries.mapInArrow(_deltas, "shared int, rest binary, file_id int, step long")
    entries.write.option("compression", codec).mode("overwrite").parquet(path)


def read_runs(spark: SparkSession, path: str, delta: bool = False) -> DataFrame:
    """What ``compress_runs`` wrote: ``(key, file_id, pos)``.

    Spark takes the size of differences for that of their files' names, and would broadcast them however many: join them by a hint.
    """
    if not delta:
        return spark.read.parquet(path).select("key", "file_id", "pos")
    # A file is one chain of differences: each is read whole by one task.
    names = sorted(name for name, _ in files.listed(path, ".parquet"))
    tasks = spark.createDataFrame([(n,) for n in names], "name string").repartition(max(1, len(names)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for name in (n for b in batches for n in b.column(0).to_pylist()):
            system, local = files.opened(name)
            with pq.ParquetFile(local, filesystem=system) as f:
                yield from _sums(f.iter_batches(1 << 16))

    return tasks.mapInArrow(run, "key binary, file_id int, pos long")


def _deltas(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    key, pos = b"", 0
    for b in batches:
        shared, rest, step = [], [], []
        for k, p in zip(b.column("key").to_pylist(), b.column("pos").to_pylist(), strict=True):
            n = len(os.path.commonprefix([key, k]))
            shared.append(n)
            rest.append(k[n:])
            step.append(p - pos)
            key, pos = k, p
        yield pa.RecordBatch.from_arrays([pa.array(shared, pa.int32()), pa.array(rest, pa.binary()), b.column("file_id"), pa.array(step, pa.int64())], ["shared", "rest", "file_id", "step"])


def _sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    key, pos = b"", 0
    for b in batches:
        keys, places = [], []
        for n, r, s in zip(*(b.column(c).to_pylist() for c in ("shared", "rest", "step")), strict=True):
            key, pos = key[:n] + r, pos + s
            keys.append(key)
            places.append(pos)
        yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), b.column("file_id"), pa.array(places, pa.int64())], ["key", "file_id", "pos"])
