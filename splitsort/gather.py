"""Fetching values by locator: four strategies with the same rows.

``point_fetch`` moves no value through a shuffle: each task reads the values of its stretch of the sorted
index straight from storage.  ``broadcast_rank`` and ``locator_join`` bring values to their ranks by
joins; ``file_local_fetch`` sweeps each file in order for every batch, for storage with slow seeks.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .plans.concurrency import exclusive_map
from .records import RecordSpec
from .session import staged
from .sources import files, with_locator

#: Entries an index may have to be broadcast at once.
BROADCAST_ENTRIES = 1_000_000
BATCH_BYTES, GAP_BYTES, READ_POOL = 8 << 20, 4096, 4
#: Rows of an Arrow batch and of a usual row group; rows decoded for each one fetched beyond which a join is cheaper, and rows under which no one counts.
BATCH_ROWS, GROUP_ROWS, DECODED, LEAST_ROWS = 10_000, 1 << 17, 20, 200_000
#: Bytes read before they are put in place, and seconds a read takes on average from which threads share the reads: shorter ones only wait for each other's turn.
PIECE, WAITS = 8 << 20, 20e-6
#: What one request costs in a Python worker, in nanoseconds, and how fast a file is read on, in bytes a nanosecond.
REQUEST_NS, STREAM = 2000.0, 2.0


class OffsetQueue:
    """Locators wait here until their values fill one write buffer; counts its fills."""

    def __init__(self, capacity: int) -> None:
        self.capacity, self.waiting, self.size, self.fills = max(1, capacity), [], 0, 0

    def put(self, batch: pa.RecordBatch, sizes: np.ndarray) -> Iterator[list[pa.RecordBatch]]:
        """Take a batch of locators in; hand out the queue each time the next value no longer fits."""
        at = 0
        while at < len(sizes):
            ends = np.cumsum(sizes[at:])
            n = int(np.searchsorted(ends, self.capacity - self.size, "right"))
            if n == 0 and not self.waiting:
                n = 1  # a value longer than the buffer goes alone
            if n:
                self.waiting.append(batch.slice(at, n))
                self.size += int(ends[n - 1])
                at += n
            if at < len(sizes):
                yield self.flush()

    def flush(self) -> list[pa.RecordBatch]:
        out, self.waiting, self.size = self.waiting, [], 0
        self.fills += bool(out)
        return out


def coalesced(file_id: np.ndarray, start: np.ndarray, size: np.ndarray, gap: int) -> list[tuple[int, int, int, np.ndarray]]:
    """Reads (file, from, to, rows in order) that cover all pieces; pieces ``gap`` or less apart share one."""
    order = np.lexsort((start, file_id))
    if not len(order):
        return []
    f, a = file_id[order], start[order]
    z = a + size[order]
    new = np.ones(len(order), bool)
    new[1:] = (f[1:] != f[:-1]) | (a[1:] - z[:-1] > gap)
    cuts = np.flatnonzero(new)
    ends = [*cuts[1:].tolist(), len(order)]
    tops = np.maximum.reduceat(z, cuts)
    return [(int(f[i]), int(a[i]), int(t), order[i:j]) for i, j, t in zip(cuts.tolist(), ends, tops.tolist(), strict=True)]


def expected_amplification(density: float, spec: RecordSpec, gap: int) -> float:
    """Bytes read for each byte needed when a share ``density`` of a file's records is fetched at random.

    Neighbours j records apart share a request where the j - 1 records and the key between them are within ``gap``.
    """
    reach = max(0, (gap - spec.key_bytes) // spec.record_bytes + 1) if gap >= spec.key_bytes else 0
    skipped = sum(density * (1 - density) ** (j - 1) * (j * spec.record_bytes - spec.value_bytes) for j in range(1, reach + 1))
    return 1 + skipped / spec.value_bytes


def best_gap(density: float, spec: RecordSpec, request_ns: float = REQUEST_NS, gb_per_s: float = STREAM) -> int:
    """The gap at which reading on costs no more than another request, or 0 if no neighbour is that near."""
    gap = int(request_ns * gb_per_s)
    return gap if expected_amplification(density, spec, gap) > 1 else 0


def _on_grid(paths: list[str], file_id: np.ndarray, start: np.ndarray, width: int, gap: int, pool: int) -> tuple[np.ndarray, int, int]:
    """Rows of ``width`` bytes in the order asked for, the bytes read and the requests made: the same reads as ``coalesced`` names, by arrays."""
    out = np.empty((len(start), width), np.uint8)
    if not len(start):
        return out, 0, 0
    order = np.lexsort((start, file_id))
    f, a = file_id[order], start[order]
    new = np.ones(len(order), bool)
    new[1:] = (f[1:] != f[:-1]) | (a[1:] - a[:-1] - width > gap)
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(order))
    sizes = a[last - 1] + width - a[first]
    sums = np.cumsum(sizes)
    # A piece is some reads of one file, PIECE bytes in all or a single longer one.
    piece = (sums - 1) // PIECE
    cuts = np.flatnonzero(np.append(True, (piece[1:] != piece[:-1]) | (f[first][1:] != f[first][:-1])))
    pieces = list(zip(cuts.tolist(), [*cuts[1:].tolist(), len(first)], strict=True))

    def one(span: tuple[int, int]) -> None:
        i, j = span
        read = files.handle(paths[int(f[first[i]])]).read_at
        blocks = list(map(read, sizes[i:j].tolist(), a[first[i:j]].tolist()))
        raw = np.frombuffer(blocks[0] if len(blocks) == 1 else b"".join(blocks), np.uint8)
        x, z = first[i], last[j - 1]
        if len(raw) != sums[j - 1] - sums[i] + sizes[i]:
            raise ValueError(f"{paths[int(f[x])]} ends before its records do")
        if z - x == j - i:
            out[order[x:z]] = raw.reshape(z - x, width)
            return
        base = (sums[i:j] - sizes[i:j] - (sums[i] - sizes[i])) - a[first[i:j]]
        at = a[x:z] + np.repeat(base, last[i:j] - first[i:j])
        out[order[x:z]] = np.lib.stride_tricks.as_strided(raw, (len(raw) - width + 1, width), (1, 1))[at]

    began = time.perf_counter()
    one(pieces[0])
    waits = (time.perf_counter() - began) / (pieces[0][1] - pieces[0][0]) > WAITS
    if pool > 1 and waits and len(pieces) > 1:
        with ThreadPoolExecutor(pool) as threads:
            list(threads.map(one, pieces[1:]))
    else:
        for span in pieces[1:]:
            one(span)
    return out, int(sums[-1]), len(first)


def read_values(paths: list[str], file_id: np.ndarray, start: np.ndarray, size: np.ndarray, gap: int, pool: int, stride: int = 0) -> tuple[pa.Array, int, int]:
    """Values in the order asked for, the bytes read and the requests made.

    ``stride`` is the record width where all values are equally long and lie on one grid: these are copied by the piece.
    """
    if stride:
        matrix, got, asked = _on_grid(paths, file_id, start, int(size[0]) if len(size) else 0, gap, pool)
        return files.fixed_binary(matrix), got, asked
    reads = coalesced(file_id, start, size, gap)
    out: list[bytes] = [b""] * len(start)

    def one(read: tuple) -> int:
        f, a, z, rows = read
        block = files.handle(paths[f]).read_at(z - a, a)
        for r in rows.tolist():
            out[r] = block[start[r] - a : start[r] - a + size[r]]
        return z - a

    if pool > 1 and len(reads) > 1:
        with ThreadPoolExecutor(pool) as threads:
            got = sum(threads.map(one, reads, chunksize=1) if len(reads) < 64 else threads.map(lambda part: sum(map(one, part)), [reads[k::pool] for k in range(pool)]))
    else:
        got = sum(map(one, reads))
    return pa.array(out, pa.binary()), got, len(reads)


def point_fetch(
    idx: DataFrame,
    path: str,
    spec: RecordSpec,
    batch_bytes: int = BATCH_BYTES,
    gap_bytes: int = GAP_BYTES,
    read_pool: int = READ_POOL,
    counters: bool = False,
    policy: str = "no_sync",
    refetch_key: bool = False,
) -> DataFrame:
    """``idx`` (with file_id, pos and for length-prefixed records vlength) with ``value``; no shuffle.

    Values are fetched a write buffer at a time, over as many input batches as it takes: sorted by place, near
    neighbours in one request, put back in the index's order.  ``batch_bytes`` 0 fetches one value at a time.  With
    ``counters`` the result is one row for each task in place of the data.

    ``policy`` says how reads and the handing on of rows (the writes) meet: ``no_sync`` one after the other in each task
    and no task waiting for another; ``overlap`` with two buffers, the next one read while the last is handed on;
    ``exclusive`` by a barrier, so that at no time one task reads while another writes.  ``refetch_key`` reads whole fixed
    records, and takes the key from there.
    """
    klv = spec.length_bytes > 0
    paths = [p for p, _ in files.listed(path, ".klv" if klv else ".rec")]
    names, width, k, v = idx.columns, spec.record_bytes, spec.key_bytes, spec.value_bytes
    kinds = ", ".join(f"`{n}` {t}" for n, t in idx.dtypes)
    if refetch_key and klv:
        raise ValueError("keys of length-prefixed records are not fetched again")

    def sizes_of(batch: pa.RecordBatch) -> np.ndarray:
        if klv:
            return batch.column("vlength").to_numpy().astype(np.int64)
        return np.full(batch.num_rows, width if refetch_key else v, np.int64)

    def queued(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        queue = OffsetQueue(batch_bytes)
        for batch in batches:
            if not batch.num_rows:
                continue
            if not batch_bytes:
                yield batch  # no buffer: one request after the other
                continue
            for full in queue.put(batch, sizes_of(batch)):
                yield _joined(full)
        if queue.waiting:
            yield _joined(queue.flush())

    def fetched(batch: pa.RecordBatch) -> tuple[pa.RecordBatch, list[int]]:
        f, pos, size = batch.column("file_id").to_numpy(), batch.column("pos").to_numpy(), sizes_of(batch)
        start = pos if klv else pos * width + (0 if refetch_key else k)
        gap, pool = (gap_bytes, read_pool) if batch_bytes else (-1, 1)
        values, got, asked = read_values(paths, f, start, size, gap, pool, 0 if klv else width)
        columns = list(batch.columns)
        if refetch_key:
            whole = np.frombuffer(values.buffers()[2], np.uint8).reshape(len(pos), width)
            columns[names.index("key")], values = files.fixed_binary(whole[:, :k]), files.fixed_binary(whole[:, k:])
        out = pa.RecordBatch.from_arrays([*columns, values], [*names, "value"])
        return out, [batch.num_rows, int(size.sum()), got, asked, 1 if batch_bytes else asked]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if policy == "overlap":
            with ThreadPoolExecutor(1) as ahead:
                coming = None
                for batch in queued(batches):
                    following = ahead.submit(fetched, batch)
                    if coming is not None:
                        yield coming.result()[0]
                    coming = following
                if coming is not None:
                    yield coming.result()[0]
            return
        for batch in queued(batches):
            yield fetched(batch)[0]

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(5, np.int64)
        for batch in queued(batches):
            total += fetched(batch)[1]
        fields = ["records", "bytes_needed", "bytes_read", "requests", "fills"]
        yield pa.RecordBatch.from_arrays([pa.array(["record_read"]), *(pa.array([int(x)]) for x in total)], ["op", *fields])

    if counters:
        return idx.mapInArrow(counted, "op string, records long, bytes_needed long, bytes_read long, requests long, fills long")
    schema = f"{kinds}, value binary"
    if policy == "exclusive":
        slots = idx.sparkSession.sparkContext.defaultParallelism  # all tasks of a barrier stage run at once
        return exclusive_map(idx.coalesce(slots), queued, lambda batch: fetched(batch)[0], schema)
    if policy not in ("no_sync", "overlap"):
        raise ValueError(f"{policy} isn't a policy of the fetch")
    return idx.mapInArrow(run, schema)


def _joined(batches: list[pa.RecordBatch]) -> pa.RecordBatch:
    return batches[0] if len(batches) == 1 else pa.Table.from_batches(batches).combine_chunks().to_batches()[0]


def file_local_fetch(idx: DataFrame, path: str, spec: RecordSpec, batch_bytes: int = 16 * BATCH_BYTES) -> DataFrame:
    """As ``point_fetch`` with one sweep over each file's touched span for every large batch."""
    return point_fetch(idx, path, spec, batch_bytes, gap_bytes=1 << 40, read_pool=1)


def broadcast_rank(ranked: DataFrame, wide: DataFrame, on: list[str], entries: int, bound: int = 0) -> DataFrame:
    """Wide rows with the rank of a broadcast index; one over the bound is broadcast a slice of ranks at a time.

    Slices are joined and written one after the other, so that no two are in memory; each scans the wide rows again.
    """
    slim, bound, out = ranked.select(*on, "rank"), bound or BROADCAST_ENTRIES, None
    if entries <= bound:
        return wide.join(F.broadcast(slim), on)
    for first in range(1, entries + 1, bound):
        part = slim.where(F.col("rank").between(first, first + bound - 1))
        one = staged(wide.join(F.broadcast(part), on), "ranks")
        out = one if out is None else out.unionAll(one)
    return out


def locator_join(ranked: DataFrame, wide: DataFrame, on: list[str]) -> DataFrame:
    """Wide rows with their rank by a shuffled join on the locator."""
    return wide.join(ranked.select(*on, "rank").hint("merge"), on)


def decoded_rows(ranked: DataFrame) -> int:
    """Rows that ``parquet_fetch`` decodes for a ranked index, at batches of BATCH_ROWS and row groups of GROUP_ROWS rows."""
    batch, group = F.floor((F.col("rank") - 1) / BATCH_ROWS), F.floor(F.col("row_index") / GROUP_ROWS)
    return ranked.select(batch.alias("b"), "file_path", group.alias("g")).distinct().count() * GROUP_ROWS


def fetch_or_join(ranked: DataFrame, df: DataFrame, wide: list[str]) -> DataFrame:
    """Columns ``wide`` of the Parquet scan ``df`` at their ranks: by point fetches, or by a shuffled join on the locator.

    A batch of the index decodes every row group that it touches.  Where keys lie at random that is each group once for every
    batch; the join decodes each row once.  So fetches are for indexes near the order of the file, and for small ones.
    """
    n = ranked.count()
    if n <= LEAST_ROWS or decoded_rows(ranked) <= DECODED * n:
        return parquet_fetch(ranked, df.select(*wide))
    return locator_join(ranked, with_locator(df).select(*wide, "file_path", "row_index"), ["file_path", "row_index"])


def parquet_fetch(idx: DataFrame, columns: DataFrame, sweep: bool = False) -> DataFrame:
    """Fetch rows of Parquet files by (file_path, row_index), a batch at a time.

    Point fetches read the row groups a batch touches, ``sweep`` whole files in order.  Row groups amplify
    like any block: measured by ``measures.amplification``.
    """
    names = [c for c in columns.columns if c not in idx.columns]
    kinds = ", ".join(f"`{n}` {t}" for n, t in [*idx.dtypes, *[(c, t) for c, t in columns.dtypes if c in names]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            path, row = batch.column("file_path").to_pylist(), batch.column("row_index").to_numpy()
            parts, places = [], []
            for one in sorted(set(path)):
                mine = np.flatnonzero(np.array([p == one for p in path]))
                system, name = files.opened(one)
                with pq.ParquetFile(name, filesystem=system) as f:
                    starts = np.cumsum([0] + [f.metadata.row_group(g).num_rows for g in range(f.num_row_groups)])
                    group = np.searchsorted(starts, row[mine], "right") - 1
                    for g in range(f.num_row_groups) if sweep else sorted(set(group.tolist())):
                        here = mine[group == g]
                        if len(here):
                            parts.append(f.read_row_group(g, columns=names).take(pa.array(row[here] - starts[g])))
                            places.append(here)
            if parts:
                got = pa.concat_tables(parts).take(pa.array(np.argsort(np.concatenate(places), kind="stable")))
                cols = [got.column(n).combine_chunks() for n in names]
                yield pa.RecordBatch.from_arrays([*batch.columns, *cols], [*batch.schema.names, *names])

    return idx.mapInArrow(run, kinds)
