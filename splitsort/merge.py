"""Merging sorted slim runs.

A merge task has one key range of all runs.  Cursors stand on the least unmerged entry of each
run's slice; the least of them go to the output, and a slice whose buffer share is used up is
refilled from its file.  Shares decide when refills happen, never what comes out.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession

from .sources import files

ENTRY, BY = "key binary, file_id int, pos long", ("key", "file_id", "pos")
TRACE = ("refills", "compared", "comparisons", "drained")
#: Entries of all runs in a merge task's memory, of one read from a file, and of one piece of the last run.
BUFFER_ENTRIES, READ_ENTRIES, DRAIN = 1 << 20, 1 << 16, 1 << 18


def redistribute(shares: list[int], dead: int) -> list[int]:
    """The share of an exhausted run goes half and half to its nearest live neighbours, the odd byte left.

    With a live neighbour on one side only, that one gets all; the sum stays the same.
    """
    out = list(shares)
    left = next((i for i in range(dead - 1, -1, -1) if shares[i] > 0), None)
    right = next((i for i in range(dead + 1, len(shares)) if shares[i] > 0), None)
    if left is None and right is None:
        return out
    give, out[dead] = out[dead], 0
    if left is None or right is None:
        out[left if right is None else right] += give
    else:
        out[left] += give - give // 2
        out[right] += give // 2
    return out


def first_shares(buffer: int, runs: int) -> list[int]:
    """The buffer split evenly, remainder to the first runs."""
    return [buffer // runs + (i < buffer % runs) for i in range(runs)]


class Cursor:
    """One run's slice, read in order from its files, a share of the buffer at a time."""

    def __init__(self, batches: Iterator[pa.RecordBatch]) -> None:
        self.batches, self.held, self.pending = batches, None, None
        self._fetch()

    def _fetch(self) -> None:
        self.pending = next((b for b in self.batches if b.num_rows), None)

    @property
    def more(self) -> bool:
        """Whether the file holds entries that are not in the buffer."""
        return self.pending is not None

    def refill(self, entries: int | None) -> int:
        """Load up to ``entries`` further entries, or all that is left in the next batches up to a bound; how many came."""
        parts, got = [], 0
        while self.pending is not None and (entries is None or got < entries):
            take = self.pending.num_rows if entries is None else min(self.pending.num_rows, entries - got)
            parts.append(self.pending.slice(0, take))
            got += take
            rest = self.pending.num_rows - take
            self.pending = self.pending.slice(take) if rest else None
            if not rest:
                self._fetch()
            if entries is None and got >= DRAIN:
                break
        self.held = pa.Table.from_batches(parts).combine_chunks() if parts else None
        return got

    def last(self) -> tuple:
        return _entry(self.held, self.held.num_rows - 1)

    def upto(self, bound: tuple) -> int:
        """How many held entries are at most ``bound``."""
        lo, hi = 0, self.held.num_rows
        while lo < hi:
            mid = (lo + hi) // 2
            if _entry(self.held, mid) <= bound:
                lo = mid + 1
            else:
                hi = mid
        return lo


def _entry(t: pa.Table, k: int) -> tuple:
    return tuple(t.column(c)[k].as_py() for c in BY)


def merge_streams(streams: list[Iterator[pa.RecordBatch]], buffer_entries: int, trace: dict[str, int]) -> Iterator[pa.Table]:
    """Entries of all sorted runs in order, block by block, with at most ``buffer_entries`` of them in memory.

    The buffer is split evenly.  Up to the least of the runs' last buffered entries nothing can still come in from a file:
    that much of all buffers is put in order and goes out, and the run whose buffer is used up by it is
    refilled.  A run that has ended leaves its share to its neighbours; the last one is handed on as it is read.
    ``trace`` counts refills, entries that were compared, comparisons of a one-by-one merge of that width, drained ones.
    """
    cursors = [Cursor(iter(s)) for s in streams]
    shares = first_shares(max(buffer_entries, len(cursors)), len(cursors)) if cursors else []
    live = [i for i, c in enumerate(cursors) if c.more]
    for i in range(len(cursors)):
        if i not in live:
            shares = redistribute(shares, i)
    for i in live:
        cursors[i].refill(max(1, shares[i]))
        trace["refills"] += 1
    while live:
        if len(live) == 1:  # one run left: nothing to compare with
            c = cursors[live[0]]
            while c.held is not None:
                trace["drained"] += c.held.num_rows
                yield c.held
                c.refill(None)
            return
        bounds = [(cursors[i].last(), i) for i in live if cursors[i].more]
        parts = []
        bound = min(bounds)[0] if bounds else None
        for i in live:
            c = cursors[i]
            n = c.held.num_rows if bound is None else c.upto(bound)
            if n:
                parts.append(c.held.slice(0, n))
                c.held = c.held.slice(n) if n < c.held.num_rows else None
        block = pa.concat_tables(parts).combine_chunks()
        trace["compared"] += block.num_rows
        trace["comparisons"] += block.num_rows * (len(live) - 1)
        yield block if len(parts) == 1 else block.take(pc.sort_indices(block, sort_keys=[(c, "ascending") for c in BY]))
        for i in list(live):
            c = cursors[i]
            if c.held is None and c.more:
                c.refill(max(1, shares[i]))
                trace["refills"] += 1
            elif c.held is None:
                live.remove(i)
                shares = redistribute(shares, i)


def run_slices(path: str, runs: int, range_id: int) -> list[Iterator[pa.RecordBatch]]:
    """The slices of one range in all run folders, as streams of batches in their order."""

    def stream(names: list[str]) -> Iterator[pa.RecordBatch]:
        for name in names:
            system, local = files.opened(name)
            with pq.ParquetFile(local, filesystem=system) as f:
                yield from f.iter_batches(READ_ENTRIES)

    out = []
    for r in range(runs):
        found = [name for name, _ in files.listed(f"{path}/run={r}/range_id={range_id}", ".parquet", missing=True)]
        if found:
            out.append(stream(found))
    return out


def merge_runs(spark: SparkSession, path: str, runs: int, ranges: int, extra: str = "", buffer_entries: int = BUFFER_ENTRIES, trace: bool = False) -> DataFrame:
    """The runs that ``sorter.write_runs`` left under ``path`` as ``(range_id, i, key, file_id, pos[, extra])``.

    ``i`` is the place inside the range.  One task merges one range of all runs, streaming their slices through a buffer of
    fixed size, so that memory depends neither on the range nor on the number of runs.  No shuffle.  With ``trace``
    the result is one row of counters for each range in place of the entries.
    """
    names = [*BY, *[f.split()[0] for f in extra.split(",") if f.strip()]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for g in (g for b in batches for g in b.column(0).to_pylist()):
            counts = dict.fromkeys(TRACE, 0)
            at = 0
            for block in merge_streams(run_slices(path, runs, g), buffer_entries, counts):
                for b in [] if trace else block.select(names).combine_chunks().to_batches():
                    place = pa.array(np.arange(at, at + b.num_rows, dtype=np.int64))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(b.num_rows, g, np.int32)), place, *b.columns], ["range_id", "i", *names])
                    at += b.num_rows
            if trace:
                yield pa.RecordBatch.from_arrays([pa.array([g], pa.int32()), *(pa.array([counts[c]], pa.int64()) for c in TRACE)], ["range_id", *TRACE])

    tasks = spark.range(0, ranges, 1, max(1, ranges))
    if trace:
        return tasks.mapInArrow(run, "range_id int, " + ", ".join(f"{c} long" for c in TRACE))
    return tasks.mapInArrow(run, "range_id int, i long, " + ENTRY + (f", {extra}" if extra else ""))


def phases(runs: int, fan_in: int) -> int:
    """Merge phases that ``runs`` need at a fan-in."""
    n = 0
    while runs > 1:
        runs, n = -(-runs // fan_in), n + 1
    return n
