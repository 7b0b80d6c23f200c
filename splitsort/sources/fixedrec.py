"""``fixedrec``: fixed-size records in ``.rec`` files, read by byte ranges, written one file a task.

``access`` says what a scan touches: ``strided`` the keys only, ``sequential`` whole records of
which the values are dropped, ``full`` whole records.  ``counters`` true returns one row of byte and
request counts for each partition in place of the data: bytes that were needed, and bytes that were read.

A strided load of values shorter than option ``stridegap`` reads whole blocks and skips the values in memory, since
files, unlike byte-addressable devices, serve a small gap faster than a request; it then reads as much as a
sequential load.  ``stridegap`` 0 reads each key by a request of its own, and not one byte more.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition, WriterCommitMessage

from . import files

SLIM = "key binary, file_id int, pos long"
COUNTERS = "op string, records long, bytes_needed long, bytes_read long, requests long"
#: Bytes read at once; a gap between keys from which each key is a request of its own.
CHUNK, STRIDE_GAP = 8 << 20, 4096


def split_ranges(n: int, parts: int) -> list[tuple[int, int]]:
    """``n`` records dealt evenly over at most ``parts`` readers, in order; sizes differ by at most one."""
    parts = max(1, min(parts, n))
    cuts = [n * k // parts for k in range(parts + 1)]
    return [(a, b) for a, b in zip(cuts, cuts[1:], strict=False) if a < b]


@dataclass
class Range(InputPartition):
    file_id: int
    path: str
    first: int
    last: int

    def __post_init__(self) -> None:
        super().__init__((self.file_id, self.first))


class FixedReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.path = options["path"]
        self.k, self.v = int(options.get("keybytes", 10)), int(options.get("valuebytes", 90))
        self.access, self.readers = options.get("access", "full"), int(options.get("readers", 0))
        self.per_task = int(options.get("taskbytes", 64 << 20))
        self.counters = options.get("counters", "false") == "true"
        self.gap = int(options.get("stridegap", STRIDE_GAP))

    def partitions(self) -> list[Range]:
        width, out = self.k + self.v, []
        found = files.listed(self.path, ".rec")
        total = sum(size for _, size in found)
        for i, (path, size) in enumerate(found):
            if size % width:
                raise ValueError(f"{path}: {size} bytes aren't whole records of {width}")
            parts = max(1, round(self.readers * size / total)) if self.readers and total else -(-size // self.per_task)
            out += [Range(i, path, a, b) for a, b in split_ranges(size // width, parts)]
        return out or [Range(0, "", 0, 0)]

    def read(self, part: Range) -> Iterator[pa.RecordBatch]:
        width, needed, got, asked = self.k + self.v, 0, 0, 0
        step = max(1, CHUNK // width)
        for a in range(part.first, part.last, step):
            b = min(part.last, a + step)
            f = files.handle(part.path)
            if self.access == "strided" and self.v >= self.gap:
                keys = np.frombuffer(b"".join(map(f.read_at, repeat(self.k), range(a * width, b * width, width))), np.uint8).reshape(b - a, self.k)
                block, asked, got = None, asked + b - a, got + (b - a) * self.k
            else:
                block = np.frombuffer(f.read_at((b - a) * width, a * width), np.uint8).reshape(b - a, width)
                keys, asked, got = block[:, : self.k], asked + 1, got + (b - a) * width
            needed += (b - a) * (self.k if self.access == "strided" else width)
            if self.counters:
                continue
            cols = [files.fixed_binary(keys)]
            names = ["key"]
            if self.access == "full":
                cols.append(files.fixed_binary(block[:, self.k :]))
                names.append("value")
            cols += [pa.array(np.full(b - a, part.file_id, np.int32)), pa.array(np.arange(a, b, dtype=np.int64))]
            yield pa.RecordBatch.from_arrays(cols, [*names, "file_id", "pos"])
        if self.counters:
            rows = [[f"run_read_{self.access}"], [part.last - part.first], [needed], [got], [asked]]
            yield pa.RecordBatch.from_arrays([pa.array(r) for r in rows], ["op", "records", "bytes_needed", "bytes_read", "requests"])


@dataclass
class Written(WriterCommitMessage):
    draft: str
    final: str


class FixedWriter(DataSourceArrowWriter):
    """Keys and values side by side; files are named by task, so their order is that of the partitions."""

    def __init__(self, options: dict) -> None:
        self.path = options["path"].rstrip("/")
        self.k, self.v = int(options.get("keybytes", 10)), int(options.get("valuebytes", 90))

    def write(self, batches: Iterator[pa.RecordBatch]) -> Written:
        task = TaskContext.get()
        final = f"{self.path}/part-{task.partitionId():06d}.rec"
        draft = f"{final}.{task.taskAttemptId()}.draft"

        def parts() -> Iterator[bytes]:
            for b in batches:
                cols = [files.byte_matrix(b.column("key"), self.k), files.byte_matrix(b.column("value"), self.v)]
                yield np.concatenate(cols, axis=1).tobytes()

        return Written(draft, final) if files.write_bytes(draft, parts()) else Written(draft, "")

    def commit(self, messages: list[Written]) -> None:
        for m in messages:
            if m and m.final:
                files.move(m.draft, m.final)
            elif m:
                files.remove(m.draft)

    def abort(self, messages: list[Written]) -> None:
        for m in messages:
            if m:
                files.remove(m.draft)


class FixedRecords(DataSource):
    @classmethod
    def name(cls) -> str:
        return "fixedrec"

    def schema(self) -> str:
        if self.options.get("counters", "false") == "true":
            return COUNTERS
        return "key binary, value binary, file_id int, pos long" if self.options.get("access", "full") == "full" else SLIM

    def reader(self, schema) -> FixedReader:
        return FixedReader(dict(self.options))

    def writer(self, schema, overwrite: bool) -> FixedWriter:
        return FixedWriter(dict(self.options))
