"""``klvrec``: records of key, length and value in ``.klv`` files, with anchors beside them.

The next record starts where the last one's value ends, so a file alone can only be walked from
its start.  The writer therefore notes the offset of every m-th record in an ``.anchors`` file; with
it, stretches of one file are walked side by side.  Option ``anchors`` is m when writing (0: none)
and whether to use them when reading; ``value`` true returns the values as well.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition

from . import files
from .fixedrec import Written

SLIM = "key binary, vlength int, file_id int, pos long"
CHUNK, BATCH = 4 << 20, 20_000


@dataclass
class Stretch(InputPartition):
    file_id: int
    path: str
    start: int
    end: int

    def __post_init__(self) -> None:
        super().__init__((self.file_id, self.start))


class KlvReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.path, self.k = options["path"], int(options.get("keybytes", 10))
        self.anchors, self.value = options.get("anchors", "true") != "false", options.get("value", "false") == "true"
        self.per_task = int(options.get("taskbytes", 64 << 20))

    def partitions(self) -> list[Stretch]:
        out = []
        known = dict(files.listed(self.path, ".anchors"))
        for i, (path, size) in enumerate(files.listed(self.path, ".klv")):
            side = path[:-4] + ".anchors"
            cuts = [0]
            if self.anchors and side in known:
                marks = np.frombuffer(files.handle(side).read_at(known[side], 0), "<u8")
                for m in marks.tolist():
                    if m - cuts[-1] >= self.per_task:
                        cuts.append(m)
            out += [Stretch(i, path, a, b) for a, b in zip(cuts, [*cuts[1:], size], strict=True) if a < b]
        return out or [Stretch(0, "", 0, 0)]

    def read(self, part: Stretch) -> Iterator[pa.RecordBatch]:
        if part.start >= part.end:
            return
        f, head, at = files.handle(part.path), self.k + 4, part.start
        block, base = b"", at
        keys, lengths, places, values = [], [], [], []

        def batch() -> pa.RecordBatch:
            cols = [pa.array(keys, pa.binary()), pa.array(lengths, pa.int32()), pa.array([part.file_id] * len(keys), pa.int32()), pa.array(places, pa.int64())]
            names = ["key", "vlength", "file_id", "pos"]
            if self.value:
                cols.append(pa.array(values, pa.binary()))
                names.append("value")
            return pa.RecordBatch.from_arrays(cols, names)

        while at < part.end:
            if at + head > base + len(block):
                base, block = at, f.read_at(min(CHUNK, part.end - at), at)
            if at + head > base + len(block):
                raise ValueError(f"{part.path}: the record at byte {at} has no whole head")
            o = at - base
            n = int.from_bytes(block[o + self.k : o + head], "little")
            if at + head + n > part.end:
                raise ValueError(f"{part.path}: the value at byte {at + head} is cut off")
            keys.append(block[o : o + self.k])
            lengths.append(n)
            places.append(at + head)
            if self.value:
                whole = block[o + head : o + head + n]
                values.append(whole if len(whole) == n else f.read_at(n, at + head))
            at += head + n
            if len(keys) >= BATCH:
                yield batch()
                keys, lengths, places, values = [], [], [], []
        if keys:
            yield batch()


class KlvWriter(DataSourceArrowWriter):
    def __init__(self, options: dict) -> None:
        self.path, self.k, self.every = options["path"].rstrip("/"), int(options.get("keybytes", 10)), int(options.get("anchors", 1000))

    def write(self, batches: Iterator[pa.RecordBatch]) -> Written:
        task = TaskContext.get()
        final = f"{self.path}/part-{task.partitionId():06d}.klv"
        draft = f"{final}.{task.taskAttemptId()}.draft"
        marks: list[int] = []

        def parts() -> Iterator[bytes]:
            at = seen = 0
            for b in batches:
                for key, value in zip(b.column("key").to_pylist(), b.column("value").to_pylist(), strict=True):
                    if key is None or len(key) != self.k:
                        raise ValueError(f"a key isn't {self.k} bytes long")
                    if self.every and seen % self.every == 0:
                        marks.append(at)
                    value = value or b""
                    yield key + len(value).to_bytes(4, "little") + value
                    at, seen = at + self.k + 4 + len(value), seen + 1

        if not files.write_bytes(draft, parts()):
            return Written(draft, "")
        if marks:
            files.write_bytes(draft + ".anchors", [np.array(marks, "<u8").tobytes()])
        return Written(draft, final)

    def commit(self, messages: list[Written]) -> None:
        for m in messages:
            if m and m.final:
                if self.every:
                    files.move(m.draft + ".anchors", m.final[:-4] + ".anchors")
                files.move(m.draft, m.final)
            elif m:
                files.remove(m.draft)

    def abort(self, messages: list[Written]) -> None:
        for m in messages:
            if m:
                files.remove(m.draft)


class KlvRecords(DataSource):
    @classmethod
    def name(cls) -> str:
        return "klvrec"

    def schema(self) -> str:
        return SLIM + (", value binary" if self.options.get("value", "false") == "true" else "")

    def reader(self, schema) -> KlvReader:
        return KlvReader(dict(self.options))

    def writer(self, schema, overwrite: bool) -> KlvWriter:
        return KlvWriter(dict(self.options))
