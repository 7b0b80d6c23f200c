"""Byte files by any path that pyarrow's file systems open: local paths, file:, hdfs:, s3:, gs: ..."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyarrow import fs


def opened(path: str) -> tuple[fs.FileSystem, str]:
    if path.startswith("file:"):
        return fs.LocalFileSystem(), "/" + path[5:].lstrip("/")
    return fs.FileSystem.from_uri(path) if "://" in path else (fs.LocalFileSystem(), path)


@lru_cache(64)
def handle(path: str):
    """An open file for positional reads; kept by the worker."""
    system, name = opened(path)
    return system.open_input_file(name)


def listed(path: str, suffix: str, missing: bool = False) -> list[tuple[str, int]]:
    """(path, size) of the folder's files with a suffix, in the order of their names: the file ids."""
    system, name = opened(path)
    prefix = path.rstrip("/")
    found = system.get_file_info(fs.FileSelector(name.rstrip("/"), allow_not_found=missing))
    return sorted((f"{prefix}/{f.base_name}", f.size) for f in found if f.is_file and f.base_name.endswith(suffix) and not f.base_name.startswith("_"))


def fixed_binary(block: np.ndarray) -> pa.Array:
    """Rows of a byte matrix as a binary array."""
    n, width = block.shape
    ends = np.arange(n + 1, dtype=np.int32) * width
    return pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(block))])


def byte_matrix(column: pa.Array, width: int) -> np.ndarray:
    """A binary array of equal widths as a byte matrix: the array's own bytes, where its rows all have that width."""
    if pa.types.is_binary(column.type) and len(column) and not column.null_count:
        ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
        if (np.diff(ends) == width).all():
            return np.frombuffer(column.buffers()[2], np.uint8)[ends[0] : ends[-1]].reshape(len(column), width)
    rows = column.to_pylist()
    if any(r is None or len(r) != width for r in rows):
        raise ValueError(f"a key or value isn't {width} bytes long")
    return np.frombuffer(b"".join(rows), np.uint8).reshape(len(rows), width)


def write_bytes(path: str, parts) -> int:
    """Write the parts under a name of their own, then move them into place: a lost task leaves no half file."""
    system, name = opened(path)
    system.create_dir(name.rsplit("/", 1)[0], recursive=True)
    size = 0
    with system.open_output_stream(name) as out:
        for p in parts:
            out.write(p)
            size += len(p)
    return size


def move(source: str, target: str) -> None:
    system, a = opened(source)
    system.move(a, opened(target)[1])


def remove(path: str) -> None:
    system, name = opened(path)
    system.delete_file(name)


def remove_folder(path: str) -> None:
    """A folder that this library wrote, with what is in it; none is no error."""
    system, name = opened(path)
    if system.get_file_info(name).type == fs.FileType.Directory:
        system.delete_dir(name)
