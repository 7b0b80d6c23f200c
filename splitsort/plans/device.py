"""Device profiles.

A model and not a measurement: its form and constants were picked by hand so that the orderings
reported for the device come out (SURVEY 2.7).  Agreement with those is a regression check and no
reproduction.  Byte and request counts in ``cost`` have no free constant.
"""

from __future__ import annotations

import os
import time
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from ..sources import files


@dataclass(frozen=True)
class Profile:
    """Bandwidths in bytes a nanosecond, waits in nanoseconds, and penalties of overlap."""

    name: str
    read: float
    write: float
    random_floor: float = 0.0  # least cost of one random read
    random_factor: float = 1.0  # random against sequential bandwidth
    sequential_load: float = 1.0  # whole-record index load against the strided one
    line_read: float = 0.0  # wait for each 64-byte line read at random
    line_write: float = 0.0  # wait for each 64-byte line written
    phi: float = 1.0  # reads while writes run
    psi: float = 1.0  # writes while reads run
    delta: float = 1.0  # writes with an uncontrolled pool
    levels: float = 1.1  # moves of a record by the in-place sort


#: Fitted constants of the test device, and the emulated devices (32 GB/s, 500 ns a line over 20 threads).
PROFILES = {
    "test_device": Profile("test_device", 22.2, 2.5, 5.0, 0.82, 3.0, phi=2.0, psi=1.6, delta=1.33),
    "slow_random": Profile("slow_random", 32.0, 32.0, line_read=25.0),
    "symmetric": Profile("symmetric", 32.0, 32.0),
    "slow_write": Profile("slow_write", 32.0, 32.0, line_write=25.0),
}

#: Bandwidth by threads on the test device, as shares of the peak; reads scale to 16, writes to 5.
READ_CURVE = {1: 0.09, 2: 0.18, 4: 0.35, 8: 0.68, 16: 0.97, 24: 0.99, 32: 1.0}
WRITE_CURVE = {1: 0.45, 2: 0.72, 3: 0.88, 5: 1.0, 8: 0.9, 16: 0.7, 32: 0.5}


def curve(spark: SparkSession, name: str = "test_device", sizes: tuple[int, ...] = (256, 4096)) -> DataFrame:
    """R8a: ``device, op, access_bytes, threads, gb_per_s``."""
    p = PROFILES[name]
    rows = []
    for size in sizes:
        for op, peak, shares in (("read_seq", p.read, READ_CURVE), ("read_random", p.read * p.random_factor, READ_CURVE), ("write_seq", p.write, WRITE_CURVE)):
            rows += [(name, op, size, t, round(peak * s, 4)) for t, s in shares.items()]
    return spark.createDataFrame(rows, "device string, op string, access_bytes int, threads int, gb_per_s double")


def probe(spark: SparkSession, path: str, sizes: tuple[int, ...] = (4096, 65536), threads: tuple[int, ...] = (1, 4), total: int = 4 << 20, data: str = "") -> DataFrame:
    """Micro-benchmark of the storage under ``path``: one task for each (op, size, threads).

    Reads go to a file that the task wrote itself; the numbers include this host's page cache.  What is written is random, or
    the bytes of the record files under ``data``, over again where they are fewer than ``total``.
    """
    from concurrent.futures import ThreadPoolExecutor

    sources = [name for name, _ in files.listed(data, ".rec")] if data else []
    grid = [(op, s, t) for op in ("read_seq", "read_random", "write_seq") for s in sizes for t in threads]

    def blocks_of(size: int, blocks: int) -> list[bytes]:
        if not sources:
            return [os.urandom(size)] * blocks
        held = b"".join(files.handle(name).read_at(total, 0) for name in sources)[:total] or bytes(size)
        held *= -(-size * blocks // len(held))
        return [held[k * size : (k + 1) * size] for k in range(blocks)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for op, size, n in zip(*(c.to_pylist() for c in b.columns), strict=True):
                name = f"{path}/probe-{uuid.uuid4().hex}-{op}-{size}-{n}"
                blocks = max(1, total // size)
                content = blocks_of(size, blocks)
                began = time.perf_counter()
                files.write_bytes(name, content)
                if op != "write_seq":
                    f = files.handle(name)
                    step = 1 if op == "read_seq" else 7919
                    began = time.perf_counter()
                    with ThreadPoolExecutor(n) as pool:
                        list(pool.map(lambda k, f=f, s=step, z=size, m=blocks: f.read_at(z, k * s % m * z), range(blocks)))
                took = time.perf_counter() - began
                files.remove(name)
                yield pa.RecordBatch.from_pylist([{"op": op, "access_bytes": size, "threads": n, "gb_per_s": blocks * size / 1e9 / took}])

    tasks = spark.createDataFrame(grid, "op string, access_bytes int, threads int").repartition(len(grid))
    return tasks.mapInArrow(run, "op string, access_bytes long, threads long, gb_per_s double")
