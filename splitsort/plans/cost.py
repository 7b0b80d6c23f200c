"""Traffic of each system in closed form, modelled time, space, and the advisor."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..records import RecordSpec
from ..sorter import choose_mode
from .concurrency import penalty
from .device import PROFILES, Profile

SYSTEMS = ("wide", "one_pass", "two_pass", "in_place", "serial_split", "resorting")


def traffic(system: str, n: int, spec: RecordSpec, phases: int = 1, levels: float = 1.1) -> tuple[float, float]:
    """Bytes read and written by a system."""
    k, v, e = spec.key_bytes, spec.value_bytes, spec.entry_bytes
    if system == "wide":
        return (1 + phases) * n * (k + v), (1 + phases) * n * (k + v)
    if system == "one_pass":
        return n * (k + v), n * (k + v)
    if system == "two_pass":
        return n * (k + v) + phases * n * e, n * (k + v) + phases * n * e
    if system == "in_place":
        return levels * n * (k + v), levels * n * (k + v)
    if system == "serial_split":
        return n * (k + v) + phases * n * e + n * v, n * (k + v) + phases * n * e
    if system == "resorting":
        return n * (k + v) + 2 * n * e + n * (k + v), n * (k + v) + 2 * n * e + n * (k + v)
    raise ValueError(system)


OPS = "system string, stage string, op string, kind string, bytes double, requests long, ns double"


def ops(spark: SparkSession, n: int, spec: RecordSpec, profile: Profile) -> DataFrame:
    """R8b with exclusive times: ``system, stage, op, kind, bytes, requests, ns`` of each operation."""
    return spark.createDataFrame(op_rows(n, spec, profile), OPS)


def ops_of_sizes(spark: SparkSession, sizes: dict[int, int], spec: RecordSpec, profile: Profile) -> DataFrame:
    """The same for records of several value sizes, ``sizes`` of each so many; ``ns`` is the mean of all."""
    total = max(1, sum(sizes.values()))
    rows = [(*row[:6], row[6] * n / total) for v, n in sorted(sizes.items()) for row in op_rows(n, spec.with_value(v), profile)]
    return spark.createDataFrame(rows, OPS)


def op_rows(n: int, spec: RecordSpec, profile: Profile) -> list[tuple]:
    """``kind`` is what policies and background load act on: strided, random, seq or write; merge reads of
    slim runs stay outside overlap.
    """
    k, v, e, w = spec.key_bytes, spec.value_bytes, spec.entry_bytes, spec.record_bytes
    p = profile
    seq = lambda b: b / p.read
    put = lambda b: b / p.write + b / 64 * p.line_write
    lines = lambda b: -(-b // 64) * p.line_read
    if p.line_read or p.random_floor == 0:
        strided, value = k / p.read + lines(k), v / p.read + lines(v)
    else:
        strided, value = w / p.read, max(p.random_floor, v / p.read / p.random_factor)
    direct = w / p.read / p.random_factor * (1 if p.random_floor else 1) + lines(w)
    rows = [
        ("wide", "run", "run_read", "seq", w, seq(w)), ("wide", "run", "run_write", "write", w, put(w)),
        ("wide", "merge", "merge_read", "seq", w, seq(w)), ("wide", "merge", "merge_write", "write", w, put(w)),
        ("one_pass", "run", "run_read", "strided", k, strided), ("one_pass", "run", "record_read", "random", v, value), ("one_pass", "run", "run_write", "write", w, put(w)),
        ("two_pass", "run", "run_read", "strided", k, strided), ("two_pass", "run", "run_write", "write", e, put(e)),
        ("two_pass", "merge", "merge_read", "slim", e, seq(e)), ("two_pass", "merge", "record_read", "random", v, value), ("two_pass", "merge", "merge_write", "write", w, put(w)),
        ("serial_split", "run", "run_read", "seq_load", w, p.sequential_load * w / p.read), ("serial_split", "run", "run_write", "write", e, put(e)),
        ("serial_split", "merge", "merge_read", "slim", e, seq(e)), ("serial_split", "merge", "record_read", "random", v, value), ("serial_split", "merge", "merge_write", "write", w, put(w)),
        ("in_place", "run", "move_read", "random", p.levels * w, p.levels * direct), ("in_place", "run", "move_write", "write", p.levels * w, p.levels * put(w)),
    ]
    return [(s, stage, op, kind, float(b) * n, n, float(ns)) for s, stage, op, kind, b, ns in rows]


#: Background clients: what one random reader, or one writer, adds to each kind of operation.
SLOPES = {
    "random_readers": {"random": 0.1475, "strided": 0.1475, "write": 0.035},
    "sequential_readers": {},
    "writers": {"random": 1.625, "strided": 1.625, "write": 1.625, "seq": 0.5},
}


def model(ops: DataFrame, policy: str, profile: Profile) -> DataFrame:
    """``system, policy, ns``: modelled nanoseconds a record."""
    return ops.groupBy("system").agg(F.sum(F.col("ns") * penalty(policy, profile)).alias("ns")).withColumn("policy", F.lit(policy))


def space(n: int, spec: RecordSpec) -> dict[str, int]:
    """Bytes of input, slim runs and output side by side."""
    return {"input": n * spec.record_bytes, "runs": n * spec.entry_bytes, "output": n * spec.record_bytes}


def compress_pays(raw: int, packed: int, read_gbps: float, write_gbps: float, pack_gbps: float, unpack_gbps: float) -> bool:
    """Whether what compression of runs saves in writing and reading exceeds what it costs."""
    return (raw - packed) / write_gbps + (raw - packed) / read_gbps > raw / pack_gbps + raw / unpack_gbps


def advise(spark: SparkSession, profile: str, n: int, spec: RecordSpec, budget: int, amplification: float = 1.0) -> DataFrame:
    """Plans by modelled seconds, then by bytes written, with ``place`` 1 for the best.

    ``amplification`` is what the fetch of values reads for each byte it needs (``gather.expected_amplification``).
    """
    p = PROFILES[profile]
    plan = choose_mode(n, spec, budget)
    use = ["two_pass", "wide", "in_place"] + (["one_pass"] if plan.mode == "one_pass" else [])
    o = ops(spark, n, spec, p).where(F.col("system").isin(use))
    fetch = F.when(F.col("op") == "record_read", amplification).otherwise(1.0)
    o = o.withColumn("ns", F.col("ns") * fetch).withColumn("bytes", F.col("bytes") * fetch)
    seconds = o.groupBy("system").agg(
        (F.sum("ns") * n / 1e9).alias("seconds"),
        F.sum(F.when(F.col("kind") == "write", F.col("bytes")).otherwise(0)).alias("written"),
        F.sum(F.when(F.col("kind") != "write", F.col("bytes")).otherwise(0)).alias("read"),
    )
    from pyspark.sql import Window

    order = Window.orderBy("seconds", "written")  # at most four rows
    return seconds.withColumn("place", F.row_number().over(order)).withColumn("profile", F.lit(profile))
