"""Pool sizes, scheduling policies, and the barrier form of exclusive reads and writes."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark import BarrierTaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .device import READ_CURVE, WRITE_CURVE, Profile

POLICIES = ("single_thread", "no_sync", "no_sync_buffered_merge", "overlap", "exclusive")


@dataclass(frozen=True)
class ConcurrencyPlan:
    """Threads by operation and access size, and a policy; what ``sorter.one_pass`` and ``two_pass`` run by."""

    pools: dict[str, int]
    policy: str = "exclusive"

    def threads(self, op: str, default: int) -> int:
        """The pool of an operation, of its largest access size."""
        sizes = sorted((int(k.split("/")[1]), n) for k, n in self.pools.items() if k.startswith(op + "/"))
        return sizes[-1][1] if sizes else default


def size_pools(curve: DataFrame, eps: float = 0.05) -> DataFrame:
    """``op, access_bytes, threads, peak``: the fewest threads within ``eps`` of the peak bandwidth."""
    peak = curve.groupBy("op", "access_bytes").agg(F.max("gb_per_s").alias("peak"))
    near = curve.join(F.broadcast(peak), ["op", "access_bytes"]).where(F.col("gb_per_s") >= (1 - eps) * F.col("peak"))
    return near.groupBy("op", "access_bytes").agg(F.min("threads").cast("int").alias("threads"), F.first("peak").alias("peak"))


def plan_of(pools: DataFrame, policy: str = "exclusive") -> ConcurrencyPlan:
    return ConcurrencyPlan({f"{r['op']}/{r['access_bytes']}": r["threads"] for r in pools.collect()}, policy)


def schedule(ops: DataFrame, policy: str = "exclusive", profile: Profile | None = None, duplex: bool = False) -> DataFrame:
    """A timeline of ``ops(system, seq, kind, stage, seconds)``: start and end of each operation under a policy.

    Reads and writes share one channel: what runs at the same time is slowed by the profile's penalties and gains
    nothing.  ``duplex`` is the other reading, kept for comparison: a write hides as much of itself as the read before it lasts.
    """
    order = Window.partitionBy("system").orderBy("seq")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    cost = F.col("seconds") * (penalty(policy, profile) if profile is not None else F.lit(1.0))
    ops = ops.withColumn("seconds", cost)
    hidden = F.lit(0.0)
    if duplex and policy != "exclusive":
        prev_kind, prev = F.lag("kind").over(order), F.lag("seconds").over(order)
        hidden = F.when((F.col("kind") == "write") & (prev_kind != "write"), F.least("seconds", prev)).otherwise(0.0)
    ops = ops.withColumn("hidden", hidden)
    start = F.coalesce(F.sum(F.col("seconds") - F.col("hidden")).over(before), F.lit(0.0)) - F.col("hidden")
    return ops.withColumn("start_s", start).withColumn("end_s", F.col("start_s") + F.col("seconds")).drop("hidden")


def penalty(policy: str, profile: Profile) -> Column:
    """The factor of a policy on each operation."""
    read, write = F.col("kind") != "write", F.col("kind") == "write"
    touched = F.col("kind") != "slim"
    p = profile
    if policy == "exclusive":
        return F.lit(1.0)
    if policy == "single_thread":
        return F.when(write, 1 / WRITE_CURVE[1]).otherwise(1 / READ_CURVE[1])
    if policy == "overlap":
        return F.when(write, p.psi).when(read & touched, p.phi).otherwise(1.0)
    if policy == "no_sync":
        return F.when(write, p.psi * p.delta).when(read & touched, p.phi).otherwise(1.0)
    if policy == "no_sync_buffered_merge":
        merge = F.col("stage") == "merge"
        return F.when(write & merge, p.delta).when(write, p.psi * p.delta).when(merge, 1.0).otherwise(p.phi)
    raise ValueError(policy)


def exclusive_map(
    df: DataFrame, cut: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], fetch: Callable[[pa.RecordBatch], pa.RecordBatch], schema: str
) -> DataFrame:
    """Barrier stage: all tasks fetch one piece that ``cut`` hands out, wait, all emit it, wait.

    It needs a slot for each partition; ``df`` may not have more of them than that.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, it = BarrierTaskContext.get(), cut(batches)
        while True:
            batch = next(it, None)
            out = fetch(batch) if batch is not None else None
            more = task.allGather("1" if batch is not None else "0")
            if out is not None:
                yield out
            task.barrier()
            if "1" not in more:
                return

    return df.mapInArrow(run, schema, barrier=True)
