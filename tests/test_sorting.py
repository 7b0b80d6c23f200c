"""Every sort gives the sorted permutation, on edge inputs too; plans are slim."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from splitsort import baselines, gather, keyindex, sorter, validate
from splitsort.plans import counters, device
from splitsort.plans.concurrency import ConcurrencyPlan
from splitsort.records import TEXTS, RecordSpec
from splitsort.session import new_path
from splitsort.sources import write_fixed, write_klv

SPEC = RecordSpec(key_bytes=4, value_bytes=6)
INPUTS = {
    "one": [(b"aaaa", b"value1")],
    "equal": [(b"same", b"%06d" % i) for i in range(300)],
    "sorted": [(b"%04d" % i, b"%06d" % i) for i in range(501)],
    "reversed": [(b"%04d" % (999 - i), b"%06d" % i) for i in range(333)],
    "bytes": [(bytes([i * 37 % 256, 255 - i % 256, 0, i % 2]), b"\x00\xff%04d" % i) for i in range(257)],
}


def rows(df):
    return [(bytes(r["key"]), bytes(r["value"])) for r in df.orderBy("rank").collect()]


@pytest.fixture(scope="module", params=list(INPUTS))
def records(request, spark):
    path = new_path(spark, "in").removeprefix("file:")
    data = INPUTS[request.param]
    write_fixed(spark.createDataFrame(data, "key binary, value binary").repartition(3), path, SPEC)
    return path, data


@pytest.mark.parametrize("sort", ["one", "unbuffered", "exact", "refetch", "overlap", "exclusive", "planned", "two", "two-overlap", "wide", "sample", "deep", "memory", "resort", "serial", "quick"])
def test_sorts(spark, records, sort):
    path, data = records
    budget = max(SPEC.entry_bytes, len(data) * SPEC.entry_bytes // 3)
    out = {
        "one": lambda: sorter.one_pass(spark, path, SPEC),
        "unbuffered": lambda: sorter.one_pass(spark, path, SPEC, buffered=False),
        "exact": lambda: sorter.one_pass(spark, path, SPEC, stride_gap=0, gap_bytes=0),
        "refetch": lambda: sorter.one_pass(spark, path, SPEC, refetch_key=True),
        "overlap": lambda: sorter.one_pass(spark, path, SPEC, policy="overlap"),
        "exclusive": lambda: sorter.one_pass(spark, path, SPEC, policy="exclusive"),
        "planned": lambda: sorter.one_pass(spark, path, SPEC, plan=ConcurrencyPlan({"read_random/4096": 3, "write_seq/4096": 2}, "overlap")),
        "two-overlap": lambda: sorter.two_pass(spark, path, SPEC, budget, policy="overlap"),
        "deep": lambda: baselines.sample_sort(spark, path, SPEC, oversample=8, fanout=2, bucket_bytes=500),
        "memory": lambda: baselines.sample_sort(spark, path, SPEC, fanout=4, device="memory"),
        "quick": lambda: baselines.serial_split(spark, path, SPEC, budget, run_sort="quick"),
        "two": lambda: sorter.two_pass(spark, path, SPEC, budget, fan_in=2),
        "wide": lambda: baselines.wide_merge(spark, path, SPEC, "exclusive"),
        "sample": lambda: baselines.sample_sort(spark, path, SPEC, fanout=4),
        "resort": lambda: baselines.resorting_key_sort(spark, path, SPEC),
        "serial": lambda: baselines.serial_split(spark, path, SPEC, budget),
    }[sort]()
    got = rows(out)
    assert [k for k, _ in got] == sorted(k for k, _ in data)
    assert sorted(got) == sorted(data)


def test_validity_is_noticed(spark):
    good = spark.createDataFrame([(i + 1, b"%03d" % i, b"v") for i in range(50)], "rank long, key binary, value binary")
    assert validate.is_sorted_permutation(good, good, ["key", "value"])
    bad = good.withColumn("key", F.when(F.col("rank") == 9, F.lit(b"999")).otherwise(F.col("key")))
    assert validate.order_violations(bad).first()["descents"] == 1
    assert not validate.is_sorted_permutation(good, bad, ["key", "value"])


def test_truncated_file_fails(spark, tmp_path):
    (tmp_path / "part-0.rec").write_bytes(b"x" * 25)
    with pytest.raises(Exception, match="whole records"):
        keyindex.build_fixed(spark, str(tmp_path), SPEC).count()
    (tmp_path / "part-0.klv").write_bytes(b"k" * 10 + (99).to_bytes(4, "little") + b"short")
    with pytest.raises(Exception, match="cut off"):
        keyindex.build_klv(spark, str(tmp_path), TEXTS).count()


def test_klv_with_and_without_anchors(spark):
    path = new_path(spark, "klv").removeprefix("file:")
    data = [(b"%010d" % (i * 7919 % 1000), (b"x" * (i % 5 * 100)) + "é".encode() * (i % 3)) for i in range(400)]
    write_klv(spark.createDataFrame(data, "key binary, value binary").repartition(2), path, TEXTS, anchors=10)
    walk = keyindex.build_klv(spark, path, TEXTS, anchors=False)
    jump = keyindex.build_klv(spark, path, TEXTS, anchors=True, task_bytes=1000)
    assert jump.rdd.getNumPartitions() > walk.rdd.getNumPartitions()
    assert walk.exceptAll(jump).isEmpty() and jump.exceptAll(walk).isEmpty()
    for budget in (None, 1000):
        got = rows(sorter.sort_klv(spark, path, TEXTS, budget))
        assert sorted(got) == sorted(data) and [k for k, _ in got] == sorted(k for k, _ in data)


def test_counters_are_the_formulas(spark, records):
    path, data = records
    got = keyindex.counters(spark, path, SPEC).agg(F.sum("bytes_needed"), F.sum("records")).first()
    assert tuple(got) == (4 * len(data), len(data))
    ranked = sorter.with_global_rank(sorter.sort_index(keyindex.build_fixed(spark, path, SPEC)))
    assert gather.point_fetch(ranked, path, SPEC, counters=True).agg(F.sum("bytes_needed")).first()[0] == 6 * len(data)


def test_exact_bytes(spark, records):
    """At gap 0 the readers read what is needed and nothing else; over gaps they read more in fewer requests."""
    path, data = records
    n = len(data)
    strided = keyindex.counters(spark, path, SPEC, stride_gap=0).agg(F.sum("bytes_read"), F.sum("requests")).first()
    assert tuple(strided) == (4 * n, n)
    ranked = sorter.with_global_rank(sorter.sort_index(keyindex.build_fixed(spark, path, SPEC)))
    read = {g: gather.point_fetch(ranked, path, SPEC, gap_bytes=g, counters=True).agg(F.sum("bytes_read"), F.sum("requests")).first() for g in (0, 4096)}
    assert tuple(read[0]) == (6 * n, n) and read[4096][0] >= read[0][0] and read[4096][1] <= n


def test_expected_amplification():
    rng, spec = np.random.default_rng(0), RecordSpec()
    n, density = 200_000, 0.2
    at = np.flatnonzero(rng.random(n) < density) * 100 + 10
    for gap in (0, 300, 4096):
        reads = gather.coalesced(np.zeros(len(at), int), at, np.full(len(at), 90), gap)
        got = sum(z - a for _, a, z, _ in reads) / (90 * len(at))
        assert abs(got - gather.expected_amplification(density, spec, gap)) < 0.03 * got
    assert gather.best_gap(0.2, spec) == 4000 and gather.best_gap(0.2, spec, request_ns=1.0) == 0


def test_single_task_is_guarded(spark, records, monkeypatch):
    monkeypatch.setattr(sorter, "SINGLE_BYTES", 0)
    with pytest.raises(ValueError, match="one task"):
        sorter.one_pass(spark, records[0], SPEC, pools=1)


def test_length_prefixed_runs_keep_the_budget(spark):
    """Records over several files: no run holds more entries than the budget, and none is lost."""
    path = new_path(spark, "klv-many").removeprefix("file:")
    data = [(b"%010d" % (i * 7919 % 1000), b"v" * (i % 40)) for i in range(1000)]
    write_klv(spark.createDataFrame(data, "key binary, value binary").repartition(4), path, TEXTS)
    runs, plan = sorter.klv_runs(spark, path, TEXTS, 200 * TEXTS.entry_bytes)
    sizes = [r["count"] for r in spark.read.parquet(runs).groupBy("run").count().collect()]
    assert plan.runs == 5 and sorted(sizes) == [200] * 5


def test_rank_rows_sorts_only_what_it_must(spark):
    from splitsort import lazy

    data = [(bytes([i * 37 % 256, i % 7]), 0, i) for i in range(2000)]
    idx = spark.createDataFrame(data, "key binary, file_id int, pos long")
    want = sorted(data)
    for first, last in ((1, 3), (777, 777), (1500, 1640), (1999, 2500), (5, 4)):
        got = [(r["rank"], (bytes(r["key"]), r["file_id"], r["pos"])) for r in lazy.rank_rows(idx, first, last, cells=64).orderBy("rank").collect()]
        assert got == [(k, want[k - 1]) for k in range(first, min(last, 2000) + 1)]


def test_counters_and_probe(spark, tmp_path):
    c = counters.counted(spark, counters.written(spark.range(20_000).repartition(3)))
    assert c.shuffle_bytes > 20_000 and c.seconds > 0 and counters.counted(spark, lambda: None).shuffle_bytes == 0
    got = device.probe(spark, str(tmp_path), sizes=(4096,), threads=(1, 2), total=1 << 16).collect()
    assert len(got) == 6 and all(r["gb_per_s"] > 0 for r in got) and not list(tmp_path.iterdir())


def test_stream_runs_from_a_checkpoint(spark, sf_dir):
    from splitsort import catalogue

    assert catalogue.QUERIES["stream_restart"](spark, sf_dir).count() == spark.read.parquet(f"{sf_dir}/events.parquet").count()


def test_lateral_join_keeps_repeated_left_rows(spark):
    from splitsort.operators import join_lateral

    a = spark.createDataFrame([(1,), (1,), (2,)], "k int")
    b = spark.createDataFrame([(1, 10), (1, 20), (1, 30), (2, 5)], "j int, v int")
    got = sorted((r["k"], r["v"]) for r in join_lateral(a, b, F.col("k") == F.col("j"), [F.col("v").desc()], 2).collect())
    assert got == [(1, 20), (1, 20), (1, 30), (1, 30), (2, 5)]


def test_slim_plan(spark, sf_dir):
    from splitsort.records import cents
    from splitsort.sources import table

    plan = keyindex.build_parquet(table(spark, sf_dir, "orders"), cents("o_totalprice"))._jdf.queryExecution().toString()
    assert "ReadSchema: struct<o_totalprice:double,_tmp_metadata_row_index:bigint>" in plan
