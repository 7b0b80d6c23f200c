"""What a larger input brings out: bounds that hold, and rows that stay off the driver."""

import pytest
from pyspark.sql import functions as F

from splitsort import catalogue, sorter
from splitsort.records import TEXTS


def test_runs_hold_whole_entries():
    """211 entries of 19 bytes are nine bytes over a budget of 4000."""
    plan = sorter.choose_mode(51_282, TEXTS, 4000)
    assert plan.records_per_run * TEXTS.entry_bytes <= 4000 and plan.runs * plan.records_per_run >= 51_282


def test_an_index_over_the_broadcast_bound_is_joined_in_slices(spark):
    """ranks of an index that is larger than one broadcast."""
    from splitsort import gather

    ranked = spark.range(250).select(F.col("id").alias("k"), (F.col("id") + 1).alias("rank"))
    got = gather.broadcast_rank(ranked, spark.range(300).withColumnRenamed("id", "k"), ["k"], 250, bound=100)
    assert sorted((r["k"], r["rank"]) for r in got.collect()) == [(i, i + 1) for i in range(250)]


def test_compressed_runs_are_never_broadcast(spark, sf_dir):
    """the entries of the differences were taken for as small as their files' names, and sent to the driver."""
    got = catalogue.QUERIES["compressed_runs"](spark, sf_dir)
    assert "BroadcastHashJoin" not in got._jdf.queryExecution().executedPlan().toString()
    assert {(r["codec"], r["entries"]) for r in got.collect()} == {(c, 6000) for c in ("none", "snappy", "zstd", "delta")}


@pytest.mark.parametrize("name", ["stream_dedup", "stream_static_join", "stream_session"])  # F6, F7, F8
def test_results_of_streams_lie_in_files(spark, sf_dir, name):
    assert catalogue.QUERIES[name](spark, sf_dir).inputFiles()  # a memory sink has none: it holds its rows on the driver


def test_keys_in_random_order_are_joined_not_fetched(spark, sf_dir, monkeypatch):
    """point fetches decode a row group again for each batch that touches it."""
    from splitsort import gather, keyindex
    from splitsort.sources import table

    monkeypatch.setattr(gather, "LEAST_ROWS", 0)
    monkeypatch.setattr(gather, "GROUP_ROWS", 300)
    monkeypatch.setattr(gather, "BATCH_ROWS", 100)
    orders = table(spark, sf_dir, "orders")
    plans = {}
    for name, key in (("random", F.md5(F.col("o_orderkey").cast("string"))), ("as they lie", F.lit(0))):
        ranked = sorter.with_global_rank(sorter.sort_index(keyindex.build_parquet(orders, key)))
        monkeypatch.setattr(gather, "DECODED", 4)
        got = gather.fetch_or_join(ranked, orders, ["o_orderkey"])
        plans[name] = "MapInArrow" in got._jdf.queryExecution().toString()
        assert [r[0] for r in got.orderBy("rank").select("o_orderkey").collect()] == [r[1] for r in orders.select(key.alias("k"), "o_orderkey").orderBy("k", "o_orderkey").collect()]
    assert plans == {"random": False, "as they lie": True}


MODELS = ["background_readers", "background_sequential_readers", "background_writers", "buffer_redistribution", "compression_pays", "concurrency_model_matrix", "dataset_size", "device_overlap", "device_probe", "device_slow_random", "device_slow_write"]


@pytest.mark.parametrize("name", MODELS)
def test_measures_need_a_given_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):  # in a folder without tables there is nothing to tell
        catalogue.QUERIES[name](spark, str(tmp_path)).collect()


def test_value_ratio_sorts_leave_no_sorted_copy(spark, sf_dir):
    """15 sorted copies of the records, and as many of the ranked rows, lay side by side."""
    from splitsort.session import shared_dir
    from splitsort.sources import files

    def copies():
        system, name = files.opened(shared_dir(spark))
        found = system.get_file_info(files.fs.FileSelector(name))
        return {f.base_name for f in found if f.base_name.startswith(("sorted-", "ranked-wide", "ranked-one_pass", "ranked-two_pass", "slim-runs-"))}

    before = copies()
    assert catalogue.QUERIES["value_ratio_sorts"](spark, sf_dir).count() == 15
    assert not copies() - before


def test_value_ratio_sorts_write_each_row_once(spark, sf_dir, monkeypatch):
    """each sort's rows were written as a table, and read from it twice, besides the record files; the index was sorted again for the slim runs."""
    from splitsort import keyindex
    from splitsort.catalogue import measured

    staged, sorts, keep, order = [], [], measured.staged, sorter.sort_index
    monkeypatch.setattr(measured, "staged", lambda df, name: staged.append(name) or keep(df, name))
    monkeypatch.setattr(sorter, "sort_index", lambda idx, parts=None: sorts.append(parts) or order(idx, parts))
    assert keyindex.STRIDE_GAP > max(measured.VALUES)
    got = catalogue.QUERIES["value_ratio_sorts"](spark, sf_dir).collect()
    assert not staged and len(sorts) == 15  # the counted fetch, wide and one_pass, for each of five sizes
    assert len({r["checksum"] for r in got}) == 5 and {r["rows"] for r in got} == {6000}


@pytest.mark.parametrize("gap", [-1, 0, 30, 4096, 1 << 40])
@pytest.mark.parametrize("piece", [200, 8 << 20])
def test_values_on_a_grid_are_read_by_the_piece(tmp_path, monkeypatch, gap, piece):
    """every value took a call of several lines, and threads that waited for each other's turn."""
    import numpy as np

    from splitsort import gather

    rng = np.random.default_rng(3)
    blocks = [rng.integers(0, 256, (n, 25), dtype=np.uint8) for n in (400, 1, 300)]
    paths = [str(tmp_path / f"{i}.rec") for i in range(3)]
    for path, block in zip(paths, blocks, strict=True):
        block.tofile(path)
    f = rng.choice(3, 250, p=[0.5, 0.01, 0.49]).astype(np.int32)
    pos = np.array([rng.integers(len(blocks[i])) for i in f], np.int64)  # some of them twice
    monkeypatch.setattr(gather, "PIECE", piece)
    size = np.full(250, 15, np.int64)
    want = gather.coalesced(f, pos * 25 + 10, size, gap)
    for waits in (0.0, 1e9):
        monkeypatch.setattr(gather, "WAITS", waits)
        if waits:
            monkeypatch.setattr(gather, "ThreadPoolExecutor", None)  # reads that don't wait take no threads
        got, read, asked = gather.read_values(paths, f, pos * 25 + 10, size, gap, 4, 25)
        assert got.to_pylist() == [blocks[i][p, 10:].tobytes() for i, p in zip(f, pos, strict=True)]
        assert (read, asked) == (sum(z - a for _, a, z, _ in want), len(want))
        monkeypatch.undo()
        monkeypatch.setattr(gather, "PIECE", piece)
    with pytest.raises(ValueError, match="ends before"):
        gather.read_values(paths, f[:1] * 0 + 1, np.array([10 + 25]), size[:1], gap, 4, 25)


def test_bytes_of_records_are_not_copied_row_by_row():
    import numpy as np
    import pyarrow as pa

    from splitsort.sources import files

    column = pa.array([b"ab", b"cd", b"ef", b"gh"], pa.binary())
    got = files.byte_matrix(column.slice(1, 2), 2)
    assert got.tobytes() == b"cdef" and np.shares_memory(got, np.frombuffer(column.buffers()[2], np.uint8))
    for bad in ([b"ab", None], [b"ab", b"c"], [b"abc", b"c"]):
        with pytest.raises(ValueError, match="2 bytes"):
            files.byte_matrix(pa.array(bad, pa.binary()), 2)
