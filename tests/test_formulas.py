"""Closed forms, and the pure parts of merge, gather and mode choice."""

import numpy as np
import pyarrow as pa
import pytest

from splitsort import gather, merge, sorter
from splitsort.plans import cost
from splitsort.records import BENCHMARK, RecordSpec
from splitsort.sources.fixedrec import split_ranges


@pytest.mark.parametrize(("v", "pct"), [(90, 42.5), (502, 48.5), (50, 37.5)])
def test_two_pass_reduction(v, pct):
    s = BENCHMARK.with_value(v)
    wide, two = sum(cost.traffic("wide", 1000, s)), sum(cost.traffic("two_pass", 1000, s))
    assert round(100 * (1 - two / wide), 1) == pytest.approx(pct, abs=0.05)
    assert sum(cost.traffic("one_pass", 1000, s)) * 2 == wide
    assert wide - two == 2 * 1000 * (v - 5)


def test_mode_edge_and_runs():
    gb = 10**9
    assert sorter.choose_mode(133 * gb // 100, BENCHMARK, 20 * gb).mode == "one_pass"
    assert sorter.choose_mode(134 * gb // 100, BENCHMARK, 20 * gb).mode == "two_pass"
    assert sorter.choose_mode(160 * gb // 100, BENCHMARK, 20 * gb).runs == 2
    assert sorter.choose_mode(200 * gb // 100, BENCHMARK, 20 * gb).index_bytes == 30 * gb


def test_split_ranges():
    assert split_ranges(10, 3) == [(0, 3), (3, 6), (6, 10)]
    assert split_ranges(0, 4) == [] and split_ranges(2, 9) == [(0, 1), (1, 2)]


def test_redistribute_keeps_the_sum():
    shares = merge.first_shares(100, 7)
    for dead in (3, 0, 6, 1):
        shares = merge.redistribute(shares, dead)
        assert sum(shares) == 100 and shares[dead] == 0
    assert merge.redistribute([30, 31, 30], 1) == [46, 0, 45]


def _stream(rows, size):
    for k in range(0, len(rows), size):
        cols = zip(*rows[k : k + size], strict=True)
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.binary(), pa.int32(), pa.int64()), strict=True)], list(merge.BY))


def test_merge_against_sorted():
    rng = np.random.default_rng(0)
    slices = [sorted((bytes(rng.integers(0, 3, 2, dtype=np.uint8)), r, i) for i in range(n)) for r, n in enumerate((0, 1, 50, 7))]
    for buffer in (1, 4, 1000):
        trace = dict.fromkeys(merge.TRACE, 0)
        out = [tuple(r.values()) for t in merge.merge_streams([_stream(s, 8) for s in slices], buffer, trace) for r in t.to_pylist()]
        assert out == sorted(x for s in slices for x in s)
        assert trace["refills"] >= 3 and trace["compared"] + trace["drained"] == 58
    apart, trace = [[(b"%03d" % i, r, i) for i in range(100 * r, 100 * r + 40)] for r in range(2)], dict.fromkeys(merge.TRACE, 0)
    out = [x for t in merge.merge_streams([_stream(s, 8) for s in apart], 8, trace) for x in t.column("pos").to_pylist()]
    assert out == [*range(40), *range(100, 140)] and trace["drained"] >= 30  # one run outlives the other
    trace = dict.fromkeys(merge.TRACE, 0)
    assert list(merge.merge_streams([], 10, trace)) == [] and not any(trace.values())
    assert [merge.phases(r, 4) for r in (1, 4, 5, 16, 17)] == [0, 1, 2, 2, 3]


def test_merge_holds_no_more_than_its_buffer(monkeypatch):
    rng, most, held = np.random.default_rng(1), [0], {}
    refill = merge.Cursor.refill

    def counted(self, entries):
        got = refill(self, entries)
        held[id(self)] = 0 if self.held is None else self.held.num_rows
        if entries is not None:
            most[0] = max(most[0], sum(held.values()))
        return got

    monkeypatch.setattr(merge.Cursor, "refill", counted)
    slices = [sorted((rng.bytes(4), r, i) for i in range(500)) for r in range(6)]
    trace = dict.fromkeys(merge.TRACE, 0)
    out = [tuple(r.values()) for t in merge.merge_streams([_stream(s, 64) for s in slices], 60, trace) for r in t.to_pylist()]
    assert out == sorted(x for s in slices for x in s)
    assert most[0] <= 60 and trace["refills"] >= 40 and trace["comparisons"] <= 5 * 3000


def test_offset_queue_fills():
    batch = pa.RecordBatch.from_arrays([pa.array(range(23))], ["pos"])
    q = gather.OffsetQueue(10)
    full = list(q.put(batch.slice(0, 4), np.ones(4, np.int64))) + list(q.put(batch.slice(4), np.ones(19, np.int64)))
    assert [sum(b.num_rows for b in f) for f in full] == [10, 10]
    assert sum(b.num_rows for b in q.flush()) == 3 and q.fills == 3
    long = list(q.put(batch, np.full(23, 50)))  # values longer than the buffer go alone
    assert [sum(b.num_rows for b in f) for f in long] == [1] * 22


def test_coalesced_reads():
    f, a, n = np.array([0, 1, 0, 0]), np.array([100, 0, 0, 12]), np.array([10, 5, 10, 10])
    reads = [(x[0], x[1], x[2]) for x in gather.coalesced(f, a, n, 2)]
    assert reads == [(0, 0, 22), (0, 100, 110), (1, 0, 5)]
    assert len(gather.coalesced(f, a, n, 0)) == 4


def test_entry_sizes():
    assert BENCHMARK.entry_bytes == 15 and RecordSpec(length_bytes=4).entry_bytes == 19
    assert cost.space(2 * 10**9, BENCHMARK) == {"input": 200 * 10**9, "runs": 30 * 10**9, "output": 200 * 10**9}
