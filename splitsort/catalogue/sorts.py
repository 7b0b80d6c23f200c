"""Queries of the sorting methods, their variants and baselines, and of lazy use."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import baselines, gather, keyindex, lazy, merge, sorter, validate
from ..functions import encode_sort_key
from ..plans import concurrency, device
from ..records import BENCHMARK, TEXTS, cents, lineitem_text, packed, unpacked
from ..session import new_path, staged
from ..sources import table, with_locator, write_fixed
from ..workloads import dataset

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


#: R1 in SQL: the joined text of a lineitem row.
R1 = """concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, CAST(round(l_quantity * 100) AS BIGINT),
    CAST(round(l_extendedprice * 100) AS BIGINT), CAST(round(l_discount * 100) AS BIGINT), CAST(round(l_tax * 100) AS BIGINT),
    l_returnflag, l_linestatus, strftime(l_shipdate, '%Y-%m-%d'))"""
SORTED = f"""SELECT row_number() OVER (ORDER BY key_hex) AS rank, key_hex, md5(rpad(t, 90, ' ')) AS value_md5
    FROM (SELECT substr(md5(t), 1, 20) AS key_hex, t FROM (SELECT {R1} AS t FROM lineitem))"""


def shown(df: DataFrame) -> DataFrame:
    return df.select("rank", F.lower(F.hex("key")).alias("key_hex"), F.md5("value").alias("value_md5"))


def bench(spark: SparkSession, sf_dir: str) -> str:
    return dataset(spark, sf_dir, "benchmark")


def budget_of(path: str, share: float = 0.10) -> int:
    """A memory budget as a share of the record bytes, at which the slim index needs two passes."""
    return int(share * baselines.dataset_bytes(path))


def _published(spark: SparkSession) -> concurrency.ConcurrencyPlan:
    """The controller's plan from the bandwidth curve that comes with the test device."""
    return concurrency.plan_of(concurrency.size_pools(device.curve(spark)))


def _probed(spark: SparkSession) -> concurrency.ConcurrencyPlan:
    """The controller's plan from a probe of the storage that the shared folder is on."""
    return concurrency.plan_of(concurrency.size_pools(device.probe(spark, new_path(spark, "probe"))), "no_sync")


SORTS = {
    "split_one_pass_sort": lambda s, p: sorter.one_pass(s, p, BENCHMARK),
    "split_one_pass_unbuffered": lambda s, p: sorter.one_pass(s, p, BENCHMARK, buffered=False),
    "split_one_pass_single_pool": lambda s, p: sorter.one_pass(s, p, BENCHMARK, pools=1),
    "split_one_pass_sequential_load": lambda s, p: sorter.one_pass(s, p, BENCHMARK, access="sequential"),
    "split_two_pass_sort": lambda s, p: sorter.two_pass(s, p, BENCHMARK, budget_of(p)),
    "split_two_pass_multi_phase": lambda s, p: sorter.two_pass(s, p, BENCHMARK, budget_of(p, 0.02), fan_in=3),
    "split_sort_auto_mode": lambda s, p: sorter.sort_records(s, p, BENCHMARK, budget_of(p)),
    "wide_merge_sort": lambda s, p: baselines.wide_merge(s, p, BENCHMARK),
    "wide_merge_exclusive": lambda s, p: baselines.wide_merge(s, p, BENCHMARK, policy="exclusive"),
    "wide_in_memory_sort": lambda s, p: baselines.wide_in_memory(s, p, BENCHMARK),
    "inplace_sample_sort": lambda s, p: baselines.sample_sort(s, p, BENCHMARK),
    "resorting_key_sort": lambda s, p: baselines.resorting_key_sort(s, p, BENCHMARK),
    "serial_split_sort": lambda s, p: baselines.serial_split(s, p, BENCHMARK, budget_of(p)),
    "serial_split_no_sync": lambda s, p: baselines.serial_split(s, p, BENCHMARK, budget_of(p), "no_sync"),
    "serial_split_overlap": lambda s, p: baselines.serial_split(s, p, BENCHMARK, budget_of(p), "overlap"),
    "serial_split_quick_sort": lambda s, p: baselines.serial_split(s, p, BENCHMARK, budget_of(p), run_sort="quick"),
    "inplace_in_memory_sort": lambda s, p: baselines.sample_sort(s, p, BENCHMARK, device="memory"),
    "inplace_sample_sort_recursive": lambda s, p: baselines.sample_sort(s, p, BENCHMARK, fanout=4, bucket_bytes=baselines.dataset_bytes(p) // 40),
    "split_one_pass_exact_bytes": lambda s, p: sorter.one_pass(s, p, BENCHMARK, stride_gap=0, gap_bytes=0),
    "split_one_pass_refetched_key": lambda s, p: sorter.one_pass(s, p, BENCHMARK, refetch_key=True),
    "split_one_pass_overlap": lambda s, p: sorter.one_pass(s, p, BENCHMARK, policy="overlap"),
    "split_one_pass_exclusive": lambda s, p: sorter.one_pass(s, p, BENCHMARK, policy="exclusive"),
    "split_two_pass_overlap": lambda s, p: sorter.two_pass(s, p, BENCHMARK, budget_of(p), policy="overlap"),
    "split_two_pass_exclusive": lambda s, p: sorter.two_pass(s, p, BENCHMARK, budget_of(p), policy="exclusive"),
    "split_two_pass_single_thread": lambda s, p: sorter.two_pass(s, p, BENCHMARK, budget_of(p), parts=1, read_pool=1),
    "split_one_pass_published_pools": lambda s, p: sorter.one_pass(s, p, BENCHMARK, plan=_published(s)),
    "split_two_pass_published_pools": lambda s, p: sorter.two_pass(s, p, BENCHMARK, budget_of(p), plan=_published(s)),
    "split_one_pass_probed_pools": lambda s, p: sorter.one_pass(s, p, BENCHMARK, plan=_probed(s)),
}
for _name, _sort in SORTS.items():
    query(_name, SORTED)(lambda spark, sf_dir, _sort=_sort: shown(_sort(spark, bench(spark, sf_dir))))


def klv_sql(source: str, key: str, text: str) -> str:
    return f"""SELECT row_number() OVER (ORDER BY k) AS rank, k AS key_hex, octet_length(encode({text})) AS vlength, md5({text}) AS text_md5
        FROM (SELECT substr(md5({key}), 1, 20) AS k, {text} FROM {source})"""


def klv_shown(df: DataFrame) -> DataFrame:
    return df.select("rank", F.lower(F.hex("key")).alias("key_hex"), F.col("vlength").cast("long").alias("vlength"), F.md5("value").alias("text_md5"))


KLV = {
    "klv_one_pass_documents": ("documents", "CAST(doc_id AS VARCHAR)", "text", False, True),
    "klv_serial_walk_documents": ("documents", "CAST(doc_id AS VARCHAR)", "text", False, False),
    "klv_two_pass_pages": ("pages", "url", "html", True, True),
    "ratio_small_key_large_value": ("pages", "url", "html", False, True),
    "klv_sort_conversations": ("conversations", "concat_ws('|', conv_id, turn)", "text", True, True),
}
for _name, (_t, _k, _x, _two, _anchors) in KLV.items():

    def _klv(spark, sf_dir, t=_t, two=_two, anchors=_anchors):
        path = dataset(spark, sf_dir, t)
        budget = 4000 if two else None  # forces two passes at every size
        return klv_shown(sorter.sort_klv(spark, path, TEXTS, budget, anchors))

    query(_name, klv_sql(_t, _k, _x))(_klv)


def _index_sql() -> str:
    return f"SELECT substr(md5({R1}), 1, 20) AS key_hex, count(*) AS entries FROM lineitem GROUP BY 1"


@query("slim_index_fixed", _index_sql())
def slim_index_fixed(spark, sf_dir):
    idx = keyindex.build_fixed(spark, bench(spark, sf_dir), BENCHMARK)
    return idx.groupBy(F.lower(F.hex("key")).alias("key_hex")).agg(F.countDistinct("file_id", "pos").alias("entries"))


@query("slim_index_sequential", _index_sql())
def slim_index_sequential(spark, sf_dir):
    idx = keyindex.build_fixed(spark, bench(spark, sf_dir), BENCHMARK, access="sequential")
    return idx.groupBy(F.lower(F.hex("key")).alias("key_hex")).agg(F.countDistinct("file_id", "pos").alias("entries"))


@query("slim_index_parquet", "SELECT o_orderkey, CAST(round(o_totalprice * 100) AS BIGINT) AS price_cents FROM orders")
def slim_index_parquet(spark, sf_dir):
    idx = keyindex.build_parquet(table(spark, sf_dir, "orders"), cents("o_totalprice"))
    wide = with_locator(table(spark, sf_dir, "orders").select("o_orderkey", "_metadata"))
    return gather.locator_join(idx.withColumnRenamed("key", "rank"), wide, ["file_path", "row_index"]).select("o_orderkey", F.col("rank").alias("price_cents"))


@query(
    "slim_index_klv_offsets",
    "SELECT sum(14 + octet_length(encode(text)))::BIGINT AS bytes, count(*) AS records, sum(octet_length(encode(text)))::BIGINT AS value_bytes FROM documents",
)
def slim_index_klv_offsets(spark, sf_dir):
    """Offsets chain: each value starts a head after the end of the one before; the ends sum to the files' bytes."""
    idx = keyindex.build_klv(spark, dataset(spark, sf_dir, "documents"), TEXTS)
    ends = idx.groupBy("file_id").agg(F.max(F.col("pos") + F.col("vlength")).alias("end"), F.count("*").alias("n"), F.sum("vlength").alias("v"))
    return ends.agg(F.sum("end").alias("bytes"), F.sum("n").alias("records"), F.sum("v").alias("value_bytes"))


@query(
    "run_catalogue",
    """WITH n AS (SELECT count(*) AS n FROM lineitem), r AS (SELECT n, CAST(ceil(n * 15.0 / floor(0.1 * n * 100)) AS BIGINT) AS runs FROM n),
       c AS (SELECT n, runs, CAST(ceil(n * 1.0 / runs) AS BIGINT) AS per FROM r)
       SELECT CAST(k AS INTEGER) AS run, least(per, n - k * per) AS entries FROM c, range(0, 1000) t(k) WHERE k < runs""",
)
def run_catalogue(spark, sf_dir):
    path = bench(spark, sf_dir)
    n = baselines.dataset_bytes(path) // BENCHMARK.record_bytes
    plan = sorter.choose_mode(n, BENCHMARK, budget_of(path))
    runs = sorter.write_runs(keyindex.build_fixed(spark, path, BENCHMARK), plan, sorter.record_number(path, BENCHMARK))
    return spark.read.parquet(runs).groupBy("run").agg(F.count("*").alias("entries"))


ORDERS = """SELECT row_number() OVER (ORDER BY CAST(round(o_totalprice * 100) AS BIGINT), o_orderdate, o_orderpriority, o_orderkey) AS rank,
    o_orderkey, o_orderstatus FROM orders"""


def _orders_ranked(spark, sf_dir):
    """The slim index of orders: an encoded composite key and the Parquet locator."""
    orders = table(spark, sf_dir, "orders")
    parts = [(cents("o_totalprice"), "bigint", True, True), (F.col("o_orderdate"), "timestamp_ntz", True, True), (F.col("o_orderpriority"), "string", True, True), (F.col("o_orderkey"), "bigint", True, True)]
    return sorter.with_global_rank(sorter.sort_index(keyindex.build_parquet(orders, encode_sort_key(parts))))


def _orders_wide(spark, sf_dir):
    return with_locator(table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus", "_metadata")).drop("_metadata")


@query("gather_point_fetch", ORDERS)
def gather_point_fetch(spark, sf_dir):
    wide = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus")
    return gather.parquet_fetch(_orders_ranked(spark, sf_dir), wide).select("rank", "o_orderkey", "o_orderstatus")


@query("gather_file_local", ORDERS)
def gather_file_local(spark, sf_dir):
    wide = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus")
    return gather.parquet_fetch(_orders_ranked(spark, sf_dir), wide, sweep=True).select("rank", "o_orderkey", "o_orderstatus")


@query("gather_broadcast_rank", ORDERS)
def gather_broadcast_rank(spark, sf_dir):
    ranked = _orders_ranked(spark, sf_dir)
    return gather.broadcast_rank(ranked, _orders_wide(spark, sf_dir), ["file_path", "row_index"], ranked.count()).select("rank", "o_orderkey", "o_orderstatus")


@query("gather_locator_join", ORDERS)
def gather_locator_join(spark, sf_dir):
    return gather.locator_join(_orders_ranked(spark, sf_dir), _orders_wide(spark, sf_dir), ["file_path", "row_index"]).select("rank", "o_orderkey", "o_orderstatus")


@query("gather_file_local_records", SORTED)
def gather_file_local_records(spark, sf_dir):
    path = bench(spark, sf_dir)
    ranked = sorter.with_global_rank(sorter.sort_index(keyindex.build_fixed(spark, path, BENCHMARK)))
    return shown(gather.file_local_fetch(ranked, path, BENCHMARK))


@query("sort_validity", "SELECT count(*) AS rows, CAST(0 AS BIGINT) AS descents, CAST(0 AS BIGINT) AS gaps, true AS same_rows FROM lineitem")
def sort_validity(spark, sf_dir):
    path = bench(spark, sf_dir)
    out = staged(sorter.one_pass(spark, path, BENCHMARK), "sorted")
    a = validate.checksum(keyindex.records(spark, path, BENCHMARK), ["key", "value"])
    b = validate.checksum(out, ["key", "value"])
    same = a.join(b.withColumnsRenamed({c: f"{c}2" for c in ("n", "xor", "total")}), F.lit(True))
    same = same.select(F.col("n2").alias("rows"), ((F.col("n") == F.col("n2")) & (F.col("xor") == F.col("xor2")) & F.col("total").eqNullSafe(F.col("total2"))).alias("same_rows"))
    return same.join(validate.order_violations(out), F.lit(True)).select("rows", "descents", "gaps", "same_rows")


@query("buffer_sweep", f"SELECT b AS batch_bytes, count(*) AS rows, bit_xor(CAST('0x' || substr(h, 1, 15) AS BIGINT)) AS checksum FROM (SELECT md5(rank || key_hex || value_md5) AS h FROM ({SORTED})), (VALUES (65536), (1048576), (16777216)) v(b) GROUP BY b")
def buffer_sweep(spark, sf_dir):
    """The output for three sizes of the write buffer: the same rows at the same ranks."""
    path = bench(spark, sf_dir)
    ranked = sorter.with_global_rank(sorter.sort_index(keyindex.build_fixed(spark, path, BENCHMARK)))
    out = None
    for size in (65536, 1048576, 16777216):
        rows = shown(gather.point_fetch(ranked, path, BENCHMARK, batch_bytes=size)).withColumn("batch_bytes", F.lit(size))
        out = rows if out is None else out.unionAll(rows)
    h = F.conv(F.substring(F.md5(F.concat("rank", "key_hex", "value_md5")), 1, 15), 16, 10).cast("long")
    return out.groupBy("batch_bytes").agg(F.count("*").alias("rows"), F.bit_xor(h).alias("checksum"))


@query(
    "compressed_runs",
    f"""SELECT c AS codec, count(*) AS entries, count(DISTINCT k) AS keys, bit_xor(CAST('0x' || substr(md5(k), 1, 15) AS BIGINT)) AS checksum
        FROM (SELECT substr(md5({R1}), 1, 20) AS k FROM lineitem), (VALUES ('none'), ('snappy'), ('zstd'), ('delta')) v(c) GROUP BY c""",
)
def compressed_runs(spark, sf_dir):
    """Runs by codec, and as differences; the entries that come back are the same, at their places too.

    The index is sorted once for all codecs, and all that comes back meets it in one merge join.
    """
    idx = keyindex.build_fixed(spark, bench(spark, sf_dir), BENCHMARK)
    back, h = None, F.conv(F.substring(F.md5(F.lower(F.hex("key"))), 1, 15), 16, 10).cast("long")
    ordered = sorter.sort_index(idx).persist(StorageLevel.DISK_ONLY)
    for codec in ("none", "snappy", "zstd", "delta"):
        path, delta = new_path(spark, f"runs-{codec}"), codec == "delta"
        lazy.compress_runs(ordered, path, "zstd" if delta else codec, delta, ordered=True)
        rows = lazy.read_runs(spark, path, delta).withColumn("codec", F.lit(codec))
        back = rows if back is None else back.unionByName(rows)
    ordered.unpersist()
    met = back.join(idx.hint("merge"), ["key", "file_id", "pos"])
    return met.groupBy("codec").agg(F.count("*").alias("entries"), F.countDistinct("key").alias("keys"), F.bit_xor(h).alias("checksum"))


@query("packed_runs", f"SELECT n * 15 AS bytes, key_hex, value_md5 FROM ({SORTED}), (SELECT count(*) AS n FROM lineitem)")
def packed_runs(spark, sf_dir):
    """The sorted index as records of key and five-byte record number on disk, read back, and the values fetched by it."""
    path, out = bench(spark, sf_dir), new_path(spark, "packed")
    slim = BENCHMARK.with_value(BENCHMARK.locator_bytes)
    idx = keyindex.build_fixed(spark, path, BENCHMARK)
    ordered = sorter.sort_index(idx, 4).select("key", packed(sorter.record_number(path, BENCHMARK)).alias("value"))
    write_fixed(ordered, out, slim)
    back = keyindex.records(spark, out, slim).select("key", unpacked(F.col("value")).alias("number"))
    got = gather.point_fetch(sorter.locators(back, path, BENCHMARK), path, BENCHMARK)
    return got.select(F.lit(baselines.dataset_bytes(out)).cast("long").alias("bytes"), F.lower(F.hex("key")).alias("key_hex"), F.md5("value").alias("value_md5"))


@query("merge_trace", "SELECT 2 AS runs, count(*) AS entries, true AS refilled, true AS narrowed FROM lineitem")
def merge_trace(spark, sf_dir):
    """Counters of the merge: entries compared or drained, refills beyond the first of each slice, comparisons under full width."""
    path = bench(spark, sf_dir)
    plan = sorter.choose_mode(sorter.records_in(path, BENCHMARK), BENCHMARK, budget_of(path))
    parts = 4
    runs = sorter.write_runs(keyindex.build_fixed(spark, path, BENCHMARK), plan, sorter.record_number(path, BENCHMARK), parts)
    t = merge.merge_runs(spark, runs, plan.runs, parts, buffer_entries=256, trace=True).agg(*[F.sum(c).alias(c) for c in merge.TRACE])
    return t.select(
        F.lit(plan.runs).alias("runs"),
        (F.col("compared") + F.col("drained")).alias("entries"),
        (F.col("refills") > plan.runs * parts).alias("refilled"),
        (F.col("comparisons") <= F.col("compared") * (plan.runs - 1)).alias("narrowed"),
    )


@query("merge_trace_counters")
def merge_trace_counters(spark, sf_dir):
    """The same for each range, in full."""
    path = bench(spark, sf_dir)
    plan = sorter.choose_mode(sorter.records_in(path, BENCHMARK), BENCHMARK, budget_of(path, 0.02))
    runs = sorter.write_runs(keyindex.build_fixed(spark, path, BENCHMARK), plan, sorter.record_number(path, BENCHMARK), 4)
    return merge.merge_runs(spark, runs, plan.runs, 4, buffer_entries=1024, trace=True)


@query("klv_run_catalogue", "SELECT count(*) AS entries, true AS within_budget, CAST(ceil(count(*) * 19.0 / 4000) AS INTEGER) AS runs FROM documents")
def klv_run_catalogue(spark, sf_dir):
    """No run of length-prefixed records holds more entries than the budget, however the files are cut."""
    runs, plan = sorter.klv_runs(spark, dataset(spark, sf_dir, "documents"), TEXTS, 4000)
    sizes = spark.read.parquet(runs).groupBy("run").agg(F.count("*").alias("n"))
    return sizes.agg(F.sum("n").alias("entries"), (F.max("n") * TEXTS.entry_bytes <= 4000).alias("within_budget"), F.count("*").cast("int").alias("runs"))


@query("sample_sort_buckets", "SELECT count(*) AS rows, true AS fit, true AS recursed FROM lineitem")
def sample_sort_buckets(spark, sf_dir):
    """Buckets of the recursive classification: all records, none over the bound, and more than one level."""
    path = bench(spark, sf_dir)
    bound = baselines.dataset_bytes(path) // 40
    tree = baselines.classes(spark, path, BENCHMARK, 32, 4, bound)
    fit = all(c * BENCHMARK.record_bytes <= bound for b, c in tree.counts.items() if b % 2 == 0)
    return spark.createDataFrame([(sum(tree.counts.values()), fit, tree.levels > 1)], "rows long, fit boolean, recursed boolean")


# --- key distributions and typed keys ---



def _ranked_by(df: DataFrame, key, tie: list[str]) -> DataFrame:
    return sorter.with_global_rank(df.repartitionByRange(key, *tie).sortWithinPartitions(key, *tie))


def _indexed(df: DataFrame, parts: list, wide: list[str]) -> DataFrame:
    """A Parquet table in the order of encoded keys: index of keys and locators, rank, and the columns asked for by locator."""
    ranked = sorter.with_global_rank(sorter.sort_index(keyindex.build_parquet(df, encode_sort_key(parts))))
    return gather.fetch_or_join(ranked, df, wide).select("rank", *wide)


@query("key_ties", "SELECT row_number() OVER (ORDER BY o_orderpriority, o_orderkey) AS rank, o_orderkey AS id FROM orders")
def key_ties(spark, sf_dir):
    parts = [(F.col("o_orderpriority"), "string", True, True), (F.col("o_orderkey"), "bigint", True, True)]
    return _indexed(table(spark, sf_dir, "orders"), parts, ["o_orderkey"]).withColumnRenamed("o_orderkey", "id")


@query("key_presorted", "SELECT row_number() OVER (ORDER BY ts, event_id) AS rank, event_id AS id FROM events")
def key_presorted(spark, sf_dir):
    return _indexed(table(spark, sf_dir, "events"), [(F.col("ts"), "timestamp_ntz", True, True)], ["event_id"]).withColumnRenamed("event_id", "id")


@query("key_reversed", "SELECT row_number() OVER (ORDER BY ts DESC, event_id) AS rank, event_id AS id FROM events")
def key_reversed(spark, sf_dir):
    return _indexed(table(spark, sf_dir, "events"), [(F.col("ts"), "timestamp_ntz", False, False)], ["event_id"]).withColumnRenamed("event_id", "id")


@query("key_skew", f"SELECT row_number() OVER (ORDER BY l_returnflag, t) AS rank, md5(t) AS row_md5 FROM (SELECT l_returnflag, {R1} AS t FROM lineitem)")
def key_skew(spark, sf_dir):
    names = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
    parts = [(F.col("l_returnflag"), "string", True, True), (lineitem_text(), "string", True, True)]
    return _indexed(table(spark, sf_dir, "lineitem"), parts, names).select("rank", F.md5(lineitem_text()).alias("row_md5"))


@query("key_all_equal", "SELECT row_number() OVER (ORDER BY o_orderkey) AS rank, o_orderkey AS id FROM orders")
def key_all_equal(spark, sf_dir):
    """One key for all rows: the locator alone orders them, as they lie in the file."""
    return _indexed(table(spark, sf_dir, "orders"), [(F.lit(0), "int", True, True)], ["o_orderkey"]).withColumnRenamed("o_orderkey", "id")


TYPED = {
    "typed_key_long": ("orders", [("o_custkey", "bigint", True, True)], "o_orderkey", "o_custkey ASC NULLS FIRST"),
    "typed_key_double": ("customer", [("c_acctbal", "double", True, True)], "c_custkey", "c_acctbal ASC NULLS FIRST"),
    "typed_key_string": ("customer", [("c_mktsegment", "string", True, True)], "c_custkey", "c_mktsegment ASC NULLS FIRST"),
    "typed_key_timestamp": ("orders", [("o_orderdate", "timestamp_ntz", True, True)], "o_orderkey", "o_orderdate ASC NULLS FIRST"),
    "typed_key_composite_desc": ("orders", [("o_orderpriority", "string", False, False), ("o_custkey", "bigint", True, True)], "o_orderkey", "o_orderpriority DESC NULLS LAST, o_custkey ASC NULLS FIRST"),
}
for _name, (_t, _parts, _id, _order) in TYPED.items():

    def _typed(spark, sf_dir, t=_t, parts=_parts, i=_id):
        key = encode_sort_key([(F.col(c), kind, asc, first) for c, kind, asc, first in parts])
        return _ranked_by(table(spark, sf_dir, t).select(key.alias("key"), F.col(i).alias("id")), "key", ["id"]).select("rank", "id")

    query(_name, f"SELECT row_number() OVER (ORDER BY {_order}, {_id}) AS rank, {_id} AS id FROM {_t}")(_typed)


@query("typed_key_decimal", "SELECT row_number() OVER (ORDER BY CAST(o_totalprice AS DECIMAL(12,2)), o_orderkey) AS rank, o_orderkey AS id FROM orders")
def typed_key_decimal(spark, sf_dir):
    key = encode_sort_key([(F.col("o_totalprice").cast("decimal(12,2)"), "decimal(12,2)", True, True)])
    return _ranked_by(table(spark, sf_dir, "orders").select(key.alias("key"), F.col("o_orderkey").alias("id")), "key", ["id"]).select("rank", "id")


@query("typed_key_wide_decimal", "SELECT row_number() OVER (ORDER BY CAST(c_acctbal AS DECIMAL(38,2)) * 1000000000000000000000000 DESC, c_custkey) AS rank, c_custkey AS id FROM customer")
def typed_key_wide_decimal(spark, sf_dir):
    """Decimals beyond 64 bits."""
    key = encode_sort_key([((F.col("c_acctbal").cast("decimal(12,2)") * F.lit(10**12).cast("decimal(13,0)") * F.lit(10**12).cast("decimal(13,0)")).cast("decimal(38,2)"), "decimal(38,2)", False, False)])
    return _ranked_by(table(spark, sf_dir, "customer").select(key.alias("key"), F.col("c_custkey").alias("id")), "key", ["id"]).select("rank", "id")


@query("typed_key_nulls_last", "SELECT row_number() OVER (ORDER BY nullif(o_orderpriority, '1-URGENT') ASC NULLS LAST, o_orderkey) AS rank, o_orderkey AS id FROM orders")
def typed_key_nulls_last(spark, sf_dir):
    key = encode_sort_key([(F.expr("nullif(o_orderpriority, '1-URGENT')"), "string", True, False)])
    return _ranked_by(table(spark, sf_dir, "orders").select(key.alias("key"), F.col("o_orderkey").alias("id")), "key", ["id"]).select("rank", "id")


# --- ORDER BY, top-k, lazy use ---


@query("order_by_nonindexed", "SELECT row_number() OVER (ORDER BY o_totalprice, o_orderkey) AS rank, o_orderkey, o_orderstatus FROM orders")
def order_by_nonindexed(spark, sf_dir):
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice", "o_orderstatus")
    out = sorter.order_by(orders, [F.col("o_totalprice"), F.col("o_orderkey")], carry=orders, ids=["o_orderkey"])
    return out.select(F.col("rank").cast("long").alias("rank"), "o_orderkey", "o_orderstatus")


@query("topk_slim", "SELECT o_orderkey, o_orderstatus, CAST(round(o_totalprice * 100) AS BIGINT) AS price_cents FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100")
def topk_slim(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    best = sorter.top_k(orders, [F.col("o_totalprice").desc(), F.col("o_orderkey")], 100, ["o_orderkey"])
    return best.select("o_orderkey", "o_orderstatus", cents("o_totalprice").alias("price_cents"))


@query("topk_ties", "SELECT o_orderkey, o_orderdate FROM orders WHERE o_orderdate >= (SELECT min(d) FROM (SELECT o_orderdate AS d FROM orders ORDER BY 1 DESC LIMIT 50))")
def topk_ties(spark, sf_dir):
    return sorter.top_k_ties(table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate"), "o_orderdate", 50)


@query("kth_element", "SELECT o_orderkey, rank FROM (SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey) AS rank FROM orders) WHERE rank = 777")
def kth_element(spark, sf_dir):
    parts = [(F.col("o_totalprice"), "double", True, True), (F.col("o_orderkey"), "bigint", True, True)]
    idx = table(spark, sf_dir, "orders").select(encode_sort_key(parts).alias("key"), "o_orderkey")
    return lazy.rank_rows(idx, 777, 777).select("o_orderkey", F.col("rank").cast("long").alias("rank"))


RANGE_SQL = "FROM (SELECT key_hex, rank, value_md5 FROM (" + SORTED + "))"


@query("lazy_range", f"SELECT row_number() OVER (ORDER BY rank) AS rank, key_hex, value_md5 {RANGE_SQL} WHERE key_hex >= '40000000000000000000' AND key_hex < '48000000000000000000'")
def lazy_range(spark, sf_dir):
    path = bench(spark, sf_dir)
    idx = keyindex.build_fixed(spark, path, BENCHMARK)
    found = lazy.range_rows(idx, F.unhex(F.lit("40" + "0" * 18)), F.unhex(F.lit("48" + "0" * 18)))
    return shown(gather.point_fetch(found, path, BENCHMARK))


@query("lazy_rank_window", f"SELECT rank, key_hex, value_md5 {RANGE_SQL} WHERE rank BETWEEN 1001 AND 1100")
def lazy_rank_window(spark, sf_dir):
    path = bench(spark, sf_dir)
    found = lazy.rank_rows(keyindex.build_fixed(spark, path, BENCHMARK), 1001, 1100)
    return shown(gather.point_fetch(found, path, BENCHMARK))


SLIM_O, SLIM_L = "o_orderkey AS k, o_custkey", "l_orderkey AS k, l_linenumber, l_suppkey"
JOINS = {
    "index_join_inner": ("inner", "SELECT o.k, o_custkey, l_suppkey, l_linenumber FROM (SELECT {o} FROM orders) o JOIN (SELECT {l} FROM lineitem) l ON o.k = l.k"),
    "index_join_left": ("left", "SELECT o.k, o_custkey, l_suppkey, l_linenumber FROM (SELECT {o} FROM orders) o LEFT JOIN (SELECT {l} FROM lineitem) l ON o.k = l.k"),
    "index_join_semi": ("left_semi", "SELECT k, o_custkey FROM (SELECT {o} FROM orders) WHERE k IN (SELECT l_orderkey FROM lineitem)"),
    "index_join_anti": ("left_anti", "SELECT k, o_custkey FROM (SELECT {o} FROM orders) WHERE k NOT IN (SELECT l_orderkey FROM lineitem)"),
}
for _name, (_how, _sql) in JOINS.items():

    def _join(spark, sf_dir, how=_how):
        a = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k"), "o_custkey")
        b = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k"), "l_linenumber", "l_suppkey")
        return lazy.index_join(a, b, ["k"], how)

    query(_name, _sql.format(o=SLIM_O, l=SLIM_L))(_join)


@query("index_join_late_values", "SELECT o_orderkey, l_linenumber, o_orderstatus, c_mktsegment FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey WHERE l_quantity >= 49")
def index_join_late_values(spark, sf_dir):
    """Keys and locators are joined; the wide columns of what is left are read from the files by locator."""
    orders, customers = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer")
    place = lambda df, name: with_locator(df).withColumnsRenamed({"file_path": f"{name}_path", "row_index": f"{name}_row"})
    a = place(orders, "o").select("o_orderkey", "o_custkey", "o_path", "o_row")
    c = place(customers, "c").select(F.col("c_custkey").alias("o_custkey"), "c_path", "c_row")
    b = table(spark, sf_dir, "lineitem").where("l_quantity >= 49").select(F.col("l_orderkey").alias("o_orderkey"), "l_linenumber")
    slim = lazy.index_join(a, c, ["o_custkey"])
    out = lazy.index_join(slim, b, ["o_orderkey"], fetch=[(orders.select("o_orderstatus"), "o_path", "o_row"), (customers.select("c_mktsegment"), "c_path", "c_row")])
    return out.select("o_orderkey", "l_linenumber", "o_orderstatus", "c_mktsegment")
