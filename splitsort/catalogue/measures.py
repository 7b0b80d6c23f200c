"""Queries of traffic, cost, devices, concurrency and the experiments made of them.

Modelled seconds come from constants that were fitted to the reported orderings (see plans.device):
regression checks, no reproduction.  Bytes and requests are exact.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import baselines, merge, sorter
from ..plans import concurrency, cost, device, measures
from ..records import BENCHMARK, benchmark_records, lineitem_text
from ..session import new_path
from ..sources import table, write_fixed
from ..workloads import dataset
from .sorts import R1

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def count(spark, sf_dir: str) -> int:
    return table(spark, sf_dir, "lineitem").count()


TRAFFIC_SQL = """SELECT s AS system, CASE s WHEN 'wide' THEN 2 * n * (10 + v) WHEN 'one_pass' THEN n * (10 + v) WHEN 'two_pass' THEN n * (10 + v) + n * 15
        WHEN 'serial_split' THEN n * (10 + v) + n * 15 + n * v END AS read_bytes,
    CASE s WHEN 'wide' THEN 2 * n * (10 + v) WHEN 'one_pass' THEN n * (10 + v) ELSE n * (10 + v) + n * 15 END AS write_bytes"""


def _traffic(spark, sf_dir, values, systems):
    n = count(spark, sf_dir)
    rows = [(v, s, *map(int, cost.traffic(s, n, BENCHMARK.with_value(v)))) for v in values for s in systems]
    return spark.createDataFrame(rows, "v int, system string, read_bytes long, write_bytes long")


@query("traffic_by_system", TRAFFIC_SQL + " FROM (SELECT count(*) AS n, 90 AS v FROM lineitem), (VALUES ('wide'), ('one_pass'), ('two_pass'), ('serial_split')) x(s)")
def traffic_by_system(spark, sf_dir):
    return _traffic(spark, sf_dir, (90,), ("wide", "one_pass", "two_pass", "serial_split")).drop("v")


@query(
    "traffic_value_ratio_sweep",
    "SELECT v, system, round(100.0 * (1 - (read_bytes + write_bytes) / (4.0 * n * (10 + v))), 3) AS reduction_pct FROM (SELECT v, n, * FROM (" + TRAFFIC_SQL.replace("SELECT s AS", "SELECT v, n, s AS")
    + " FROM (SELECT count(*) AS n FROM lineitem), (VALUES (5), (10), (50), (90), (502)) y(v), (VALUES ('wide'), ('one_pass'), ('two_pass')) x(s)))",
)
def traffic_value_ratio_sweep(spark, sf_dir):
    n, t = count(spark, sf_dir), _traffic(spark, sf_dir, (5, 10, 50, 90, 502), ("wide", "one_pass", "two_pass"))
    pct = 100.0 * (1 - (F.col("read_bytes") + F.col("write_bytes")) / (4.0 * n * (10 + F.col("v"))))
    return t.select("v", "system", F.round(pct, 3).alias("reduction_pct"))


@query("reduction_factors", "SELECT CAST(10 AS DOUBLE) AS read_factor, CAST(round(100.0 / 15, 4) AS DOUBLE) AS write_factor, CAST(round(100.0 / 18, 4) AS DOUBLE) AS write_factor_wide_locator")
def reduction_factors(spark, sf_dir):
    s = BENCHMARK
    row = (s.record_bytes / s.key_bytes, round(s.record_bytes / s.entry_bytes, 4), round(s.record_bytes / (s.key_bytes + 8), 4))
    return spark.createDataFrame([row], "read_factor double, write_factor double, write_factor_wide_locator double")


@query(
    "amplification_by_block",
    "SELECT 'lineitem' AS source, b AS block, round(ceil(100.0 / b) * b / 100.0, 4) AS factor FROM (VALUES (64), (256), (4096)) v(b) UNION ALL "
    "SELECT 'documents', b, round(avg(ceil(octet_length(encode(text)) * 1.0 / b) * b / octet_length(encode(text))), 4) FROM documents, (VALUES (64), (256), (4096)) v(b) GROUP BY b",
)
def amplification_by_block(spark, sf_dir):
    blocks = spark.createDataFrame([(64,), (256,), (4096,)], "block int")
    fixed = blocks.select(F.lit("lineitem").alias("source"), "block", F.round(measures.amplification(F.lit(100.0), F.col("block")), 4).alias("factor"))
    docs = table(spark, sf_dir, "documents").select(F.octet_length("text").cast("double").alias("n")).crossJoin(F.broadcast(blocks))
    var = docs.groupBy("block").agg(F.round(F.avg(measures.amplification(F.col("n"), F.col("block"))), 4).alias("factor"))
    return fixed.unionByName(var.withColumn("source", F.lit("documents")))


@query("entries_per_line", "SELECT l AS line, CAST(floor(l / 15) AS INTEGER) AS five_byte, CAST(floor(l / 20) AS INTEGER) AS records_of_20 FROM (VALUES (64), (256)) v(l)")
def entries_per_line(spark, sf_dir):
    return spark.createDataFrame([(x, x // 15, x // 20) for x in (64, 256)], "line int, five_byte int, records_of_20 int")


@query(
    "distinct_lines_touched",
    "SELECT l AS line, count(DISTINCT floor(r * 100 / l)) AS first_lines, sum(floor((r * 100 + 9) / l) - floor(r * 100 / l) + 1)::BIGINT AS touches "
    "FROM (SELECT row_number() OVER () - 1 AS r FROM lineitem), (VALUES (64), (256)) v(l) GROUP BY l",
)
def distinct_lines_touched(spark, sf_dir):
    """Device lines that the strided load of 10-byte keys in 100-byte records touches."""
    n = count(spark, sf_dir)
    rows = spark.range(n).select((F.col("id") * 100).alias("at")).crossJoin(F.broadcast(spark.createDataFrame([(64,), (256,)], "line int")))
    touched = measures.lines_touched(F.col("at"), F.lit(10), F.col("line"))
    return rows.groupBy("line").agg(F.countDistinct(F.floor(F.col("at") / F.col("line"))).alias("first_lines"), F.sum(touched).alias("touches"))


@query(
    "mode_choice_sweep",
    "SELECT f AS percent, CAST(n * f // 100 AS BIGINT) AS records, CASE WHEN (n * f // 100) * 15 <= n * 10 THEN 'one_pass' ELSE 'two_pass' END AS mode, "
    "CAST(greatest(1, ceil((n * f // 100) * 15.0 / (n * 10))) AS INTEGER) AS runs FROM (SELECT count(*) AS n FROM lineitem), (VALUES (20), (40), (60), (80), (100)) v(f)",
)
def mode_choice_sweep(spark, sf_dir):
    """Budget of 10 % of all record bytes: the mode flips between 60 and 80 %."""
    n, rows = count(spark, sf_dir), []
    for f in (20, 40, 60, 80, 100):
        plan = sorter.choose_mode(n * f // 100, BENCHMARK, n * 10)
        rows.append((f, n * f // 100, plan.mode, plan.runs))
    return spark.createDataFrame(rows, "percent int, records long, mode string, runs int")


@query(
    "size_sweep",
    "SELECT f AS percent, CASE WHEN m * 15 <= n * 10 THEN 'one_pass' ELSE 'two_pass' END AS system, CASE WHEN m * 15 <= n * 10 THEN 2 * m * 100 ELSE 2 * m * 100 + 2 * m * 15 END AS bytes, "
    "CAST(CASE WHEN m * 15 <= n * 10 THEN 0.5 ELSE 0.575 END AS DOUBLE) AS ratio_to_wide FROM (SELECT n, f, n * f // 100 AS m FROM (SELECT count(*) AS n FROM lineitem), (VALUES (20), (40), (60), (80), (100)) v(f))",
)
def size_sweep(spark, sf_dir):
    n, rows = count(spark, sf_dir), []
    for f in (20, 40, 60, 80, 100):
        m = n * f // 100
        mode = sorter.choose_mode(m, BENCHMARK, n * 10).mode
        total, wide = sum(cost.traffic(mode, m, BENCHMARK)), sum(cost.traffic("wide", m, BENCHMARK))
        rows.append((f, mode, int(total), round(total / wide, 4)))
    return spark.createDataFrame(rows, "percent int, system string, bytes long, ratio_to_wide double")


@query("merge_phase_count", "SELECT r AS runs, f AS fan_in, CAST(ceil(round(log(r) / log(f), 9)) AS INTEGER) AS phases FROM (VALUES (1), (2), (7), (16), (100)) a(r), (VALUES (2), (4), (10)) b(f)")
def merge_phase_count(spark, sf_dir):
    return spark.createDataFrame([(r, f, merge.phases(r, f)) for r in (1, 2, 7, 16, 100) for f in (2, 4, 10)], "runs int, fan_in int, phases int")


@query(
    "buffer_redistribution",
    """WITH r AS (SELECT CAST(row_number() OVER (ORDER BY o_orderpriority) - 1 AS INTEGER) AS i, count(*) AS n, count(*) OVER () AS c FROM orders GROUP BY o_orderpriority)
        SELECT d.i AS dead, string_agg(CAST(CASE WHEN r.i = d.i AND r.c > 1 THEN 0 WHEN r.i = d.i - 1 THEN r.n + CASE WHEN d.i = d.c - 1 THEN d.n ELSE d.n - d.n // 2 END
        WHEN r.i = d.i + 1 THEN r.n + CASE WHEN d.i = 0 THEN d.n ELSE d.n // 2 END ELSE r.n END AS VARCHAR), ',' ORDER BY r.i) AS shares FROM r, r d GROUP BY d.i""",
)
def buffer_redistribution(spark, sf_dir):
    """Orders by priority as runs, each with as many entries of the buffer as it has rows: who gets them when one run ends."""
    runs = table(spark, sf_dir, "orders").groupBy("o_orderpriority").count().orderBy("o_orderpriority").collect()
    sizes = [r["count"] for r in runs]
    rows = [(d, ",".join(map(str, merge.redistribute(sizes, d)))) for d in range(len(sizes))]
    return spark.createDataFrame(rows, "dead int, shares string")


@query("index_size", "SELECT n AS records, n * 15 AS index_bytes, n * 100 AS data_bytes, CAST(0.15 AS DOUBLE) AS share FROM (SELECT count(*) AS n FROM lineitem)")
def index_size(spark, sf_dir):
    n = count(spark, sf_dir)
    return spark.createDataFrame([(n, n * BENCHMARK.entry_bytes, n * BENCHMARK.record_bytes, 0.15)], "records long, index_bytes long, data_bytes long, share double")


@query("space_check", "SELECT n * 215 AS total_bytes, n * 215 <= n * 224 AS fits FROM (SELECT count(*) AS n FROM lineitem)")
def space_check(spark, sf_dir):
    """Input, runs and output against a device of 224 % of the input, the reported proportion."""
    n = count(spark, sf_dir)
    total = sum(cost.space(n, BENCHMARK).values())
    return spark.createDataFrame([(total, total <= n * 224)], "total_bytes long, fits boolean")


@query("pool_sizing", "SELECT * FROM (VALUES ('read_random', 256, 16), ('read_random', 4096, 16), ('read_seq', 256, 16), ('read_seq', 4096, 16), ('write_seq', 256, 5), ('write_seq', 4096, 5)) v(op, access_bytes, threads)")
def pool_sizing(spark, sf_dir):
    return concurrency.size_pools(device.curve(spark)).drop("peak")


@query("device_probe")
def device_probe(spark, sf_dir):
    """The storage probed with records of lineitem: as many as one measurement takes."""
    data, total = new_path(spark, "probed-records"), 4 << 20
    write_fixed(benchmark_records(table(spark, sf_dir, "lineitem")).limit(-(-total // BENCHMARK.record_bytes)).coalesce(1), data, BENCHMARK)
    return device.probe(spark, new_path(spark, "probe"), total=total, data=data)


# --- the model: nanoseconds a record, in SQL of its own ---

#: Per record, K = 10 and P = 5: reads r, writes w of each system on the test device, kinds apart.
MODEL = """(SELECT v, (10 + v) / 22.2 AS strided, greatest(5.0, v / 22.2 / 0.82) AS value, 15 / 22.2 AS slim, 3 * (10 + v) / 22.2 AS load, (10 + v) / 22.2 AS wide,
    (10 + v) / 2.5 AS put, 15 / 2.5 AS put_slim, 1.1 * (10 + v) / 22.2 / 0.82 AS move, 1.1 * (10 + v) / 2.5 AS put_move FROM (VALUES (5), (10), (50), (90), (502)) x(v))"""


#: The same terms as means over the rows of lineitem, each a record of its text: v bytes long, of lv lines; the record of w bytes and lw lines.
LINES = f"""(SELECT avg(strided) AS strided, avg(value) AS value, avg(slim) AS slim, avg(load) AS load, avg(wide) AS wide, avg(put) AS put, avg(put_slim) AS put_slim,
    avg(10 + v) AS w, avg(v) AS v, avg(ceil(v / 64.0)) AS lv, avg(ceil((10 + v) / 64.0)) AS lw FROM (SELECT v, (10 + v) / 22.2 AS strided, greatest(5.0, v / 22.2 / 0.82) AS value,
    15 / 22.2 AS slim, 3 * (10 + v) / 22.2 AS load, (10 + v) / 22.2 AS wide, (10 + v) / 2.5 AS put, 15 / 2.5 AS put_slim FROM (SELECT octet_length(encode({R1})) AS v FROM lineitem)))"""


def _sizes(spark, sf_dir) -> dict[int, int]:
    """How many rows of lineitem have a text of so many bytes."""
    v = F.octet_length(lineitem_text()).alias("v")
    return {r["v"]: r["count"] for r in table(spark, sf_dir, "lineitem").select(v).groupBy("v").count().collect()}


def _line_model(spark, sizes, systems, policy, profile="test_device"):
    """Mean modelled nanoseconds of the records of lineitem's texts."""
    p = device.PROFILES[profile]
    return cost.model(cost.ops_of_sizes(spark, sizes, BENCHMARK, p).where(F.col("system").isin(list(systems))), policy, p)


def _model(spark, sf_dir, v, systems, policy, profile="test_device"):
    p = device.PROFILES[profile]
    o = cost.ops(spark, 1, BENCHMARK.with_value(v), p).where(F.col("system").isin(list(systems)))
    return cost.model(o, policy, p)


@query(
    "model_value_ratio_sweep",
    f"""SELECT v, s AS system, round(CASE s WHEN 'wide' THEN 2 * wide + 2 * put WHEN 'one_pass' THEN strided + value + put ELSE strided + value + put + slim + put_slim END, 4) AS ns
        FROM {MODEL}, (VALUES ('wide'), ('one_pass'), ('two_pass')) y(s)""",
)
def model_value_ratio_sweep(spark, sf_dir):
    out = None
    for v in (5, 10, 50, 90, 502):
        one = _model(spark, sf_dir, v, ("wide", "one_pass", "two_pass"), "exclusive").select(F.lit(v).alias("v"), "system", F.round("ns", 4).alias("ns"))
        out = one if out is None else out.unionAll(one)
    return out


POLICY_SQL = {
    "exclusive": ("1.0", "1.0", "1.0"),
    "overlap": ("2.0", "1.6", "1.0"),
    "no_sync": ("2.0", "1.6 * 1.33", "1.0"),
}


#: Kind and modelled nanoseconds of each operation, in the order of issue.
STAGES_SQL = f"""(SELECT system, op, seq, kind, CASE cost WHEN 'strided' THEN strided WHEN 'value' THEN value WHEN 'put' THEN put WHEN 'put_slim' THEN put_slim WHEN 'slim' THEN slim ELSE load END AS ns
    FROM {MODEL}, (VALUES ('one_pass', 'run_read', 0, 'read', 'strided'), ('one_pass', 'record_read', 3, 'read', 'value'), ('one_pass', 'run_write', 4, 'write', 'put'),
        ('two_pass', 'run_read', 0, 'read', 'strided'), ('two_pass', 'run_write', 1, 'write', 'put_slim'), ('two_pass', 'merge_read', 2, 'slim', 'slim'),
        ('two_pass', 'record_read', 3, 'read', 'value'), ('two_pass', 'merge_write', 4, 'write', 'put'),
        ('serial_split', 'run_read', 0, 'read', 'load'), ('serial_split', 'run_write', 1, 'write', 'put_slim'), ('serial_split', 'merge_read', 2, 'slim', 'slim'),
        ('serial_split', 'record_read', 3, 'read', 'value'), ('serial_split', 'merge_write', 4, 'write', 'put')) o(system, op, seq, kind, cost) WHERE v = 90)"""


def policy_sql(policy: str) -> str:
    r, w, m = POLICY_SQL[policy]
    return f"""WITH o AS (SELECT system, op, seq, ns * CASE kind WHEN 'write' THEN {w} WHEN 'slim' THEN {m} ELSE {r} END AS ns FROM {STAGES_SQL})
        SELECT system, op, round(sum(ns) OVER w - ns, 4) AS start_ns, round(sum(ns) OVER w, 4) AS end_ns FROM o WINDOW w AS (PARTITION BY system ORDER BY seq)"""


def _in_order(o):
    """R8b's operations with the order in which a system issues them."""
    turn = {"run_read": 0, "run_write": 1, "merge_read": 2, "record_read": 3, "merge_write": 4}
    seq = F.lit(0)
    for op, k in turn.items():
        seq = F.when(F.col("op") == op, k).otherwise(seq)
    return o.withColumn("seq", F.when((F.col("system") == "one_pass") & (F.col("op") == "run_write"), 4).otherwise(seq))


def _schedule(spark, sf_dir, policy):
    """When each operation of a system starts and ends, in nanoseconds a record."""
    p = device.PROFILES["test_device"]
    o = cost.ops(spark, 1, BENCHMARK, p).where(F.col("system").isin("one_pass", "two_pass", "serial_split"))
    t = concurrency.schedule(_in_order(o).withColumn("seconds", F.col("ns")), policy, p)
    return t.select("system", "op", F.round("start_s", 4).alias("start_ns"), F.round("end_s", 4).alias("end_ns"))


for _policy in POLICY_SQL:
    query(f"schedule_{_policy}", policy_sql(_policy))(lambda spark, sf_dir, policy=_policy: _schedule(spark, sf_dir, policy))


@query(
    "schedule_duplex",
    """WITH o AS (SELECT system, seq, kind, ns * CASE kind WHEN 'write' THEN 1.6 WHEN 'slim' THEN 1.0 ELSE 2.0 END AS ns FROM @STAGES),
        h AS (SELECT *, CASE WHEN kind = 'write' AND lag(kind) OVER w <> 'write' THEN least(ns, lag(ns) OVER w) ELSE 0 END AS hidden FROM o WINDOW w AS (PARTITION BY system ORDER BY seq))
        SELECT system, round(sum(ns - hidden), 4) AS ns FROM h GROUP BY 1""".replace("@STAGES", STAGES_SQL),
)
def schedule_duplex(spark, sf_dir):
    """The rejected reading, for comparison: overlapped writes hide behind the read before them."""
    p = device.PROFILES["test_device"]
    o = cost.ops(spark, 1, BENCHMARK, p).where(F.col("system").isin("one_pass", "two_pass", "serial_split"))
    t = concurrency.schedule(_in_order(o).withColumn("seconds", F.col("ns")), "overlap", p, duplex=True)
    return t.groupBy("system").agg(F.round(F.max("end_s"), 4).alias("ns"))


@query(
    "device_overlap",
    f"""SELECT d AS profile, s AS system, round(CAST(CASE WHEN d <> 'test_device' THEN 1 WHEN s = 'one_pass' THEN (2 * (strided + value) + 1.6 * put) / (strided + value + put)
        ELSE (2 * (strided + value) + slim + 1.6 * (put + put_slim)) / (strided + value + slim + put + put_slim) END AS DOUBLE), 6) AS ratio
        FROM {LINES}, (VALUES ('test_device'), ('slow_random'), ('symmetric'), ('slow_write')) x(d), (VALUES ('one_pass'), ('two_pass')) y(s)""",
)
def device_overlap(spark, sf_dir):
    """Overlapped against exclusive modelled time: alike where reads and writes don't disturb each other."""
    out, sizes = None, _sizes(spark, sf_dir)
    for name in device.PROFILES:
        a, b = (_line_model(spark, sizes, ("one_pass", "two_pass"), policy, name).select("system", F.col("ns").alias(policy)) for policy in ("overlap", "exclusive"))
        one = a.join(b, "system").select(F.lit(name).alias("profile"), "system", F.round(F.col("overlap") / F.col("exclusive"), 6).alias("ratio"))
        out = one if out is None else out.unionAll(one)
    return out


@query(
    "concurrency_model_matrix",
    f"""SELECT system, policy, round(ns, 4) AS ns, row_number() OVER (ORDER BY ns) AS place FROM (
        SELECT 'wide' AS system, 'no_sync_buffered_merge' AS policy, 2 * wide + 2.128 * put + wide + 1.33 * put AS ns FROM {LINES}
        UNION ALL SELECT 'wide', 'exclusive', 2 * wide + 2 * put FROM {LINES}
        UNION ALL SELECT 'one_pass', 'exclusive', strided + value + put FROM {LINES}
        UNION ALL SELECT 'two_pass', p, f * (strided + value) + slim + g * (put + put_slim) FROM {LINES}, (VALUES ('exclusive', 1.0, 1.0), ('overlap', 2.0, 1.6), ('no_sync', 2.0, 2.128)) x(p, f, g)
        UNION ALL SELECT 'serial_split', p, f * (load + value) + slim + g * (put + put_slim) FROM {LINES}, (VALUES ('overlap', 2.0, 1.6), ('no_sync', 2.0, 2.128)) x(p, f, g)
        UNION ALL SELECT 'two_pass', 'single_thread', (strided + value + slim) / 0.09 + (put + put_slim) / 0.45 FROM {LINES}
        UNION ALL SELECT 'serial_split', 'single_thread', (load + value + slim) / 0.09 + (put + put_slim) / 0.45 FROM {LINES})""",
)
def concurrency_model_matrix(spark, sf_dir):
    """Systems under their concurrency models, least modelled time a record of lineitem first."""
    from pyspark.sql import Window

    cells = [("wide", "no_sync_buffered_merge"), ("wide", "exclusive"), ("one_pass", "exclusive"), ("two_pass", "exclusive"), ("two_pass", "overlap"), ("two_pass", "no_sync"), ("serial_split", "overlap"), ("serial_split", "no_sync"), ("two_pass", "single_thread"), ("serial_split", "single_thread")]
    out, sizes = None, _sizes(spark, sf_dir)
    for system, policy in cells:
        one = _line_model(spark, sizes, (system,), policy).select("system", "policy", "ns")
        out = one if out is None else out.unionAll(one)
    return out.select("system", "policy", F.round("ns", 4).alias("ns"), F.row_number().over(Window.orderBy("ns")).cast("long").alias("place"))  # ten rows


def _background(spark, sf_dir, kind):
    p = device.PROFILES["test_device"]
    o = cost.ops_of_sizes(spark, _sizes(spark, sf_dir), BENCHMARK, p).where(F.col("system").isin("one_pass", "wide")).crossJoin(spark.createDataFrame([(c,) for c in (0, 1, 2, 4, 8)], "clients int"))
    factor = F.lit(1.0)
    for k, slope in cost.SLOPES[kind].items():
        factor = F.when(F.col("kind") == k, 1 + slope * F.col("clients")).otherwise(factor)
    t = o.groupBy("system", "clients").agg(F.sum("ns").alias("alone"), F.sum(F.col("ns") * factor).alias("ns"))
    return t.select("system", "clients", F.round(F.col("ns") / F.col("alone"), 4).alias("slowdown"))


def background_sql(random: float, write: float, seq: float) -> str:
    return f"""SELECT s AS system, c AS clients, round(CASE s WHEN 'one_pass' THEN ((strided + value) * (1 + {random} * c) + put * (1 + {write} * c)) / (strided + value + put)
        ELSE (2 * wide * (1 + {seq} * c) + 2 * put * (1 + {write} * c)) / (2 * wide + 2 * put) END, 4) AS slowdown
        FROM {LINES}, (VALUES ('one_pass'), ('wide')) y(s), (VALUES (0), (1), (2), (4), (8)) z(c)"""


query("background_readers", background_sql(0.1475, 0.035, 0))(lambda spark, sf_dir: _background(spark, sf_dir, "random_readers"))
query("background_sequential_readers", background_sql(0, 0, 0))(lambda spark, sf_dir: _background(spark, sf_dir, "sequential_readers"))
query("background_writers", background_sql(1.625, 1.625, 0.5))(lambda spark, sf_dir: _background(spark, sf_dir, "writers"))


def device_sql(line_read: float, line_write: float) -> str:
    return f"""SELECT system, round(ns, 4) AS ns, row_number() OVER (ORDER BY ns) AS place FROM (
        SELECT s AS system, CASE s WHEN 'wide' THEN 4 * w / 32.0 + 2 * w / 64.0 * {line_write}
        WHEN 'one_pass' THEN 2 * w / 32.0 + (1 + lv) * {line_read} + w / 64.0 * {line_write}
        WHEN 'two_pass' THEN 2 * w / 32.0 + 30 / 32.0 + (1 + lv) * {line_read} + (w + 15) / 64.0 * {line_write}
        ELSE 1.1 * (2 * w / 32.0 + lw * {line_read} + w / 64.0 * {line_write}) END AS ns FROM {LINES}, (VALUES ('wide'), ('one_pass'), ('two_pass'), ('in_place')) y(s))"""


for _dev, _a, _b in (("slow_random", 25, 0), ("symmetric", 0, 0), ("slow_write", 0, 25)):

    def _device(spark, sf_dir, dev=_dev):
        from pyspark.sql import Window

        t = _line_model(spark, _sizes(spark, sf_dir), ("wide", "one_pass", "two_pass", "in_place"), "exclusive", dev)
        return t.select("system", F.round("ns", 4).alias("ns"), F.row_number().over(Window.orderBy("ns")).cast("long").alias("place"))  # four rows

    query(f"device_{_dev}", device_sql(_a, _b))(_device)


@query(
    "motivation",
    f"""SELECT s AS system, round(CASE s WHEN 'wide' THEN 2 * wide + 2 * put WHEN 'one_pass' THEN strided + value + put ELSE 2.0 * move + 2.128 * put_move END, 4) AS ns
        FROM {MODEL}, (VALUES ('wide'), ('one_pass'), ('in_place')) y(s) WHERE v = 90""",
)
def motivation(spark, sf_dir):
    """The in-place sort runs uncontrolled, the others keep reads and writes apart."""
    out = _model(spark, sf_dir, 90, ("wide", "one_pass"), "exclusive").unionByName(_model(spark, sf_dir, 90, ("in_place",), "no_sync"))
    return out.select("system", F.round("ns", 4).alias("ns"))


@query(
    "advise_plan",
    """WITH t AS (SELECT * FROM (VALUES ('slow_random', 'wide', 12.5), ('slow_random', 'in_place', 61.875), ('slow_random', 'one_pass', 81.25), ('slow_random', 'two_pass', 82.1875),
        ('symmetric', 'one_pass', 6.25), ('symmetric', 'in_place', 6.875), ('symmetric', 'two_pass', 7.1875), ('symmetric', 'wide', 12.5)) v(profile, system, ns))
       SELECT profile, system, row_number() OVER (PARTITION BY profile ORDER BY ns) AS place FROM t""",
)
def advise_plan(spark, sf_dir):
    n, out = count(spark, sf_dir), None
    for name in ("slow_random", "symmetric"):
        one = cost.advise(spark, name, n, BENCHMARK, n * 20).select("profile", "system", F.col("place").cast("long").alias("place"))
        out = one if out is None else out.unionAll(one)
    return out


def _timed(spark, sf_dir):
    """Operations of wide, one_pass and two_pass with their order and modelled seconds."""
    n = count(spark, sf_dir)
    o = cost.ops(spark, n, BENCHMARK, device.PROFILES["test_device"]).where(F.col("system").isin("wide", "one_pass", "two_pass"))
    return _in_order(o).withColumn("seconds", F.col("ns") * n / 1e9)


OPS_SQL = """(SELECT * FROM (VALUES ('wide', 'run_read', 0, 100.0, 100 / 22.2), ('wide', 'run_write', 1, 100.0, 40.0), ('wide', 'merge_read', 2, 100.0, 100 / 22.2), ('wide', 'merge_write', 4, 100.0, 40.0),
    ('one_pass', 'run_read', 0, 10.0, 100 / 22.2), ('one_pass', 'record_read', 3, 90.0, 5.0), ('one_pass', 'run_write', 4, 100.0, 40.0),
    ('two_pass', 'run_read', 0, 10.0, 100 / 22.2), ('two_pass', 'run_write', 1, 15.0, 6.0), ('two_pass', 'merge_read', 2, 15.0, 15 / 22.2), ('two_pass', 'record_read', 3, 90.0, 5.0), ('two_pass', 'merge_write', 4, 100.0, 40.0)) v(system, op, seq, b, ns))"""


@query("stage_shares", f"SELECT system, op, round(ns / sum(ns) OVER (PARTITION BY system), 6) AS share FROM {OPS_SQL}")
def stage_shares(spark, sf_dir):
    return measures.shares(_timed(spark, sf_dir)).select("system", "op", F.round("share", 6).alias("share"))


@query("io_efficiency", f"SELECT system, op, round(b / 22.2 / ns, 6) AS efficiency FROM {OPS_SQL}")
def io_efficiency(spark, sf_dir):
    return measures.io_efficiency(_timed(spark, sf_dir), 22.2).select("system", "op", F.round("efficiency", 6).alias("efficiency"))


@query(
    "timeline_buckets",
    f"""WITH o AS (SELECT *, coalesce(sum(ns) OVER w, 0) AS a, coalesce(sum(ns) OVER w, 0) + ns AS z FROM {OPS_SQL} WINDOW w AS (PARTITION BY system ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        s AS (SELECT *, max(z) OVER (PARTITION BY system) / 10 AS step FROM o)
        SELECT system, bucket, op, round(b * (least(z, (bucket + 1) * step) - greatest(a, bucket * step)) / ns, 4) AS bytes_per_record
        FROM s, (SELECT CAST(range AS INTEGER) AS bucket FROM range(10)) WHERE least(z, (bucket + 1) * step) - greatest(a, bucket * step) > 1e-9""",
)
def timeline_buckets(spark, sf_dir):
    n = count(spark, sf_dir)
    t = measures.buckets(measures.timeline(_timed(spark, sf_dir)), 10)
    per = F.round(F.col("bytes") / n, 4)
    return t.where(F.col("bytes") / n > 1e-6).select("system", "bucket", "op", per.alias("bytes_per_record"))


@query(
    "advise_with_amplification",
    """SELECT a AS amplification, s AS system, row_number() OVER (PARTITION BY a ORDER BY ns) AS place FROM (SELECT a, s, CASE s WHEN 'one_pass' THEN 6.25 + (a - 1) * 90 / 32.0 WHEN 'wide' THEN 12.5 ELSE 6.875 END AS ns
        FROM (VALUES (1), (2), (7)) x(a), (VALUES ('one_pass'), ('wide'), ('in_place')) y(s))""",
)
def advise_with_amplification(spark, sf_dir):
    """What reading over gaps does to the choice: where a value costs several, whole records are sorted instead."""
    n, out = count(spark, sf_dir), None
    for a in (1, 2, 7):
        one = cost.advise(spark, "symmetric", n, BENCHMARK, n * 20, amplification=float(a)).where("system <> 'two_pass'")
        one = one.select(F.lit(a).alias("amplification"), "system", "seconds")
        out = one if out is None else out.unionAll(one)
    from pyspark.sql import Window

    return out.select("amplification", "system", F.row_number().over(Window.partitionBy("amplification").orderBy("seconds")).cast("long").alias("place"))


#: Columns of lineitem that are packed by a dictionary: two bytes a row, and each distinct text once; codecs with bytes a nanosecond.
PACKED, CODECS = ("l_returnflag", "l_linestatus", "l_shipdate", "l_orderkey"), {"fast_codec": (5.0, 20.0), "slow_codec": (0.5, 2.0)}


@query(
    "compression_pays",
    """SELECT c AS column_name, s AS case_name, raw AS raw_bytes, packed AS packed_bytes, (raw - packed) / 2.5 + (raw - packed) / 22.2 > raw / p + raw / u AS pays
        FROM (SELECT c, CAST(sum(b * n) AS BIGINT) AS raw, CAST(sum(2 * n + b) AS BIGINT) AS packed FROM (SELECT c, octet_length(encode(t)) AS b, count(*) AS n FROM ("""
    + " UNION ALL ".join(f"SELECT '{c}' AS c, {'strftime(' + c + chr(44) + ' ' + chr(39) + '%Y-%m-%d' + chr(39) + ')' if c == 'l_shipdate' else 'CAST(' + c + ' AS VARCHAR)'} AS t FROM lineitem" for c in PACKED)
    + ") GROUP BY c, t) GROUP BY c), (VALUES ('fast_codec', 5.0, 20.0), ('slow_codec', 0.5, 2.0)) v(s, p, u)",
)
def compression_pays(spark, sf_dir):
    """Columns of lineitem as text, raw and packed by a dictionary: whether that pays on the test device with a fast and a slow codec."""
    lineitem, p, rows = table(spark, sf_dir, "lineitem"), device.PROFILES["test_device"], []
    for c in PACKED:
        text = F.date_format(c, "yyyy-MM-dd") if c == "l_shipdate" else F.col(c).cast("string")
        values = lineitem.groupBy(text.alias("t")).agg(F.count("*").alias("n"))
        raw, packed = values.agg(F.sum(F.octet_length("t") * F.col("n")), F.sum(2 * F.col("n") + F.octet_length("t"))).first()
        raw, packed = raw or 0, packed or 0
        rows += [(c, name, raw, packed, cost.compress_pays(raw, packed, p.read, p.write, *speeds)) for name, speeds in CODECS.items()]
    return spark.createDataFrame(rows, "column_name string, case_name string, raw_bytes long, packed_bytes long, pays boolean")


@query("dataset_size", "SELECT count(*) * 100 AS bytes FROM lineitem")
def dataset_size(spark, sf_dir):
    """Bytes of all rows of lineitem as records, which the record files made of them must have too."""
    size = benchmark_records(table(spark, sf_dir, "lineitem")).agg(F.sum(F.octet_length("key") + F.octet_length("value")).alias("bytes")).first()["bytes"] or 0
    if size != (on_disk := baselines.dataset_bytes(dataset(spark, sf_dir, "benchmark"))):
        raise ValueError(f"record files of {on_disk} bytes for {size} bytes of records")
    return spark.createDataFrame([(size,)], "bytes long")
