"""Queries of the operators, formats and functions around the sort."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import operators as op
from ..functions import encode_sort_key, order_checksum, register_all, slim_range
from ..records import TEXTS, cents
from ..session import new_path
from ..sources import read, table, write_sorted
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


def t(spark, sf_dir, *names):
    found = [table(spark, sf_dir, n) for n in names]
    return found[0] if len(found) == 1 else found


EQUI = "SELECT c_custkey, o_orderkey FROM customer JOIN orders ON c_custkey = o_custkey WHERE c_mktsegment = 'BUILDING'"


def _equi(how):
    def f(spark, sf_dir):
        c, o = t(spark, sf_dir, "customer", "orders")
        a = o.select("o_orderkey", F.col("o_custkey").alias("c_custkey"))
        b = op.where(c, "c_mktsegment = 'BUILDING'").select("c_custkey")
        return how(a, b).select("c_custkey", "o_orderkey")

    return f


query("join_broadcast", EQUI)(_equi(lambda a, b: op.join_broadcast(a, b, "c_custkey")))
query("join_shuffle_hash", EQUI)(_equi(lambda a, b: op.join_hash(a, b, "c_custkey")))
query("join_sort_merge", EQUI)(_equi(lambda a, b: op.join_sort_merge(a, b, "c_custkey")))
query("join_skew", EQUI)(_equi(lambda a, b: op.join_skew(a, b, "c_custkey")))


@query("join_theta", "SELECT s_suppkey, r_regionkey FROM supplier JOIN region ON s_nationkey % 5 > r_regionkey")
def join_theta(spark, sf_dir):
    s, r = t(spark, sf_dir, "supplier", "region")
    return op.join_theta(s, r, F.col("s_nationkey") % 5 > F.col("r_regionkey")).select("s_suppkey", "r_regionkey")


BANDS = "(SELECT CAST(k AS BIGINT) AS band, k * 7000.0 AS lo, k * 7000.0 + 9000.0 AS hi FROM range(0, 60) x(k))"


@query("join_range", f"SELECT o_orderkey, band FROM orders JOIN {BANDS} ON o_totalprice >= lo AND o_totalprice < hi")
def join_range(spark, sf_dir):
    bands = spark.range(60).select(F.col("id").alias("band"), (F.col("id") * 7000.0).alias("lo"), (F.col("id") * 7000.0 + 9000.0).alias("hi"))
    return op.join_range(t(spark, sf_dir, "orders"), bands, "o_totalprice", "lo", "hi", 7000.0).select("o_orderkey", "band")


SPANS = "SELECT event_id, user_id, epoch_us(ts) // 1000000 AS a, epoch_us(ts) // 1000000 + 600 AS z FROM events"


def _overlaps(e):
    at = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1000000)
    a = e.select(F.col("event_id").alias("left_id"), F.col("user_id").alias("u"), at.alias("a"), (at + 600).alias("z"))
    b = e.select(F.col("event_id").alias("right_id"), F.col("user_id").alias("v"), at.alias("c"), (at + 600).alias("d"))
    return op.join_overlap(a, b, "a", "z", "c", "d", 600).where("u < v").select("left_id", "right_id")


@query("join_interval", f"SELECT x.event_id AS left_id, y.event_id AS right_id FROM ({SPANS}) x JOIN ({SPANS}) y ON x.a < y.z AND y.a < x.z AND x.user_id < y.user_id")
def join_interval(spark, sf_dir):
    """Overlapping ten-minute spans of all events."""
    return _overlaps(t(spark, sf_dir, "events"))


@query(
    "join_asof",
    "SELECT p.event_id, q.event_id AS last_purchase FROM (SELECT * FROM events WHERE event_type <> 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') q ON p.user_id = q.user_id AND p.ts >= q.ts",
)
def join_asof(spark, sf_dir):
    e = t(spark, sf_dir, "events")
    left = e.where("event_type <> 'purchase'").select("user_id", "ts", "event_id")
    right = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("last_purchase"))
    return op.join_asof(left, right, ["user_id"], "ts", "last_purchase").select("event_id", "last_purchase")


@query("join_full_outer", "SELECT d.doc_id, l.doc_id AS label_id, quality FROM (SELECT doc_id FROM documents WHERE lang = 'en') d FULL JOIN labels l ON d.doc_id = l.doc_id")
def join_full_outer(spark, sf_dir):
    d, lab = t(spark, sf_dir, "documents", "labels")
    a, b = d.where("lang = 'en'").select("doc_id"), lab.select(F.col("doc_id").alias("label_id"), "quality")
    return op.join(a, b, F.col("doc_id") == F.col("label_id"), "full").select("doc_id", "label_id", "quality")


@query("join_cross", "SELECT n_nationkey, r_name FROM nation, region")
def join_cross(spark, sf_dir):
    n, r = t(spark, sf_dir, "nation", "region")
    return op.join_cross(n, F.broadcast(r)).select("n_nationkey", "r_name")


@query("join_lateral", "SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM customer JOIN orders ON c_custkey = o_custkey) WHERE k <= 2")
def join_lateral(spark, sf_dir):
    c, o = t(spark, sf_dir, "customer", "orders")
    out = op.join_lateral(c, o, F.col("c_custkey") == F.col("o_custkey"), [F.col("o_totalprice").desc(), F.col("o_orderkey")], 2)
    return out.select("c_custkey", "o_orderkey")


CENTS = "CAST(round(l_extendedprice * 100) AS BIGINT)"


def _aggs():
    return {"n": F.count("*"), "cents": F.sum(cents("l_extendedprice"))}


@query("agg_hash", f"SELECT l_returnflag, l_linestatus, count(*) AS n, sum({CENTS})::BIGINT AS cents FROM lineitem GROUP BY 1, 2")
def agg_hash(spark, sf_dir):
    return op.agg_hash(t(spark, sf_dir, "lineitem"), ["l_returnflag", "l_linestatus"], _aggs())


@query("agg_sorted", f"SELECT l_orderkey, count(*) AS n, sum({CENTS})::BIGINT AS cents FROM lineitem GROUP BY 1")
def agg_sorted(spark, sf_dir):
    return op.agg_sorted(t(spark, sf_dir, "lineitem"), "l_orderkey", _aggs())


@query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return op.agg_hash(t(spark, sf_dir, "lineitem"), ["l_returnflag"], {"suppliers": op.agg_distinct(None, "l_suppkey")})


for _kind, _sql in (("rollup", "ROLLUP (l_returnflag, l_linestatus)"), ("cube", "CUBE (l_returnflag, l_linestatus)")):
    query(f"agg_{_kind}", f"SELECT l_returnflag, l_linestatus, CAST(GROUPING_ID(l_returnflag, l_linestatus) AS BIGINT) AS gid, count(*) AS n, sum({CENTS})::BIGINT AS cents FROM lineitem GROUP BY {_sql}")(
        lambda spark, sf_dir, k=_kind: op.agg_cube(t(spark, sf_dir, "lineitem"), ["l_returnflag", "l_linestatus"], _aggs(), k == "rollup")
    )


@query("agg_grouping_sets", "SELECT l_returnflag, l_linenumber, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linenumber), ())")
def agg_grouping_sets(spark, sf_dir):
    df = t(spark, sf_dir, "lineitem")
    return df.groupingSets([[F.col("l_returnflag")], [F.col("l_linenumber")], []], "l_returnflag", "l_linenumber").agg(F.count("*").alias("n"))


@query("agg_pivot", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o FROM orders GROUP BY 1")
def agg_pivot(spark, sf_dir):
    p = op.agg_pivot(t(spark, sf_dir, "orders"), ["o_orderpriority"], "o_orderstatus", ["F", "O"], F.count(F.lit(1)))
    return p.select("o_orderpriority", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


@query(
    "agg_unpivot",
    "SELECT o_orderkey, 'price' AS name, CAST(round(o_totalprice * 100) AS BIGINT) AS value FROM orders UNION ALL SELECT o_orderkey, 'customer', o_custkey FROM orders",
)
def agg_unpivot(spark, sf_dir):
    o = t(spark, sf_dir, "orders").select("o_orderkey", cents("o_totalprice").alias("price"), F.col("o_custkey").alias("customer"))
    return op.unpivot(o, ["o_orderkey"], ["price", "customer"])


@query("agg_corr", "SELECT l_returnflag, round(corr(l_quantity, l_extendedprice), 6) AS corr FROM lineitem GROUP BY 1")
def agg_corr(spark, sf_dir):
    return op.agg_corr(t(spark, sf_dir, "lineitem"), ["l_returnflag"], "l_quantity", "l_extendedprice").select("l_returnflag", F.round("corr", 6).alias("corr"))


@query("agg_median", "SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.5), 4) AS median FROM orders GROUP BY 1")
def agg_median(spark, sf_dir):
    q = op.agg_quantile(t(spark, sf_dir, "orders"), ["o_orderpriority"], "o_totalprice", [0.5], exact=True)
    return q.select("o_orderpriority", F.round(F.col("quantiles")[0], 4).alias("median"))


@query("agg_filtered", "SELECT l_returnflag, count(*) FILTER (l_quantity > 25) AS large, count(*) FILTER (l_tax = 0) AS untaxed FROM lineitem GROUP BY 1")
def agg_filtered(spark, sf_dir):
    return op.agg_filtered(t(spark, sf_dir, "lineitem"), ["l_returnflag"], {"large": F.col("l_quantity") > 25, "untaxed": F.col("l_tax") == 0})


@query("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12")
def agg_having(spark, sf_dir):
    return op.agg_having(t(spark, sf_dir, "orders"), ["o_custkey"], {"n": F.count("*")}, "n > 12")


@query("agg_argmax", "SELECT o_custkey, max_by(o_orderkey, o_totalprice) AS o_orderkey FROM orders GROUP BY 1")
def agg_argmax(spark, sf_dir):
    return op.agg_argmax(t(spark, sf_dir, "orders"), ["o_custkey"], "o_orderkey", "o_totalprice")


@query("agg_collect", "SELECT o_custkey, string_agg(o_orderkey, ',' ORDER BY o_orderkey) AS keys FROM orders GROUP BY 1")
def agg_collect(spark, sf_dir):
    return op.agg_collect(t(spark, sf_dir, "orders"), ["o_custkey"], "o_orderkey").select("o_custkey", F.array_join("o_orderkey", ",").alias("keys"))


@query("agg_stats", "SELECT o_orderpriority, round(avg(o_totalprice), 3) AS mean, round(stddev_samp(o_totalprice), 3) AS deviation FROM orders GROUP BY 1")
def agg_stats(spark, sf_dir):
    return op.agg_stats(t(spark, sf_dir, "orders"), ["o_orderpriority"], "o_totalprice").select("o_orderpriority", F.round("mean", 3).alias("mean"), F.round("deviation", 3).alias("deviation"))


@query("agg_checksum", "SELECT count(*) AS n, bit_xor(CAST('0x' || substr(md5(CAST(o_orderkey AS VARCHAR)), 1, 15) AS BIGINT)) AS checksum FROM orders")
def agg_checksum(spark, sf_dir):
    h = F.conv(F.substring(F.md5(F.col("o_orderkey").cast("string")), 1, 15), 16, 10).cast("long")
    return t(spark, sf_dir, "orders").agg(F.count("*").alias("n"), F.bit_xor(h).alias("checksum"))


@query("agg_key_histogram", "SELECT upper(substr(md5(CAST(o_orderkey AS VARCHAR)), 1, 2)) AS prefix, count(*) AS n FROM orders GROUP BY 1")
def agg_key_histogram(spark, sf_dir):
    return op.agg_key_histogram(t(spark, sf_dir, "orders").select(F.unhex(F.md5(F.col("o_orderkey").cast("string"))).alias("key")))


W = "OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)"


@query("win_ranks", f"SELECT o_orderkey, row_number() {W} AS rn, rank() {W} AS rk, dense_rank() {W} AS dr, ntile(4) {W} AS quarter FROM orders")
def win_ranks(spark, sf_dir):
    return op.win_rank(t(spark, sf_dir, "orders"), ["o_custkey"], [F.col("o_totalprice"), F.col("o_orderkey")]).select("o_orderkey", "rn", "rk", "dr", "quarter")


SHARE = "OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey)"


@query("win_shares", f"SELECT o_orderkey, round(percent_rank() {SHARE}, 9) AS percent, round(cume_dist() {SHARE}, 9) AS cume FROM orders")
def win_shares(spark, sf_dir):
    out = op.win_share(t(spark, sf_dir, "orders"), ["o_orderpriority"], [F.col("o_totalprice"), F.col("o_orderkey")])
    return out.select("o_orderkey", F.round("percent", 9).alias("percent"), F.round("cume", 9).alias("cume"))


ENDS = "OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"


@query("win_first_last_nth", f'SELECT event_id, first_value(event_id) {ENDS} AS "first", last_value(event_id) {ENDS} AS "last", nth_value(event_id, 2) {ENDS} AS nth FROM events')
def win_first_last_nth(spark, sf_dir):
    return op.win_ends(t(spark, sf_dir, "events"), ["user_id"], [F.col("ts")], "event_id").select("event_id", "first", "last", "nth")


@query("win_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)")
def win_lag_lead(spark, sf_dir):
    return op.win_shift(t(spark, sf_dir, "events"), ["user_id"], [F.col("ts")], "event_id").select("event_id", "before", "after")


@query("win_frames", "SELECT o_orderkey, sum(CAST(round(o_totalprice * 100) AS BIGINT)) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS framed FROM orders")
def win_frames(spark, sf_dir):
    o = t(spark, sf_dir, "orders").withColumn("c", cents("o_totalprice"))
    return op.win_frame(o, ["o_custkey"], [F.col("o_orderdate"), F.col("o_orderkey")], "c", -2, 0).select("o_orderkey", "framed")


@query("win_range_interval", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range_interval(spark, sf_dir):
    from pyspark.sql import Window

    e = t(spark, sf_dir, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)).alias("n"))


@query("win_prefix_sum", "SELECT doc_id, coalesce(sum(14 + octet_length(encode(text))) OVER (PARTITION BY source ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS offset_bytes FROM documents")
def win_prefix_sum(spark, sf_dir):
    """Offsets of length-prefixed records, a file for each source."""
    from pyspark.sql import Window

    w = Window.partitionBy("source").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, -1)
    return t(spark, sf_dir, "documents").select("doc_id", F.coalesce(F.sum(F.octet_length("text") + 14).over(w), F.lit(0)).alias("offset_bytes"))


@query("topk_per_group", "SELECT o_custkey, o_orderkey, rn FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 3")
def topk_per_group(spark, sf_dir):
    return op.topk_per_group(t(spark, sf_dir, "orders"), ["o_custkey"], [F.col("o_totalprice").desc(), F.col("o_orderkey")], 3).select("o_custkey", "o_orderkey", "rn")


@query("page_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 25 OFFSET 50")
def page_offset(spark, sf_dir):
    return op.page(t(spark, sf_dir, "orders"), [F.col("o_totalprice"), F.col("o_orderkey")], 25, 50).select("o_orderkey")


@query("sort_by_expression", "SELECT row_number() OVER (ORDER BY length(text), doc_id) AS rank, doc_id FROM documents")
def sort_by_expression(spark, sf_dir):
    from ..sorter import with_global_rank

    d = t(spark, sf_dir, "documents").select(F.length("text").alias("n"), "doc_id")
    return with_global_rank(d.repartitionByRange("n", "doc_id").sortWithinPartitions("n", "doc_id")).select("rank", "doc_id")


CUSTS = "SELECT o_custkey AS k FROM orders WHERE o_orderpriority = '{}'"


def _prio(spark, sf_dir, p):
    return t(spark, sf_dir, "orders").where(F.col("o_orderpriority") == p).select(F.col("o_custkey").alias("k"))


for _n, _s, _f in (
    ("union", "UNION", lambda a, b: a.union(b).distinct()),
    ("intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("except", "EXCEPT", lambda a, b: a.subtract(b)),
    ("union_all", "UNION ALL", lambda a, b: op.union_all(a, b)),
    ("intersect_all", "INTERSECT ALL", lambda a, b: op.intersect_all(a, b)),
    ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    query(f"set_{_n}", f"{CUSTS.format('1-URGENT')} {_s} {CUSTS.format('5-LOW')}")(lambda spark, sf_dir, f=_f: f(_prio(spark, sf_dir, "1-URGENT"), _prio(spark, sf_dir, "5-LOW")))


@query("set_permutation_proof", "SELECT CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS extra")
def set_permutation_proof(spark, sf_dir):
    o = t(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return op.is_permutation(o, o.orderBy("o_custkey"))


@query("filter_pushdown", "SELECT o_orderkey FROM orders WHERE o_totalprice >= 1000 AND o_totalprice < 50000")
def filter_pushdown(spark, sf_dir):
    return op.key_range(t(spark, sf_dir, "orders"), "o_totalprice", 1000.0, 50000.0).select("o_orderkey")


@query("filter_by_locator", "SELECT o_orderkey FROM orders WHERE o_totalprice < 2000")
def filter_by_locator(spark, sf_dir):
    """Rows named by their place in the files: here those that a filter found."""
    from ..sources import with_locator

    orders = t(spark, sf_dir, "orders")
    ids = with_locator(orders).where("o_totalprice < 2000").select("file_path", "row_index")
    return op.by_locator(orders, ids).select("o_orderkey")


@query("sampled_keys", "SELECT true AS subset, true AS near_share")
def sampled_keys(spark, sf_dir):
    """A tenth of the keys, drawn by share and by stratum: all of them keys, and about a tenth."""
    orders = t(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    n = orders.count()
    plain = op.sample_keys(orders, 0.1)
    strata = op.sample_keys(orders, 0.0, by="o_orderpriority", shares={r[0]: 0.1 for r in orders.select("o_orderpriority").distinct().collect()})
    both = plain.unionAll(strata)
    found = both.join(orders.select("o_orderkey"), "o_orderkey", "left_anti").agg((F.count("*") == 0).alias("subset"))
    return found.join(both.agg((F.abs(F.count("*") / n - 0.2) < 0.06).alias("near_share")), F.lit(True))


@query("replicated_rows", "SELECT k AS copy, count(*) AS n FROM nation, range(0, 5) x(k) GROUP BY 1")
def replicated_rows(spark, sf_dir):
    """The scale-up generator: every row with every copy number."""
    from ..workloads import replicate

    return replicate(t(spark, sf_dir, "nation"), 5, 0.3).groupBy("copy").agg(F.count("*").alias("n"))


@query("registered_views", "SELECT count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey")
def registered_views(spark, sf_dir):
    from ..sources import register_tables

    register_tables(spark, sf_dir)
    return spark.sql("SELECT count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey")


@query("dedup_distinct", "SELECT DISTINCT o_custkey, o_orderpriority FROM orders")
def dedup_distinct(spark, sf_dir):
    return op.dedup(t(spark, sf_dir, "orders").select("o_custkey", "o_orderpriority"))


# --- functions ---


@query("fn_string", "SELECT c_custkey, upper(c_name) AS a, substr(c_name, 3, 4) AS b, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS c, reverse(c_mktsegment) AS d, length(c_name) AS n, regexp_replace(c_name, '[0-9]+', '#') AS e, translate(c_mktsegment, 'AEIOU', '12345') AS f FROM customer")
def fn_string(spark, sf_dir):
    c = t(spark, sf_dir, "customer")
    return c.select("c_custkey", F.upper("c_name").alias("a"), F.substring("c_name", 3, 4).alias("b"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("c"), F.reverse("c_mktsegment").alias("d"), F.length("c_name").cast("long").alias("n"), F.regexp_replace("c_name", "[0-9]+", "#").alias("e"), F.translate("c_mktsegment", "AEIOU", "12345").alias("f"))


@query("fn_date", "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS a, year(o_orderdate) AS b, month(o_orderdate) AS c, datediff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS d, strftime(last_day(CAST(o_orderdate AS DATE)), '%Y-%m-%d') AS e, epoch_us(o_orderdate) AS f FROM orders")
def fn_date(spark, sf_dir):
    o, d = t(spark, sf_dir, "orders"), F.col("o_orderdate")
    return o.select("o_orderkey", F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("a"), F.year(d).cast("long").alias("b"), F.month(d).cast("long").alias("c"), F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date")).cast("long").alias("d"), F.date_format(F.last_day(d.cast("date")), "yyyy-MM-dd").alias("e"), F.unix_micros(d.cast("timestamp")).alias("f"))


@query("fn_math", "SELECT o_orderkey, round(sqrt(o_totalprice), 4) AS a, CAST(floor(o_totalprice / 7) AS BIGINT) AS b, o_orderkey % 13 AS c, greatest(o_orderkey, o_custkey) AS d, abs(o_custkey - o_orderkey) AS e, o_orderkey & 255 AS f, round(log2(o_totalprice), 4) AS g FROM orders")
def fn_math(spark, sf_dir):
    p, k = F.col("o_totalprice"), F.col("o_orderkey")
    return t(spark, sf_dir, "orders").select("o_orderkey", F.round(F.sqrt(p), 4).alias("a"), F.floor(p / 7).alias("b"), F.pmod(k, F.lit(13)).alias("c"), F.greatest(k, "o_custkey").alias("d"), F.abs(F.col("o_custkey") - k).alias("e"), k.bitwiseAND(255).alias("f"), F.round(F.log2(p), 4).alias("g"))


@query("fn_array", "SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE))), 4) AS total, len(list_filter(embedding, lambda x: x > 0)) AS positive, CAST(round(CAST(embedding[1] AS DOUBLE) * 1000000) AS BIGINT) AS first FROM embeddings")
def fn_array(spark, sf_dir):
    v, d = F.col("embedding"), F.transform("embedding", lambda x: x.cast("double"))
    return t(spark, sf_dir, "embeddings").select("vec_id", F.size(v).cast("long").alias("n"), F.round(F.aggregate(d, F.lit(0.0), lambda a, x: a + x), 4).alias("total"), F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"), F.round(F.element_at(v, 1).cast("double") * 1000000).cast("long").alias("first"))


@query("fn_json", "SELECT event_id, CAST(props->>'k' AS BIGINT) AS k FROM events")
def fn_json(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("fn_map", "SELECT event_id, event_type || '=' || CAST(user_id AS VARCHAR) AS entry FROM events")
def fn_map(spark, sf_dir):
    m = F.map_from_entries(F.array(F.struct("event_type", "user_id")))
    return t(spark, sf_dir, "events").select("event_id", F.concat_ws("=", F.map_keys(m)[0], F.map_values(m)[0].cast("string")).alias("entry"))


@query("fn_bytes", "SELECT doc_id, octet_length(encode(text)) AS n, sha256(text) AS s, md5(text) AS m, upper(hex(encode(substr(text, 1, 5)))) AS h FROM documents")
def fn_bytes(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id", F.octet_length("text").cast("long").alias("n"), F.sha2("text", 256).alias("s"), F.md5("text").alias("m"), F.hex(F.encode(F.substring("text", 1, 5), "UTF-8")).alias("h"))


@query(
    "fn_decimal",
    "SELECT o_orderkey, CAST(CAST(o_totalprice AS DECIMAL(12,2)) * 300 AS BIGINT) AS tripled, TRY_CAST(substr(o_orderpriority, 1, 1) AS INTEGER) AS first, coalesce(TRY_CAST(o_orderpriority AS INTEGER), -1) AS bad, "
    "coalesce(round(o_totalprice / nullif(o_orderkey % 4, 0), 4), -1) AS divided FROM orders",
)
def fn_decimal(spark, sf_dir):
    return t(spark, sf_dir, "orders").select(
        "o_orderkey",
        (F.col("o_totalprice").cast("decimal(12,2)") * 300).cast("long").alias("tripled"),
        F.substring("o_orderpriority", 1, 1).try_cast("int").alias("first"),
        F.coalesce(F.col("o_orderpriority").try_cast("int"), F.lit(-1)).alias("bad"),
        F.coalesce(F.round(F.try_divide("o_totalprice", F.col("o_orderkey") % 4), 4), F.lit(-1.0)).alias("divided"),
    )


@query("fn_conditional", "SELECT d.doc_id, coalesce(quality, -1) AS q, nullif(lang, 'en') AS other, CASE WHEN n_chars > 2000 THEN 'long' WHEN n_chars > 500 THEN 'medium' ELSE 'short' END AS size FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def fn_conditional(spark, sf_dir):
    d, lab = t(spark, sf_dir, "documents", "labels")
    size = F.when(F.col("n_chars") > 2000, "long").when(F.col("n_chars") > 500, "medium").otherwise("short")
    return d.join(lab, "doc_id", "left").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("q"), F.expr("nullif(lang, 'en')").alias("other"), size.alias("size"))


# --- formats ---

ROUND = "SELECT o_orderkey, o_custkey, o_orderstatus, o_orderpriority FROM orders"
for _fmt in ("csv", "json", "orc", "parquet"):

    def _roundtrip(spark, sf_dir, fmt=_fmt):
        o = t(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority")
        path = new_path(spark, fmt)
        write_sorted(o.orderBy("o_orderkey"), path, fmt)
        return read(spark, path, fmt, o.schema)

    query(f"fmt_{_fmt}_roundtrip", ROUND)(_roundtrip)


@query("fmt_text_lines", "SELECT count(*) AS lines, sum(octet_length(encode(c_name)))::BIGINT AS bytes FROM customer")
def fmt_text_lines(spark, sf_dir):
    path = new_path(spark, "text")
    write_sorted(t(spark, sf_dir, "customer").select(F.col("c_name").alias("value")), path, "text")
    return read(spark, path, "text").agg(F.count("*").alias("lines"), F.sum(F.octet_length("value")).alias("bytes"))


@query("fmt_binary_files", "SELECT count(*) * 100 AS bytes, true AS whole_records FROM lineitem")
def fmt_binary_files(spark, sf_dir):
    """Record files read whole, as binary files."""
    found = read(spark, dataset(spark, sf_dir, "benchmark"), "binaryFile", pathGlobFilter="*.rec")
    return found.agg(F.sum("length").alias("bytes"), F.min((F.octet_length("content") == F.col("length")) & (F.col("length") % 100 == 0)).alias("whole_records"))


@query("sink_partitioned", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_orderpriority < '3' GROUP BY 1")
def sink_partitioned(spark, sf_dir):
    """Folders by value: a filter on them reads no other."""
    path = new_path(spark, "partitioned")
    write_sorted(t(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority").sortWithinPartitions("o_orderpriority", "o_orderkey"), path, by=["o_orderpriority"])
    return read(spark, path, "parquet").where("o_orderpriority < '3'").groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@query("sink_bucketed_join", "SELECT o_orderkey, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def sink_bucketed_join(spark, sf_dir):
    """Tables bucketed and sorted by the join key, joined by merging them."""
    names = []
    for source, key in (("orders", "o_orderkey"), ("lineitem", "l_orderkey")):
        path = new_path(spark, f"bucketed-{source}")
        names.append(f"bucketed_{path.rsplit('-', 1)[1]}_{source}")
        write_sorted(t(spark, sf_dir, source).select(key), path, by=[key], buckets=4, table_name=names[-1])
    a, b = (spark.table(n) for n in names)
    return a.join(b.hint("MERGE"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.count("*").alias("n"))


@query("fmt_fixedrec_roundtrip", "SELECT count(*) AS n, count(*) * 100 AS bytes FROM lineitem")
def fmt_fixedrec_roundtrip(spark, sf_dir):
    df = read(spark, dataset(spark, sf_dir, "benchmark"), "fixedrec", keyBytes=10, valueBytes=90)
    return df.agg(F.count("*").alias("n"), F.sum(F.length("key") + F.length("value")).alias("bytes"))


@query("fmt_klvrec_roundtrip", "SELECT substr(md5(CAST(doc_id AS VARCHAR)), 1, 20) AS key_hex, md5(text) AS text_md5 FROM documents")
def fmt_klvrec_roundtrip(spark, sf_dir):
    df = read(spark, dataset(spark, sf_dir, "documents"), "klvrec", keyBytes=TEXTS.key_bytes, value="true")
    return df.select(F.lower(F.hex("key")).alias("key_hex"), F.md5("value").alias("text_md5"))


# --- user-defined functions ---


@query("udf_sort_key", "SELECT row_number() OVER (ORDER BY c_acctbal DESC, c_custkey) AS rank, c_custkey FROM customer")
def udf_sort_key(spark, sf_dir):
    from ..sorter import with_global_rank

    key = encode_sort_key([(F.col("c_acctbal"), "double", False, False), (F.col("c_custkey"), "bigint", True, True)])
    c = t(spark, sf_dir, "customer").select(key.alias("key"), "c_custkey")
    return with_global_rank(c.repartitionByRange("key").sortWithinPartitions("key")).select("rank", "c_custkey")


@query("udf_order_checksum", "SELECT sum(o_orderkey * 7)::VARCHAR AS total FROM orders")
def udf_order_checksum(spark, sf_dir):
    register_all(spark)
    return t(spark, sf_dir, "orders").agg(order_checksum(F.col("o_orderkey") * 7).cast("string").alias("total"))


@query("udf_slim_range_udtf", "SELECT md5(CAST(o_orderkey AS VARCHAR)) AS key, o_orderkey AS pos FROM orders WHERE md5(CAST(o_orderkey AS VARCHAR)) >= '40' AND md5(CAST(o_orderkey AS VARCHAR)) < '48'")
def udf_slim_range_udtf(spark, sf_dir):
    path = new_path(spark, "slim")
    t(spark, sf_dir, "orders").select(F.md5(F.col("o_orderkey").cast("string")).alias("key"), F.col("o_orderkey").alias("pos")).orderBy("key").write.parquet(path)
    register_all(spark, path)
    return spark.sql("SELECT key, pos FROM range(0, 4, 1, 4) parts, LATERAL slim_range('40', '48', CAST(parts.id AS INT), 4)")
