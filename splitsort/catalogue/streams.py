"""Queries of the stream side, run to the end of the events and compared with batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import streaming as st
from ..session import new_path
from ..sources import table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def events(spark, sf_dir):
    return st.event_stream(spark, table(spark, sf_dir, "events"))


VALUE = "sum(CAST(round(value * 100) AS BIGINT))::BIGINT AS cents"


def shown(df):
    return df.select(F.unix_micros("w.start").alias("start_us"), *[c for c in df.columns if c != "w"])


@query("stream_tumbling", f"SELECT (epoch_us(ts) // 3600000000) * 3600000000 AS start_us, event_type, count(*) AS n, {VALUE} FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    return shown(st.collected(st.stream_window(st.with_watermark(events(spark, sf_dir)), "tumbling", "1 hour", by=["event_type"]), "complete"))


@query("stream_update_mode", f"SELECT (epoch_us(ts) // 3600000000) * 3600000000 AS start_us, count(*) AS n, {VALUE} FROM events GROUP BY 1")
def stream_update_mode(spark, sf_dir):
    """Each batch puts out the windows it changed; the last state of each is the sum of all."""
    out = shown(st.collected(st.stream_window(st.with_watermark(events(spark, sf_dir)), "tumbling", "1 hour"), "update"))
    return out.groupBy("start_us").agg(F.max("n").alias("n"), F.max_by("cents", "n").alias("cents"))


@query("stream_sliding", f"SELECT (epoch_us(ts) // 1800000000 - k) * 1800000000 AS start_us, count(*) AS n, {VALUE} FROM events, (VALUES (0), (1)) v(k) GROUP BY 1")
def stream_sliding(spark, sf_dir):
    return shown(st.collected(st.stream_window(st.with_watermark(events(spark, sf_dir)), "sliding", "1 hour", "30 minutes"), "complete"))


@query(
    "stream_session",
    f"""WITH m AS (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < 600000000 THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
        s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM m) SELECT epoch_us(min(ts)) AS start_us, user_id, count(*) AS n, {VALUE} FROM s GROUP BY user_id, g""",
)
def stream_session(spark, sf_dir):
    return shown(st.collected(st.stream_window(st.with_watermark(events(spark, sf_dir)), "session", "10 minutes", by=["user_id"]), "complete"))


@query("stream_dedup", "SELECT event_id FROM events")
def stream_dedup(spark, sf_dir):
    """Every event twice, once each out."""
    twice = events(spark, sf_dir).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return st.collected(st.stream_dedup(st.with_watermark(twice), ["event_id"])).select("event_id")


@query("stream_late", "SELECT CASE WHEN epoch_us(ts) < (SELECT max(epoch_us(ts)) FROM events) - 36000000000 THEN 'late' ELSE 'on time' END AS kind, count(*) AS n FROM events GROUP BY 1")
def stream_late(spark, sf_dir):
    batch = table(spark, sf_dir, "events").withColumn("at", F.col("ts").cast("timestamp"))
    ontime, late = st.late_split(batch, 36_000)
    both = ontime.select(F.lit("on time").alias("kind")).unionAll(late.select(F.lit("late")))
    return both.groupBy("kind").agg(F.count("*").alias("n"))


@query("stream_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, sf_dir):
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return st.collected(st.stream_enrich(events(spark, sf_dir), c, "user_id")).select("event_id", "c_mktsegment")


@query("stream_interval_join", "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def stream_interval_join(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    a, b = (st.with_watermark(st.event_stream(spark, e)) for _ in range(2))
    return st.collected(st.stream_pair(a, b, "30 MINUTES")).select("first_id", "second_id")


HOUR = 3_600_000_000


@query(
    "stream_late_dropped",
    f"""WITH e AS (SELECT event_id, epoch_us(ts) AS us, (epoch_us(ts) // {HOUR}) * {HOUR} AS start_us FROM events),
        m AS (SELECT ((max(us) FILTER (event_id % 3 = 0) - {HOUR}) // 1000) * 1000 AS late, ((max(us) - {HOUR}) // 1000) * 1000 AS closed FROM e)
        SELECT start_us, count(*) AS n FROM e, m WHERE (event_id % 3 < 2 OR start_us + {HOUR} > late) AND start_us + {HOUR} <= closed GROUP BY 1""",
)
def stream_late_dropped(spark, sf_dir):
    """A third of the events comes when the watermark has passed nearly all of them: windows that are closed drop them.

    In append mode a window comes out once, when the watermark passes its end.
    """
    e, path = table(spark, sf_dir, "events"), new_path(spark, "late-events")
    for k in range(3):  # one file, and so one micro-batch, each
        e.where(F.col("event_id") % 3 == k).coalesce(1).write.mode("append").parquet(path)
    rows = st.stream(spark, path, e.schema, 1).withColumn("at", F.col("ts").cast("timestamp"))
    return shown(st.collected(st.stream_window(st.with_watermark(rows), "tumbling", "1 hour"), "append")).select("start_us", "n")


RANKED = "SELECT row_number() OVER (ORDER BY md5(CAST(event_id AS VARCHAR))) AS rank, event_id FROM events"
QUARTERS = [b"\x40", b"\x80", b"\xc0"]


@query("stream_run_merge", RANKED)
def stream_run_merge(spark, sf_dir):
    path = new_path(spark, "stream-runs")
    st.stream_runs(events(spark, sf_dir), path, F.unhex(F.md5(F.col("event_id").cast("string"))), bounds=QUARTERS)
    return st.merged_runs(spark, path).select("rank", F.col("pos").alias("event_id"))


@query("stream_restart", RANKED)
def stream_restart(spark, sf_dir):
    """Runs made in two goes from one checkpoint, and a third go that finds nothing new: each event is in one run."""
    e, source, path, checkpoint = table(spark, sf_dir, "events"), *(new_path(spark, n) for n in ("restart-events", "restart-runs", "restart-checkpoint"))
    for k in (0, 1, None):
        if k is not None:
            e.where(F.col("event_id") % 2 == k).repartition(2).write.mode("append").parquet(source)
        st.stream_runs(st.stream(spark, source, e.schema, 1), path, F.unhex(F.md5(F.col("event_id").cast("string"))), checkpoint, QUARTERS)
    return st.merged_runs(spark, path).select("rank", F.col("pos").alias("event_id"))


@query("stream_topk", "SELECT event_type, string_agg(c, ',' ORDER BY c DESC) AS best FROM (SELECT event_type, CAST(round(value * 100) AS BIGINT) AS c, row_number() OVER (PARTITION BY event_type ORDER BY value DESC) AS k FROM events) WHERE k <= 5 GROUP BY 1")
def stream_topk(spark, sf_dir):
    out = st.collected(st.stream_topk(events(spark, sf_dir), 5), "update")
    last = out.groupBy("event_type").agg(F.max("best").alias("best"))  # lists only grow in state, so the last is the largest
    return last.select("event_type", F.array_join("best", ",").alias("best"))
