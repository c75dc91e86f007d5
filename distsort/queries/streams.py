"""Streams over slices of events, drained and held against the answer for the whole table."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..catalog import query
from ..functions.classify import SplitterTree
from ..operators.sort import sort_global
from ..plans.sampling import SplitterSet
from ..sources.io import load
from ..streaming import streams as S

CUTS = (10.0, 25.0, 50.0, 75.0, 100.0)
COLS = ("event_id", "ts", "user_id", "event_type", "value")
_B = " + ".join(f"(value >= {c})::int" for c in CUTS)


def _events(spark, d, slices=4):
    df = load(spark, d, "events", *COLS)
    return _instants(S.source(spark, S.sliced(df, "ts", slices), df.schema)), df


def _instants(stream):
    """Watermarks want instants; the session's time zone is used both ways."""
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def _tree(df):
    return SplitterTree.build(df, ["value"], SplitterSet(tuple((c,) for c in CUTS), False))


@query(f"select event_id, {_B} as bucket from events")
def q_stream_classify(spark, d):
    stream, df = _events(spark, d)
    return S.drained(S.classify_stream(stream, _tree(df)).select("event_id", "bucket"))


@query(f"select {_B} as bucket, count(*) as n from events group by 1")
def q_stream_histogram(spark, d):
    stream, df = _events(spark, d)
    return S.drained(S.bucket_histogram(stream, _tree(df)), "complete")


@query("select row_number() over (order by value, event_id) - 1 as pos, event_id, value from events")
def q_stream_sorted_runs(spark, d):
    stream, _ = _events(spark, d)
    return S.sorted_runs(stream.select("event_id", "value"), ["value", "event_id"], lambda runs: sort_global(runs, ["value", "event_id"]))


def _windowed(stream, window):
    return stream.withWatermark("ts", "10 minutes").groupBy(window).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@query("select time_bucket(interval 1 hour, ts) as start, count(*) as n from events group by 1")
def q_stream_tumbling(spark, d):
    stream, _ = _events(spark, d)
    return S.drained(_windowed(stream, F.window("ts", "1 hour")), "complete")


@query("select start, count(*) as n from (select time_bucket(interval 30 minute, ts) - interval 30 minute * k as start, ts from events, (values (0), (1)) as x(k)) group by start")
def q_stream_sliding(spark, d):
    stream, _ = _events(spark, d)
    return S.drained(_windowed(stream, F.window("ts", "1 hour", "30 minutes")), "complete")


@query("""with g as (select user_id, ts, case when ts >= lag(ts) over (partition by user_id order by ts) + interval 30 minute or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as new from events),
s as (select user_id, ts, sum(new) over (partition by user_id order by ts) as sid from g) select user_id, min(ts) as start, count(*) as n from s group by user_id, sid""")
def q_stream_session(spark, d):
    stream, _ = _events(spark, d)
    grouped = stream.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return S.drained(grouped.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n"), "complete")


@query("select true as some, true as fewer, true as bounded")
def q_stream_late(spark, d):
    """Slices in reverse: rows behind the watermark are dropped, so that sums fall short of the table's, in no window beyond them."""
    df = load(spark, d, "events", *COLS).withColumn("late", -F.unix_micros(F.to_timestamp_ltz(F.date_format("ts", "yyyy-MM-dd HH:mm:ss"))))
    stream = _instants(S.source(spark, S.sliced(df, "late"), df.schema))
    out, names = S.drained(_windowed(stream, F.window("ts", "1 hour"))), ("start", "n")
    hour = F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("start")
    table = df.groupBy(hour).agg(F.count(F.lit(1)).alias("of_table"))
    both = out.select(*names).join(table, "start", "left").agg(F.sum("n").alias("n"), F.every(F.col("n") <= F.coalesce("of_table", F.lit(0))).alias("bounded"))
    every = df.agg(F.count(F.lit(1)).alias("every"))
    return both.join(F.broadcast(every)).select((F.col("n") > 0).alias("some"), (F.col("n") < F.col("every")).alias("fewer"), "bounded")


@query("select distinct user_id, event_type from events")
def q_stream_dedup(spark, d):
    stream, _ = _events(spark, d)
    return S.drained(stream.withWatermark("ts", "400 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"))


@query("select event_id, c_name from events join customer on user_id = c_custkey")
def q_stream_static_join(spark, d):
    stream, _ = _events(spark, d)
    return S.drained(stream.join(load(spark, d, "customer", "c_custkey", "c_name"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_name"))


@query("select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour")
def q_stream_stream_join(spark, d):
    one, df = _events(spark, d)
    two = _instants(S.source(spark, S.sliced(df, "ts"), df.schema))
    a = one.where("event_type = 'click'").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withWatermark("ta", "400 days")
    b = two.where("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", "400 days")
    near = (F.col("ua") == F.col("ub")) & (F.col("tb") >= F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("interval 1 hour"))
    return S.drained(a.join(b, near).select("a", "b"))


@query(f"select {_B} as bucket, min(value) as lo, max(value) as hi, count(*) as n from events where value is not null group by 1")
def q_stream_state(spark, d):
    stream, df = _events(spark, d)
    newest = S.drained(S.running_extremes(stream.where("value is not null").select("event_id", "value"), _tree(df), "value"), "update")
    return newest.groupBy("bucket").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.max("n").alias("n"))
