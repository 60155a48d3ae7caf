"""Streams over the given tables; each result equals its batch twin."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import extract as E
from ..operators import units as U
from ..streaming import index as S
from ..plans.store import Store
from . import engine
from .tables import table


def stream_index(spark, d):
    docs = S.source(spark, f"{d}/documents.parquet")
    when = table(spark, d, "events", F.col("event_id").alias("doc_id"), F.col("ts").alias("released_at"))
    prints = E.additive_print(U.lines(docs, "doc_id", "source"), "line", "doc_id", F.col("source").alias("group_id"))
    return S.origin_index(prints.join(when, "doc_id").select("print", "group_id", "released_at"))


def stream_recognize(spark, d):
    docs = S.source(spark, f"{d}/documents.parquet")
    sent = U.sentences(U.lines(docs, "doc_id"), "doc_id").where(F.length("sentence") > engine.MIN_CHARS)
    prints = E.additive_print(sent, "sentence", F.col("doc_id").alias("subject"))
    index = engine._item_index(spark, d)
    return S.recognize(prints, index).groupBy("subject", F.col("group_id").alias("component")).agg(F.count_distinct("print").alias("n_evidence"))


def _events(spark, d):
    return S.source(spark, f"{d}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")


def _out(rows, *keys):
    out = S.latest(rows, "start", *keys)
    return out.select(F.col("start").cast("timestamp_ntz").alias("w_start"), F.col("end").cast("timestamp_ntz").alias("w_end"), *keys, "n", F.round("total", 4).alias("total"))


def tumbling(spark, d):
    return _out(S.changes(S.windowed(_events(spark, d), "ts", "1 hour", F.window("ts", "1 hour"), "event_type"), "tumbling"), "event_type")


def sliding(spark, d):
    return _out(S.changes(S.windowed(_events(spark, d), "ts", "1 hour", F.window("ts", "2 hours", "1 hour"), "event_type"), "sliding"), "event_type")


def session(spark, d):
    """Sessions come out once, when the watermark has passed them, and their state goes."""
    events = _events(spark, d)
    last = table(spark, d, "events").agg(F.max("ts").alias("ts")).select(F.lit(-1).cast("long").alias("event_id"), (F.col("ts").cast("timestamp") + F.expr("interval 30 days")).alias("ts"), F.lit(-1).cast(events.schema["user_id"].dataType).alias("user_id"), F.lit("end").alias("event_type"), F.lit(0.0).alias("value"))
    rows = S.to_the_end(events, last, "ts", "session", lambda df: S.windowed(df, "ts", "1 hour", F.session_window("ts", "30 minutes"), "user_id")).where("user_id <> -1")
    return rows.select(F.col("start").cast("timestamp_ntz").alias("w_start"), F.col("end").cast("timestamp_ntz").alias("w_end"), "user_id", "n", F.round("total", 4).alias("total"))


def dedup(spark, d):
    """Users per type and hour; the hour is part of the key, so the state of an hour goes with the watermark."""
    hour = F.window("ts", "1 hour")["start"]
    first = _events(spark, d).withWatermark("ts", "1 hour").select("ts", hour.alias("hour"), "user_id", "event_type")
    first = first.withColumn("hour", F.col("hour")).dropDuplicatesWithinWatermark(["hour", "user_id", "event_type"])
    rows = S.changes(first.select(F.col("hour").cast("timestamp_ntz").alias("hour"), "user_id", "event_type"), "dedup", "append")
    return rows.groupBy("hour", "event_type").agg(F.count_distinct("user_id").alias("n_users"))


def late(spark, d):
    """The newer days come first; what an older day brings after that is beyond the watermark and does not count."""
    store = Store(spark, "late")
    events = table(spark, d, "events")
    cut = events.agg(F.date_trunc("day", F.max("ts").cast("timestamp")).alias("day")).select((F.col("day") - F.expr("interval 10 days")).alias("cut")).first()["cut"]
    rows = events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")
    older, newer = rows.where(F.col("ts") < F.lit(cut)), rows.where(F.col("ts") >= F.lit(cut))
    newer.write.parquet(store.path("in"))
    stream = spark.readStream.schema(rows.schema).parquet(store.path("in"))
    counted = S.windowed(stream, "ts", "1 hour", F.window("ts", "1 hour"), "event_type")
    S.changes(counted, "late", store=store)
    older.write.mode("append").parquet(store.path("in"))
    return _out(S.changes(counted, "late", store=store), "event_type")


QUERIES = {"stream_index": stream_index, "stream_recognize": stream_recognize, "stream_windows_tumbling": tumbling, "stream_windows_sliding": sliding, "stream_windows_session": session, "stream_dedup": dedup, "stream_late": late}
ORACLE = {
    "stream_index": f"with {engine._FEAT('mono')} select print, arg_min(group_id, (released_at is null, released_at, group_id)) as group_id, min(released_at) as first_at from feats group by print",
    "stream_recognize": engine.ORACLE["detect_flagship"],
    "stream_windows_tumbling": "select time_bucket(interval '1 hour', ts) as w_start, time_bucket(interval '1 hour', ts) + interval '1 hour' as w_end, event_type, count(*) as n, round(sum(value), 4) as total from events group by all",
    "stream_windows_sliding": "select s as w_start, s + interval '2 hours' as w_end, event_type, count(*) as n, round(sum(value), 4) as total from (select *, unnest([time_bucket(interval '1 hour', ts), time_bucket(interval '1 hour', ts) - interval '1 hour']) as s from events) group by all",
    "stream_windows_session": "select min(ts) as w_start, max(ts) + interval '30 minutes' as w_end, user_id, count(*) as n, round(sum(value), 4) as total from (select *, sum(fresh) over (partition by user_id order by ts, event_id) as sid from (select *, case when ts < lag(ts) over (partition by user_id order by ts, event_id) + interval '30 minutes' then 0 else 1 end as fresh from events)) group by user_id, sid",
    "stream_dedup": "select time_bucket(interval '1 hour', ts) as hour, event_type, count(distinct user_id) as n_users from events group by all",
    "stream_late": "select time_bucket(interval '1 hour', ts) as w_start, time_bucket(interval '1 hour', ts) + interval '1 hour' as w_end, event_type, count(*) as n, round(sum(value), 4) as total from events where ts >= (select date_trunc('day', max(ts)) - interval 10 days from events) group by all",
}
