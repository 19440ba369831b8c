"""Streams run to their end; oracles are the batch answers."""

from __future__ import annotations

from pyspark.sql import functions as F

from qacurate.functions.text import tokens
from qacurate.operators.decontam import window_questions
from qacurate.queries import curate
from qacurate.queries.common import docs
from qacurate.queries.decontam import _ALL, _EVIDENCE
from qacurate.queries.dedup import _BASE
from qacurate.registry import query, read
from qacurate.staging import fresh_path, released_shuffles, stage
from qacurate.streaming import streams as S


def events(spark, d, time="ts"):
    """The event table as a stream of four files in order of time."""
    path = fresh_path(spark, "events-in")
    table = read(spark, d, "events")
    S.split_files(table, path, "ts")
    return S.file_stream(spark, path, table.schema, time=time)


def _naive(df, *columns):
    for c in columns:
        df = df.withColumn(c, F.col(c).cast("timestamp_ntz"))
    return df


@query("stream_tumbling", "select time_bucket(interval 1 day, ts) as start, event_type, count(*) as n, round(sum(value), 4) as total from events group by all")
def stream_tumbling(spark, d):
    return _naive(S.run_once(S.tumbling(events(spark, d)), "complete", "tumbling"), "start")


@query("stream_sliding", "with w as (select unnest([time_bucket(interval 1 day, ts), time_bucket(interval 1 day, ts) - interval 1 day]) as start from events) select start, count(*) as n from w group by start")
def stream_sliding(spark, d):
    return _naive(S.run_once(S.sliding(events(spark, d)), "complete", "sliding"), "start")


@query("stream_session", """with g as (select user_id, ts, case when ts < lag(ts) over w + interval 1 day then 0 else 1 end as fresh from events window w as (partition by user_id order by ts)),
s as (select user_id, ts, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as no from g)
select user_id, min(ts) as start, max(ts) + interval 1 day as "end", count(*) as n from s group by user_id, no""")
def stream_session(spark, d):
    return _naive(S.run_once(S.sessions(events(spark, d)), "complete", "session"), "start", "end")


@query("stream_dedup", "select distinct user_id, event_type, date_trunc('hour', ts) as hour from events")
def stream_dedup(spark, d):
    e = events(spark, d).withColumn("hour", F.date_trunc("hour", "ts"))
    return _naive(S.run_once(S.dedup_within(e, ["user_id", "event_type", "hour"]).select("user_id", "event_type", "hour"), "append", "dedup"), "hour")


def late_events(spark, d):
    """The event table as a stream in order of time, then its first tenth once more: rows that come far too late."""
    path = fresh_path(spark, "events-late-in")
    table = read(spark, d, "events")
    S.split_files(table, path, "ts")
    low, high = table.agg(F.unix_micros(F.min(F.col("ts").cast("timestamp"))), F.unix_micros(F.max(F.col("ts").cast("timestamp")))).first()
    late = table.where(F.unix_micros(F.col("ts").cast("timestamp")) < low + (high - low) // 10)
    late.coalesce(1).write.mode("append").parquet(path)
    return S.file_stream(spark, path, table.schema, time="ts")


@query("stream_late", """with t as (select time_bucket(interval 1 day, ts) as start, event_type, count(*) as n, round(sum(value), 4) as total from events group by all)
select * from t where start + interval 1 day <= (select max(ts) - interval 10 minute from events)""")
def stream_late(spark, d):
    """Days that a watermark of ten minutes closes while the stream runs: the newest stay open, late rows count for nothing."""
    e = late_events(spark, d).withWatermark("ts", S.WATERMARK)
    return _naive(S.run_once(S.tumbling(e), "append", "late"), "start")


@query("stream_counters", """with e as (select *, epoch_us(ts) as u from events), l as (select min(u) as low, max(u) as high from e), late as (select e.* from e, l where u < low + (high - low) // 10)
select (select count(*) from e) + (select count(*) from late) as rows_read, (select count(*) from late where event_type = 'view') as rows_late,
  (select count_if(event_type = 'view') from e) + (select count_if(event_type = 'view') from late) as views""")
def stream_counters(spark, d):
    """What the progress of a stream reports: rows read, rows behind the watermark, rows that passed a stage."""
    views = S.counted(late_events(spark, d).where("event_type = 'view'"), "views")
    out = S.dedup_within(views, ["event_id"]).select("event_id")
    seen = S.counters(S.drain(out, "append", "counters")[1])
    return spark.createDataFrame([(seen["rows_read"], seen["rows_late"], seen["views.n"])], "rows_read long, rows_late long, views long")


@query("stream_join", "select a.user_id, a.ts as t1, b.ts as t2 from events a join events b on a.user_id = b.user_id and a.event_type = 'view' and b.event_type = 'purchase' and b.ts between a.ts and a.ts + interval 1 hour")
def stream_join(spark, d):
    e = events(spark, d)
    out = S.join_streams(e.where("event_type = 'view'"), e.where("event_type = 'purchase'"))
    return _naive(S.run_once(out, "append", "join"), "t1", "t2")


@query("stream_minhash", f"{_BASE}, c as (select k.id, min(x.id) as keep from k join x using (ws) group by k.id), f as (select b, min(a) as a from e group by b) select id, coalesce(least(a, keep), keep) as keep_id from c left join f on keep = b where id = keep")
def stream_minhash(spark, d):
    """First wins over texts that differ, in order of id, four batches."""
    from qacurate.operators.minhash import exact_dedup

    t = docs(spark, d).select(F.col("doc_id").alias("id"), "text")
    t = t.join(stage(exact_dedup(t, "id", "text").where("id = keep").select("id"), "stream-ids"), "id", "left_semi")
    path = fresh_path(spark, "docs-in")
    with released_shuffles(spark):
        S.split_files(t, path, "id")
    return S.IncrementalDedup(spark).run(S.file_stream(spark, path, t.schema))


@query("stream_decontaminate", f"{_ALL} select * from {_EVIDENCE}")
def stream_decontaminate(spark, d):
    q = window_questions(docs(spark, d), "doc_id")
    path = fresh_path(spark, "windows-in")
    S.split_files(q, path, "doc_id", 2)
    m = read(spark, d, "benchmark").select("item_id", tokens("text").alias("words"))
    return S.incremental_decontaminate(S.file_stream(spark, path, q.schema), m)


@query("stream_difficulty", f"{curate.CHAIN}, kept as (select s.* from scores s where k <= 10 or ('0x' || substr(md5('d:' || qid), 1, 2))::int % 5 <> 0) select qid, count(*) as n, sum(score)::bigint as total from kept group by qid")
def stream_difficulty(spark, d):
    """Sums of scores as they come, a minute apart; every fifth question or so never gets its last six."""
    scores = curate._scores(spark, d).select("qid", "k", "score")
    short = F.conv(F.substring(F.md5(F.concat(F.lit("d:"), "qid")), 1, 2), 16, 10).cast("int") % 5 == 0
    begin = F.lit("2024-01-01 00:00:00").cast("timestamp")
    timed = stage(scores.where((F.col("k") <= 10) | ~short).withColumn("ts", F.timestamp_add("MINUTE", F.col("k"), begin)), "scores-timed")
    path = fresh_path(spark, "scores-in")
    S.split_files(timed, path, "k")
    # A score that comes days later moves the watermark past the wait of all others; its own question stays open.
    spark.createDataFrame([("later", 99, 0)], "qid string, k int, score int").withColumn("ts", F.timestamp_add("DAY", F.lit(9), begin)).write.mode("append").parquet(path)
    return S.IncrementalScores(spark).run(S.file_stream(spark, path, timed.schema))
