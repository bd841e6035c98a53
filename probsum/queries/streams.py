"""Streaming queries: windows, late rows, joins, state, and a summary kept current; batch SQL is their oracle."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probsum.functions.domain import Attr
from probsum.plans.summary import summarise
from probsum.queries import query
from probsum.sources import workloads as wl
from probsum.sources.tables import scratch, table
from probsum.streaming.updates import Maintained, as_delta


def event_stream(spark, d, files: int = 4) -> DataFrame:
    """The events as a stream of a few files in time order."""
    path = scratch(spark, "events")
    e = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    e.repartitionByRange(files, "ts").sortWithinPartitions("ts").write.parquet(path)
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def run_to_table(stream: DataFrame, label: str, mode: str = "append") -> DataFrame:
    """Run a stream until its source is exhausted into a parquet table (append) or a batch-wise overwritten one, and read it."""
    spark = stream.sparkSession
    out, mark = scratch(spark, label), scratch(spark, f"{label}-mark")
    writer = stream.writeStream.option("checkpointLocation", mark).trigger(availableNow=True).outputMode(mode)
    if mode == "append":
        q = writer.format("parquet").option("path", out).start()
    else:
        q = writer.foreachBatch(lambda df, i: df.write.mode("overwrite").parquet(out)).start()
    q.awaitTermination()
    schema = stream.schema
    return spark.read.schema(schema).parquet(out)


def _windowed(spark, d, *spec):
    stream = event_stream(spark, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", *spec), "event_type").agg(F.count(F.lit(1)).alias("n"))
    rows = run_to_table(stream.select(F.col("window.start").alias("start"), "event_type", "n"), "windows", "complete")
    return rows.select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("at"), "event_type", "n")


@query("select strftime(time_bucket(interval '1 hour', ts), '%Y-%m-%d %H:%M') as at, event_type, count(*) as n from events group by all")
def st_tumbling(spark, d):
    return _windowed(spark, d, "1 hour")


@query("""select strftime(s, '%Y-%m-%d %H:%M') as at, event_type, count(*) as n from (select unnest([time_bucket(interval '30 minutes', ts), time_bucket(interval '30 minutes', ts) - interval '30 minutes']) as s, event_type from events) group by all""")
def st_sliding(spark, d):
    return _windowed(spark, d, "1 hour", "30 minutes")


@query("""with g as (select user_id, ts, case when ts <= lag(ts) over w + interval '2 hours' then 0 else 1 end as fresh from events window w as (partition by user_id order by ts)),
s as (select user_id, ts, sum(fresh) over (partition by user_id order by ts, fresh desc rows unbounded preceding) as k from g) select user_id, count(*) as sessions, sum(n)::bigint as events from (select user_id, k, count(*) as n from s group by all) group by 1""")
def st_session(spark, d):
    stream = event_stream(spark, d).withWatermark("ts", "40 days").groupBy(F.session_window("ts", "2 hours"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    rows = run_to_table(stream.select("user_id", "n"), "sessions", "complete")
    return rows.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("events"))


@query()
def st_late(spark, d):
    """Rows behind the watermark are dropped: windows closed by append mode."""
    stream = event_stream(spark, d).withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    return run_to_table(stream.select(F.col("window.start").alias("start"), "n"), "late")


@query("select event_id, user_id from events")
def st_dedup(spark, d):
    path = scratch(spark, "twice")
    e = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    e.unionByName(e).repartitionByRange(2, "ts").write.parquet(path)
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(path)
    once = stream.withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"])
    return run_to_table(once.select("event_id", "user_id"), "dedup")


@query("select event_id, event_type, code from events join (select t, (row_number() over (order by t) - 1)::int as code from (select distinct event_type as t from events)) on event_type = t")
def st_static_join(spark, d):
    """Codes of a pinned domain joined to the stream."""
    types = table(spark, d, "events").select("event_type").distinct().orderBy("event_type").collect()
    book = spark.createDataFrame([(r[0], i) for i, r in enumerate(types)], "t string, code int")
    stream = event_stream(spark, d).join(F.broadcast(book), F.col("event_type") == F.col("t"))
    return run_to_table(stream.select("event_id", "event_type", "code"), "static-join")


@query("select a.event_id as click_id, b.event_id as buy_id from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval '1 hour'")
def st_stream_join(spark, d):
    e = event_stream(spark, d)
    a = e.where("event_type = 'click'").selectExpr("event_id as click_id", "user_id as u1", "ts as t1").withWatermark("t1", "40 days")
    b = e.where("event_type = 'purchase'").selectExpr("event_id as buy_id", "user_id as u2", "ts as t2").withWatermark("t2", "40 days")
    both = a.join(b, F.expr("u1 = u2 and t2 >= t1 and t2 <= t1 + interval 1 hour"))
    return run_to_table(both.select("click_id", "buy_id"), "stream-join")


@query("select user_id, count(*) as n, round(sum(value), 6) as total from events group by 1")
def st_stateful(spark, d):
    """Per-key counters in custom state; the last row of a key is its total."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    def count(key, frames, state):
        n, total = state.get if state.exists else (0, 0.0)
        for pdf in frames:
            n, total = n + len(pdf), total + float(pdf["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    stream = event_stream(spark, d).groupBy("user_id").applyInPandasWithState(
        count, "user_id long, n long, total double", "n long, total double", "update", GroupStateTimeout.NoTimeout
    )
    out, mark = scratch(spark, "state"), scratch(spark, "state-mark")
    q = stream.writeStream.option("checkpointLocation", mark).trigger(availableNow=True).outputMode("update").foreachBatch(
        lambda df, i: df.withColumn("batch", F.lit(i)).write.mode("append").parquet(out)
    ).start()
    q.awaitTermination()
    rows = spark.read.parquet(out)
    last = rows.groupBy("user_id").agg(F.max_by(F.struct("n", "total"), "batch").alias("s"))
    return last.select("user_id", "s.n", F.round("s.total", 6).alias("total"))


def _event_attrs():
    return [Attr("hour", 1, 0, 24), Attr("event_type"), Attr("bucket", 1, 0, 200)]


def _maintained(spark, d) -> Maintained:
    """A summary of the first half of the events by id, kept current by a stream of the rest and of deletes of every tenth."""
    rel = wl.event_rel(spark, d).select("hour", "event_type", "bucket", "event_id")
    half = rel.agg(F.max("event_id")).first()[0] // 2
    pinned = summarise(rel, _event_attrs(), n_pairs=0, fit=False).domain
    s = summarise(rel.where(F.col("event_id") <= half), _event_attrs(), [("hour", "event_type")], per_pair=40, domain=pinned, max_sweeps=60)
    kept = Maintained(s)
    delta = as_delta(rel.where((F.col("event_id") <= half) & (F.col("event_id") % 10 == 0)), rel.where(F.col("event_id") > half)).drop("event_id")
    path = scratch(spark, "delta")
    delta.repartition(3).write.parquet(path)
    stream = spark.readStream.schema(delta.schema).option("maxFilesPerTrigger", 1).parquet(path)
    sink = kept.sink(refit_rows=10**9)
    q = stream.writeStream.option("checkpointLocation", scratch(spark, "delta-mark")).trigger(availableNow=True).foreachBatch(sink).start()
    q.awaitTermination()
    kept.refresh(max_sweeps=200, tol=0.01)
    return kept


_KEPT = "(select * from events where not (event_id % 10 = 0 and event_id <= (select max(event_id) // 2 from events)))"


@query(f"select event_type, count(*) as n from {_KEPT} group by 1")
def st_update_summary(spark, d):
    return _maintained(spark, d).summary.groups(["event_type"]).select("event_type", F.col("est_rounded").alias("n"))


@query(f"select hour(ts)::varchar as hour, count(*) as n from {_KEPT} group by 1")
def recover_after_updates(spark, d):
    return _maintained(spark, d).summary.groups(["hour"]).where("est_rounded > 0").select("hour", F.col("est_rounded").alias("n"))
