"""Structured Streaming around the methods: windows, deduplication, joins and folds of closed sessions.

A stream is folded only once a unit is closed, since the longest repeat needs the whole text. Every query takes what is available, writes
each micro-batch under its id in the shared folder (so a batch that is run again replaces itself) and returns what stands there.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from repeatfold.plans.lineage import shared_dir
from repeatfold.sources.tables import load_table

GAP_MINUTES = 30
SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def table_stream(spark: SparkSession, sf_dir: str, name: str, schema: str) -> DataFrame:
    """A table as a stream of its files, whether it is a folder or one file in ``sf_dir``."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/{name}.parquet")
    single = path.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(path).isFile()
    reader = spark.readStream.schema(schema)
    return reader.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir) if single else reader.parquet(f"{sf_dir}/{name}.parquet")


def event_stream(spark: SparkSession, sf_dir: str, delay: str = "10 minutes") -> DataFrame:
    """The events table as a stream with a watermark on ``at``."""
    rows = table_stream(spark, sf_dir, "events", SCHEMA)
    return rows.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", delay)


def drain(stream: DataFrame, mode: str, work: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Runs ``stream`` over what is available and returns all it wrote: the last batch in complete mode, every batch in the others."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    schema = stream.schema

    def write(batch: DataFrame, number: int) -> None:
        out = work(batch) if work else batch
        out.write.mode("overwrite").parquet(f"{base}/out/complete" if mode == "complete" else f"{base}/out/batch={number}")

    q = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    if work:
        schema = work(spark.createDataFrame([], stream.schema)).schema
    try:
        return spark.read.schema(schema).parquet(f"{base}/out/complete" if mode == "complete" else f"{base}/out/*")
    except Exception as e:  # no batch was written: no input
        if "PATH_NOT_FOUND" not in str(e):
            raise
        return spark.createDataFrame([], schema)


def _time(c) -> F.Column:
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss")


def windowed(events: DataFrame, window) -> DataFrame:
    return events.groupBy(window.alias("w"), "user_id").agg(F.count("*").alias("n"), F.round(F.sum(F.col("value").cast("decimal(18,4)")), 4).cast("double").alias("total"))


def tumbling(events: DataFrame) -> DataFrame:
    return windowed(events, F.window("at", "1 hour"))


def sliding(events: DataFrame) -> DataFrame:
    return windowed(events, F.window("at", "1 hour", "15 minutes"))


def sessions(events: DataFrame) -> DataFrame:
    return windowed(events, F.session_window("at", f"{GAP_MINUTES} minutes"))


def named(df: DataFrame) -> DataFrame:
    return df.select("user_id", _time("w.start").alias("start"), "n", "total")


def session_symbols(events: DataFrame) -> DataFrame:
    """Each user's event types by session, ``user_id, start, symbols``, emitted when the session's timer runs out."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        gap = pd.Timedelta(minutes=GAP_MINUTES)
        rows = list(zip(*state.get, strict=True)) if state.exists else []
        closed = []
        if not state.hasTimedOut:
            fresh = [(int(t.value // 1000), int(i), s) for f in frames for t, i, s in zip(f["at"], f["event_id"], f["event_type"], strict=True)]
            rows = sorted([*rows, *fresh])
        runs: list[list[tuple]] = []
        for r in rows:
            if runs and r[0] - runs[-1][-1][0] <= gap.value // 1000:
                runs[-1].append(r)
            else:
                runs.append([r])
        closed, opened = (runs, []) if state.hasTimedOut else (runs[:-1], runs[-1:])
        if opened:
            state.update(tuple(list(c) for c in zip(*opened[0], strict=True)))
            state.setTimeoutTimestamp(max(opened[0][-1][0] // 1000 + int(gap.total_seconds() * 1000), state.getCurrentWatermarkMs() + 1))
        elif state.exists:
            state.remove()
        if closed:
            yield pd.DataFrame({"user_id": key[0], "start": [pd.Timestamp(r[0][0], unit="us") for r in closed], "symbols": [" ".join(x[2] for x in r) for r in closed]})

    rows = events.select("user_id", "at", "event_id", "event_type")
    return rows.groupBy("user_id").applyInPandasWithState(step, "user_id long, start timestamp, symbols string", "at array<long>, id array<long>, s array<string>", "append", GroupStateTimeout.EventTimeTimeout)


def fold_batch(batch: DataFrame) -> DataFrame:
    """The stateless fold of a micro-batch of ``unit_id, text``."""
    from repeatfold.operators.fold import fold, sizes

    return sizes(fold(batch, ["unit_id"]))


def fold_document_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table_stream(spark, sf_dir, "documents", "doc_id bigint, text string, lang string, source string, n_chars bigint")
    return drain(docs.select(F.col("doc_id").alias("unit_id"), "text"), "append", fold_batch)


def session_units(events: DataFrame) -> DataFrame:
    """The batch twin of ``session_symbols``: sessions by gaps of the whole table."""
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    new = F.coalesce((F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(w).cast("timestamp")) > GAP_MINUTES * 60_000_000).cast("int"), F.lit(1))
    rows = events.withColumn("new", new).withColumn("session", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return rows.groupBy("user_id", "session").agg(F.min("ts").alias("start"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda x: x["event_type"]), " ").alias("symbols"))


_WIN = "select user_id, strftime({start}, '%Y-%m-%d %H:%M:%S') as start, count(*)::bigint as n, round(sum(value::decimal(18, 4)), 4)::double as total from {rows} group by all"
_SESSION = """(select *, sum(new) over (partition by user_id order by ts, event_id) as s from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) <= interval 30 minute then 0 else 1 end as new from events))"""
SQL = {
    "stream_tumbling": _WIN.format(start="time_bucket(interval 1 hour, ts)", rows="events"),
    "stream_sliding": _WIN.format(start="b", rows="(select *, unnest([time_bucket(interval 15 minute, ts) - to_minutes(15 * k) for k in range(4)]) as b from events)"),
    "stream_session": f"select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as start, count(*)::bigint as n, round(sum(value::decimal(18, 4)), 4)::double as total from {_SESSION.replace('<= interval 30 minute', '< interval 30 minute')} group by user_id, s",
    "stream_dedupe": "select event_id, user_id from events",
    "stream_static_join": "select c_mktsegment, count(*)::bigint as n from events join customer on user_id = c_custkey group by 1",
    "stream_stream_join": "select v.event_id as view_id, p.event_id as purchase_id from events v join events p on v.user_id = p.user_id and v.event_type = 'view' and p.event_type = 'purchase' and p.ts between v.ts and v.ts + interval 1 hour",
    "stream_fold_sessions": f"select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as start, string_agg(event_type, ' ' order by ts, event_id) as symbols from {_SESSION} group by user_id, s",
    "stream_fold_documents": "select doc_id as unit_id, length(text)::bigint as n from documents",
}


def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return named(drain(tumbling(event_stream(spark, sf_dir)), "complete"))


def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return named(drain(sliding(event_stream(spark, sf_dir)), "complete"))


def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return named(drain(sessions(event_stream(spark, sf_dir)), "complete"))


def stream_dedupe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stream and a copy of it: each event once."""
    e = event_stream(spark, sf_dir)
    return drain(e.union(event_stream(spark, sf_dir)).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"), "append")


def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = load_table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    return drain(event_stream(spark, sf_dir).join(customers, F.col("user_id") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n")), "complete")


def stream_stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = event_stream(spark, sf_dir).where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("u"), F.col("at").alias("seen"))
    p = event_stream(spark, sf_dir).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("b"), F.col("at").alias("bought"))
    return drain(v.join(p, F.expr("u = b and bought between seen and seen + interval 1 hour")).select("view_id", "purchase_id"), "append")


def stream_fold_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Closed sessions of the stream; what the end of the input leaves open is closed by the batch twin of the same rows."""
    done = drain(session_symbols(event_stream(spark, sf_dir)), "append").select("user_id", _time("start").alias("start"), "symbols")
    units = session_units(load_table(spark, sf_dir, "events")).select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "symbols")
    return done.union(units.join(done.select("user_id", "start"), ["user_id", "start"], "left_anti"))


def stream_fold_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fold_document_stream(spark, sf_dir).select("unit_id", "n")


def queries():
    return {name: globals()[name] for name in SQL}


def oracle_sql():
    return dict(SQL)
