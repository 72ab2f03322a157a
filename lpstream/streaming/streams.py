"""Structured Streaming around the sketch: unbounded and windowed sketches, state, joins, sinks.

Streams replay a table as files; a finished run is read back from the sink's
folder, one subfolder a micro-batch, so a batch that is written twice replaces
itself.  Event times are cast to TIMESTAMP, as watermarks ask for.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F, types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.params import SketchSpec
from ..operators import recover, sampler, sketch as sk
from ..sources import updates as up
from ..sources.formats import scratch
from ..sources.tables import SCHEMAS, table, typed

SPEC = SketchSpec(p=1.0, r=500, s=5, d=5)
SET_PARTS = 128  # groups of users a kind: a call into Python costs milliseconds a group


def events_stream(spark: SparkSession, sf: str, files_per_batch: int = 1) -> DataFrame:
    """events as an unbounded file stream with a TIMESTAMP event time."""
    raw = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_batch).parquet(f"{sf}/events.parque[t]")  # a pattern may be one file as well as a folder of them
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def user_day_updates(events: DataFrame, types: list[str]) -> DataFrame:
    kind = F.array_position(F.array(*[F.lit(t) for t in types]), F.col("event_type")) - 1
    return events.select(up.user_day(F.col("user_id"), F.col("ts")).alias("row_id"), kind.cast("int").alias("col_id"), F.col("value").alias("delta"), "ts", "event_id", "user_id")


def updates_stream(spark: SparkSession, sf: str) -> DataFrame:
    return user_day_updates(events_stream(spark, sf), up.event_types(spark, sf))


def finished(stream: DataFrame, mode: str, keys: list[str] | None = None) -> DataFrame:
    """Run a stream over all that is there and read its sink back.

    append: all rows; update: the last row of each key; complete: the last batch.
    """
    spark = stream.sparkSession
    path = scratch(spark, "stream")
    columns = stream.columns

    def write(df: DataFrame, batch: int) -> None:
        df.withColumn("batch", F.lit(batch)).write.mode("overwrite").parquet(f"{path}/batch={batch}.d")

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}-state").foreachBatch(write).trigger(availableNow=True).start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
    rows = spark.read.option("recursiveFileLookup", "true").schema(T.StructType([*stream.schema.fields, T.StructField("batch", T.IntegerType())])).parquet(path)
    if mode == "append":
        return rows.select(*columns)
    if mode == "complete":
        last = rows.agg(F.max("batch")).first()[0]
        return rows.filter(F.col("batch") == F.lit(last)).select(*columns)
    newest = rows.groupBy(*keys).agg(F.max_by(F.struct(*[c for c in columns if c not in keys]), "batch").alias("v"))
    return newest.select(*keys, *[F.col("v")[c].alias(c) for c in columns if c not in keys])


# --- sketches -------------------------------------------------------------------


def shown(cells: DataFrame) -> DataFrame:
    """Cells with their exact integers as text."""
    return cells.withColumn("val", F.col("val").cast("string"))


def sketch_state(spark, sf):
    """The unbounded linear sketch; its final state is the batch sketch."""
    return finished(sk.build(updates_stream(spark, sf), SPEC), "update", ["rep", "bucket", "col_id"])


def sketch_update(spark, sf):
    return shown(sketch_state(spark, sf))


def complete_norms(spark, sf):
    """Bucket sums in complete mode, norms read from the last state."""
    cells = finished(sk.summed(_raw_cells(updates_stream(spark, sf)), "rep", "bucket", "col_id"), "complete")
    return recover.bucket_norms(sk.values(cells.filter("val <> 0"), SPEC), 1.0).select("rep", "bucket", F.round("norm", 2).alias("norm"))


def _raw_cells(log: DataFrame, *more: str) -> DataFrame:
    """Signed fixed-point cells of every update, before any sum."""
    return sk.signed_cells(sk.limbs(sk.validated(log, SPEC.d), SPEC), SPEC, *more)


def _windowed(spark, sf, *window):
    """Windowed cells in append mode; a trailing update far ahead closes the last windows."""
    log = updates_stream(spark, sf).withWatermark("ts", "1 day")
    cells = sk.summed(_raw_cells(log, "ts"), F.window("ts", *window), "rep", "bucket", "col_id")
    flat = cells.select(F.unix_seconds(F.col("window.start")).alias("start"), "rep", "bucket", "col_id", "val")
    return finished(flat, "complete").filter("val <> 0")


def tumbling(spark, sf):
    return shown(_windowed(spark, sf, "1 day"))


def sliding(spark, sf):
    return _windowed(spark, sf, "7 days", "1 day").groupBy("start").agg(F.count("*").alias("cells"), F.sum("val").cast("string").alias("total"))


def panes(spark, sf):
    """Sliding sketches as sums of daily panes: each pane feeds the seven windows that hold it."""
    daily = _windowed(spark, sf, "1 day")
    shifted = daily.select(F.explode(F.sequence(F.lit(0), F.lit(6))).alias("k"), "start", "rep", "bucket", "col_id", "val").select((F.col("start") - F.col("k") * 86400).alias("start"), "rep", "bucket", "col_id", "val")
    summed = shifted.groupBy("start", "rep", "bucket", "col_id").agg(F.sum("val").alias("val")).filter("val <> 0")
    return summed.groupBy("start").agg(F.count("*").alias("cells"), F.sum("val").cast("string").alias("total"))


def sessions(spark, sf):
    """Sessions of a user: events less than thirty minutes apart."""
    e = events_stream(spark, sf).withWatermark("ts", "1 day")
    s = e.groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("mass"))
    return finished(s.select("user_id", F.unix_micros(F.col("session_window.start")).alias("start"), "n", "mass"), "complete")


def late_data(spark, sf):
    """Windowed counts in append mode drop what comes after the watermark; only closed windows are emitted."""
    e = events_stream(spark, sf).withWatermark("ts", "1 hour")
    w = e.groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    return finished(w.select(F.unix_seconds(F.col("window.start")).alias("start"), "n"), "append")


def dedup(spark, sf):
    """An at-least-once source: repeated event ids inside the watermark count once before they are added."""
    once = events_stream(spark, sf)
    twice = once.unionByName(events_stream(spark, sf))
    unique = twice.withWatermark("ts", "2 days").dropDuplicatesWithinWatermark(["event_id"])
    log = user_day_updates(unique, up.event_types(spark, sf))
    return finished(log.select("event_id", "row_id", "col_id", "delta"), "append")


def set_value_state(spark, sf):
    """Overwrites to deltas with the history of the entries as state, many users of one kind in a group.

    A group comes in several frames, and files need not follow the order of events:
    the rows of a batch are ordered together, and one that falls between earlier
    ones changes the delta after it, which is sent again.
    """
    step = np.dtype([("user", np.int64), ("ts", np.int64), ("event_id", np.int64), ("value", np.float64)])

    def deltas(key, frames: Iterator[pd.DataFrame], state: GroupState):
        parts = [np.frombuffer(state.get[0], step) if state.exists else np.zeros(0, step)]
        for pdf in frames:
            part = np.zeros(len(pdf), step)
            micros = pdf["ts"].to_numpy("datetime64[us]")
            part["ts"] = np.where(np.isnat(micros), np.iinfo(np.int64).max, micros.astype(np.int64))  # nulls last
            part["user"], part["event_id"], part["value"] = pdf["user_id"].to_numpy(), pdf["event_id"].to_numpy(), pdf["value"].to_numpy(float)
            parts.append(part)
        every = np.concatenate(parts)
        order = np.lexsort((every["event_id"], every["ts"], every["user"]))
        every, fresh = every[order], order >= len(parts[0])
        same = np.r_[False, every["user"][1:] == every["user"][:-1]]
        before = np.where(same, np.r_[0.0, every["value"][:-1]], 0.0)
        sent = fresh | same & np.r_[False, fresh[:-1]]
        state.update((every.tobytes(),))
        change = every["value"] - np.where(np.isnan(before), 0.0, before)
        yield pd.DataFrame({"event_id": every["event_id"][sent], "row_id": every["user"][sent], "kind": key[0], "delta": change[sent]})

    user = F.coalesce("user_id", F.lit(-(2**63)).cast("long"))
    grouped = events_stream(spark, sf).withColumns({"user_id": user, "part": F.pmod(user, F.lit(SET_PARTS))}).groupBy("event_type", "part")
    out = grouped.applyInPandasWithState(deltas, "event_id long, row_id long, kind string, delta double", "history binary", "update", GroupStateTimeout.NoTimeout)
    return finished(out, "update", ["event_id"]).select("event_id", F.round("delta", 6).alias("delta"))


def static_join(spark, sf):
    """Events enriched from a static table."""
    c = table(spark, sf, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    j = events_stream(spark, sf).join(c, "user_id", "left").groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("mass"))
    return finished(j, "complete")


def stream_join(spark, sf):
    """Clicks with purchases of the same user within the hour, both sides with watermarks."""
    e = events_stream(spark, sf)
    clicks = e.filter("event_type = 'click'").select(F.col("user_id"), F.col("ts").alias("t1"), F.col("event_id").alias("click")).withWatermark("t1", "1 day")
    buys = events_stream(spark, sf).filter("event_type = 'purchase'").select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"), F.col("event_id").alias("purchase")).withWatermark("t2", "1 day")
    j = clicks.join(buys, F.expr("user_id = u2 and t2 >= t1 and t2 < t1 + interval 1 hour"))
    return finished(j.select("click", "purchase"), "append")


def snapshot_sample(spark, sf):
    """Post-processing of the latest state into a sample."""
    cells = sketch_state(spark, sf).filter("val <> 0").persist()
    ids = up.ids(up.user_days(spark, sf))
    s = sampler.sample(cells, ids, SPEC, 20)
    return s.select("row_id", F.round("norm_p", 2).alias("norm_p"), F.round("prob", 6).alias("prob"))


def stream_files(spark, sf):
    return finished(events_stream(spark, sf).groupBy("event_type").agg(F.count("*").alias("n")), "complete")


def rate_stream(spark, sf):
    """Updates of events at a bounded rate, one file a micro-batch, through a file sink; ends when all that is there has been read."""
    log = updates_stream(spark, sf).select("row_id", "col_id", "delta")
    path = scratch(spark, "rate")
    q = log.writeStream.format("parquet").option("path", path).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(log.schema).parquet(path).groupBy("col_id").agg(F.countDistinct("row_id").alias("n_rows"))


def memory_sink(spark, sf):
    """The memory sink, for small results in tests."""
    name = "events_by_type"
    q = events_stream(spark, sf).groupBy("event_type").agg(F.count("*").alias("n")).writeStream.format("memory").queryName(name).outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def foreach_batch(spark, sf):
    """Sketch snapshots upserted a micro-batch at a time: each batch's own sketch is stored by its id, the state is their sum."""
    path = scratch(spark, "snapshots")

    def write(df: DataFrame, batch: int) -> None:
        sk.build(df, SPEC).write.mode("overwrite").parquet(f"{path}/{batch}")

    q = updates_stream(spark, sf).writeStream.option("checkpointLocation", f"{path}-state").foreachBatch(write).trigger(availableNow=True).start()
    q.awaitTermination()
    return shown(sk.merge(spark.read.option("recursiveFileLookup", "true").parquet(path)))


SESSIONS_SQL = """with g as (select user_id, ts, value, event_id, case when ts - lag(ts) over w < interval 30 minutes then 0 else 1 end as opens from events window w as (partition by user_id order by ts, event_id)),
s as (select *, sum(opens) over (partition by user_id order by ts, event_id rows unbounded preceding) as k from g)
select user_id, epoch_us(min(ts)) as start, count(*) as n, round(sum(value), 4) as mass from s group by user_id, k"""


def _cells_sql(group: str = "", source_extra: str = "") -> str:
    from ..plans import method_sql as q

    return f"""with upd as ({q.USER_DAYS}), {q.rep_table(SPEC)}, {q.limbs(SPEC, "upd", "log", ", ts")},
cells as (select rep, {q.bucket(SPEC)} as bucket, col_id, {q.sign()} as sg, h2, h1, h0, ts from log, reps)"""


def queries() -> dict:
    return {
        "stream_sketch_update": sketch_update, "stream_complete_norms": complete_norms, "stream_tumbling": tumbling, "stream_sliding": sliding, "stream_panes": panes,
        "stream_session": sessions, "stream_late_data": late_data, "stream_dedup": dedup, "stream_set_value_state": set_value_state, "stream_static_join": static_join,
        "stream_stream_join": stream_join, "stream_snapshot_sample": snapshot_sample, "src_stream_files": stream_files, "src_rate_stream": rate_stream,
        "sink_foreach_batch": foreach_batch, "sink_memory": memory_sink,
    }


def oracle_sql() -> dict[str, str]:
    c = _cells_sql()
    from ..plans.method_sql import USER_DAYS, VAL, number

    sums = f"cast({VAL} as varchar)"
    cells = f"select rep, bucket, col_id, {sums} as val from cells group by all having {VAL} <> 0"
    day = f"select (epoch(ts)::bigint // 86400) * 86400 as start, rep, bucket, col_id, {sums} as val from cells group by all having {VAL} <> 0"
    slide = f"select ((floor(epoch(ts))::bigint // 86400) - k) * 86400 as start, rep, bucket, col_id, {VAL} as val from cells, range(7) r(k) group by all having {VAL} <> 0"
    day = day.replace("epoch(ts)::bigint", "floor(epoch(ts))::bigint")
    return {
        "stream_sketch_update": f"{c} {cells}",
        "sink_foreach_batch": f"{c} {cells}",
        "stream_complete_norms": f"{c}, s as ({cells.replace(sums, VAL)}) select rep, bucket, round(sum(abs({number(SPEC)})), 2) as norm from s group by all",
        "stream_tumbling": f"{c} {day}",
        "stream_sliding": f"{c}, s as ({slide}) select start, count(*) as cells, cast(sum(val) as varchar) as total from s group by start",
        "stream_panes": f"{c}, s as ({slide}) select start, count(*) as cells, cast(sum(val) as varchar) as total from s group by start",
        "stream_session": SESSIONS_SQL,
        "stream_set_value_state": "select event_id, round(value - coalesce(lag(value) over (partition by user_id, event_type order by ts, event_id), 0), 6) as delta from events",
        "stream_dedup": f"select event_id, user_id * 100000 + date_diff('day', date '1970-01-01', cast(ts as date)) as row_id, cast(k.pos as integer) as col_id, value as delta from events join (select event_type, row_number() over (order by event_type) - 1 as pos from (select distinct event_type from events)) k using (event_type)",
        "stream_static_join": "select c_mktsegment, count(*) as n, round(sum(value), 2) as mass from events left join customer on user_id = c_custkey group by 1",
        "stream_stream_join": "select c.event_id as click, p.event_id as purchase from events c join events p on c.user_id = p.user_id and p.ts >= c.ts and p.ts < c.ts + interval '1' hour where c.event_type = 'click' and p.event_type = 'purchase'",
        "src_stream_files": "select event_type, count(*) as n from events group by 1",
        "src_rate_stream": f"select col_id, count(distinct row_id) as n_rows from ({USER_DAYS}) group by col_id",
        "sink_memory": "select event_type, count(*) as n from events group by 1",
    }
