"""Streaming twins of the miner and its counts over the execution log, each equal to a batch query.

A stream reads the event files, drains them with an available-now trigger and writes Parquet in the shared
folder; checkpoints lie beside it. On a live source the same plans run with any trigger.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from nbflow.plans.eventlog import STAGE_OF, _sql
from nbflow.session import table, work_dir

WATERMARK = "10 minutes"


def event_stream(spark: SparkSession, sf_dir: str, files: int = 1) -> DataFrame:
    """The events as a stream; times become timestamps, as watermarks ask for."""
    schema = table(spark, sf_dir, "events").schema
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/events.parquet")
    folder = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(path).isDirectory()
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files)
    rows = reader.parquet(f"{sf_dir}/events.parquet") if folder else reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def drained(rows: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream until its source is empty, and read what it wrote. In complete and update mode each batch is
    written under its number, so a batch that runs again replaces itself."""
    spark = rows.sparkSession
    out = f"{work_dir(spark)}/stream-{uuid.uuid4().hex}"
    writer = rows.writeStream.outputMode(mode).option("checkpointLocation", f"{out}-state").trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").start(out)
    else:
        query = writer.foreachBatch(lambda df, n: df.write.mode("overwrite").parquet(f"{out}/batch={n}" if mode == "update" else out)).start()
    query.awaitTermination()
    return spark.read.schema(rows.schema).parquet(out)


def stage_of(column: str):
    return F.create_map(*[F.lit(x) for pair in STAGE_OF.items() for x in pair])[F.col(column)]


def tumbling(events: DataFrame) -> DataFrame:
    found = events.withWatermark("ts", WATERMARK).groupBy(F.window("ts", "1 hour"), stage_of("event_type").alias("stage")).agg(F.count("*").alias("n"))
    return found.select(F.col("window.start").alias("began"), "stage", "n")


def sliding(events: DataFrame) -> DataFrame:
    found = events.withWatermark("ts", WATERMARK).groupBy(F.window("ts", "6 hours", "1 hour")).agg(F.count("*").alias("n"))
    return found.select(F.col("window.start").alias("began"), "n")


def sessions(events: DataFrame) -> DataFrame:
    found = events.withWatermark("ts", WATERMARK).groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count("*").alias("n"), F.min("ts").alias("began"), F.max("ts").alias("ended"))
    return found.select("user_id", "began", "ended", "n")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", WATERMARK).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id", "event_type")


def with_stage(events: DataFrame) -> DataFrame:
    """Stream joined with the small static table of stages."""
    stages = events.sparkSession.createDataFrame(list(STAGE_OF.items()), "event_type string, stage string")
    return events.join(F.broadcast(stages), "event_type").select("event_id", "user_id", "stage")


def purchases_after_clicks(events: DataFrame) -> DataFrame:
    buys = events.filter("event_type = 'purchase'").select(F.col("user_id").alias("buyer"), F.col("ts").alias("at"), F.col("event_id").alias("purchase")).withWatermark("at", WATERMARK)
    clicks = events.filter("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("click")).withWatermark("ts", WATERMARK)
    return buys.join(clicks, F.expr("buyer = user_id AND ts <= at AND ts >= at - INTERVAL 1 HOUR")).select("purchase", "click")


CLOSED = "user_id long, life_no long, init_ts timestamp, end_ts timestamp, n_wrangle long"
_STATE = "life_no long, init_us long, wrangled boolean, n_wrangle long, closed boolean"


def _automaton(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """The lifecycle automaton of one variable: rows of a batch in order of time; a life is told when it closes."""
    life, begun, wrangled, n, closed = state.get if state.exists else (0, 0, False, 0, False)
    rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
    out = []
    for ts, stage in zip(rows["ts"], rows["stage"], strict=True):
        if stage == "init":
            life, begun, wrangled, n, closed = life + 1, int(ts.value // 1000), False, 0, False
        elif stage == "wrangle" and life:
            wrangled, n = True, n + 1
        elif stage == "utilize" and wrangled and not closed:
            closed = True
            out.append((key[0], life, pd.Timestamp(begun * 1000), ts, n))
    state.update((life, begun, wrangled, n, closed))
    yield pd.DataFrame(out, columns=["user_id", "life_no", "init_ts", "end_ts", "n_wrangle"])


def closed_lives(events: DataFrame) -> DataFrame:
    """Lives that close, as they close: (user_id, life_no, init_ts, end_ts, n_wrangle up to the close)."""
    rows = events.select("user_id", "event_id", "ts", stage_of("event_type").alias("stage"))
    return rows.groupBy("user_id").applyInPandasWithState(_automaton, CLOSED, _STATE, "append", GroupStateTimeout.NoTimeout)


_LATE = "user_id long, late boolean, n long"


def _late_rows(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """How many of a user's rows, in the order in which they were logged, lie further back than the watermark allows
    from the greatest time seen before them; that time is the state."""
    rows = pd.concat(list(batches)).sort_values("event_id")
    us = rows["ts"].astype("int64") // {"ns": 1000, "us": 1}[rows["ts"].dt.unit]
    least = state.get[0] if state.exists else None
    seen = us.cummax().shift(1)
    if least is not None:
        seen = seen.fillna(least).clip(lower=least)
    late = int((us < seen - pd.Timedelta(WATERMARK) // pd.Timedelta("1us")).sum())
    state.update((int(max(us.max(), least if least is not None else us.max())),))
    yield pd.DataFrame([(key[0], True, late), (key[0], False, len(rows) - late)], columns=["user_id", "late", "n"])


def late_counts(events: DataFrame) -> DataFrame:
    """Per batch, user and whether they come too late: how many events; a stream that drops late rows is watched by it."""
    return events.select("user_id", "event_id", "ts").groupBy("user_id").applyInPandasWithState(_late_rows, _LATE, "greatest_us long", "update", GroupStateTimeout.NoTimeout)


def _plain(df: DataFrame, *times: str) -> DataFrame:
    return df.withColumns({t: F.col(t).cast("timestamp_ntz") for t in times})


QUERIES = {
    "st_tumbling": lambda s, d: _plain(drained(tumbling(event_stream(s, d)), "complete"), "began"),
    "st_sliding": lambda s, d: _plain(drained(sliding(event_stream(s, d)), "complete"), "began"),
    "st_session": lambda s, d: _plain(drained(sessions(event_stream(s, d)), "complete"), "began", "ended"),
    "st_dedup": lambda s, d: drained(deduplicated(event_stream(s, d).withColumn("copy", F.explode(F.sequence(F.lit(1), 1 + F.pmod("event_id", F.lit(3)).cast("int")))).drop("copy"))),
    "st_static_join": lambda s, d: drained(with_stage(event_stream(s, d))),
    "st_stream_join": lambda s, d: drained(purchases_after_clicks(event_stream(s, d))),
    "st_lifecycle": lambda s, d: _plain(drained(closed_lives(event_stream(s, d))), "init_ts", "end_ts"),
    "st_late": lambda s, d: drained(late_counts(event_stream(s, d)), "update").groupBy("late").agg(F.sum("n").alias("n")).filter("n > 0"),
}
_CASE = "CASE event_type WHEN 'signup' THEN 'init' WHEN 'click' THEN 'wrangle' WHEN 'view' THEN 'inspect' WHEN 'purchase' THEN 'utilize' WHEN 'error' THEN 'exception' END"
_O = "OVER (PARTITION BY user_id ORDER BY ts, event_id)"
ORACLES = {
    "st_tumbling": f"SELECT date_trunc('hour', ts) AS began, {_CASE} AS stage, count(*) AS n FROM events GROUP BY ALL",
    "st_sliding": "SELECT began, count(*) AS n FROM (SELECT unnest(generate_series(date_trunc('hour', ts) - INTERVAL 5 HOUR, date_trunc('hour', ts), INTERVAL 1 HOUR)) AS began FROM events) GROUP BY 1",
    "st_session": f"SELECT user_id, min(ts) AS began, max(ts) AS ended, count(*) AS n FROM (SELECT *, sum(fresh) {_O} AS s FROM (SELECT *, CASE WHEN lag(ts) {_O} IS NULL OR ts - lag(ts) {_O} >= INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, s",
    "st_dedup": "SELECT event_id, user_id, event_type FROM events",
    "st_static_join": f"SELECT event_id, user_id, {_CASE} AS stage FROM events",
    "st_stream_join": "SELECT p.event_id AS purchase, c.event_id AS click FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click' AND c.ts <= p.ts AND c.ts >= p.ts - INTERVAL 1 HOUR",
    "st_lifecycle": _sql("min", "SELECT c.user_id, c.life_no, c.init_ts, c.end_ts, count(*) AS n_wrangle FROM closed c JOIN staged s ON s.user_id = c.user_id AND s.life_no = c.life_no AND s.stage = 'wrangle' AND s.ts < c.end_ts GROUP BY ALL"),
    "st_late": "SELECT late, count(*) AS n FROM (SELECT coalesce(ts < max(ts) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) - INTERVAL 10 MINUTE, false) AS late FROM events) GROUP BY 1",
}
