"""Lifecycle mining over an execution log: the central method of the engine, by windows only.

The given ``events`` table plays the log of kernels: a user is a tracked variable, and each event type
is a stage. One shuffle by user serves every window; nothing is joined or collected.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nbflow.session import table

#: Event type of the log -> stage of a lifecycle (fixed values).
STAGE_OF = {"signup": "init", "click": "wrangle", "view": "inspect", "purchase": "utilize", "error": "exception"}


def staged_log(events: DataFrame) -> DataFrame:
    """Rows (user_id, event_id, ts, stage, life_no): lives are numbered by the running count of inits."""
    stage = F.create_map(*[F.lit(x) for pair in STAGE_OF.items() for x in pair])[F.col("event_type")]
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    rows = events.select("user_id", "event_id", "ts", stage.alias("stage"))
    return rows.withColumn("life_no", F.sum((F.col("stage") == "init").cast("long")).over(order))


def log_lifecycles(events: DataFrame, close_on: str = "first_after_wrangle") -> DataFrame:
    """One row per life: when it began, was first wrangled, and was closed by a utilization (null: never)."""
    life = Window.partitionBy("user_id", "life_no")
    rows = staged_log(events).filter("life_no > 0").withColumn("first_wrangle_ts", F.min(F.when(F.col("stage") == "wrangle", F.col("ts"))).over(life))
    close = F.when((F.col("stage") == "utilize") & (F.col("ts") > F.col("first_wrangle_ts")), F.col("ts"))
    end = F.min(close) if close_on == "first_after_wrangle" else F.max(close)
    return rows.groupBy("user_id", "life_no").agg(
        F.min("ts").alias("init_ts"),
        F.min("first_wrangle_ts").alias("first_wrangle_ts"),
        end.alias("end_ts"),
        F.sum((F.col("stage") == "wrangle").cast("long")).alias("n_wrangle"),
    )


def log_targets(events: DataFrame, close_on: str = "first_after_wrangle") -> DataFrame:
    """Spans between successive inspections of a complete life that hold at least one wrangling step."""
    life = Window.partitionBy("user_id", "life_no")
    rows = staged_log(events).filter("life_no > 0").withColumn("first_wrangle_ts", F.min(F.when(F.col("stage") == "wrangle", F.col("ts"))).over(life))
    close = F.when((F.col("stage") == "utilize") & (F.col("ts") > F.col("first_wrangle_ts")), F.col("ts"))
    end = F.min(close) if close_on == "first_after_wrangle" else F.max(close)
    rows = rows.withColumn("end_ts", end.over(life)).filter(F.col("ts") < F.col("end_ts"))
    order = life.orderBy("ts", "event_id")
    so_far = F.sum((F.col("stage") == "wrangle").cast("long")).over(order.rowsBetween(Window.unboundedPreceding, 0))
    looks = rows.withColumn("done", so_far).filter("stage = 'inspect'")
    spans = looks.withColumn("end_pos_ts", F.lead("ts").over(order)).withColumn("n_wrangle", F.lead("done").over(order) - F.col("done"))
    return spans.filter("n_wrangle > 0").select("user_id", "life_no", F.col("ts").alias("begin_ts"), F.col("end_pos_ts").alias("end_ts"), "n_wrangle")


_STAGED = """staged AS (
  SELECT user_id, event_id, ts,
         CASE event_type WHEN 'signup' THEN 'init' WHEN 'click' THEN 'wrangle' WHEN 'view' THEN 'inspect'
                         WHEN 'purchase' THEN 'utilize' WHEN 'error' THEN 'exception' END AS stage,
         CAST(sum(CASE WHEN event_type = 'signup' THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS life_no
  FROM events),
lives AS (
  SELECT s.user_id, s.life_no, min(s.ts) AS init_ts, min(CASE WHEN stage = 'wrangle' THEN ts END) AS first_wrangle_ts,
         CAST(count(CASE WHEN stage = 'wrangle' THEN 1 END) AS BIGINT) AS n_wrangle
  FROM staged s WHERE life_no > 0 GROUP BY ALL),
closed AS (
  SELECT l.user_id, l.life_no, l.init_ts, l.first_wrangle_ts, {end}(s.ts) AS end_ts, l.n_wrangle
  FROM lives l LEFT JOIN staged s ON s.user_id = l.user_id AND s.life_no = l.life_no AND s.stage = 'utilize' AND s.ts > l.first_wrangle_ts
  GROUP BY ALL),
looks AS (
  SELECT s.user_id, s.life_no, s.ts AS begin_ts, lead(s.ts) OVER (PARTITION BY s.user_id, s.life_no ORDER BY s.ts, s.event_id) AS end_ts
  FROM staged s JOIN closed c USING (user_id, life_no) WHERE s.stage = 'inspect' AND s.ts < c.end_ts),
targets AS (
  SELECT k.user_id, k.life_no, k.begin_ts, k.end_ts, count(*) AS n_wrangle
  FROM looks k JOIN staged s ON s.user_id = k.user_id AND s.life_no = k.life_no AND s.stage = 'wrangle' AND s.ts > k.begin_ts AND s.ts < k.end_ts
  GROUP BY ALL)"""


def _sql(end: str, tail: str) -> str:
    return f"WITH {_STAGED.format(end=end)} {tail}"


def _on_events(method, **args):
    return lambda spark, sf_dir: method(table(spark, sf_dir, "events"), **args)


QUERIES = {
    "w9_stages": _on_events(staged_log),
    "w9_lifecycles": _on_events(log_lifecycles),
    "w9_lifecycles_last": _on_events(log_lifecycles, close_on="last"),
    "w9_targets": _on_events(log_targets),
    "w9_targets_last": _on_events(log_targets, close_on="last"),
}

ORACLES = {
    "w9_stages": _sql("min", "SELECT user_id, event_id, ts, stage, life_no FROM staged"),
    "w9_lifecycles": _sql("min", "SELECT user_id, life_no, init_ts, first_wrangle_ts, end_ts, n_wrangle FROM closed"),
    "w9_lifecycles_last": _sql("max", "SELECT user_id, life_no, init_ts, first_wrangle_ts, end_ts, n_wrangle FROM closed"),
    "w9_targets": _sql("min", "SELECT user_id, life_no, begin_ts, end_ts, n_wrangle FROM targets"),
    "w9_targets_last": _sql("max", "SELECT user_id, life_no, begin_ts, end_ts, n_wrangle FROM targets"),
}
