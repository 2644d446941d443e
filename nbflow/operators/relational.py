"""Relational helpers that the methods share: islands, sessions, band and salted joins, bounded top-k."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def islands(df: DataFrame, keys: Sequence[str], at: str) -> DataFrame:
    """Rows with ``island``: equal for successive values of ``at`` under the same keys."""
    return df.withColumn("island", F.col(at) - F.row_number().over(Window.partitionBy(*keys).orderBy(at)))


def sessions(df: DataFrame, key: str, at: str, tie: str, gap: str) -> DataFrame:
    """Runs of a key's rows with no pause longer than ``gap``: began, ended, n."""
    order = Window.partitionBy(key).orderBy(at, tie)
    fresh = F.coalesce((F.col(at) > F.lag(at).over(order) + F.expr(f"INTERVAL {gap}")).cast("int"), F.lit(1))
    numbered = df.withColumn("__fresh", fresh).withColumn("__s", F.sum("__fresh").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy(key, "__s").agg(F.min(at).alias("began"), F.max(at).alias("ended"), F.count("*").alias("n")).drop("__s")


def ranked_counts(df: DataFrame, column: str) -> DataFrame:
    """Counts of a column's values with their rank, ties sharing one; for columns of a bounded domain."""
    order = Window.partitionBy(F.lit(0)).orderBy(F.col("n").desc())
    return df.groupBy(column).agg(F.count("*").alias("n")).withColumns({"r": F.rank().over(order), "d": F.dense_rank().over(order)})


def band_join(left: DataFrame, right: DataFrame, key: str, x: str, y: str, width: int) -> DataFrame:
    """Pairs of a key with x < y <= x + width. The band becomes a second equality: y lies in x's cell of that width
    or in the next one, so no pair outside two cells is looked at."""
    cells = left.withColumn("__cell", F.explode(F.array(F.floor(F.col(x) / width), F.floor(F.col(x) / width) + 1)))
    return cells.join(right.withColumn("__cell", F.floor(F.col(y) / width)), [key, "__cell"]).filter((F.col(x) < F.col(y)) & (F.col(y) <= F.col(x) + width)).drop("__cell")


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int) -> DataFrame:
    """An inner join whose left side may hold a very frequent key: its rows are spread over ``salts`` parts, and
    the right side comes once per part. It is never broadcast: Spark's guess of its size leaves out the copies."""
    mine = left.withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)))
    theirs = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)).cast("array<bigint>")))
    return mine.join(theirs.hint("merge"), [key, "__salt"]).drop("__salt")


def top_per_group(df: DataFrame, keys: Sequence[str], order: Sequence, k: int) -> DataFrame:
    """The first k rows of each key; Spark keeps k rows per key before the shuffle."""
    nth = F.row_number().over(Window.partitionBy(*keys).orderBy(*order))
    return df.withColumn("__nth", nth).filter(F.col("__nth") <= k).drop("__nth")
