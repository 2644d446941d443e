"""Wrangling operations on Spark frames: what a notebook's target code does, as lazy plans.

Every function takes a frame and gives a frame. None collects rows, except where the domain of values
that becomes columns is not given (``get_dummies``, ``pivot_table``): then one aggregate job reads that
domain, which is bounded by ``max_columns`` and refused beyond it. Order matters in pandas and not in
Spark; where an operation depends on it, the ordering columns are arguments.
"""

from __future__ import annotations

from collections.abc import Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from nbflow.session import settle

MAX_COLUMNS = 1000


def _domain(df: DataFrame, column: str, values: Sequence | None) -> list:
    if values is not None:
        return list(values)
    found = [r[0] for r in df.select(column).filter(F.col(column).isNotNull()).distinct().limit(MAX_COLUMNS + 1).collect()]
    if len(found) > MAX_COLUMNS:
        raise ValueError(f"{column} has more than {MAX_COLUMNS} values; name those that become columns")
    return sorted(found)


# --- missing values -------------------------------------------------------------------------------------


def dropna(df: DataFrame, subset: Sequence[str] | None = None, how: str = "any", thresh: int | None = None) -> DataFrame:
    return df.na.drop(how, thresh, list(subset) if subset else None)


def fillna(df: DataFrame, values: dict) -> DataFrame:
    return df.na.fill(values)


def fill_mean(df: DataFrame, column: str) -> DataFrame:
    """Nulls become the column's mean: one aggregate row, broadcast."""
    mean = df.agg(F.avg(column).alias("__mean"))
    return df.crossJoin(F.broadcast(mean)).withColumn(column, F.coalesce(column, "__mean")).drop("__mean")


def ffill(df: DataFrame, column: str, keys: Sequence[str], order: Sequence[str]) -> DataFrame:
    window = Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    return df.withColumn(column, F.last(column, ignorenulls=True).over(window))


# --- rows and columns -------------------------------------------------------------------------------------


def drop_duplicates(df: DataFrame, subset: Sequence[str], order: Sequence[str], keep: str = "first") -> DataFrame:
    """Of rows equal in ``subset``, the first or last by ``order``."""
    by = [F.col(c) if keep == "first" else F.col(c).desc() for c in order]
    nth = F.row_number().over(Window.partitionBy(*subset).orderBy(*by))
    return df.withColumn("__nth", nth).filter("__nth = 1").drop("__nth")


def astype(df: DataFrame, kinds: dict[str, str]) -> DataFrame:
    """Casts whose failures are null."""
    return df.withColumns({c: F.expr(f"try_cast(`{c}` AS {k})") for c, k in kinds.items()})


def rename(df: DataFrame, names: dict[str, str]) -> DataFrame:
    return df.withColumnsRenamed(names)


def drop_columns(df: DataFrame, *names: str) -> DataFrame:
    return df.drop(*names)


def select(df: DataFrame, *names: str) -> DataFrame:
    return df.select(*names)


def query(df: DataFrame, condition: str | Column) -> DataFrame:
    return df.filter(condition)


def assign(df: DataFrame, **columns: Column) -> DataFrame:
    return df.withColumns(columns)


def map_values(df: DataFrame, column: str, mapping: dict, out: str | None = None) -> DataFrame:
    """Values by a dict; what it lacks is null, as in pandas."""
    pairs = F.create_map(*[F.lit(x) for pair in mapping.items() for x in pair])
    return df.withColumn(out or column, F.try_element_at(pairs, F.col(column)))


def replace(df: DataFrame, column: str, mapping: dict) -> DataFrame:
    return df.replace(mapping, subset=[column])


def apply_rows(df: DataFrame, out: str, function, kind: str, *inputs: str) -> DataFrame:
    """A Python function over rows, in Arrow batches; for what no expression says."""
    @F.pandas_udf(kind)
    def batched(rows: pd.DataFrame) -> pd.Series:
        return pd.Series([function(*row) for row in rows.itertuples(index=False, name=None)], index=rows.index)

    return df.withColumn(out, batched(F.struct(*[F.col(c) for c in inputs])))


def get_dummies(df: DataFrame, column: str, values: Sequence | None = None) -> DataFrame:
    marks = {f"{column}_{v}": F.coalesce((F.col(column) == v).cast("int"), F.lit(0)) for v in _domain(df, column, values)}
    return df.withColumns(marks).drop(column)


def cut(df: DataFrame, column: str, edges: Sequence[float], out: str) -> DataFrame:
    """The number of the interval (edge, next edge] that holds the value, from 0; null outside."""
    ladder = F.lit(None).cast("int")
    for i in reversed(range(len(edges) - 1)):
        ladder = F.when((F.col(column) > edges[i]) & (F.col(column) <= edges[i + 1]), i).otherwise(ladder)
    return df.withColumn(out, ladder)


def qcut(df: DataFrame, column: str, q: int, out: str, accuracy: int | None = None) -> DataFrame:
    """The number of the quantile interval, from 0. Quantiles are exact, or approximate by an accuracy for large
    tables; either way they are one row, and the values need no total order."""
    shares = [i / q for i in range(1, q)]
    measure = F.percentile(column, F.array(*map(F.lit, shares))) if accuracy is None else F.percentile_approx(column, shares, accuracy)
    edges = df.agg(measure.alias("__edges"))
    nth = F.size(F.filter("__edges", lambda e: e < F.col(column)))
    return df.crossJoin(F.broadcast(edges)).withColumn(out, F.when(F.col(column).isNotNull(), nth)).drop("__edges")


# --- several frames -------------------------------------------------------------------------------------


def merge(left: DataFrame, right: DataFrame, on: Sequence[str] | Column, how: str = "inner") -> DataFrame:
    return left.join(right, on, {"outer": "full", "semi": "left_semi", "anti": "left_anti"}.get(how, how)) if how != "cross" else left.crossJoin(right)


def merge_asof(left: DataFrame, right: DataFrame, by: str, at: str, right_at: str, value: str, out: str) -> DataFrame:
    """For each left row the ``value`` of the latest right row of the same ``by`` up to its time: one shuffle of
    both sides and a running window, no range join."""
    names = left.columns
    both = left.select(*names, F.col(at).alias("__t"), F.lit(1).alias("__side"), F.lit(None).cast(right.schema[value].dataType).alias("__v")).unionByName(
        right.select(by, F.col(right_at).alias("__t"), F.lit(0).alias("__side"), F.col(value).alias("__v")), allowMissingColumns=True
    )
    window = Window.partitionBy(by).orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(out, F.last("__v", ignorenulls=True).over(window)).filter("__side = 1").select(*names, out)


def concat(*frames: DataFrame) -> DataFrame:
    out = frames[0]
    for frame in frames[1:]:
        out = out.unionByName(frame, allowMissingColumns=True)
    return out


def arithmetic(left: DataFrame, right: DataFrame, key: str, a: str, b: str, op: str, out: str) -> DataFrame:
    """a op b of the rows that share a key; dividing by zero is null."""
    x, y = F.col(a), F.col(b)
    value = {"+": x + y, "-": x - y, "*": x * y, "/": F.try_divide(x, y)}[op]
    return left.join(right, key).select(key, value.alias(out))


# --- groups and shapes ----------------------------------------------------------------------------------


def groupby_agg(df: DataFrame, keys: Sequence[str], **measures: Column) -> DataFrame:
    return df.groupBy(*keys).agg(*[m.alias(n) for n, m in measures.items()])


def transform(df: DataFrame, keys: Sequence[str], measure: Column, out: str) -> DataFrame:
    return df.withColumn(out, measure.over(Window.partitionBy(*keys)))


def pivot_table(df: DataFrame, index: Sequence[str], columns: str, measure: Column, values: Sequence | None = None) -> DataFrame:
    return df.groupBy(*index).pivot(columns, _domain(df, columns, values)).agg(measure)


def crosstab(df: DataFrame, index: str, columns: str, values: Sequence | None = None) -> DataFrame:
    return pivot_table(df, [index], columns, F.count(F.lit(1)), values).na.fill(0)


def melt(df: DataFrame, ids: Sequence[str], values: Sequence[str], name: str = "variable", value: str = "value") -> DataFrame:
    return df.unpivot(list(ids), list(values), name, value)


def stack(df: DataFrame, ids: Sequence[str], values: Sequence[str], name: str, value: str) -> DataFrame:
    """As ``melt``, without rows whose value is null."""
    return melt(df, ids, values, name, value).filter(F.col(value).isNotNull())


def unstack(df: DataFrame, index: Sequence[str], level: str, value: str, values: Sequence) -> DataFrame:
    return df.groupBy(*index).pivot(level, list(values)).agg(F.first(value))


def sort(df: DataFrame, *order: str | Column) -> DataFrame:
    return df.orderBy(*order)


def sorted_places(df: DataFrame, order: Sequence[Column], out: str) -> DataFrame:
    """Rows with their place, from 1, in a total order of the whole frame: ranges are sorted each by a task, and the
    ranges before a row's are added to its place in its own."""
    ranged = settle(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__at", F.monotonically_increasing_id()), "sorted")
    part = F.shiftright("__at", 33).alias("__part")
    before = Window.partitionBy(F.lit(0)).orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)  # a row per range
    bases = ranged.groupBy(part).agg(F.count("*").alias("__n")).select("__part", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__base"))
    rows = ranged.withColumn("__part", F.shiftright("__at", 33)).join(F.broadcast(bases), "__part")
    return rows.withColumn(out, F.col("__base") + F.col("__at").bitwiseAND(F.lit((1 << 33) - 1)) + 1).drop("__at", "__part", "__base")


def nlargest(df: DataFrame, n: int, column: str, *ties: str) -> DataFrame:
    return df.orderBy(F.col(column).desc(), *ties).limit(n)


def head(df: DataFrame, n: int, *order: str) -> DataFrame:
    return df.orderBy(*order).limit(n)


def tail(df: DataFrame, n: int, *order: str) -> DataFrame:
    return df.orderBy(*[F.col(c).desc() for c in order]).limit(n)


# --- along an order -------------------------------------------------------------------------------------


def along(df: DataFrame, keys: Sequence[str], order: Sequence[str], **measures) -> DataFrame:
    """Columns from functions of a window over ``keys`` in ``order``: measures are functions of that window."""
    window = Window.partitionBy(*keys).orderBy(*order)
    return df.withColumns({n: m(window) for n, m in measures.items()})


def rank(df, keys, order, out="rank"):
    return along(df, keys, order, **{out: lambda w: F.rank().over(w)})


def shift(df, column, n, keys, order, out):
    return along(df, keys, order, **{out: lambda w: F.lag(column, n).over(w)})


def diff(df, column, keys, order, out):
    return along(df, keys, order, **{out: lambda w: F.col(column) - F.lag(column).over(w)})


def pct_change(df, column, keys, order, out):
    return along(df, keys, order, **{out: lambda w: F.try_divide(F.col(column) - F.lag(column).over(w), F.lag(column).over(w))})


def cumsum(df, column, keys, order, out):
    return along(df, keys, order, **{out: lambda w: F.sum(column).over(w.rowsBetween(Window.unboundedPreceding, 0))})


def rolling(df, measure: Column, n: int, keys, order, out):
    return along(df, keys, order, **{out: lambda w: measure.over(w.rowsBetween(1 - n, 0))})


def resample(df: DataFrame, at: str, unit: str, **measures: Column) -> DataFrame:
    return df.groupBy(F.date_trunc(unit, F.col(at)).alias(at)).agg(*[m.alias(n) for n, m in measures.items()])


# --- values -----------------------------------------------------------------------------------------------


def date_parts(df: DataFrame, at: str, *parts: str) -> DataFrame:
    made = {"year": F.year, "month": F.month, "day": F.dayofmonth, "quarter": F.quarter, "dayofyear": F.dayofyear, "hour": F.hour, "week": F.weekofyear}
    return df.withColumns({p: made[p](at) for p in parts})


def explode_words(df: DataFrame, column: str, out: str) -> DataFrame:
    words = F.regexp_extract_all(column, F.lit(r"(\S+)"), 1)
    return df.withColumn(out, F.explode(words))


def json_normalize(df: DataFrame, column: str, schema: str) -> DataFrame:
    return df.withColumn("__json", F.from_json(column, schema)).select(*[c for c in df.columns if c != column], "__json.*")


def describe(df: DataFrame, column: str) -> DataFrame:
    c = F.col(column)
    return df.agg(F.count(c).alias("count"), F.avg(c).alias("mean"), F.stddev_samp(c).alias("std"), F.min(c).alias("min"), F.percentile(c, 0.5).alias("median"), F.max(c).alias("max"))


def value_counts(df: DataFrame, column: str) -> DataFrame:
    return df.groupBy(column).agg(F.count("*").alias("count"))


def sample(df: DataFrame, n: int, key: str, seed: str = "") -> DataFrame:
    """n rows, the same ones on every run: the first by a digest of key and seed."""
    return df.orderBy(F.md5(F.concat(F.lit(seed), F.col(key).cast("string"))), key).limit(n)


def profile_frame(df: DataFrame, columns: Sequence[str]) -> DataFrame:
    """What a reader looks up about a frame: per column its type, share of nulls, distinct values, least and greatest."""
    kinds = dict(df.dtypes)
    measures = [F.count("*").alias("rows")]
    for c in columns:
        measures += [F.count(c).alias(f"{c}__n"), F.count_distinct(c).alias(f"{c}__d"), F.min(c).cast("string").alias(f"{c}__lo"), F.max(c).cast("string").alias(f"{c}__hi")]
    row = [F.struct(F.lit(c).alias("column"), F.lit(kinds[c]).alias("kind"), (F.col("rows") - F.col(f"{c}__n")).alias("nulls"), F.col(f"{c}__d").alias("distinct_values"), F.col(f"{c}__lo").alias("least"), F.col(f"{c}__hi").alias("greatest")) for c in columns]
    return df.agg(*measures).select(F.explode(F.array(*row)).alias("x")).select("x.*")
