"""Scores of predictions: surface measures, execution, outcomes, deltas and intervals.

predictions: (example_id, model, ctx, code). Scores have one row per prediction; reports one per (model, ctx).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from nbflow.functions.metrics import PARTS, code_bleu_udf
from nbflow.operators.examples import CELL_SECONDS, bundles, replay


def exact_match(predictions: DataFrame, examples: DataFrame, normalize: bool = False) -> DataFrame:
    """Predictions with ``em``; normalized: trailing spaces and blank lines don't count."""
    rows = predictions.join(examples.select("example_id", "target_code"), "example_id")
    plain = lambda c: F.trim(F.regexp_replace(c, r"[ \t]*\n+", "\n")) if normalize else F.col(c)
    return rows.withColumn("em", plain("code").eqNullSafe(plain("target_code")))


def code_bleu(predictions: DataFrame, examples: DataFrame, weights: tuple[float, ...] = (0.25,) * 4) -> DataFrame:
    """Predictions with the four parts and ``cb``; equal pairs of reference and candidate are scored once."""
    rows = predictions.join(examples.select("example_id", "target_code"), "example_id")
    pairs = rows.select("target_code", "code").distinct().withColumn("parts", code_bleu_udf("target_code", "code")).select("target_code", "code", "parts.*")
    scored = pairs.withColumn("cb", sum((F.col(p) * w for p, w in zip(PARTS, weights, strict=True)), F.lit(0.0)))
    return rows.join(scored, ["target_code", "code"])


def execute(spark: SparkSession, predictions: DataFrame, examples: DataFrame, cells: DataFrame, files: DataFrame, limit_s: float = CELL_SECONDS, mode: str = "strict") -> DataFrame:
    """Predictions with ``ea`` and ``outcome``: each distinct (example, code) runs once, from the state that its
    notebook has before the target; failures and frames that differ count as wrong."""
    distinct = predictions.select("example_id", "code").distinct().withColumn("id", F.concat_ws("|", "example_id", F.md5("code")))
    spans = distinct.join(examples.select("example_id", "nb_id", "var", "begin_pos", "end_pos", F.col("out_frame").alias("truth")), "example_id")
    asked = spans.select("nb_id", "id", "var", "begin_pos", "end_pos", F.col("code").alias("candidate"))
    ran = replay(spark, bundles(cells, asked), files, limit_s).select(F.col("target_id").alias("id"), "outcome", F.col("out_frame").alias("made"))
    judged = spans.join(ran, "id", "left").withColumn("ea", (F.col("outcome") == "ok") & F.coalesce(F.col(f"made.{mode}") == F.col(f"truth.{mode}"), F.lit(False)))
    return predictions.join(judged.select("example_id", "code", "outcome", F.coalesce("ea", F.lit(False)).alias("ea")), ["example_id", "code"], "left")


def execution_outcomes(scores: DataFrame) -> DataFrame:
    """(model, ctx, outcome, n) with kinds: ok, key error, name error, timeout, other."""
    kind = F.when(F.col("outcome") == "ok", "ok").when(F.col("outcome") == "KeyError", "key").when(F.col("outcome") == "NameError", "name").when(F.col("outcome") == "TimeoutError", "timeout").otherwise("other")
    return scores.groupBy("model", "ctx", kind.alias("outcome")).agg(F.count("*").alias("n"))


def row_digest(df: DataFrame) -> Column:
    """A digest of all columns of a row; null differs from every value."""
    return F.xxhash64(*[F.coalesce(F.col(c).cast("string"), F.lit("\x00null")) for c in sorted(df.columns)])


def frame_digest(df: DataFrame) -> DataFrame:
    """One row: number of rows and two sums over row digests, the same for equal bags. Sums are decimals: they can't
    overflow."""
    rows = df.select(row_digest(df).alias("h"))
    return rows.agg(F.count("*").alias("n"), F.sum(F.col("h").cast("decimal(38,0)")).alias("s"), F.sum(F.xxhash64("h").cast("decimal(38,0)")).alias("t"))


def frames_equal(a: DataFrame, b: DataFrame, mode: str = "bag") -> DataFrame:
    """One row (equal): whether two frames hold the same columns and rows. One pass over each, no shuffle of rows.

    strict: columns must also come in the same order and have the same types. The order of rows needs no look of
    its own: a frame has an order here only by columns it holds, and equal bags are then in equal order."""
    same = sorted(a.columns) == sorted(b.columns) if mode == "bag" else a.dtypes == b.dtypes
    if not same:
        return a.sparkSession.createDataFrame([(False,)], "equal boolean")
    x, y = frame_digest(a), frame_digest(b)
    return x.alias("x").crossJoin(y.alias("y")).select(((F.col("x.n") == F.col("y.n")) & F.col("x.s").eqNullSafe(F.col("y.s")) & F.col("x.t").eqNullSafe(F.col("y.t"))).alias("equal"))


def report(scores: DataFrame) -> DataFrame:
    """(model, ctx, n, em, cb, ea) in percent; measures that are absent are left out."""
    have = [m for m in ("em", "cb", "ea") if m in scores.columns]
    return scores.groupBy("model", "ctx").agg(F.count("*").alias("n"), *[F.round(100 * F.avg(F.col(m).cast("double")), 1).alias(m) for m in have])


def delta(rows: DataFrame, base_model: str, keys: tuple[str, ...] = ()) -> DataFrame:
    """Differences of em, cb and ea from those of ``base_model``."""
    base = rows.filter(F.col("model") == base_model).select(*keys, *[F.col(m).alias(f"b_{m}") for m in ("em", "cb", "ea")])
    joined = rows.join(F.broadcast(base), list(keys)) if keys else rows.crossJoin(F.broadcast(base))
    return joined.select("model", *keys, *[F.round(F.col(m) - F.col(f"b_{m}"), 1).alias(f"d_{m}") for m in ("em", "cb", "ea")])


def bootstrap_ci(scores: DataFrame, measure: str = "ea", rounds: int = 200, seed: int = 1) -> DataFrame:
    """(model, low, mean, high): percentile interval of a mean over resamples. A row's count in a resample is drawn
    from a Poisson law by a hash of row and round, so resampling is one pass and the same on every run."""
    u = (F.pmod(F.xxhash64("example_id", "model", "ctx", "round", F.lit(seed)), F.lit(1 << 24)) + 0.5) / float(1 << 24)
    edges, total, p = [], 0.0, 0.36787944117144233
    for k in range(8):
        total += p
        edges.append(total)
        p /= k + 1
    weight = sum(((u > e).cast("int") for e in edges), F.lit(0))
    rows = scores.select("example_id", "model", "ctx", F.col(measure).cast("double").alias("m"), F.explode(F.sequence(F.lit(1), F.lit(rounds))).alias("round")).withColumn("w", weight)
    means = rows.groupBy("model", "round").agg((F.sum(F.col("m") * F.col("w")) / F.nullif(F.sum("w"), F.lit(0))).alias("mean"))
    return means.groupBy("model").agg(F.percentile("mean", 0.025).alias("low"), F.avg("mean").alias("mean"), F.percentile("mean", 0.975).alias("high"))
