"""Model inputs: flattened frames, joint and dual token sequences, masks, demonstrations and prompts.

All are expressions over examples; nothing here runs Python. Truncation keeps the end of a context, which is
next to the target, and the beginning of data.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from nbflow.operators.examples import tokens
from nbflow.operators.mining import wrap_text

#: Which modalities the context ablation leaves: (name, code, text, input frame, output frame) (fixed values).
MASKS = (("full", 1, 1, 1, 1), ("code+text", 1, 1, 0, 0), ("code+text+in", 1, 1, 1, 0), ("code+text+out", 1, 1, 0, 1), ("in+out", 0, 0, 1, 1), ("in+out+text", 0, 1, 1, 1), ("in+out+code", 1, 0, 1, 1))
#: Which parts of frames the component ablation leaves: (name, values, column names) (fixed values).
COMPONENTS = (("full", True, True), ("no values", False, True), ("no column names", True, False))
ROWS_SWEEP = (0, 1, 2, 3, 5, 10)
TARGET_TOKENS = 300
INSTRUCTION = "Complete the next cell: write the code that turns the input frame into the output frame."


def flatten_frame(frame: str, rows: int = 5, with_columns: bool = True, with_values: bool = True) -> Column:
    """A frame as text, row by row from left to right, header first."""
    columns = F.col(f"{frame}.columns")
    header = columns if with_columns else F.transform(columns, lambda c, i: F.concat(F.lit("c"), i.cast("string")))
    lines = F.transform(F.slice(F.col(f"{frame}.rows"), 1, rows), lambda r: F.array_join(F.transform(r, lambda x: F.coalesce(x, F.lit("NaN"))), " | ")) if with_values and rows else F.array().cast("array<string>")
    return F.array_join(F.concat(F.array(F.array_join(header, " | ")), lines), "\n")


def _tail(words: Column, n: int) -> Column:
    return F.slice(words, F.greatest(F.size(words) - n + 1, F.lit(1)), n)


def context_text(code: int = 1, text: int = 1) -> Column:
    """The unified context, or what a mask leaves of it."""
    if code and text:
        return F.col("merged_ctx")
    return F.concat_ws("\n", F.nullif("prelude", F.lit("")), F.col("code_ctx")) if code else F.col("text_ctx") if text else F.lit("")


def data_text(frame_in: int = 1, frame_out: int = 1, **parts) -> Column:
    used = [flatten_frame(f, **parts) for f, on in (("in_frame", frame_in), ("out_frame", frame_out)) if on]
    return F.concat_ws("\n", *used) if used else F.lit("")


def serialize_joint(examples: DataFrame, ctx_tokens: int = 256, data_tokens: int = 256, mask=MASKS[0], **parts) -> DataFrame:
    """(example_id, ctx_tokens, data_tokens, n_ctx, n_data, truncated) within one budget; a modality that a mask
    drops is never built."""
    _, code, text, a, b = mask
    rows = examples.select("example_id", "split", tokens(context_text(code, text)).alias("c"), tokens(data_text(a, b, **parts)).alias("d"))
    return rows.select("example_id", "split", _tail(F.col("c"), ctx_tokens).alias("ctx_tokens"), F.slice("d", 1, data_tokens).alias("data_tokens"), F.size("c").alias("n_ctx"), F.size("d").alias("n_data"), ((F.size("c") > ctx_tokens) | (F.size("d") > data_tokens)).alias("truncated"))


def serialize_dual(examples: DataFrame, ctx_tokens: int = 512, data_tokens: int = 512, mask=MASKS[0], **parts) -> DataFrame:
    """As ``serialize_joint``, with a budget of its own for each of two encoders."""
    return serialize_joint(examples, ctx_tokens, data_tokens, mask, **parts)


def truncation_rate(inputs: DataFrame) -> DataFrame:
    return inputs.agg(F.avg(F.col("truncated").cast("double")).alias("share"), F.avg("n_ctx").alias("ctx"), F.avg("n_data").alias("data"))


def cap_target(examples: DataFrame, most: int = TARGET_TOKENS) -> DataFrame:
    return examples.select("example_id", F.slice(tokens("target_code"), 1, most).alias("target_tokens"))


def ring_demos(train: DataFrame, test: DataFrame, k: int = 2, seed: str = "") -> DataFrame:
    """(example_id, demo_rank, demo_id): k demonstrations per test example, all different, without a cross join.

    Training examples stand on a ring in the order of a digest; the i-th test example takes the next k from
    place i * k on. Ranks are found in two levels (within a bucket, then buckets added up), so no task sorts all."""

    def ranked(rows: DataFrame) -> DataFrame:
        digest = F.md5(F.concat(F.lit(seed), "example_id"))
        rows = rows.select("example_id", digest.alias("__m"), F.substring(digest, 1, 2).alias("__b"))
        sizes = rows.groupBy("__b").agg(F.count("*").alias("__n"))
        base = sizes.withColumn("__base", F.coalesce(F.sum("__n").over(Window.partitionBy(F.lit(0)).orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        inside = F.row_number().over(Window.partitionBy("__b").orderBy("__m", "example_id")) - 1
        return rows.withColumn("__i", inside).join(F.broadcast(base), "__b").select("example_id", (F.col("__base") + F.col("__i")).alias("place"))

    pool = ranked(train)
    size = F.broadcast(train.agg(F.count("*").alias("size")))
    asked = ranked(test).crossJoin(size).withColumn("demo_rank", F.explode(F.sequence(F.lit(0), F.lit(k - 1)))).filter("demo_rank < size")
    asked = asked.select("example_id", "demo_rank", F.pmod(F.col("place") * k + F.col("demo_rank"), F.col("size")).alias("place"))
    return asked.join(pool.withColumnRenamed("example_id", "demo_id"), "place").select("example_id", "demo_rank", "demo_id")


def build_prompt(examples: DataFrame, demos: DataFrame | None = None, instruction: str = INSTRUCTION, pool: DataFrame | None = None) -> DataFrame:
    """(example_id, prompt): instruction, demonstrations with their answers, then the example; the instruction and frames
    are triple-quoted prose, so that a prompt is code throughout."""
    head = wrap_text(F.lit(instruction))
    body = F.concat_ws("\n", F.col("merged_ctx"), wrap_text(F.concat_ws("\n", F.lit("Input:"), flatten_frame("in_frame"), F.lit("Output:"), flatten_frame("out_frame"))), F.lit("# code:"))
    asked = examples.select("example_id", body.alias("body"))
    if demos is None:
        return asked.select("example_id", F.concat_ws("\n\n", head, F.col("body")).alias("prompt"))
    shown = (pool if pool is not None else examples).select(F.col("example_id").alias("demo_id"), F.concat_ws("\n", body, F.col("target_code")).alias("demo"))
    listed = demos.join(shown, "demo_id").groupBy("example_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("demo_rank", "demo"))), lambda x: x["demo"]), "\n\n").alias("demos"))
    return asked.join(listed, "example_id", "left").select("example_id", F.concat_ws("\n\n", head, F.col("demos"), F.col("body")).alias("prompt"))


def fits_window(prompts: DataFrame, windows: DataFrame) -> DataFrame:
    """(model, window, fits, n): how many prompts a model's window holds, by our token count."""
    sized = prompts.select(F.size(tokens("prompt")).alias("n_tokens"))
    return sized.crossJoin(F.broadcast(windows)).groupBy("model", "window").agg(F.count_if(F.col("n_tokens") <= F.col("window")).alias("fits"), F.count("*").alias("n"))


def schema_diff(examples: DataFrame) -> DataFrame:
    """(example_id, added, dropped, rows_changed): how the output frame's shape differs from the input's."""
    return examples.select(
        "example_id",
        F.array_sort(F.array_except("out_frame.columns", "in_frame.columns")).alias("added"),
        F.array_sort(F.array_except("in_frame.columns", "out_frame.columns")).alias("dropped"),
        (F.col("out_frame.n_rows") - F.col("in_frame.n_rows")).alias("rows_changed"),
    )
