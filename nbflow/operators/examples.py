"""From targets to a published corpus: replay, frames, caps, deduplication, splits, leakage and statistics."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from nbflow.functions import sandbox
from nbflow.operators.relational import salted_join
from nbflow.session import many_tasks

FRAME = "struct<columns: array<string>, dtypes: array<string>, n_rows: long, rows: array<array<string>>, strict: string, bag: string>"
#: Seconds that a cell or a candidate may take, and rows of a frame that are stored unless the whole is asked for.
CELL_SECONDS, STORED_ROWS = 300, 10
#: Replayed spans that a task holds before it hands them on; frames wanted whole are large.
HELD_SPANS = 100
#: Words of code whose result may differ from run to run: chance, clocks, addresses.
VARYING = r"random|sample|shuffle|permutation|\bnow\b|today|time|\bid\b|hash|object\("
#: Shares of the splits, in thousandths: those of the published corpus, and larger tests for a small corpus.
PUBLISHED_SPLIT, SMALL_SPLIT = (937, 35, 28), (600, 100, 300)


def bundles(cells: DataFrame, spans: DataFrame, whole: Column | None = None) -> DataFrame:
    """One row per notebook: its code cells, its spans (id, var, begin_pos, end_pos, candidate), and whether its frames
    are wanted whole."""
    code = cells.filter("kind = 'code'").groupBy("nb_id").agg(F.array_sort(F.collect_list(F.struct("cell_idx", "source"))).alias("cells"))
    asked = spans.groupBy("nb_id").agg(F.array_sort(F.collect_list(F.struct("id", "var", "begin_pos", "end_pos", "candidate"))).alias("spans"))
    return asked.join(code, "nb_id").select("nb_id", "cells", "spans", (F.lit(False) if whole is None else whole).alias("whole"))


def _runs(notebooks: DataFrame) -> DataFrame:
    """Bundles with ``run``: equal where cells, places of spans, candidates and wholeness are, so that one run answers for
    all. Code that names what may differ from run to run (VARYING) has a run of its own."""
    places = F.transform("spans", lambda s: F.struct(s["var"], s["begin_pos"], s["end_pos"], s["candidate"]))
    named = lambda code: F.coalesce(code.rlike(VARYING), F.lit(False))
    own = F.when(F.exists("cells", lambda c: named(c["source"])) | F.exists("spans", lambda s: named(s["candidate"])), F.col("nb_id"))
    return notebooks.withColumn("run", F.sha2(F.to_json(F.struct("cells", places.alias("places"), "whole", own.alias("own"))), 256))


def replay(spark: SparkSession, notebooks: DataFrame, files: DataFrame, limit_s: float = CELL_SECONDS) -> DataFrame:
    """Rows (target_id, outcome, in_frame, out_frame) of bundled notebooks, whose cells and candidates may take
    ``limit_s`` each; notebooks of equal code run once. ``files`` is bounded by its maker (slices of a bounded number of
    rows); it is sent to every task once. A failing notebook gives its outcome to all of its spans; outcome is 'ok' or the
    error's class. Bundles are a few kilobytes and take long to run, so their number of tasks is given."""
    held = spark.sparkContext.broadcast({r["name"]: r["csv"] for r in files.collect()})
    made = f"at string, outcome string, in_frame {FRAME}, out_frame {FRAME}"
    schema = to_arrow_schema(StructType.fromDDL(made))

    def run(batches):
        import pandas  # noqa: F401  (here once, so that no child has to)

        for batch in batches:
            out = []
            for key, cells, spans, whole in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                todo = [(i, s["var"], s["begin_pos"], s["end_pos"], s["candidate"]) for i, s in enumerate(spans)]
                plain = [(c["cell_idx"], c["source"]) for c in cells]
                total = limit_s * (len(plain) + sum(s[4] is not None for s in todo)) + 10
                found, error = sandbox.limited(lambda plain=plain, todo=todo, whole=whole: sandbox.replay(plain, todo, held.value, limit_s, None if whole else STORED_ROWS), total)
                for span in todo:
                    got = (found or {}).get(span[0])
                    outcome = error or (got["error"] if got else "Missing") or ("ok" if got["after"] else "NotAFrame")
                    out.append({"at": f"{key}/{span[0]}", "outcome": outcome, "in_frame": got and got["before"], "out_frame": got and got["after"]})
                if len(out) >= HELD_SPANS:
                    yield pa.RecordBatch.from_pylist(out, schema=schema)
                    out = []
            yield pa.RecordBatch.from_pylist(out, schema=schema)

    keyed = _runs(notebooks)
    once = keyed.select("run", "cells", "spans", "whole").dropDuplicates(["run"])
    ran = once.repartition(many_tasks(spark), "run").mapInArrow(run, made)
    asked = keyed.select("run", F.posexplode("spans").alias("nth", "span")).select(F.concat_ws("/", "run", F.col("nth").cast("string")).alias("at"), F.col("span.id").alias("target_id"))
    return salted_join(asked, ran, "at", 8).select("target_id", "outcome", "in_frame", "out_frame")


# --- finalizing


def cap_context(examples: DataFrame, max_cells: int = 10) -> DataFrame:
    return examples.filter(F.col("n_code_cells") <= max_cells)


def drop_noop(examples: DataFrame) -> DataFrame:
    """Without examples whose input and output frames are equal."""
    return examples.filter(F.col("in_frame.strict") != F.col("out_frame.strict"))


def normalized(code: Column) -> Column:
    """Code without comment lines, blank lines and spaces at line ends."""
    return F.array_join(F.filter(F.transform(F.split(code, "\n"), lambda x: F.rtrim(x)), lambda x: (x != "") & ~F.ltrim(x).startswith("#")), "\n")


def dedup_examples(examples: DataFrame, on: Column | None = None) -> DataFrame:
    """Of examples with the same target code the first by id."""
    digest = F.md5(normalized(F.col("target_code")) if on is None else on)
    keep = examples.groupBy(digest.alias("__d")).agg(F.min("example_id").alias("example_id")).select("example_id")
    return examples.join(keep, "example_id", "left_semi")


def split_of(nb_id: Column, shares: tuple[int, int, int] = PUBLISHED_SPLIT) -> Column:
    """Train, dev or test by arithmetic on the notebook, so that no notebook spans two splits."""
    place = F.pmod(nb_id * 7919 + 13, F.lit(1000))
    return F.when(place < shares[0], "train").when(place < shares[0] + shares[1], "dev").otherwise("test")


def remove_leakage(examples: DataFrame) -> DataFrame:
    """Without test examples whose target's lines occur in succession in the context of another split's example.

    Probe: a target's first line by digest, against an index of context lines; candidates are then compared. Neither side
    is broadcast: Spark's guess of their sizes leaves out how well equal code folds in files, and the lines' explosion."""
    lines = lambda c: F.split(normalized(F.col(c)), "\n")
    tests = examples.filter("split = 'test'").select("example_id", normalized(F.col("target_code")).alias("t"), F.xxhash64(F.get(lines("target_code"), F.lit(0))).alias("h"))
    others = examples.filter("split <> 'test'").select(F.concat(F.lit("\n"), normalized(F.col("merged_ctx")), F.lit("\n")).alias("c"), F.array_distinct(F.transform(lines("merged_ctx"), lambda x: F.xxhash64(x))).alias("hs"))
    met = others.select("c", F.explode("hs").alias("h")).join(tests.hint("merge"), "h").filter(F.contains("c", F.concat(F.lit("\n"), F.col("t"), F.lit("\n"))))
    return examples.join(met.select("example_id").distinct().hint("merge"), "example_id", "left_anti")


def assemble(targets: DataFrame, contexts: DataFrame, frames: DataFrame, shares: tuple[int, int, int] = PUBLISHED_SPLIT) -> DataFrame:
    """Examples before finalizing; those whose notebook failed are gone."""
    rows = targets.select("target_id", "nb_id", "var", "life_no", "begin_pos", "end_pos", "target_code").join(contexts, "target_id").join(frames.filter("outcome = 'ok' and in_frame is not null"), "target_id")
    return rows.withColumnRenamed("target_id", "example_id").withColumn("split", split_of(F.col("nb_id"), shares)).drop("outcome")


def finalized(examples: DataFrame, max_cells: int = 10) -> DataFrame:
    return remove_leakage(dedup_examples(drop_noop(cap_context(examples, max_cells))))


# --- statistics


def tokens(text: str | Column) -> Column:
    """Words and single signs."""
    return F.regexp_extract_all(text, F.lit(r"(\w+|[^\w\s])"), 1)


def corpus_stats(examples: DataFrame) -> DataFrame:
    """Rows (metric, split, value): number of examples, average columns and stored rows of the frames (whole ones for test),
    tokens of text and target."""
    one = examples.groupBy("split").agg(
        F.count("*").cast("double").alias("examples"),
        F.avg(F.size("in_frame.columns")).alias("in_columns"),
        F.avg(F.size("in_frame.rows")).alias("in_rows"),
        F.avg(F.size("out_frame.columns")).alias("out_columns"),
        F.avg(F.size("out_frame.rows")).alias("out_rows"),
        F.avg(F.size(tokens("text_ctx"))).alias("text_tokens"),
        F.avg(F.size(tokens("target_code"))).alias("target_tokens"),
    )
    return one.unpivot(["split"], [c for c in one.columns if c != "split"], "metric", "value")


def used_names(of_target: DataFrame, stmts: DataFrame, modules: DataFrame, kind: str) -> DataFrame:
    """(target_id, name): modules or calls that a target uses."""
    rows = of_target.select("target_id", "nb_id", "pos").join(stmts.select("nb_id", "pos", "calls", "uses"), ["nb_id", "pos"])
    if kind == "api":
        return rows.select("target_id", F.explode("calls").alias("c")).select("target_id", F.col("c.api").alias("name")).distinct()
    named = rows.select("target_id", "nb_id", "pos", F.explode("uses").alias("var")).join(modules.filter("module is not null").select("nb_id", "pos", "var", "module"), ["nb_id", "pos", "var"])
    return named.select("target_id", F.split("module", r"\.")[0].alias("name")).distinct()


def usage_histogram(targets: DataFrame, used: DataFrame) -> DataFrame:
    """(n, targets): how many targets use n different names."""
    counted = targets.select("target_id").join(used, "target_id", "left").groupBy("target_id").agg(F.count("name").alias("n"))
    return counted.groupBy("n").agg(F.count("*").alias("targets"))


def usage_frequency(used: DataFrame) -> DataFrame:
    return used.groupBy("name").agg(F.count("*").alias("targets"))


def share_below(histogram: DataFrame, k: int = 3) -> DataFrame:
    return histogram.agg((F.sum(F.when(F.col("n") < k, F.col("targets")).otherwise(0)) / F.sum("targets")).alias("share"))


# --- human verification

#: Context combinations and the rates that serve as thresholds of the stand-in votes (fixed values).
COMBINATIONS = (("CT", 34), ("CTI", 40), ("CTO", 42), ("CTIO", 76))


def votes(labels: DataFrame) -> DataFrame:
    """Stand-in votes of five annotators for every labelled document and combination."""
    combos = F.array(*[F.struct(F.lit(c).alias("ctx"), F.lit(t).alias("thr")) for c, t in COMBINATIONS])
    rows = labels.select("doc_id", "quality", "toxic", F.explode(F.sequence(F.lit(0), F.lit(4))).alias("annotator")).withColumn("c", F.explode(combos))
    score = F.pmod(F.col("doc_id") * 37, F.lit(100)) + F.pmod(F.col("annotator") * 17 + F.col("doc_id") * 11, F.lit(21)) - 10 + 10 * F.col("toxic") - 5 * F.col("quality")
    return rows.select("doc_id", "annotator", F.col("c.ctx").alias("ctx"), (score < F.col("c.thr")).alias("solvable"))


def majority(votes_: DataFrame) -> DataFrame:
    return votes_.groupBy("doc_id", "ctx").agg((F.count_if("solvable") * 2 > F.count("*")).alias("solvable"))


def solvable_rate(majority_: DataFrame) -> DataFrame:
    return majority_.groupBy("ctx").agg(F.count_if("solvable").alias("solvable"), F.count("*").alias("n"))


def sample_fixed(rows: DataFrame, n: int, key: str, seed: str = "") -> DataFrame:
    return rows.orderBy(F.md5(F.concat(F.lit(seed), F.col(key).cast("string"))), key).limit(n)
