"""The experiment workloads: mining run, model comparison, and the ablations of contexts and frames.

Each is a function of (spark, sf_dir). The corpus behind them is mined and replayed once per session and
folder and kept as Parquet in the shared folder.
"""

from __future__ import annotations

from functools import cached_property, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nbflow.operators import examples as ex
from nbflow.operators import generators as g
from nbflow.operators import inputs, scoring
from nbflow.plans.mine import Mined
from nbflow.session import kept, settle
from nbflow.sources import render

_CORPORA: dict[tuple[str, str], Corpus] = {}


class Corpus:
    """Tables of a mined corpus: cells, statements, targets, frames, all examples and the finalized ones. Each is made
    when it is first asked for, so a query pays for what it reads: statistics of targets run no notebook."""

    def __init__(self, spark: SparkSession, d: str, shares: tuple[int, int, int] = ex.SMALL_SPLIT, limit_s: float = ex.CELL_SECONDS):
        self.spark, self.d, self.shares, self.limit_s = spark, d, shares, limit_s
        self.mined = Mined(spark, d)

    @property
    def cells(self) -> DataFrame:
        return self.mined.cells

    @property
    def targets(self) -> DataFrame:
        return self.mined.targets

    @property
    def of_target(self) -> DataFrame:
        return self.mined.of_target

    @cached_property
    def files(self) -> DataFrame:
        return settle(render.data_files(self.spark, self.d), "files")

    @cached_property
    def frames(self) -> DataFrame:
        spans = self.targets.select("nb_id", F.col("target_id").alias("id"), "var", "begin_pos", "end_pos", F.lit(None).cast("string").alias("candidate"))
        whole = ex.split_of(F.col("nb_id"), self.shares) == "test"
        return kept(ex.replay(self.spark, ex.bundles(self.cells, spans, whole), self.files, self.limit_s), "frames")

    @cached_property
    def all(self) -> DataFrame:
        return kept(ex.assemble(self.targets, self.mined.contexts(), self.frames, self.shares), "examples")

    @cached_property
    def examples(self) -> DataFrame:
        return kept(ex.finalized(self.all), "corpus")

    @property
    def train(self) -> DataFrame:
        return self.examples.filter("split = 'train'")

    @property
    def dev(self) -> DataFrame:
        return self.examples.filter("split = 'dev'")

    @property
    def test(self) -> DataFrame:
        return self.examples.filter("split = 'test'")


def corpus(spark: SparkSession, d: str) -> Corpus:
    key = (spark.sparkContext.applicationId, d)
    if key not in _CORPORA:
        _CORPORA[key] = Corpus(spark, d)
    return _CORPORA[key]


def predictions(found: list[tuple[str, str, DataFrame]]) -> DataFrame:
    return reduce(DataFrame.unionByName, [rows.select("example_id", F.lit(m).alias("model"), F.lit(c).alias("ctx"), F.coalesce("code", F.lit("")).alias("code")) for m, c, rows in found])


def scored(c: Corpus, found: list[tuple[str, str, DataFrame]], mode: str = "strict") -> DataFrame:
    """Rows (example_id, model, ctx, em, cb, ea, outcome) of predictions on the test split."""
    rows = kept(predictions(found), "predictions")
    surface = scoring.code_bleu(scoring.exact_match(rows, c.test).drop("target_code"), c.test).select("example_id", "model", "ctx", "code", "em", "cb")
    ran = scoring.execute(c.spark, rows, c.test, c.cells, c.files, mode=mode).select("example_id", "model", "ctx", "outcome", "ea")
    return settle(surface.join(ran, ["example_id", "model", "ctx"]), "scores")


def mining_run(spark: SparkSession, d: str) -> DataFrame:
    """(step, kept): from notebooks to finalized examples."""
    c = corpus(spark, d)
    done = ex.drop_noop(ex.cap_context(c.all))
    steps = [
        ("notebooks", c.cells.select("nb_id").distinct()),
        ("lifecycles", c.mined.lives.filter("end_pos is not null")),
        ("targets", c.targets),
        ("replayed", c.all),
        ("context cap", ex.cap_context(c.all)),
        ("changed frames", done),
        ("unique targets", ex.dedup_examples(done)),
        ("no leakage", c.examples),
    ]
    return reduce(DataFrame.unionByName, [rows.agg(F.count("*").alias("kept")).select(F.lit(i).alias("nth"), F.lit(name).alias("step"), "kept") for i, (name, rows) in enumerate(steps)])


def model_comparison(spark: SparkSession, d: str) -> DataFrame:
    """Stand-ins of every family on the test split: (model, ctx, n, em, cb, ea)."""
    c = corpus(spark, d)
    made = [("two-tower stand-in", g.TwoTowerRetriever().fit(c.train, c.dev))]
    made += [(f"joint stand-in: {features}", g.JointRetriever(features).fit(c.train)) for _, features in g.PLM_CONFIGS]
    made += [("prompt stand-in, 2 demonstrations", g.PromptCopy(2).fit(c.train)), ("prompt stand-in, none", g.PromptCopy(0).fit(c.train)), ("low-rank stand-in", g.LowRankHead().fit(c.train, c.dev)), ("by example", g.ByExample().fit(c.train)), ("copy last cell", g.CopyLast()), ("most frequent", g.ModeTarget().fit(c.train))]
    return scoring.report(scored(c, [(name, "full", model.generate(c.test)) for name, model in made]))


#: The two models whose input is varied: the two-tower one, and a prompted one with two demonstrations.
VARIED = {"two-tower stand-in": g.TwoTowerRetriever, "prompt stand-in, 2 demonstrations": g.PromptCopy}


def _varied(c: Corpus, inputs_: list[tuple[str, dict]]) -> DataFrame:
    """Both models under each input: (name, keywords of the generator)."""
    return scoring.report(scored(c, [(model, name, make(**given).fit(c.train).generate(c.test)) for name, given in inputs_ for model, make in VARIED.items()]))


def context_ablation(spark: SparkSession, d: str) -> DataFrame:
    """Seven contexts, two stand-ins: (model, ctx, n, em, cb, ea)."""
    return _varied(corpus(spark, d), [(mask[0], {"mask": mask}) for mask in inputs.MASKS])


def component_ablation(spark: SparkSession, d: str) -> DataFrame:
    """Frames without values or without column names, two stand-ins: (model, ctx, n, em, cb, ea)."""
    return _varied(corpus(spark, d), [(name, {"parts": {"with_values": values, "with_columns": columns}}) for name, values, columns in inputs.COMPONENTS])


def rows_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Input frames of 0 to 10 rows, two stand-ins: (model, ctx, n, em, cb, ea)."""
    return _varied(corpus(spark, d), [(f"rows={n}", {"parts": {"rows": n}}) for n in inputs.ROWS_SWEEP])


#: The five inputs of the case study: (name, mask, parts of frames).
CASES = (("all", inputs.MASKS[0], {}), ("no column names", inputs.MASKS[0], {"with_columns": False}), ("no values", inputs.MASKS[0], {"with_values": False}), ("no input frame", inputs.MASKS[3], {}), ("no output frame", inputs.MASKS[2], {}))


def case_study(spark: SparkSession, d: str) -> DataFrame:
    """Every example that makes an indicator of a column of words, under five inputs, by the sketch that fills in what it
    sees: (example_id, ctx, code, outcome, em, ea)."""
    c = corpus(spark, d)
    cases = c.all.filter(F.col("target_code").contains(".astype(int)"))
    found = predictions([("sketch", name, g.IndicatorSketch(mask, parts).generate(cases)) for name, mask, parts in CASES])
    ran = scoring.execute(c.spark, kept(found, "predictions"), cases, c.cells, c.files)
    return scoring.exact_match(ran, cases).select("example_id", "ctx", "code", "outcome", "em", "ea")


def corruption_study(spark: SparkSession, d: str) -> DataFrame:
    """Targets with seeded errors of three kinds and three rates: every measure falls as the rate rises."""
    c = corpus(spark, d)
    found = [(kind, f"{rate}%", g.corrupt(c.test, rate, kind)) for kind in ("rename_col", "swap_literal", "drop_stmt") for rate in (0, 50, 100)]
    return scoring.report(scored(c, found))
