"""Accuracy measures, the sandbox, model inputs and generators."""

from __future__ import annotations

import math
import time

import numpy as np
import pytest
from hypothesis import given
from hypothesis import strategies as st
from pyspark.sql import functions as F

from nbflow import experiments
from nbflow.functions import metrics as m
from nbflow.functions import sandbox
from nbflow.operators import examples as ex
from nbflow.operators import generators as g
from nbflow.operators import inputs, mining, scoring

SF = "/root/testdata/sf0.01"
STEP = sandbox.CELL_STEP


def test_identity_and_nothing_in_common():
    code = "df = df.dropna()\nx = df['a'] + 1"
    assert m.code_bleu_parts(code, code) == (1, 1, 1, 1)
    assert m.code_bleu("df = df.dropna()", "") < 0.3
    assert m.ast_match(code, "((") == m.dataflow_match(code, "((") == 0


def test_worked_ngram_match():
    # 4 of 5 tokens agree; 3, 2 and 1 of 4, 3 and 2 longer grams, each with one added to both
    expected = math.exp((math.log(4 / 5) + math.log(4 / 5) + math.log(3 / 4) + math.log(2 / 3)) / 4)
    assert m.ngram_match("a + b + c", "a + b + d") == pytest.approx(expected)
    assert m.ngram_match("a + b", "a + b + c") < 1 and m.ngram_match("a", "a", "none") == 0


def test_dataflow_ignores_names_and_empty_graphs():
    assert m.dataflow_match("b = a", "y = x") == 1
    assert m.dataflow_match("1", "2") == 1 and m.dataflow_match("1", "b = a") == 0


@given(st.text(alphabet="ab=+(\n )", max_size=30), st.text(alphabet="ab=+(\n )", max_size=30))
def test_scores_lie_between_zero_and_one(a, b):
    for part in m.code_bleu_parts(a, b):
        assert 0 <= part <= 1 + 1e-12


def run(*cells, spans=(), files=None):
    return sandbox.limited(lambda: sandbox.replay(list(enumerate(cells)), list(spans), files or {}), 20)


CELLS = ("import pandas as pd\nimport seaborn as sns\ndf = pd.read_csv('x/a.csv')", "df.head()", "df = df.dropna()", "df.head()", "sns.barplot(data=df); df.plot()")
FILES = {"a.csv": "k,v\n1,2.5\n2,\n3,4.0\n"}


def test_replay_records_both_frames():
    found, error = run(*CELLS, spans=[("t", "df", STEP, 3 * STEP, None)], files=FILES)
    assert error is None and found["t"]["before"]["n_rows"] == 3 and found["t"]["after"]["n_rows"] == 2
    assert found["t"]["before"]["rows"][1] == ["2", None]


def test_candidates_run_on_their_own_copy():
    found, _ = run(*CELLS, spans=[("t", "df", STEP, 3 * STEP, None), ("ok", "df", STEP, 3 * STEP, "df = df[df['v'] > 0]"), ("bad", "df", STEP, 3 * STEP, "df['nope']")], files=FILES)
    assert found["ok"]["after"]["strict"] == found["t"]["after"]["strict"] and found["bad"]["error"] == "KeyError"


def test_a_candidate_that_hangs_or_exits_fails_alone():
    found, error = sandbox.limited(
        lambda: sandbox.replay(
            list(enumerate(CELLS)),
            [("t", "df", STEP, 3 * STEP, None)] + [(k, "df", STEP, 3 * STEP, code) for k, code in (("ok", "df = df.dropna()"), ("hang", "while True: pass"), ("exit", "raise SystemExit"), ("spoil", "df.drop(df.index, inplace=True)\npd.merge = None"))],
            FILES,
            1,
        ),
        60,
    )
    assert error is None and {k: v["error"] for k, v in found.items()} == {"t": None, "ok": None, "hang": "TimeoutError", "exit": "SystemExit", "spoil": None}
    assert found["ok"]["after"] == found["t"]["after"]


def test_each_cell_has_its_own_time():
    slow = "import datetime\nt = datetime.datetime.now()\nwhile (datetime.datetime.now() - t).total_seconds() < 0.7: pass"
    assert sandbox.limited(lambda: sandbox.replay([(i, slow) for i in range(4)], [], {}, 1), 60) == ({}, None)
    assert sandbox.limited(lambda: sandbox.replay([(0, slow), (1, "try:\n    while True: pass\nexcept Exception: pass")], [], {}, 1), 60)[1] == "TimeoutError"


def test_two_models_on_one_notebook(spark):
    cells = spark.createDataFrame([(1, i, "code", c) for i, c in enumerate(CELLS)], "nb_id long, cell_idx int, kind string, source string")
    files = spark.createDataFrame([("a.csv", FILES["a.csv"])], "name string, csv string")
    spans = spark.createDataFrame([(1, "truth", "df", STEP, 3 * STEP, None)], "nb_id long, id string, var string, begin_pos long, end_pos long, candidate string")
    frames = ex.replay(spark, ex.bundles(cells, spans), files, 5)
    examples = frames.select(F.lit("e").alias("example_id"), F.lit(1).cast("long").alias("nb_id"), F.lit("df").alias("var"), F.lit(STEP).alias("begin_pos"), F.lit(3 * STEP).alias("end_pos"), "out_frame")
    asked = spark.createDataFrame([("e", "good", "full", "df = df.dropna()"), ("e", "bad", "full", "while True: pass"), ("e", "worse", "full", "raise SystemExit")], "example_id string, model string, ctx string, code string")
    rows = {r["model"]: (r["ea"], r["outcome"]) for r in scoring.execute(spark, asked, examples, cells, files, 2).collect()}
    assert rows == {"good": (True, "ok"), "bad": (False, "TimeoutError"), "worse": (False, "SystemExit")}


def _books(spark, *sources):
    cells = spark.createDataFrame([(i, j, "code", c) for i, code in enumerate(sources) for j, c in enumerate([code, "df.head()", "df = df.dropna()", "df.head()"])], "nb_id long, cell_idx int, kind string, source string")
    spans = spark.createDataFrame([(i, f"t{i}", "df", STEP, 3 * STEP, None) for i in range(len(sources))], "nb_id long, id string, var string, begin_pos long, end_pos long, candidate string")
    return ex.bundles(cells, spans)


def test_equal_notebooks_run_once_and_each_has_its_rows(spark):
    load, other = "import pandas as pd\ndf = pd.read_csv('a.csv')", "import pandas as pd\ndf = pd.read_csv('none.csv')"
    books = _books(spark, load, load, other, load, load + "\nimport random", load + "\nimport random")
    assert ex._runs(books).select("run").distinct().count() == 4
    files = spark.createDataFrame([("a.csv", FILES["a.csv"])], "name string, csv string")
    rows = {r["target_id"]: r for r in ex.replay(spark, books, files, 5).collect()}
    assert {k: r["outcome"] for k, r in rows.items()} == {"t0": "ok", "t1": "ok", "t2": "FileNotFoundError", "t3": "ok", "t4": "ok", "t5": "ok"}
    assert rows["t0"]["out_frame"] == rows["t3"]["out_frame"] and rows["t0"]["in_frame"] == rows["t1"]["in_frame"] and rows["t2"]["in_frame"] is None


def test_few_bytes_of_code_are_dealt_to_many_tasks(spark):
    """Spark folds tasks of few bytes into one, however long they run."""
    books = _books(spark, *[f"import pandas as pd\ndf = pd.DataFrame({{'a': [{i}, None]}})" for i in range(100)])
    files = spark.createDataFrame([("a.csv", "a\n1\n")], "name string, csv string")
    plans = [p._jdf.queryExecution().toString() for p in (ex.replay(spark, books, files, 5), mining.parse_cells(books.select("nb_id", F.lit(0).alias("cell_idx"), F.lit("code").alias("kind"), F.lit("a = 1").alias("source"))))]
    assert all("REPARTITION_BY_NUM" in p for p in plans)


def test_sandbox_limits():
    assert run("import os")[1] == "ImportError" and run("open('/etc/passwd')")[1] == "NameError"
    assert run("import pandas as pd\npd.read_csv('none.csv')")[1] == "FileNotFoundError"
    began = time.time()
    assert sandbox.limited(lambda: sandbox.replay([(0, "while True: pass")], [], {}, 1), 20)[1] in ("TimeoutError", "Killed")
    assert time.time() - began < 10


def test_bag_and_strict_digests():
    import pandas as pd

    a, b = pd.DataFrame({"x": [1, 2], "y": ["p", None]}), pd.DataFrame({"x": [2, 1], "y": [None, "p"]})
    assert sandbox.snapshot(a)["bag"] == sandbox.snapshot(b)["bag"] and sandbox.snapshot(a)["strict"] != sandbox.snapshot(b)["strict"]
    assert sandbox.snapshot(3) is None


def test_frame_equality_at_scale(spark):
    a = spark.range(100).withColumn("v", F.col("id") % 7)
    assert scoring.frames_equal(a, a.repartition(5)).first()[0]
    assert not scoring.frames_equal(a, a.union(a.limit(1))).first()[0]
    assert not scoring.frames_equal(a, a.withColumn("v", F.col("v") + 1)).first()[0]
    assert not scoring.frames_equal(a, a.select("v", "id"), "strict").first()[0]


def test_by_example_finds_simple_steps():
    frame = {"columns": ["a", "b"], "dtypes": ["int", "int"], "rows": [["2", "1"], ["1", "5"]]}
    assert g.synthesize(frame, frame | {"rows": [["1", "5"], ["2", "1"]]}, 1) == "{v} = {v}.sort_values('a')"
    assert g.synthesize(frame, {"columns": ["a"], "dtypes": ["int"], "rows": [["2"], ["1"]]}, 1) == "{v} = {v}.drop(columns=['b'])"
    assert g.synthesize(frame, frame | {"rows": [["9", "9"]]}, 1) is None


def test_parameter_counts_are_near_the_published_size():
    assert 3.0e8 < g.parameter_count(12, 768, 3072, 32100, 2) < 3.1e8
    assert g.lora_param_count(2, 4, 8, 2) == 2 * 2 * 2 * 4 * 8


@pytest.fixture(scope="module")
def corpus(spark):
    return experiments.corpus(spark, SF)


def test_corpus_invariants(corpus):
    rows = corpus.examples.collect()
    assert rows
    for r in rows:
        assert r["n_code_cells"] <= 10 and r["in_frame"]["strict"] != r["out_frame"]["strict"] 
        assert len(r["in_frame"]["rows"]) == (r["in_frame"]["n_rows"] if r["split"] == "test" else min(10, r["in_frame"]["n_rows"]))
        compile(r["merged_ctx"], "context", "exec")
    targets = [r["target_code"] for r in rows]
    assert len(set(targets)) == len(targets)
    others = [r["merged_ctx"] for r in rows if r["split"] != "test"]
    assert not [r for r in rows if r["split"] == "test" and any(r["target_code"] in c for c in others)]
    assert len({(r["nb_id"], r["split"]) for r in rows}) == len({r["nb_id"] for r in rows})


def test_token_budgets_and_masks(corpus):
    for rows, most in ((inputs.serialize_joint(corpus.examples), 256), (inputs.serialize_dual(corpus.examples), 512)):
        assert rows.filter((F.size("ctx_tokens") > most) | (F.size("data_tokens") > most)).count() == 0
    sizes = {mask[0]: inputs.serialize_dual(corpus.examples, mask=mask).agg(F.sum("n_ctx"), F.sum("n_data")).first() for mask in inputs.MASKS}
    for name, (ctx, data) in sizes.items():
        assert ctx <= sizes["full"][0] and data <= sizes["full"][1], name
    assert sizes["in+out"][0] == 0 and sizes["code+text"][1] == 0


def test_truth_scores_full_marks_and_errors_lower_them(spark, corpus):
    found = [(kind, str(rate), g.corrupt(corpus.test, rate, kind)) for kind in ("rename_col", "drop_stmt") for rate in (0, 100)]
    rows = {(r["model"], r["ctx"]): r for r in scoring.report(experiments.scored(corpus, found)).collect()}
    for kind in ("rename_col", "drop_stmt"):
        assert (rows[kind, "0"]["em"], rows[kind, "0"]["cb"], rows[kind, "0"]["ea"]) == (100, 100, 100)
        assert all(rows[kind, "100"][x] < rows[kind, "0"][x] for x in ("em", "cb", "ea"))


def test_generators_answer_every_example_and_data_helps(spark, corpus):
    n = corpus.test.count()
    for model in (g.TwoTowerRetriever(), g.JointRetriever("ast"), g.PromptCopy(2), g.LowRankHead(epochs=3), g.ByExample(), g.CopyLast(), g.ModeTarget()):
        assert model.fit(corpus.train).generate(corpus.test).count() == n
    head = g.LowRankHead(epochs=6).fit(corpus.train)
    assert head.losses[-1] < head.losses[0]
    held = g.LowRankHead(epochs=6, patience=0).fit(corpus.train, corpus.dev)
    assert 1 <= len(held.dev_losses) <= 6


def test_prompts_are_code_throughout(corpus):
    for r in inputs.build_prompt(corpus.test, inputs.ring_demos(corpus.train, corpus.test), pool=corpus.train).collect():
        compile(r["prompt"], "prompt", "exec")


def test_less_context_gives_lower_marks(spark):
    rows = {(r["model"], r["ctx"]): r for r in experiments.context_ablation(spark, SF).collect()}
    assert len(rows) == 14
    for model in experiments.VARIED:
        assert rows[model, "in+out"]["ea"] <= rows[model, "full"]["ea"] and rows[model, "in+out+text"]["ea"] <= rows[model, "in+out+code"]["ea"]


def test_the_case_study_needs_all_of_both_frames(spark):
    rows = experiments.case_study(spark, SF).collect()
    assert rows and all(r["ea"] == (r["ctx"] == "all") == r["em"] for r in rows)
    assert {r["outcome"] for r in rows if r["ctx"] == "no column names"} == {"KeyError"}


def test_external_models_answer_prompts(spark, corpus):
    def make():
        return lambda prompts: np.array([f"# {len(p)}" for p in prompts], dtype=object)

    rows = g.ExternalGenerator(make).fit(corpus.train).generate(corpus.test).collect()
    sizes = {r["example_id"]: len(r["prompt"]) for r in inputs.build_prompt(corpus.test).collect()}
    assert {r["example_id"]: r["code"] for r in rows} == {k: f"# {n}" for k, n in sizes.items()}


def test_nearest_is_exact(spark):
    import numpy as np

    rng = np.random.default_rng(0)
    q, p = rng.normal(size=(7, 5)), rng.normal(size=(40, 5))
    queries = spark.createDataFrame([(str(i), v.tolist()) for i, v in enumerate(q)], "example_id string, vec array<double>")
    pool = spark.createDataFrame([(str(i), v.tolist()) for i, v in enumerate(p)], "id string, vec array<double>")
    got = {r["example_id"]: int(r["id"]) for r in g.nearest(queries, pool).collect()}
    assert got == {str(i): int(j) for i, j in enumerate((q @ p.T).argmax(1))}


def test_bootstrap_interval_holds_the_mean(spark):
    rows = spark.range(300).select(F.col("id").cast("string").alias("example_id"), F.lit("m").alias("model"), F.lit("c").alias("ctx"), (F.col("id") % 4 == 0).alias("ea"))
    [r] = scoring.bootstrap_ci(rows).collect()
    assert r["low"] < 0.25 < r["high"] and r["high"] - r["low"] < 0.2


def test_ring_demos_differ_and_are_stable(spark):
    ids = lambda a, b: spark.range(a, b).select(F.col("id").cast("string").alias("example_id"))
    rows = inputs.ring_demos(ids(0, 20), ids(100, 130), 3)
    assert rows.count() == 90 and rows.groupBy("example_id").agg(F.count_distinct("demo_id").alias("n")).filter("n <> 3").count() == 0
    assert sorted(rows.collect()) == sorted(inputs.ring_demos(ids(0, 20).repartition(5), ids(100, 130), 3).collect())
