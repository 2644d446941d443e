"""Whole jobs: inputs on which a shortened search, probe or number of rounds gives less."""

from __future__ import annotations

import itertools
import re

import pandas as pd
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from nbflow import experiments, registry
from nbflow.operators import collect, mining, relational
from nbflow.operators import generators as g
from nbflow.plans import mine
from nbflow.session import many_tasks


def test_near_duplicates_equal_brute_force(spark, monkeypatch):
    monkeypatch.setattr(collect, "BLOCK", 4)
    base = [f"w{i}" for i in range(60)]
    texts = [" ".join(base[:-n] if n else base) for n in range(12)] * 2  # copies, and near copies of which some are too far apart
    texts += [" ".join([f"u{n}", *base[1:]]) for n in range(12)] + ["other text", "other text"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found = collect.near_duplicates(docs).collect()
    words = {i: re.split(r"\s+", t) for i, t in enumerate(texts)}
    sets = {i: {tuple(w[j : j + 5]) for j in range(max(len(w) - 4, 1))} for i, w in words.items()}
    least = {i: min(j for j in sets if sets[j] == sets[i]) for i in sets}
    likeness = {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for a, b in itertools.combinations(sorted(set(least.values())), 2)}
    expected = [(*k, round(x, 9)) for k, x in likeness.items() if x >= 0.8] + [(a, i, 1.0) for i, a in least.items() if i != a]
    assert sorted((r["a"], r["b"], round(r["similarity"], 9)) for r in found) == sorted(expected)


def test_chain_of_six_frames(spark):
    lines = ["import pandas as pd", "a = pd.read_csv('a.csv')", *(f"{y} = {x}[['x']]" for x, y in itertools.pairwise("abcdefg")), "g.head()", "g = g.dropna()", "g", "g.plot()", "f = 3", "h = f[0]"]
    cells = spark.createDataFrame([(1, i, "code", x) for i, x in enumerate(lines)], "nb_id long, cell_idx int, kind string, source string")
    staged = mining.label_stages(mining.parse_cells(cells))
    assert [(r["var"], r["init_kind"]) for r in staged.filter("stage = 'init'").orderBy("pos").collect()] == [("a", "loading"), *((x, "operation") for x in "bcdefg")]
    assert [r["stage"] for r in staged.filter((F.col("var") == "g") & (F.col("stage") != "other")).orderBy("pos").collect()] == ["init", "inspect", "wrangle", "inspect", "utilize"]
    assert staged.filter("var = 'h' and stage = 'init'").isEmpty()


def test_by_example_searches_all_of_two_steps():
    columns = [f"c{i}" for i in range(150)]
    frame = {"columns": columns, "dtypes": ["int"] * 150, "rows": [[str((7 * i + j) % 5) for i in range(150)] for j in range(3)]}
    last = pd.DataFrame([[int(x) for x in r] for r in frame["rows"]], columns=columns).sort_values("c149", ascending=False)
    goal = {"columns": ["c0"], "dtypes": ["int"], "rows": [[str(x)] for x in last["c0"]]}
    small = {"columns": ["a", "b"], "dtypes": ["int", "int"], "rows": [["2", "1"], ["1", "5"]]}
    assert g.ByExample().max_len == 2
    assert g.synthesize(small, small | {"rows": [["2", "10"], ["4", "2"]]}, g.ByExample().max_len) == "{v} = {v} * 2\n{v} = {v}.sort_values('a')"
    code = g.synthesize(frame, goal, 2)
    assert code and code.count("\n") == 1


def test_low_rank_head_keeps_all_classes(spark, monkeypatch):
    class Frozen:
        def __init__(self, *_):
            pass

        def fit(self, train):
            self.pool = train.select("example_id", F.array_repeat(F.lit(0.5), g.DIM).alias("vec"))
            return self

    monkeypatch.setattr(g, "JointRetriever", Frozen)
    train = spark.range(1005).select(F.lit("train").alias("split"), F.col("id").cast("string").alias("example_id"), F.concat(F.lit("df = df.head("), F.col("id"), F.lit(")")).alias("target_code"), F.lit("df").alias("var"))
    assert len(g.LowRankHead(epochs=1).fit(train).classes) == 1005


def test_quoted_items_are_contained(spark):
    items = {n: " ".join(f"w{n}x{i}" for i in range(n)) for n in (3, 8, 9, 10, 20)}
    around = ['say "{}" now', "({})", "x{}y", "so {} it is", "{}", "so {", "{}."]
    texts = [a.replace("{}", t) for a in around for t in items.values()] + [" ".join(t.split()[1:]) for t in items.values()]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found = collect.contained_items(docs, spark.createDataFrame(list(items.items()), "item_id long, text string")).collect()
    assert sorted(map(tuple, found)) == sorted((i, n) for i, x in enumerate(texts) for n, t in items.items() if t in x)


def test_a_salted_side_is_never_broadcast(spark):
    """Spark's guess of its size leaves out the copies that salting makes."""
    left, right = spark.range(50).selectExpr("id % 3 AS k", "id AS x"), spark.range(3).selectExpr("id AS k", "id * 10 AS y")
    rows = relational.salted_join(left, right, "k", 8)
    assert "Broadcast" not in rows._jdf.queryExecution().executedPlan().toString()
    assert sorted((r["x"], r["y"]) for r in rows.collect()) == [(i, i % 3 * 10) for i in range(50)]


@pytest.mark.parametrize("name", ["b4_api_db", "d7p_params", "d11_params", "e5_delta", "w6_published_delta"])
def test_query_scans_a_given_table(spark, name):
    plan = registry.queries()[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "FileScan parquet" in plan


def test_statistics_of_targets_run_no_notebook(spark, monkeypatch):
    def never(*_):
        raise AssertionError("a notebook ran")

    monkeypatch.setattr(experiments, "_CORPORA", {})
    monkeypatch.setattr(experiments.ex, "replay", never)
    for name in ("c16_share", "c16_mod_hist", "c16_mod_freq", "c16_api_hist", "c16_api_freq"):
        assert registry.queries()[name](spark, "/root/testdata/sf0.001").count() > 0


def test_contexts_reread_what_the_miner_wrote(spark):
    plan = mine.Mined(spark, "/root/testdata/sf0.001").contexts()._jdf.queryExecution().optimizedPlan().toString()
    assert len(re.findall(r"\bWindow \[", plan)) == 1, "the run of markdown before a cell, and nothing of the steps before"


def test_equal_cells_of_a_batch_are_parsed_once(spark, monkeypatch):
    schema = to_arrow_schema(StructType.fromDDL(mining.STATEMENTS))
    sources = ["x = 1\ny = x.sum()  # all", "", "not python (", None, "x = 1\ny = x.sum()  # all", "import pandas as pd", "not python ("] * 3
    cells = pa.record_batch({"nb_id": pa.array(range(len(sources)), pa.int64()), "cell_idx": pa.array([i % 5 for i in range(len(sources))], pa.int32()), "source": pa.array(sources, pa.string())})
    one_by_one = [row for i in range(len(sources)) for got in mining._parsed([cells.slice(i, 1)], schema) for row in got.to_pylist()]
    parsed, plain = [], mining.parse_cell
    monkeypatch.setattr(mining, "parse_cell", lambda source: parsed.append(source) or plain(source))
    assert [row for got in mining._parsed([cells], schema) for row in got.to_pylist()] == one_by_one
    assert len(parsed) == len(set(parsed)) == 4 and len(one_by_one) == 3 * 7
    assert {r["pos"] - r["cell_idx"] * mining.CELL_STEP for r in one_by_one} == {0, 1}


def test_search_by_example_runs_once_in_many_tasks(spark):
    frame = {"columns": ["x"], "dtypes": ["int"], "n_rows": 2, "rows": [["1"], ["2"]], "strict": "", "bag": ""}
    rows = [(str(i), "df", frame, frame | {"rows": [["2"], ["4"]]}) for i in range(9)]
    examples = spark.createDataFrame(rows, f"example_id string, var string, in_frame {experiments.ex.FRAME}, out_frame {experiments.ex.FRAME}").coalesce(1)
    found = g.ByExample().generate(examples)
    assert found.rdd.getNumPartitions() == many_tasks(spark) and {r["code"] for r in found.collect()} == {"df = df * 2"}
    for name, udf in (("d12_pbe", "search("), ("d11_lowrank", "best(")):
        assert udf not in registry.queries()[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()


def test_histograms_make_no_code_of_targets(spark, monkeypatch):
    d, names = "/root/testdata/sf0.001", ("c16_mod_hist", "c16_api_hist", "c16_share")
    c = experiments.Corpus(spark, d)
    expected = {}
    for name, kind in (("c16_mod_hist", "module"), ("c16_api_hist", "api")):
        used = experiments.ex.used_names(c.of_target, c.mined.stmts, mining.named_rows(c.mined.stmts), kind)
        expected[name] = sorted(map(tuple, experiments.ex.usage_histogram(c.targets, used).collect()))

    def never(*_):
        raise AssertionError("code of targets was put together")

    monkeypatch.setattr(experiments, "_CORPORA", {})
    monkeypatch.setattr(mining, "with_code", never)
    found = {name: sorted(map(tuple, registry.queries()[name](spark, d).collect())) for name in names}
    assert all(found.values()) and {k: found[k] for k in expected} == expected


def test_only_what_is_read_later_goes_through_the_pass_over_stages(spark):
    stmts = mine.Mined(spark, "/root/testdata/sf0.001").stmts
    whole, narrow = mining.label_stages(stmts), mining.label_stages(stmts, facts=False)
    assert whole.select(*narrow.columns).exceptAll(narrow).isEmpty() and whole.count() == narrow.count()
    passes = [next(x for x in rows._jdf.queryExecution().optimizedPlan().toString().split("\n") if "MapInArrow" in x) for rows in (whole, narrow)]
    assert all(not re.search(r"\b(calls|literals|imports|rhs_names)#", x) for x in passes)
    assert re.search(r"\bsrc#", passes[0]) and not re.search(r"\b(src|comments|uses)#", passes[1])


def test_joins_of_the_corpus_send_no_table_through_the_driver(spark):
    """Settled tables look a hundredth of their size; joins that go by that broadcast a gigabyte."""
    c = experiments.corpus(spark, "/root/testdata/sf0.001")
    m = c.mined
    plans = {
        "spans": mining.segment_targets(m.staged, m.lives),
        "statements": mining.target_statements(m.spans, m.staged, m.stmts, m.lives),
        "targets": mining.with_code(m.spans, m.of_target),
        "cells": mining.context_cells(m.targets, m.lives),
        "contexts": m.contexts(),
        "bundles": experiments.ex.bundles(m.cells, m.targets.select("nb_id", F.col("target_id").alias("id"), "var", "begin_pos", "end_pos", F.lit(None).cast("string").alias("candidate"))),
        "examples": experiments.ex.assemble(m.targets, m.contexts(), c.frames, c.shares),
        "corpus": experiments.ex.finalized(c.all),
        "copies": g._copied(c.test.select("example_id", F.col("example_id").alias("id")), c.test, c.train),
    }
    plans |= {name: registry.queries()[name](spark, c.d) for name in ("c11_dedup_target", "c13_leak_examples", "d13_copy_last", "d14_corrupt")}
    sent = [name for name, rows in plans.items() if "Broadcast" in rows._jdf.queryExecution().executedPlan().toString()]
    assert not sent
