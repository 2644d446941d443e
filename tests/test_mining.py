"""Hand-written notebooks with known stages, lifecycles, targets and contexts."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from nbflow.functions import apidb
from nbflow.functions.parsing import dataflow, is_path, parse_cell, subtrees
from nbflow.operators import collect, mining

SCHEMA = "nb_id long, cell_idx int, kind string, source string"


def notebook(spark, *cells: str | tuple[str, str], nb: int = 1):
    rows = [(nb, i, *(c if isinstance(c, tuple) else ("code", c))) for i, c in enumerate(cells)]
    return spark.createDataFrame(rows, SCHEMA)


def stages(spark, *cells, var="df", **options):
    rows = mining.label_stages(mining.parse_cells(notebook(spark, *cells)), **options).filter(F.col("var") == var)
    return [(r["pos"], r["stage"]) for r in rows.filter("stage <> 'other'").orderBy("pos").collect()]


STEP = mining.CELL_STEP
LOAD = "import pandas as pd\ndf = pd.read_csv('a.csv')"


def test_lifecycle_of_one_frame(spark):
    assert stages(spark, LOAD, "df.head()", "df = df.dropna()", "df", "df.plot()") == [(1, "init"), (1 * STEP, "inspect"), (2 * STEP, "wrangle"), (3 * STEP, "inspect"), (4 * STEP, "utilize")]


def test_alias_and_look_alike(spark):
    assert stages(spark, "import pandas as q\ndf = q.merge(1, 2)") == [(1, "init")]
    assert stages(spark, "import mypd\ndf = mypd.merge(1, 2)") == [(1, "kill")]
    assert stages(spark, "from pandas import read_csv\ndf = read_csv('a')") == [(1, "init")]


def test_self_reassignment_wrangles_and_new_name_does_not(spark):
    assert stages(spark, LOAD, "df = pd.merge(df, df)") == [(1, "init"), (1 * STEP, "wrangle")]
    assert stages(spark, LOAD, "other = df.dropna()") == [(1, "init")]


def test_in_place_changes(spark):
    assert stages(spark, LOAD, "df.dropna(inplace=True)", "df['a'] = 1", "del df['a']", "df += 1", "df.loc[0, 'a'] = 2") == [(1, "init")] + [(i * STEP, "wrangle") for i in range(1, 6)]
    assert stages(spark, LOAD, "df['a'] = 1", subscript_store=False) == [(1, "init")]


def test_operations_on_live_frames_begin_frames(spark):
    assert stages(spark, LOAD, "a = df[['x']]\nb = a * 2\nc = b[['y']]", var="c") == [(1 * STEP + 2, "init")]
    assert stages(spark, "x = [1, 2]\ny = x[0]", var="y") == [(1, "kill")]
    assert stages(spark, LOAD, "w = df.corr()", var="w") == [(1 * STEP, "init")]


def test_kill_ends_liveness(spark):
    assert stages(spark, LOAD, "df = 3", "df.head()") == [(1, "init"), (1 * STEP, "kill")]


def test_reinitialisation_numbers_lives(spark):
    rows = mining.lifecycles(mining.label_stages(mining.parse_cells(notebook(spark, LOAD, "df = pd.read_csv('b')", "df = df.dropna()", "df.hist()")))).filter("var = 'df'")
    assert [(r["life_no"], r["end_pos"]) for r in rows.orderBy("life_no").collect()] == [(1, None), (2, 3 * STEP)]


def test_inspection_position(spark):
    assert stages(spark, LOAD, "df.head()\nx = 1", inspect_position="last_line") == [(1, "init")]
    assert stages(spark, LOAD, "x = 1\ndf.head()", inspect_position="last_line") == [(1, "init"), (1 * STEP + 1, "inspect")]


def test_utilization_needs_the_variable(spark):
    assert stages(spark, LOAD, "import seaborn as sns\nsns.barplot(x=1)", "sns.barplot(data=df)", "ax = df['a'].hist()") == [(1, "init"), (2 * STEP, "utilize"), (3 * STEP, "utilize")]


@pytest.mark.parametrize("api", apidb.LOADERS + apidb.CONSTRUCTORS + apidb.MANIPULATIONS)
def test_every_init_api_is_matched(api):
    assert api in apidb.names("init")


def test_every_init_api_in_one_notebook(spark):
    cells = ["import pandas as pd"] + [f"df{i} = pd.{a}(1)" for i, a in enumerate(apidb.LOADERS + apidb.CONSTRUCTORS + apidb.MANIPULATIONS)]
    rows = mining.label_stages(mining.parse_cells(notebook(spark, *cells)))
    assert rows.filter("stage = 'init'").count() == len(cells) - 1


def test_every_utilize_api_in_one_notebook(spark):
    names = apidb.names("utilize")
    rows = mining.label_stages(mining.parse_cells(notebook(spark, LOAD, *[f"lib.{a}(df)" for a in names])))
    assert rows.filter("stage = 'utilize' and var = 'df'").count() == len(names)


def mined(spark, *cells):
    book = notebook(spark, *cells)
    stmts = mining.parse_cells(book)
    staged = mining.label_stages(stmts)
    lives = mining.lifecycles(staged)
    spans = mining.segment_targets(staged, lives)
    of_target = mining.target_statements(spans, staged, stmts, lives)
    targets = mining.with_code(spans, of_target)
    ctx = mining.context_cells(targets, lives)
    first = mining.prelude(targets, of_target, ctx, stmts)
    return targets, mining.contexts(targets, ctx, first, book, stmts), lives


BOOK = ("import pandas as pd\nimport os", "n = 3", LOAD.split("\n")[1], "df.head()", ("markdown", "drop the gaps"), "# first step\ndf = df.dropna()", "z = 1", "df['a'] = df['b'] * n", "df.head()", "df.plot()")


def test_target_spans_cells_and_keeps_comments(spark):
    targets, contexts, _ = mined(spark, *BOOK)
    [row] = targets.collect()
    assert row["target_code"] == "# first step\ndf = df.dropna()\ndf['a'] = df['b'] * n"
    assert (row["begin_pos"], row["end_pos"], row["n_wrangle"]) == (3 * STEP, 8 * STEP, 2)
    [c] = contexts.collect()
    assert c["prelude"] == "import pandas as pd\nn = 3"
    assert c["code_ctx"] == "df = pd.read_csv('a.csv')\ndf.head()"
    assert "first step" in c["text_ctx"] and c["n_code_cells"] == 2


def test_markdown_before_a_context_cell_is_context(spark):
    book = (LOAD.split("\n")[0], ("markdown", "Load\n\"\"\"data\"\"\""), ("markdown", "  "), LOAD.split("\n")[1], "df.head()", "df = df.dropna()", "df", "df.hist()")
    _, contexts, _ = mined(spark, *book)
    [c] = contexts.collect()
    assert c["merged_ctx"].startswith('import pandas as pd\n"""Load')
    compile(c["merged_ctx"], "context", "exec")


def test_no_target_without_wrangling_or_close(spark):
    assert mined(spark, LOAD, "df.head()", "x = 1", "df.head()", "df.plot()")[0].count() == 0
    assert mined(spark, LOAD, "df.head()", "df = df.dropna()", "df.head()")[0].count() == 0


def test_broken_cells_and_magics(spark):
    rows = mining.parse_cells(notebook(spark, "%matplotlib inline\n!ls\nx = 1", "x = = 2", "")).orderBy("pos").collect()
    assert [(r["kind"], r["parse_ok"]) for r in rows] == [("assign", True), ("error", False)]


def test_renaming_variables_keeps_stages(spark):
    cells = (LOAD, "df.head()", "df = df.dropna()", "df", "df.plot()")
    assert stages(spark, *cells) == stages(spark, *[c.replace("df", "table") for c in cells], var="table")


def test_def_use_and_slices(spark):
    stmts = mining.parse_cells(notebook(spark, "a = 1", "b = a", "c = b", "print(c)"))
    edges = mining.def_use(stmts).filter("def_pos is not null")
    assert sorted((r["use_pos"], r["def_pos"]) for r in edges.collect()) == [(STEP, 0), (2 * STEP, STEP), (3 * STEP, 2 * STEP)]
    seeds = spark.createDataFrame([(1, 3 * STEP)], "nb_id long, pos long")
    assert sorted((r["pos"], r["hops"]) for r in mining.slice_back(edges, seeds, 2).collect()) == [(STEP, 2), (2 * STEP, 1)]


def test_paths(spark):
    assert is_path("data/a.csv") and not is_path("hello world") and not is_path("http://x/y")
    cells = notebook(spark, "x = read('data/a.csv')", "y = read('more/a.csv')", "z = 'b.csv'")
    refs = collect.path_literals(mining.parse_cells(cells))
    files = spark.createDataFrame([("a.csv",)], "name string")
    assert collect.resolve_paths(refs, files).filter("name is null").count() == 1
    flat = [r["source"] for r in collect.flatten_paths(cells, refs).orderBy("cell_idx").collect()]
    assert flat[2] == "z = 'b.csv'" and flat[0] != flat[1] and "/" not in flat[0]


def test_paths_within_paths_stay_whole(spark):
    cells = notebook(spark, "a = read('data/f.csv')", "b = read('x/data/f.csv')", 'c = read("x/data/f.csv")')
    refs = collect.path_literals(mining.parse_cells(cells))
    flat = {r["raw"]: r["flat"] for r in collect.flat_names(refs.select("raw").distinct(), "raw").collect()}
    sources = [r["source"] for r in collect.flatten_paths(cells, refs).orderBy("cell_idx").collect()]
    assert sources == [f"a = read('{flat['data/f.csv']}')", f"b = read('{flat['x/data/f.csv']}')", f'c = read("{flat["x/data/f.csv"]}")']


def test_paths_are_resolved_in_their_own_repository(spark):
    refs = spark.createDataFrame([(1, "r", "data/a.csv"), (2, "s", "data/a.csv"), (3, "t", "data/a.csv"), (4, "u", "a.csv")], "nb_id long, repo string, raw string")
    files = spark.createDataFrame([("r", "data/a.csv"), ("r", "old/a.csv"), ("s", "input/a.csv"), ("u", "x/a.csv"), ("u", "y/a.csv")], "repo string, name string")
    found = {r["nb_id"]: r["name"] for r in collect.resolve_paths(refs, files, ("repo",)).collect()}
    assert found == {1: "data/a.csv", 2: "input/a.csv", 3: None, 4: None}


def test_cells_of_many_statements_keep_their_places(spark):
    many = "\n".join(["x = 1"] * 1500)
    rows = mining.parse_cells(notebook(spark, many, "y = 2")).select("pos").distinct()
    assert rows.count() == 1501


def test_parser_facts():
    [s] = parse_cell("df = df.dropna().reset_index()  # tidy")
    assert [c[1] for c in s.calls] == ["dropna", "reset_index"] and s.comments == ["tidy"] and s.api == "reset_index"
    assert parse_cell("for i in x:\n    y = i")[0].defs == ["i", "y"]
    assert subtrees("a = b + 1") == subtrees("x = y + 2") != subtrees("x = y * 2")
    assert dataflow("b = a") == ["v1<-v0"] and dataflow("(") is None


def test_result_is_independent_of_partitions(spark):
    rows = notebook(spark, *BOOK)
    many = mining.label_stages(mining.parse_cells(rows.repartition(7))).select("pos", "var", "stage")
    one = mining.label_stages(mining.parse_cells(rows.coalesce(1))).select("pos", "var", "stage")
    assert sorted(many.collect()) == sorted(one.collect())
