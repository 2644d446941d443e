"""Compiled plans against pandas, and what is refused."""

from __future__ import annotations

import pandas as pd
import pytest

from nbflow.functions import sandbox
from nbflow.operators.compiler import Unsupported, apply_ops, compile_ops

FRAME = pd.DataFrame({"k": [3, 1, 2, 4], "v": [1.25, None, 4.0, -2.5], "s": ["a b", "B", None, "c"]})

CODES = [
    "df = df.dropna()",
    "df = df.dropna(subset=['v'])\ndf['w'] = df['v'] * 2 + df['k']",
    "df.fillna({'v': 0}, inplace=True)",
    "df = df[df['v'] > 1]",
    "n = 2\ndf = df[(df['k'] >= n) & ~(df['v'] < 0)]",
    "df = df.rename(columns={'v': 'value'}).drop(columns=['s'])",
    "df['s'] = df['s'].str.upper()",
    "df['hit'] = (df['s'] == 'B').astype(int)",
    "df = df[['k', 'v']]\ndf = df * 3",
    "df = df.melt(id_vars='k', value_vars=['v'])",
    "df = df.dropna(subset=['v'])\ndf = df.groupby('k', as_index=False)['v'].sum()",
    "df = df.sort_values('k', ascending=False)",
    "df['v'] = df['v'].fillna(1.0).round(1)",
    "df = df[df['k'].isin([1, 2])]",
    "del df['s']",
]


@pytest.mark.parametrize("code", CODES)
def test_native_plan_equals_pandas(spark, code):
    rows = [[None if x != x else x for x in r] for r in FRAME.itertuples(index=False, name=None)]
    frame = spark.createDataFrame(rows, "k long, v double, s string")
    mine = apply_ops(frame, compile_ops(code, "df")).toPandas()
    space = {"df": FRAME.copy(), "pd": pd}
    exec(code, space)
    theirs = space["df"]
    as_bag = lambda f: sorted([[sandbox._cell(float(x) if isinstance(x, (int, float)) else x) for x in r] for r in f.itertuples(index=False, name=None)], key=repr)
    assert list(map(str, mine.columns)) == list(map(str, theirs.columns)) and as_bag(mine) == as_bag(theirs)


@pytest.mark.parametrize("code", ["df = df.apply(len)", "df = other", "import os", "df = df.pivot_table('a')", "df.plot()"])
def test_what_is_not_recognized_is_refused(code):
    with pytest.raises(Unsupported):
        compile_ops(code, "df")


def test_filter_reaches_the_scan(spark):
    orders = spark.read.parquet("/root/testdata/sf0.001/orders.parquet")
    plan = apply_ops(orders, compile_ops("df = df[df['o_totalprice'] > 1000]\ndf = df[['o_orderkey']]", "df"))._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters" in plan and "ReadSchema: struct<o_orderkey:bigint,o_totalprice:double>" in plan
