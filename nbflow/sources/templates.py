"""Sixteen small analyses from which the stand-in corpus is rendered: ten that hold a complete lifecycle of
a frame and six that fail in one known way. ``{v}`` is the tracked variable, ``{f}`` a file name.

Each cell is a list of (line, stage, names) with the stage that the line has for ``{v}`` by the rules; the
facts serve as the oracle's side, so the engine's parser never sees them. Stages: init, wrangle, inspect,
utilize, kill, other.
"""

from __future__ import annotations

#: (template, table) in order of template number.
TABLES = ("orders", "customer", "lineitem", "part", "events", "orders", "part", "nation", "orders", "supplier", "orders", "customer", "part", "secret", "orders", "supplier")

I, W, L, U, K, O = "init", "wrangle", "inspect", "utilize", "kill", "other"  # noqa: E741

_IMPORTS = [("import pandas as pd", O), ("import numpy as np", O), ("import matplotlib.pyplot as plt", O), ("import seaborn as sns", O)]
_LOAD = [("{v} = pd.read_csv('data/raw/{f}.csv')", I)]

TEMPLATES: list[list[list[tuple[str, str]]]] = [
    # 0 missing values and a cast
    [_IMPORTS, _LOAD, [("{v}.head()", L)], [("# keep rows with a price", O), ("{v} = {v}.dropna()", W), ("{v}['o_totalprice'] = {v}['o_totalprice'].astype(float).round(1)", W), ("{v} = {v}[{v}['o_totalprice'] > 1000]", W)], [("{v}.head()", L)], [("{v}['o_totalprice'].hist()", U)]],
    # 1 filling and a new column from quantiles
    [_IMPORTS, _LOAD, [("{v}", L)], [("{v} = {v}.fillna(0)", W), ("# quartiles of the balance", O), ("{v}['band'] = pd.qcut({v}['c_acctbal'], 4, labels=False)", W)], [("{v}.tail()", L)], [("sns.boxplot(x='c_mktsegment', y='c_acctbal', data={v})", U)]],
    # 2 two targets in one lifecycle
    [
        _IMPORTS,
        _LOAD,
        [("{v}.head()", L)],
        [("{v}.drop_duplicates(subset=['l_orderkey', 'l_linenumber'], inplace=True)", W), ("{v}['revenue'] = {v}['l_extendedprice'] * (1 - {v}['l_discount'])", W)],
        [("{v}.head()", L)],
        [("# revenue by flag", O), ("{v} = {v}.groupby('l_returnflag', as_index=False)['revenue'].sum()", W), ("{v}.head()", L)],
        [("sns.barplot(x='l_returnflag', y='revenue', data={v})", U)],
    ],
    # 3 strings and names
    [_IMPORTS, _LOAD, [("{v}.head()", L)], [("{v}['p_name'] = {v}['p_name'].str.upper()", W), ("{v} = {v}.rename(columns={{'p_brand': 'brand'}})", W)], [("{v}.head()", L)], [("sns.countplot(x='brand', data={v})", U)]],
    # 4 filter and order
    [_IMPORTS, [("limit = 20", O)], _LOAD, [("{v}.head()", L)], [("{v} = {v}[{v}['value'] > limit]", W), ("# latest first", O), ("{v} = {v}.sort_values('event_id', ascending=False)", W), ("{v}.head()", L)], [("sns.lineplot(x='event_id', y='value', data={v})", U)]],
    # 5 a merge of two loaded frames
    [_IMPORTS, [("left_{v} = pd.read_csv('data/raw/{f}.csv')", O), ("right_{v} = pd.read_csv('data/raw/{g}.csv')", O)], [("{v} = pd.merge(left_{v}, right_{v}, left_on='o_custkey', right_on='c_custkey')", I), ("{v}.head()", L)], [("{v} = {v}.drop(columns=['c_custkey', 'c_name'])", W)], [("{v}.head()", L)], [("sns.heatmap({v}.select_dtypes('number').corr())", U)]],
    # 6 a frame from a literal, long form
    [_IMPORTS, [("{v} = pd.DataFrame({{'key': [1, 2, 3], 'a': [10, 20, 30], 'b': [1, 4, 9]}})", I)], [("{v}.head()", L)], [("{v} = {v}.melt(id_vars='key', value_vars=['a', 'b'])", W)], [("{v}.tail()", L)], [("sns.catplot(x='variable', y='value', data={v})", U)]],
    # 7 a pivot of a merge
    [_IMPORTS, [("left_{v} = pd.read_csv('data/raw/{f}.csv')", O), ("right_{v} = pd.read_csv('data/raw/{g}.csv')", O)], [("{v} = pd.merge(left_{v}, right_{v}, left_on='n_regionkey', right_on='r_regionkey')", I)], [("{v}.head()", L)], [("{v} = {v}.pivot_table(index='r_name', values='n_nationkey', aggfunc='count').reset_index()", W)], [("{v}.head()", L)], [("{v}.plot()", U)]],
    # 8 indicator columns
    [_IMPORTS + [("from sklearn.metrics import accuracy_score", O)], _LOAD, [("{v}.head()", L)], [("{v}['open'] = ({v}['o_orderstatus'] == 'O').astype(int)", W), ("{v} = {v}.drop('o_orderstatus', axis=1)", W)], [("{v}.head()", L)], [("accuracy_score({v}['open'], {v}['open'])", U)]],
    # 9 a slice of a live frame
    [_IMPORTS + [("from sklearn.metrics import r2_score", O)], [("base_{v} = pd.read_csv('data/raw/{f}.csv')", O)], [("{v} = base_{v}[['s_suppkey', 's_acctbal']]", I), ("{v}.head()", L)], [("{v} = {v} * 2", W)], [("{v}.head()", L)], [("r2_score({v}['s_suppkey'], {v}['s_acctbal'])", U)]],
    # 10 never used
    [_IMPORTS, _LOAD, [("{v}.head()", L)], [("{v} = {v}.dropna()", W)], [("{v}.head()", L)]],
    # 11 result under a new name only
    [_IMPORTS, _LOAD, [("{v}.head()", L)], [("other = {v}.sort_values('c_acctbal')", O)], [("{v}.head()", L)], [("{v}['c_acctbal'].hist()", U)]],
    # 12 a cell that isn't Python
    [_IMPORTS, _LOAD, [("{v}.head()", L)], [("{v} = = {v}.dropna(", O)], [("{v}.head()", L)], [("{v}['p_size'].hist()", U)]],
    # 13 a file that no one has
    [_IMPORTS, _LOAD, [("{v}.head()", L)], [("{v} = {v}.dropna()", W)], [("{v}.head()", L)], [("{v}.plot()", U)]],
    # 14 a step that changes nothing
    [_IMPORTS, _LOAD, [("{v}.head()", L)], [("{v} = {v}.reset_index(drop=True)", W)], [("{v}.head()", L)], [("{v}['o_totalprice'].hist()", U)]],
    # 15 a step that fails
    [_IMPORTS, _LOAD, [("{v}.head()", L)], [("{v} = {v}.drop(columns=['no_such_column'])", W)], [("{v}.head()", L)], [("{v}['s_acctbal'].hist()", U)]],
]

#: The second file of those templates that load two.
SECOND = {5: "customer", 7: "region"}
#: Files are slices of the given tables: rows whose key modulo this is the file's number, the first rows by key.
SLICES, SLICE_ROWS = 4, 250
KEYS = {"orders": "o_orderkey", "customer": "c_custkey", "lineitem": "l_orderkey", "part": "p_partkey", "events": "event_id", "nation": "n_nationkey", "supplier": "s_suppkey", "region": "r_regionkey"}


#: What each line reads, defines and calls, written down by hand: (names defined or imported, names read, calls in the
#: order in which they run, whether it stores into a part of ``{v}``). Chains are named by their first variable, which
#: a bracket lacks. The oracle's side of the parser.
LINES: dict[str, tuple[str, str, str, bool]] = {
    "import pandas as pd": ("pd", "", "", False),
    "import numpy as np": ("np", "", "", False),
    "import matplotlib.pyplot as plt": ("plt", "", "", False),
    "import seaborn as sns": ("sns", "", "", False),
    "from sklearn.metrics import accuracy_score": ("accuracy_score", "", "", False),
    "from sklearn.metrics import r2_score": ("r2_score", "", "", False),
    "{v} = pd.read_csv('data/raw/{f}.csv')": ("{v}", "pd", "pd.read_csv", False),
    "left_{v} = pd.read_csv('data/raw/{f}.csv')": ("left_{v}", "pd", "pd.read_csv", False),
    "right_{v} = pd.read_csv('data/raw/{g}.csv')": ("right_{v}", "pd", "pd.read_csv", False),
    "base_{v} = pd.read_csv('data/raw/{f}.csv')": ("base_{v}", "pd", "pd.read_csv", False),
    "{v}.head()": ("", "{v}", "{v}.head", False),
    "{v}.tail()": ("", "{v}", "{v}.tail", False),
    "{v}": ("", "{v}", "", False),
    "{v}.plot()": ("", "{v}", "{v}.plot", False),
    "{v} = {v}.dropna()": ("{v}", "{v}", "{v}.dropna", False),
    "{v}['o_totalprice'] = {v}['o_totalprice'].astype(float).round(1)": ("", "{v} float", "{v}.astype {v}.round", True),
    "{v} = {v}[{v}['o_totalprice'] > 1000]": ("{v}", "{v}", "", False),
    "{v}['o_totalprice'].hist()": ("", "{v}", "{v}.hist", False),
    "{v} = {v}.fillna(0)": ("{v}", "{v}", "{v}.fillna", False),
    "{v}['band'] = pd.qcut({v}['c_acctbal'], 4, labels=False)": ("", "pd {v}", "pd.qcut", True),
    "sns.boxplot(x='c_mktsegment', y='c_acctbal', data={v})": ("", "sns {v}", "sns.boxplot", False),
    "{v}.drop_duplicates(subset=['l_orderkey', 'l_linenumber'], inplace=True)": ("", "{v}", "{v}.drop_duplicates", False),
    "{v}['revenue'] = {v}['l_extendedprice'] * (1 - {v}['l_discount'])": ("", "{v}", "", True),
    "{v} = {v}.groupby('l_returnflag', as_index=False)['revenue'].sum()": ("{v}", "{v}", "{v}.groupby {v}.sum", False),
    "sns.barplot(x='l_returnflag', y='revenue', data={v})": ("", "sns {v}", "sns.barplot", False),
    "{v}['p_name'] = {v}['p_name'].str.upper()": ("", "{v}", "{v}.upper", True),
    "{v} = {v}.rename(columns={{'p_brand': 'brand'}})": ("{v}", "{v}", "{v}.rename", False),
    "sns.countplot(x='brand', data={v})": ("", "sns {v}", "sns.countplot", False),
    "limit = 20": ("limit", "", "", False),
    "{v} = {v}[{v}['value'] > limit]": ("{v}", "{v} limit", "", False),
    "{v} = {v}.sort_values('event_id', ascending=False)": ("{v}", "{v}", "{v}.sort_values", False),
    "sns.lineplot(x='event_id', y='value', data={v})": ("", "sns {v}", "sns.lineplot", False),
    "{v} = pd.merge(left_{v}, right_{v}, left_on='o_custkey', right_on='c_custkey')": ("{v}", "pd left_{v} right_{v}", "pd.merge", False),
    "{v} = {v}.drop(columns=['c_custkey', 'c_name'])": ("{v}", "{v}", "{v}.drop", False),
    "sns.heatmap({v}.select_dtypes('number').corr())": ("", "sns {v}", "{v}.select_dtypes {v}.corr sns.heatmap", False),
    "{v} = pd.DataFrame({{'key': [1, 2, 3], 'a': [10, 20, 30], 'b': [1, 4, 9]}})": ("{v}", "pd", "pd.DataFrame", False),
    "{v} = {v}.melt(id_vars='key', value_vars=['a', 'b'])": ("{v}", "{v}", "{v}.melt", False),
    "sns.catplot(x='variable', y='value', data={v})": ("", "sns {v}", "sns.catplot", False),
    "{v} = pd.merge(left_{v}, right_{v}, left_on='n_regionkey', right_on='r_regionkey')": ("{v}", "pd left_{v} right_{v}", "pd.merge", False),
    "{v} = {v}.pivot_table(index='r_name', values='n_nationkey', aggfunc='count').reset_index()": ("{v}", "{v}", "{v}.pivot_table {v}.reset_index", False),
    "{v}['open'] = ({v}['o_orderstatus'] == 'O').astype(int)": ("", "{v} int", ".astype", True),
    "{v} = {v}.drop('o_orderstatus', axis=1)": ("{v}", "{v}", "{v}.drop", False),
    "accuracy_score({v}['open'], {v}['open'])": ("", "accuracy_score {v}", "accuracy_score.accuracy_score", False),
    "{v} = base_{v}[['s_suppkey', 's_acctbal']]": ("{v}", "base_{v}", "", False),
    "{v} = {v} * 2": ("{v}", "{v}", "", False),
    "r2_score({v}['s_suppkey'], {v}['s_acctbal'])": ("", "r2_score {v}", "r2_score.r2_score", False),
    "other = {v}.sort_values('c_acctbal')": ("other", "{v}", "{v}.sort_values", False),
    "{v}['c_acctbal'].hist()": ("", "{v}", "{v}.hist", False),
    "{v}['p_size'].hist()": ("", "{v}", "{v}.hist", False),
    "{v} = {v}.reset_index(drop=True)": ("{v}", "{v}", "{v}.reset_index", False),
    "{v} = {v}.drop(columns=['no_such_column'])": ("{v}", "{v}", "{v}.drop", False),
    "{v}['s_acctbal'].hist()": ("", "{v}", "{v}.hist", False),
}
#: Modules that imported names stand for, and errors of the templates that fail, with the cell where they do.
MODULES = {"pd": "pandas", "np": "numpy", "plt": "matplotlib.pyplot", "sns": "seaborn", "accuracy_score": "sklearn.metrics.accuracy_score", "r2_score": "sklearn.metrics.r2_score"}
FAILURES = {12: (3, "SyntaxError"), 13: (1, "FileNotFoundError"), 15: (3, "KeyError")}


def cells() -> list[tuple[int, int, str]]:
    """Rows (template, cell, code) with the placeholders of variable and files as ``<v>``, ``<f>`` and ``<g>``."""
    rows = []
    for t, analysis in enumerate(TEMPLATES):
        for j, cell in enumerate(analysis):
            code = "\n".join(line for line, _ in cell)
            rows.append((t, j, code.format(v="<v>", f=f"{TABLES[t]}_<k>", g=f"{SECOND.get(t, '')}_<k>")))
    return rows


def _statements():
    """(template, cell, statement, line, stage, comment before it); comments are no statements, and the cell that isn't
    Python has none."""
    for t, analysis in enumerate(TEMPLATES):
        for j, cell in enumerate(analysis):
            if any("= =" in line for line, _ in cell):
                continue
            s, note = 0, ""
            for line, stage in cell:
                if line.startswith("#"):
                    note = line.lstrip("# ")
                    continue
                yield t, j, s, line, stage, note
                s, note = s + 1, ""


def facts() -> list[tuple[int, int, int, str]]:
    """Rows (template, cell, statement, stage of the tracked variable)."""
    return [(t, j, s, stage) for t, j, s, _, stage, _ in _statements()]


def code_facts() -> list[tuple]:
    """Rows (template, cell, statement, source, comment, defs, uses, calls, stores, tracks); names are apart by spaces, and
    the last says whether the statement has the tracked variable at all."""
    rows = []
    for t, j, s, line, _, note in _statements():
        defs, uses, calls, stores = LINES[line]
        names = [x.replace("{v}", "<v>") for x in (defs, uses, calls)]
        source = line.format(v="<v>", f=f"{TABLES[t]}_<k>", g=f"{SECOND.get(t, '')}_<k>")
        rows.append((t, j, s, source, note, *names, int(stores), int(stores or "{v}" in f"{defs} {uses}".split())))
    return rows
