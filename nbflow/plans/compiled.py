"""Target code of the templates compiled to native plans over full tables, each with its SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from nbflow.operators.compiler import apply_ops, compile_ops
from nbflow.operators.mining import CELLS_UDTF
from nbflow.session import table
from nbflow.sources import render

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

#: (name, table, columns, code on ``df``, SQL)
CODE = [
    ("dropna_filter", "orders", ["o_orderkey", "o_totalprice"], "df = df.dropna()\ndf = df[df['o_totalprice'] > 100000]", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > 100000"),
    ("upper_rename", "part", ["p_partkey", "p_name", "p_brand"], "df['p_name'] = df['p_name'].str.upper()\ndf = df.rename(columns={'p_brand': 'brand'})", "SELECT p_partkey, upper(p_name) AS p_name, p_brand AS brand FROM part"),
    ("filter_sort", "events", ["event_id", "value"], "limit = 20\ndf = df[(df['value'] > limit) & (df['value'] < 60)]\ndf = df.sort_values('event_id', ascending=False)", "SELECT event_id, value FROM events WHERE value > 20 AND value < 60"),
    ("indicator", "orders", ["o_orderkey", "o_orderstatus"], "df['open'] = (df['o_orderstatus'] == 'O').astype(int)\ndf = df.drop('o_orderstatus', axis=1)", "SELECT o_orderkey, CAST(o_orderstatus = 'O' AS BIGINT) AS open FROM orders"),
    ("slice_scale", "supplier", ["s_suppkey", "s_acctbal"], "df = df[['s_suppkey', 's_acctbal']] * 2", "SELECT s_suppkey * 2 AS s_suppkey, s_acctbal * 2 AS s_acctbal FROM supplier"),
    ("melt", "part", ["p_partkey", "p_size"], "df = df.melt(id_vars='p_partkey', value_vars=['p_size'])", "SELECT p_partkey, 'p_size' AS variable, p_size AS value FROM part"),
    ("group", "lineitem", ["l_returnflag", "l_quantity"], "df = df.groupby('l_returnflag', as_index=False)['l_quantity'].max()", "SELECT l_returnflag, max(l_quantity) AS l_quantity FROM lineitem GROUP BY 1"),
    ("quantiles", "customer", ["c_custkey", "c_acctbal"], "df = df.fillna(0)\ndf['band'] = pd.qcut(df['c_acctbal'], 2, labels=False)", "SELECT c_custkey, c_acctbal, CAST(c_acctbal > (SELECT quantile_cont(c_acctbal, 0.5) FROM customer) AS INT) AS band FROM customer"),
]
for _name, _table, _columns, _code, _sql in CODE:
    QUERIES[f"c7b_{_name}"] = lambda s, d, t=_table, c=_columns, code=_code: apply_ops(table(s, d, t).select(*c), compile_ops(code, "df"))
    ORACLES[f"c7b_{_name}"] = _sql


def _udtf(spark, d):
    """Statements by a table function joined laterally: the parser as SQL sees it."""
    spark.udtf.register("nbflow_statements", CELLS_UDTF)
    render.rendered_cells(spark, d).filter("kind = 'code'").createOrReplaceTempView("nbflow_cells")
    return spark.sql("SELECT c.nb_id, s.kind, count(*) AS n FROM nbflow_cells c, LATERAL nbflow_statements(c.source) s GROUP BY ALL")


QUERIES["udtf_parse"] = _udtf



def _top(spark, d):
    from nbflow.operators import mining
    from nbflow.plans.mine import statements

    return mining.api_frequency(statements(spark, d)).orderBy(F.col("n").desc(), "api").limit(10)


QUERIES["topk_api"] = _top
