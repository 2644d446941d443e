"""Queries of sources, sinks and the SQL surface: what is written is what is read back."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from nbflow.plans.mine import FACTS
from nbflow.session import table, work_dir
from nbflow.sources import notebooks, render

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(build):
        QUERIES[name] = build
        if sql:
            ORACLES[name] = sql
        return build

    return keep


def _place(spark) -> str:
    return f"{work_dir(spark)}/store-{uuid.uuid4().hex}"


@query("src_csv_json_roundtrip", "SELECT o_orderkey, o_totalprice, o_orderstatus FROM orders UNION ALL SELECT o_orderkey, o_totalprice, o_orderstatus FROM orders")
def _text_formats(spark, d):
    rows, place = table(spark, d, "orders").select("o_orderkey", "o_totalprice", "o_orderstatus"), _place(spark)
    rows.write.csv(f"{place}/csv", header=True)
    rows.write.json(f"{place}/json")
    return spark.read.schema(rows.schema).csv(f"{place}/csv", header=True).unionByName(spark.read.schema(rows.schema).json(f"{place}/json").select(rows.columns))


@query("sink_partitioned", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_orderstatus = 'F' GROUP BY 1")
def _partitioned(spark, d):
    place = _place(spark)
    table(spark, d, "orders").write.partitionBy("o_orderstatus").parquet(place)
    return spark.read.parquet(place).filter("o_orderstatus = 'F'").groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@query("src_ipynb_roundtrip", f"WITH {FACTS} SELECT nb_id, count(*) AS cells FROM (SELECT DISTINCT nb_id, pos // 4294967296 AS cell FROM rows_ UNION SELECT nb_id, (base_turn * 20 + CASE WHEN odd IS NULL THEN 3 ELSE 6 + odd END) FROM placed WHERE role = 'assistant' AND template = 12) GROUP BY 1")
def _books(spark, d):
    """Code cells by notebook after writing notebooks as JSON text and reading their cells again."""
    place = _place(spark)
    notebooks.notebook_json(render.rendered_cells(spark, d)).write.parquet(place)
    books = spark.read.parquet(place)
    cell = "struct<cells: array<struct<cell_type: string, source: array<string>>>>"
    rows = books.select("nb_id", F.explode(F.from_json("json", cell)["cells"]).alias("c"))
    return rows.filter("c.cell_type = 'code'").groupBy("nb_id").agg(F.count("*").alias("cells"))


@query("sql_surface", f"WITH {FACTS} SELECT stage, count(*) AS n FROM rows_ WHERE stage <> 'other' GROUP BY 1")
def _sql(spark, d):
    from nbflow.plans.mine import staged

    notebooks.register_sql(spark, {"nbflow_staged": staged(spark, d)})
    return spark.sql("SELECT stage, count(*) AS n FROM nbflow_staged WHERE stage <> 'other' AND (var LIKE 'data%' OR var LIKE 'df%') GROUP BY stage")


@query("sink_parquet")
def _published(spark, d):
    """Examples written by split and read back: (split, n)."""
    from nbflow import experiments

    place = _place(spark)
    notebooks.write_examples(experiments.corpus(spark, d).examples, f"{place}/parquet")
    notebooks.write_jsonl(experiments.corpus(spark, d).examples, f"{place}/jsonl")
    lines = spark.read.text(f"{place}/jsonl").agg(F.count("*").alias("n")).select(F.lit("jsonl").alias("split"), "n")
    return spark.read.parquet(f"{place}/parquet").groupBy(F.col("split").cast("string").alias("split")).agg(F.count("*").alias("n")).unionByName(lines)
