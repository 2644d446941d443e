"""Notebook files as a Spark data source, and corpus sinks.

``spark.dataSource.register(NotebookSource)`` and ``spark.read.format("ipynb").load(folder)`` give one row per
cell: path, cell_idx, kind, source, exec_order, lang. Files are dealt to tasks in groups; a task reads its files
only. ``read_notebooks`` is the same through Spark's binary reader, for stores that only Spark opens.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

CELLS = "path string, cell_idx int, kind string, source string, exec_order int, lang string"


def cells_of(path: str, text: str) -> Iterator[tuple]:
    """Rows of one notebook file; a file that isn't a notebook has none."""
    try:
        book = json.loads(text)
        language = book.get("metadata", {}).get("language_info", {}).get("version") or book.get("metadata", {}).get("kernelspec", {}).get("name", "")
        for i, cell in enumerate(book["cells"]):
            source = cell.get("source", "")
            yield path, i, cell.get("cell_type", "raw"), "".join(source) if isinstance(source, list) else source, cell.get("execution_count"), language
    except (ValueError, KeyError, TypeError, AttributeError):
        return


class _Group(InputPartition):
    def __init__(self, files: list[str]):
        self.files = files


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.groups = options["path"], int(options.get("groups", "64"))

    def partitions(self) -> list[InputPartition]:
        import glob

        files = sorted(glob.glob(f"{self.path}/**/*.ipynb", recursive=True))
        return [_Group(files[i :: self.groups]) for i in range(min(self.groups, max(len(files), 1)))]

    def read(self, partition: _Group) -> Iterator[tuple]:
        for name in partition.files:
            with open(name, encoding="utf-8", errors="replace") as file:
                yield from cells_of(name, file.read())


class NotebookSource(DataSource):
    """Options: path (a folder all machines see), groups (tasks at most)."""

    @classmethod
    def name(cls) -> str:
        return "ipynb"

    def schema(self) -> str:
        return CELLS

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def read_notebooks(spark: SparkSession, folder: str) -> DataFrame:
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.ipynb").option("recursiveFileLookup", "true").load(folder).select("path", "content")

    def run(batches):
        for pdf in batches:
            rows = [r for path, content in zip(pdf["path"], pdf["content"], strict=True) for r in cells_of(path, bytes(content).decode("utf-8", "replace"))]
            yield pd.DataFrame(rows, columns=["path", "cell_idx", "kind", "source", "exec_order", "lang"])

    return files.mapInPandas(run, CELLS)


def notebook_json(cells: DataFrame) -> DataFrame:
    """(nb_id, json): cells as notebook files, built by Spark's own JSON writer."""
    cell = F.struct(F.col("kind").alias("cell_type"), F.lit(None).cast("int").alias("execution_count"), F.array("source").alias("source"))
    body = cells.groupBy("nb_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("cell_idx", cell.alias("c")))), lambda x: x["c"]).alias("cells"))
    return body.select("nb_id", F.to_json(F.struct("cells", F.lit(4).alias("nbformat"))).alias("json"))


def write_examples(examples: DataFrame, path: str) -> None:
    """The corpus as Parquet by split: a reader of one split scans that split only."""
    examples.write.mode("overwrite").partitionBy("split").parquet(path)


def write_jsonl(examples: DataFrame, path: str) -> None:
    examples.write.mode("overwrite").json(path)


def register_sql(spark: SparkSession, tables: dict[str, DataFrame]) -> None:
    """Views of the engine's tables and its measures as SQL functions."""
    from nbflow.functions import metrics

    for name, rows in tables.items():
        rows.createOrReplaceTempView(name)
    spark.udf.register("code_bleu_parts", metrics.code_bleu_udf)
    spark.udf.register("ast_subtrees", metrics.subtrees_udf)
    spark.udf.register("code_tokens", metrics.tokens_udf)
