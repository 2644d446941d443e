"""A deterministic corpus of notebooks rendered from the given conversations and documents.

No given table holds code, so each assistant turn becomes one small analysis from a template chosen by
arithmetic on its key, user and system turns become markdown, and the document of the same number gives
repository, licence and content digest. Everything is built in the JVM from a small broadcast table, so
any engine that knows the arithmetic can repeat it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nbflow.session import table
from nbflow.sources import templates as t

#: Cells of a turn have numbers from turn times this; a turn's analysis has fewer than half as many.
STEP = 20


def template_cells(spark: SparkSession) -> DataFrame:
    return F.broadcast(spark.createDataFrame(t.cells(), "template int, j int, code string"))


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows (nb_id, turn, role, text, template, var, base_turn, odd): assistant turns of notebooks with odd numbers
    go in pairs whose cells alternate; there, each has a variable of its own."""
    rows = table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("nb_id"), "turn", "role", "text")
    order = Window.partitionBy("nb_id", "role").orderBy("turn")
    rows = rows.withColumn("nth", F.row_number().over(order) - 1)
    pair = F.col("nth") - F.pmod("nth", F.lit(2))
    first = F.min("turn").over(Window.partitionBy("nb_id", "role", pair))
    tangled = (F.col("role") == "assistant") & (F.pmod("nb_id", F.lit(2)) == 1)
    template = F.pmod(F.col("nb_id") * 31 + F.col("turn") * 7, F.lit(16)).cast("int")
    rows = rows.withColumn("template", F.when(F.col("role") == "assistant", template))
    return rows.select(
        "nb_id",
        "turn",
        "role",
        "text",
        "template",
        F.when(F.pmod("template", F.lit(2)) == 0, F.concat(F.lit("df"), F.col("turn").cast("string"))).when(tangled, F.concat(F.lit("data"), F.col("turn").cast("string"))).otherwise(F.lit("data")).alias("var"),
        F.when(tangled, first).otherwise(F.col("turn")).alias("base_turn"),
        F.when(tangled, F.pmod("nth", F.lit(2)).cast("int")).alias("odd"),
    )


def rendered_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows (nb_id, cell_idx, kind, source)."""
    rows = turns(spark, sf_dir)
    place = F.col("base_turn") * STEP
    text = rows.filter("role <> 'assistant'").select("nb_id", place.cast("int").alias("cell_idx"), F.lit("markdown").alias("kind"), F.when(F.pmod(F.col("nb_id") + F.col("turn"), F.lit(13)) == 0, F.lit(" ")).otherwise(F.col("text")).alias("source"))
    code = rows.filter("role = 'assistant'").join(template_cells(spark), "template")
    nth = F.when(F.col("odd").isNull(), F.col("j")).otherwise(F.col("j") * 2 + F.col("odd"))
    file_no = F.pmod("nb_id", F.lit(t.SLICES)).cast("string")
    source = F.replace(F.replace("code", F.lit("<v>"), F.col("var")), F.lit("<k>"), file_no)
    return text.unionByName(code.select("nb_id", (place + nth).cast("int").alias("cell_idx"), F.lit("code").alias("kind"), source.alias("source")))


def notebook_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows (nb_id, repo, path, license, lang_major, content_md5): what a crawl knows about a notebook."""
    ids = table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("nb_id")).distinct()
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("nb_id"), F.col("source").alias("repo"), license_of("text").alias("license"), F.md5("text").alias("content_md5"))
    suffix = F.when(F.pmod("nb_id", F.lit(23)) == 0, F.lit(".py")).otherwise(F.lit(".ipynb"))
    return ids.join(docs, "nb_id", "left").select("nb_id", "repo", F.concat(F.lit("nb/"), F.col("nb_id").cast("string"), suffix).alias("path"), "license", F.when(F.pmod("nb_id", F.lit(17)) == 0, 2).otherwise(3).alias("lang_major"), "content_md5")


#: Licence lines of the given documents (fixed values), in the order in which they are looked for.
LICENSES = (("Apache-2.0", "Apache License, Version 2.0"), ("MIT", "MIT License"), ("GPL-3", "GNU General Public License, version 3"), ("CC-BY-NC", "CC BY-NC 4.0"))


def license_of(column: str):
    found = F.lit("none")
    for name, pattern in reversed(LICENSES):
        found = F.when(F.col(column).rlike(pattern), name).otherwise(found)
    return found


def data_files(spark: SparkSession, sf_dir: str, most_rows: int | None = t.SLICE_ROWS) -> DataFrame:
    """Rows (name, csv): the files that notebooks load, each a slice of a given table of at most ``most_rows`` rows
    (None: all), as files that one process reads are of bounded size."""
    out = None
    for name, key in t.KEYS.items():
        rows = table(spark, sf_dir, name)
        columns = rows.columns
        nth = F.row_number().over(Window.partitionBy("__k").orderBy(key, *[c for c in columns if c != key]))
        picked = rows.withColumn("__k", F.pmod(F.col(key), F.lit(t.SLICES))).withColumn("__n", nth)
        picked = picked if most_rows is None else picked.filter(F.col("__n") <= most_rows)
        picked = picked.withColumn("__row", F.to_csv(F.struct(*columns), {"escape": '"'}))
        one = picked.groupBy("__k").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("__n", "__row"))), lambda x: x["__row"]), "\n").alias("body"))
        one = one.select(F.concat(F.lit(f"{name}_"), F.col("__k").cast("string"), F.lit(".csv")).alias("name"), F.concat(F.lit(",".join(columns) + "\n"), "body").alias("csv"))
        out = one if out is None else out.unionByName(one)
    return out


def repo_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows (repo, name): the paths of the data files in each repository of the stand-in crawl."""
    repos = notebook_facts(spark, sf_dir).select(F.coalesce("repo", F.lit("none")).alias("repo")).distinct()
    names = F.array(*[F.lit(f"data/raw/{name}_{k}.csv") for name in t.KEYS for k in range(t.SLICES)])
    return repos.withColumn("name", F.explode(names))
