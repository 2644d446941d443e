"""Token counts as rollups that deltas keep up to date.

A rollup is a folder of committed batches. A batch holds signed changes, already summed to one row per
source, language and tokenizer version: a document that comes adds its counts, one that goes subtracts
them, and a revised count subtracts the old and adds the new. Totals are sums over batches, so batches may
come in any order. A batch is written once: its folder counts when Spark has marked it whole, and a batch
that comes again, after a failure or a restart, is left as it is. Compaction sums old batches into one; which
batches that holds is kept as ranges of numbers, so that a log of any age is a few rows.

A tokenizer version is the name of a vocabulary file, whose path is a parameter; documents are counted by its library
in Arrow batches, once for all versions asked for.

Defined cases: a null text has no tokens; null sources and languages are groups of their own; groups whose
documents have all gone are left out of the totals; rows that share a doc_id count each; an empty batch is
a batch; other columns are ignored and may have any name.
"""

from __future__ import annotations

import base64
from collections.abc import Callable
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nbflow.llm.common import small_batches, text_views
from nbflow.llm.slack_packing import SPLIT, byte_bpe

KEYS = ("source", "lang", "tokenizer")
SCHEMA = "source string, lang string, tokenizer string, n_docs long, n_tokens long"
#: Versions and their files; the part of the name before the last dot is the version.
VERSIONS = ("byte_bpe_50k.json", "byte_bpe_multi_50k.tiktoken")


def version(path: str) -> str:
    return path.rsplit("/", 1)[-1].rsplit(".", 1)[0]


@lru_cache(maxsize=4)
def counter(path: str) -> Callable[[str], int]:
    """How many tokens a text has under a vocabulary file: a ``tokenizers`` file, or byte ranks as ``tiktoken`` reads them."""
    if path.endswith(".json"):
        encoder = byte_bpe(path)
        return lambda text: len(encoder.ids(text))
    import tiktoken

    with open(path, "rb") as file:
        ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, file)}
    plain = tiktoken.Encoding(version(path), pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={})

    def count(text: str) -> int:
        try:
            return len(plain.encode_ordinary(text))
        except BaseException as error:  # the library gives up on very long runs, with an error of a class of its own
            if isinstance(error, (KeyboardInterrupt, SystemExit, MemoryError)):
                raise
            return len(plain._encode_only_native_bpe(text))  # the same, with the text split by Python

    return count


def counted(docs: DataFrame, paths: dict[str, str]) -> DataFrame:
    """Rows (doc_id, source, lang, one column per version): the number of tokens; ``paths``: versions and their files."""
    small_batches(docs.sparkSession)
    names = list(paths)
    fields = [("doc_id", pa.int64()), ("source", pa.string()), ("lang", pa.string()), *((n, pa.int64()) for n in names)]
    schema = pa.schema(fields)

    def run(batches):
        count = [counter(paths[n]) for n in names]
        for batch in batches:
            data, offsets = text_views(batch.column(3))
            body, at = data.tobytes(), offsets.tolist()
            texts = [body[a:b].decode("utf-8", "replace") for a, b in zip(at[:-1], at[1:], strict=True)]
            columns = [batch.column(i).cast(schema.field(i).type) for i in range(3)]
            yield pa.RecordBatch.from_arrays([*columns, *(pa.array([c(t) for t in texts], pa.int64()) for c in count)], schema=schema)

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), F.col("lang").cast("string").alias("lang"), "text")
    return rows.mapInArrow(run, ", ".join(["doc_id long", "source string", "lang string", *(f"`{n}` long" for n in names)]))


def estimate(text: str = "text") -> Column:
    """A count before any tokenizer has run: one token per four bytes, or part of them."""
    return F.coalesce(F.ceil(F.octet_length(text) / 4), F.lit(0)).cast("long")


def changes(docs: DataFrame, tokenizer: str, tokens: Column, sign: int = 1) -> DataFrame:
    """Signed rows of documents that come (1) or go (-1), with their ``tokens``."""
    return docs.select("source", "lang", F.lit(tokenizer).alias("tokenizer"), F.lit(sign).cast("long").alias("n_docs"), (tokens * sign).cast("long").alias("n_tokens"))


def revisions(docs: DataFrame, tokenizer: str, old: Column, new: Column) -> DataFrame:
    """Signed rows of documents whose count is corrected from ``old`` to ``new``."""
    return docs.select("source", "lang", F.lit(tokenizer).alias("tokenizer"), F.lit(0).cast("long").alias("n_docs"), (new - old).cast("long").alias("n_tokens"))


class TokenRollup:
    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        jvm = spark.sparkContext._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _whole(self, folder: str) -> bool:
        return self._fs.exists(self._path(f"{folder}/_SUCCESS"))

    def commit(self, batch: int, rows: DataFrame) -> bool:
        """Add a batch of signed rows; False if it is there already. Fit for foreachBatch of a stream."""
        folder = f"{self.path}/batch={int(batch)}"
        if self._whole(folder) or int(batch) not in self.loose([int(batch)]):
            return False
        summed = rows.groupBy(*KEYS).agg(F.sum("n_docs").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))
        summed.write.mode("overwrite").parquet(folder)
        return True

    def _folders(self) -> list[str]:
        if not self._fs.exists(self._path(self.path)):
            return []
        found = [s.getPath().toString() for s in self._fs.listStatus(self._path(self.path)) if s.isDirectory()]
        return sorted(f for f in found if self._whole(f))

    def _bases(self) -> list[str]:
        """Finished bases, oldest first. The list of a base's batches is written before the base itself."""
        found = [f for f in self._folders() if "/base=" in f and not f.endswith("-batches")]
        return sorted(found, key=lambda f: int(f.rsplit("=", 1)[1]))

    def _ranges(self) -> DataFrame | None:
        """Ranges (low, high) of the numbers of the batches that the newest base holds."""
        bases = self._bases()
        return self.spark.read.schema("low long, high long").parquet(f"{bases[-1]}-batches") if bases else None

    def loose(self, numbers: list[int]) -> set[int]:
        """Which of the batches ``numbers`` the newest base doesn't hold."""
        ranges = self._ranges()
        if ranges is None or not numbers:
            return set(numbers)
        asked = self.spark.createDataFrame([(n,) for n in numbers], "n long")
        held = asked.join(ranges, F.col("n").between(F.col("low"), F.col("high")), "left_semi")
        return set(numbers) - {r["n"] for r in held.collect()}

    def live(self) -> list[str]:
        """The folders whose sums are the totals: the newest base and the batches that it doesn't hold."""
        batches = {int(f.rsplit("=", 1)[1]): f for f in self._folders() if "/batch=" in f}
        return self._bases()[-1:] + [batches[n] for n in sorted(self.loose(list(batches)))]

    def totals(self) -> DataFrame:
        """One row per source, language and tokenizer version that still has documents or tokens."""
        folders = self.live()
        if not folders:
            return self.spark.createDataFrame([], SCHEMA)
        rows = self.spark.read.schema(SCHEMA).parquet(*folders)
        summed = rows.groupBy(*KEYS).agg(F.sum("n_docs").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))
        return summed.filter("n_docs <> 0 or n_tokens <> 0")

    def compact(self) -> None:
        """Sum all batches into a new base. Old folders stay until ``clean``, so readers are not disturbed."""
        numbers = self.spark.createDataFrame([(int(f.rsplit("=", 1)[1]),) * 2 for f in self.live() if "/batch=" in f], "low long, high long")
        known = self._ranges()
        known = numbers if known is None else numbers.unionByName(known)
        order = Window.partitionBy(F.lit(0)).orderBy("low")  # as many rows as there are batches since the last base, and gaps
        run = known.withColumn("new", F.when(F.col("low") > F.max("high").over(order.rowsBetween(Window.unboundedPreceding, -1)) + 1, 1).otherwise(0))
        ranges = run.withColumn("run", F.sum("new").over(order)).groupBy("run").agg(F.min("low").alias("low"), F.max("high").alias("high"))
        nth = 1 + max((int(b.rsplit("=", 1)[1]) for b in self._bases()), default=0)
        ranges.select("low", "high").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/base={nth}-batches")
        self.totals().coalesce(1).write.mode("overwrite").parquet(f"{self.path}/base={nth}")

    def clean(self) -> None:
        """Delete folders that the newest base has made idle."""
        live = set(self.live())
        keep = {f"{f}-batches" for f in live if "/base=" in f}
        for folder in self._folders():
            if folder not in live and folder not in keep:
                self._fs.delete(self._path(folder), True)
