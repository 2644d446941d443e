"""Session and table access shared by every module of the engine."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: While a table is settled, Spark drops the shuffle files of that write at its end, on every machine.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_FOLDERS: set[str] = set()


def local_session(name: str = "nbflow", cores: str = "8") -> SparkSession:
    """A session for tests and benches; a driver that passes its own session never calls this."""
    spark = (
        SparkSession.builder.master(f"local[{cores}]")
        .appName(name)
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.execution.arrow.pyspark.enabled", "true")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; only Spark's reader touches the path, so any store it knows will do."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all machines share. Where the session names none, only a session on one machine gets one of its own."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir", "")
    if found:
        return found.rstrip("/")
    jsc = spark.sparkContext._jsc.sc()
    if not jsc.getCheckpointDir().isDefined():
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all machines share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="nbflow-"))
    return jsc.getCheckpointDir().get().rstrip("/")


def many_tasks(spark: SparkSession) -> int:
    """Number of tasks for steps that are long on few bytes: given to repartition, it keeps Spark from folding the
    tasks into one because their bytes are few."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)


def _path(spark: SparkSession, path: str):
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at, at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def work_dir(spark: SparkSession) -> str:
    """This application's folder for intermediate tables, which goes when the driver ends."""
    folder = f"{shared_dir(spark)}/nbflow-{spark.sparkContext.applicationId}"
    if folder not in _FOLDERS:
        at, files = _path(spark, folder)
        files.mkdirs(at)
        files.deleteOnExit(at)
        _FOLDERS.add(folder)
    return folder


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write a table in the shared folder and read it back: lineage ends there and a lost executor loses nothing."""
    spark = df.sparkSession
    path = f"{work_dir(spark)}/{name}-{uuid.uuid4().hex}"
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        spark.conf.set(_CLEANUP, before)
    settled = spark.read.schema(df.schema).parquet(path)
    settled.settled_at = path
    return settled


def kept(df: DataFrame, name: str) -> DataFrame:
    """A settled table of the miner or its corpus, which joins sort and merge. Spark goes by the size of its files, where
    equal texts and frames take a hundredth of their room: it would send tables of a gigabyte through the driver."""
    return settle(df, name).hint("merge")


def discard(*tables: DataFrame) -> None:
    """Delete settled tables that no plan will read again."""
    for table_ in tables:
        at, files = _path(table_.sparkSession, table_.settled_at)
        files.delete(at, True)
