"""Session helpers: durable intermediate tables and size checks."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Tables written by this process, removed when it ends.
_written: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share; a local one only where the session names none (tests)."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    known = spark.sparkContext.getCheckpointDir()
    if known:
        return known.rsplit("/", 1)[0]
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="saferoads-"))
    return spark.sparkContext.getCheckpointDir().rsplit("/", 1)[0]


def durable(df: DataFrame, onto: DataFrame | None = None) -> DataFrame:
    """Write df to the shared folder and read it back: cuts the lineage and survives lost executors. onto: a durable table of
    the same columns that the rows are added to."""
    spark = df.sparkSession
    path = onto._durable_path if onto is not None else f"{shared_dir(spark)}/saferoads-{uuid.uuid4().hex}"
    df.write.mode("append" if onto is not None else "error").parquet(path)
    if onto is None:
        _written.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._durable_path = path
    return out


def drop(*tables: DataFrame) -> None:
    """Delete durable tables that no later step reads; other frames are left alone."""
    for table in tables:
        path = getattr(table, "__dict__", {}).get("_durable_path")
        if path and (table.sparkSession, path) in _written:
            forget(table.sparkSession, path)
            _written.remove((table.sparkSession, path))


def forget(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def _folder(spark: SparkSession, path: str):
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target, target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def names_in(spark: SparkSession, path: str) -> list[str]:
    """Names of what lies in a folder of any file system that Spark reads; empty if there is none."""
    target, files = _folder(spark, path)
    return [x.getPath().getName() for x in files.listStatus(target)] if files.exists(target) else []


def exists(spark: SparkSession, path: str) -> bool:
    target, files = _folder(spark, path)
    return files.exists(target)


def mark(spark: SparkSession, path: str) -> None:
    """An empty file, made at once."""
    target, files = _folder(spark, path)
    files.create(target, True).close()


def bytes_of(spark: SparkSession, path: str) -> int:
    target, files = _folder(spark, path)
    return files.getContentSummary(target).getLength()


@atexit.register
def _clean() -> None:
    for spark, path in _written:
        try:
            forget(spark, path)
        except Exception:  # the session may be gone already
            return


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def small_enough(df: DataFrame, rows: int) -> bool:
    """True if df has at most `rows` rows. A count needs no rows to meet in one task, as a limit would."""
    return df.count() <= rows
