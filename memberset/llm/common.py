"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_fallback: str | None = None


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where the session does not name one, a local folder is made if driver and executors are one process; a cluster is refused.
    """
    global _fallback
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    _fallback = _fallback or tempfile.mkdtemp(prefix="memberset-")
    return f"file://{_fallback}"


def fresh_path(spark: SparkSession, label: str) -> str:
    return f"{_own_dir(spark)}/{label}-{uuid.uuid4().hex}"


def _own_dir(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/memberset/{spark.sparkContext.applicationId}"


def stage(df: DataFrame, label: str, codec: str = "zstd") -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back: cuts lineage, outlives executors."""
    path = fresh_path(df.sparkSession, label)
    df.write.option("compression", codec).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop_staged(spark: SparkSession) -> None:
    """Delete every table that this application staged in the shared folder; those of others stay."""
    path = spark._jvm.org.apache.hadoop.fs.Path(_own_dir(spark))
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def doc_text(df: DataFrame) -> DataFrame:
    """Only the id and the whole text of each document; a null text counts as empty."""
    return df.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))


def crc_bucket(column, n: int):
    """crc32 of the value as text, modulo n; null stays null."""
    return F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(n))


def columns_of(df: DataFrame) -> list:
    """All columns by name, whatever signs the names hold."""
    return [F.col("`" + c.replace("`", "``") + "`") for c in df.columns]


def free_name(df: DataFrame, wanted: str) -> str:
    """``wanted``, or it behind underscores, so that no column of df has the name."""
    taken = {c.lower() for c in df.columns}
    while wanted in taken:
        wanted = f"_{wanted}"
    return wanted


def _one_parquet_table(df: DataFrame) -> bool:
    """Is df a Parquet table as read, whose rows have a place in a file?"""
    plan = df._jdf.queryExecution().analyzed()
    if plan.getClass().getSimpleName() != "LogicalRelation" or "_metadata" in df.columns:
        return False
    if "row_index" not in df.select("_metadata").schema["_metadata"].dataType.names:
        return False
    return plan.relation().location().rootPaths().size() == 1


def keyed(df: DataFrame, column: str) -> DataFrame:
    """df with ``column``, a string that is one row's alone and the same whenever the table is read again.

    Rows straight from a Parquet table are named by their file and their place in it, so nothing is written. Any
    other DataFrame is staged with a running number. Null and repeated ids need no thought then.
    """
    if _one_parquet_table(df):
        place = F.concat_ws("-", F.md5(F.col("_metadata.file_path").cast("binary")), F.col("_metadata.row_index").cast("string"))
        return df.select("*", place.alias(column))
    return stage(df.withColumn(column, F.monotonically_increasing_id().cast("string")), "rows")
