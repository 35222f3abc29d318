"""Readers of the given tables and of long or packed series, and writers of results."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rankscan import schema


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A Parquet table, its columns pruned; timestamps without zone are taken as UTC."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """The folder shared by driver and executors: ``spark.checkpoint.dir``, else the checkpoint folder that the session
    has. Only a session on a single machine (``local[..]``, as in tests) may go without and takes a temporary one."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    context = spark.sparkContext._jsc.sc()
    if not found:
        if context.getCheckpointDir().isDefined():
            found = context.getCheckpointDir().get().rsplit("/", 1)[0]
        elif spark.sparkContext.master.startswith("local["):
            found = f"file://{tempfile.gettempdir()}/rankscan-shared"
        else:
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not context.getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def shared_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Materialises in the shared folder, so that the lineage ends there."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def read_series(spark: SparkSession, path: str, form: str = "parquet", **options) -> DataFrame:
    """A long series table from parquet, orc, csv or json with the canonical columns."""
    reader = spark.read.options(**options)
    if form in ("csv", "json"):
        reader = reader.schema(schema.SERIES_POINTS)
    return reader.format(form).load(path).selectExpr("cast(series_id as string) series_id", "cast(t as bigint) t", "cast(value as double) value")


def unpack(df: DataFrame, key: str, values: str) -> DataFrame:
    """A long series from one array per row."""
    return df.select(F.col(key).cast("string").alias("series_id"), F.posexplode(values).alias("pos", "v")).select("series_id", (F.col("pos") + 1).cast("bigint").alias("t"), F.col("v").cast("double").alias("value"))


def write_segments(segments: DataFrame, path: str) -> None:
    """Packed segments, partitioned by length: later searches read them without any shuffle."""
    segments.write.mode("overwrite").partitionBy("n").parquet(path)


def read_segments(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).select("series_id", "seg_id", "seg_start", "n", "t", "values")


def write_report(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").json(path)
