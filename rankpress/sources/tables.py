"""Readers with fixed schemas, and the folders that all machines share."""

from __future__ import annotations

import gc
import tempfile

from pyspark.sql import DataFrame, SparkSession, types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; Parquet brings its schema, so no inference over the data."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_books(spark: SparkSession, path: str) -> DataFrame:
    """Plain text files, one row each: path, text."""
    return spark.read.text(path, wholetext=True).selectExpr("_metadata.file_path as path", "value as text")


def records(spark: SparkSession, path: str, fmt: str, schema: T.StructType | str) -> DataFrame:
    """csv (with a header), json (lines), orc or parquet under a given schema."""
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def binary(spark: SparkSession, path: str) -> DataFrame:
    """Opaque files, one row each: path, length, content. A row holds at most 2 GB; larger files are to be cut upstream."""
    return spark.read.format("binaryFile").load(path).select("path", "length", "content")


def stream(spark: SparkSession, path: str, schema: T.StructType | str, files: int = 1) -> DataFrame:
    """Parquet files of a folder as a stream, `files` to a micro-batch."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def shared_folder(spark: SparkSession) -> str:
    """The folder that all machines share, from spark.checkpoint.dir. Where the session names none, a new local one on a local
    master, as in tests; on a cluster executors could not read such a folder, so that is an error."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir has to name a folder that all machines share")
    return named or tempfile.mkdtemp(prefix="shared")


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint in the shared folder that the session names."""
    spark = df.sparkSession
    sc = spark.sparkContext
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(shared_folder(spark))
    return df.checkpoint(eager=True)


def swept(df: DataFrame) -> DataFrame:
    """df, once Spark may drop from disk what was shuffled on the way to it and nothing refers to any more."""
    gc.collect()
    df.sparkSession.sparkContext._jvm.System.gc()
    return df
