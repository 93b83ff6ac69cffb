"""Cutting lineage in driver loops: tables in the folder that all executors share."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        at = f"file:///tmp/gridmatch-{spark.sparkContext.applicationId}"
        spark.sparkContext.setCheckpointDir(at)
    return at


def saved(df: DataFrame, rows_per_file: int = 0) -> DataFrame:
    """The table written and read again.  `rows_per_file` is for rows with long arrays: a reader holds
    some thousand rows of a file at once."""
    path = f"{shared_dir(df.sparkSession).rstrip('/')}/saved-{uuid.uuid4().hex}"
    df.write.option("maxRecordsPerFile", rows_per_file).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
